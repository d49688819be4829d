"""A share of the registered queries against their SQL twins, on the smallest tables."""

from __future__ import annotations

import math

import duckdb
import pytest

from coloc import catalog
from tests.conftest import DATA

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["emissions", "buffer_ellipse", "tx_uncertain_long", "exp_sup_patterns", "exp_conf_rules", "rand_population", "mine_rules_um", "baseline_participation", "candidates_given", "line_buffer", "synth_source", "stream_running_supports", "wind_idw", "polygon_buffer", "support_cube", "stream_session"]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return c


def _plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    return round(float(v), 6) if isinstance(v, float) else v


def same(left, right) -> bool:
    cols = sorted(left.columns)
    rows = lambda df: sorted((str([_plain(x) for x in r]) for r in df[cols].astype(object).itertuples(index=False)))
    return cols == sorted(right.columns) and len(left) == len(right) and rows(left) == rows(right)


@pytest.mark.parametrize("name", SOME)
def test_twin(spark, con, name):
    got = catalog.queries()[name](spark, DATA).toPandas()
    want = con.execute(catalog.oracles()[name]).fetchdf()
    assert same(got, want)


def test_every_oracle_has_a_query():
    assert catalog.oracles().keys() <= catalog.queries().keys()
    assert len(catalog.queries()) > 170
