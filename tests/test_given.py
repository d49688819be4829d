"""Queries whose jobs were moved onto given tables."""

from __future__ import annotations

import re

import pytest

from coloc import catalog
from tests.conftest import DATA
from tests.test_oracles import con, same  # noqa: F401


def test_wind_quadrants_read_events(spark):
    got = catalog.queries()["wind_quadrants"](spark, DATA)
    assert any(f.endswith("events.parquet") for f in got.inputFiles())
    rows = got.collect()
    assert sum(r["n"] for r in rows) == spark.read.parquet(f"{DATA}/events.parquet").count()
    assert all(abs(r["by_atan2"] - r["t"]) < 1e-3 and abs(r["by_quadrant"] - r["t"]) < 1e-3 for r in rows)


#: Queries that made their rows up before.
MOVED = [
    "synth_source",
    "wkt_parse",
    "synth_distance",
    "proximity_counts",
    "p_value_table",
    "p_error",
    "grid_points",
    "grid_geodesic",
    "clique_vs_overlap",
    "candidate_counts",
]


@pytest.mark.parametrize("name", MOVED)
def test_moved_equals_twin(spark, con, name):
    assert same(catalog.queries()[name](spark, DATA).toPandas(), con.execute(catalog.oracles()[name]).fetchdf())
    assert re.search(r"\b(part|events|supplier)\b", catalog.oracles()[name])


def test_lineitem_meets_small_tables_without_a_shuffle(spark, monkeypatch):
    from coloc.sources import given
    from tests.conftest import DATA

    shown = lambda df: sorted(tuple(r) for r in df.collect())
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        sent, few = given.yearly_amounts(spark, DATA), given.cases_linked(spark, DATA)
        assert "BroadcastHashJoin [l_partkey" in plan(sent) and "BroadcastHashJoin [l_orderkey" in plan(few)
        monkeypatch.setattr(given, "SMALL", 0)
        met, many = given.yearly_amounts(spark, DATA), given.cases_linked(spark, DATA)
        assert "SortMergeJoin [l_partkey" in plan(met) and "SortMergeJoin [l_orderkey" in plan(many)
        assert shown(sent) == shown(met) and shown(few) == shown(many)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
