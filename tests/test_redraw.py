"""Simulations that tasks draw by themselves against those that are made as rows."""

from __future__ import annotations

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from coloc.catalog import methods as m
from coloc.operators import buffers, redraw
from coloc.plans import miner
from tests.conftest import DATA

FEW = replace(m.RULES, sims=2, step=2.0, d=2)


def _sums(run, first, last):
    alive = run.observed
    drawn = run._drawn_again(alive, run.codes.features(alive), alive.count(), first, last)
    rows = run.codes.encoded(run.randomiser(first, last))
    keys = alive.select("key")
    want = miner.measured(rows, run.grid, run.cfg, miner._Plain(run.codes)).join(keys, "key", "left_semi")
    shown = lambda df: sorted(tuple(r) for r in df.select("sim_id", "key", "size", "sup", F.round("exp_sup", 9)).collect())
    return shown(drawn), shown(want)


@pytest.mark.parametrize("how", ["both", "causes", "effects", "uniform"])
def test_rules_drawn_by_tasks_equal_rows(spark, how):
    cfg = replace(FEW, randomise=how)
    buffered, randomiser = m.world(spark, DATA, cfg)
    run = miner._Run(buffered, randomiser, cfg, None, None)
    got, want = _sums(run, 3, 4)
    assert got == want and len({r[0] for r in got}) == 2


def test_patterns_drawn_by_tasks_equal_rows(spark, monkeypatch):
    pts, box = m.given.event_points(spark, DATA), (0.0, 0.0, 100.0, 100.0)
    draws = miner.uniform_randomiser(pts, box, lambda rows: buffers.fixed(rows, 1.0))
    cfg = m.pattern_cfg(sims=2)
    run = miner._Run(buffers.fixed(pts, 1.0), draws, cfg, None, None)
    got, want = _sums(run, 1, 2)
    assert got == want and got
    monkeypatch.setattr(redraw, "MOST", 10)  # more objects than that are rows as before
    assert draws.groups({}) is None


def test_digests_in_arrays_equal_the_library():
    import hashlib

    import numpy as np
    import pyarrow as pa

    texts = [b"", b"a", "é".encode() * 20, *[b"x" * n for n in (47, 48, 51, 52, 55, 56, 64, 200)], *[b"%d" % n for n in range(redraw.FEW + 5)]]
    for some in (texts, texts[11:], texts[:1], []):
        keys = pa.array(some, pa.large_binary())
        want = np.frombuffer(b"".join(hashlib.md5(b"s1:" + k).digest() for k in some), ">u8").reshape(-1, 2)
        assert (redraw._digests("s1:", keys) == want).all() and (redraw.draws("s1:", keys) == (want[:, 0] >> np.uint64(32)) / 4294967296.0).all()
        assert (redraw._digests("s1:", keys.slice(1)) == want[1:]).all()


def test_digests_are_not_made_one_by_one(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(redraw, "md5", None)
    assert redraw.draws("p1:", pa.array([b"%d" % n for n in range(100)], pa.large_binary())).max() < 1
