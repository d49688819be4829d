"""Sums by tiles against those of the plans that make a row for each point and set."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from coloc.functions import decay as decays
from coloc.operators import buffers, dense, grids, prevalence, transactions

GRID = grids.Grid(1.0, (0.0, 0.0, 150.0, 90.0))
BITS = 4


def _objects(spark):
    rng = random.Random(3)
    rows = [(s, rng.randint(1, 6), rng.uniform(-3, 153), rng.uniform(-3, 93), rng.uniform(0.5, 9), rng.choice([0.0, rng.uniform(0, 8)]), rng.uniform(0, 360)) for s in (1, 2) for _ in range(60)]
    df = spark.createDataFrame(rows, "sim_id int, feature int, x double, y double, r double, speed double, bearing double")
    return buffers.ellipse(df)


@pytest.mark.parametrize("decay,mode", [("cosine", "uncertain"), ("linear", "uncertain"), ("steps", "uncertain"), ("boolean", "uncertain"), ("cosine", "certain")])
def test_tiles_equal_rows(spark, decay, mode):
    objects, fn = _objects(spark), decays.NAMED[decay]()
    assert dense.fits(objects, GRID, fn, mode, "cells", "max")
    wide = transactions.to_wide(transactions.build(objects, GRID, fn, mode), 6)
    shown = lambda df, *c: sorted(tuple(r) for r in df.select("sim_id", "key", "size", *[F.round(x, 6).alias(x) for x in c]).collect())
    both = ("sup", "sup_lhs", "exp_sup", "exp_sup_lhs", "conf", "exp_conf")
    want = shown(prevalence.confidences(wide, 6, 3, BITS), *both)
    assert len(want) > 20
    assert shown(prevalence.rules_of(dense.tiles(objects, GRID, fn, mode, "ray", 6, 3, BITS)), *both) == want
    live = spark.createDataFrame([r[1:3] for r in want[::3]], "key long, size int").distinct()
    keys = {r["key"] for r in live.collect()}
    assert shown(prevalence.rules_of(dense.tiles(objects, GRID, fn, mode, "ray", 6, 3, BITS, live)), *both) == [w for w in want if w[1] in keys]
    plain = prevalence.supports(transactions.to_wide(transactions.build(objects, GRID, fn, mode)), 3, BITS)
    assert shown(prevalence.sets_of(dense.tiles(objects, GRID, fn, mode, "ray", None, 3, BITS)), "sup", "exp_sup") == shown(plain, "sup", "exp_sup")


def test_nearest_stations_equal_brute_force(spark):
    import numpy as np

    from coloc.operators import winds

    rng = np.random.default_rng(2)
    x, y = rng.uniform(0, 50, 300), np.r_[rng.uniform(0, 50, 150), rng.normal(20, 0.1, 150)]
    x[10], y[10] = x[11], y[11]  # a tie
    places = winds.Places(np.arange(300)[::-1], x, y)
    at = np.column_stack([rng.uniform(-60, 120, 400), rng.uniform(-60, 120, 400)])
    at[0] = x[10], y[10]
    for k in (1, 2, 300, 400):
        got = places.nearest(at[:, 0], at[:, 1], k)
        for p, row in zip(at, got):
            d = np.hypot(p[0] - x, p[1] - y)
            assert row.tolist() == sorted(range(300), key=lambda s: (d[s], 299 - s))[:k]
    objects = spark.createDataFrame([("a", 1.0, 1.0)], "object_id string, x double, y double")
    none = spark.createDataFrame([], "station_id long, x double, y double, speed double, bearing double")
    assert winds.interpolate(objects, none, "nearest").count() == 0
    plan = winds.interpolate(objects, spark.createDataFrame([(1, 0.0, 0.0, 1.0, 90.0)], none.schema), "nearest")._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_participation_by_squares_equals_cliques(spark):
    from coloc.operators import baselines

    rng = random.Random(8)
    rows = [(s, f"o{i}", rng.choice("ABCDE"), rng.uniform(-20, 20), rng.uniform(-20, 20)) for s in (1, 2) for i in range(250)] + [(1, "edge", "A", 12.0, 0.0), (1, "edge2", "B", 15.0, 0.0)]
    objects = spark.createDataFrame(rows, "sim_id int, object_id string, feature string, x double, y double")
    for d in (2, 3):
        shown = lambda one_row: sorted(tuple(r) for r in baselines.participation(objects, 3.0, d=d, one_row=one_row).collect())  # noqa: E731, B023
        assert shown(True) == shown(False) and any(r[2] == d for r in shown(True))
    plan = baselines.participation(objects, 3.0, d=3, one_row=True)._jdf.queryExecution().executedPlan().toString()
    assert "members" not in plan


@pytest.mark.parametrize("name,mode", [("cosine", "uncertain"), ("linear", "uncertain"), ("cosine", "certain")])
def test_circles_by_columns_equal_tiles(name, mode):
    import numpy as np

    rng = np.random.default_rng(5)
    n, grid = 3000, grids.Grid(1.0, (0.0, 0.0, 300.0, 90.0))
    code = rng.integers(1, 7, n)
    x, y, r = rng.uniform(-9, 309, n), rng.uniform(-9, 99, n), rng.choice([0.3, 1.0, 2.5, 6.0], n)
    x[:50], y[:50], x[50] = np.round(x[:50]), np.round(y[:50]), np.nan
    fn = decays.of_arrays(decays.NAMED[name]()) if mode == "uncertain" else None
    on = ~np.isnan(x)
    rows = {"x": x[on], "y": y[on], "r": r[on], **{c: np.full(n - 1, np.nan) for c in dense.ELLIPSE}}
    low_i, high_i, low_j, high_j = grid.bounds
    for effect in (6, None):
        got = dense.of_simulation(1, code, x, y, r, grid, fn, "radius", effect, 3, BITS, None).to_pandas().set_index("key")
        both = np.zeros(len(got))
        sup = np.zeros(len(got))
        for box in [(i, min(high_i, i + 63), j, min(high_j, j + 63)) for i in range(low_i, high_i + 1, 64) for j in range(low_j, high_j + 1, 64)]:
            parts = dense.raster(rows, code[on] - 1, 6, box, grid, fn, "radius")
            assert (parts == dense.of_shares(dense.nearest_shares(code[on] - 1, x[on], y[on], r[on], 6, box, grid), fn)).all()
            p = {c: np.maximum(parts[c - 1], 0) / dense.PARTS for c in range(1, 7)}
            there = {c: parts[c - 1] >= 0 for c in range(1, 7)}
            for k, key in enumerate(got.index):
                items = [c for c in ((key >> BITS * (2 - m)) & 15 for m in range(3)) if c] + ([effect] if effect else [])
                q = p[items[0]]
                for c in items[1:]:
                    q = q * p[c]
                both[k] += np.floor(q * dense.PARTS + 0.5).sum()
                sup[k] += np.logical_and.reduce([there[c] for c in items]).sum()
        assert len(got) >= 25 and (got["sup"] == sup).all() and (got["bh"] * dense.HALF + got["bl"] == both).all()
