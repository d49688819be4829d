"""Splines through more stations than one dense system takes."""

from __future__ import annotations

import numpy as np

from coloc.operators import plates, winds


def test_iterated_spline_equals_dense():
    rng = np.random.default_rng(4)
    at = np.concatenate([rng.uniform(0, 1, (900, 2)), rng.normal(0.3, 0.02, (300, 2))])
    at = (at - at.min(0)) / np.ptp(at, axis=0)
    values = rng.normal(0, 20, (len(at), 2))
    where = rng.uniform(-0.1, 1.1, (200, 2))
    basis = lambda p: np.column_stack([plates.kernel(((p[:, None] - at[None]) ** 2).sum(-1)), np.ones(len(p)), p])
    side = np.column_stack([np.ones(len(at)), at]).T
    system = np.vstack([basis(at), np.column_stack([side, np.zeros((3, 3))])])
    want = basis(where) @ np.linalg.solve(system, np.concatenate([values, np.zeros((3, 2))]))
    places = winds.Places(np.arange(len(at)), at[:, 0], at[:, 1])
    w, plane = plates.solved(at, values, lambda p, k: places.nearest(p[:, 0], p[:, 1], k))
    got = plates.Plate(at).load(w).at(where) + np.column_stack([np.ones(len(where)), where]) @ plane
    assert np.abs(got - want).max() < 1e-4 * np.abs(want).max()


def test_spline_takes_more_than_4000_stations(spark):
    rng = np.random.default_rng(5)
    rows = [(k, float(x), float(y), float(u), float(v)) for k, (x, y, u, v) in enumerate(rng.uniform(0, 50, (4100, 4)))]
    stations = spark.createDataFrame(rows, "station_id long, x double, y double, u double, v double")
    objects = stations.where("station_id % 100 = 0").selectExpr("cast(station_id as string) as object_id", "x", "y")
    got = {r["object_id"]: (r["u"], r["v"]) for r in winds.spline(objects, stations).collect()}
    assert len(got) == 41
    assert all(abs(a - b) < 1e-4 for k, x, y, *uv in rows if k % 100 == 0 for a, b in zip(got[str(k)], uv))


def test_sums_of_crowded_places_take_work_in_proportion(monkeypatch):
    rng = np.random.default_rng(6)
    at = np.concatenate([rng.uniform(0, 1, (6000, 2)), rng.normal(0.4, 1e-4, (6000, 2))])
    w = rng.normal(0, 1, (len(at), 2))
    where = np.concatenate([at, rng.uniform(-1, 2, (500, 2)), rng.normal(0.4, 0.01, (500, 2))])
    made, kernel = [], plates.kernel
    monkeypatch.setattr(plates, "kernel", lambda d2: made.append(d2.size) or kernel(d2))
    got = plates.Plate(at).load(w).at(where)
    assert sum(made) < 1500 * len(where)
    some = np.r_[0 : len(at) : 60, len(at) : len(where)]
    want = np.concatenate([kernel(((p[:, None] - at[None]) ** 2).sum(-1)) @ w for p in np.array_split(where[some], 40)])
    assert np.abs(got[some] - want).max() < 1e-8 * np.abs(want).max()


def test_calm_stations():
    at = np.random.default_rng(7).uniform(0, 200, (4100, 2))
    assert not winds._spline_of(at, np.zeros((4100, 2)))(at[:50] + 0.5).any()


def test_crowded_stations_of_a_smooth_wind():
    rng = np.random.default_rng(8)
    at = np.concatenate([rng.uniform(0, 200, (2200, 2)), rng.normal(80, 0.05, (2200, 2))])
    values = np.column_stack([20 * np.sin(at[:, 0] / 30) + at[:, 1] / 9, 9 * np.cos(at[:, 1] / 20)])
    assert np.abs(winds._spline_of(at, values)(at) - values).max() < 1e-4
