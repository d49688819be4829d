"""Definitions by hand, published counts, and properties of the methods."""

from __future__ import annotations

import math
from itertools import combinations

import pytest
from hypothesis import given as examples
from hypothesis import settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from coloc.functions import angles
from coloc.functions import decay as decays
from coloc.functions.tests_of_chance import most_exceedances
from coloc.operators import baselines, buffers, candidates, grids, itemsets, measures, prevalence, randomize, transactions, winds
from coloc.plans import miner
from coloc.plans.config import MinerConfig
from coloc.sources import synthetic

HAND = [("t1", "A", 1.0), ("t1", "B", 0.5), ("t2", "A", 0.5), ("t2", "B", 0.5), ("t2", "D", 0.4), ("t3", "B", 1.0), ("t3", "D", 1.0), ("t4", "A", 0.25)]
GRID = grids.Grid(0.5, (0.0, 0.0, 20.0, 20.0))


@pytest.fixture(scope="module")
def hand(spark):
    return transactions.to_wide(transactions.from_table(spark.createDataFrame(HAND, "tx_id string, item string, p double")))


@pytest.fixture(scope="module")
def objects(spark):
    rows = [(f"o{i}", "ABC"[i % 3], float((i * 7) % 19), float((i * 11) % 17)) for i in range(40)]
    return spark.createDataFrame(rows, "object_id string, feature string, x double, y double")


def test_expected_support_by_hand(hand):
    got = {r["key"]: (float(r["exp_sup"]), r["sup"]) for r in prevalence.supports(hand, 3).collect()}
    want = {"A": (1.75, 3), "B": (2.0, 3), "D": (1.4, 2), "A+B": (0.75, 2), "A+D": (0.2, 1), "B+D": (1.2, 2), "A+B+D": (0.1, 1)}
    assert {k: (round(v[0], 9), v[1]) for k, v in got.items()} == want


def test_expected_confidence_by_hand(hand):
    got = {r["key"]: r for r in prevalence.confidences(hand, "D", 2).collect()}
    assert got["A"]["exp_conf"] == pytest.approx(0.2 / 1.75)
    assert got["B"]["exp_conf"] == pytest.approx(0.6)
    assert got["A+B"]["exp_conf"] == pytest.approx(0.1 / 0.75)
    assert got["A+B"]["conf"] == pytest.approx(0.5)


def test_decisions():
    assert most_exceedances(0.05, 99) == 4
    assert most_exceedances(0.05, 19) == 0
    assert most_exceedances(0.05, 99, strict=True) == 3
    assert most_exceedances(0.05, 9) == -1


@pytest.mark.parametrize(("n", "count"), [(47, 17343), (26, 2951)])
def test_candidate_counts(spark, n, count):
    features = spark.range(n).select(F.format_string("f%02d", "id").alias("feature"))
    assert candidates.enumerate_patterns(features, 3).count() == count


def _brute(objects, r: float, fn) -> dict:
    out: dict = {}
    for o in objects.collect():
        for i in range(41):
            for j in range(41):
                d = math.hypot(i * 0.5 - o["x"], j * 0.5 - o["y"])
                if d <= r + 1e-12:
                    key = (i, j, o["feature"])
                    out[key] = max(out.get(key, 0.0), fn(d / r))
    return out


def _long(tx) -> dict:
    return {(r["gi"], r["gj"], r["feature"]): float(r["p"]) for r in tx.collect()}


def test_transactions_equal_brute_force(objects):
    want = _brute(objects, 2.0, lambda s: math.cos(math.pi * s) / 2 + 0.5)
    b = buffers.fixed(objects, 2.0)
    for strategy in ("cells", "tiled", "cross"):
        got = _long(transactions.build(b, GRID, strategy=strategy, tile=8))
        assert got.keys() == want.keys()
        assert all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_tiled_plan_has_one_exchange_before_supports(objects):
    tx = transactions.build(buffers.fixed(objects, 2.0), GRID, strategy="tiled", tile=8)
    plan = prevalence.supports(transactions.to_wide(tx), 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 2  # tiles, and keys


def test_certain_equals_uncertain_with_boolean_decay(objects):
    b = buffers.fixed(objects, 2.0)
    one = transactions.build(b, GRID, mode="certain")
    two = transactions.build(b, GRID, decays.boolean())
    assert _long(one) == _long(two)


def test_ellipse_keeps_area_and_calm_keeps_circle(objects):
    b = buffers.fixed(objects, 2.0)
    e = buffers.ellipse(b.withColumns({"speed": F.lit(5.0), "bearing": F.lit(30.0)}))
    assert all(r["a"] * r["b"] == pytest.approx(4.0) for r in e.collect())
    calm = buffers.ellipse(b.withColumns({"speed": F.lit(0.0), "bearing": F.lit(30.0)}))
    assert _long(transactions.build(calm, GRID)) == pytest.approx(_long(transactions.build(b, GRID)))


def test_bearings_round_trip(spark):
    x, y = angles.components(F.lit(3.0), F.col("t"))
    rows = spark.range(0, 360, 5).select(F.col("id").cast("double").alias("t")).select("t", angles.bearing(x, y).alias("b"), angles.bearing_by_quadrant(x, y).alias("q"))
    for r in rows.collect():
        assert min(abs(r["b"] - r["t"]), abs(r["b"] - r["t"] - 360)) < 1e-6
        assert min(abs(r["q"] - r["t"]), abs(abs(r["q"] - r["t"]) - 360)) < 1e-6


def test_spline_meets_its_stations(spark):
    st_ = spark.createDataFrame([(i, float(i * 3 % 11), float(i * 5 % 13), float(i), float(10 - i)) for i in range(8)], "station_id int, x double, y double, u double, v double")
    at = st_.select(F.col("station_id").cast("string").alias("object_id"), "x", "y")
    got = {r["object_id"]: (r["u"], r["v"]) for r in winds.spline(at, st_).collect()}
    assert all(got[str(i)] == pytest.approx((i, 10 - i), abs=1e-6) for i in range(8))


def test_decay_falls(spark):
    for name, make in decays.NAMED.items():
        rows = spark.range(0, 41).select(make()(F.col("id") / 10.0, F.lit(4.0)).alias("p"), "id").orderBy("id").collect()
        p = [r["p"] for r in rows]
        assert all(a >= b - 1e-12 for a, b in zip(p, p[1:])), name
        assert p[0] == 1.0 and 0 <= min(p)


def test_permutation_keeps_counts(spark):
    rows = spark.createDataFrame([(f"{i}", f"f{i % 4}", "cause", f"s{i % 5}", float(i % 5), 1.0, 10.0 + i) for i in range(20)], "object_id string, feature string, role string, site_id string, x double, y double, amount double")
    for moved in (randomize.permute_features(rows, 1, 3), randomize.permute_by_hash(rows, 1, 3)):
        by = lambda c: sorted((r["sim_id"], r[c], r["count"]) for r in moved.groupBy("sim_id", c).count().collect())
        assert by("feature") == sorted((s, f"f{k}", 5) for s in (1, 2, 3) for k in range(4))
        assert by("site_id") == sorted((s, f"s{k}", 4) for s in (1, 2, 3) for k in range(5))


def test_population_shares_are_kept(spark):
    cases = spark.createDataFrame([(f"{i:02d}", "D", "effect", i < 10, 0.0, 0.0) for i in range(15)], "object_id string, feature string, role string, urban boolean, x double, y double")
    zones = spark.createDataFrame([(1, 0.0, 0.0, 1.0, 1.0, 70), (2, 5.0, 5.0, 6.0, 6.0, 30)], "zone_id int, x0 double, y0 double, x1 double, y1 double, population long")
    rows = randomize.by_population(cases, zones, (0.0, 0.0, 10.0, 10.0), 1, 4).collect()
    for sim in (1, 2, 3, 4):
        mine = [r for r in rows if r["sim_id"] == sim]
        assert len(mine) == 15
        assert sum(r["urban"] and r["x"] < 1 for r in mine) == 7
        assert sum(r["urban"] and 5 <= r["x"] < 6 for r in mine) == 3
        assert not any(not r["urban"] and ((r["x"] < 1 and r["y"] < 1) or (5 <= r["x"] < 6 and 5 <= r["y"] < 6)) for r in mine)


def test_blocks_change_no_survivor(spark):
    pts = synthetic.planted(spark).where("feature in ('C1', 'C2', 'D')")
    b = buffers.fixed(pts, 1.0)
    draws = lambda first, last: buffers.fixed(randomize.uniform(pts, synthetic.BOX, first, last), 1.0)
    cfg = MinerConfig(effect="D", box=synthetic.BOX, step=0.5, d=2, sims=19)
    full = {(r["key"], r["exceed"]) for r in miner.single_plan(b, draws, cfg).where("significant").collect()}
    blocks, trace = miner.in_blocks(b, draws, MinerConfig(effect="D", box=synthetic.BOX, step=0.5, d=2, sims=19, sim_batch=8))
    assert {(r["key"], r["exceed"]) for r in blocks.collect()} == full
    assert {"C1", "C2", "C1+C2"} <= {k for k, _ in full}
    assert [t["candidates"] for t in trace] == sorted((t["candidates"] for t in trace), reverse=True)


def test_distance_study_falls(spark):
    from coloc.catalog.methods import distance_study

    got = [r["mean_exp_sup"] for r in distance_study(spark, reps=3).orderBy("range_id").collect()]
    published = [1558.9, 1355.3, 1017.1, 649.9, 353.3, 155.9, 52.8, 16.6, 8.3, 5.7]
    assert all(a > b for a, b in zip(got[:8], got[1:8]))
    assert all(abs(a / b - 1) < 0.15 for a, b in zip(got[:5], published))


def test_level_wise_growth_misses_nothing_frequent(spark):
    tx = transactions.from_table(spark.createDataFrame(HAND, "tx_id string, item string, p double"))
    got = {(r["key"], r["sup"]) for r in baselines.levelwise(tx, 2, 3).collect()}
    assert got == {("A", 3), ("B", 3), ("D", 2), ("A+B", 2), ("B+D", 2)}


def test_overlap_regions(spark):
    a = spark.createDataFrame([("x", 0.01), ("y", 0.03)], "key string, p_value double")
    b = spark.createDataFrame([("y", 0.05), ("z", 0.02)], "key string, p_value double")
    got = {r["region"]: (r["n"], round(r["p_mean"], 3)) for r in measures.regions(measures.overlap({"a": a, "b": b})).collect()}
    assert got == {1: (1, 0.01), 3: (1, 0.04), 2: (1, 0.02)}


@settings(max_examples=8, deadline=None)
@examples(st.lists(st.lists(st.tuples(st.sampled_from("ABCDE"), st.integers(1, 10)), min_size=1, max_size=5, unique_by=lambda t: t[0]), min_size=1, max_size=5))
def test_supports_equal_brute_force(spark, txs):
    rows = [(i, f, p / 10) for i, t in enumerate(txs) for f, p in t]
    wide = transactions.to_wide(transactions.from_table(spark.createDataFrame(rows, "tx_id int, item string, p double")))
    got = {r["key"]: float(r["exp_sup"]) for r in prevalence.supports(wide, 3).collect()}
    want: dict[str, float] = {}
    for t in txs:
        for n in (1, 2, 3):
            for c in combinations(sorted(t), n):
                want["+".join(f for f, _ in c)] = want.get("+".join(f for f, _ in c), 0.0) + math.prod(p / 10 for _, p in c)
    assert got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_empty_objects(spark, objects):
    none = buffers.fixed(objects.where("false"), 1.0)
    tx = transactions.build(none, GRID)
    assert tx.count() == 0 and itemsets.occurring(transactions.to_wide(tx)).count() == 0
