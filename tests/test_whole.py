"""The registered queries do the whole job, at the settings of the experiments."""

from __future__ import annotations

import math
import re

import pytest

import __spark_entry__
from coloc import catalog
from coloc.catalog import methods, twins
from coloc.functions import geometry, sqlfuncs
from coloc.operators import baselines, buffers, grids, indexing, randomize, transactions
from coloc.plans import miner
from coloc.plans.config import MinerConfig
from coloc.sources import files
from coloc.sources.staging import shared_folder
from coloc.streaming import windows
from tests.conftest import DATA


def test_settings_are_those_of_the_experiments():
    assert (methods.RULES.sims, methods.RULES.d, methods.RULES.alpha) == (99, 3, 0.05)
    assert (methods.pattern_cfg().sims, methods.pattern_cfg().d) == (99, 3)
    assert (twins.R, twins.D) == (99, 3)
    without = __spark_entry__.queries().keys() - __spark_entry__.oracle_sql().keys()
    assert {n for n in without if n in catalog.queries()} == {"approx_features", "runtime_fit", "synth_planted_mine", "synth_truth", "wind_tps", "workload_run_times", "workload_wind_rules"}


def test_toxic_rules_have_every_word(spark):
    toxic = {r[0]: False for r in spark.read.parquet(f"{DATA}/labels.parquet").select("doc_id").collect()}
    toxic |= {r[0]: True for r in spark.read.parquet(f"{DATA}/labels.parquet").where("toxic = 1").select("doc_id").collect()}
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    want: dict = {}
    for r in spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text").distinct().collect():
        for w in set(re.split(r"[\x20\x09-\x0D]+", r["text"].translate(lower))) - {""} if r["doc_id"] in toxic else ():
            both, one = want.get(w, (0, 0))
            want[w] = (both + toxic[r["doc_id"]], one + 1)
    got = {r["key"]: (r["sup"], r["sup_lhs"]) for r in __spark_entry__.queries()["rules_documents_toxic"](spark, DATA).collect()}
    assert len(got) > 50 and got == want


@pytest.fixture(scope="module")
def scene(spark):
    """Causes with awkward names near or far from the effect D."""
    names = ["Q+X", "Q", "X", "Z"]
    rows = [(f"{n}{i}", n, "cause", f"s{i % 7}{n}", float(5 * (i % 6)), float(5 * (i // 6)), 3.0) for n in names for i in range(12)]
    rows += [(f"d{i}", "D", "effect", f"d{i}", float(5 * (i % 6)) + 0.5, float(5 * (i // 6)), 3.0) for i in range(12)]
    objects = spark.createDataFrame(rows, "object_id string, feature string, role string, site_id string, x double, y double, amount double")
    box = (-5.0, -5.0, 60.0, 60.0)
    draws = lambda first, last: buffers.fixed(randomize.uniform(objects, box, first, last), 2.0)
    return buffers.fixed(objects, 2.0), draws, MinerConfig(effect="D", box=box, sims=19, d=2)


def _found(rows) -> dict:
    return {tuple(r["items"]): (r["exceed"], round(r["p_value"], 6)) for r in rows.collect()}


def test_blocks_equal_the_single_plan_for_any_names(scene):
    from dataclasses import replace

    objects, draws, cfg = scene
    whole = _found(miner.single_plan(objects, draws, cfg).where("significant"))
    assert whole and ("Q+X",) in whole and ("Q", "X") in whole
    for size in (3, 7):
        assert _found(miner.in_blocks(objects, draws, replace(cfg, sim_batch=size))[0]) == whole


def test_only_given_candidates_are_tested(spark, scene):
    objects, draws, cfg = scene
    given = spark.createDataFrame([(["X", "Q"],), (["Q+X"],), (["nobody"],)], "items array<string>")
    got = _found(miner.single_plan(objects, draws, cfg, given=given))
    assert got.keys() == {("Q", "X"), ("Q+X",)}


def test_own_random_sets(spark, scene):
    """Simulations that a user has ready, here copies of the observed set: nothing is rare then."""
    objects, _, cfg = scene
    copies = randomize.with_sims(objects, 1, 19)
    got = miner.single_plan(objects, lambda a, b: copies.where(f"sim_id between {a} and {b}"), cfg)
    assert {r["exceed"] for r in got.collect()} == {19}


def test_dense_index(spark):
    rows = spark.range(1000).selectExpr("pmod(id * 7919, 1000) AS a", "id")
    got = indexing.dense_index(rows.repartition(7), "a").collect()
    assert all(r["i"] == r["a"] for r in got) and len(got) == 1000


def test_cliques_equal_brute_force(spark):
    import random

    rnd = random.Random(3)
    rows = [(f"o{i}", rnd.choice("ABCD"), rnd.uniform(0, 8), rnd.uniform(0, 8)) for i in range(60)]
    objects = spark.createDataFrame(rows, "object_id string, feature string, x double, y double")
    got = {tuple(r["members"]) for r in baselines.cliques(objects, 1.5, 3).collect()}
    near = lambda a, b: math.hypot(a[2] - b[2], a[3] - b[3]) <= 1.5
    want = {(a[0], b[0]) for a in rows for b in rows if a[1] < b[1] and near(a, b)}
    want |= {(a[0], b[0], c[0]) for a in rows for b in rows for c in rows if a[1] < b[1] < c[1] and near(a, b) and near(b, c) and near(a, c)}
    assert got == want


def test_transactions_on_the_globe(spark):
    box, step = (-114.0, 49.0, -113.0, 50.0), 5.0
    objects = spark.createDataFrame([("o", "A", -113.5, 49.5), ("p", "A", -113.9, 49.9)], "object_id string, feature string, x double, y double")
    grid = grids.fixed(*box, step, "geodesic")
    got = {(r["gi"], r["gj"]): (r["n_inst"], float(r["p"])) for r in transactions.build(buffers.fixed(objects, 12.0), grid).collect()}
    want: dict = {}
    for g in grids.points(spark, grid).collect():
        near = []
        for x, y in ((-113.5, 49.5), (-113.9, 49.9)):
            a, b, c, e = map(math.radians, (g["gx"], g["gy"], x, y))
            h = math.sin((b - e) / 2) ** 2 + math.cos(b) * math.cos(e) * math.sin((a - c) / 2) ** 2
            near.append(2 * grids.KM_PER_DEGREE * 180 / math.pi * math.asin(math.sqrt(h)))
        if any(d <= 12.0 for d in near):
            want[g["gi"], g["gj"]] = (sum(d <= 12.0 for d in near), math.cos(math.pi * min(near) / 12.0) / 2 + 0.5)
    assert got.keys() == want.keys() and len(got) > 20
    assert all(got[k][0] == want[k][0] and got[k][1] == pytest.approx(want[k][1], abs=1e-9) for k in want)


def test_results_by_run_do_not_double(spark):
    path = f"{shared_folder(spark)}/rules-by-run"
    rules = spark.createDataFrame([("A", 0.01), ("B", 0.02)], "key string, p_value double")
    for run in ("one", "two", "one"):
        files.save_results(rules, path, run)
    assert {r[0]: r[1] for r in files.results(spark, path).groupBy("run_id").count().collect()} == {"one": 2, "two": 2}


def test_arrow_rings_equal_the_built_in_ones(spark):
    from pyspark.sql import functions as F

    rows = [(float(x), float(y), [(0.0, 0.0), (4.0, 0.0), (4.0, 3.0), (2.0, 5.0), (0.0, 3.0), (0.0, 0.0)]) for x in range(-2, 7) for y in range(-2, 7)]
    df = spark.createDataFrame(rows, "x double, y double, ring array<struct<x: double, y: double>>")
    both = df.select(sqlfuncs.ring_distance("x", "y", "ring").alias("a"), geometry.ring_distance(F.col("x"), F.col("y"), F.col("ring")).alias("b")).collect()
    assert all(r["a"] == pytest.approx(r["b"], abs=1e-9) for r in both)
    assert df.agg(sqlfuncs.sum_of_products("x", "y")).first()[0] == pytest.approx(df.agg(F.sum(F.col("x") * F.col("y"))).first()[0])


def test_late_rows_are_counted_and_batches_mined_again(spark, tmp_path):
    from pyspark.sql import functions as F

    schema = "ts timestamp, k int"
    source = str(tmp_path / "in")
    for day, n in (("2024-01-10", 1), ("2024-01-20", 2), ("2024-01-01", 3)):
        spark.createDataFrame([(day, n)], "d string, k int").select(F.to_timestamp("d").alias("ts"), "k").coalesce(1).write.mode("append").parquet(source)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(source)
    counted = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).count()
    run = counted.writeStream.format("noop").outputMode("append").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert windows.late_rows(run) == 1
    results = str(tmp_path / "results")
    windows.retested(stream, lambda held: held.agg(F.count(F.lit(1)).alias("n")), str(tmp_path / "held"), results, str(tmp_path / "c2")).awaitTermination()
    assert {r["run_id"]: r["n"] for r in files.results(spark, results).collect()} == {"0": 1, "1": 2, "2": 3}
