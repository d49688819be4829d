"""Lines, whose distances are worked out in numpy."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from coloc.functions import geometry
from coloc.operators import grids, transactions


def test_lines_make_no_row_for_each_point_and_segment(spark):
    rng = random.Random(6)
    at = lambda: {"x": rng.uniform(-10, 60), "y": rng.uniform(-10, 60)}
    rows = [("a", [at() for _ in range(40)]), ("b", [at()]), ("b", [at()] * 3), ("a", [at(), {"x": None, "y": 1.0}, at(), at()])]
    lines = spark.createDataFrame(rows, "feature string, ring array<struct<x: double, y: double>>")
    grid = grids.Grid(2.0, (0.0, 0.0, 50.0, 50.0))
    got = transactions.extended(lines, grid, 3.0, "line")
    assert "MapInArrow" in got._jdf.queryExecution().executedPlan().toString()
    d = geometry.polyline_distance(F.col("gx"), F.col("gy"), F.col("ring"))
    near = lines.crossJoin(grids.points(spark, grid)).withColumn("d", d).where("d <= 3.0 + 1e-9")
    want = near.groupBy("gi", "gj", "feature").agg(F.count(F.lit(1)).alias("n"), F.round(F.max(F.cos(F.pi() * F.least(F.lit(1.0), F.col("d") / 3.0)) / 2 + 0.5), 9).alias("p"))
    shown = lambda df: sorted(tuple(r) for r in df.collect())
    assert shown(got.select("gi", "gj", "feature", "n_inst", F.round(F.col("p").cast("double"), 9))) == shown(want.select("gi", "gj", "feature", "n", "p"))
