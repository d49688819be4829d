"""Generated objects: the planted set, the distance study and the small illustrations."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.functions.draws import draw

SIDE = 100.0
BOX = (0.0, 0.0, SIDE, SIDE)
#: Largest offset of a planted neighbour: places are uniform in that distance, so the mean is half of it.
OFFSET = 0.8
PLANTED = ("C1", "C2", "C3", "C4", "C5", "C1+C2", "C3+C4")
NOISE = ("C6", "C7")


def _near(tag: str, key: Column, x: Column, y: Column, offset: float = OFFSET) -> tuple[Column, Column]:
    r, t = offset * draw(tag + "r", key), 2 * math.pi * draw(tag + "t", key)
    return x + r * F.cos(t), y + r * F.sin(t)


def planted(spark: SparkSession, seed: str = "s") -> DataFrame:
    """object_id, feature, role, x, y: pairs C1-C2 and C3-C4 and most of C5 lie near the effect D; C6 is anywhere, C7 away from D."""
    key = F.col("id").cast("string")

    def free(feature: str, n: int, first: int = 0) -> DataFrame:
        k = F.concat(F.lit(f"{seed}{feature}-"), (F.col("id") + first).cast("string"))
        return spark.range(n).select(k.alias("object_id"), F.lit(feature).alias("feature"), (SIDE * draw("x", k)).alias("x"), (SIDE * draw("y", k)).alias("y"))

    def near(base: DataFrame, feature: str, tag: str) -> DataFrame:
        x, y = _near(tag, F.col("object_id"), F.col("x"), F.col("y"))
        return base.select(F.concat("object_id", F.lit(f">{feature}")).alias("object_id"), F.lit(feature).alias("feature"), x.alias("x"), y.alias("y"))

    c1, c3, c5 = free("C1", 20), free("C3", 20), free("C5", 30)
    d = near(c1, "D", "d1").unionByName(near(c3, "D", "d3")).unionByName(near(c5, "D", "d5")).unionByName(free("D", 30))
    parts = [c1, near(c1, "C2", "n1"), c3, near(c3, "C4", "n3"), free("C3", 10, 100), free("C4", 10, 100), c5, free("C5", 10, 100), free("C6", 30), d]
    del key
    away = free("C7", 120)
    apart = away.join(F.broadcast(d.select(F.col("x").alias("dx"), F.col("y").alias("dy"))), F.hypot(F.col("x") - F.col("dx"), F.col("y") - F.col("dy")) < 2.0, "left_anti")
    parts.append(apart.orderBy("object_id").limit(30))
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return rows.withColumn("role", F.when(F.col("feature") == "D", "effect").otherwise("cause"))


def distance_pairs(spark: SparkSession, reps: int = 100, pairs: int = 30, ranges: int = 10, width: float = 0.2, ids: DataFrame | None = None) -> DataFrame:
    """ids (id): of given rows, else as many as reps need. set_id, range_id, object_id, feature, x, y: f1 anywhere, and one f2 for each at a distance from the range."""
    ids = spark.range(reps * ranges * pairs) if ids is None else ids
    rows = ids.select("id", F.floor(F.col("id") / pairs).alias("set_id"))
    rows = rows.withColumn("range_id", (F.col("set_id") % ranges).cast("int"))
    k = F.col("id")
    x, y = SIDE * draw("px", k), SIDE * draw("py", k)
    r, t = width * (F.col("range_id") + draw("pr", k)), 2 * math.pi * draw("pt", k)
    one = rows.select("set_id", "range_id", F.concat(F.lit("a"), k.cast("string")).alias("object_id"), F.lit("f1").alias("feature"), x.alias("x"), y.alias("y"))
    two = rows.select("set_id", "range_id", F.concat(F.lit("b"), k.cast("string")).alias("object_id"), F.lit("f2").alias("feature"), (x + r * F.cos(t)).alias("x"), (y + r * F.sin(t)).alias("y"))
    return one.unionByName(two)


def two_pairs(spark: SparkSession) -> DataFrame:
    """A close pair A1-B1 and a far pair A2-B2."""
    return spark.createDataFrame([("A1", "A", 5.0, 5.0), ("B1", "B", 5.5, 5.0), ("A2", "A2", 15.0, 5.0), ("B2", "B2", 16.8, 5.0)], "object_id string, feature string, x double, y double")


def triples(spark: SparkSession) -> DataFrame:
    """set_id 1, 2, 3: three mutual neighbours with a large, a small and no common area of their unit buffers."""
    rows = []
    for set_id, side in ((1, 0.5), (2, 1.6), (3, 1.9)):
        high = side * math.sqrt(3) / 2
        rows += [(set_id, f"{f}{set_id}", f, 5.0 + x, 5.0 + y) for f, x, y in (("A", 0.0, 0.0), ("B", side, 0.0), ("C", side / 2, high))]
    return spark.createDataFrame(rows, "set_id int, object_id string, feature string, x double, y double")
