"""Candidate patterns and rules from a feature list."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.operators.itemsets import SEP


def enumerate_patterns(features: DataFrame, d: int = 3) -> DataFrame:
    """key, items, size of every combination of 1 to d features: self joins on order."""
    one = features.select(F.col("feature").alias("last")).distinct()
    level = one.select("last", F.array("last").alias("items"))
    out = level
    for _ in range(d - 1):
        level = level.join(F.broadcast(one.withColumnRenamed("last", "next")), F.col("last") < F.col("next")).select(F.col("next").alias("last"), F.array_append("items", F.col("next")).alias("items"))
        out = out.unionByName(level)
    return out.select(F.array_join("items", SEP).alias("key"), "items", F.size("items").alias("size"))


def rules_to(effect: str, causes: DataFrame, d: int = 3) -> DataFrame:
    rows = enumerate_patterns(causes.where(F.col("feature") != effect), d)
    return rows.select("key", F.col("items").alias("lhs"), F.array(F.lit(effect)).alias("rhs"), "size")


def rules_all(features: DataFrame, max_lhs: int = 2, max_rhs: int = 1) -> DataFrame:
    """Rules with disjoint sides of bounded size."""
    lhs = enumerate_patterns(features, max_lhs).select(F.col("key").alias("lhs_key"), F.col("items").alias("lhs"))
    rhs = enumerate_patterns(features, max_rhs).select(F.col("key").alias("rhs_key"), F.col("items").alias("rhs"))
    return lhs.join(F.broadcast(rhs), ~F.arrays_overlap("lhs", "rhs")).withColumn("both_key", F.array_join(F.array_sort(F.concat("lhs", "rhs")), SEP))
