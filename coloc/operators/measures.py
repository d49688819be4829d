"""Measures of results, data and work."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def overlap(results: dict[str, DataFrame]) -> DataFrame:
    """key, region (bit k set if result k has the set), p_mean over the results that have it; sets are told apart by items where all results have them."""
    by = ["key", "items"] if all("items" in df.columns for df in results.values()) else ["key"]
    rows = None
    for k, (_, df) in enumerate(results.items()):
        one = df.select(*by, F.lit(1 << k).alias("bit"), F.col("p_value").cast("double").alias("p"))
        rows = one if rows is None else rows.unionByName(one)
    return rows.groupBy(*by).agg(F.sum("bit").cast("int").alias("region"), F.avg("p").alias("p_mean"))


def regions(overlapped: DataFrame) -> DataFrame:
    """region, n, p_mean."""
    return overlapped.groupBy("region").agg(F.count(F.lit(1)).alias("n"), F.avg("p_mean").alias("p_mean"))


def tx_stats(tx: DataFrame) -> DataFrame:
    """n_transactions, mean_features, max_features."""
    by = [c for c in ("tx_id", "gi", "gj") if c in tx.columns]
    per = tx.groupBy(*by).agg(F.count(F.lit(1)).alias("s"))
    return per.agg(F.count(F.lit(1)).alias("n_transactions"), F.avg("s").alias("mean_features"), F.max("s").alias("max_features"))


def buffer_stats(buffered: DataFrame) -> DataFrame:
    return buffered.agg(F.count(F.lit(1)).alias("n"), F.avg("r").alias("mean_r"), F.min("r").alias("min_r"), F.max("r").alias("max_r"), F.avg(F.pi() * F.col("a") * F.col("b")).alias("mean_area"))


def low_support(rules: DataFrame, below: float = 1.0) -> DataFrame:
    return rules.agg(F.count(F.lit(1)).alias("n_rules"), F.coalesce(F.sum(F.when(F.col("exp_sup") < below, 1).otherwise(0)), F.lit(0)).alias("n_low"))


def line(x: str = "r", y: str = "seconds") -> list[Column]:
    """Aggregates slope, intercept, r2 of y against x."""
    return [F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2")]


def truth(rules: DataFrame, planted: list[str], noise: list[str]) -> DataFrame:
    """found / missed of the rules that must be there, reported of those that must not."""
    want = rules.sparkSession.createDataFrame([(k, True) for k in planted] + [(k, False) for k in noise], "key string, wanted boolean")
    got = want.join(rules.select("key", F.lit(True).alias("got")).distinct(), "key", "left").withColumn("got", F.coalesce("got", F.lit(False)))
    hit = lambda cond: F.sum(F.when(cond, 1).otherwise(0))
    return got.agg(hit(F.col("wanted") & F.col("got")).alias("found"), hit(F.col("wanted") & ~F.col("got")).alias("missed"), hit(~F.col("wanted") & F.col("got")).alias("false_hits"))


def work(tx: DataFrame, wide: DataFrame, d: int = 3) -> DataFrame:
    """What the plan handles instead of grid points times features: instances, items, transactions and subsets."""
    from coloc.operators.itemsets import expand

    a = tx.agg(F.sum("n_inst").alias("n_cells"), F.count(F.lit(1)).alias("n_items"))
    b = wide.agg(F.count(F.lit(1)).alias("n_transactions"))
    c = expand(wide, d).agg(F.count(F.lit(1)).alias("n_subsets"))
    return a.crossJoin(b).crossJoin(c)
