"""Prevalence measures, each one partial and one final aggregation of whole numbers, so no sum depends on the order of rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.operators import itemsets


def supports(wide: DataFrame, d: int = 3, bits: int | None = None, live: DataFrame | None = None) -> DataFrame:
    """key, size, sup (count), exp_sup (sum of products); items too if they are names."""
    rows = itemsets.expand(wide, d, bits, live)
    by = [c for c in ("sim_id", "set_id") if c in wide.columns]
    high, low = itemsets.total(F.col("p"))
    out = sets_of(rows.groupBy(*by, "key", "size").agg(F.count(F.lit(1)).alias("sup"), high.alias("bh"), low.alias("bl")))
    return out if itemsets.coded(wide) else itemsets.named(out)


def sets_of(sums: DataFrame) -> DataFrame:
    """Supports of sums of parts (bh, bl: the high and low halves)."""
    return sums.withColumn("exp_sup", itemsets.joined(F.col("bh"), F.col("bl"))).drop("bh", "bl", "lh", "ll", "sup_lhs")


def rules_of(sums: DataFrame) -> DataFrame:
    """Confidences of sums of parts of both sides (bh, bl) and of the antecedent (lh, ll)."""
    out = sums.withColumns({"exp_sup": itemsets.joined(F.col("bh"), F.col("bl")), "exp_sup_lhs": itemsets.joined(F.col("lh"), F.col("ll"))}).drop("bh", "bl", "lh", "ll")
    ratio = lambda a, b: F.when(F.col(b) > 0, F.col(a).cast("double") / F.col(b).cast("double"))
    return out.withColumns({"conf": ratio("sup", "sup_lhs"), "exp_conf": ratio("exp_sup", "exp_sup_lhs")})


def confidences(wide: DataFrame, effect: str | int, d: int = 3, bits: int | None = None, live: DataFrame | None = None) -> DataFrame:
    """key (antecedent), size, sup, sup_lhs, exp_sup, exp_sup_lhs, conf, exp_conf of rules to the effect; items too if they are names.

    A rule whose antecedent has no support has no confidence (null).
    """
    rows = itemsets.expand_rules(wide, effect, d, bits, live)
    by = [c for c in ("sim_id", "set_id") if c in wide.columns]
    both, lhs = itemsets.total(F.col("p_both")), itemsets.total(F.col("p_lhs"))
    sums = {"bh": both[0], "bl": both[1], "lh": lhs[0], "ll": lhs[1]}
    counts = F.sum(F.col("has").cast("long")).alias("sup"), F.count(F.lit(1)).alias("sup_lhs")
    out = rules_of(rows.groupBy(*by, "key", "size").agg(*counts, *[v.alias(k) for k, v in sums.items()]))
    return out if itemsets.coded(wide) else itemsets.named(out)


def general_confidence(tx: DataFrame, rules: DataFrame) -> DataFrame:
    """Rules with any two disjoint sides (lhs, rhs: arrays of names in order) from pattern supports."""
    sup = supports(tx, 8).select("items", "exp_sup")
    rows = rules.withColumn("_both", F.array_sort(F.concat("lhs", "rhs")))
    both = rows.join(sup.select(F.col("items").alias("_both"), F.col("exp_sup").alias("exp_both")), "_both")
    out = both.join(sup.select(F.col("items").alias("lhs"), F.col("exp_sup").alias("exp_lhs")), "lhs").drop("_both")
    return out.withColumn("exp_conf", F.when(F.col("exp_lhs") > 0, F.col("exp_both") / F.col("exp_lhs")))
