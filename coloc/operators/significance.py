"""Exceedance counts, p-values and decisions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.functions.tests_of_chance import most_exceedances, p_value


def exceedances(observed: DataFrame, simulated: DataFrame, measure: str) -> DataFrame:
    """key, exceed: simulations whose measure is at least the observed one. A key that is absent from a simulation, or has
    no confidence there, is not at least anything."""
    obs = observed.select("key", F.col(measure).alias("_obs"))
    hits = simulated.select("key", F.col(measure).alias("_sim")).join(obs, "key").where(F.col("_sim") >= F.col("_obs"))
    return hits.groupBy("key").agg(F.count(F.lit(1)).cast("int").alias("exceed"))


def decided(observed: DataFrame, exceed: DataFrame, sims: int, alpha: float, strict: bool = False) -> DataFrame:
    rows = observed.join(exceed, "key", "left").withColumn("exceed", F.coalesce("exceed", F.lit(0)))
    return rows.withColumns({"p_value": p_value(F.col("exceed"), sims), "significant": F.col("exceed") <= most_exceedances(alpha, sims, strict)})


def adjusted(rows: DataFrame, method: str = "bh") -> DataFrame:
    """With p_adjusted over all rows: bonferroni or the step-up false discovery rate.

    Rows of equal p have equal adjusted p, and a p is one of as many values as there are simulations, so only those are put in order.
    """
    each = rows.groupBy("p_value").agg(F.count(F.lit(1)).alias("_n"))
    n = F.sum("_n").over(W.partitionBy())
    if method == "bonferroni":
        q = F.col("p_value") * n
    else:
        up, later = W.orderBy("p_value").rowsBetween(W.unboundedPreceding, 0), W.orderBy(F.desc("p_value")).rowsBetween(W.unboundedPreceding, 0)
        each = each.withColumn("_q", F.col("p_value") * n / F.sum("_n").over(up))
        q = F.min("_q").over(later)
    return rows.join(each.select("p_value", F.least(F.lit(1.0), q).alias("p_adjusted")), "p_value")


def p_error(p: Column, sims: Column) -> Column:
    """Standard error of a p-value from that many simulations."""
    return F.sqrt(p * (1 - p) / (sims + 1))
