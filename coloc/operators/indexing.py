"""Dense places of rows in an order, without one task that sees all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.sources.staging import staged


def dense_index(df: DataFrame, *order: str, name: str = "i") -> DataFrame:
    """df with the place of each row, from 0, in the order of columns that tell all rows apart.

    Rows are dealt out by ranges and sorted within them; a range's first place is the number of rows in the ranges before it, which
    are as many as there are partitions.
    """
    nth = F.monotonically_increasing_id()
    ranges = df.repartitionByRange(*order).sortWithinPartitions(*order)
    placed = staged(ranges.select("*", F.shiftright(nth, 33).alias("_range"), nth.bitwiseAND(F.lit((1 << 33) - 1)).alias("_nth")), "sorted")
    before = F.sum("_n").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1))
    first = placed.groupBy("_range").agg(F.count(F.lit(1)).alias("_n")).select("_range", F.coalesce(before, F.lit(0)).alias("_first"))
    return placed.join(F.broadcast(first), "_range").withColumn(name, F.col("_first") + F.col("_nth")).drop("_range", "_nth", "_first")
