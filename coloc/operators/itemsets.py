"""Item sets that occur, expanded inside each transaction with the product of their probabilities.

Items are names, or codes of names from 1 in the order of the names. A set of names is the array of them in order. A set of codes is one long: `bits` bits for
each code, the first in the highest of d places. A set grows by the items after its last one, a generator for each size, all in generated code.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

SEP = "+"
#: A probability as a whole number of this many parts, so that sums do not depend on the order of rows.
PARTS, HALF = 10**12, 10**6


def coded(wide: DataFrame) -> bool:
    return not isinstance(wide.schema["items"].dataType.elementType["f"].dataType, StringType)


def prefix(key: Column, size: Column, n: int, d: int, bits: int) -> Column:
    """The first n items of a coded set."""
    low = bits * (d - n)
    return F.when(size > n, F.shiftleft(F.shiftright(key, low), low)).otherwise(key)


def grown(wide: DataFrame, d: int, bits: int | None = None, live: DataFrame | None = None) -> DataFrame:
    """wide without items, and key, p, size of every subset of 1 to d items. With live (key, size of coded sets, few enough to
    be sent to all executors), a set that begins none of those grows no further, and no other sets come out."""
    names = not coded(wide)
    if not names and (bits is None or bits * d > 63):
        raise ValueError(f"sets of {d} codes of {bits} bits do not fit a long")
    others = [c for c in wide.columns if c != "items"]
    put = lambda k, n: F.array(k) if names else F.shiftleft(k.cast("long"), bits * (d - n))
    add = lambda key, k, n: F.array_append(key, k) if names else key.bitwiseOR(put(k, n))
    # outer generators, as the others test their arrays for emptiness by making them twice
    rows = wide.select(*others, "items", F.posexplode_outer("items").alias("at", "it"))
    rows = rows.select(*others, "items", "at", put(F.col("it.f"), 1).alias("key"), F.col("it.p").alias("p"), F.lit(1).alias("size"))
    for n in range(2, d + 1):
        # its own place stands for the end of the set, the places after it for the next item
        last = F.when(F.col("size") == n - 1, F.size("items") - 1).otherwise(F.col("at"))
        rows = rows.select(*others, "items", "at", "key", "p", "size", F.explode_outer(F.sequence("at", last)).alias("to"))
        on, it = F.col("to") > F.col("at"), F.get("items", F.col("to"))
        rows = rows.select(*others, "items", F.col("to").alias("at"), F.when(on, add(F.col("key"), it["f"], n)).otherwise(F.col("key")).alias("key"), F.when(on, F.col("p") * it["p"]).otherwise(F.col("p")).alias("p"), F.when(on, n).otherwise(F.col("size")).alias("size"))
        if live is not None and n < d:
            begins = live.select(prefix(F.col("key"), F.col("size"), n, d, bits).alias("key")).union(live.select("key")).distinct()
            rows = rows.join(F.broadcast(begins), "key", "left_semi")
    rows = rows.select(*others, "key", "p", "size")
    return rows if live is None else rows.join(F.broadcast(live.select("key")), "key", "left_semi")


def parts(p: Column) -> Column:
    return (p * float(PARTS) + 0.5).cast("long")


def total(p: Column) -> tuple[Column, Column]:
    """Sums of the high and the low half of the parts of p: exact for 9 * 10^12 rows."""
    whole = parts(p)
    return F.sum(F.floor(whole / HALF)), F.sum(whole % HALF)


def joined(high: Column, low: Column) -> Column:
    return (high.cast("double") * float(HALF) + low.cast("double")) / float(PARTS)


def named(rows: DataFrame) -> DataFrame:
    """Sets of names with items, the array, and key, the names joined for the eye; what has the same key may be another set."""
    return rows.withColumn("items", F.col("key")).withColumn("key", F.array_join("items", SEP))


def expand(wide: DataFrame, d: int = 3, bits: int | None = None, live: DataFrame | None = None) -> DataFrame:
    """Rows (sim_id, set_id, key, size, p) of every occurring set of 1 to d features."""
    by = [c for c in ("sim_id", "set_id") if c in wide.columns]
    return grown(wide.select(*by, "items").where(F.size("items") > 0), d, bits, live).select(*by, "key", "size", "p")


def expand_rules(wide: DataFrame, effect: str | int, d: int = 3, bits: int | None = None, live: DataFrame | None = None) -> DataFrame:
    """Rows (sim_id, key, size, p_lhs, p_both, has) of every occurring antecedent of up to d causes. wide may have the effect's p apart in pe."""
    by = [c for c in ("sim_id", "set_id") if c in wide.columns]
    if "pe" not in wide.columns:
        own = F.get(F.filter("items", lambda s: s["f"] == effect), F.lit(0))["p"]
        wide = wide.select(*by, own.alias("pe"), F.filter("items", lambda s: s["f"] != effect).alias("items"))
    rows = wide.select(*by, F.coalesce("pe", F.lit(0.0)).alias("pe"), F.col("pe").isNotNull().alias("has"), "items").where(F.size("items") > 0)
    return grown(rows, d, bits, live).select(*by, "key", "size", F.col("p").alias("p_lhs"), (F.col("p") * F.col("pe")).alias("p_both"), "has")


def occurring(wide: DataFrame, d: int = 3) -> DataFrame:
    """key, size, n of the sets found: candidates without zero support, never the full product."""
    return named(expand(wide, d).groupBy("key", "size").agg(F.count(F.lit(1)).alias("n")))
