"""Randomised copies of objects under sim_id, drawn so that any node can redo any simulation.

Draws are digests of a seed, the simulation and an object. Places in an order come from dense_index, so no task sees a whole simulation.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.functions.draws import draw
from coloc.operators.indexing import dense_index
from coloc.sources.staging import staged

ATTEMPTS = 8
#: Zones that are ordered in one task and sent to all executors, at most.
MAX_ZONES = 100_000


def with_sims(objects: DataFrame, first: int, last: int) -> DataFrame:
    # a small file is one or two tasks, and what is drawn for it is many times as large
    objects = objects.repartition(int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return objects.withColumn("sim_id", F.explode(F.sequence(F.lit(first), F.lit(last))))


def _tag(name: str, seed: str = "") -> Column:
    return F.concat(F.lit(seed + name), F.col("sim_id").cast("string"), F.lit(":"))


def slots(objects: DataFrame) -> DataFrame:
    """objects with slot, their place from 1 in the order of sites and features."""
    placed = dense_index(objects, "site_id", "feature", name="slot")
    return placed.withColumn("slot", F.col("slot") + 1)


def permute_features(objects: DataFrame, first: int, last: int, carry_amount: bool = True, placed: DataFrame | None = None, seed: str = "", n: int | None = None) -> DataFrame:
    """Sites keep their number of features; the features (with their amounts, or not) change places among all slots.

    `placed` are slots(objects) and n their number, where they are known already.
    """
    placed = slots(objects) if placed is None else placed
    n = placed.count() if n is None else n
    own = placed.select("slot", "site_id", "x", "y", *([] if carry_amount else ["amount"]))
    digest = F.md5(F.concat(F.lit(seed + "p"), F.col("sim_id").cast("string"), F.lit(":"), "site_id", "feature"))
    rows = with_sims(objects.select("site_id", "feature", "role", *(["amount"] if carry_amount else [])), first, last).withColumn("_digest", digest)
    drawn = dense_index(rows, "sim_id", "_digest", "site_id", "feature")
    drawn = drawn.withColumn("slot", F.col("i") - (F.col("sim_id") - first) * n + 1).drop("i", "_digest", "site_id")
    return own.join(drawn, "slot").withColumn("object_id", F.concat_ws("/", "site_id", "slot")).drop("slot")


def feistel(index: Column, size: Column, seed: Column, rounds: int = 6) -> Column:
    """A keyed bijection of the smallest square of a power of two that holds [0, size): two half words are mixed in turn."""
    half = F.greatest(F.lit(1), F.ceil(F.log2(F.greatest(size, F.lit(2)).cast("double")) / 2)).cast("int")
    mask = F.pow(F.lit(2.0), half).cast("long") - 1
    wide = mask + 1

    def once(v: Column) -> Column:
        left, right = F.floor(v / wide).cast("long"), F.pmod(v, wide)
        for r in range(rounds):
            left, right = right, left.bitwiseXOR(F.xxhash64(right, seed, F.lit(r)).bitwiseAND(mask))
        return left * wide + right

    return once(index)


def permute_by_hash(objects: DataFrame, first: int, last: int, placed: DataFrame | None = None, n: int | None = None) -> DataFrame:
    """As permute_features with places from a keyed bijection of the slots instead of text digests: order by number only."""
    placed = slots(objects) if placed is None else placed
    n = placed.count() if n is None else n
    rows = with_sims(placed.select("slot", "feature", "role", "amount"), first, last)
    rows = rows.withColumn("_place", feistel(F.col("slot") - 1, F.lit(n), F.col("sim_id"))).drop("slot")
    moved = dense_index(rows, "sim_id", "_place").withColumn("slot", F.col("i") - (F.col("sim_id") - first) * n + 1).drop("i", "_place")
    return placed.select("slot", "site_id", "x", "y").join(moved, "slot").withColumn("object_id", F.concat_ws("/", "site_id", "slot")).drop("slot")


def apportion(zones: DataFrame, total: DataFrame) -> DataFrame:
    """zone_id and box with low < place <= high: the shares of `total` (column total) by population, largest remainders first."""
    people = F.sum("population").over(W.partitionBy())
    rows = zones.crossJoin(F.broadcast(total)).withColumn("quota", F.when(people > 0, F.col("total") * F.col("population") / people).otherwise(0.0))
    rows = rows.withColumn("whole", F.floor("quota"))
    spare = F.col("total") - F.sum("whole").over(W.partitionBy())
    rank = F.row_number().over(W.orderBy(F.desc(F.col("quota") - F.col("whole")), "zone_id"))
    rows = rows.withColumn("share", F.col("whole") + F.when(rank <= spare, 1).otherwise(0))
    high = F.sum("share").over(W.orderBy("zone_id").rowsBetween(W.unboundedPreceding, 0))
    return rows.withColumn("high", high).withColumn("low", F.col("high") - F.col("share")).select("zone_id", "x0", "y0", "x1", "y1", "share", "low", "high")


def bounded(zones: DataFrame) -> DataFrame:
    """zones, written once, if they are few enough."""
    zones = staged(zones, "zones")
    if zones.count() > MAX_ZONES:
        raise ValueError(f"at most {MAX_ZONES} zones")
    return zones


def ranked(cases: DataFrame) -> DataFrame:
    """The urban cases with k, their place from 1 in the order of ids."""
    placed = dense_index(cases.where("urban"), "object_id", name="k")
    return placed.withColumn("k", F.col("k") + 1)


def by_population(cases: DataFrame, zones: DataFrame, box: tuple[float, float, float, float], first: int, last: int, how: str = "largest_remainder", placed: DataFrame | None = None, seed: str = "") -> DataFrame:
    """Cases placed anew: urban ones in the zones by population, the others anywhere outside the zones.

    The zones are a list of at most MAX_ZONES; more are refused. With how="draw" each urban case draws its zone by population instead of filling shares.
    `placed` are ranked(cases), and then zones bounded(zones), where they are known already.
    """
    zones = bounded(zones) if placed is None else zones
    urban = ranked(cases) if placed is None else placed
    total = urban.agg(F.count(F.lit(1)).alias("total"))
    key = F.col("object_id")
    if how == "draw":
        people = W.orderBy("zone_id").rowsBetween(W.unboundedPreceding, 0)
        all_ = F.sum("population").over(W.partitionBy())
        cum = zones.withColumn("high", F.sum("population").over(people) / all_).withColumn("low", F.col("high") - F.col("population") / all_)
        rows = with_sims(urban, first, last).withColumn("at", draw(_tag("z", seed), key))
        placed = rows.join(F.broadcast(cum), (F.col("at") >= F.col("low")) & (F.col("at") < F.col("high")))
    else:
        rows = with_sims(urban, first, last)
        placed = rows.join(F.broadcast(apportion(zones, total)), (F.col("k") > F.col("low")) & (F.col("k") <= F.col("high")))
    inner = placed.select("sim_id", "object_id", "feature", "role", "urban", (F.col("x0") + (F.col("x1") - F.col("x0")) * draw(_tag("sx", seed), key)).alias("x"), (F.col("y0") + (F.col("y1") - F.col("y0")) * draw(_tag("sy", seed), key)).alias("y"))
    bx0, by0, bx1, by1 = box
    tries = with_sims(cases.where("not urban"), first, last).withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(ATTEMPTS - 1))))
    t = F.col("t").cast("string")
    tries = tries.withColumns({"x": bx0 + (bx1 - bx0) * draw(F.concat(_tag("rx", seed), t, F.lit(":")), key), "y": by0 + (by1 - by0) * draw(F.concat(_tag("ry", seed), t, F.lit(":")), key)})
    z = F.broadcast(zones.select(F.col("x0").alias("zx0"), F.col("y0").alias("zy0"), F.col("x1").alias("zx1"), F.col("y1").alias("zy1")))
    outside = tries.join(z, (F.col("x") >= F.col("zx0")) & (F.col("x") < F.col("zx1")) & (F.col("y") >= F.col("zy0")) & (F.col("y") < F.col("zy1")), "left_anti")
    # the last attempt stands if all fell into zones
    any_try = outside.unionByName(tries.where(F.col("t") == ATTEMPTS - 1).withColumn("t", F.lit(ATTEMPTS)))
    best = any_try.groupBy("sim_id", "object_id", "feature", "role", "urban").agg(F.min(F.struct("t", "x", "y")).alias("s"))
    return inner.unionByName(best.select("sim_id", "object_id", "feature", "role", "urban", "s.x", "s.y"))


def uniform(objects: DataFrame, box: tuple[float, float, float, float], first: int, last: int, seed: str = "") -> DataFrame:
    """Complete spatial randomness: every object anywhere in the box."""
    x0, y0, x1, y1 = box
    key = F.col("object_id")
    return with_sims(objects.drop("x", "y"), first, last).withColumns({"x": x0 + (x1 - x0) * draw(_tag("ux", seed), key), "y": y0 + (y1 - y0) * draw(_tag("uy", seed), key)})
