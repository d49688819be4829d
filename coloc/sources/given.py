"""Spatial objects from the given tables: emitting sites, cases, zones, wind stations and general points."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.functions.angles import octant
from coloc.functions.draws import draw
from coloc.sources.staging import staged

#: Rows that are sent to all executors at once, at most, so that lineitem need not be shuffled to meet them; more are joined by shuffling.
SMALL = 2_000_000
CELL, SIDE = 40.0, 5
URBAN = ("BUILDING", "HOUSEHOLD", "AUTOMOBILE")
EFFECT = "CASE"
REGION = (0.0, 0.0, 200.0, 200.0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _small(rows: DataFrame) -> DataFrame:
    """rows, sent to all executors if they are few enough."""
    return F.broadcast(rows) if rows.count() <= SMALL else rows


def corner(nation: Column) -> tuple[Column, Column]:
    """Lower left corner of a nation's cell."""
    return (nation % SIDE) * CELL, F.floor(nation / SIDE) * CELL


def facilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """site_id, nation, x, y."""
    x0, y0 = corner(F.col("s_nationkey"))
    key = F.col("s_suppkey")
    return table(spark, sf_dir, "supplier").select(key.cast("string").alias("site_id"), F.col("s_nationkey").alias("nation"), (x0 + CELL * draw("x", key)).alias("x"), (y0 + CELL * draw("y", key)).alias("y"))


def yearly_amounts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """site_id, feature, amount: the mean over years of the yearly quantity of each brand."""
    line = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey", "l_quantity", F.year("l_shipdate").alias("y"))
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("feature"))
    yearly = line.join(_small(part), "l_partkey").groupBy("l_suppkey", "feature", "y").agg(F.sum("l_quantity").alias("q"))
    return yearly.groupBy(F.col("l_suppkey").cast("string").alias("site_id"), "feature").agg(F.avg("q").alias("amount"))


def drop_rare(objects: DataFrame, min_sites: int = 3) -> DataFrame:
    """Without the features of fewer than min_sites sites."""
    common = objects.groupBy("feature").agg(F.countDistinct("site_id").alias("n")).where(F.col("n") >= min_sites)
    return objects.join(common.select("feature"), "feature", "left_semi")


def emissions(spark: SparkSession, sf_dir: str, top: int = 4, min_sites: int = 3) -> DataFrame:
    """object_id, feature, role, site_id, x, y, amount: each site's largest brands, rare brands left out."""
    order = W.partitionBy("site_id").orderBy(F.desc("amount"), "feature")
    best = yearly_amounts(spark, sf_dir).withColumn("k", F.row_number().over(order)).where(F.col("k") <= top)
    # read twice, for rare brands and for the others
    placed = drop_rare(staged(best.drop("k"), "best"), min_sites).join(facilities(spark, sf_dir), "site_id")
    return placed.select(F.concat_ws("/", "site_id", "feature").alias("object_id"), "feature", F.lit("cause").alias("role"), "site_id", "x", "y", "amount")


def _case_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The customers that are cases."""
    return table(spark, sf_dir, "customer").where("c_acctbal < 0")


def cases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """object_id, feature, role, nation, urban, x, y."""
    key = F.col("c_custkey")
    x0, y0 = corner(F.col("c_nationkey"))
    urban = F.col("c_mktsegment").isin(*URBAN)
    at = lambda low, tag: F.when(urban, low + 15.0 + 10.0 * draw(tag, key)).otherwise(low + CELL * draw(tag, key))
    return _case_rows(spark, sf_dir).select(key.cast("string").alias("object_id"), F.lit(EFFECT).alias("feature"), F.lit("effect").alias("role"), F.col("c_nationkey").alias("nation"), urban.alias("urban"), at(x0, "cx").alias("x"), at(y0, "cy").alias("y"))


def cases_linked(spark: SparkSession, sf_dir: str, sites: DataFrame | None = None) -> DataFrame:
    """Cases, of which those whose main supplier emits the most common brand lie near that supplier. sites: emissions(), if they are there already."""
    sites = emissions(spark, sf_dir) if sites is None else sites
    target = sites.groupBy("feature").agg(F.countDistinct("site_id").alias("n")).orderBy(F.desc("n"), "feature").limit(1).select("feature")
    at = sites.join(F.broadcast(target), "feature").select("site_id", F.col("x").alias("sx"), F.col("y").alias("sy"))
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    # the orders of cases only, written once as they are counted before they meet all of lineitem
    people = _small(_case_rows(spark, sf_dir).select(F.col("c_custkey").alias("o_custkey")))
    order = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey").join(people, "o_custkey", "left_semi")
    bought = line.join(_small(staged(order, "orders")), "l_orderkey").groupBy("o_custkey", "l_suppkey").agg(F.sum("l_quantity").alias("q"))
    main = bought.groupBy("o_custkey").agg(F.min_by("l_suppkey", F.struct((-F.col("q")).alias("q"), "l_suppkey")).alias("s"))
    near = main.select(F.col("o_custkey").cast("string").alias("object_id"), F.col("s").cast("string").alias("site_id")).join(at, "site_id").drop("site_id")
    rows = cases(spark, sf_dir).join(near, "object_id", "left").withColumn("linked", F.col("sx").isNotNull())
    moved = lambda s, tag, old: F.when(F.col("linked"), F.col(s) + 6.0 * draw(tag, F.col("object_id")) - 3.0).otherwise(F.col(old))
    return rows.withColumns({"x": moved("sx", "lx", "x"), "y": moved("sy", "ly", "y")}).drop("sx", "sy")


def zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """zone_id, x0, y0, x1, y1, population: the urban square of each nation; people are its customers."""
    x0, y0 = corner(F.col("n_nationkey"))
    people = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.count(F.lit(1)).alias("population"))
    rows = table(spark, sf_dir, "nation").join(people, "n_nationkey", "left")
    return rows.select(F.col("n_nationkey").alias("zone_id"), (x0 + 15.0).alias("x0"), (y0 + 15.0).alias("y0"), (x0 + 25.0).alias("x1"), (y0 + 25.0).alias("y1"), F.coalesce("population", F.lit(0)).alias("population"))


def wind_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """station_id, day, speed, bearing."""
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("station_id"), F.to_date("ts").alias("day"), F.col("value").alias("speed"), (k * 3.6).alias("bearing"))


def station_places(stations: DataFrame) -> DataFrame:
    key = F.col("station_id")
    return stations.withColumns({"x": 200.0 * draw("wx", key), "y": 200.0 * draw("wy", key)})


def event_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """General points: value and props.k as place, event type as feature."""
    k = F.get_json_object("props", "$.k").cast("double")
    rows = table(spark, sf_dir, "events").where("value < 100")
    return rows.select(F.col("event_id").cast("string").alias("object_id"), F.col("event_type").alias("feature"), F.lit("any").alias("role"), F.col("user_id").cast("string").alias("site_id"), F.col("value").alias("x"), k.alias("y"))


def embedding_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points of the first two components: nearly a null set."""
    rows = table(spark, sf_dir, "embeddings").where("embedding is not null")
    return rows.select(F.col("vec_id").cast("string").alias("object_id"), F.concat(F.lit("L"), F.col("label").cast("string")).alias("feature"), F.lit("any").alias("role"), (100.0 * F.col("embedding")[0].cast("double")).alias("x"), (100.0 * F.col("embedding")[1].cast("double")).alias("y"))


def user_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line objects: each user's event points in order of time."""
    k = F.get_json_object("props", "$.k").cast("double")
    point = F.struct("ts", "event_id", F.struct(F.col("value").alias("x"), k.alias("y")).alias("p"))
    rows = table(spark, sf_dir, "events").where("value < 100").groupBy("user_id").agg(F.array_sort(F.collect_list(point)).alias("path"))
    return rows.select(F.col("user_id").cast("string").alias("object_id"), F.lit("PATH").alias("feature"), F.transform("path", lambda e: e["p"]).alias("ring"))


def nation_squares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Polygon objects: the urban squares, with the region as feature."""
    named = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("zone_id"), F.col("r_name").alias("feature"))
    z = zones(spark, sf_dir).join(named, "zone_id")
    point = lambda x, y: F.struct(F.col(x).alias("x"), F.col(y).alias("y"))
    ring = F.array(point("x0", "y0"), point("x1", "y0"), point("x1", "y1"), point("x0", "y1"), point("x0", "y0"))
    return z.select(F.col("zone_id").cast("string").alias("object_id"), "feature", ring.alias("ring"))


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """tx_id, item, p: orders and part types, with a probability by quantity."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_type").alias("item"))
    return line.join(part, "l_partkey").select(F.col("l_orderkey").alias("tx_id"), "item", (F.col("l_quantity") / 50.0).alias("p"))


def word_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """tx_id, item, p = 1: the distinct words of each document."""
    word = F.explode(F.array_distinct(F.filter(F.split(F.translate("text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), r"[\x20\x09-\x0D]+"), lambda w: w != "")))
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("tx_id"), word.alias("item"), F.lit(1.0).alias("p"))


def role_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("tx_id"), F.col("role").alias("item"), F.lit(1.0).alias("p")).distinct()


def page_sets(spark: SparkSession, sf_dir: str, tags: tuple[str, ...] = ("nav", "script", "article", "table", "form", "style")) -> DataFrame:
    has = F.filter(F.array(*[F.when(F.contains("html", F.lit(f"<{t}")), F.lit(t)) for t in tags]), lambda t: t.isNotNull())
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("tx_id"), F.explode(has).alias("item"), F.lit(1.0).alias("p"))


def octant_normals(daily: DataFrame) -> DataFrame:
    return daily.withColumn("octant", octant(F.col("bearing")))
