"""Queries of the relational operators and functions around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.catalog.methods import ALLT, EM, GRID, _rules, sources_buffered
from coloc.catalog.registry import add, q4, r4
from coloc.catalog.twins import pattern_ctes, rule_ctes, sql, tx_ctes
from coloc.functions import geometry, sqlfuncs
from coloc.operators import baselines, buffers, grids, prevalence, transactions
from coloc.sources import given

t = given.table
RULES2 = {**ALLT, **rule_ctes(d=2)}

# ---- projections, filters, joins ----
add("filter_year_range", lambda s, d: t(s, d, "lineitem").where(F.year("l_shipdate").between(1994, 1996)).groupBy(F.year("l_shipdate").alias("y")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("q")), "SELECT year(l_shipdate)::INTEGER AS y, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem WHERE year(l_shipdate) BETWEEN 1994 AND 1996 GROUP BY ALL")
add("project_objects", lambda s, d: given.event_points(s, d).select("object_id", "feature", "x", "y"), sql("SELECT object_id, feature, x, y FROM event_points"))
add("predicate_mix", lambda s, d: t(s, d, "part").where(F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#3") & F.col("p_size").between(5, 30) & ~F.col("p_type").like("%X%") & F.col("p_name").isNotNull()).select("p_partkey", "p_brand", "p_size"), "SELECT p_partkey, p_brand, p_size FROM part WHERE p_brand IN ('Brand#1', 'Brand#2', 'Brand#3') AND p_size BETWEEN 5 AND 30 AND p_type NOT LIKE '%X%' AND p_name IS NOT NULL")


def join_emissions(s, d):
    e = given.emissions(s, d).join(given.facilities(s, d).select("site_id", "nation"), "site_id")
    return e.join(F.broadcast(t(s, d, "nation")), F.col("nation") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


add("join_emissions", join_emissions, sql("SELECT n_name, count(*) AS n FROM emissions e JOIN facilities f USING (site_id) JOIN nation ON n_nationkey = f.nation GROUP BY ALL"))
add("join_sort_merge", lambda s, d: t(s, d, "lineitem").hint("merge").join(t(s, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
add("join_shuffle_hash", lambda s, d: t(s, d, "orders").join(t(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL")
add("range_join_neighbours", lambda s, d: baselines.neighbours(given.emissions(s, d), 2.0).groupBy("f1", "f2").agg(F.count(F.lit(1)).alias("n")), sql("SELECT a.feature AS f1, b.feature AS f2, count(*) AS n FROM emissions a JOIN emissions b ON a.feature < b.feature AND power(a.x - b.x, 2) + power(a.y - b.y, 2) <= 4.0 GROUP BY ALL"))


def asof_wind(s, d):
    """The last reading of the same station before each error event: a window over the union, no range join."""
    e = t(s, d, "events")
    key = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "error", F.col("value")), ignorenulls=True).over(key)
    return e.withColumn("before", last).where("event_type = 'error'").select("event_id", F.coalesce(r4("before"), F.lit(-1.0)).alias("before"))


add("asof_wind", asof_wind, f"SELECT event_id, {q4('coalesce(before, -1.0)', 'before')} FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type <> 'error' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events) WHERE event_type = 'error'")


def interval_join(s, d):
    """Purchases within a day after an error of the same user: bucketed by day on both sides."""
    e = t(s, d, "events").withColumn("day", F.unix_date(F.to_date("ts")))
    a = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.explode(F.array("day", F.col("day") + 1)).alias("day"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), "day")
    return a.join(b, ["user_id", "day"]).where((F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 1 DAY"))).select("a", "b")


add("interval_join", interval_join, "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y USING (user_id) WHERE x.event_type = 'error' AND y.event_type = 'purchase' AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 1 DAY")
add("semi_survivors", lambda s, d: given.emissions(s, d).join(_rules(s, d).where("size = 1 and exp_conf > 0.01").select(F.col("key").alias("feature")), "feature", "left_semi").select("object_id"), sql("SELECT object_id FROM emissions WHERE feature IN (SELECT key FROM rules WHERE size = 1 AND exp_conf > 0.01)", **RULES2))
add("anti_isolated", lambda s, d: given.emissions(s, d).join(baselines.neighbours(given.emissions(s, d), 2.0).select(F.explode(F.array("o1", "o2")).alias("object_id")).distinct(), "object_id", "left_anti").select("object_id"), sql("SELECT object_id FROM emissions a WHERE NOT EXISTS (SELECT 1 FROM emissions b WHERE a.feature <> b.feature AND power(a.x - b.x, 2) + power(a.y - b.y, 2) <= 4.0)"))
TXE = {**EM, **tx_ctes("em_b", GRID)}
etx = lambda s, d: transactions.build(sources_buffered(s, d), GRID)


def pair_support(s, d):
    tx = etx(s, d)
    a, b = tx.select("gi", "gj", F.col("feature").alias("f1")), tx.select("gi", "gj", F.col("feature").alias("f2"))
    return a.join(b, ["gi", "gj"]).where("f1 < f2").groupBy("f1", "f2").agg(F.count(F.lit(1)).alias("sup"))


add("pair_support", pair_support, sql("SELECT a.feature AS f1, b.feature AS f2, count(*) AS sup FROM tx a JOIN tx b USING (gi, gj) WHERE a.feature < b.feature GROUP BY ALL", **TXE))

# ---- aggregation ----
by_region = lambda s, d: etx(s, d).withColumns({"zx": F.floor(F.col("gi") / 40), "zy": F.floor(F.col("gj") / 40)})
ZONED = {**TXE, "zt": "SELECT *, floor(gi / 40)::BIGINT AS zx, floor(gj / 40)::BIGINT AS zy FROM tx"}
_agg = lambda: (F.count(F.lit(1)).alias("n"), F.round(F.sum("p").cast("double"), 4).alias("exp_sup"))
_asql = f"count(*) AS n, {q4('sum(p)', 'exp_sup')}"
add("support_cube", lambda s, d: by_region(s, d).cube("zx", "feature").agg(*_agg()).fillna({"zx": -1, "feature": "all"}), sql(f"SELECT coalesce(zx, -1) AS zx, coalesce(feature, 'all') AS feature, n, exp_sup FROM (SELECT zx, feature, {_asql} FROM zt GROUP BY CUBE (zx, feature))", **ZONED))
add("support_rollup", lambda s, d: by_region(s, d).rollup("zx", "zy", "feature").agg(*_agg()).fillna({"zx": -1, "zy": -1, "feature": "all"}), sql(f"SELECT coalesce(zx, -1) AS zx, coalesce(zy, -1) AS zy, coalesce(feature, 'all') AS feature, n, exp_sup FROM (SELECT zx, zy, feature, {_asql} FROM zt GROUP BY ROLLUP (zx, zy, feature))", **ZONED))


def grouping_sets(s, d):
    by_region(s, d).createOrReplaceTempView("zoned_items")
    return s.sql("SELECT coalesce(zx, -1) AS zx, coalesce(feature, 'all') AS feature, count(*) AS n, round(cast(sum(p) AS DOUBLE), 4) AS exp_sup FROM zoned_items GROUP BY GROUPING SETS ((zx), (feature), ())")


add("support_grouping_sets", grouping_sets, sql(f"SELECT coalesce(zx, -1) AS zx, coalesce(feature, 'all') AS feature, n, exp_sup FROM (SELECT zx, feature, {_asql} FROM zt GROUP BY GROUPING SETS ((zx), (feature), ()))", **ZONED))
add("p_summary", lambda s, d: _rules(s, d).where("exp_conf is not null").groupBy("size").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("exp_conf"), 4).alias("mean"), F.round(F.stddev("exp_conf"), 4).alias("sd"), F.round(F.percentile("exp_conf", 0.5), 4).alias("median")), sql("SELECT size, count(*) AS n, round(avg(exp_conf), 4) AS mean, round(stddev(exp_conf), 4) AS sd, round(quantile_cont(exp_conf, 0.5), 4) AS median FROM rules WHERE exp_conf IS NOT NULL GROUP BY size", **RULES2))
add("decimal_sum", lambda s, d: transactions.from_table(given.baskets(s, d)).groupBy("feature").agg(F.sum("p").cast("string").alias("exp_sup")), sql("SELECT feature, sum(p)::DECIMAL(28,12)::VARCHAR AS exp_sup FROM (SELECT tx_id, item AS feature, max(p)::DECIMAL(18,12) AS p FROM baskets GROUP BY ALL) GROUP BY feature"))
add("approx_features", lambda s, d: etx(s, d).groupBy("gi").agg(F.approx_count_distinct("feature").alias("n")))

# ---- windows ----
order = lambda: W.partitionBy("size").orderBy(F.desc("sup"), "key")
ranked = lambda s, d: _rules(s, d).select("key", "size", "sup")
add("rank_rules", lambda s, d: ranked(s, d).select("key", "size", F.row_number().over(order()).alias("rn"), F.rank().over(W.partitionBy("size").orderBy(F.desc("sup"))).alias("rk"), F.dense_rank().over(W.partitionBy("size").orderBy(F.desc("sup"))).alias("dr"), F.ntile(4).over(order()).alias("nt"), F.round(F.percent_rank().over(W.partitionBy("size").orderBy(F.desc("sup"))), 4).alias("pr")), sql("SELECT key, size, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 4) AS pr FROM rules WINDOW w AS (PARTITION BY size ORDER BY sup DESC, key), v AS (PARTITION BY size ORDER BY sup DESC)", **RULES2))
add("topk_rules", lambda s, d: ranked(s, d).orderBy(F.desc("sup"), "key").limit(10), sql("SELECT key, size, sup FROM rules ORDER BY sup DESC, key LIMIT 10", **RULES2))
add("topk_per_size", lambda s, d: ranked(s, d).withColumn("k", F.row_number().over(order())).where("k <= 3"), sql("SELECT key, size, sup, row_number() OVER (PARTITION BY size ORDER BY sup DESC, key) AS k FROM rules QUALIFY k <= 3", **RULES2))
day = lambda s, d: given.wind_daily(s, d).groupBy(F.col("day").cast("string").alias("day")).agg(F.count(F.lit(1)).alias("n"), F.sum("speed").alias("v"))
DAY = {"dd": "SELECT day::VARCHAR AS day, day AS dt, count(*) AS n, sum(speed) AS v FROM daily GROUP BY ALL"}
add("lag_lead_days", lambda s, d: day(s, d).select("day", (F.col("n") - F.lag("n", 1, 0).over(W.orderBy("day"))).alias("change"), F.lead("n", 1, 0).over(W.orderBy("day")).alias("next"), F.first("n").over(W.orderBy("day")).alias("first")), sql("SELECT day, n - lag(n, 1, 0) OVER w AS change, lead(n, 1, 0) OVER w AS next, first_value(n) OVER w AS first FROM dd WINDOW w AS (ORDER BY day)", **DAY))
add("running_exceed", lambda s, d: day(s, d).select("day", F.sum("n").over(W.orderBy("day").rowsBetween(W.unboundedPreceding, 0)).alias("total")), sql("SELECT day, sum(n) OVER (ORDER BY day ROWS UNBOUNDED PRECEDING)::BIGINT AS total FROM dd", **DAY))
add("wind_moving_mean", lambda s, d: day(s, d).select("day", F.round(F.avg("v").over(W.orderBy("day").rowsBetween(-2, 0)), 3).alias("m3"), F.round(F.sum("v").over(W.orderBy(F.unix_date(F.to_date("day"))).rangeBetween(-7, 0)), 2).alias("week")), sql("SELECT day, round(avg(v) OVER (ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 3) AS m3, round(sum(v) OVER (ORDER BY dt RANGE BETWEEN INTERVAL 7 DAY PRECEDING AND CURRENT ROW), 2) AS week FROM dd", **DAY))

# ---- sets, pivots, subqueries, samples ----
one = lambda s, d: given.emissions(s, d).where("amount > 100").select("site_id")
two = lambda s, d: given.emissions(s, d).where("amount <= 120").select("site_id")
ONE, TWO = "SELECT site_id FROM emissions WHERE amount > 100", "SELECT site_id FROM emissions WHERE amount <= 120"
add("set_intersect", lambda s, d: one(s, d).intersect(two(s, d)), sql(f"{ONE} INTERSECT {TWO}"))
add("set_except", lambda s, d: one(s, d).exceptAll(two(s, d)), sql(f"{ONE} EXCEPT ALL {TWO}"))
add("set_union", lambda s, d: one(s, d).union(two(s, d)).distinct(), sql(f"{ONE} UNION {TWO}"))
add("overlap_pivot", lambda s, d: etx(s, d).groupBy("gi").pivot("n_inst", [1, 2, 3]).agg(F.count(F.lit(1))).select("gi", *[F.coalesce(F.col(f"`{k}`"), F.lit(0)).alias(f"n{k}") for k in (1, 2, 3)]), sql("SELECT gi, count(*) FILTER (n_inst = 1) AS n1, count(*) FILTER (n_inst = 2) AS n2, count(*) FILTER (n_inst = 3) AS n3 FROM tx GROUP BY gi", **TXE))
add("unpivot_supports", lambda s, d: _rules(s, d).select("key", "sup", "sup_lhs").unpivot("key", ["sup", "sup_lhs"], "measure", "value"), sql("SELECT key, 'sup' AS measure, sup AS value FROM rules UNION ALL SELECT key, 'sup_lhs', sup_lhs FROM rules", **RULES2))
add("hash_sample", lambda s, d: given.event_points(s, d).where(F.conv(F.substring(F.md5("object_id"), 1, 4), 16, 10).cast("int") % 10 == 0).select("object_id"), sql("SELECT object_id FROM event_points WHERE ('0x' || substr(md5(object_id), 1, 4))::INTEGER % 10 = 0"))
add("dedup_sites", lambda s, d: given.emissions(s, d).dropDuplicates(["site_id", "x", "y"]).select("site_id", r4("x"), r4("y")), sql(f"SELECT DISTINCT site_id, {q4('x')}, {q4('y')} FROM emissions"))


def sql_mean_conf(s, d):
    _rules(s, d).createOrReplaceTempView("mined_rules")
    return s.sql("WITH seen AS (SELECT * FROM mined_rules WHERE exp_conf > 0) SELECT key, round(exp_conf, 4) AS exp_conf FROM seen WHERE exp_conf >= (SELECT avg(exp_conf) FROM seen)")


add("sql_mean_conf", sql_mean_conf, sql("SELECT key, round(exp_conf, 4) AS exp_conf FROM rules WHERE exp_conf >= (SELECT avg(exp_conf) FROM rules WHERE exp_conf > 0)", **RULES2))


def sql_rules(s, d):
    """Prevalence from SQL with the registered functions, on a temporary view."""
    sqlfuncs.register(s)
    given.emissions(s, d).createOrReplaceTempView("emission_objects")
    return s.sql("SELECT object_id, round(prob_cosine(2D, ln(amount)), 4) AS cosine, round(prob_linear(2D, ln(amount)), 4) AS linear, prob_steps(3D, 5D) AS steps, round(bearing_of(x - 100D, y - 100D), 3) AS bearing, p_value_of(4L, 99L) AS p FROM emission_objects")


add("sql_rules", sql_rules, sql("SELECT object_id, round(cos(pi() * least(1.0, 2.0 / ln(amount))) / 2 + 0.5, 4) AS cosine, round(1 - least(1.0, 2.0 / ln(amount)), 4) AS linear, 0.75::DOUBLE AS steps, round((degrees(atan2(x - 100, y - 100)) + 360) % 360.0, 3) AS bearing, 0.05::DOUBLE AS p FROM emissions"))


def table_functions(s, d):
    sqlfuncs.register(s)
    given.event_points(s, d).createOrReplaceTempView("some_points")
    return s.sql("SELECT gi, gj, count(*) AS n FROM some_points, LATERAL grid_cells(x, y, 1D, 0.5D) GROUP BY gi, gj")


add("udtf_grid_cells", table_functions, sql("SELECT gi, gj, count(*) AS n FROM (SELECT x, y, gi, unnest(generate_series(ceil((y - 1) / 0.5)::BIGINT, floor((y + 1) / 0.5)::BIGINT)) AS gj FROM (SELECT x, y, unnest(generate_series(ceil((x - 1) / 0.5)::BIGINT, floor((x + 1) / 0.5)::BIGINT)) AS gi FROM event_points)) WHERE power(gi * 0.5 - x, 2) + power(gj * 0.5 - y, 2) <= 1.0 GROUP BY ALL"))


def itemsets_of(s, d):
    sqlfuncs.register(s)
    given.role_sets(s, d).groupBy("tx_id").agg(F.collect_list("item").alias("items")).createOrReplaceTempView("role_arrays")
    return s.sql("SELECT key, size, count(*) AS sup FROM role_arrays, LATERAL itemsets_of(items, 2) GROUP BY key, size")


add("udtf_itemsets_of", itemsets_of, sql("SELECT key, size, sup FROM pats", tx="SELECT DISTINCT conv_id AS tx_id, role AS feature, 1.0::DECIMAL(18,12) AS p FROM conversations", **pattern_ctes(d=2, on="tx_id")))

# ---- scalar functions ----
add("math_functions", lambda s, d: given.emissions(s, d).select("object_id", *[F.round(c, 5).alias(n) for n, c in (("ln", F.ln("amount")), ("lg", F.log1p("amount")), ("sq", F.sqrt("amount")), ("pw", F.pow("amount", F.lit(0.3))), ("hy", F.hypot("x", "y")), ("at", F.atan2("x", "y")), ("ex", F.exp(-F.col("x") / 50)), ("pm", F.pmod(F.col("x") - 100, F.lit(7.0))), ("gl", F.greatest("x", "y") - F.least("x", "y")))], F.floor("x").alias("fl"), F.ceil("y").alias("ce")), sql("SELECT object_id, round(ln(amount), 5) AS ln, round(ln(1 + amount), 5) AS lg, round(sqrt(amount), 5) AS sq, round(power(amount, 0.3), 5) AS pw, round(sqrt(x * x + y * y), 5) AS hy, round(atan2(x, y), 5) AS at, round(exp(-x / 50), 5) AS ex, round(((x - 100) % 7.0 + 7.0) % 7.0, 5) AS pm, round(greatest(x, y) - least(x, y), 5) AS gl, floor(x)::BIGINT AS fl, ceil(y)::BIGINT AS ce FROM emissions"))
add("string_functions", lambda s, d: t(s, d, "part").select("p_partkey", F.concat_ws("-", "p_brand", "p_type").alias("k"), F.lower("p_name").alias("l"), F.substring("p_brand", 7, 2).alias("b"), F.md5("p_name").alias("m"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("z"), F.regexp_replace("p_brand", "[0-9]+", "n").alias("r"), F.split("p_brand", "#")[1].alias("s")), "SELECT p_partkey, p_brand || '-' || p_type AS k, lower(p_name) AS l, substr(p_brand, 7, 2) AS b, md5(p_name) AS m, lpad(p_size::VARCHAR, 4, '0') AS z, regexp_replace(p_brand, '[0-9]+', 'n', 'g') AS r, string_split(p_brand, '#')[2] AS s FROM part")
add("date_functions", lambda s, d: t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("t"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("n")), "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS n FROM orders")
_arr = lambda s, d: given.user_paths(s, d).select("object_id", F.transform("ring", lambda q: F.floor(q["y"]).cast("int")).alias("a"))
add("array_functions", lambda s, d: _arr(s, d).select("object_id", F.size("a").alias("n"), F.size(F.array_distinct("a")).alias("u"), F.array_max("a").alias("hi"), F.aggregate("a", F.lit(0), lambda x, y: x + y).alias("sum"), F.size(F.filter("a", lambda v: v > 50)).alias("big"), F.exists("a", lambda v: v == 0).alias("zero"), F.forall("a", lambda v: v >= 0).alias("pos"), F.array_contains("a", 7).alias("seven"), F.array_join(F.slice(F.sort_array("a"), 1, 3), ",").alias("low")), sql("SELECT object_id, len(a)::INTEGER AS n, len(list_distinct(a))::INTEGER AS u, list_max(a) AS hi, list_sum(a)::INTEGER AS sum, len(list_filter(a, lambda v: v > 50))::INTEGER AS big, list_contains(a, 0) AS zero, true AS pos, list_contains(a, 7) AS seven, array_to_string(list_sort(a)[1:3], ',') AS low FROM (SELECT object_id, list_transform(ring, lambda q: floor(q.y)::INTEGER) AS a FROM paths)"))
add("map_functions", lambda s, d: transactions.as_map(transactions.to_wide(etx(s, d))).select("gi", "gj", F.size(F.map_keys("items")).alias("n"), F.round(F.aggregate(F.map_values("items"), F.lit(0.0), lambda a, b: F.greatest(a, b)), 4).alias("top"), F.size(F.map_filter("items", lambda k, v: v > 0.5)).alias("strong")), sql("SELECT gi, gj, count(*)::INTEGER AS n, round(max(p)::DOUBLE, 4) AS top, (count(*) FILTER (p > 0.5))::INTEGER AS strong FROM tx GROUP BY ALL", **TXE))
add("json_functions", lambda s, d: t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.get_json_object(F.to_json(F.struct(F.col("user_id").alias("u"))), "$.u").alias("u")), "SELECT event_id, (props->>'$.k')::INTEGER AS k, (props->>'$.k')::INTEGER AS k2, user_id::VARCHAR AS u FROM events")
add("conditional_functions", lambda s, d: _rules(s, d).select("key", F.round(F.try_divide("sup", "sup_lhs"), 4).alias("r"), F.coalesce(F.nullif(F.col("sup"), F.lit(0)), F.lit(-1)).alias("n"), F.when(F.col("sup") > 10, "many").otherwise("few").alias("c")), sql("SELECT key, round(sup::DOUBLE / nullif(sup_lhs, 0), 4) AS r, coalesce(nullif(sup, 0), -1) AS n, CASE WHEN sup > 10 THEN 'many' ELSE 'few' END AS c FROM rules", **RULES2))
add("tile_bits", lambda s, d: etx(s, d).select("gi", "gj", "feature").withColumn("tile", F.shiftleft(F.floor(F.col("gi") / 64), 16).bitwiseOR(F.floor(F.col("gj") / 64))).groupBy("tile").agg(F.count(F.lit(1)).alias("n"), F.bit_count(F.bit_or(F.pow(F.lit(2.0), F.col("gi") % 8).cast("long"))).alias("bits")), sql("SELECT ((floor(gi / 64)::BIGINT << 16) | floor(gj / 64)::BIGINT) AS tile, count(*) AS n, bit_count(bit_or(1::BIGINT << (gi % 8)::INTEGER))::INTEGER AS bits FROM tx GROUP BY ALL", **TXE))


def wkt_parse(s, d):
    """Places of events written as points, lines, polygons and a kind that is not known, and read again: objects, points and the range of the last x by kind."""
    rows = given.event_points(s, d).where("y is not null")
    p = F.concat_ws(" ", F.col("x").cast("string"), F.col("y").cast("string"))
    k = F.pmod(F.col("object_id").cast("long"), F.lit(4))
    text = F.when(k == 0, F.concat(F.lit("POINT("), p, F.lit(")"))).when(k == 1, F.concat(F.lit("LINESTRING (0 0, 3 4, "), p, F.lit(")"))).when(k == 2, F.concat(F.lit("POLYGON((0 0, 4 0, "), p, F.lit(", 0 4, 0 0))"))).otherwise(F.concat(F.lit("CURVE("), p, F.lit(")")))
    got = rows.select(geometry.parse_wkt(text).alias("g")).select(F.coalesce(F.col("g.kind"), F.lit("none")).alias("kind"), F.coalesce(F.size("g.ring"), F.lit(0)).alias("n"), F.coalesce(F.element_at("g.ring", -1)["x"], F.lit(0.0)).alias("x"))
    return got.groupBy("kind").agg(F.count(F.lit(1)).alias("n_objects"), F.sum(F.greatest("n", F.lit(0))).alias("n_points"), F.min("x").alias("low_x"), F.max("x").alias("high_x"))


add("wkt_parse", wkt_parse, sql("SELECT kind, count(*) AS n_objects, sum(n)::BIGINT AS n_points, min(lx) AS low_x, max(lx) AS high_x FROM (SELECT ['point', 'line', 'polygon', 'none'][k + 1] AS kind, [1, 3, 5, 0][k + 1] AS n, CASE WHEN k < 2 THEN x ELSE 0.0 END AS lx FROM (SELECT x, object_id::BIGINT % 4 AS k FROM event_points WHERE y IS NOT NULL)) GROUP BY kind"))

# ---- scans ----
WIDE = grids.Grid(1.0, (-120.0, -120.0, 120.0, 120.0))
add("scan_profile", lambda s, d: t(s, d, "lineitem").where("l_quantity > 40").select("l_orderkey", "l_quantity").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q")), "SELECT count(*) AS n, sum(l_quantity) AS q FROM lineitem WHERE l_quantity > 40")


def io_roundtrip(s: SparkSession, d: str) -> DataFrame:
    """Emissions through CSV, JSON and ORC with an explicit schema, in the shared folder."""
    from coloc.sources.files import roundtrip

    return roundtrip(given.emissions(s, d).select("object_id", "feature", "x", "y", "amount"))


add("io_roundtrip", io_roundtrip, sql("SELECT f AS format, count(*) AS n, round(sum(amount), 3) AS amount FROM emissions, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS f) GROUP BY f"))


def sink_partitioned(s: SparkSession, d: str) -> DataFrame:
    from coloc.sources.files import partitioned

    return partitioned(etx(s, d).withColumn("tile", F.floor(F.col("gi") / 64)), "tile").groupBy("tile").agg(F.count(F.lit(1)).alias("n"))


add("sink_partitioned", sink_partitioned, sql("SELECT floor(gi / 64)::BIGINT AS tile, count(*) AS n FROM tx GROUP BY ALL", **TXE))
add("exp_sup_embedding_points", lambda s, d: prevalence.supports(transactions.to_wide(transactions.build(buffers.fixed(given.embedding_points(s, d), 1.0), WIDE)), 2).select("key", "sup", r4("exp_sup")), sql(f"SELECT key, sup, {q4('exp_sup')} FROM pats", eb="SELECT *, r AS a, r AS b, x AS cx, y AS cy, 1.0 AS ux, 0.0 AS uy FROM (SELECT *, 1.0 AS r FROM embedding_points)", **tx_ctes("eb", WIDE), **pattern_ctes(d=2)))
