"""Queries of the methods: buffers, wind, grids, transactions, prevalence, simulations, baselines, measures."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.catalog.registry import add, q4, r4
from coloc.catalog.twins import CIRCLE, D, R, pattern_ctes, rule_ctes, sql, survivors, tx_ctes
from coloc.functions import angles, geometry
from coloc.functions import decay as decays
from coloc.functions.tests_of_chance import most_exceedances, p_value
from coloc.operators import baselines, buffers, candidates, grids, itemsets, measures, prevalence, randomize, significance, transactions, winds
from coloc.plans import miner
from coloc.plans.config import MinerConfig
from coloc.sources import given, synthetic
from coloc.sources.given import EFFECT, REGION
from coloc.sources.staging import staged

GRID = grids.Grid(1.0, REGION)
POINTS = grids.Grid(0.5, (0.0, 0.0, 100.0, 100.0))
CASE_RADIUS = 3.0
MOST = most_exceedances(0.05, R)
LOG = f"SELECT *, {CIRCLE} FROM (SELECT *, ln(amount) AS r FROM {{}} WHERE amount > 0) WHERE r > 0"
CASES = f"SELECT *, {CIRCLE} FROM (SELECT *, 3.0 AS r FROM {{}})"
BUF_COLS = ("r", "a", "b", "cx", "cy", "ux", "uy")


def emissions(s, d):
    return given.emissions(s, d)


def sources_buffered(s: SparkSession, d: str) -> DataFrame:
    return buffers.log_amount(given.emissions(s, d))


KEEP = ("object_id", "feature", "x", "y", *BUF_COLS)


def all_buffered(s: SparkSession, d: str, linked: bool = True) -> DataFrame:
    """Emissions by amount and cases by a fixed radius."""
    cases = given.cases_linked(s, d) if linked else given.cases(s, d)
    return sources_buffered(s, d).select(*KEEP).unionByName(buffers.fixed(cases, CASE_RADIUS).select(*KEEP))


def _cols(names: str) -> str:
    return ", ".join(names.split())


ALL_SQL = "SELECT object_id, feature, x, y, r, a, b, cx, cy, ux, uy FROM em_b UNION ALL SELECT object_id, feature, x, y, r, a, b, cx, cy, ux, uy FROM ca_b"
ALL = {"em_b": LOG.format("emissions"), "ca_b": CASES.format("cases_linked"), "objs": ALL_SQL}

# ---- buffers ----


def shown():
    return [r4(c) for c in BUF_COLS]


_shown_sql = ", ".join(q4(c) for c in BUF_COLS)
add("emissions", lambda s, d: given.emissions(s, d).select("object_id", "feature", r4("x"), r4("y"), r4("amount")), sql(f"SELECT object_id, feature, {q4('x')}, {q4('y')}, {q4('amount')} FROM emissions"))
add("rare_feature_filter", lambda s, d: given.drop_rare(given.yearly_amounts(s, d), 5).groupBy("feature").agg(F.countDistinct("site_id").alias("n_sites")), sql("SELECT feature, count(DISTINCT site_id) AS n_sites FROM amounts GROUP BY feature HAVING count(DISTINCT site_id) >= 5"))
add("buffer_fixed", lambda s, d: buffers.fixed(given.cases(s, d), CASE_RADIUS).select("object_id", *shown()), sql(f"SELECT object_id, {_shown_sql} FROM c", c=CASES.format("cases")))


def radii(s, d):
    return given.emissions(s, d).groupBy("feature").agg((F.count(F.lit(1)) / 10.0).alias("r"))


add("buffer_by_feature", lambda s, d: buffers.by_feature(given.emissions(s, d), radii(s, d)).select("object_id", *shown()), sql(f"SELECT object_id, {_shown_sql} FROM b", b=f"SELECT *, {CIRCLE} FROM emissions JOIN (SELECT feature, count(*) / 10.0 AS r FROM emissions GROUP BY feature) USING (feature)"))
add("buffer_log_amount", lambda s, d: sources_buffered(s, d).select("object_id", *shown()), sql(f"SELECT object_id, {_shown_sql} FROM b", b=LOG.format("emissions")))


def growth_compare(s, d):
    e = given.emissions(s, d)
    rows = None
    for fn in ("log", "log1p", "sqrt", "linear"):
        one = measures.buffer_stats(buffers.amount(e, fn)).select(F.lit(fn).alias("fn"), "n", r4("mean_r"), r4("max_r"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


add("buffer_growth_compare", growth_compare, sql(" UNION ALL ".join(f"SELECT '{n}' AS fn, count(*) AS n, {q4(f'avg({e})', 'mean_r')}, {q4(f'max({e})', 'max_r')} FROM emissions WHERE {e} > 0" for n, e in (("log", "ln(amount)"), ("log1p", "ln(1 + amount)"), ("sqrt", "sqrt(amount)"), ("linear", "amount")))))


def tx_show(tx):
    by = [c for c in ("sim_id", "set_id") if c in tx.columns]
    return tx.select(*by, "gi", "gj", "feature", "n_inst", r4("p"))


TX_SQL = f"SELECT gi, gj, feature, n_inst, {q4('p')} FROM tx"
EM = {"em_b": LOG.format("emissions")}
add("buffer_ring", lambda s, d: tx_show(transactions.build(buffers.inner_radius(sources_buffered(s, d), F.col("r") * 0.5), GRID)), sql(TX_SQL, **EM, **{**tx_ctes("em_b", GRID), "tx": "SELECT gi, gj, feature, count(*)::INTEGER AS n_inst, max(p)::DECIMAL(18,12) AS p FROM tx_p WHERE d >= r * 0.5 GROUP BY ALL"}))


def windy(s, d, method="idw"):
    return winds.interpolate(sources_buffered(s, d), given.station_places(winds.normals(given.wind_daily(s, d))), method)


IDW = {
    "near": "SELECT o.object_id, greatest(sqrt((o.x - t.x) * (o.x - t.x) + (o.y - t.y) * (o.y - t.y)), 1e-9) AS dist, u, v FROM em_b o, stations t",
    "idw": "SELECT object_id, sum(power(dist, -2) * u) / sum(power(dist, -2)) AS u, sum(power(dist, -2) * v) / sum(power(dist, -2)) AS v FROM near GROUP BY object_id",
    "wind": "SELECT e.*, i.u AS wu, i.v AS wv, sqrt(i.u * i.u + i.v * i.v) AS speed, (degrees(atan2(i.u, i.v)) + 360.0) % 360.0 AS bearing FROM em_b e JOIN idw i USING (object_id)",
}


def ellipse_sql(source: str = "wind", gamma: str = "0.3", k: float = 0.5) -> dict[str, str]:
    return {
        "el1": f"SELECT object_id, feature, x, y, r, r + {gamma} * speed AS a, sin(radians(bearing)) AS ux, cos(radians(bearing)) AS uy FROM {source}",
        "el2": "SELECT *, r * r / a AS b FROM el1",
        "el": f"SELECT *, x + {k} * sqrt(greatest(a * a - b * b, 0.0)) * ux AS cx, y + {k} * sqrt(greatest(a * a - b * b, 0.0)) * uy AS cy FROM el2",
    }


W = {**EM, **IDW}
add("buffer_ellipse", lambda s, d: buffers.ellipse(windy(s, d)).select("object_id", *shown()), sql(f"SELECT object_id, {_shown_sql} FROM el", **W, **ellipse_sql()))
add("buffer_ellipse_calm", lambda s, d: buffers.ellipse(sources_buffered(s, d).withColumns({"speed": F.lit(0.0), "bearing": F.lit(90.0)})).select("object_id", r4("a"), r4("b"), r4("r"), r4("cx"), r4("cy")), sql(f"SELECT object_id, {q4('r', 'a')}, {q4('r', 'b')}, {q4('r')}, {q4('x', 'cx')}, {q4('y', 'cy')} FROM em_b", **EM))
add("buffer_gamma_by_feature", lambda s, d: buffers.ellipse(windy(s, d), buffers.gamma_of(0.3, {"Brand#2": 0.1, "Brand#11": 0.6})).select("object_id", r4("a"), r4("b")), sql(f"SELECT object_id, {q4('a')}, {q4('b')} FROM el", **W, **ellipse_sql(gamma="CASE feature WHEN 'Brand#2' THEN 0.1 WHEN 'Brand#11' THEN 0.6 ELSE 0.3 END")))


def seasonal(s, d):
    w = s.createDataFrame([("winter", 3.0, 0.0), ("summer", 6.0, 135.0)], "season string, speed double, bearing double")
    return transactions.build(buffers.ellipse_multi(sources_buffered(s, d), w), GRID)


add("buffer_seasonal", lambda s, d: tx_show(seasonal(s, d)), sql(TX_SQL, **EM, season="SELECT em_b.*, speed, bearing FROM em_b, (VALUES (3.0, 0.0), (6.0, 135.0)) AS t(speed, bearing)", **ellipse_sql("season"), **tx_ctes("el", GRID)))
for _name, _k in buffers.SOURCE_AT.items():
    add(f"ellipse_centre_{_name}", lambda s, d, n=_name: buffers.ellipse(windy(s, d), source_at=n).select("object_id", r4("cx"), r4("cy")), sql(f"SELECT object_id, {q4('cx')}, {q4('cy')} FROM el", **W, **ellipse_sql(k=_k)))
add("buffer_stats", lambda s, d: measures.buffer_stats(sources_buffered(s, d)).select("n", r4("mean_r"), r4("min_r"), r4("max_r"), r4("mean_area")), sql(f"SELECT count(*) AS n, {q4('avg(r)', 'mean_r')}, {q4('min(r)', 'min_r')}, {q4('max(r)', 'max_r')}, {q4('avg(pi() * r * r)', 'mean_area')} FROM em_b", **EM))

# ---- extended objects ----
COARSE = grids.Grid(2.0, (0.0, 0.0, 200.0, 200.0))
LINE_GRID = grids.Grid(4.0, (0.0, 0.0, 100.0, 100.0))
add("line_buffer", lambda s, d: tx_show(transactions.extended(given.user_paths(s, d), LINE_GRID, 3.0, "line")), sql(TX_SQL, **{
    "lines": "SELECT * FROM paths",
    "segs": "SELECT object_id, feature, ring[i] AS p, ring[least(i + 1, len(ring))] AS q FROM (SELECT *, unnest(generate_series(1, greatest(len(ring) - 1, 1))) AS i FROM lines)",
    "gp": "SELECT gi, gj, gi * 4.0 AS gx, gj * 4.0 AS gy FROM (SELECT unnest(generate_series(0, 25)) AS gi), (SELECT unnest(generate_series(0, 25)) AS gj)",
    "tt": "SELECT s.*, g.*, (q.x - p.x) AS dx, (q.y - p.y) AS dy FROM segs s, gp g",
    "t2": "SELECT *, CASE WHEN dx * dx + dy * dy > 0 THEN greatest(0.0, least(1.0, ((gx - p.x) * dx + (gy - p.y) * dy) / (dx * dx + dy * dy))) ELSE 0.0 END AS t FROM tt",
    "dd": "SELECT object_id, feature, gi, gj, min(sqrt(power(gx - (p.x + t * dx), 2) + power(gy - (p.y + t * dy), 2))) AS d FROM t2 GROUP BY ALL HAVING d <= 3.0 + 1e-9",
    "tx": "SELECT gi, gj, feature, count(*)::INTEGER AS n_inst, max(cos(pi() * least(1.0, d / 3.0)) / 2.0 + 0.5)::DECIMAL(18,12) AS p FROM dd GROUP BY ALL",
}))
add("polygon_buffer", lambda s, d: tx_show(transactions.extended(given.nation_squares(s, d), COARSE, 5.0, "polygon")), sql(TX_SQL, **{
    "gp": "SELECT gi, gj, gi * 2.0 AS gx, gj * 2.0 AS gy FROM (SELECT unnest(generate_series(0, 100)) AS gi), (SELECT unnest(generate_series(0, 100)) AS gj)",
    "dd": "SELECT feature, gi, gj, sqrt(power(greatest(x0 - gx, gx - x1, 0.0), 2) + power(greatest(y0 - gy, gy - y1, 0.0), 2)) AS d FROM squares, gp WHERE d <= 5.0 + 1e-9",
    "tx": "SELECT gi, gj, feature, count(*)::INTEGER AS n_inst, max(cos(pi() * least(1.0, d / 5.0)) / 2.0 + 0.5)::DECIMAL(18,12) AS p FROM dd GROUP BY ALL",
}))


def mixed(s, d):
    pts = transactions.build(buffers.fixed(given.cases(s, d), CASE_RADIUS), COARSE)
    return transactions.union_merge(pts, transactions.extended(given.nation_squares(s, d), COARSE, 5.0, "polygon"))


_MIXED = {
    "ca_b": CASES.format("cases"), **tx_ctes("ca_b", COARSE, name="txp"),
    "gp": "SELECT gi, gj, gi * 2.0 AS gx, gj * 2.0 AS gy FROM (SELECT unnest(generate_series(0, 100)) AS gi), (SELECT unnest(generate_series(0, 100)) AS gj)",
    "dd": "SELECT feature, gi, gj, sqrt(power(greatest(x0 - gx, gx - x1, 0.0), 2) + power(greatest(y0 - gy, gy - y1, 0.0), 2)) AS d FROM squares, gp WHERE d <= 5.0 + 1e-9",
    "txs": "SELECT gi, gj, feature, count(*)::INTEGER AS n_inst, max(cos(pi() * least(1.0, d / 5.0)) / 2.0 + 0.5)::DECIMAL(18,12) AS p FROM dd GROUP BY ALL",
    "tx": "SELECT * FROM txp UNION ALL SELECT * FROM txs",
}
add("tx_mixed_geometry", lambda s, d: tx_show(mixed(s, d)), sql(TX_SQL, **_MIXED))

# ---- decay ----
for _name in ("cosine", "linear", "steps", "boolean"):
    add(f"decay_{_name}", lambda s, d, n=_name: tx_show(transactions.build(sources_buffered(s, d), GRID, decays.NAMED[n]())), sql(TX_SQL, **EM, **tx_ctes("em_b", GRID, _name)))
add("decay_custom", lambda s, d: tx_show(transactions.build(sources_buffered(s, d), GRID, decays.custom(lambda x, m: F.exp(-x)))), sql(TX_SQL, **EM, **tx_ctes("em_b", GRID, "custom")))
for _name in ("ray", "major", "radius"):
    add(f"decay_ellipse_{_name}", lambda s, d, n=_name: tx_show(transactions.build(buffers.ellipse(windy(s, d)), GRID, dmax=n)), sql(TX_SQL, **W, **ellipse_sql(), **tx_ctes("el", GRID, dmax=_name)))
add("combine_noisy_or", lambda s, d: tx_show(transactions.build(sources_buffered(s, d), GRID, combine="noisy_or")), sql(TX_SQL, **EM, **tx_ctes("em_b", GRID, noisy=True)))

# ---- wind ----
add("wind_normals", lambda s, d: winds.normals(given.wind_daily(s, d)).select("station_id", r4("speed"), "octant", "n_obs"), sql(f"SELECT station_id, {q4('speed')}, octant, n_obs FROM normals"))
add("wind_min_obs", lambda s, d: winds.normals(given.wind_daily(s, d), 60).select("station_id", "n_obs"), sql("SELECT station_id, n_obs FROM normals WHERE n_obs >= 60"))


def prevailing(s, d):
    rows = given.octant_normals(given.wind_daily(s, d)).groupBy("station_id").agg(F.mode("octant", True).alias("octant"))
    return rows.groupBy("octant").agg(F.count(F.lit(1)).alias("n"))


add("wind_prevailing", prevailing, sql("SELECT octant, count(*) AS n FROM modes GROUP BY octant"))


def two_sources(s, d):
    daily = given.wind_daily(s, d)
    return winds.normals(daily.where("station_id % 2 = 0")).unionByName(winds.normals(daily.where("station_id % 2 = 1"))).select("station_id", r4("speed"), "octant")


add("wind_sources_union", two_sources, sql(f"SELECT station_id, {q4('speed')}, octant FROM normals"))
_stations = lambda s, d: given.station_places(winds.normals(given.wind_daily(s, d)))
add("wind_components", lambda s, d: winds.with_components(_stations(s, d)).select("station_id", r4("u"), r4("v"), r4("x"), r4("y")), sql(f"SELECT station_id, {q4('u')}, {q4('v')}, {q4('x')}, {q4('y')} FROM stations"))
add("wind_idw", lambda s, d: windy(s, d).select("object_id", r4("u"), r4("v"), r4("speed")), sql(f"SELECT object_id, {q4('wu', 'u')}, {q4('wv', 'v')}, {q4('speed')} FROM wind", **W))
add("wind_nearest", lambda s, d: windy(s, d, "nearest").select("object_id", r4("u"), r4("v")), sql(f"SELECT object_id, {q4('u')}, {q4('v')} FROM (SELECT o.object_id, u, v FROM em_b o, stations t QUALIFY row_number() OVER (PARTITION BY o.object_id ORDER BY sqrt(power(o.x - t.x, 2) + power(o.y - t.y, 2)), station_id) = 1)", **EM))
add("wind_tps", lambda s, d: windy(s, d, "spline").select("object_id", r4("u"), r4("v"), r4("speed"), r4("bearing")))
add("wind_recompose", lambda s, d: winds.recomposed(winds.with_components(_stations(s, d)).drop("bearing", "speed")).select("station_id", r4("speed"), r4("bearing", "bearing", 3)), sql(f"SELECT station_id, {q4('speed')}, round(CASE WHEN speed = 0 THEN 0 ELSE bearing END, 3) AS bearing FROM stations"))


def quadrants(s, d):
    """n of the daily winds by bearing, and their bearings by both ways back from the components; off the axes, where 0 and 360 are the same."""
    rows = given.wind_daily(s, d).where("bearing is not null").groupBy((F.col("bearing") + 0.7).alias("t")).agg(F.count(F.lit(1)).alias("n"))
    x, y = angles.components(F.lit(2.0), F.col("t"))
    return rows.select(r4("t"), "n", F.round(angles.bearing(x, y), 4).alias("by_atan2"), F.round(angles.bearing_by_quadrant(x, y), 4).alias("by_quadrant"))


add("wind_quadrants", quadrants, sql(f"SELECT {q4('bearing + 0.7', 't')}, count(*) AS n, {q4('bearing + 0.7', 'by_atan2')}, {q4('bearing + 0.7', 'by_quadrant')} FROM daily WHERE bearing IS NOT NULL GROUP BY bearing"))
add("wind_naive_angle", lambda s, d: winds.naive_angle(sources_buffered(s, d), _stations(s, d)).select("object_id", r4("bearing")), sql(f"SELECT object_id, {q4('avg(bearing)', 'bearing')} FROM (SELECT o.object_id, t.bearing FROM em_b o, stations t QUALIFY row_number() OVER (PARTITION BY o.object_id ORDER BY sqrt(power(o.x - t.x, 2) + power(o.y - t.y, 2)), station_id) <= 2) GROUP BY object_id", **EM))

# ---- grids ----
add("grid_bbox", lambda s, d: given.emissions(s, d).agg(*[F.round(f(c), 4).alias(n) for f, c, n in ((F.min, "x", "x0"), (F.min, "y", "y0"), (F.max, "x", "x1"), (F.max, "y", "y1"))]), sql("SELECT round(min(x), 4) AS x0, round(min(y), 4) AS y0, round(max(x), 4) AS x1, round(max(y), 4) AS y1 FROM emissions"))
add("grid_points", lambda s, d: grids.points(s, grids.from_objects(given.event_points(s, d), 2.0)), sql("SELECT gi, gj, gi * 2.0::DOUBLE AS gx, gj * 2.0::DOUBLE AS gy FROM (SELECT *, unnest(generate_series(j0, j1)) AS gj FROM (SELECT *, unnest(generate_series(i0, i1)) AS gi FROM box))", box="SELECT ceil(min(x) / 2.0 - 1e-9)::BIGINT AS i0, floor(max(x) / 2.0 + 1e-9)::BIGINT AS i1, ceil(min(y) / 2.0 - 1e-9)::BIGINT AS j0, floor(max(y) / 2.0 + 1e-9)::BIGINT AS j1 FROM event_points"))


def geodesic_points(s, d):
    """A grid of 10 km over the places of events, read as hundredths of degrees east and north of a corner."""
    at = given.event_points(s, d).select((F.col("x") / 100 - 114.0).alias("x"), (F.col("y") / 100 + 49.0).alias("y"))
    return grids.points(s, grids.from_objects(at, 10.0, "geodesic")).select("gi", "gj", r4("gx"), r4("gy"))


add("grid_geodesic", geodesic_points, sql(f"""SELECT gi, gj, {q4('x0 + gi * dlon', 'gx')}, {q4('gy')} FROM (SELECT *, unnest(generate_series(0, floor((x1 - x0) / dlon)::BIGINT)) AS gi FROM
    (SELECT *, y0 + gj * (10.0 / 111.32) AS gy, 10.0 / (111.32 * cos(radians(y0 + gj * (10.0 / 111.32)))) AS dlon FROM (SELECT *, unnest(generate_series(0, floor((y1 - y0) * 111.32 / 10.0)::BIGINT)) AS gj FROM box)))""", box="SELECT min(x / 100 - 114.0) AS x0, min(y / 100 + 49.0) AS y0, max(x / 100 - 114.0) AS x1, max(y / 100 + 49.0) AS y1 FROM event_points"))
add("grid_suggest", lambda s, d: grids.suggest_step(sources_buffered(s, d)).select(r4("step")), sql(f"SELECT {q4('avg(r) / 4.0', 'step')} FROM em_b", **EM))
SHIFTED = grids.shift(GRID, 0.5, 0.25)
add("grid_shift", lambda s, d: tx_show(transactions.build(sources_buffered(s, d), SHIFTED)), sql(TX_SQL, **EM, **tx_ctes("em_b", SHIFTED)))

# ---- transactions ----
EV = {"ev_b": f"SELECT *, {CIRCLE} FROM (SELECT *, 1.0 AS r FROM event_points)"}
events_buffered = lambda s, d: buffers.fixed(given.event_points(s, d), 1.0)
add("tx_uncertain_long", lambda s, d: tx_show(transactions.build(events_buffered(s, d), POINTS)), sql(TX_SQL, **EV, **tx_ctes("ev_b", POINTS)))
add("tx_certain_long", lambda s, d: tx_show(transactions.build(events_buffered(s, d), POINTS, mode="certain")), sql(TX_SQL, **EV, **tx_ctes("ev_b", POINTS, "boolean")))
add("tx_bruteforce", lambda s, d: tx_show(transactions.build(buffers.fixed(given.cases(s, d), CASE_RADIUS), COARSE, strategy="cross")), sql(TX_SQL, ca_b=CASES.format("cases"), **tx_ctes("ca_b", COARSE)))
add("tx_tiled", lambda s, d: tx_show(transactions.build(all_buffered(s, d), GRID, strategy="tiled", tile=32)), sql(TX_SQL, **ALL, **tx_ctes("objs", GRID)))
add("tx_wide", lambda s, d: transactions.to_wide(transactions.build(sources_buffered(s, d), GRID)).select("gi", "gj", F.array_join(F.transform("items", lambda i: i["f"]), ";").alias("items"), F.size("items").alias("n")), sql("SELECT gi, gj, string_agg(feature, ';' ORDER BY feature) AS items, count(*)::INTEGER AS n FROM tx GROUP BY ALL", **EM, **tx_ctes("em_b", GRID)))
add("tx_with_empty", lambda s, d: transactions.with_empty(transactions.build(sources_buffered(s, d), COARSE), COARSE), sql("SELECT g.gi, g.gj, count(feature) AS n_features FROM (SELECT gi, gj FROM (SELECT unnest(generate_series(0, 100)) AS gi), (SELECT unnest(generate_series(0, 100)) AS gj)) g LEFT JOIN tx ON tx.gi = g.gi AND tx.gj = g.gj GROUP BY ALL", **EM, **tx_ctes("em_b", COARSE)))
add("tx_from_baskets", lambda s, d: transactions.from_table(given.baskets(s, d)).select("tx_id", "feature", "n_inst", r4("p")), sql(f"SELECT tx_id, item AS feature, count(*)::INTEGER AS n_inst, {q4('max(p)', 'p')} FROM baskets GROUP BY ALL"))
WORDS = {
    "ww": "SELECT doc_id AS tx_id, unnest(list_distinct(list_filter(string_split_regex(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda w: w <> ''))) AS item FROM documents",
    "wsets": "SELECT DISTINCT tx_id, item AS feature, 1.0::DECIMAL(18,12) AS p FROM ww",
}
add("tx_from_documents", lambda s, d: transactions.from_table(given.word_sets(s, d)).select("tx_id", "feature"), sql("SELECT tx_id, feature FROM wsets", **WORDS))
add("tx_stats", lambda s, d: measures.tx_stats(transactions.build(sources_buffered(s, d), GRID)).select("n_transactions", r4("mean_features"), "max_features"), sql(f"SELECT count(*) AS n_transactions, {q4('avg(s)', 'mean_features')}, max(s) AS max_features FROM (SELECT count(*) AS s FROM tx GROUP BY gi, gj)", **EM, **tx_ctes("em_b", GRID)))


def work_counts(s, d):
    tx = transactions.build(events_buffered(s, d), POINTS)
    return measures.work(tx, transactions.to_wide(tx), 2)


add("work_counts", work_counts, sql("SELECT (SELECT sum(n_inst)::BIGINT FROM tx) AS n_cells, (SELECT count(*) FROM tx) AS n_items, (SELECT count(*) FROM (SELECT DISTINCT gi, gj FROM tx)) AS n_transactions, (SELECT sum(sup)::BIGINT FROM pats) AS n_subsets", **EV, **tx_ctes("ev_b", POINTS), **pattern_ctes()))

# ---- candidates and prevalence ----
features = lambda s, d: given.emissions(s, d).select("feature").distinct()
add("candidates_patterns", lambda s, d: candidates.enumerate_patterns(features(s, d), 3).select("key", "size"), sql("SELECT feature AS key, 1 AS size FROM f UNION ALL SELECT a.feature || '+' || b.feature, 2 FROM f a, f b WHERE a.feature < b.feature UNION ALL SELECT a.feature || '+' || b.feature || '+' || c.feature, 3 FROM f a, f b, f c WHERE a.feature < b.feature AND b.feature < c.feature", f="SELECT DISTINCT feature FROM emissions"))


def candidate_counts(s, d):
    """Patterns of up to three part sizes, and of up to three brands, by enumeration."""
    rows = None
    for column in ("p_size", "p_brand"):
        names = given.table(s, d, "part").select(F.col(column).cast("string").alias("feature")).where("feature is not null").distinct()
        one = candidates.enumerate_patterns(names, 3).agg(F.count(F.when(F.col("size") == 1, 1)).cast("int").alias("n_features"), F.count(F.lit(1)).alias("n_candidates"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


add("candidate_counts", candidate_counts, "SELECT n::INTEGER AS n_features, (n + n * (n - 1) // 2 + n * (n - 1) * (n - 2) // 6)::BIGINT AS n_candidates FROM (SELECT count(DISTINCT p_size) AS n FROM part UNION ALL SELECT count(DISTINCT p_brand) FROM part) AS t")
add("candidates_rules", lambda s, d: candidates.rules_to(EFFECT, features(s, d), 2).select("key", F.array_join("rhs", "+").alias("rhs"), "size"), sql("SELECT feature AS key, 'CASE' AS rhs, 1 AS size FROM f UNION ALL SELECT a.feature || '+' || b.feature, 'CASE', 2 FROM f a, f b WHERE a.feature < b.feature", f="SELECT DISTINCT feature FROM emissions"))
add("candidates_rules_all", lambda s, d: candidates.rules_all(given.event_points(s, d).select("feature").distinct(), 2, 1).select("lhs_key", "rhs_key", "both_key"), sql("SELECT lhs_key, rhs_key, (SELECT string_agg(x, '+' ORDER BY x) FROM (SELECT unnest(list_append(l, rhs_key)) AS x)) AS both_key FROM (SELECT feature AS lhs_key, [feature] AS l FROM f UNION ALL SELECT a.feature || '+' || b.feature, [a.feature, b.feature] FROM f a, f b WHERE a.feature < b.feature), (SELECT feature AS rhs_key FROM f) WHERE NOT list_contains(l, rhs_key)", f="SELECT DISTINCT feature FROM event_points"))
ev_wide = lambda s, d: transactions.to_wide(transactions.build(events_buffered(s, d), POINTS))
EVT = {**EV, **tx_ctes("ev_b", POINTS)}
add("itemsets_occurring", lambda s, d: itemsets.occurring(transactions.to_wide(transactions.build(sources_buffered(s, d), GRID)), 2).drop("items"), sql("SELECT key, size, sup AS n FROM pats", **EM, **tx_ctes("em_b", GRID), **pattern_ctes(d=2)))
add("exp_sup_patterns", lambda s, d: prevalence.supports(ev_wide(s, d), 3).select("key", "size", "sup", r4("exp_sup")), sql(f"SELECT key, size, sup, {q4('exp_sup')} FROM pats", **EVT, **pattern_ctes(d=3)))
add("sup_patterns", lambda s, d: prevalence.supports(transactions.to_wide(transactions.build(events_buffered(s, d), POINTS, mode="certain")), 3).select("key", "size", "sup"), sql("SELECT key, size, sup FROM pats", **EV, **tx_ctes("ev_b", POINTS, "boolean"), **pattern_ctes(d=3)))
all_wide = lambda s, d, **kw: transactions.to_wide(transactions.build(all_buffered(s, d), GRID, **kw))
ALLT = {**ALL, **tx_ctes("objs", GRID)}
ALLC = {**ALL, **tx_ctes("objs", GRID, "boolean")}
add("exp_conf_rules", lambda s, d: prevalence.confidences(all_wide(s, d), EFFECT, 2).select("key", "size", "sup", "sup_lhs", r4("exp_sup"), r4("exp_sup_lhs"), r4("exp_conf")), sql(f"SELECT key, size, sup, sup_lhs, {q4('exp_sup')}, {q4('exp_sup_lhs')}, {q4('exp_conf')} FROM rules", **ALLT, **rule_ctes(d=2)))
add("conf_rules", lambda s, d: prevalence.confidences(all_wide(s, d, mode="certain"), EFFECT, 2).select("key", "size", "sup", "sup_lhs", r4("conf")), sql(f"SELECT key, size, sup, sup_lhs, {q4('conf')} FROM rules", **ALLC, **rule_ctes(d=2)))
add("rules_min_support", lambda s, d: prevalence.confidences(all_wide(s, d), EFFECT, 2).where("exp_sup >= 1").select("key", r4("exp_sup"), r4("exp_conf")), sql(f"SELECT key, {q4('exp_sup')}, {q4('exp_conf')} FROM rules WHERE exp_sup >= 1", **ALLT, **rule_ctes(d=2)))
add("low_support_rules", lambda s, d: measures.low_support(prevalence.confidences(all_wide(s, d), EFFECT, 2)), sql("SELECT count(*) AS n_rules, count(*) FILTER (exp_sup < 1) AS n_low FROM rules", **ALLT, **rule_ctes(d=2)))
add("exp_conf_general", lambda s, d: prevalence.general_confidence(ev_wide(s, d), candidates.rules_all(given.event_points(s, d).select("feature").distinct(), 2, 1)).select("lhs_key", "rhs_key", r4("exp_conf")), sql(f"SELECT lhs_key, rhs_key, {q4('b.exp_sup::DOUBLE / l.exp_sup::DOUBLE', 'exp_conf')} FROM ra JOIN pats b ON b.key = both_key JOIN pats l ON l.key = lhs_key", **EVT, **pattern_ctes(d=3), f="SELECT DISTINCT feature FROM event_points", ra="SELECT lhs_key, rhs_key, (SELECT string_agg(x, '+' ORDER BY x) FROM (SELECT unnest(list_append(l, rhs_key)) AS x)) AS both_key FROM (SELECT feature AS lhs_key, [feature] AS l FROM f UNION ALL SELECT a.feature || '+' || b.feature, [a.feature, b.feature] FROM f a, f b WHERE a.feature < b.feature), (SELECT feature AS rhs_key FROM f) WHERE NOT list_contains(l, rhs_key)"))
add("prevalence_baskets", lambda s, d: prevalence.supports(transactions.to_wide(transactions.from_table(given.baskets(s, d))), 2).select("key", "size", "sup", r4("exp_sup")), sql(f"SELECT key, size, sup, {q4('exp_sup')} FROM pats", tx="SELECT tx_id, item AS feature, max(p)::DECIMAL(18,12) AS p FROM baskets GROUP BY ALL", **pattern_ctes(d=2, on="tx_id")))


def toxic_rules(s, d):
    words = given.word_sets(s, d)
    toxic = given.table(s, d, "labels").where("toxic = 1").select(F.col("doc_id").alias("tx_id"), F.lit("TOXIC").alias("item"), F.lit(1.0).alias("p"))
    known = given.table(s, d, "labels").select(F.col("doc_id").alias("tx_id")).distinct()
    return prevalence.confidences(transactions.to_wide(transactions.from_table(words.join(known, "tx_id", "left_semi").unionByName(toxic.distinct()))), "TOXIC", 1)


add("rules_documents_toxic", lambda s, d: toxic_rules(s, d).select("key", "sup", "sup_lhs", r4("conf")), sql(f"SELECT key, sup, sup_lhs, {q4('conf')} FROM rules", **WORDS, tx="SELECT * FROM wsets WHERE tx_id IN (SELECT doc_id FROM labels) UNION ALL SELECT DISTINCT doc_id, 'TOXIC', 1.0::DECIMAL(18,12) FROM labels WHERE toxic = 1", **rule_ctes(effect="TOXIC", d=1, on="tx_id")))
add("prevalence_roles", lambda s, d: prevalence.supports(transactions.to_wide(transactions.from_table(given.role_sets(s, d))), 3).select("key", "sup"), sql("SELECT key, sup FROM pats", tx="SELECT DISTINCT conv_id AS tx_id, role AS feature, 1.0::DECIMAL(18,12) AS p FROM conversations", **pattern_ctes(d=3, on="tx_id")))
add("prevalence_pages", lambda s, d: prevalence.supports(transactions.to_wide(transactions.from_table(given.page_sets(s, d))), 2).select("key", "sup"), sql("SELECT key, sup FROM pats", tx=" UNION ALL ".join(f"SELECT page_id AS tx_id, '{t}' AS feature, 1.0::DECIMAL(18,12) AS p FROM pages WHERE contains(html, '<{t}')" for t in ("nav", "script", "article", "table", "form", "style")), **pattern_ctes(d=2, on="tx_id")))

# ---- simulations ----
add("rand_permute", lambda s, d: randomize.permute_features(given.emissions(s, d), 1, R).select("sim_id", "object_id", "feature", r4("amount")), sql(f"SELECT sim_id, object_id, feature, {q4('amount')} FROM rand_causes"))
add("rand_permute_site_amount", lambda s, d: randomize.permute_features(given.emissions(s, d), 1, R, carry_amount=False).select("sim_id", "object_id", "feature", r4("amount")), sql(f"SELECT sim_id, object_id, feature, {q4('site_amount', 'amount')} FROM rand_causes"))


def hash_counts(s, d):
    """Every simulation keeps each feature's and each site's number of emissions."""
    rows = randomize.permute_by_hash(given.emissions(s, d), 1, R)
    return rows.groupBy("sim_id", "feature").agg(F.count(F.lit(1)).alias("n"))


add("rand_permute_hash", hash_counts, sql("SELECT sim_id, feature, count(*) AS n FROM emissions, sims GROUP BY ALL"))
population = lambda s, d, linked=False, first=1, last=R, how="largest_remainder": randomize.by_population(given.cases_linked(s, d) if linked else given.cases(s, d), given.zones(s, d), REGION, first, last, how)
add("rand_population", lambda s, d: population(s, d).select("sim_id", "object_id", "urban", r4("x"), r4("y")), sql(f"SELECT sim_id, object_id, urban, {q4('x')}, {q4('y')} FROM rand_cases"))
add("rand_population_draw", lambda s, d: population(s, d, how="draw").where("urban").groupBy("sim_id").agg(F.count(F.lit(1)).alias("n")), sql("SELECT sim_id, count(*) AS n FROM cases, sims WHERE urban GROUP BY ALL"))
_usim = lambda t, k: f"(('0x' || substr(md5('{t}' || sim_id || ':' || {k}), 1, 8))::BIGINT / 4294967296.0)"
UNI = {"rand_uni": f"SELECT sim_id, feature, object_id, 100.0 * {_usim('ux', 'object_id')} AS x, 100.0 * {_usim('uy', 'object_id')} AS y FROM event_points, sims"}
uniform_counts = lambda s, d, last=R: randomize.uniform(given.event_points(s, d), (0.0, 0.0, 100.0, 100.0), 1, last).groupBy("sim_id", "feature").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("x"), 4).alias("mean_x"), F.round(F.avg("y"), 4).alias("mean_y"))
add("rand_uniform", uniform_counts, sql("SELECT sim_id, feature, count(*) AS n, round(avg(x), 4) AS mean_x, round(avg(y), 4) AS mean_y FROM rand_uni GROUP BY ALL", **UNI))


# ---- significance ----
RULES = MinerConfig(effect=EFFECT, box=REGION, d=D, sims=R)


def near_cases(rows: DataFrame) -> DataFrame:
    return buffers.fixed(rows, CASE_RADIUS)


def world(s: SparkSession, d: str, cfg: MinerConfig = RULES, linked: bool = True):
    """(buffered objects, their randomiser), from emissions and cases that are written once."""
    e = staged(given.emissions(s, d), "emissions")
    c = staged(given.cases_linked(s, d, e) if linked else given.cases(s, d), "cases")
    both = buffers.log_amount(e).select(*KEEP).unionByName(near_cases(c).select(*KEEP))
    return both, miner.randomiser(e, c, given.zones(s, d), cfg, buffers.log_amount, near_cases, KEEP, circles=True)


def mine_rules(s, d, how="both", linked=True, choose=None, **kw):
    cfg = replace(RULES, randomise=how, **kw)
    return miner.significant(*world(s, d, cfg, linked), cfg, choose=choose)


def sim_sql(how: str = "both", decay: str = "cosine") -> dict[str, str]:
    causes = "rand_causes" if how in ("both", "causes") else "(SELECT * FROM emissions, sims)"
    effects = "rand_cases_linked" if how in ("both", "effects") else "(SELECT * FROM cases_linked, sims)"
    cols = "sim_id, object_id, feature, x, y, r, a, b, cx, cy, ux, uy"
    return {
        "sim_em": LOG.format(causes), "sim_ca": CASES.format(effects), "sim_objs": f"SELECT {cols} FROM sim_em UNION ALL SELECT {cols} FROM sim_ca",
        **tx_ctes("sim_objs", GRID, decay, by=("sim_id",), name="stx"), **rule_ctes("stx", by=("sim_id",), d=D, name="srules"),
    }


def mined_sql(how: str = "both", certain: bool = False, extra: str = "", most: int = MOST) -> dict[str, str]:
    base = {**(ALLC if certain else ALLT), **rule_ctes(d=D), **sim_sql(how, "boolean" if certain else "cosine")}
    return {**base, **survivors("rules", "srules", "conf" if certain else "exp_conf", "sup" if certain else "exp_sup", most, extra)}


MINED = f"SELECT key, size, exceed, {q4(f'(exceed + 1) / {R + 1}.0', 'p_value')} FROM found"
_show_mined = lambda df: df.select("key", "size", F.col("exceed").cast("int").alias("exceed"), r4("p_value"))
add("mine_rules_um", lambda s, d: _show_mined(mine_rules(s, d)), sql(MINED, **mined_sql()))
add("mine_rules_cm", lambda s, d: _show_mined(mine_rules(s, d, mode="certain")), sql(MINED, **mined_sql(certain=True)))
add("mine_rules_nofilter", lambda s, d: _show_mined(mine_rules(s, d, early_stop=False)), sql(MINED, **mined_sql()))
add("mine_rules_batched", lambda s, d: _show_mined(mine_rules(s, d, sim_batch=33)), sql(MINED, **mined_sql()))
add("mine_rules_rand_causes", lambda s, d: _show_mined(mine_rules(s, d, "causes", early_stop=False)), sql(MINED, **mined_sql("causes")))
add("mine_rules_rand_effects", lambda s, d: _show_mined(mine_rules(s, d, "effects", early_stop=False)), sql(MINED, **mined_sql("effects")))
add("mine_rules_tiled", lambda s, d: _show_mined(mine_rules(s, d, early_stop=False, strategy="tiled")), sql(MINED, **mined_sql()))
add("mine_rules_min_support", lambda s, d: _show_mined(mine_rules(s, d, early_stop=False, min_exp_sup=1.0)), sql(MINED, **mined_sql(extra="AND exp_sup >= 1")))
add("filter_zero", lambda s, d: miner.observed(all_buffered(s, d), GRID, RULES).agg(F.count(F.lit(1)).alias("n_left")).crossJoin(candidates.rules_to(EFFECT, features(s, d), D).agg(F.count(F.lit(1)).alias("n_candidates"))), sql("SELECT (SELECT count(*) FROM rules WHERE exp_sup > 0) AS n_left, (SELECT count(*) + count(*) * (count(*) - 1) // 2 + count(*) * (count(*) - 1) * (count(*) - 2) // 6 FROM (SELECT DISTINCT feature FROM emissions)) AS n_candidates", **ALLT, **rule_ctes(d=D)))


def filter_trace(s, d):
    """Candidates left after every simulation."""
    _, trace = miner.in_blocks(*world(s, d), replace(RULES, sim_batch=TRACED))
    return s.createDataFrame([(t["last_sim"], t["candidates"]) for t in trace if t["candidates"]], "last_sim int, candidates long")


#: Simulations between two steps of the trace.
TRACED = 9
_BASE = {**ALLT, **rule_ctes(d=D), **sim_sql()}
TRACE_SQL = f"SELECT last_sim::INTEGER AS last_sim, count(*) AS candidates FROM (SELECT unnest(generate_series(0, {R}, {TRACED})) AS last_sim), (SELECT r.key, list(s.sim_id) FILTER (s.exp_conf >= r.exp_conf) AS hits FROM rules r LEFT JOIN srules s ON s.key = r.key WHERE r.exp_sup > 0 GROUP BY r.key) WHERE len(list_filter(coalesce(hits, []), lambda h: h <= last_sim)) <= {MOST} GROUP BY last_sim"
add("filter_trace", filter_trace, sql(TRACE_SQL, **_BASE))
#: Draws of events in [0, 100) as numbers of simulations that exceed.
_drawn = lambda s, d: given.table(s, d, "events").select(F.get_json_object("props", "$.k").cast("long").alias("exceed")).where(F.col("exceed").between(0, R)).groupBy("exceed").agg(F.count(F.lit(1)).alias("n"))
add("p_value_table", lambda s, d: _drawn(s, d).select("exceed", "n", F.round(p_value(F.col("exceed"), R), 4).alias("p_value"), (F.col("exceed") <= MOST).alias("significant")), sql(f"SELECT k::BIGINT AS exceed, count(*) AS n, round((k + 1) / {R + 1}.0::DOUBLE, 4) AS p_value, (k + 1) / {R + 1}.0::DOUBLE <= 0.05 AS significant FROM ev WHERE k BETWEEN 0 AND {R} GROUP BY k"))
add("p_error", lambda s, d: given.table(s, d, "part").where("p_size is not null").select((F.col("p_size").cast("long") * 20 - 1).alias("sims")).groupBy("sims").agg(F.count(F.lit(1)).alias("n")).select("sims", "n", F.round(significance.p_error(F.lit(0.05), F.col("sims")), 6).alias("error")), "SELECT (p_size * 20 - 1)::BIGINT AS sims, count(*) AS n, round(sqrt(0.05 * 0.95 / (p_size * 20)), 6)::DOUBLE AS error FROM part WHERE p_size IS NOT NULL GROUP BY p_size")


def tested(s, d, cfg=RULES):
    """Every candidate with its p-value."""
    return miner.single_plan(*world(s, d), cfg)


_TESTED = {**_BASE, **survivors("rules", "srules", "exp_conf", "exp_sup", R)}
add("p_adjust", lambda s, d: significance.adjusted(tested(s, d)).select("key", r4("p_value"), r4("p_adjusted")), sql(f"SELECT key, {q4('p', 'p_value')}, {q4('least(1.0, min(p * n / k) OVER (ORDER BY p DESC, key DESC ROWS UNBOUNDED PRECEDING))', 'p_adjusted')} FROM (SELECT key, p, count(*) OVER () AS n, row_number() OVER (ORDER BY p, key) AS k FROM (SELECT key, (exceed + 1) / {R + 1}.0::DOUBLE AS p FROM tested))", **_TESTED))


def pattern_cfg(**kw):
    return MinerConfig(objective="patterns", **{"box": (0.0, 0.0, 100.0, 100.0), "step": 0.5, "d": D, "sims": R} | kw)


def mine_patterns(s, d, cfg=None, **kw):
    pts = given.event_points(s, d)
    draws = miner.uniform_randomiser(pts, (0.0, 0.0, 100.0, 100.0), lambda rows: buffers.fixed(rows, 1.0))
    return miner.significant(buffers.fixed(pts, 1.0), draws, cfg or pattern_cfg(**kw))


def patterns_sql(certain: bool = False) -> dict[str, str]:
    decay = "boolean" if certain else "cosine"
    return {
        **EV, **tx_ctes("ev_b", POINTS, decay), **pattern_ctes(d=D), "obs": "SELECT * FROM pats WHERE size >= 2", **UNI,
        "uni_b": f"SELECT *, {CIRCLE} FROM (SELECT *, 1.0 AS r FROM rand_uni)", **tx_ctes("uni_b", POINTS, decay, by=("sim_id",), name="stx"), **pattern_ctes("stx", ("sim_id",), D, "spats"),
        **survivors("obs", "spats", "sup" if certain else "exp_sup", "sup", MOST),
    }


add("mine_patterns_um", lambda s, d: _show_mined(mine_patterns(s, d, early_stop=False)), sql(MINED, **patterns_sql()))
add("mine_patterns_cm", lambda s, d: _show_mined(mine_patterns(s, d, mode="certain", early_stop=False)), sql(MINED, **patterns_sql(True)))

# ---- baselines ----
_rules = lambda s, d, certain=False, most=2: prevalence.confidences(all_wide(s, d, mode="certain" if certain else "uncertain"), EFFECT, most)
for _short, _measure, _ctes in (("um", "exp_conf", ALLT), ("cm", "conf", ALLC)):
    add(f"baseline_mean_conf_{_short}", lambda s, d, m=_measure: baselines.mean_conf(_rules(s, d, m == "conf"), m).where("kept").select("key", r4("threshold"), r4(m, "measure")), sql(f"SELECT key, {q4('t', 'threshold')}, {q4(_measure, 'measure')} FROM rules, (SELECT avg({_measure}) AS t FROM rules WHERE {_measure} > 0) WHERE {_measure} >= t", **_ctes, **rule_ctes(d=2)))


def prune_counts(s, d):
    out = None
    for mode, measure in (("uncertain", "exp_conf"), ("certain", "conf")):
        one = baselines.mean_conf(_rules(s, d, mode == "certain", D), measure).groupBy("kept").agg(F.count(F.lit(1)).alias("n")).select(F.lit(mode).alias("mode"), "kept", "n")
        out = one if out is None else out.unionByName(one)
    return out


_PRUNED = "SELECT '{0}' AS mode, coalesce({1} >= t, false) AS kept, count(*) AS n FROM {2}, (SELECT avg({1}) AS t FROM {2} WHERE {1} > 0) GROUP BY ALL"
add("baseline_prune_counts", prune_counts, sql(_PRUNED.format("uncertain", "exp_conf", "rules") + " UNION ALL " + _PRUNED.format("certain", "conf", "crules"), **ALLT, **rule_ctes(d=D), **tx_ctes("objs", GRID, "boolean", name="ctx"), **rule_ctes("ctx", d=D, name="crules")))


def then_test(s, d, mode="uncertain"):
    """The rules over the mean confidence that pass the test."""
    measure = replace(RULES, mode=mode).measure
    return mine_rules(s, d, mode=mode, choose=lambda rows: baselines.mean_conf(rows, measure).where("kept"))


_KEPT = {"kept": "SELECT rules.* FROM rules, (SELECT avg(exp_conf) AS t FROM rules WHERE exp_conf > 0) WHERE exp_conf >= t"}
_KEPT_CM = {"kept": "SELECT rules.* FROM rules, (SELECT avg(conf) AS t FROM rules WHERE conf > 0) WHERE conf >= t"}


def then_test_both(s, d):
    """key, region (1: uncertain, 2: certain, 3: both) of the rules over either mean confidence that pass its test."""
    return measures.overlap({"um": then_test(s, d), "cm": then_test(s, d, "certain")}).select("key", "region")


def coverage(s, d):
    """Of the rules that the method finds, uncertain or certain, how many the cuts followed by the tests find."""
    full = mine_rules(s, d).select("key").union(mine_rules(s, d, mode="certain").select("key")).distinct()
    base = then_test_both(s, d).select("key", F.lit(1).alias("b"))
    return full.join(base, "key", "left").agg(F.count(F.lit(1)).alias("n_method"), F.count("b").alias("n_baseline"), (F.count(F.lit(1)) - F.count("b")).alias("n_missed"))


add("baseline_support_conf", lambda s, d: baselines.support_conf(_rules(s, d, True), 20, 0.2).select("key", "sup", r4("conf")), sql(f"SELECT key, sup, {q4('conf')} FROM rules WHERE sup >= 20 AND conf >= 0.2", **ALLC, **rule_ctes(d=2)))
add("baseline_levelwise", lambda s, d: baselines.levelwise(transactions.build(sources_buffered(s, d), GRID, mode="certain"), 60, 3).select("key", "size", "sup"), sql("SELECT p.key, p.size, p.sup FROM pats p WHERE sup >= 60", **EM, **tx_ctes("em_b", GRID, "boolean"), **pattern_ctes(d=3)))
PAIRS = {"np": "SELECT a.feature AS f1, b.feature AS f2, a.object_id AS o1, b.object_id AS o2 FROM {0} a JOIN {0} b ON a.feature < b.feature AND power(a.x - b.x, 2) + power(a.y - b.y, 2) <= 9.0", "nt": "SELECT feature, count(DISTINCT object_id) AS n FROM {0} GROUP BY ALL"}
BOTH = {"both_o": "SELECT object_id, feature, x, y FROM emissions UNION ALL SELECT object_id, feature, x, y FROM cases_linked"}
plain_objects = lambda s, d: given.emissions(s, d).select("object_id", "feature", "x", "y").unionByName(given.cases_linked(s, d).select("object_id", "feature", "x", "y"))
NEAR = {
    "np": "SELECT a.feature AS f1, b.feature AS f2, a.object_id AS o1, b.object_id AS o2 FROM both_o a JOIN both_o b ON a.feature < b.feature AND power(a.x - b.x, 2) + power(a.y - b.y, 2) <= 9.0",
    "c3": "SELECT p.f1, p.f2, q.f2 AS f3, p.o1, p.o2, q.o2 AS o3 FROM np p JOIN np q ON q.o1 = p.o1 AND q.f1 = p.f1 AND q.f2 > p.f2 JOIN np r ON r.f1 = p.f2 AND r.o1 = p.o2 AND r.f2 = q.f2 AND r.o2 = q.o2",
    "mem": "SELECT f1 || '+' || f2 AS key, 2 AS size, unnest([f1, f2]) AS feature, unnest([o1, o2]) AS o FROM np UNION ALL SELECT f1 || '+' || f2 || '+' || f3, 3, unnest([f1, f2, f3]), unnest([o1, o2, o3]) FROM c3",
    "nt": "SELECT feature, count(DISTINCT object_id) AS t FROM both_o GROUP BY ALL",
    "pis": "SELECT key, size, min(n / t) AS pi FROM (SELECT key, size, feature, count(DISTINCT o) AS n FROM mem GROUP BY ALL) JOIN nt USING (feature) GROUP BY ALL",
}
add("baseline_participation", lambda s, d: baselines.participation(plain_objects(s, d), 3.0, 0.1, 3, one_row=True).select("key", "size", r4("pi")), sql(f"SELECT key, size, {q4('pi')} FROM pis WHERE pi >= 0.1", **BOTH, **NEAR))
add("baseline_cliques", lambda s, d: baselines.participation(plain_objects(s, d), 3.0, d=3, one_row=True).select("key", "size", r4("pi")), sql(f"SELECT key, size, {q4('pi')} FROM pis", **BOTH, **NEAR))


def participation_test(s, d, n=R):
    obs = staged(baselines.participation(plain_objects(s, d), 3.0, one_row=True), "participation")
    e, c = given.emissions(s, d), given.cases_linked(s, d)
    sims = randomize.permute_features(e, 1, n).select("sim_id", "object_id", "feature", "x", "y").unionByName(randomize.by_population(c, given.zones(s, d), REGION, 1, n).select("sim_id", "object_id", "feature", "x", "y"))
    return significance.decided(obs, significance.exceedances(obs, baselines.participation(sims, 3.0, one_row=True), "pi"), n, 0.05).where("significant")


add("baseline_participation_test", lambda s, d: participation_test(s, d).select("key", r4("pi"), "exceed"), sql("""SELECT o.key, o.pi, coalesce(n, 0)::INTEGER AS exceed FROM obs o LEFT JOIN (SELECT o.key, count(*) AS n FROM obs o JOIN sim_pi s ON s.key = o.key AND s.pi >= o.pi0 GROUP BY o.key) x ON x.key = o.key WHERE coalesce(n, 0) <= 4""", **BOTH, **{k: v.format("both_o") for k, v in PAIRS.items()},
    obs="SELECT f1 || '+' || f2 AS key, least(count(DISTINCT o1) / any_value(a.n), count(DISTINCT o2) / any_value(b.n)) AS pi0, round(pi0, 4) AS pi FROM np JOIN nt a ON a.feature = f1 JOIN nt b ON b.feature = f2 GROUP BY f1, f2",
    sim_o="SELECT sim_id, object_id, feature, x, y FROM rand_causes UNION ALL SELECT sim_id, object_id, feature, x, y FROM rand_cases_linked",
    snp="SELECT sim_id, a.feature AS f1, b.feature AS f2, a.object_id AS o1, b.object_id AS o2 FROM sim_o a JOIN sim_o b USING (sim_id) WHERE a.feature < b.feature AND power(a.x - b.x, 2) + power(a.y - b.y, 2) <= 9.0",
    snt="SELECT sim_id, feature, count(DISTINCT object_id) AS n FROM sim_o GROUP BY ALL",
    sim_pi="SELECT p.sim_id, f1 || '+' || f2 AS key, least(count(DISTINCT o1) / any_value(a.n), count(DISTINCT o2) / any_value(b.n)) AS pi FROM snp p JOIN snt a ON a.feature = f1 AND a.sim_id = p.sim_id JOIN snt b ON b.feature = f2 AND b.sim_id = p.sim_id GROUP BY p.sim_id, f1, f2"))
add("baseline_window_tx", lambda s, d: baselines.window_tx(plain_objects(s, d), 5.0).select("gi", "gj", "feature", "n_inst"), sql("SELECT floor(x / 5.0)::BIGINT AS gi, floor(y / 5.0)::BIGINT AS gj, feature, count(*)::INTEGER AS n_inst FROM both_o GROUP BY ALL", **BOTH))
add("baseline_reference_tx", lambda s, d: baselines.reference_tx(plain_objects(s, d), EFFECT, 3.0), sql("SELECT tx_id, feature, count(*)::INTEGER AS n_inst FROM (SELECT c.object_id AS tx_id, e.feature FROM both_o c JOIN both_o e ON c.feature = 'CASE' AND e.feature <> 'CASE' AND power(c.x - e.x, 2) + power(c.y - e.y, 2) <= 9.0 UNION ALL SELECT object_id, 'CASE' FROM both_o WHERE feature = 'CASE') GROUP BY ALL", **BOTH))
add("baseline_overlap", lambda s, d: baselines.overlap_threshold(transactions.build(sources_buffered(s, d), GRID, mode="certain"), 0.02).select("key", r4("cov")), sql("SELECT * FROM (SELECT a.feature || '+' || b.feature AS key, round(count(*) / (any_value(ca.n) + any_value(cb.n) - count(*)), 4) AS cov, count(*) / (any_value(ca.n) + any_value(cb.n) - count(*)) AS c0 FROM tx a JOIN tx b USING (gi, gj) JOIN cov ca ON ca.feature = a.feature JOIN cov cb ON cb.feature = b.feature WHERE a.feature < b.feature GROUP BY a.feature, b.feature) WHERE c0 >= 0.02".replace("SELECT * FROM", "SELECT key, cov FROM", 1), **EM, **tx_ctes("em_b", GRID, "boolean"), cov="SELECT feature, count(*) AS n FROM tx GROUP BY feature"))
add("ablate_single_radius", lambda s, d: prevalence.supports(transactions.to_wide(transactions.build(buffers.fixed(given.emissions(s, d), 5.0), GRID)), 2).select("key", "sup", r4("exp_sup")), sql(f"SELECT key, sup, {q4('exp_sup')} FROM pats", one=f"SELECT *, {CIRCLE} FROM (SELECT *, 5.0 AS r FROM emissions)", **tx_ctes("one", GRID), **pattern_ctes(d=2)))
add("ablate_no_wind", lambda s, d: prevalence.supports(transactions.to_wide(transactions.build(sources_buffered(s, d), GRID)), 2).select("key", "sup", r4("exp_sup")), sql(f"SELECT key, sup, {q4('exp_sup')} FROM pats", **EM, **tx_ctes("em_b", GRID), **pattern_ctes(d=2)))
add("ablate_wind", lambda s, d: prevalence.supports(transactions.to_wide(transactions.build(buffers.ellipse(windy(s, d)), GRID)), 1).select("key", "sup", r4("exp_sup", digits=2)), sql(f"SELECT key, sup, {q4('exp_sup', digits=2)} FROM pats", **W, **ellipse_sql(), **tx_ctes("el", GRID), **pattern_ctes(d=1)))

# ---- measures ----
add("dataset_profile", lambda s, d: given.emissions(s, d).agg(F.count(F.lit(1)).alias("n_emissions"), F.countDistinct("feature").alias("n_chemicals"), F.countDistinct("site_id").alias("n_sites")).crossJoin(given.cases(s, d).agg(F.count(F.lit(1)).alias("n_cases"), F.sum(F.col("urban").cast("int")).alias("n_urban"))), sql("SELECT * FROM (SELECT count(*) AS n_emissions, count(DISTINCT feature) AS n_chemicals, count(DISTINCT site_id) AS n_sites FROM emissions), (SELECT count(*) AS n_cases, count(*) FILTER (urban) AS n_urban FROM cases)"))


def um_vs_cm(s, d):
    um, cm = mine_rules(s, d), mine_rules(s, d, mode="certain")
    return measures.regions(measures.overlap({"um": um, "cm": cm})).select("region", "n", r4("p_mean"))


def _renamed(ctes: dict[str, str], suffix: str, names: tuple[str, ...]) -> dict[str, str]:
    import re

    pattern = re.compile(r"\b(" + "|".join(sorted(names, key=len, reverse=True)) + r")\b")
    return {(n + suffix if n in names else n): pattern.sub(lambda m: m[0] + suffix, t) for n, t in ctes.items()}


def um_cm_sql() -> dict[str, str]:
    um, cm = mined_sql(), mined_sql(certain=True)
    shared = {"em_b", "ca_b", "objs", "sim_em", "sim_ca", "sim_objs"}
    own = tuple(n for n in cm if n not in shared)
    return {**um, **_renamed(cm, "_cm", own)}


def _cut_sql() -> dict[str, str]:
    um = {**mined_sql(), **_KEPT, **{k: v for k, v in _renamed(survivors("kept", "srules", "exp_conf", "exp_sup", MOST), "_k", ("exceeding", "tested", "found")).items()}}
    cm = {**mined_sql(certain=True), **_KEPT_CM, **_renamed(survivors("kept", "srules", "conf", "sup", MOST), "_k", ("exceeding", "tested", "found"))}
    return {**um, **{k: v for k, v in _renamed(cm, "_cm", tuple(n for n in cm if n not in {"em_b", "ca_b", "objs", "sim_em", "sim_ca", "sim_objs"})).items() if k.endswith("_cm")}}


_CUT = "(SELECT key, sum(bit)::INTEGER AS region FROM (SELECT key, 1 AS bit FROM found_k UNION ALL SELECT key, 2 FROM found_k_cm) GROUP BY key)"
add("baseline_then_test", then_test_both, sql(f"SELECT key, region FROM {_CUT}", **_cut_sql()))
add("baseline_coverage", coverage, sql(f"SELECT count(*) AS n_method, count(c.key) AS n_baseline, count(*) - count(c.key) AS n_missed FROM (SELECT key FROM found UNION SELECT key FROM found_cm) m LEFT JOIN {_CUT} c ON c.key = m.key", **_cut_sql()))
add("um_vs_cm", um_vs_cm, sql(f"SELECT region::INTEGER AS region, count(*) AS n, {q4('avg(p)', 'p_mean')} FROM (SELECT key, sum(bit) AS region, avg((exceed + 1) / {R + 1}.0::DOUBLE) AS p FROM (SELECT key, 1 AS bit, exceed FROM found UNION ALL SELECT key, 2, exceed FROM found_cm) GROUP BY key) GROUP BY region", **um_cm_sql()))
add("n_significant", lambda s, d: mine_rules(s, d).groupBy("size").agg(F.count(F.lit(1)).alias("n")), sql("SELECT size, count(*) AS n FROM found GROUP BY size", **mined_sql()))



# ---- generated sets ----
def distance_study(s: SparkSession, reps: int = 100, ids: DataFrame | None = None) -> DataFrame:
    pts = buffers.fixed(synthetic.distance_pairs(s, reps=reps, ids=ids), 1.0)
    grid = grids.Grid(0.1, (-3.0, -3.0, 103.0, 103.0))
    sup = prevalence.supports(transactions.to_wide(transactions.build(pts, grid)), 2).where("size = 2")
    return sup.groupBy((F.col("set_id") % 10).cast("int").alias("range_id")).agg(F.avg(F.col("exp_sup").cast("double")).alias("mean_exp_sup"))


DIST = {
    "ids": "SELECT i, i // 30 AS set_id, ((i // 30) % 10)::INTEGER AS range_id FROM (SELECT unnest(generate_series(0, 29999)) AS i)",
    "ab": "SELECT *, 100.0 * (('0x' || substr(md5('px' || i), 1, 8))::BIGINT / 4294967296.0) AS x, 100.0 * (('0x' || substr(md5('py' || i), 1, 8))::BIGINT / 4294967296.0) AS y, 0.2 * (range_id + (('0x' || substr(md5('pr' || i), 1, 8))::BIGINT / 4294967296.0)) AS dr, 2 * pi() * (('0x' || substr(md5('pt' || i), 1, 8))::BIGINT / 4294967296.0) AS t FROM ids",
    "dp": f"SELECT *, {CIRCLE} FROM (SELECT set_id, 'f1' AS feature, x, y, 1.0 AS r FROM ab UNION ALL SELECT set_id, 'f2', x + dr * cos(t), y + dr * sin(t), 1.0 FROM ab)",
    **tx_ctes("dp", grids.Grid(0.1, (-3.0, -3.0, 103.0, 103.0)), by=("set_id",)), **pattern_ctes(by=("set_id",), d=2),
}
_by_site = lambda s, d: given.table(s, d, "supplier").select(F.col("s_suppkey").cast("long").alias("id"))
add("synth_distance", lambda s, d: distance_study(s, ids=_by_site(s, d)).select("range_id", r4("mean_exp_sup", digits=2)), sql(f"SELECT (set_id % 10)::INTEGER AS range_id, {q4('avg(exp_sup::DOUBLE)', 'mean_exp_sup', 2)} FROM pats WHERE size = 2 GROUP BY ALL", **{**DIST, "ids": "SELECT s_suppkey AS i, s_suppkey // 30 AS set_id, ((s_suppkey // 30) % 10)::INTEGER AS range_id FROM supplier"}))


def planted_rules(s: SparkSession, sims: int = R, d: int = D, step: float = 0.1) -> DataFrame:
    pts = synthetic.planted(s)
    cfg = MinerConfig(effect="D", box=synthetic.BOX, step=step, d=d, sims=sims)
    draws = lambda first, last: buffers.fixed(randomize.uniform(pts, synthetic.BOX, first, last), 1.0)
    return miner.significant(buffers.fixed(pts, 1.0), draws, cfg)


add("synth_planted_mine", lambda s, d: planted_rules(s).select("key", "size", r4("exp_sup"), r4("exp_conf"), r4("p_value")))
add("synth_truth", lambda s, d: measures.truth(planted_rules(s), list(synthetic.PLANTED), list(synthetic.NOISE)))


#: Sides of the triples of mutual neighbours whose unit buffers have a large, a small and no common area.
SIDES = (0.5, 1.6, 1.9)
NEAR_SITES = grids.Grid(0.2, (-3.0, -3.0, 205.0, 205.0))


def clique_vs_overlap(s, d):
    """Three mutual neighbours at each site, of one of three sides: the triples and their common points by side."""
    site = given.facilities(s, d).select(F.col("site_id").cast("long").alias("set_id"), "x", "y")
    kind = F.pmod("set_id", F.lit(3))
    side = F.element_at(F.array(*[F.lit(v) for v in SIDES]), (kind + 1).cast("int"))
    rows = None
    for name, ex, ey in (("A", 0.0, 0.0), ("B", 1.0, 0.0), ("C", 0.5, 3**0.5 / 2)):
        one = site.select("set_id", F.lit(name).alias("feature"), (F.col("x") + side * ex).alias("x"), (F.col("y") + side * ey).alias("y"))
        rows = one if rows is None else rows.unionByName(one)
    got = prevalence.supports(transactions.to_wide(transactions.build(buffers.fixed(rows, 1.0), NEAR_SITES)), 3).where("size = 3").select("set_id", "sup")
    return site.join(got, "set_id", "left").groupBy((kind + 1).cast("int").alias("kind")).agg(F.count(F.lit(1)).alias("n_triples"), F.count("sup").alias("n_overlap"), F.coalesce(F.sum("sup"), F.lit(0)).cast("long").alias("n_common"))


_SITE = {"site": "SELECT site_id::BIGINT AS set_id, x, y, (site_id::BIGINT % 3 + 1)::INTEGER AS kind, [0.5::DOUBLE, 1.6, 1.9][site_id::BIGINT % 3 + 1] AS side FROM facilities"}
add("clique_vs_overlap", clique_vs_overlap, sql("SELECT kind, count(*) AS n_triples, count(sup) AS n_overlap, coalesce(sum(sup), 0)::BIGINT AS n_common FROM site LEFT JOIN (SELECT * FROM pats WHERE size = 3) USING (set_id) GROUP BY kind", **_SITE, tri=f"SELECT *, {CIRCLE} FROM (SELECT set_id, feature, x + side * ex AS x, y + side * ey AS y, 1.0::DOUBLE AS r FROM site, (VALUES ('A', 0.0::DOUBLE, 0.0::DOUBLE), ('B', 1.0, 0.0), ('C', 0.5, {3**0.5 / 2!r}::DOUBLE)) AS t(feature, ex, ey))", **tx_ctes("tri", NEAR_SITES, by=("set_id",)), **pattern_ctes(by=("set_id",), d=3)))


def proximity_counts(s, d):
    """A pair at each site, close at every other one and far apart at the rest: common points of both kinds."""
    site = given.facilities(s, d).select(F.col("site_id").cast("long").alias("set_id"), "x", "y")
    far = F.pmod("set_id", F.lit(2)) == 1
    one = site.select("set_id", F.when(far, "A2").otherwise("A").alias("feature"), "x", "y")
    two = site.select("set_id", F.when(far, "B2").otherwise("B").alias("feature"), (F.col("x") + F.when(far, 1.8).otherwise(0.5)).alias("x"), "y")
    grid = grids.Grid(0.2, (-3.0, -3.0, 205.0, 205.0))
    wide = transactions.to_wide(transactions.build(buffers.fixed(one.unionByName(two), 1.0), grid))
    return prevalence.supports(wide, 2).where("size = 2").groupBy("key").agg(F.sum("sup").alias("sup"), F.sum("exp_sup").alias("exp_sup")).select("key", "sup", r4("exp_sup"))


_PAIRS = f"SELECT *, {CIRCLE} FROM (SELECT site_id::BIGINT AS set_id, CASE WHEN site_id::BIGINT % 2 = 1 THEN 'A2' ELSE 'A' END AS feature, x, y, 1.0::DOUBLE AS r FROM facilities UNION ALL SELECT site_id::BIGINT, CASE WHEN site_id::BIGINT % 2 = 1 THEN 'B2' ELSE 'B' END, x + CASE WHEN site_id::BIGINT % 2 = 1 THEN 1.8::DOUBLE ELSE 0.5 END, y, 1.0 FROM facilities)"
add("proximity_counts", proximity_counts, sql(f"SELECT key, sum(sup)::BIGINT AS sup, {q4('sum(exp_sup)', 'exp_sup')} FROM pats WHERE size = 2 GROUP BY key", pairs=_PAIRS, **tx_ctes("pairs", grids.Grid(0.2, (-3.0, -3.0, 205.0, 205.0)), by=("set_id",)), **pattern_ctes(by=("set_id",), d=2)))

