"""Queries of the experiments."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from coloc.catalog import methods as m
from coloc.catalog.registry import add, q4, r4
from coloc.catalog.twins import D, R, pattern_ctes, rand_cases, rule_ctes, sql, survivors, tx_ctes
from coloc.functions import decay as decays
from coloc.operators import buffers, grids, measures, prevalence, randomize, transactions, winds
from coloc.plans import miner, workloads
from coloc.sources import generated, given
from coloc.sources.staging import staged

OWN = ("stx", "srules", "exceeding", "tested", "found", "tx", "rules")


def _variant(ctes: dict[str, str], suffix: str, shared: set[str]) -> dict[str, str]:
    return m._renamed(ctes, suffix, tuple(n for n in ctes if n not in shared))


def randomisations(s, d):
    return workloads.counts({how: m.mine_rules(s, d, how) for how in ("both", "causes", "effects")}, "randomised")


_SAME = {"em_b", "ca_b", "objs", *tx_ctes("objs", m.GRID), *rule_ctes(d=D)}
add("workload_randomisations", randomisations, sql("SELECT 'both' AS randomised, count(*) AS n FROM found UNION ALL SELECT 'causes', count(*) FROM found_ca UNION ALL SELECT 'effects', count(*) FROM found_ef", **m.mined_sql(), **{k: v for k, v in _variant(m.mined_sql("causes"), "_ca", _SAME).items() if k not in _SAME}, **{k: v for k, v in _variant(m.mined_sql("effects"), "_ef", _SAME).items() if k not in _SAME}))

STEPS = (0.5, 1.0, 2.0)
_OBJ = {"em_b", "ca_b", "objs", "sim_em", "sim_ca", "sim_objs"}


def grid_sql(h: float, d: int = D) -> dict[str, str]:
    g = grids.Grid(h, m.REGION)
    base = {**m.ALL, **tx_ctes("objs", g), **rule_ctes(d=d), **m.sim_sql()}
    base |= tx_ctes("sim_objs", g, by=("sim_id",), name="stx") | rule_ctes("stx", by=("sim_id",), d=d, name="srules")
    return {**base, **survivors("rules", "srules", "exp_conf", "exp_sup", m.MOST)}


def _of_steps() -> dict[str, str]:
    out: dict[str, str] = {}
    for k, h in enumerate(STEPS):
        out |= {a: b for a, b in _variant(grid_sql(h), f"_h{k}", _OBJ).items()}
    return out


_KEYS = " UNION ALL ".join(f"SELECT key, {1 << k} AS bit, exceed FROM found_h{k}" for k in range(len(STEPS)))


def overlap_grids(s, d):
    """region, n, p_mean of the rules found with three grid steps: bit 1, 2 and 4 for a step of 0.5, 1 and 2."""
    return workloads.shared({f"h{h}": m.mine_rules(s, d, step=h) for h in STEPS}).select("region", "n", r4("p_mean"))


add("overlap_grids", overlap_grids, sql(f"SELECT region::INTEGER AS region, count(*) AS n, {q4('avg(p)', 'p_mean')} FROM (SELECT key, sum(bit) AS region, avg((exceed + 1) / {R + 1}.0::DOUBLE) AS p FROM ({_KEYS}) GROUP BY key) GROUP BY region", **_of_steps()))


def granularity(s, d):
    """Transactions, their mean number of features and the significant rules by grid step."""
    out = None
    for h in STEPS:
        tx = transactions.build(m.all_buffered(s, d), grids.Grid(h, m.REGION))
        one = measures.tx_stats(tx).select(F.lit(h).alias("h"), "n_transactions", r4("mean_features")).crossJoin(m.mine_rules(s, d, step=h).agg(F.count(F.lit(1)).alias("n_rules")))
        out = one if out is None else out.unionByName(one)
    return out


add("workload_granularity", granularity, sql(" UNION ALL ".join(f"SELECT {h}::DOUBLE AS h, count(*) AS n_transactions, {q4('avg(n)', 'mean_features')}, (SELECT count(*) FROM found_h{k}) AS n_rules FROM (SELECT count(*) AS n FROM tx_h{k} GROUP BY gi, gj)" for k, h in enumerate(STEPS)), **_of_steps()))


def null_cases(s, d):
    """Rules to cases that were placed by chance: about alpha of the candidates."""
    return m.mine_rules(s, d, linked=False)


add("workload_null_cases", lambda s, d: m._show_mined(null_cases(s, d)), sql(m.MINED, em_b=m.LOG.format("emissions"), ca_b=m.CASES.format("cases"), objs=m.ALL_SQL, **tx_ctes("objs", m.GRID), **rule_ctes(d=D), **{k: v.replace("rand_cases_linked", "rand_cases") for k, v in m.sim_sql().items()}, **survivors("rules", "srules", "exp_conf", "exp_sup", m.MOST)))

SIMS = (9, 19, 39, 59, 79, 99)


def run_times(s, d):
    """mode, r, seconds, n: time to mine with 9 to 99 simulations, uncertain and certain, at the same alpha."""
    objects, draws = m.world(s, d)
    objects = staged(objects, "objects")  # the time is the mining's alone
    mine = lambda cfg: miner.single_plan(objects, draws, cfg).where("significant")
    one = lambda mode: workloads.run_times(s, mine, replace(m.RULES, mode=mode), SIMS, raised=False).select(F.lit(mode).alias("mode"), "r", "seconds", "n")
    return one("uncertain").unionByName(one("certain"))


add("workload_run_times", run_times)


def runtime_fit(s, d):
    """mode, slope, intercept, r2 of the measured run times."""
    times = staged(run_times(s, d), "run-times")
    return times.groupBy("mode").agg(*measures.line("r", "seconds"))


add("runtime_fit", runtime_fit)


def one_region(s, d):
    """(objects, randomiser) of the smaller data set: the sites and cases of one region's nations."""
    nations = given.table(s, d, "nation").join(given.table(s, d, "region").where("r_regionkey = 0"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("nation"))
    sites = given.facilities(s, d).join(F.broadcast(nations), "nation", "left_semi").select("site_id")
    e = staged(given.emissions(s, d).join(sites, "site_id", "left_semi"), "region-causes")
    c = staged(given.cases_linked(s, d).join(F.broadcast(nations), "nation", "left_semi"), "region-effects")
    both = buffers.log_amount(e).select(*m.KEEP).unionByName(m.near_cases(c).select(*m.KEEP))
    own = given.zones(s, d).join(F.broadcast(nations), F.col("zone_id") == F.col("nation"), "left_semi")
    return both, lambda cfg: miner.randomiser(e, c, own, cfg, buffers.log_amount, m.near_cases, m.KEEP)


_REGION = {
    "rn": "SELECT n_nationkey AS nation FROM nation WHERE n_regionkey = 0", "re": "SELECT e.* FROM emissions e JOIN facilities f USING (site_id) WHERE f.nation IN (SELECT nation FROM rn)", "rc": "SELECT * FROM cases_linked WHERE nation IN (SELECT nation FROM rn)",
    "rz": "SELECT * FROM zones WHERE zone_id IN (SELECT nation FROM rn)", "em_b": m.LOG.format("re"), "ca_b": m.CASES.format("rc"), "objs": m.ALL_SQL, **tx_ctes("objs", m.GRID), **rule_ctes(d=D),
}


def by_region(s, d):
    return prevalence.confidences(transactions.to_wide(transactions.build(one_region(s, d)[0], m.GRID)), given.EFFECT, D)


add("workload_one_region", lambda s, d: by_region(s, d).select("key", "sup", r4("exp_sup"), r4("exp_conf")), sql(f"SELECT key, sup, {q4('exp_sup')}, {q4('exp_conf')} FROM rules", **_REGION))


def region_rules(s, d, how: str = "both", **kw):
    objects, draws = one_region(s, d)
    cfg = replace(m.RULES, randomise=how, **kw)
    return miner.significant(objects, draws(cfg), cfg)


def _region_sql(how: str = "both", certain: bool = False) -> dict[str, str]:
    """The twins' simulations over the region's own emissions, cases and zones."""
    sims = {
        "em_slots": "SELECT sim_id, row_number() OVER (PARTITION BY sim_id ORDER BY site_id, feature) AS slot, site_id, x, y, amount AS site_amount FROM re, sims",
        "em_drawn": "SELECT sim_id, row_number() OVER (PARTITION BY sim_id ORDER BY md5('p' || sim_id || ':' || site_id || feature), site_id, feature) AS slot, feature, amount FROM re, sims",
        **{k: v.replace("zones", "rz") for k, v in rand_cases("rc").items()},
    }
    texts = {k: v.replace("rand_cases_linked", "rand_rc").replace("(SELECT * FROM emissions, sims)", "(SELECT * FROM re, sims)").replace("(SELECT * FROM cases_linked, sims)", "(SELECT * FROM rc, sims)") for k, v in m.sim_sql(how, "boolean" if certain else "cosine").items()}
    base = {**_REGION, **(tx_ctes("objs", m.GRID, "boolean") if certain else {}), **sims, **texts}
    return {**base, **survivors("rules", "srules", "conf" if certain else "exp_conf", "sup" if certain else "exp_sup", m.MOST)}


add("mine_region_um", lambda s, d: m._show_mined(region_rules(s, d)), sql(m.MINED, **_region_sql()))
add("mine_region_cm", lambda s, d: m._show_mined(region_rules(s, d, mode="certain")), sql(m.MINED, **_region_sql(certain=True)))
add("mine_region_rand_causes", lambda s, d: m._show_mined(region_rules(s, d, "causes")), sql(m.MINED, **_region_sql("causes")))
add("mine_region_rand_effects", lambda s, d: m._show_mined(region_rules(s, d, "effects")), sql(m.MINED, **_region_sql("effects")))


def region_trace(s, d):
    objects, draws = one_region(s, d)
    _, trace = miner.in_blocks(objects, draws(m.RULES), replace(m.RULES, sim_batch=m.TRACED))
    return s.createDataFrame([(t["last_sim"], t["candidates"]) for t in trace if t["candidates"]], "last_sim int, candidates long")


add("filter_trace_region", region_trace, sql(m.TRACE_SQL, **_region_sql()))


def low_support_found(s, d):
    """Significant rules, and those of them with an expected support below 1."""
    return measures.low_support(m.mine_rules(s, d))


add("low_support_found", low_support_found, sql("SELECT count(*) AS n_rules, count(*) FILTER (exp_sup < 1) AS n_low FROM found", **m.mined_sql()))


def given_candidates(s, d):
    """Only the rules of two causes that a user names: here the pairs of the three most common features."""
    top = given.emissions(s, d).groupBy("feature").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "feature").limit(3).select("feature")
    pairs = top.alias("a").join(top.alias("b"), F.col("a.feature") < F.col("b.feature")).select(F.array("a.feature", "b.feature").alias("items"))
    return miner.single_plan(*m.world(s, d), m.RULES, given=pairs)


add("candidates_given", lambda s, d: m._show_mined(given_candidates(s, d)), sql(m.MINED.replace("FROM found", "FROM tested JOIN named USING (key)"), top3="SELECT feature FROM emissions GROUP BY feature ORDER BY count(*) DESC, feature LIMIT 3", named="SELECT a.feature || '+' || b.feature AS key FROM top3 a JOIN top3 b ON a.feature < b.feature", **m.mined_sql()))


def decay_rules(s, d):
    """Significant rules by the decay of probability with distance."""
    return workloads.counts({name: m.mine_rules(s, d, decay=decays.NAMED[name]()) for name in ("cosine", "linear", "steps")}, "decay")


def _decay_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for name in ("cosine", "linear", "steps"):
        base = {**m.ALL, **tx_ctes("objs", m.GRID, name), **rule_ctes(d=D), **m.sim_sql(decay=name), **survivors("rules", "srules", "exp_conf", "exp_sup", m.MOST)}
        out |= _variant(base, f"_{name}", _OBJ)
    return out


add("workload_decay", decay_rules, sql(" UNION ALL ".join(f"SELECT '{n}' AS decay, count(*) AS n FROM found_{n}" for n in ("cosine", "linear", "steps")), **_decay_sql()))

GAMMAS = (0.1, 0.3, 0.5)


def gamma_sweep(s, d):
    """Points, mean area and expected support of all single features as wind stretches buffers more and more."""
    out = None
    placed = staged(m.windy(s, d), "windy")
    for g in GAMMAS:
        shape = buffers.ellipse(placed, g)
        tx = transactions.build(shape, m.GRID)
        one = tx.agg(F.lit(g).alias("gamma"), F.count(F.lit(1)).alias("n_items"), F.round(F.sum("p").cast("double"), 1).alias("sum_p")).crossJoin(shape.agg(F.round(F.avg(F.pi() * F.col("a") * F.col("b")), 4).alias("mean_area")))
        out = one if out is None else out.unionByName(one)
    return out


def _gamma_sql() -> dict[str, str]:
    out = dict(m.W)
    for k, g in enumerate(GAMMAS):
        out |= _variant({**m.ellipse_sql(gamma=str(g)), **tx_ctes("el", m.GRID)}, f"_g{k}", set(m.W))
    return out


add("workload_gamma", gamma_sweep, sql(" UNION ALL ".join(f"SELECT {g}::DOUBLE AS gamma, (SELECT count(*) FROM tx_g{k}) AS n_items, (SELECT round(sum(p)::DOUBLE, 1) FROM tx_g{k}) AS sum_p, (SELECT round(avg(pi() * a * b), 4) FROM el_g{k}) AS mean_area" for k, g in enumerate(GAMMAS)), **_gamma_sql()))


def wind_rules(s, d, gamma: float):
    """Significant rules with the causes' buffers stretched by wind, in simulations too."""
    stations = staged(given.station_places(winds.normals(given.wind_daily(s, d))), "stations")
    blown = lambda rows: buffers.ellipse(winds.interpolate(buffers.log_amount(rows), stations, "idw"), gamma)
    e = staged(given.emissions(s, d), "emissions")
    c = staged(given.cases_linked(s, d, e), "cases")
    both = blown(e).select(*m.KEEP).unionByName(m.near_cases(c).select(*m.KEEP))
    return miner.significant(both, miner.randomiser(e, c, given.zones(s, d), m.RULES, blown, m.near_cases, m.KEEP), m.RULES)


add("workload_wind_rules", lambda s, d: workloads.counts({f"gamma {g}": wind_rules(s, d, g) for g in GAMMAS}, "gamma"))


def embedding_patterns(s, d):
    """Patterns of nearly independent points: what is found is chance."""
    pts = given.embedding_points(s, d)
    box = (-100.0, -100.0, 100.0, 100.0)
    cfg = m.pattern_cfg(box=box, step=2.0)
    draws = lambda first, last: buffers.fixed(randomize.uniform(pts, box, first, last), 4.0)
    return miner.significant(buffers.fixed(pts, 4.0), draws, cfg)


_EMB = grids.Grid(2.0, (-100.0, -100.0, 100.0, 100.0))
_USIM = lambda t: f"-100.0 + 200.0 * {m._usim(t, 'object_id')}"
add("mine_embedding_patterns", lambda s, d: m._show_mined(embedding_patterns(s, d)), sql(m.MINED, emb=f"SELECT *, {m.CIRCLE} FROM (SELECT *, 4.0 AS r FROM embedding_points)", **tx_ctes("emb", _EMB), **pattern_ctes(d=D), obs="SELECT * FROM pats WHERE size >= 2", emb_r=f"SELECT *, {m.CIRCLE} FROM (SELECT sim_id, feature, 4.0 AS r, {_USIM('ux')} AS x, {_USIM('uy')} AS y FROM embedding_points, sims)", **tx_ctes("emb_r", _EMB, by=("sim_id",), name="stx"), **pattern_ctes("stx", ("sim_id",), D, "spats"), **survivors("obs", "spats", "exp_sup", "sup", m.MOST)))


def synth_source(s, d):
    """Pairs with the numbers of suppliers, read as a table of a data source; those of suppliers with a debt are left out."""
    generated.register(s)
    sites = given.table(s, d, "supplier")
    rows = s.read.format("coloc_pairs").option("files", "\n".join(sites.inputFiles())).option("column", "s_suppkey").load()
    solvent = sites.where("s_acctbal >= 0").select(F.col("s_suppkey").cast("string").alias("_site"))
    return rows.join(solvent, F.substring("object_id", 2, 20) == F.col("_site"), "left_semi").groupBy("range_id", "feature").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("x"), 4).alias("mean_x"), F.round(F.avg("y"), 4).alias("mean_y"))


add("synth_source", synth_source, sql("SELECT range_id, feature, count(*) AS n, round(avg(x), 4) AS mean_x, round(avg(y), 4) AS mean_y FROM dp GROUP BY ALL", **{**m.DIST, "ids": "SELECT s_suppkey AS i, s_suppkey // 30 AS set_id, ((s_suppkey // 30) % 10)::INTEGER AS range_id FROM supplier WHERE s_acctbal >= 0", "dp": "SELECT set_id, range_id, 'f1' AS feature, x, y FROM ab UNION ALL SELECT set_id, range_id, 'f2', x + dr * cos(t), y + dr * sin(t) FROM ab"}))
