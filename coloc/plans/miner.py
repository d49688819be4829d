"""Significant patterns and rules: observed prevalence, simulations in blocks, and decisions.

Features become codes before anything is expanded, and sets of codes one long. Candidates that are decided leave the computation before
the expansion where they can, and always before the sums. Results have names again: items, and key for the eye.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.functions import decay as decays
from coloc.functions.tests_of_chance import most_exceedances
from coloc.operators import dense, grids, itemsets, prevalence, randomize, redraw, significance, transactions
from coloc.operators.indexing import dense_index
from coloc.plans.config import MinerConfig
from coloc.sources.staging import dropped, staged

#: Keys that are sent to all executors at once, at most; beyond, survivors are joined by shuffling.
SMALL = 500_000
#: Buffered objects of the simulations (first, last): DataFrame with sim_id.
Randomiser = Callable[[int, int], DataFrame]
#: Observed candidates -> those to be tested.
Choice = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class Codes:
    """names: feature, code from 1 in the order of features. Without bits sets are too large for a long and stay arrays of names."""

    names: DataFrame
    bits: int | None
    effect: str | int | None
    d: int

    def encoded(self, objects: DataFrame) -> DataFrame:
        """objects with codes as features; those of unknown features are gone."""
        if self.bits is None:
            return objects
        return objects.join(self.names, "feature").drop("feature").withColumnRenamed("code", "feature").select(*objects.columns)

    def key(self, sets: DataFrame) -> DataFrame:
        """key, size of sets (items: arrays of names in any order); sets with unknown names are gone."""
        sets = sets.select(F.array_sort(F.array_distinct("items")).alias("items")).distinct()
        if self.bits is None:
            return sets.select(F.col("items").alias("key"), F.size("items").alias("size"))
        each = sets.select("items", F.posexplode("items").alias("at", "feature")).join(self.names, "feature")
        part = F.col("code").cast("long") * F.pow(F.lit(2.0), F.lit(self.bits) * (F.lit(self.d - 1) - F.col("at"))).cast("long")
        whole = each.groupBy("items").agg(F.sum(part).alias("key"), F.count(F.lit(1)).alias("n"))
        return whole.where(F.col("n") == F.size("items")).where(F.col("n") <= self.d).select("key", F.col("n").cast("int").alias("size"))

    def features(self, rows: DataFrame) -> DataFrame:
        """feature of the sets in rows (key, size)."""
        if self.bits is None:
            return rows.select(F.explode("key").alias("feature")).distinct()
        return rows.select(F.explode(self._codes()).alias("feature")).where("feature > 0").select(F.col("feature").cast("int")).distinct()

    def _codes(self):
        return F.array(*[F.shiftright("key", self.bits * (self.d - n)).bitwiseAND((1 << self.bits) - 1) for n in range(1, self.d + 1)])

    def decoded(self, rows: DataFrame) -> DataFrame:
        """rows with items, an array of names, and key, the names joined."""
        if self.bits is None:
            return itemsets.named(rows)
        each = rows.select("key").distinct().select("key", F.posexplode(self._codes()).alias("at", "code")).where("code > 0").join(self.names, "code")
        names = each.groupBy("key").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "feature"))), lambda x: x["feature"]).alias("items"))
        return rows.join(names, "key").withColumn("key", F.array_join("items", itemsets.SEP))


def codes(objects: DataFrame, cfg: MinerConfig) -> Codes:
    names = dense_index(objects.select("feature").where("feature is not null").distinct(), "feature", name="code")
    names = staged(names.select("feature", (F.col("code") + 1).cast("int").alias("code")), "codes")
    bits = max(1, names.count().bit_length())
    if bits * cfg.d > 63:
        return Codes(names, None, cfg.effect, cfg.d)
    found = names.where(F.col("feature") == cfg.effect).first() if cfg.effect is not None else None
    return Codes(names, bits, found["code"] if found else 0, cfg.d)


def measured(buffered: DataFrame, grid: grids.Grid, cfg: MinerConfig, known: Codes | None = None, live: DataFrame | None = None) -> DataFrame:
    """Prevalence of everything that occurs, by sim_id if the objects have it; by codes if known ones are given, and then of the live keys only."""
    objects = known.encoded(buffered) if known else buffered
    decay = cfg.decay or decays.cosine()
    if known and known.bits is not None and dense.fits(objects, grid, decay, cfg.mode, cfg.strategy, cfg.combine):
        effect = known.effect if cfg.objective == "rules" else None
        found = dense.tiles(objects, grid, decay, cfg.mode, cfg.dmax, effect, cfg.d, known.bits, live)
        return prevalence.rules_of(found) if cfg.objective == "rules" else prevalence.sets_of(found)
    if known:  # a few objects make many cells, so even a few are spread over all tasks
        tasks = int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        objects = objects.repartition(tasks, *[c for c in ("sim_id", "object_id") if c in objects.columns])
    tx = transactions.build(objects, grid, cfg.decay, cfg.mode, cfg.strategy, cfg.dmax, cfg.combine)
    bits, effect = (known.bits, known.effect) if known else (None, cfg.effect)
    wide = transactions.to_wide(tx, effect if cfg.objective == "rules" else None)
    live = live if bits is not None else None
    return prevalence.confidences(wide, effect, cfg.d, bits, live) if cfg.objective == "rules" else prevalence.supports(wide, cfg.d, bits, live)


def observed(buffered: DataFrame, grid: grids.Grid, cfg: MinerConfig, known: Codes | None = None) -> DataFrame:
    """Candidates with their observed measure: the first filter drops those without support, or below a threshold."""
    rows = measured(buffered, grid, cfg, known).where(F.col("exp_sup") > 0 if cfg.mode == "uncertain" else F.col("sup") > 0)
    if known and known.bits is None:
        rows = rows.drop("key").withColumnRenamed("items", "key")
    if cfg.objective == "patterns":
        rows = rows.where("size >= 2")
    return rows.where(F.col("exp_sup") >= cfg.min_exp_sup) if cfg.min_exp_sup is not None else rows


def _grid(buffered: DataFrame, cfg: MinerConfig) -> grids.Grid:
    return grids.Grid(cfg.step, cfg.box, metric=cfg.metric) if cfg.box else grids.from_objects(buffered, cfg.step, cfg.metric)


class _Run:
    """What blocks and the single plan share: the grid, the codes, the observed candidates and the simulated measures."""

    def __init__(self, buffered: DataFrame, randomiser: Randomiser, cfg: MinerConfig, given: DataFrame | None, choose: Choice | None):
        self.cfg, self.randomiser, self.paths = cfg, randomiser, []
        buffered = staged(buffered, "objects", self.paths)
        self.grid, self.codes = _grid(buffered, cfg), codes(buffered, cfg)
        rows = observed(buffered, self.grid, cfg, self.codes)
        if given is not None:
            rows = rows.join(self.codes.key(given).select("key"), "key", "left_semi")
        rows = staged(rows, "observed", self.paths)
        self.observed = staged(choose(rows), "chosen", self.paths) if choose else rows
        self.again = self._again(buffered)

    def _again(self, buffered: DataFrame) -> list | None:
        """What tasks draw simulations from by themselves, if the randomiser has such a form and all else fits it."""
        cfg, groups = self.cfg, getattr(self.randomiser, "groups", None)
        decay = cfg.decay or decays.cosine()
        if groups is None or self.codes.bits is None or not dense.fits(buffered, self.grid, decay, cfg.mode, cfg.strategy, cfg.combine):
            return None
        return groups({r["feature"]: r["code"] for r in self.codes.names.collect()})

    def exceedances(self, alive: DataFrame, n: int, first: int, last: int) -> DataFrame:
        """key, exceed of n live candidates in the simulations first to last."""
        needed = self.codes.features(alive)
        if self.again is not None:
            return significance.exceedances(alive, self._drawn_again(alive, needed, n, first, last), self.cfg.measure)
        objects = self.codes.encoded(self.randomiser(first, last))
        if self.cfg.objective == "rules":
            effect = F.lit(self.codes.effect).alias("feature")
            needed = needed.union(needed.sparkSession.range(1).select(effect.cast(needed.schema["feature"].dataType))).distinct()
        objects = objects.join(needed, "feature", "left_semi").select(*objects.columns)
        sims = measured(objects, self.grid, self.cfg, _Plain(self.codes), alive.select("key", "size") if n <= SMALL else None)
        if self.codes.bits is None:
            sims = sims.drop("key").withColumnRenamed("items", "key")
        return significance.exceedances(alive, sims, self.cfg.measure)

    def _drawn_again(self, alive: DataFrame, needed: DataFrame, n: int, first: int, last: int) -> DataFrame:
        cfg, rules = self.cfg, self.cfg.objective == "rules"
        effect = self.codes.effect if rules else None
        features = [r["feature"] for r in needed.collect()] + ([effect] if rules else [])
        live = alive.select("key", "size") if n <= SMALL else None
        sums = redraw.measured(alive.sparkSession, self.again, first, last, self.grid, cfg.decay or decays.cosine(), cfg.mode, cfg.dmax, effect, cfg.d, self.codes.bits, features, live)
        return prevalence.rules_of(sums) if rules else prevalence.sets_of(sums)

    def done(self, rows: DataFrame, name: str) -> DataFrame:
        out = staged(self.codes.decoded(rows), name)
        for path in self.paths:
            dropped(out.sparkSession, path)
        return out


class _Plain(Codes):
    """Codes of objects that have them already."""

    def __init__(self, known: Codes):
        super().__init__(known.names, known.bits, known.effect, known.d)

    def encoded(self, objects: DataFrame) -> DataFrame:
        return objects


def single_plan(buffered: DataFrame, randomiser: Randomiser, cfg: MinerConfig, given: DataFrame | None = None, choose: Choice | None = None) -> DataFrame:
    """All simulations of all candidates in one plan, without dropping any on the way."""
    run = _Run(buffered, randomiser, cfg, given, choose)
    exceed = run.exceedances(run.observed, run.observed.count(), 1, cfg.sims)
    return run.done(significance.decided(run.observed, exceed, cfg.sims, cfg.alpha, cfg.strict), "decided")


def in_blocks(buffered: DataFrame, randomiser: Randomiser, cfg: MinerConfig, given: DataFrame | None = None, choose: Choice | None = None) -> tuple[DataFrame, list[dict]]:
    """(survivors with exceedances, trace of candidates by block). Exceedances only grow, so dropping a candidate as soon as
    they decide against it changes no survivor, whatever the block size. A block expands what survivors use only, and sums survivors only."""
    run = _Run(buffered, randomiser, cfg, given, choose)
    most = most_exceedances(cfg.alpha, cfg.sims, cfg.strict)
    alive = run.observed.withColumn("exceed", F.lit(0))
    trace = [{"block": 0, "last_sim": 0, "candidates": alive.count()}]
    for first in range(1, cfg.sims + 1, cfg.sim_batch):
        last = min(cfg.sims, first + cfg.sim_batch - 1)
        n = trace[-1]["candidates"]
        if not n:
            break
        more = run.exceedances(alive, n, first, last).withColumnRenamed("exceed", "_more")
        alive = alive.join(more, "key", "left").withColumn("exceed", (F.col("exceed") + F.coalesce("_more", F.lit(0))).cast("int")).drop("_more")
        alive = staged(alive.where(F.col("exceed") <= most), "alive", run.paths)
        trace.append({"block": len(trace), "last_sim": last, "candidates": alive.count()})
    rows = alive.withColumns({"p_value": (F.col("exceed") + 1) / (cfg.sims + 1), "significant": F.lit(most >= 0)}).where("significant")
    return run.done(rows, "survivors"), trace


def significant(buffered: DataFrame, randomiser: Randomiser, cfg: MinerConfig, given: DataFrame | None = None, choose: Choice | None = None) -> DataFrame:
    """The significant rules or patterns; given (items: arrays of names) are then the only candidates, and choose picks some of the observed ones."""
    if cfg.early_stop:
        return in_blocks(buffered, randomiser, cfg, given, choose)[0]
    return single_plan(buffered, randomiser, cfg, given, choose).where("significant")


def randomiser(causes: DataFrame, effects: DataFrame, zones: DataFrame | None, cfg: MinerConfig, buffer_causes: Choice, buffer_effects: Choice, keep: tuple[str, ...], circles: bool = False) -> Randomiser:
    """Simulated objects as cfg.randomise, cfg.draws, cfg.apportion and cfg.seed say, buffered anew.

    What is drawn from again in each block, and its places in order, are written once. circles: the buffers are circles whose radius is the same
    wherever an object lies, so tasks may draw simulations by themselves.
    """
    if cfg.randomise not in ("both", "causes", "effects", "uniform"):
        raise ValueError(f"unknown randomisation {cfg.randomise}")
    causes, effects = staged(causes, "causes"), staged(effects, "effects")
    move_causes, move_effects = cfg.randomise in ("both", "causes"), cfg.randomise in ("both", "effects")
    slots = staged(randomize.slots(causes), "slots") if move_causes else None
    n = slots.count() if move_causes else 0
    zones = randomize.bounded(zones) if move_effects else zones
    urban = staged(randomize.ranked(effects), "urban") if move_effects and cfg.apportion == "largest_remainder" else None

    def drawn(first: int, last: int) -> DataFrame:
        if cfg.randomise == "uniform":
            moved, placed = (randomize.uniform(rows, cfg.box, first, last, cfg.seed) for rows in (causes, effects))
        else:
            one = randomize.permute_by_hash if cfg.draws == "bijection" else randomize.permute_features
            extra = {} if cfg.draws == "bijection" else {"seed": cfg.seed}
            moved = one(causes, first, last, placed=slots, n=n, **extra) if move_causes else randomize.with_sims(causes, first, last)
            placed = randomize.by_population(effects, zones, cfg.box, first, last, cfg.apportion, urban, cfg.seed) if move_effects else randomize.with_sims(effects, first, last)
        return buffer_causes(moved).select("sim_id", *keep).unionByName(buffer_effects(placed).select("sim_id", *keep))

    def groups(codes: dict[str, int]) -> list | None:
        if causes.count() + effects.count() > redraw.MOST:
            return None
        if cfg.randomise == "uniform":
            return _all([_uniform(buffer(rows), cfg.box, cfg.seed, codes) for buffer, rows in ((buffer_causes, causes), (buffer_effects, effects))])
        moved = _permuted(slots, buffer_causes, cfg.seed, codes) if move_causes else _still(buffer_causes(causes), codes)
        placed = _by_population(effects, urban, zones, buffer_effects, cfg, codes) if move_effects else [_still(buffer_effects(effects), codes)]
        return _all([moved, *placed])

    if circles and (cfg.randomise == "uniform" or ((cfg.draws == "digest" or not move_causes) and (urban is not None or not move_effects))):
        drawn.groups = groups
    return drawn


def uniform_randomiser(objects: DataFrame, box: tuple[float, float, float, float], buffer: Choice, seed: str = "") -> Randomiser:
    """Objects anywhere in the box, with circles whose radius is the same wherever they lie."""
    objects = staged(objects, "anywhere")

    def drawn(first: int, last: int) -> DataFrame:
        return buffer(randomize.uniform(objects, box, first, last, seed))

    drawn.groups = lambda codes: _all([_uniform(buffer(objects), box, seed, codes)]) if objects.count() <= redraw.MOST else None
    return drawn


def _all(groups: list) -> list | None:
    return None if any(g is None for g in groups) else groups


def _coded(table: pa.Table, codes: dict[str, int]) -> np.ndarray:
    return np.fromiter((codes.get(f, 0) for f in table["feature"].to_pylist()), np.int32, table.num_rows)


def _still(buffered: DataFrame, codes: dict[str, int]) -> redraw.Still:
    t = buffered.select("feature", "r", "x", "y").toArrow()
    return redraw.Still(_coded(t, codes), *[redraw.column(t, c) for c in ("r", "x", "y")])


def _uniform(buffered: DataFrame, box: tuple[float, float, float, float], seed: str, codes: dict[str, int]) -> redraw.Uniform | None:
    t = buffered.select("feature", "r", F.col("object_id").cast("string").alias("key")).toArrow()
    return redraw.Uniform(_coded(t, codes), redraw.column(t, "r"), redraw.keys(t["key"]), box, seed) if not t["key"].null_count else None


def _permuted(slots: DataFrame, buffer: Choice, seed: str, codes: dict[str, int]) -> redraw.Permuted | None:
    radius = buffer(slots).select("slot", "r")
    t = slots.select("slot", "site_id", "feature", "x", "y").join(radius, "slot", "left").toArrow().sort_by("slot")
    if t["site_id"].null_count or t["feature"].null_count:
        return None
    return redraw.Permuted(_coded(t, codes), *[redraw.column(t, c) for c in ("r", "x", "y")], redraw.keys(t["site_id"], t["feature"]), seed)


def _by_population(effects: DataFrame, urban: DataFrame, zones: DataFrame, buffer: Choice, cfg: MinerConfig, codes: dict[str, int]) -> list:
    sides = ("x0", "y0", "x1", "y1")
    shares = randomize.apportion(zones, urban.agg(F.count(F.lit(1)).alias("total"))).where("share > 0").toArrow().sort_by("low")
    every = zones.select(*sides).toArrow()
    key = F.col("object_id").cast("string").alias("key")
    inner = buffer(urban).select("feature", "r", "k", key).toArrow()
    outer = buffer(effects.where("not urban")).select("feature", "r", key).toArrow()
    if every.num_rows > redraw.MOST_ZONES or inner["key"].null_count or outer["key"].null_count:
        return [None]
    high, k = redraw.column(shares, "high"), redraw.column(inner, "k")
    at = np.searchsorted(high, k)
    inner = inner.filter(at < len(high))
    boxes = lambda t: np.column_stack([redraw.column(t, c) for c in sides])
    placed = redraw.Urban(_coded(inner, codes), redraw.column(inner, "r"), redraw.keys(inner["key"]), boxes(shares)[at[at < len(high)]], cfg.seed)
    return [placed, redraw.Rural(_coded(outer, codes), redraw.column(outer, "r"), redraw.keys(outer["key"]), boxes(every), cfg.box, cfg.seed)]
