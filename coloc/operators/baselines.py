"""The methods it is compared with: thresholds, level-wise growth, neighbour cliques, other ways to make transactions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.operators import itemsets
from coloc.sources.staging import staged


def mean_conf(rules: DataFrame, measure: str = "exp_conf", mean_over: str = "occurring") -> DataFrame:
    """rules with threshold (mean measure over the rules that occur, or over all) and kept."""
    rows = rules.where(F.col(measure) > 0) if mean_over == "occurring" else rules
    cut = rows.agg(F.avg(F.coalesce(F.col(measure), F.lit(0.0))).alias("threshold"))
    return rules.crossJoin(F.broadcast(cut)).withColumn("kept", F.coalesce(F.col(measure) >= F.col("threshold"), F.lit(False)))


def support_conf(rules: DataFrame, min_sup: float, min_conf: float, support: str = "sup", measure: str = "conf") -> DataFrame:
    return rules.where((F.col(support) >= min_sup) & (F.col(measure) >= min_conf))


def levelwise(tx: DataFrame, min_sup: int, d: int = 3) -> DataFrame:
    """key, size, sup of sets grown from frequent sets only: a set with a rare subset is never looked at."""
    by = [c for c in ("tx_id", "gi", "gj") if c in tx.columns]
    one = tx.groupBy("feature").agg(F.count(F.lit(1)).alias("sup")).where(F.col("sup") >= min_sup)
    level = tx.join(one.select("feature"), "feature", "left_semi").select(*by, F.col("feature").alias("last"), F.col("feature").alias("key"))
    single = level.select(*by, F.col("last").alias("next"))
    out = one.select(F.col("feature").alias("key"), F.lit(1).alias("size"), "sup")
    for size in range(2, d + 1):
        grown = level.join(single, by).where(F.col("last") < F.col("next")).select(*by, F.col("next").alias("last"), F.concat_ws(itemsets.SEP, "key", "next").alias("key"))
        frequent = grown.groupBy("key").agg(F.count(F.lit(1)).alias("sup")).where(F.col("sup") >= min_sup)
        out = out.unionByName(frequent.select("key", F.lit(size).alias("size"), "sup"))
        level = grown.join(frequent.select("key"), "key", "left_semi").select(*by, "last", "key")
    return out


def neighbours(objects: DataFrame, dist: float) -> DataFrame:
    """Pairs (f1, o1, f2, o2) of objects of different features (f1 < f2) within dist, by buckets of that size."""
    by = [c for c in ("sim_id", "set_id") if c in objects.columns]
    rows = objects.select(*by, "feature", "object_id", "x", "y", F.floor(F.col("x") / dist).alias("bx"), F.floor(F.col("y") / dist).alias("by_"))
    near = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)]))
    spread = rows.withColumn("n", near).select(*by, (F.col("bx") + F.col("n.i")).alias("bx"), (F.col("by_") + F.col("n.j")).alias("by_"), F.col("feature").alias("f2"), F.col("object_id").alias("o2"), F.col("x").alias("x2"), F.col("y").alias("y2"))
    one = rows.select(*by, "bx", "by_", F.col("feature").alias("f1"), F.col("object_id").alias("o1"), F.col("x").alias("x1"), F.col("y").alias("y1"))
    pairs = one.join(spread, [*by, "bx", "by_"])
    return pairs.where((F.col("f1") < F.col("f2")) & (F.pow(F.col("x1") - F.col("x2"), 2) + F.pow(F.col("y1") - F.col("y2"), 2) <= dist * dist)).select(*by, "f1", "o1", "f2", "o2")


def cliques(objects: DataFrame, dist: float, d: int = 3) -> DataFrame:
    """features, members: sets of 2 to d objects of different features that are all within dist of each other, in the order of features.

    A clique grows by an object that neighbours its first and, each in a join, all its other members.
    """
    by = [c for c in ("sim_id", "set_id") if c in objects.columns]
    pairs = staged(neighbours(objects, dist), "neighbours")
    level = pairs.select(*by, F.array("f1", "f2").alias("features"), F.array("o1", "o2").alias("members"))
    out = level
    for size in range(2, d):
        last = level.select(*by, "features", "members", F.col("members")[0].alias("o1"), F.col("features")[0].alias("f1"))
        grown = last.join(pairs, [*by, "f1", "o1"]).where(F.col("f2") > F.element_at("features", -1)).select(*by, "features", "members", "f2", "o2")
        for k in range(1, size):
            seen = pairs.select(*by, F.col("f1").alias("fk"), F.col("o1").alias("ok"), "f2", "o2")
            grown = grown.withColumns({"fk": F.col("features")[k], "ok": F.col("members")[k]}).join(seen, [*by, "fk", "ok", "f2", "o2"], "left_semi").select(*by, "features", "members", "f2", "o2")
        level = grown.select(*by, F.array_append("features", F.col("f2")).alias("features"), F.array_append("members", F.col("o2")).alias("members"))
        out = out.unionByName(level)
    return out


#: Side of the squares whose objects are looked at together, in distances.
SQUARE = 4


def _members(part: pd.DataFrame, dist: float, d: int) -> pd.DataFrame:
    """features, feature, n: own objects of a feature that are in a clique of the set of 2 or 3 features. part: feature, x, y, own of a square and what is near it."""
    part = part.sort_values("feature", kind="stable")
    names, at = np.unique(part["feature"].to_numpy().astype(str), return_inverse=True)
    first = np.searchsorted(at, np.arange(len(names)))
    x, y, own = part["x"].to_numpy(), part["y"].to_numpy(), np.flatnonzero(part["own"].to_numpy())
    near = np.empty((len(x), len(x)) if d > 2 else (len(own), len(x)), bool)
    for k, i in enumerate(range(len(x)) if d > 2 else own):
        near[k] = (x - x[i]) ** 2 + (y - y[i]) ** 2 <= dist * dist
    of_own = np.logical_or.reduceat(near[own] if d > 2 else near, first, axis=1) if len(own) else np.zeros((0, len(names)), bool)
    pairs = np.zeros((len(names), len(names)), np.int64)
    np.add.at(pairs, at[own], of_own)
    out = [([names[min(a, b)], names[max(a, b)]], names[a], int(pairs[a, b])) for a, b in zip(*np.nonzero(pairs)) if a != b]
    if d > 2:
        triples = np.zeros((len(names),) * 3, np.int64)
        for i in own:
            by = np.flatnonzero(near[i])
            by = by[at[by] != at[i]]
            if len(by) > 1:
                here = at[by]
                starts = np.flatnonzero(np.r_[True, here[1:] != here[:-1]])
                both = np.logical_or.reduceat(np.logical_or.reduceat(near[np.ix_(by, by)], starts, axis=0), starts, axis=1)
                one, two = np.nonzero(np.triu(both, 1))
                triples[at[i], here[starts[one]], here[starts[two]]] += 1
        out += [(sorted((names[a], names[b], names[c])), names[a], int(triples[a, b, c])) for a, b, c in zip(*np.nonzero(triples))]
    return pd.DataFrame(out, columns=["features", "feature", "n"])


def _in_squares(objects: DataFrame, dist: float, d: int) -> DataFrame:
    """Objects in cliques by sim_id, set_id, features and feature, from squares with what is within dist of them; no pair is ever a row."""
    by = [c for c in ("sim_id", "set_id") if c in objects.columns]
    kinds = "".join(f"{c} long, " for c in by)
    side = dist * SQUARE
    rows = objects.select(*[F.col(c).cast("long").alias(c) for c in by], "feature", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")).where("feature is not null")

    def spread(parts):
        for part in parts:
            part = part[part["x"].notna() & part["y"].notna()]
            bx, by_ = np.floor(part["x"] / side), np.floor(part["y"] / side)
            for i in (-1, 0, 1):
                for j in (-1, 0, 1):
                    # a little more than the distance, as borders are rounded
                    off = lambda v, b, k: (v - b * side >= side - dist * 1.001) if k > 0 else (v - b * side <= dist * 1.001) if k < 0 else np.ones(len(part), bool)
                    here = off(part["x"], bx, i) & off(part["y"], by_, j)
                    yield part[here].assign(bx=(bx[here] + i).astype("int64"), by_=(by_[here] + j).astype("int64"), own=i == 0 and j == 0)

    placed = rows.mapInPandas(spread, f"{kinds}feature string, x double, y double, bx long, by_ long, own boolean")
    keys = [*by, "bx", "by_"]
    placed = placed.repartition(int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)

    def one(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        out = _members(part, dist, d)
        for c, v in zip(by, key):
            out.insert(0, c, v)
        return out[[*by, "features", "feature", "n"]]

    found = placed.groupBy(*keys).applyInPandas(one, f"{kinds}features array<string>, feature string, n long")
    return found.groupBy(*by, "features", "feature").agg(F.sum("n").alias("n"))


def participation(objects: DataFrame, dist: float, min_pi: float = 0.0, d: int = 2, one_row: bool = False) -> DataFrame:
    """key, size, pi of sets of 2 to d features: the smallest share of a feature's objects that are in a clique of the set.

    one_row: an object has one row, so those of up to three features are counted square by square and cliques are never listed.
    """
    by = [c for c in ("sim_id", "set_id") if c in objects.columns]
    if one_row and d <= 3:
        total = objects.groupBy(*by, "feature").agg(F.count(F.lit(1)).alias("t"))
        in_any = _in_squares(objects, dist, d)
    else:
        total = objects.groupBy(*by, "feature").agg(F.countDistinct("object_id").alias("t"))
        each = cliques(objects, dist, d).select(*by, "features", F.explode(F.arrays_zip("features", "members")).alias("m"))
        in_any = each.groupBy(*by, "features", F.col("m.features").alias("feature")).agg(F.countDistinct("m.members").alias("n"))
    share = in_any.join(total, [*by, "feature"]).groupBy(*by, "features").agg(F.min(F.col("n") / F.col("t")).alias("pi"))
    return share.select(*by, F.array_join("features", itemsets.SEP).alias("key"), F.size("features").alias("size"), "pi").where(F.col("pi") >= min_pi)


def window_tx(objects: DataFrame, w: float) -> DataFrame:
    """Transactions of disjoint square cells: neighbours across a border are lost."""
    return objects.groupBy(F.floor(F.col("x") / w).alias("gi"), F.floor(F.col("y") / w).alias("gj"), "feature").agg(F.count(F.lit(1)).cast("int").alias("n_inst"), F.lit(1.0).cast("decimal(18,12)").alias("p"))


def reference_tx(objects: DataFrame, ref: str, dist: float) -> DataFrame:
    """A transaction for each object of a reference feature: an object near two of them counts twice."""
    centre = objects.where(F.col("feature") == ref).select(F.col("object_id").alias("tx_id"), F.col("x").alias("x0"), F.col("y").alias("y0"), F.floor(F.col("x") / dist).alias("bx"), F.floor(F.col("y") / dist).alias("by_"))
    near = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)]))
    other = objects.where(F.col("feature") != ref).withColumn("n", near).select("feature", "x", "y", (F.floor(F.col("x") / dist) + F.col("n.i")).alias("bx"), (F.floor(F.col("y") / dist) + F.col("n.j")).alias("by_"))
    found = centre.join(other, ["bx", "by_"]).where(F.pow(F.col("x") - F.col("x0"), 2) + F.pow(F.col("y") - F.col("y0"), 2) <= dist * dist)
    rows = found.select("tx_id", "feature").unionByName(centre.select("tx_id", F.lit(ref).alias("feature")))
    return rows.groupBy("tx_id", "feature").agg(F.count(F.lit(1)).cast("int").alias("n_inst"))


def overlap_threshold(tx: DataFrame, min_cov: float) -> DataFrame:
    """key, cov of feature pairs: points covered by both over points covered by either."""
    cover = tx.groupBy("feature").agg(F.count(F.lit(1)).alias("n"))
    one, two = tx.select("gi", "gj", F.col("feature").alias("f1")), tx.select("gi", "gj", F.col("feature").alias("f2"))
    both = one.join(two, ["gi", "gj"]).where("f1 < f2").groupBy("f1", "f2").agg(F.count(F.lit(1)).alias("c"))
    rows = both.join(cover.select(F.col("feature").alias("f1"), F.col("n").alias("n1")), "f1").join(cover.select(F.col("feature").alias("f2"), F.col("n").alias("n2")), "f2")
    return rows.select(F.concat_ws(itemsets.SEP, "f1", "f2").alias("key"), (F.col("c") / (F.col("n1") + F.col("n2") - F.col("c"))).alias("cov")).where(F.col("cov") >= min_cov)
