"""Exact nearest rows by integer inner product with Fagin's threshold algorithm over sorted per-dimension lists.

Candidates lie in shards of bounded size, each with a list of its rows for every dimension, sorted by that component. A query goes
down the lists side by side, from the largest component where its own is positive and from the smallest where it is
negative, in rounds that double the depth. Rows met in any list are scored in full. No row that was not met can score more than the sum of
the query's components times the components where its lists stand; the search ends when that bound is below the k-th
best score known. A query first searches one shard, its home; the k-th score there bounds what any other shard can add, and goes with the query into the
others. Each shard gives k rows at most for a query, and the best k of all are the result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.llm.tables import narrow, ship, staged

SCALE, K, EVERY = 256, 5, 50
#: Rows in a shard of candidates, at most about so many.
SHARD = 4096
FIRST_DEPTH = 16
#: Products are exact in float64 up to here, and in long up to there.
EXACT, LARGEST = 1 << 53, (1 << 63) - 1
FOUND = "query_id long, vector array<long>, width int, home int, floor long, ids array<long>, scores array<long>"


class Lists:
    """A shard's rows and its sorted lists."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        by_id = np.argsort(ids, kind="stable")  # so that ties fall to the smaller id
        self.ids, self.rows = ids[by_id], rows[by_id]
        self.order = np.argsort(self.rows, axis=0, kind="stable")
        self.values = np.take_along_axis(self.rows, self.order, 0)
        self.peak = max((abs(int(v)) for v in (self.rows.min(), self.rows.max())), default=0) if self.rows.size else 0
        self.floats = self.rows.astype(np.float64)

    def products(self, query: np.ndarray):
        """A function from row numbers to exact inner products with the query; those beyond a long stay at its ends."""
        top = self.peak * max((abs(int(v)) for v in query), default=0) * len(query)
        if top < EXACT:
            own = query.astype(np.float64)
            return lambda at: (self.floats[at] @ own).astype(np.int64)
        if top <= LARGEST:
            return lambda at: (self.rows[at] * query).sum(1)
        own = [int(v) for v in query]
        return lambda at: np.array([min(LARGEST, max(-LARGEST - 1, sum(int(a) * b for a, b in zip(row, own)))) for row in self.rows[at].tolist()], np.int64)


def threshold_search(lists: Lists, query_id: int, query: np.ndarray, k: int, floor: float = -np.inf) -> tuple[np.ndarray, np.ndarray, int]:
    """(ids, scores, rows scored) of the shard's best k rows but the query's own, of those scoring at least floor."""
    n = len(lists.ids)
    use = np.flatnonzero(query)
    product = lists.products(query)
    up = query[use] > 0
    met = np.zeros(n, bool)
    met[lists.ids == query_id] = True
    best_id, best = np.zeros(0, np.int64), np.zeros(0, np.int64)
    depth, start, scored = FIRST_DEPTH, 0, 0
    while True:
        depth = min(depth, n)
        spots = np.where(up, n - 1 - np.arange(start, depth)[:, None], np.arange(start, depth)[:, None]) if len(use) else np.zeros((0, 0), np.int64)
        found = lists.order[spots, use].ravel() if len(use) else np.arange(n)
        fresh = np.zeros(n, bool)
        fresh[found] = True
        new = np.flatnonzero(fresh & ~met)
        met[new] = True
        scored += len(new)
        score = product(new)
        best_id, best = np.concatenate([best_id, lists.ids[new]]), np.concatenate([best, score])
        keep = np.lexsort((best_id, -best))[:k]
        best_id, best = best_id[keep], best[keep]
        if depth >= n or not len(use):
            break
        bound = sum(int(a) * int(b) for a, b in zip(query[use], lists.values[np.where(up, n - depth, depth - 1), use]))
        kth = max(best[-1] if len(best) == k else -np.inf, floor)
        if bound < kth:  # a row that ties with the k-th could have a smaller id, so ties go on
            break
        start, depth = depth, 2 * depth
    at = best >= floor
    return best_id[at], best[at], scored


def _rows(cells: pd.Series) -> np.ndarray:
    return np.stack([np.asarray(c, np.int64) for c in cells])


def _searched(frames: Iterator[pd.DataFrame], k: int) -> Iterator[pd.DataFrame]:
    """Frames sorted by width with its candidates (kind 0) before its queries (kind 1)."""
    width, ids, rows, lists = None, [], [], None
    for frame in frames:
        for (number, kind), part in frame.groupby(["width", "kind"], sort=True):
            if number != width:
                width, ids, rows, lists = number, [], [], None
            if kind == 0:
                ids.append(part["vec_id"].to_numpy(np.int64))
                rows.append(_rows(part["vector"]))
                continue
            if lists is None and ids:
                lists = Lists(np.concatenate(ids), np.concatenate(rows))
            out = []
            for query_id, vector, home, floor in zip(part["vec_id"].to_numpy(np.int64), part["vector"], part["home"], part["floor"]):
                least = -np.inf if floor is None or floor != floor else int(floor)
                found, score, _ = threshold_search(lists, int(query_id), np.asarray(vector, np.int64), k, least) if lists else ([], [], 0)
                out.append((query_id, vector, width, home, int(score[-1]) if len(score) == k else None, list(found), list(score)))
            yield pd.DataFrame(out, columns=["query_id", "vector", "width", "home", "floor", "ids", "scores"]).astype({"floor": "Int64"})


def quantised(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = SCALE) -> DataFrame:
    """vec_id, vector (array<long>): floor(scale * x) of every component; vectors that are null, or hold a null or a component
    that is not finite, are left out."""
    rows = narrow(vectors, vec_id=id_col, raw=vector_col).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("raw").cast("array<double>").alias("raw"))
    bad = F.exists("raw", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    whole = rows.where(F.col("raw").isNotNull() & ~bad & F.col("vec_id").isNotNull())
    return whole.select("vec_id", F.transform("raw", lambda x: F.floor(x * scale)).alias("vector"))


def nearest(vectors: DataFrame, k: int = K, every: int = EVERY, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: for every row whose id `every` divides, the k best other rows.

    Ties in score go to the smaller vec_id. Rows without an id take no part. A query leaves out all rows that share its id; repeated
    rows ask once, rows of one id with different vectors share its k results, and each repeated row may be found. Vectors of another length than the query's are never its
    candidates. Scores beyond a long stay at its ends. An empty table gives no rows; other columns are ignored.
    """
    spark = vectors.sparkSession
    ship(spark)
    rows = staged(quantised(vectors, id_col, vector_col).withColumn("width", F.size("vector")), "vectors")
    shards = max(1, -(-rows.count() // SHARD))
    nothing = F.lit(None).cast("long").alias("floor")
    candidates = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int").alias("shard"), F.lit(0).alias("kind"), "width", "vec_id", "vector", F.lit(0).alias("home"), nothing)

    def searched(queries: DataFrame) -> DataFrame:
        """Each task has one shard: all its candidates, and the queries as they stream by."""
        both = candidates.unionByName(queries.select("shard", F.lit(1).alias("kind"), "width", "vec_id", "vector", "home", "floor"))
        dealt = both.repartitionById(shards, F.col("shard")).sortWithinPartitions("width", "kind", "vec_id")
        return dealt.select("width", "kind", "vec_id", "vector", "home", "floor").mapInPandas(partial(_searched, k=k), FOUND)

    asked = rows.where(F.col("vec_id") % every == 0).dropDuplicates(["vec_id", "vector"])
    home = F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(shards)).cast("int")
    first = staged(searched(asked.select("*", home.alias("home"), nothing).withColumn("shard", F.col("home"))), "topk-home")
    others = first.select(F.explode(F.filter(F.sequence(F.lit(0), F.lit(shards - 1)), lambda i: i != F.col("home"))).alias("shard"), "width", F.col("query_id").alias("vec_id"), "vector", "home", "floor")
    found = first if shards == 1 else first.unionByName(searched(others))
    pairs = found.select("query_id", F.explode(F.arrays_zip("ids", "scores")).alias("r")).select("query_id", F.col("r.ids").alias("vec_id"), F.col("r.scores").alias("score"))
    order = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = pairs.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")
