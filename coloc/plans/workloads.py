"""The experiments on the given tables, as functions that return tables of results."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.operators import measures
from coloc.plans import miner
from coloc.plans.config import MinerConfig

Mined = Callable[..., DataFrame]


def counts(results: dict[str, DataFrame], name: str = "variant") -> DataFrame:
    """variant, n of significant results."""
    out = None
    for label, df in results.items():
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(label).alias(name), "n")
        out = one if out is None else out.unionByName(one)
    return out


def shared(results: dict[str, DataFrame]) -> DataFrame:
    """region, n, p_mean: which results are found by which variants."""
    return measures.regions(measures.overlap(results))


def run_times(spark: SparkSession, mine: Callable[[MinerConfig], DataFrame], cfg: MinerConfig, sims: tuple[int, ...] = (9, 19, 39, 59, 79, 99), raised: bool = True) -> DataFrame:
    """r, seconds, n: time to mine with more and more simulations; raised: alpha is at least the smallest p."""
    rows = []
    for r in sims:
        start = time.time()
        n = mine(replace(cfg, sims=r, alpha=max(cfg.alpha, 1.0 / (r + 1)) if raised else cfg.alpha)).count()
        rows.append((r, time.time() - start, n))
    return spark.createDataFrame(rows, "r int, seconds double, n long")


def trace(spark: SparkSession, buffered: DataFrame, randomiser: miner.Randomiser, cfg: MinerConfig) -> DataFrame:
    """block, last_sim, candidates left."""
    _, steps = miner.in_blocks(buffered, randomiser, cfg)
    return spark.createDataFrame([(t["block"], t["last_sim"], t["candidates"]) for t in steps], "block int, last_sim int, candidates long")
