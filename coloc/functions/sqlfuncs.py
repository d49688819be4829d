"""SQL functions for analysts: bodies in SQL, so that the optimizer inlines them, and two table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

BODIES = {
    "prob_cosine": ("d DOUBLE, dmax DOUBLE", "DOUBLE", "cos(pi() * least(1D, d / dmax)) / 2D + 0.5D"),
    "prob_linear": ("d DOUBLE, dmax DOUBLE", "DOUBLE", "1D - least(1D, d / dmax)"),
    "prob_steps": ("d DOUBLE, dmax DOUBLE", "DOUBLE", "CASE WHEN d > dmax THEN 0D ELSE coalesce(get(array(1D, 0.75D, 0.5D, 0.25D), cast(floor(d / 2D) AS INT)), 0D) END"),
    "p_value_of": ("exceed BIGINT, sims BIGINT", "DOUBLE", "(exceed + 1) / (sims + 1)"),
    "bearing_of": ("x DOUBLE, y DOUBLE", "DOUBLE", "pmod(degrees(atan2(x, y)) + 360D, 360D)"),
}


@udtf(returnType="gi long, gj long")
class GridCells:
    """grid_cells(x, y, r, h): lattice points within r."""

    def eval(self, x: float, y: float, r: float, h: float) -> Iterator[tuple[int, int]]:
        import math

        for i in range(math.ceil((x - r) / h), math.floor((x + r) / h) + 1):
            for j in range(math.ceil((y - r) / h), math.floor((y + r) / h) + 1):
                if (i * h - x) ** 2 + (j * h - y) ** 2 <= r * r:
                    yield i, j


@udtf(returnType="key string, size int")
class ItemsetsOf:
    """itemsets_of(items, d): all sets of 1 to d of the items, in order."""

    def eval(self, items: list, d: int) -> Iterator[tuple[str, int]]:
        from itertools import combinations

        for n in range(1, d + 1):
            for c in combinations(sorted(set(items)), n):
                yield "+".join(c), n


def register(spark: SparkSession) -> None:
    for name, (args, kind, body) in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("grid_cells", GridCells)
    spark.udtf.register("itemsets_of", ItemsetsOf)


@pandas_udf(DoubleType())
def ring_distance(x: pd.Series, y: pd.Series, ring: pd.Series) -> pd.Series:
    """Distance to rings of many points, a whole ring in one numpy pass: the way beside geometry.ring_distance for large rings."""
    import numpy as np

    def away(px: float, py: float, points) -> float:
        at = np.array([(p["x"], p["y"]) for p in points], float)
        one, step = at[:-1], at[1:] - at[:-1]
        size = np.maximum((step**2).sum(1), 1e-300)
        t = np.clip(((np.array([px, py]) - one) * step).sum(1) / size, 0, 1)
        near = np.hypot(*(np.array([px, py]) - one - t[:, None] * step).T).min()
        low, high = one[:, 1], at[1:, 1]
        crossed = ((low > py) != (high > py)) & (px < step[:, 0] * (py - low) / np.where(high == low, 1, high - low) + one[:, 0])
        return 0.0 if crossed.sum() % 2 else float(near)

    return pd.Series([away(a, b, c) for a, b, c in zip(x, y, ring)])


@pandas_udf(DoubleType())
def sum_of_products(p: pd.Series, q: pd.Series) -> float:
    """Expected support of a pair as an aggregate of its own, to hold the built-in sums against."""
    return float((p * q).sum())
