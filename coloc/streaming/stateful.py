"""Running expected supports with state per tile: a late, larger probability corrects what was counted before."""

from __future__ import annotations

import json
import math
from collections.abc import Iterator
from functools import partial
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STATE = "points string"
OUTPUT = "key string, delta double"


def _supports(items: dict[str, float], d: int) -> dict[str, float]:
    names = sorted(items)
    return {"+".join(c): math.prod(items[f] for f in c) for n in range(1, d + 1) for c in combinations(names, n)}


def _updated(key: tuple, frames: Iterator[pd.DataFrame], state, d: int) -> Iterator[pd.DataFrame]:
    """State: point -> feature -> largest probability. Emits the change of each pattern's expected support."""
    held: dict[str, dict[str, float]] = json.loads(state.get[0]) if state.exists else {}
    change: dict[str, float] = {}
    for frame in frames:
        for (gi, gj), part in frame.groupby(["gi", "gj"]):
            point = held.setdefault(f"{gi},{gj}", {})
            before = _supports(point, d)
            for f, p in zip(part["feature"], part["p"]):
                point[f] = max(point.get(f, 0.0), float(p))
            for k, v in _supports(point, d).items():
                if v != before.get(k, 0.0):
                    change[k] = change.get(k, 0.0) + v - before.get(k, 0.0)
    state.update((json.dumps(held),))
    yield pd.DataFrame({"key": list(change), "delta": list(change.values())}, columns=["key", "delta"])


def running_supports(pts: DataFrame, tile: int = 16, d: int = 3) -> DataFrame:
    """Stream of (key, delta) for patterns of up to d features; the sum of deltas of a key is its expected support so far.

    State is bounded by a tile's points and stays, as a support has no end.
    """
    keyed = pts.select(F.floor(F.col("gi") / tile).alias("ti"), F.floor(F.col("gj") / tile).alias("tj"), "gi", "gj", "feature", "p")
    return keyed.groupBy("ti", "tj").applyInPandasWithState(partial(_updated, d=d), OUTPUT, STATE, "append", "NoTimeout")
