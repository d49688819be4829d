"""Presence probability by distance: functions of (distance, largest distance) to Columns in [0, 1]."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

Decay = Callable[[Column, Column], Column]


def _arrays(fn: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Callable[[Decay], Decay]:
    """Gives a decay its form for arrays."""

    def put(decay: Decay) -> Decay:
        decay.arrays = fn
        return decay

    return put


def of_arrays(decay: Decay) -> Callable[[np.ndarray, np.ndarray], np.ndarray] | None:
    """The decay for arrays of distances and largest distances, if it has that form."""
    return getattr(decay, "arrays", None)


def _part(d: np.ndarray, dmax: np.ndarray) -> np.ndarray:
    """_share() for arrays."""
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(dmax > 0, np.minimum(1.0, d / dmax), (d > 0).astype(float))


def share_of(d: np.ndarray, dmax: np.ndarray) -> np.ndarray:
    """Distances as shares of the largest ones."""
    return _part(d, dmax)


def by_share(fn: Callable[[np.ndarray, np.ndarray], np.ndarray] | None) -> bool:
    """Whether a decay for arrays depends on the share alone and never grows with it."""
    return getattr(fn, "by_share", False)


def _falling(fn: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    fn.by_share = True
    return fn


def _share(d: Column, dmax: Column) -> Column:
    return F.when(dmax > 0, F.least(F.lit(1.0), d / dmax)).otherwise(F.when(d > 0, 1.0).otherwise(0.0))


def steps(width: float = 2.0, levels: Sequence[float] = (1.0, 0.75, 0.5, 0.25)) -> Decay:
    """A level for each range of `width`; none beyond the last, or beyond the largest distance."""
    table = F.array(*[F.lit(float(v)) for v in levels])

    values = np.append(np.array(levels, float), 0.0)

    @_arrays(lambda d, dmax: np.where(d > dmax, 0.0, values[np.minimum(np.floor(d / width), len(levels)).astype(int)]))
    def at(d: Column, dmax: Column) -> Column:
        return F.when(d > dmax, 0.0).otherwise(F.coalesce(F.get(table, F.floor(d / width).cast("int")), F.lit(0.0)))

    return at


def linear() -> Decay:
    return _arrays(_falling(lambda d, dmax: 1.0 - _part(d, dmax)))(lambda d, dmax: 1.0 - _share(d, dmax))


def cosine() -> Decay:
    """Slow at first, then nearly straight, slow again: half a wave of the cosine."""
    return _arrays(_falling(lambda d, dmax: np.cos(np.pi * _part(d, dmax)) / 2.0 + 0.5))(lambda d, dmax: F.cos(F.pi() * _share(d, dmax)) / 2.0 + 0.5)


def boolean() -> Decay:
    """Certain presence in the whole buffer."""
    return _arrays(lambda d, dmax: (d <= dmax).astype(float))(lambda d, dmax: F.when(d <= dmax, 1.0).otherwise(0.0))


def custom(fn: Decay) -> Decay:
    return lambda d, dmax: F.greatest(F.lit(0.0), F.least(F.lit(1.0), fn(d, dmax)))


NAMED: dict[str, Callable[[], Decay]] = {"steps": steps, "linear": linear, "cosine": cosine, "boolean": boolean}
