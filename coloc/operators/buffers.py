"""Buffers around objects: r, a, b (semi-axes), cx, cy (centre) and ux, uy (axis direction) beside x, y (source)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SOURCE_AT = {"half": 0.5, "focus": 1.0, "centre": 0.0}


def _circle(objects: DataFrame, r: Column) -> DataFrame:
    rows = objects.withColumn("r", r)
    return rows.withColumns({"a": F.col("r"), "b": F.col("r"), "cx": F.col("x"), "cy": F.col("y"), "ux": F.lit(1.0), "uy": F.lit(0.0)})


def fixed(objects: DataFrame, r: float) -> DataFrame:
    return _circle(objects, F.lit(float(r)))


def by_feature(objects: DataFrame, radii: DataFrame) -> DataFrame:
    """radii: feature, r. Objects of other features have no buffer and are left out."""
    return _circle(objects.join(radii.select("feature", F.col("r").cast("double").alias("_r")), "feature"), F.col("_r")).drop("_r")


GROWTH = {"log": F.log, "log1p": F.log1p, "sqrt": F.sqrt, "linear": lambda c: c}


def amount(objects: DataFrame, fn: str = "log", unit: float = 1.0, floor: float = 0.0) -> DataFrame:
    """Radius as a growing function of the released amount; objects whose radius is not above the floor have no buffer."""
    return _circle(objects.where(F.col("amount") > 0), F.greatest(GROWTH[fn](F.col("amount") / unit), F.lit(floor))).where("r > 0")


def log_amount(objects: DataFrame, unit: float = 1.0, floor: float = 0.0) -> DataFrame:
    return amount(objects, "log", unit, floor)


def inner_radius(buffered: DataFrame, r0: Column) -> DataFrame:
    """A ring: no presence nearer to the source than r0."""
    return buffered.withColumn("r0", r0)


def ellipse(buffered: DataFrame, gamma: Column | float = 0.3, source_at: str = "half") -> DataFrame:
    """Circles of objects with wind (speed, bearing: where it blows to) as ellipses of the same area.

    The long semi-axis grows with speed; the centre lies downwind of the source by the chosen share of the
    distance from the centre to a focus. Without wind the circle stays.
    """
    k = SOURCE_AT[source_at]
    g = F.lit(float(gamma)) if isinstance(gamma, (int, float)) else gamma
    rows = buffered.withColumn("a", F.col("r") + g * F.col("speed"))
    rows = rows.withColumns({"b": F.col("r") * F.col("r") / F.col("a"), "ux": F.sin(F.radians("bearing")), "uy": F.cos(F.radians("bearing"))})
    shift = k * F.sqrt(F.greatest(F.col("a") * F.col("a") - F.col("b") * F.col("b"), F.lit(0.0)))
    return rows.withColumns({"cx": F.col("x") + shift * F.col("ux"), "cy": F.col("y") + shift * F.col("uy")})


def gamma_of(default: float, by_name: dict[str, float]) -> Column:
    """Stretching per feature."""
    out = F.lit(float(default))
    for name, value in sorted(by_name.items()):
        out = F.when(F.col("feature") == name, float(value)).otherwise(out)
    return out


def ellipse_multi(buffered: DataFrame, winds: DataFrame, gamma: float = 0.3, source_at: str = "half") -> DataFrame:
    """One ellipse per season of winds (season, speed, bearing), united by the largest probability later."""
    return ellipse(buffered.drop("speed", "bearing").crossJoin(F.broadcast(winds)), gamma, source_at)
