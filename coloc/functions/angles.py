"""Wind as speed and compass bearing, and as components."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def octant(degrees: Column) -> Column:
    """The nearest of eight compass points, 0 for north, clockwise."""
    return F.floor(F.pmod(degrees + 22.5, F.lit(360.0)) / 45).cast("int")


def components(speed: Column, degrees: Column) -> tuple[Column, Column]:
    """(by sine, by cosine): east and north of a compass bearing."""
    return speed * F.sin(F.radians(degrees)), speed * F.cos(F.radians(degrees))


def speed(x: Column, y: Column) -> Column:
    return F.sqrt(x * x + y * y)


def bearing(x: Column, y: Column) -> Column:
    """Compass bearing in [0, 360) of sine part x and cosine part y."""
    return F.pmod(F.degrees(F.atan2(x, y)) + 360.0, F.lit(360.0))


def bearing_by_quadrant(x: Column, y: Column) -> Column:
    """The same from four quadrant formulas on absolute ratios; null without wind."""
    ax, ay = F.abs(x), F.abs(y)
    return (
        F.when((x == 0) & (y == 0), F.lit(None).cast("double"))
        .when((x >= 0) & (y > 0), F.degrees(F.atan(ax / ay)))
        .when((x > 0) & (y <= 0), F.degrees(F.atan(ay / ax)) + 90.0)
        .when((x <= 0) & (y < 0), F.degrees(F.atan(ax / ay)) + 180.0)
        .otherwise(F.degrees(F.atan(ay / ax)) + 270.0)
    )
