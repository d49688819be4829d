"""Regular grids, kept as step, offset and bounds; points exist only where something is near."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KM_PER_DEGREE = 111.32


@dataclass(frozen=True)
class Grid:
    """Points (dx + gi * step, dy + gj * step) within the box. With metric geodesic, x and y are degrees and step is km: a row's step in
    longitude grows with its latitude."""

    step: float
    box: tuple[float, float, float, float]
    dx: float = 0.0
    dy: float = 0.0
    metric: str = "planar"

    def __post_init__(self):
        if self.step <= 0:
            raise ValueError("a grid's step must be above 0")

    @property
    def bounds(self) -> tuple[int, int, int, int]:
        x0, y0, x1, y1 = self.box
        tiny = 1e-9
        return (math.ceil((x0 - self.dx) / self.step - tiny), math.floor((x1 - self.dx) / self.step + tiny), math.ceil((y0 - self.dy) / self.step - tiny), math.floor((y1 - self.dy) / self.step + tiny))

    def x(self, gi: Column) -> Column:
        return gi * self.step + self.dx

    def y(self, gj: Column) -> Column:
        return gj * self.step + self.dy


def fixed(x0: float, y0: float, x1: float, y1: float, h: float, metric: str = "planar") -> Grid:
    return Grid(h, (x0, y0, x1, y1), metric=metric)


def from_objects(objects: DataFrame, h: float, metric: str = "planar") -> Grid:
    """The box of all objects' places: one row comes to the driver."""
    r = objects.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    return Grid(h, tuple(float(v) if v is not None else 0.0 for v in r), metric=metric)


def shift(grid: Grid, dx: float, dy: float) -> Grid:
    return replace(grid, dx=dx, dy=dy)


def points(spark: SparkSession, grid: Grid) -> DataFrame:
    """gi, gj, gx, gy of every grid point."""
    if grid.metric == "geodesic":
        return _geodesic(spark, grid)
    i0, i1, j0, j1 = grid.bounds
    wide, high = max(0, i1 - i0 + 1), max(0, j1 - j0 + 1)
    rows = spark.range(wide * high)
    rows = rows.select((F.col("id") % max(wide, 1) + i0).alias("gi"), (F.floor(F.col("id") / max(wide, 1)) + j0).alias("gj"))
    return rows.select("gi", "gj", grid.x(F.col("gi")).alias("gx"), grid.y(F.col("gj")).alias("gy"))


def _geodesic(spark: SparkSession, grid: Grid) -> DataFrame:
    x0, y0, x1, y1 = grid.box
    rows = spark.range(int((y1 - y0) * KM_PER_DEGREE / grid.step) + 1).select(F.col("id").alias("gj"), (y0 + F.col("id") * (grid.step / KM_PER_DEGREE)).alias("gy"))
    dlon = grid.step / (KM_PER_DEGREE * F.cos(F.radians("gy")))
    cells = rows.withColumn("dlon", dlon).withColumn("gi", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((x1 - x0) / F.col("dlon")))))
    return cells.select("gi", "gj", (x0 + F.col("gi") * F.col("dlon")).alias("gx"), "gy")


def suggest_step(buffered: DataFrame, points_per_radius: float = 4.0) -> DataFrame:
    """step: the mean buffer radius over the points wanted along it."""
    return buffered.agg((F.avg("r") / points_per_radius).alias("step"))
