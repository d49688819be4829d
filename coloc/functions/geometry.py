"""Plane geometry on Columns: ellipses, polylines, rings, and the text form of simple shapes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SLACK = 1e-12


def frame(gx: Column, gy: Column, cx: Column, cy: Column, ux: Column, uy: Column) -> tuple[Column, Column]:
    """Coordinates along and across the direction (ux, uy) seen from (cx, cy)."""
    return (gx - cx) * ux + (gy - cy) * uy, (gy - cy) * ux - (gx - cx) * uy


def inside(gx: Column, gy: Column, b: dict[str, Column]) -> Column:
    """Whether a point lies in the buffer's ellipse, its border included."""
    u, v = frame(gx, gy, b["cx"], b["cy"], b["ux"], b["uy"])
    return (u * u) / (b["a"] * b["a"]) + (v * v) / (b["b"] * b["b"]) <= 1 + SLACK


def half_widths(b: dict[str, Column]) -> tuple[Column, Column]:
    """Of the ellipse's bounding box."""
    aa, bb, xx, yy = b["a"] * b["a"], b["b"] * b["b"], b["ux"] * b["ux"], b["uy"] * b["uy"]
    return F.sqrt(aa * xx + bb * yy), F.sqrt(aa * yy + bb * xx)


def ray(gx: Column, gy: Column, x: Column, y: Column, b: dict[str, Column]) -> Column:
    """Distance from the source (x, y) to the ellipse's border in the direction of the grid point; null at the source itself."""
    d = F.hypot(gx - x, gy - y)
    e1 = ((gx - x) * b["ux"] + (gy - y) * b["uy"]) / d
    e2 = ((gy - y) * b["ux"] - (gx - x) * b["uy"]) / d
    s, _ = frame(x, y, b["cx"], b["cy"], b["ux"], b["uy"])
    aa, bb = b["a"] * b["a"], b["b"] * b["b"]
    p, q, r = (e1 * e1) / aa + (e2 * e2) / bb, (2 * s * e1) / aa, (s * s) / aa - 1
    return F.when(d > 0, (F.sqrt(F.greatest(q * q - 4 * p * r, F.lit(0.0))) - q) / (2 * p))


def segment_distance(px: Column, py: Column, one: Column, two: Column) -> Column:
    """Distance from a point to the segment between two structs (x, y)."""
    dx, dy = two["x"] - one["x"], two["y"] - one["y"]
    size = dx * dx + dy * dy
    t = F.when(size > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), ((px - one["x"]) * dx + (py - one["y"]) * dy) / size))).otherwise(0.0)
    return F.hypot(px - (one["x"] + t * dx), py - (one["y"] + t * dy))


def polyline_distance(px: Column, py: Column, ring: Column) -> Column:
    """Shortest distance to the consecutive points' segments; of a single point the distance to it."""
    pairs = F.zip_with(F.slice(ring, 1, F.greatest(F.size(ring) - 1, F.lit(1))), F.slice(ring, F.least(F.size(ring), F.lit(2)), F.greatest(F.size(ring) - 1, F.lit(1))), lambda a, b: segment_distance(px, py, a, b))
    return F.array_min(pairs)


def in_ring(px: Column, py: Column, ring: Column) -> Column:
    """Whether a point lies inside a closed ring (last point the first again), by counting crossings of a ray."""

    def crosses(a: Column, b: Column) -> Column:
        return F.when(((a["y"] > py) != (b["y"] > py)) & (px < (b["x"] - a["x"]) * (py - a["y"]) / (b["y"] - a["y"]) + a["x"]), 1).otherwise(0)

    pairs = F.zip_with(F.slice(ring, 1, F.size(ring) - 1), F.slice(ring, 2, F.size(ring) - 1), crosses)
    return F.aggregate(pairs, F.lit(0), lambda n, x: n + x) % 2 == 1


def ring_distance(px: Column, py: Column, ring: Column) -> Column:
    """0 inside, else the shortest distance to the border."""
    return F.when(in_ring(px, py, ring), 0.0).otherwise(polyline_distance(px, py, ring))


def parse_wkt(text: Column) -> Column:
    """struct(kind, ring) of POINT, LINESTRING and POLYGON (outer ring) texts; null for others."""
    kind = F.lower(F.regexp_extract(text, r"^\s*([A-Za-z]+)\s*\(", 1))
    body = F.regexp_extract(text, r"\(+([^()]*)\)", 1)
    ring = F.transform(F.split(F.trim(body), r"\s*,\s*"), lambda p: F.struct(F.split(p, r"\s+")[0].cast("double").alias("x"), F.split(p, r"\s+")[1].cast("double").alias("y")))
    name = F.when(kind == "point", "point").when(kind == "linestring", "line").when(kind == "polygon", "polygon")
    return F.when(name.isNotNull(), F.struct(name.alias("kind"), ring.alias("ring")))
