"""Transactions: the features present at each grid point, with probabilities.

Objects list the lattice cells of their bounding box themselves, so no join with the grid is made and empty points never exist. With
strategy tiled each object is shuffled once per tile it touches, and all later grouping by point needs no other exchange.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coloc.functions import decay as decays
from coloc.functions import geometry
from coloc.functions.draws import PROBABILITY, exact
from coloc.operators.grids import KM_PER_DEGREE, Grid, points

BUFFER = ("a", "b", "cx", "cy", "ux", "uy")
TILE = 64


def _buffer() -> dict[str, Column]:
    return {c: F.col(c) for c in BUFFER}


def _indices(rows: DataFrame, grid: Grid) -> DataFrame:
    """i0, i1, j0, j1 of the bounding boxes, within the grid."""
    wx, wy = geometry.half_widths(_buffer())
    low_i, high_i, low_j, high_j = grid.bounds
    at = lambda c, w, off, sign: (F.col(c) + sign * w - off) / grid.step
    return rows.withColumns({
        "i0": F.greatest(F.ceil(at("cx", wx, grid.dx, -1) - 1e-9), F.lit(low_i)),
        "i1": F.least(F.floor(at("cx", wx, grid.dx, 1) + 1e-9), F.lit(high_i)),
        "j0": F.greatest(F.ceil(at("cy", wy, grid.dy, -1) - 1e-9), F.lit(low_j)),
        "j1": F.least(F.floor(at("cy", wy, grid.dy, 1) + 1e-9), F.lit(high_j)),
    }).where("i0 <= i1 and j0 <= j1")


def _cells(rows: DataFrame) -> DataFrame:
    rows = rows.withColumn("gi", F.explode(F.sequence("i0", "i1")))
    return rows.withColumn("gj", F.explode(F.sequence("j0", "j1")))


def probability(rows: DataFrame, grid: Grid, decay: decays.Decay, dmax: str = "ray") -> DataFrame:
    """Rows (object, gi, gj) in the buffer, with p > 0 or a certain presence."""
    gx, gy = grid.x(F.col("gi")), grid.y(F.col("gj"))
    b, x, y = _buffer(), F.col("x"), F.col("y")
    d = F.sqrt((gx - x) * (gx - x) + (gy - y) * (gy - y))
    most = {
        "ray": F.coalesce(geometry.ray(gx, gy, x, y, b), F.lit(1.0)),
        "major": F.col("a") + F.hypot(F.col("cx") - x, F.col("cy") - y),
        "radius": F.col("r"),
    }[dmax]
    circle = (F.col("a") == F.col("b")) & (F.col("cx") == x) & (F.col("cy") == y)
    reach = F.when(circle, F.col("r")).otherwise(most) if dmax == "ray" else most
    rows = rows.where(geometry.inside(gx, gy, b))
    rows = rows.withColumns({"d": d, "dm": reach})
    near = rows.where(F.col("d") >= F.col("r0")) if "r0" in rows.columns else rows
    return near.withColumn("p", F.greatest(F.lit(0.0), F.least(F.lit(1.0), decay(F.col("d"), F.col("dm")))))


def _on_globe(rows: DataFrame, grid: Grid, decay: decays.Decay) -> DataFrame:
    """As probability() for circles of r km around degrees x, y, on a grid whose rows are one step apart and have steps of their own in
    longitude. The distance is the great circle's."""
    x0, y0, x1, y1 = grid.box
    high = int((y1 - y0) * KM_PER_DEGREE / grid.step)
    lat = F.col("r") / KM_PER_DEGREE
    up = grid.step / KM_PER_DEGREE
    rows = rows.where((F.col("a") == F.col("b")) & (F.col("cx") == F.col("x"))).withColumns({"j0": F.greatest(F.ceil((F.col("y") - lat - y0) / up - 1e-9), F.lit(0)), "j1": F.least(F.floor((F.col("y") + lat - y0) / up + 1e-9), F.lit(high))})
    rows = rows.where("j0 <= j1").withColumn("gj", F.explode(F.sequence("j0", "j1")))
    gy = y0 + F.col("gj") * up
    side = grid.step / (KM_PER_DEGREE * F.cos(F.radians(gy)))
    # a circle is widest, in degrees, at its latitude nearest to a pole
    wide = lat / F.cos(F.radians(F.least(F.lit(89.0), F.abs(F.col("y")) + lat)))
    rows = rows.withColumns({"side": side, "i0": F.greatest(F.ceil((F.col("x") - wide - x0) / side - 1e-9), F.lit(0)), "i1": F.least(F.floor((F.col("x") + wide - x0) / side + 1e-9), F.floor((x1 - x0) / side))})
    rows = rows.where("i0 <= i1").withColumn("gi", F.explode(F.sequence("i0", "i1")))
    gx = x0 + F.col("gi") * F.col("side")
    h = F.pow(F.sin(F.radians(gy - F.col("y")) / 2), 2) + F.cos(F.radians(gy)) * F.cos(F.radians("y")) * F.pow(F.sin(F.radians(gx - F.col("x")) / 2), 2)
    d = 2 * (KM_PER_DEGREE * 180 / math.pi) * F.asin(F.least(F.lit(1.0), F.sqrt(h)))
    near = rows.withColumn("d", d).where(F.col("d") <= F.col("r") + 1e-9)
    return near.withColumn("p", F.greatest(F.lit(0.0), F.least(F.lit(1.0), decay(F.col("d"), F.col("r")))))


def _keys(rows: DataFrame) -> list[str]:
    return (["sim_id"] if "sim_id" in rows.columns else []) + (["set_id"] if "set_id" in rows.columns else [])


def merge(rows: DataFrame, combine: str = "max", extra: tuple[str, ...] = ()) -> DataFrame:
    """One row per point and feature: n_inst instances, p by the largest or by noisy-or."""
    p = F.max("p") if combine == "max" else 1 - F.exp(F.sum(F.log1p(-F.least(F.col("p"), F.lit(1 - 1e-15)))))
    return rows.groupBy(*_keys(rows), *extra, "gi", "gj", "feature").agg(F.count(F.lit(1)).cast("int").alias("n_inst"), exact(p).alias("p"))


def build(buffered: DataFrame, grid: Grid, decay: decays.Decay | None = None, mode: str = "uncertain", strategy: str = "cells", dmax: str = "ray", combine: str = "max", tile: int = TILE) -> DataFrame:
    """gi, gj, feature, n_inst, p (and sim_id, set_id if the objects have them) of all points with a feature."""
    fn = decays.boolean() if mode == "certain" else (decay or decays.cosine())
    keep = [c for c in ("sim_id", "set_id", "feature", "x", "y", "r", "r0", *BUFFER) if c in buffered.columns]
    if grid.metric == "geodesic":
        return merge(_on_globe(buffered.select(*keep), grid, fn), combine)
    rows = _indices(buffered.select(*keep), grid)
    if mode == "certain":
        dmax = "radius"
        fn = lambda d, dm: F.lit(1.0)
    if strategy == "cells":
        return merge(probability(_cells(rows), grid, fn, dmax), combine)
    if strategy == "tiled":
        tiles = rows.withColumn("ti", F.explode(F.sequence(F.floor(F.col("i0") / tile), F.floor(F.col("i1") / tile))))
        tiles = tiles.withColumn("tj", F.explode(F.sequence(F.floor(F.col("j0") / tile), F.floor(F.col("j1") / tile))))
        local = tiles.repartition(*_keys(rows), "ti", "tj").withColumns({
            "i0": F.greatest("i0", F.col("ti") * tile), "i1": F.least("i1", F.col("ti") * tile + tile - 1),
            "j0": F.greatest("j0", F.col("tj") * tile), "j1": F.least("j1", F.col("tj") * tile + tile - 1),
        })
        return merge(probability(_cells(local), grid, fn, dmax), combine, ("ti", "tj"))
    if strategy == "cross":
        every = points(buffered.sparkSession, grid).select("gi", "gj")
        return merge(probability(F.broadcast(buffered.select(*keep)).crossJoin(every), grid, fn, dmax), combine)
    raise ValueError(f"unknown strategy {strategy}")


#: Distances of points to segments that are worked out together, and rows of one batch.
BLOCK, ROWS = 2_000_000, 200_000


def _line_distance(gx: np.ndarray, gy: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Shortest distance of each point (gx, gy) to the segments between consecutive places; segments with an unknown end are left out."""
    x1, y1 = (x[:-1], y[:-1]) if len(x) > 1 else (x, y)
    dx, dy = (np.diff(v) if len(v) > 1 else np.zeros(len(v)) for v in (x, y))
    size = dx * dx + dy * dy
    out = np.full((len(gx), len(gy)), np.inf)
    step = max(1, BLOCK // max(1, out.size))
    for first in range(0, len(x1), step):
        s = slice(first, first + step)
        px, py, ex, ey, n = x1[s], y1[s], dx[s], dy[s], size[s]
        along = ((gx[:, None] - px) * ex)[:, None, :] + ((gy[:, None] - py) * ey)[None, :, :]
        t = np.clip(along / np.where(n > 0, n, 1.0), 0.0, 1.0)
        away = (gx[:, None, None] - (px + t * ex)) ** 2 + (gy[None, :, None] - (py + t * ey)) ** 2
        np.fmin(out, np.fmin.reduce(away, axis=2, initial=np.inf), out=out)
    return np.sqrt(out)


def _near_lines(batches: Iterator[pa.RecordBatch], grid: Grid, r: float) -> Iterator[pa.RecordBatch]:
    """feature, xs, ys, i0, i1, j0, j1 of lines -> feature, gi, gj, d of the points not farther than r: no row for a point and a segment."""
    for part in batches:
        bounds = [part[c].to_pylist() for c in ("i0", "i1", "j0", "j1")]
        held: list[tuple] = []

        def packed() -> pa.RecordBatch:
            at, gi, gj, d = (np.concatenate(v) for v in zip(*held))
            return pa.RecordBatch.from_arrays([part["feature"].take(pa.array(at)), pa.array(gi), pa.array(gj), pa.array(d)], ["feature", "gi", "gj", "d"])

        n = 0
        for k, (i0, i1, j0, j1) in enumerate(zip(*bounds)):
            x, y = (part[c][k].values.to_numpy(zero_copy_only=False).astype(float) for c in ("xs", "ys"))
            gi, gj = np.arange(i0, i1 + 1), np.arange(j0, j1 + 1)
            d = _line_distance(gi * grid.step + grid.dx, gj * grid.step + grid.dy, x, y)
            a, b = np.nonzero(d <= r + 1e-9)
            held.append((np.full(len(a), k), gi[a], gj[b], d[a, b]))
            n += len(a)
            if n >= ROWS:
                yield packed()
                held, n = [], 0
        if n:
            yield packed()


def extended(objects: DataFrame, grid: Grid, r: float, kind: str, decay: decays.Decay | None = None) -> DataFrame:
    """Lines and polygons (object_id, feature, ring): p is 1 on or in the shape and falls in the buffer of width r."""
    xs, ys = F.transform("ring", lambda q: q["x"]), F.transform("ring", lambda q: q["y"])
    low_i, high_i, low_j, high_j = grid.bounds
    at = lambda v, off: (v - off) / grid.step
    rows = objects.select("feature", "ring").withColumns({
        "i0": F.greatest(F.ceil(at(F.array_min(xs) - r, grid.dx) - 1e-9), F.lit(low_i)), "i1": F.least(F.floor(at(F.array_max(xs) + r, grid.dx) + 1e-9), F.lit(high_i)),
        "j0": F.greatest(F.ceil(at(F.array_min(ys) - r, grid.dy) - 1e-9), F.lit(low_j)), "j1": F.least(F.floor(at(F.array_max(ys) + r, grid.dy) + 1e-9), F.lit(high_j)),
    }).where("i0 <= i1 and j0 <= j1")
    fn = decay or decays.cosine()
    if kind == "line":
        feature = rows.schema["feature"].dataType.simpleString()
        bounds = [F.col(c).cast("long").alias(c) for c in ("i0", "i1", "j0", "j1")]
        near = rows.select("feature", xs.alias("xs"), ys.alias("ys"), *bounds).mapInArrow(partial(_near_lines, grid=grid, r=r), f"feature {feature}, gi long, gj long, d double")
    else:
        cells = _cells(rows)
        near = cells.withColumn("d", geometry.ring_distance(grid.x(F.col("gi")), grid.y(F.col("gj")), F.col("ring"))).where(F.col("d") <= r + 1e-9)
    return merge(near.withColumn("p", fn(F.col("d"), F.lit(float(r)))))


def union_merge(*long: DataFrame) -> DataFrame:
    """Transactions over several kinds of objects together."""
    rows = long[0]
    for other in long[1:]:
        rows = rows.unionByName(other)
    return rows.groupBy(*_keys(rows), "gi", "gj", "feature").agg(F.sum("n_inst").cast("int").alias("n_inst"), F.max("p").alias("p"))


def from_table(df: DataFrame, id_col: str = "tx_id", item_col: str = "item", p_col: str = "p") -> DataFrame:
    """Transactions of an existing table: tx_id, feature, n_inst, p."""
    return df.groupBy(F.col(id_col).alias("tx_id"), F.col(item_col).alias("feature")).agg(F.count(F.lit(1)).cast("int").alias("n_inst"), exact(F.max(p_col)).alias("p"))


def point_keys(tx: DataFrame) -> list[str]:
    return [c for c in ("sim_id", "set_id", "tx_id", "ti", "tj", "gi", "gj") if c in tx.columns]


def to_wide(tx: DataFrame, effect: str | int | None = None) -> DataFrame:
    """One row per point with items, an array of (f, p) sorted by f; at most one entry per feature. With an effect its p is apart in pe, null where it is not."""
    item = F.struct(F.col("feature").alias("f"), F.col("p").cast("double").alias("p"))
    if effect is None:
        return tx.groupBy(*point_keys(tx)).agg(F.sort_array(F.collect_list(item)).alias("items"))
    own = F.col("feature") == F.lit(effect)
    return tx.groupBy(*point_keys(tx)).agg(F.sort_array(F.collect_list(F.when(~own, item))).alias("items"), F.max(F.when(own, F.col("p").cast("double"))).alias("pe"))


def as_map(wide: DataFrame) -> DataFrame:
    return wide.withColumn("items", F.map_from_entries("items"))


def with_empty(tx: DataFrame, grid: Grid) -> DataFrame:
    """gi, gj, n_features of every grid point, those without a feature included."""
    n = tx.groupBy("gi", "gj").agg(F.count(F.lit(1)).alias("n"))
    return points(tx.sparkSession, grid).select("gi", "gj").join(n, ["gi", "gj"], "left").select("gi", "gj", F.coalesce("n", F.lit(0)).alias("n_features"))


def certain(tx: DataFrame) -> DataFrame:
    return tx.withColumn("p", F.lit(1).cast(PROBABILITY))
