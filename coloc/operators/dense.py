"""Sums over item sets by tiles of the grid: what a simulation has in a tile is one numpy task, and only sums by set leave it.

Objects go to the tiles that they touch. In a tile the largest probability of each feature at each point is one array, and a set's products are
products of arrays. Neither a row for each object and point nor one for each point and set is ever made. Sets are coded longs (itemsets.py), and
probabilities and products are rounded to whole numbers of parts as they are there, so sums are exact.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.functions import decay as decays
from coloc.operators.grids import Grid
from coloc.operators.itemsets import HALF, PARTS

#: Points along a tile's side: the parts of all its points together are whole numbers that a double holds.
TILE = 64
#: Points of objects' boxes that are looked at together: few enough to stay in a core's cache.
BLOCK = 40_000
#: The same for circles, and the shares of all features that are held together.
ROWS, HELD = 12_000, 1 << 22
ELLIPSE = ("a", "b", "cx", "cy", "ux", "uy")
OUT = "sim_id int, key long, size int, sup long, sup_lhs long, bh long, bl long, lh long, ll long"


class Sets:
    """The coded sets that are wanted: by the set before it each item that goes on, and the sets themselves."""

    def __init__(self, keys: np.ndarray, sizes: np.ndarray, d: int, bits: int):
        self.keys, self.after = np.sort(keys), {}
        mask = (1 << bits) - 1
        for key, size in zip(keys.tolist(), sizes.tolist()):
            before = 0
            for n in range(1, size + 1):
                code = (key >> bits * (d - n)) & mask
                self.after.setdefault(before, set()).add(code)
                before |= code << bits * (d - n)

    def has(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(keys), bool)
        return self.keys[np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)] == keys


def fits(objects: DataFrame, grid: Grid, decay: decays.Decay, mode: str, strategy: str, combine: str) -> bool:
    """Whether tiles() can do it: planar grids, the largest probability of a point, and decays that also take arrays."""
    return grid.metric == "planar" and combine == "max" and strategy in ("cells", "tiled") and not {"r0", "set_id"} & set(objects.columns) and (mode == "certain" or decays.of_arrays(decay) is not None)


def _indices(rows: dict[str, np.ndarray], box: tuple[int, int, int, int], grid: Grid) -> tuple[np.ndarray, ...]:
    """i0, i1, j0, j1 of the bounding boxes within the box; circles have no ellipse (nan)."""
    x, y, r, (a, b, cx, cy, ux, uy) = rows["x"], rows["y"], rows["r"], (rows[c] for c in ELLIPSE)
    round_ = np.isnan(a)
    wx = np.where(round_, r, np.sqrt(a * a * ux * ux + b * b * uy * uy))
    wy = np.where(round_, r, np.sqrt(a * a * uy * uy + b * b * ux * ux))
    mx, my = np.where(round_, x, cx), np.where(round_, y, cy)
    low = lambda m, w, off, least: np.maximum(np.ceil((m - w - off) / grid.step - 1e-9), least).astype(np.int64)
    high = lambda m, w, off, most: np.minimum(np.floor((m + w - off) / grid.step + 1e-9), most).astype(np.int64)
    return low(mx, wx, grid.dx, box[0]), high(mx, wx, grid.dx, box[1]), low(my, wy, grid.dy, box[2]), high(my, wy, grid.dy, box[3])


def _touched(at: np.ndarray, rows: dict[str, np.ndarray], grid: Grid, side: int = TILE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the rows `at` each once for a tile that it touches, and the tile."""
    i0, i1, j0, j1 = _indices({c: v[at] for c, v in rows.items()}, grid.bounds, grid)
    at, (i0, i1, j0, j1) = at[(i0 <= i1) & (j0 <= j1)], (v[(i0 <= i1) & (j0 <= j1)] for v in (i0, i1, j0, j1))
    wide, high = i1 // side - i0 // side + 1, j1 // side - j0 // side + 1
    k = np.repeat(np.arange(len(at)), wide * high)
    nth = np.arange(len(k)) - np.repeat(np.cumsum(wide * high) - wide * high, wide * high)
    ti, tj = i0[k] // side + nth // high[k], j0[k] // side + nth % high[k]
    return at[k], ti, tj


def _tiled(table: pa.RecordBatch, grid: Grid) -> pa.RecordBatch:
    """The objects once for each tile that they touch, circles without an ellipse."""
    rows = {c: table[c].to_numpy(zero_copy_only=False).astype(np.float64) for c in ("x", "y", "r", *ELLIPSE)}
    circle = (rows["a"] == rows["b"]) & (rows["a"] == rows["r"]) & (rows["cx"] == rows["x"]) & (rows["cy"] == rows["y"])
    for c in ELLIPSE:
        rows[c][circle] = np.nan
    known = ~(np.isnan(rows["x"]) | np.isnan(rows["y"]) | np.isnan(rows["r"])) & (circle | ~np.isnan(rows["a"]))
    at = np.flatnonzero(known)
    at, ti, tj = _touched(at, rows, grid)
    same = lambda c: table[c].to_numpy(zero_copy_only=False)[at]
    columns = {"sim_id": pa.array(same("sim_id"), pa.int32()), "ti": pa.array(ti), "tj": pa.array(tj), "feature": pa.array(same("feature"), pa.int32()), **{c: pa.array(v[at]) for c, v in rows.items()}}
    return pa.RecordBatch.from_pydict(columns)


def raster(rows: dict[str, np.ndarray], at: np.ndarray, n: int, box: tuple[int, int, int, int], grid: Grid, decay, dmax: str) -> np.ndarray:
    """Parts of the largest probability of each of n features (at: a row's) at the points i0 to i1, j0 to j1; -1 where it is not present."""
    low_i, high_i, low_j, high_j = box
    high = high_j - low_j + 1
    # of a decay by the share of the largest distance the smallest share is enough: it is put through the decay once for a point
    nearest = decays.by_share(decay)
    out = np.full(n * (high_i - low_i + 1) * high, np.inf if nearest else -1.0)
    x, y, r = rows["x"], rows["y"], rows["r"]
    a, b, cx, cy, ux, uy = (rows[c] for c in ELLIPSE)
    round_ = np.isnan(a)
    i0, i1, j0, j1 = _indices(rows, box, grid)
    wide, tall = i1 - i0 + 1, j1 - j0 + 1
    order = np.lexsort((tall, wide, round_))
    order = order[(wide[order] > 0) & (tall[order] > 0)]
    first = 0
    while first < len(order):
        # objects of about the same size, circles apart from ellipses
        some = order[first : first + max(1, BLOCK // int(wide[order[min(first + 255, len(order) - 1)]] ** 2))]
        some = some[round_[some] == round_[some[0]]]
        first += len(some)
        gi, gj = i0[some, None] + np.arange(wide[some].max()), j0[some, None] + np.arange(tall[some].max())
        gx, gy = gi * grid.step + grid.dx, gj * grid.step + grid.dy
        sx, sy = gx - x[some, None], gy - y[some, None]
        d = np.sqrt((sx * sx)[:, :, None] + (sy * sy)[:, None, :])
        if round_[some[0]]:
            rr = (r[some] * r[some])[:, None]
            inside = (sx * sx / rr)[:, :, None] + (sy * sy / rr)[:, None, :] <= 1 + 1e-12
            reach = np.broadcast_to(r[some, None, None], d.shape)
        else:
            at_ = lambda v: v[some, None, None]
            ex, ey = (gx - cx[some, None])[:, :, None], (gy - cy[some, None])[:, None, :]
            u, v = ex * at_(ux) + ey * at_(uy), ey * at_(ux) - ex * at_(uy)
            aa, bb = at_(a * a), at_(b * b)
            inside = u * u / aa + v * v / bb <= 1 + 1e-12
            if dmax == "ray":
                with np.errstate(invalid="ignore", divide="ignore"):
                    e1, e2 = (sx[:, :, None] * at_(ux) + sy[:, None, :] * at_(uy)) / d, (sy[:, None, :] * at_(ux) - sx[:, :, None] * at_(uy)) / d
                    s = at_((x - cx) * ux + (y - cy) * uy)
                    p2, q, r2 = e1 * e1 / aa + e2 * e2 / bb, 2 * s * e1 / aa, s * s / aa - 1
                    reach = np.where(d > 0, (np.sqrt(np.maximum(q * q - 4 * p2 * r2, 0.0)) - q) / (2 * p2), 1.0)
            else:
                reach = np.broadcast_to(at_(r) if dmax == "radius" else at_(a + np.hypot(cx - x, cy - y)), d.shape)
        inside &= (gi <= i1[some, None])[:, :, None] & (gj <= j1[some, None])[:, None, :]
        point = (at[some, None] * (high_i - low_i + 1) + gi - low_i)[:, :, None] * high + (gj - low_j)[:, None, :]
        if nearest:
            np.minimum.at(out, point[inside], decays.share_of(d[inside], reach[inside]))
        else:
            p = np.clip(decay(d[inside], reach[inside]), 0.0, 1.0) if decay else np.ones(int(inside.sum()))
            np.maximum.at(out, point[inside], np.floor(p * PARTS + 0.5))
    if nearest:
        there = np.isfinite(out)
        out[there] = np.floor(np.clip(decay(out[there], np.ones(int(there.sum()))), 0.0, 1.0) * PARTS + 0.5)
        out[~there] = -1.0
    return out.reshape(n, -1)


def nearest_shares(code: np.ndarray, x: np.ndarray, y: np.ndarray, r: np.ndarray, n: int, box: tuple[int, int, int, int], grid: Grid) -> np.ndarray:
    """The smallest share of the largest distance that each of n features (code: from 0, in order) has at the points of the box; inf where it is not present.

    As in raster(), but of circles, one column of points of each object's box after another and one feature after another, so that what is looked at stays in the cache.
    """
    low_i, high_i, low_j, high_j = box
    high = high_j - low_j + 1
    out = np.full((n, (high_i - low_i + 1) * high), np.inf)
    none = np.full(len(x), np.nan)
    i0, i1, j0, j1 = _indices({"x": x, "y": y, "r": r, **{c: none for c in ELLIPSE}}, box, grid)
    wide, tall = i1 - i0 + 1, j1 - j0 + 1
    order = np.lexsort((wide, tall, code))
    order = order[(wide[order] > 0) & (tall[order] > 0)]
    heads = np.searchsorted(code[order], np.arange(n + 1))
    for f in range(n):
        first = heads[f]
        while first < heads[f + 1]:
            # boxes of about the same height, which grows
            last = min(heads[f + 1], first + 255)
            last = min(heads[f + 1], first + max(1, ROWS // int(tall[order[last - 1]])))
            some = order[first:last]
            first = last
            rr = r[some] * r[some]
            gj = j0[some, None] + np.arange(tall[some].max())
            sy = gj * grid.step + grid.dy - y[some, None]
            sy *= sy
            qy = sy / rr[:, None]
            qy[gj > j1[some, None]] = np.inf
            point = gj - low_j
            for k in range(wide[some].max()):
                gi = i0[some] + k
                sx = gi * grid.step + grid.dx - x[some]
                sx *= sx
                qx = np.where(gi > i1[some], np.inf, sx / rr)
                inside = qx[:, None] + qy <= 1 + 1e-12
                d = sx[:, None] + sy
                np.sqrt(d, out=d)
                d /= r[some, None]
                np.minimum.at(out[f], (point + ((gi - low_i) * high)[:, None])[inside], d[inside])
    return out


def of_shares(shares: np.ndarray, decay) -> np.ndarray:
    """Parts of the probabilities at shares of the largest distance, all of them without a decay; -1 where there is none."""
    there = np.isfinite(shares)
    near = np.minimum(shares[there], 1.0)
    shares[there] = np.floor(np.clip(decay(near, np.ones(len(near))), 0.0, 1.0) * PARTS + 0.5) if decay else float(PARTS)
    shares[~there] = -1.0
    return shares


def sums(parts: np.ndarray, codes: np.ndarray, effect: int | None, d: int, bits: int, wanted: Sets | None) -> list[np.ndarray]:
    """key, size, sup, sup_lhs and the parts of exp_sup and exp_sup_lhs of the sets of 1 to d features; without an effect sup and exp_sup are those of sup_lhs."""
    own = codes == effect if effect is not None else np.zeros(len(codes), bool)
    causes = parts[~own]
    some = (causes >= 0).any(0)
    causes, codes = causes[:, some], codes[~own]
    there = parts[own][0][some] if own.any() else None
    pe = np.maximum(there, 0.0) / PARTS if there is not None else None
    bits_of = lambda v: np.ascontiguousarray(np.packbits(np.pad(v, [(0, 0)] * (v.ndim - 1) + [(0, -v.shape[-1] % 64)]), axis=-1)).view(np.uint64)
    has = there >= 0 if there is not None else None
    # probabilities that are all 0 or 1 need counts only
    certain = bool(((causes < 0) | (causes == PARTS)).all()) and (there is None or bool(((there < 0) | (there == PARTS)).all()))
    out: list[tuple] = []
    spare, room = np.empty(causes.shape), [np.empty(causes.size if n else 0) for n in range(d)]

    def whole(p: np.ndarray, by: np.ndarray | None = None) -> np.ndarray:
        """Sums of the parts of p, or of p * by."""
        v = spare.reshape(-1)[: p.size].reshape(p.shape)
        np.multiply(p, PARTS, out=v) if by is None else np.multiply(np.multiply(p, by, out=v), PARTS, out=v)
        v += 0.5
        return np.floor(v, out=v).sum(1)

    def grow(before: int, n: int, at: np.ndarray, p: np.ndarray, m: np.ndarray, pe, has, pv, mv, packed: tuple) -> None:
        """Sets of n items that begin with `before` (pv, mv: its products and places) and end with one of the rows `at`. packed: m, mv and has as bits."""
        if wanted is not None:
            go = wanted.after.get(before)
            if not go:
                return
            at = at[[int(codes[k]) in go for k in at]]
        if not len(at):
            return
        if mv is not None and mv.sum() * 2 < len(mv):
            p, m, pv = p[:, mv], m[:, mv], pv[mv]
            pe, has = (pe[mv], has[mv]) if pe is not None else (None, None)
            mv = None
            packed = bits_of(m), None, bits_of(has) if has is not None else None
        # places are counted as bits; rows that follow each other are not copied
        at_ = slice(at[0], at[-1] + 1) if at[-1] - at[0] + 1 == len(at) else at
        each, before_, effect_ = packed
        own = each[at_] if before_ is None else each[at_] & before_
        count = lambda v: np.bitwise_count(v).sum(1, dtype=np.int64).astype(np.float64)
        n_lhs = count(own)
        n_both = n_lhs if effect is None else np.zeros(len(at)) if pe is None else count(own & effect_)
        q = None if certain else p[at_] if pv is None else np.multiply(p[at_], pv, out=room[n - 1][: len(at) * len(pv)].reshape(len(at), len(pv)))
        lhs = n_lhs * PARTS if certain else whole(q)
        if effect is None:
            both = lhs
        elif pe is None:
            both = np.zeros(len(at))
        else:
            both = n_both * PARTS if certain else whole(q, pe)
        keys = before | codes[at].astype(np.int64) << bits * (d - n)
        keep = n_lhs > 0
        emit = keep & wanted.has(keys) if wanted is not None else keep
        out.append((keys[emit], np.full(int(emit.sum()), n), n_both[emit], n_lhs[emit], both[emit], lhs[emit]))
        if n < d:
            for k in np.flatnonzero(keep):
                places = m[at[k]] if mv is None else m[at[k]] & mv
                grow(int(keys[k]), n + 1, np.arange(at[k] + 1, len(codes)), p, m, pe, has, places if certain else q[k], places, (each, own[k], effect_))

    present = causes >= 0
    grow(0, 1, np.arange(len(codes)), np.maximum(causes, 0.0) / PARTS, present, pe, has, None, None, (bits_of(present), None, bits_of(has) if has is not None else None))
    return [np.concatenate([o[k] for o in out]).astype(np.int64) if out else np.zeros(0, np.int64) for k in range(6)]


def wanted_sets(live: DataFrame | None, d: int, bits: int) -> Sets | None:
    """The live sets (key, size), if there are any given."""
    if live is None:
        return None
    rows = live.select("key", "size").toPandas()
    return Sets(rows["key"].to_numpy(np.int64), rows["size"].to_numpy(np.int64), d, bits)


def _box(ti: int, tj: int, grid: Grid, side: int = TILE) -> tuple[int, int, int, int]:
    """Bounds of a tile's points."""
    low_i, high_i, low_j, high_j = grid.bounds
    return max(low_i, ti * side), min(high_i, ti * side + side - 1), max(low_j, tj * side), min(high_j, tj * side + side - 1)


def _shown(sim: int, keys: np.ndarray, sizes: np.ndarray, sup: np.ndarray, sup_lhs: np.ndarray, *halves: np.ndarray) -> pa.RecordBatch:
    ints = [pa.array(np.full(len(keys), sim), pa.int32()), pa.array(keys), pa.array(sizes, pa.int32()), *[pa.array(v) for v in (sup, sup_lhs, *halves)]]
    return pa.RecordBatch.from_arrays(ints, ["sim_id", "key", "size", "sup", "sup_lhs", "bh", "bl", "lh", "ll"])


def of_simulation(sim: int, code: np.ndarray, x: np.ndarray, y: np.ndarray, r: np.ndarray, grid: Grid, fn, dmax: str, effect: int | None, d: int, bits: int, wanted: Sets | None) -> pa.RecordBatch:
    """As a simulation's rows of tiles(), of circles that are all there."""
    none = np.full(len(x), np.nan)
    rows = {"x": x, "y": y, "r": r, **{c: none for c in ELLIPSE}}
    by_share = fn is None or decays.by_share(fn)
    # shares are made for some tiles along a side together, if all features have room there
    side = max(1, min(4, math.isqrt(HELD // (TILE * TILE * max(1, len(np.unique(code))))))) if by_share else 1
    at, ti, tj = _touched(np.flatnonzero(~(np.isnan(x) | np.isnan(y) | np.isnan(r))), rows, grid, TILE * side)
    order = np.lexsort((tj, ti))
    at, ti, tj = at[order], ti[order], tj[order]
    starts = np.flatnonzero(np.r_[True, (np.diff(ti) != 0) | (np.diff(tj) != 0)]) if len(at) else []
    found = []
    for first, last in zip(starts, [*starts[1:], len(at)]):
        own = at[first:last]
        codes, nth = np.unique(code[own], return_inverse=True)
        box = _box(int(ti[first]), int(tj[first]), grid, TILE * side)
        if not by_share:
            found.append(sums(raster({c: v[own] for c, v in rows.items()}, nth, len(codes), box, grid, fn, dmax), codes, effect, d, bits, wanted))
            continue
        parts = of_shares(nearest_shares(nth, x[own], y[own], r[own], len(codes), box, grid), fn).reshape(len(codes), box[1] - box[0] + 1, -1)
        for i in range(0, parts.shape[1], TILE):
            for j in range(0, parts.shape[2], TILE):
                tile = parts[:, i : i + TILE, j : j + TILE].reshape(len(codes), -1)
                there = (tile >= 0).any(1)
                if there.any():
                    found.append(sums(tile[there], codes[there], effect, d, bits, wanted))
    keys, sizes, sup, sup_lhs, both, lhs = (np.concatenate(v) for v in zip(*found)) if found else [np.zeros(0, np.int64)] * 6
    once, head, nth = np.unique(keys, return_index=True, return_inverse=True)

    def total(v: np.ndarray) -> np.ndarray:
        out = np.zeros(len(once), np.int64)
        np.add.at(out, nth, v)
        return out

    return _shown(sim, once, sizes[head], *map(total, (sup, sup_lhs, both // HALF, both % HALF, lhs // HALF, lhs % HALF)))


def tiles(objects: DataFrame, grid: Grid, decay: decays.Decay, mode: str, dmax: str, effect: int | None, d: int, bits: int, live: DataFrame | None = None) -> DataFrame:
    """sim_id (if the objects have it), key, size, sup, sup_lhs, and the sums bh, bl, lh, ll of the high and low halves of exp_sup and exp_sup_lhs,
    of the sets of coded features that occur; of the live ones (key, size) only, if they are given."""
    fn, dmax = (None, "radius") if mode == "certain" else (decays.of_arrays(decay), dmax)
    by = ["sim_id"] if "sim_id" in objects.columns else []
    shared = objects.sparkSession.sparkContext.broadcast(wanted_sets(live, d, bits))
    # places are evaluated once on their way out of the JVM; indices made of them there would draw them anew each time
    rows = objects.select((F.col("sim_id") if by else F.lit(0)).cast("int").alias("sim_id"), F.col("feature").cast("int").alias("feature"), *[F.col(c).cast("double").alias(c) for c in ("x", "y", "r", *ELLIPSE)])
    rows = rows.mapInArrow(lambda batches: (_tiled(t, grid) for t in batches), f"sim_id int, ti long, tj long, feature int, x double, y double, r double, {', '.join(f'{c} double' for c in ELLIPSE)}")
    tasks = int(objects.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(tasks, "sim_id", "ti", "tj")

    def one(key: tuple, table: pa.Table) -> pa.Table:
        sim, ti, tj = (k.as_py() for k in key)
        columns = {c: table[c].to_numpy().astype(np.float64) for c in ("x", "y", "r", *ELLIPSE)}
        codes, at = np.unique(table["feature"].to_numpy(), return_inverse=True)
        parts = raster(columns, at, len(codes), _box(ti, tj, grid), grid, fn, dmax)
        keys, sizes, sup, sup_lhs, both, lhs = sums(parts, codes, effect, d, bits, shared.value)
        halves = (both // HALF, both % HALF, lhs // HALF, lhs % HALF)
        return pa.Table.from_batches([_shown(sim, keys, sizes, sup, sup_lhs, *halves)])

    each = rows.groupBy("sim_id", "ti", "tj").applyInArrow(one, OUT)
    return each.groupBy(*by, "key", "size").agg(*[F.sum(c).alias(c) for c in ("sup", "sup_lhs", "bh", "bl", "lh", "ll")])
