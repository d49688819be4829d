"""Simulations that a task draws again by itself: objects are sent to all executors once, and only sums by set leave a task.

Draws are digests, so a task that has the objects can work out any simulation: it puts them in their places, fills one tile after another and sums its
sets (dense.py). No object of a simulation is ever a row, is shuffled or is written. For at most MOST objects, all of them circles whose radius goes
with the object and not with its place; randomize.py is the way for all else, with the same draws.
"""

from __future__ import annotations

import math
from _md5 import md5
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from coloc.functions import decay as decays
from coloc.operators import dense
from coloc.operators.grids import Grid
from coloc.operators.itemsets import HALF
from coloc.operators.randomize import ATTEMPTS

#: Objects that are sent to all executors at once, at most, and zones that a place is compared with.
MOST, MOST_ZONES = 2_000_000, 1_000
#: Keys that are digested, or places compared with zones, together.
SOME = 50_000
#: Keys that are digested in arrays together: few enough to stay in a core's cache.
FEW = 8_192

Box = tuple[float, float, float, float]


#: md5 (RFC 1321): what is added in each step, by how many bits it turns, and the words it begins with.
_ADDED = [np.uint32(int(abs(math.sin(n + 1)) * 4294967296)) for n in range(64)]
_TURNS = [[np.uint32(v) for v in row] for row in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))]
_BEGIN = [np.uint32(v) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]


def _one_block(words: list[np.ndarray | None]) -> list[np.ndarray]:
    """The four words of the md5 of each column of 16 words (None: zeros), texts with their ends and lengths."""
    n = len(words[14])
    a, b, c, d = (np.full(n, v) for v in _BEGIN)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for step in range(64):
        part = step // 16
        if part == 0:
            at = step
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif part == 1:
            at = (5 * step + 1) % 16
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif part == 2:
            at = (3 * step + 5) % 16
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            at = 7 * step % 16
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        f += a
        f += _ADDED[step]
        if words[at] is not None:
            f += words[at]
        turn = _TURNS[part][step % 4]
        np.left_shift(f, turn, out=g), np.right_shift(f, np.uint32(32) - turn, out=f), np.bitwise_or(f, g, out=f)
        f += b
        a, b, c, d, f = d, f, b, c, a
    return [v + first for v, first in zip((a, b, c, d), _BEGIN)]


def _rows(keys: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of keys in rows, each with the mark of its end, and their lengths."""
    ends = np.frombuffer(keys.buffers()[1], np.int64)[keys.offset : keys.offset + len(keys) + 1]
    data, lengths = np.frombuffer(keys.buffers()[2] or b"", np.uint8), np.diff(ends)
    out = np.zeros((len(keys), int(lengths.max(initial=0)) + 1), np.uint8)
    for k in range(out.shape[1] - 1):
        on = lengths > k
        out[on, k] = data[ends[:-1][on] + k]
    out[np.arange(len(keys)), lengths] = 0x80
    return out, lengths


def _digests(prefix: str, keys: pa.Array, words: int = 4) -> np.ndarray:
    """The two halves of the md5 of each key after a prefix, or its first word only."""
    start, out = prefix.encode(), []
    for k in range(0, len(keys), SOME):
        some = keys.slice(k, SOME)
        lengths = pc.binary_length(some)
        if len(start) + pc.max(lengths).as_py() > 55:  # more than one block
            digests = np.frombuffer(b"".join([md5(start + key).digest() for key in some.to_pylist()]), ">u4").reshape(-1, 4)
            out.append(digests.astype(np.uint32)[:, :words])
            continue
        rows, sizes = _rows(some)
        used = -(-(len(start) + rows.shape[1]) // 4)
        for j in range(0, len(rows), FEW):
            texts = np.zeros((len(rows[j : j + FEW]), used * 4), np.uint8)
            texts[:, : len(start)] = np.frombuffer(start, np.uint8)
            texts[:, len(start) : len(start) + rows.shape[1]] = rows[j : j + FEW]
            block = [*np.ascontiguousarray(texts.view("<u4").T), *[None] * (16 - used)]
            block[14] = ((sizes[j : j + FEW] + len(start)) * 8).astype(np.uint32)
            out.append(np.column_stack([v.byteswap() for v in _one_block(block)[:words]]))
    found = np.concatenate(out) if out else np.zeros((0, words), np.uint32)
    if words == 1:
        return found
    found = found.astype(np.uint64)
    return found[:, ::2] << np.uint64(32) | found[:, 1::2]


def draws(tag: str, keys: pa.Array) -> np.ndarray:
    """functions.draws.draw() of the tag and each key."""
    return _digests(tag, keys, 1)[:, 0].astype(np.float64) / 4294967296.0


@dataclass
class Still:
    """Objects that keep their places."""

    code: np.ndarray
    r: np.ndarray
    x: np.ndarray
    y: np.ndarray

    def placed(self, sim: int) -> tuple[np.ndarray, ...]:
        return self.code, self.r, self.x, self.y


@dataclass
class Permuted:
    """Slots in their order (x, y) and what is in them (code, r; keys: site and feature), as randomize.permute_features."""

    code: np.ndarray
    r: np.ndarray
    x: np.ndarray
    y: np.ndarray
    keys: pa.Array
    seed: str

    def placed(self, sim: int) -> tuple[np.ndarray, ...]:
        high, low = _digests(f"{self.seed}p{sim}:", self.keys).T
        order = np.lexsort((low, high))  # stable: equal digests stay in the order of slots
        return self.code[order], self.r[order], self.x, self.y


@dataclass
class Uniform:
    """Objects anywhere in the box, as randomize.uniform."""

    code: np.ndarray
    r: np.ndarray
    keys: pa.Array
    box: Box
    seed: str

    def placed(self, sim: int) -> tuple[np.ndarray, ...]:
        x0, y0, x1, y1 = self.box
        return self.code, self.r, x0 + (x1 - x0) * draws(f"{self.seed}ux{sim}:", self.keys), y0 + (y1 - y0) * draws(f"{self.seed}uy{sim}:", self.keys)


@dataclass
class Urban:
    """Urban cases in their zones, one row of `zones` (x0, y0, x1, y1) for each, as randomize.by_population."""

    code: np.ndarray
    r: np.ndarray
    keys: pa.Array
    zones: np.ndarray
    seed: str

    def placed(self, sim: int) -> tuple[np.ndarray, ...]:
        x0, y0, x1, y1 = self.zones.T
        return self.code, self.r, x0 + (x1 - x0) * draws(f"{self.seed}sx{sim}:", self.keys), y0 + (y1 - y0) * draws(f"{self.seed}sy{sim}:", self.keys)


@dataclass
class Rural:
    """Other cases in the box outside all zones, as randomize.by_population: the first attempt that is outside, else the last."""

    code: np.ndarray
    r: np.ndarray
    keys: pa.Array
    zones: np.ndarray
    box: Box
    seed: str

    def placed(self, sim: int) -> tuple[np.ndarray, ...]:
        x0, y0, x1, y1 = self.box
        x, y, left = np.zeros(len(self.code)), np.zeros(len(self.code)), np.arange(len(self.code))
        for t in range(ATTEMPTS):
            keys = self.keys.take(pa.array(left))
            x[left] = x0 + (x1 - x0) * draws(f"{self.seed}rx{sim}:{t}:", keys)
            y[left] = y0 + (y1 - y0) * draws(f"{self.seed}ry{sim}:{t}:", keys)
            left = left[self._in_zone(x[left], y[left])]
            if not len(left):
                break
        return self.code, self.r, x, y

    def _in_zone(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        zx0, zy0, zx1, zy1 = self.zones.T
        out = np.zeros(len(x), bool)
        step = max(1, SOME * 20 // max(1, len(self.zones)))
        for k in range(0, len(x), step):
            a, b = x[k : k + step, None], y[k : k + step, None]
            out[k : k + step] = ((a >= zx0) & (a < zx1) & (b >= zy0) & (b < zy1)).any(1)
        return out


def column(table: pa.Table, name: str) -> np.ndarray:
    """A column of numbers, unknown ones as nan."""
    return table[name].cast(pa.float64()).combine_chunks().to_numpy(zero_copy_only=False)


def keys(*parts: pa.ChunkedArray) -> pa.Array:
    """The texts of the parts, joined, as bytes."""
    texts = [p.combine_chunks().cast(pa.large_string()) for p in parts]
    return pc.binary_join_element_wise(*texts, pa.scalar("", pa.large_string())).cast(pa.large_binary()) if len(texts) > 1 else texts[0].cast(pa.large_binary())


def measured(spark: SparkSession, groups: list, first: int, last: int, grid: Grid, decay: decays.Decay, mode: str, dmax: str, effect: int | None, d: int, bits: int, needed: list[int], live: DataFrame | None) -> DataFrame:
    """dense.tiles() of the simulations first to last of groups of objects; of the needed features only."""
    fn, dmax = (None, "radius") if mode == "certain" else (decays.of_arrays(decay), dmax)
    shared = spark.sparkContext.broadcast((groups, dense.wanted_sets(live, d, bits)))
    some = np.zeros(1 << bits, bool)
    some[needed] = True

    def simulated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, wanted = shared.value
        for batch in batches:
            for sim in batch["id"].to_pylist():
                code, r, x, y = (np.concatenate(v) for v in zip(*[g.placed(sim) for g in held]))
                on = some[code]
                yield dense.of_simulation(sim, code[on], x[on], y[on], r[on], grid, fn, dmax, effect, d, bits, wanted)

    return spark.range(first, last + 1, 1, last - first + 1).mapInArrow(simulated, dense.OUT)
