"""Batches of texts as flat byte arrays, cut into chunks and coded by the batch's distinct chunks.

A chunk's work (tokenising, hashing) is then done once for each distinct chunk, and a document's result is
gathered from its codes in numpy or Arrow, without a Python loop over words.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

#: Bytes that separate words: space, tab, line feed, vertical tab, form feed, carriage return.
WHITE = np.zeros(256, bool)
WHITE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def released() -> None:
    """Gives memory that a task no longer needs back to the system, as Python workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library, without it


def slices(batches: Iterator[pa.RecordBatch], column: int, limit: int = 12_000_000) -> Iterator[pa.RecordBatch]:
    """The batches in parts of at most `limit` text bytes (or one row), which bounds the memory of what follows."""
    for batch in batches:
        start, n = 0, batch.num_rows
        if not n:
            continue
        ends = flat(batch.column(column))[1]
        while start < n:
            stop = int(np.searchsorted(ends, ends[start] + limit, side="right")) - 1
            stop = min(n, max(stop, start + 1))
            yield batch.slice(start, stop - start)
            start = stop
    released()


def flat(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary array; null counts as empty. Offsets start at 0."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null(b"" if pa.types.is_binary(texts.type) or pa.types.is_large_binary(texts.type) else "")
    n = len(texts)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    kind = np.int64 if texts.type in (pa.large_string(), pa.large_binary()) else np.int32
    _, offs, data = texts.buffers()
    off = np.frombuffer(offs, kind)[texts.offset : texts.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def as_binary(raw: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """The slices of raw between consecutive bounds, without a copy."""
    return pa.Array.from_buffers(pa.large_binary(), len(bounds) - 1, [None, pa.py_buffer(np.ascontiguousarray(bounds, np.int64)), pa.py_buffer(np.ascontiguousarray(raw))])


def before_space(raw: np.ndarray) -> np.ndarray:
    """Mask of the places where a run of ASCII white space begins after a byte that ends no other white space."""
    cut = np.zeros(len(raw), bool)
    if len(raw) > 1:
        white = WHITE[raw]
        cut[1:] = white[1:] & ~white[:-1]
        if raw.max() >= 0x80:  # wider white space ends in these pairs of bytes; no cut there, which is always allowed
            wide = np.zeros(256, bool)
            wide[[0xC2, 0x80, 0x81, 0x9A]] = True
            cut[2:] &= ~(wide[raw[:-2]] & (raw[1:-1] >= 0x80))
    return cut


#: Kinds of bytes: white space, letters, digits, other ASCII signs; HARD needs a full pattern.
SPACE_, LETTER, DIGIT, SIGN, HARD = range(5)
KIND = np.full(256, HARD, np.uint8)
KIND[33:127] = SIGN
KIND[48:58] = DIGIT
KIND[65:91] = KIND[97:123] = LETTER
KIND[[0x27, 0x3C]] = HARD  # an apostrophe may begin a contraction, < a special token
KIND[WHITE] = SPACE_
#: Second bytes, after C3, of the letters from U+00C0 to U+00FF.
LATIN = np.zeros(256, bool)
LATIN[[b for b in range(0x80, 0xC0) if b not in (0x97, 0xB7)]] = True


class Kinds:
    """Chunks of `before_space`, of which those with only ASCII and Latin-1 letters, digits and signs are easy: they can be
    cut into pre-tokens where the kind of byte changes."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray):
        self.kind = kind = KIND[raw]
        self.second = np.zeros(len(raw), bool)
        if len(raw) and raw.max() >= 0x80:
            self.second[1:] = (raw[:-1] == 0xC3) & LATIN[raw[1:]]
            kind[self.second] = LETTER
            kind[:-1][self.second[1:]] = LETTER
        self.cut = before_space(raw)
        self.cut[offsets[:-1][offsets[1:] > offsets[:-1]]] = True
        starts = np.flatnonzero(self.cut)
        hard = np.maximum.reduceat(kind, starts) == HARD if len(starts) else np.zeros(0, bool)
        self.easy = ~np.repeat(hard, np.diff(np.append(starts, len(raw))))

    def changes(self, each_digit: bool) -> np.ndarray:
        """Mask of the places inside easy words where another kind begins, or any digit."""
        kind, out = self.kind, np.zeros(len(self.kind), bool)
        other = kind[1:] != kind[:-1]
        if each_digit:
            other |= kind[1:] == DIGIT
        out[1:] = other & (kind[1:] != SPACE_) & (kind[:-1] != SPACE_) & self.easy[1:] & ~self.cut[1:]
        return out


class Coded:
    """Chunks of a batch: `table` of the distinct ones, `codes` (one for each chunk) and `docs` (chunk bounds of each document)."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, cut: np.ndarray):
        full = offsets[:-1][offsets[1:] > offsets[:-1]]
        cut[full] = True
        starts = np.flatnonzero(cut)
        coded = as_binary(raw, np.append(starts, len(raw))).dictionary_encode()
        self.codes = coded.indices.to_numpy(zero_copy_only=False)
        self.table = coded.dictionary
        self.docs = np.searchsorted(starts, offsets)
        self.starts = starts

    @property
    def distinct(self) -> list[bytes]:
        return self.table.to_pylist()

    def totals(self, values: np.ndarray) -> np.ndarray:
        """For each document the sum of its chunks' values."""
        run = np.zeros(len(self.codes) + 1, np.int64)
        np.cumsum(values[self.codes], out=run[1:])
        return run[self.docs[1:]] - run[self.docs[:-1]]


class Memo:
    """Results by distinct key in two generations of up to limit / 2 keys: a cache, so no result depends on it."""

    def __init__(self, compute: Callable[[list], list], limit: int = 300_000):
        self.compute, self.half, self.young, self.old = compute, limit // 2, {}, {}

    def __call__(self, keys: list) -> list:
        get = self.young.get
        out = [get(k) for k in keys]
        absent = [i for i, v in enumerate(out) if v is None]
        if not absent:
            return out
        fresh: dict = {}
        missing = []
        old = self.old.get
        for i in absent:
            v = old(keys[i])
            if v is None:
                missing.append(i)
            else:
                out[i] = fresh[keys[i]] = v
        if missing:
            names = [keys[i] for i in missing]
            values = self.compute(names)
            for i, v in zip(missing, values):
                out[i] = v
            fresh.update(zip(names, values))
        if len(self.young) + len(fresh) > self.half:
            self.old, self.young = self.young, {}
        for k, v in fresh.items() if len(fresh) <= self.half else list(fresh.items())[: self.half]:
            self.young[k] = v
        return out
