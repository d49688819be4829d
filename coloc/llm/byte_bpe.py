"""Byte-level BPE by rank files: encoding and decoding as monoid tree reductions.

A pre-token's bytes are encoded by halves down to leaves of a few bytes. Two encoded neighbours are joined by re-encoding a
window of tokens at their boundary; it grows on a side as long as the token outside it and the window's outermost token
are not the encoding of their own bytes. Once both borders hold, every adjacent pair of the result is the encoding of its bytes,
which only the encoding of the whole has, so no token further out can change. Joining is associative, so any tree
gives the same tokens. All distinct pre-tokens of a batch go up the tree together: a level is a handful of array operations.

Decoding goes up a tree of the tokens' bytes, which lie side by side, so that joining two neighbours is dropping the border between them.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from coloc.llm.ragged import SPACE_, Coded, Kinds, as_binary, flat, slices
from coloc.llm.rank_merge import PairTable, merge
from coloc.llm.tables import narrow, ship

LEAF = 8
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
_LOADED: dict[tuple[str, str], "ByteBpe"] = {}


def _spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices of the ranges that begin at `starts`, one range after the other."""
    ends = np.cumsum(sizes)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)


class ByteBpe:
    def __init__(self, path: str, pattern: str):
        import regex

        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.bytes_of = {i: t for t, i in self.ranks.items()}
        self.split = regex.compile(pattern).findall
        #: whether the pattern is the one that Kinds can follow in easy chunks
        self.usual = pattern == r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
        size = max(self.bytes_of) + 1
        tokens = [self.bytes_of.get(i, b"") for i in range(size)]
        self.size = np.fromiter(map(len, tokens), np.int64, size)
        self.begin = np.append(0, np.cumsum(self.size))
        self.raw = np.frombuffer(b"".join(tokens), np.uint8)
        self.decimal = pa.array([b",%d" % i for i in range(size)], pa.large_binary())
        self.single = np.array([self.ranks[bytes([b])] for b in range(256)], np.int32)
        get = self.ranks.get
        parts = [(a, b, i) for t, i in self.ranks.items() for k in range(1, len(t)) if (a := get(t[:k])) is not None and (b := get(t[k:])) is not None]
        left, right, whole = np.array(parts, np.int64).reshape(-1, 3).T
        self.table = PairTable(left, right, whole, np.arange(size))

    def spelled(self, ids: np.ndarray) -> np.ndarray:
        """The bytes of the tokens in a row, each as its one-byte token."""
        return self.single[self.raw[_spread(self.begin[ids], self.size[ids])]]

    def holds(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Whether each pair of tokens is the encoding of its own bytes."""
        key, at = np.unique((left.astype(np.int64) << 32) | right, return_inverse=True)
        a, b = key >> 32, key & 0xFFFFFFFF
        got, sizes = merge(self.table, self.spelled(np.stack([a, b], 1).ravel()), self.size[a] + self.size[b])
        first = np.cumsum(sizes) - sizes
        ok = sizes == 2
        ok[ok] = (got[first[ok]] == a[ok]) & (got[first[ok] + 1] == b[ok])
        return ok[at]

    def _join(self, ids: np.ndarray, begin: np.ndarray, middle: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Joins ids[begin:middle] with ids[middle:end] for each; returns the new ids and, by old place, how many places later
        each begins."""
        bad = np.flatnonzero(~self.holds(ids[middle - 1], ids[middle]))
        at, low, high = middle[bad], begin[bad], end[bad]
        i, j = np.ones(len(bad), np.int64), np.ones(len(bad), np.int64)
        step = 1
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        while len(at):
            inside = ids[_spread(at - i, i + j)]
            edge = np.cumsum(i + j)
            run = np.append(0, np.cumsum(self.size[inside]))
            got, sizes = merge(self.table, self.spelled(inside), run[edge] - run[edge - i - j])
            last = np.cumsum(sizes) - 1
            left, right = at - i == low, at + j == high
            left[k] = self.holds(ids[(at - i - 1)[k]], got[(last - sizes + 1)[k]]) if len(k := np.flatnonzero(~left)) else True
            right[k] = self.holds(got[last[k]], ids[(at + j)[k]]) if len(k := np.flatnonzero(~right)) else True
            fine = left & right
            done.append((at[fine] - i[fine], i[fine] + j[fine], sizes[fine], got[np.repeat(fine, sizes)]))
            i, j = np.where(left, i, np.minimum(i + step, at - low)), np.where(right, j, np.minimum(j + step, high - at))
            at, low, high, i, j = at[~fine], low[~fine], high[~fine], i[~fine], j[~fine]
            step *= 2
        if not done:
            return ids, np.zeros(len(ids) + 1, np.int64)
        start, old, new, got = (np.concatenate(x) for x in zip(*done))
        keep = np.ones(len(ids), bool)
        keep[_spread(start, old)] = False
        place = np.concatenate([np.flatnonzero(keep), np.repeat(start, new)])
        order = np.argsort(place, kind="stable")
        shift = np.zeros(len(ids) + 1, np.int64)
        shift[start + old] = new - old
        return np.concatenate([ids[keep], got])[order], np.cumsum(shift)

    def tree(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids) of the byte strings between the offsets, by the tree alone."""
        sizes = np.diff(offsets)
        leaves = -(-sizes // LEAF)
        nth = _spread(np.zeros(len(sizes), np.int64), leaves)
        own, n = np.repeat(sizes, leaves), np.repeat(leaves, leaves)
        ids, got = merge(self.table, self.single[raw], own * (nth + 1) // n - own * nth // n)
        begin = np.append(0, np.cumsum(got))[:-1]  # of each node; a node ends where the next begins
        while (leaves > 1).any():
            first = np.cumsum(leaves) - leaves
            left = np.repeat(first, leaves // 2) + 2 * _spread(np.zeros(len(leaves), np.int64), leaves // 2)
            edges = np.append(begin, len(ids))
            ids, shift = self._join(ids, edges[left], edges[left + 1], edges[left + 2])
            begin = begin + shift[begin]
            keep = np.ones(len(begin), bool)
            keep[left + 1] = False
            begin = begin[keep]
            leaves = leaves - leaves // 2
        edges = np.append(begin, len(ids))
        ends = np.cumsum(leaves)
        return ids, edges[ends] - edges[ends - leaves]

    def pre_tokens(self, parts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """As the rank files' library does: a pre-token that is a token stays one, the others are encoded."""
        whole = np.fromiter((self.ranks.get(p, -1) for p in parts), np.int64, len(parts))
        rest = np.flatnonzero(whole < 0)
        some = [parts[i] for i in rest.tolist()]
        ids, got = self.tree(np.frombuffer(b"".join(some), np.uint8), np.append(0, np.cumsum(np.fromiter(map(len, some), np.int64, len(some)))))
        counts = np.ones(len(parts), np.int64)
        counts[rest] = got
        out = np.zeros(int(counts.sum()), np.int32)
        alone = np.repeat(whole >= 0, counts)
        out[alone] = whole[whole >= 0]
        out[~alone] = ids
        return out, counts

    def cuts(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, Kinds]:
        """Where pre-tokens of the usual pattern begin in easy chunks; other chunks stay whole for the pattern itself."""
        kinds = Kinds(raw, offsets)
        if not self.usual:
            kinds.easy[:] = False
            return kinds.cut, kinds
        cut = kinds.changes(each_digit=False) | kinds.cut
        if len(raw):
            white = kinds.kind == SPACE_
            start = np.flatnonzero(white[:-1] & ~white[1:] & kinds.easy[1:] & ~kinds.cut[1:]) + 1  # of words after white space
            cut[start[raw[start - 1] != 0x20]] = True
            cut[start - 1] = True
        return cut, kinds

    def batch(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts in order, bounds of each text)."""
        raw, offsets = flat(texts)
        cut, kinds = self.cuts(raw, offsets)
        coded = Coded(raw, offsets, cut)
        parts, sizes = coded.distinct, np.ones(len(coded.table), np.int64)
        hard = np.ones(len(parts), bool)
        hard[coded.codes[kinds.easy[coded.starts]]] = False
        if hard.any():
            split = {i: [p.encode("utf-8", "surrogatepass") for p in self.split(parts[i].decode("utf-8", "surrogatepass"))] for i in np.flatnonzero(hard).tolist()}
            sizes[list(split)] = [len(s) for s in split.values()]
            parts = [p for i, one in enumerate(parts) for p in split.get(i, (one,))]
        ids, counts = self.pre_tokens(parts)
        edges, ends = np.append(0, np.cumsum(counts)), np.append(0, np.cumsum(sizes))
        whole = as_binary(ids.astype("<u4").view(np.uint8), edges[ends] * 4).take(pa.array(coded.codes))
        data, bounds = flat(whole)
        return data.view("<u4"), bounds[coded.docs] // 4

    def encode(self, text: str) -> list[int]:
        return self.batch(pa.array([text]))[0].tolist()

    def decoded(self, ids: np.ndarray, bounds: np.ndarray) -> tuple[memoryview, np.ndarray]:
        """The bytes of the documents whose ids lie between the bounds, and the documents' bounds there."""
        if len(ids) and (ids.min() < 0 or ids.max() >= len(self.size) or not self.size[ids].all()):
            raise ValueError("an id is not in the rank file")
        starts, nodes = self.begin[ids], np.diff(bounds)
        raw = self.raw[_spread(starts, self.size[ids])]
        starts = np.cumsum(self.size[ids]) - self.size[ids]  # of each node; a node ends where the next begins
        while (nodes > 1).any():
            starts = starts[_spread(np.zeros(len(nodes), np.int64), nodes) % 2 == 0]
            nodes = -(-nodes // 2)
        return memoryview(raw), np.append(starts, len(raw))[np.append(0, np.cumsum(nodes))]

    def decode(self, ids) -> bytes:
        return bytes(self.decoded(np.asarray(ids, np.int64), np.array([0, len(ids)]))[0])

    def joined(self, table: pa.Array, ids: np.ndarray, bounds: np.ndarray) -> tuple[memoryview, np.ndarray]:
        """The table's entries of the ids one after the other, and the documents' bounds there."""
        raw, at = flat(table.take(pa.array(ids)))
        return memoryview(raw), at[bounds]


def codec(path: str, pattern: str) -> ByteBpe:
    if (path, pattern) not in _LOADED:
        _LOADED[path, pattern] = ByteBpe(path, pattern)
    return _LOADED[path, pattern]


def _digests(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    for batch in slices(batches, 1):
        ids, bounds = own.batch(batch.column(1))
        text, at = own.joined(own.decimal, ids, bounds)
        sha = [hashlib.sha256(text[a + 1 : b] if b > a else b"").hexdigest() for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
        text, at = own.decoded(ids, bounds)
        back = [hashlib.sha256(text[a:b]).hexdigest() for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(bounds)), pa.array(sha), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _id_lists(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    for batch in slices(batches, 1):
        ids, bounds = own.batch(batch.column(1))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids.astype(np.int32)))], ["doc_id", "ids"])


def _texts(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    for batch in batches:
        lists = [[i for i in x if i is not None] if x else [] for x in batch.column(1).to_pylist()]
        text, at = own.decoded(np.array([i for x in lists for i in x], np.int64), np.append(0, np.cumsum([len(x) for x in lists], dtype=np.int64)))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bytes(text[a:b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist())], pa.binary())], ["doc_id", "decoded"])


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (array<int>) for every row; a null or empty text has none, and repeated rows and null ids stay."""
    ship(docs.sparkSession)
    return _source(docs, id_col, text_col).mapInArrow(partial(_id_lists, path=path, pattern=pattern), "doc_id long, ids array<int>")


def decode(encoded_docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, decoded (binary): the bytes of each row's ids; none for null or empty lists, nor for nulls in them. An id that the rank file lacks raises ValueError."""
    ship(encoded_docs.sparkSession)
    rows = narrow(encoded_docs, doc_id=id_col, ids=ids_col).selectExpr("cast(doc_id as long) doc_id", "ids")
    return rows.mapInArrow(partial(_texts, path=path, pattern=pattern), "doc_id long, decoded binary")


def digests(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: encodes every whole text, then decodes its ids.

    Null and empty texts have no ids; both digests are then those of no bytes. Null ids and repeated rows each keep
    their row, an empty table gives none, other columns are ignored. A pre-token of any length is encoded by the tree.
    """
    ship(docs.sparkSession)
    return _source(docs, id_col, text_col).mapInArrow(partial(_digests, path=path, pattern=pattern), SCHEMA)


def _source(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return narrow(docs, doc_id=id_col, text=text_col).selectExpr("cast(doc_id as long) doc_id", "text")
