"""Packing by minimum bin slack: documents' tokens laid into sequences of a fixed capacity.

Each task packs the documents it reads, in bounded groups, so nothing is shuffled and no state is shared. Whole windows are cut
off long documents first. The remaining lengths form a multiset; every window takes the sub-multiset whose sum comes
closest to the capacity. A bitset of reachable sums (one Python integer) is shifted once per usable copy of each length, longest first;
the search for a window ends as soon as the capacity itself is reachable. Walking the stored bitsets back gives how
many of each length the best sum uses. The longest remaining length is always part of the window, so none is left to the end.
Where the best sum falls short, the shortest remaining document is cut to fill the window. What is left of a group at the end
goes to sequences of power-of-two lengths, which need no padding.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from coloc.llm.ragged import slices
from coloc.llm.tables import narrow, ship
from coloc.llm.word_ids import word_ids

CAPACITY = 4096
END_ID = 2
GROUP_TOKENS = 4_000_000
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def best_fill(counts: dict[int, int], lengths: list[int], capacity: int) -> dict[int, int]:
    """How many of each length to take so that their sum, with one of lengths[0], is the largest up to capacity.

    `lengths` holds the distinct lengths with copies left, longest first, none above capacity.
    """
    first = lengths[0]
    room = capacity - first
    full = (1 << (room + 1)) - 1
    reach = 1
    steps: list[tuple[int, int]] = []  # (length, sums reachable before this copy)
    for n in lengths:
        if n > room:
            continue
        for _ in range(min(counts[n] - (n == first), room // n)):
            wider = (reach | (reach << n)) & full
            if wider == reach:
                break
            steps.append((n, reach))
            reach = wider
            if reach >> room & 1:
                break
        if reach >> room & 1:
            break
    total = reach.bit_length() - 1
    taken = {first: 1}
    for n, before in reversed(steps):
        if not before >> total & 1:
            taken[n] = taken.get(n, 0) + 1
            total -= n
    return taken


def pack(sizes: list[int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """(item, start, length, sequence, offset) of pieces that hold every token of the items once."""
    out: list[tuple[int, int, int, int, int]] = []
    seq = 0
    by_length: dict[int, list[tuple[int, int]]] = {}
    for k, n in enumerate(sizes):
        whole = n // capacity
        for w in range(whole):
            out.append((k, w * capacity, capacity, seq, 0))
            seq += 1
        if n % capacity:
            by_length.setdefault(n % capacity, []).append((k, whole * capacity))
    lengths = sorted(by_length, reverse=True)
    counts = {n: len(v) for n, v in by_length.items()}
    left = sum(n * c for n, c in counts.items())

    def take(n: int) -> tuple[int, int]:
        nonlocal left
        counts[n] -= 1
        left -= n
        if not counts[n]:
            del counts[n]
            lengths.remove(n)
        return by_length[n].pop()

    while left >= capacity:
        fill = best_fill(counts, lengths, capacity)
        at = 0
        for n, times in fill.items():
            for _ in range(times):
                k, start = take(n)
                out.append((k, start, n, seq, at))
                at += n
        if at < capacity:  # enough tokens are left, so some document can be cut to fill the gap
            gap = capacity - at
            n = next(n for n in reversed(lengths) if n > gap)
            k, start = take(n)
            out.append((k, start, gap, seq, at))
            rest = n - gap
            if rest not in counts:
                counts[rest] = 0
                lengths.append(rest)
                lengths.sort(reverse=True)
                by_length.setdefault(rest, [])
            counts[rest] += 1
            by_length[rest].append((k, start + gap))
            left += rest
        seq += 1
    rest = [(k, start, n) for n in lengths for k, start in by_length[n]]
    at, size = 0, 1 << (max(left, 1).bit_length() - 1)
    for k, start, n in rest:
        while n:
            if at == size:
                left, seq, at = left - size, seq + 1, 0
                size = 1 << (left.bit_length() - 1)
            part = min(n, size - at)
            out.append((k, start, part, seq, at))
            start, n, at = start + part, n - part, at + part
    return out


def _pieces(batches: Iterator[pa.RecordBatch], path: str, capacity: int, end_id: int) -> Iterator[pa.RecordBatch]:
    own = word_ids(path)
    ctx = TaskContext.get()
    base = (ctx.partitionId() if ctx else 0) << 36
    held: list[tuple[pa.Array, np.ndarray, np.ndarray]] = []
    tokens = 0

    def flush() -> pa.RecordBatch:
        nonlocal base
        names = pa.concat_arrays([h[0] for h in held])
        sizes = np.concatenate([np.diff(h[2]) for h in held])
        ids = np.concatenate([h[1] for h in held])
        begin = np.append(0, np.cumsum(sizes))
        item, start, length, seq, offset = np.array(pack(sizes.tolist(), capacity), np.int64).reshape(-1, 5).T
        raw = memoryview(ids.astype("<u2" if not len(ids) or ids.max() < 1 << 16 else "<u4"))
        at = begin[item] + start
        crc = [zlib.crc32(np.asarray(raw[a:b]).astype("<u4").tobytes()) for a, b in zip(at.tolist(), (at + length).tolist())]
        batch = pa.RecordBatch.from_arrays([names.take(pa.array(item)), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(sizes[item]), pa.array(seq + base), pa.array(offset)], [f.split()[0] for f in SCHEMA.split(", ")])
        base += int(seq.max()) + 1 if len(seq) else 0
        held.clear()
        return batch

    for batch in slices(batches, 1, 1_000_000):
        ids, bounds = own.ids(batch.column(1), end_id)
        held.append((batch.column(0), ids.astype(np.uint16) if not len(ids) or ids.max() < 1 << 16 else ids, bounds))
        tokens += len(ids)
        if tokens >= GROUP_TOKENS:
            yield flush()
            tokens = 0
    if held:
        yield flush()


def packed(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Every row of docs, also a repeated one or one with a null id, is a document of its own. A null or empty text is one end
    token. A text longer than the capacity fills whole windows and its rest is packed with others. Ties between equal lengths go
    to the row read last. An empty table gives no pieces; other columns are ignored. Sequences are full, or of a
    power-of-two length at the end of a group of GROUP_TOKENS tokens or of a task, so nothing is padded.
    """
    ship(docs.sparkSession)
    rows = narrow(docs, doc_id=id_col, text=text_col).selectExpr("cast(doc_id as long) doc_id", "text")
    return rows.mapInArrow(partial(_pieces, path=tokenizer_path, capacity=capacity, end_id=end_id), SCHEMA)
