"""A byte-level convolutional network in numpy that scores the quality of whole texts.

A text is read in chunks of 16 bytes, one every 8 bytes. A filter has a weight for each byte value at each of the 16
places. The filters' values are max-pooled over segments of 64 chunks, passed through a hyperbolic tangent, averaged and max-pooled
over the text's segments, and combined into one probability. Training follows the gradient through the chunks that won the pooling.

A score is a function of the text alone: no sum runs over the texts of a batch, and texts longer than a slab are read slab by slab from their own start.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.llm import samples
from coloc.llm.ragged import flat, slices
from coloc.llm.tables import narrow, ship

SCHEMA = "doc_id long, held_out boolean, score double, predicted int"
#: Bounds of the training sample: texts per label, pieces of a text, characters of a piece.
QUOTA, PIECES, PIECE = 1_500, 2, 8_192
BLOCK, FILTERS, SEGMENT = 8, 20, 64
#: Bytes of one text that are held at once: whole segments.
SLAB = BLOCK * SEGMENT * 4_096
EPOCHS, BATCH, RATE, DECAY = 12, 30, 0.01, 1e-4
THRESHOLD = 0.3
DIVISOR, HELD_OUT = 5, 0


@dataclass
class Network:
    bytes_: np.ndarray  # 16 x 256 x FILTERS
    bias: np.ndarray  # FILTERS
    out: np.ndarray  # 2 * FILTERS
    base: float


@dataclass
class Chunks:
    """Documents' bytes in blocks of 8, each document ending in a spare block; chunks are blocks with the next one."""

    blocks: np.ndarray
    chunk: np.ndarray  # block of each chunk
    segment: np.ndarray  # first chunk of each segment
    document: np.ndarray  # first segment of each document


def chunks(raw: np.ndarray, offsets: np.ndarray) -> Chunks:
    sizes = np.diff(offsets)
    n_chunks = np.maximum(-(-sizes // BLOCK), 1)
    first = np.cumsum(n_chunks + 1) - (n_chunks + 1)
    buf = np.zeros(int((n_chunks + 1).sum()) * BLOCK, np.uint8)
    buf[np.arange(len(raw)) + np.repeat(first * BLOCK - offsets[:-1], sizes)] = raw
    chunk = np.arange(int(n_chunks.sum())) + np.repeat(first - (np.cumsum(n_chunks) - n_chunks), n_chunks)
    n_segments = -(-n_chunks // SEGMENT)
    nth = np.arange(int(n_segments.sum())) - np.repeat(np.cumsum(n_segments) - n_segments, n_segments)
    segment = np.repeat(np.cumsum(n_chunks) - n_chunks, n_segments) + nth * SEGMENT
    return Chunks(buf.reshape(-1, BLOCK), chunk, segment, np.cumsum(n_segments) - n_segments)


def filtered(net: Network, c: Chunks) -> np.ndarray:
    """The filters' values of every chunk."""
    low = np.zeros((len(c.blocks), FILTERS), np.float32)
    high = np.zeros_like(low)
    for j in range(BLOCK):
        low += net.bytes_[j].take(c.blocks[:, j], 0)
        high += net.bytes_[BLOCK + j].take(c.blocks[:, j], 0)
    return low[c.chunk] + high[c.chunk + 1] + net.bias


def pooled(net: Network, c: Chunks) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sums, maxima, numbers) of the documents' segments."""
    act = np.tanh(np.maximum.reduceat(filtered(net, c), c.segment, axis=0))
    return np.add.reduceat(act, c.document, axis=0), np.maximum.reduceat(act, c.document, axis=0), np.diff(np.append(c.document, len(act)))


def _slabs(net: Network, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """pooled() of one long text, a slab at a time; a slab's last chunk reaches into the next slab."""
    total, most, count = np.zeros((1, FILTERS), np.float32), np.full((1, FILTERS), -1, np.float32), np.zeros(1, np.int64)
    for start in range(0, len(raw), SLAB):
        part = raw[start : start + SLAB + BLOCK]
        c = chunks(part, np.array([0, len(part)]))
        if len(part) > SLAB:  # the next slab begins with the chunk of these bytes
            c = Chunks(c.blocks, c.chunk[: SLAB // BLOCK], c.segment[: SLAB // BLOCK // SEGMENT], c.document)
        a, b, n = pooled(net, c)
        total, most, count = total + a, np.maximum(most, b), count + n
    return total, most, count


def probability(net: Network, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """For each text the probability of label 1."""
    if not len(offsets) - 1:
        return np.zeros(0)
    long = np.diff(offsets) > SLAB
    if long.any():
        each = [_slabs(net, raw[a:b]) if b - a > SLAB else pooled(net, chunks(raw[a:b], np.array([0, b - a]))) for a, b in zip(offsets[:-1], offsets[1:])]
        total, most, count = (np.concatenate(x) for x in zip(*each))
    else:
        total, most, count = pooled(net, chunks(raw, offsets))
    # row by row, as a matrix product may round a row by its place
    value = (total / count[:, None] * net.out[:FILTERS]).sum(1, dtype=np.float64) + (most * net.out[FILTERS:]).sum(1, dtype=np.float64)
    return 1 / (1 + np.exp(-(value + net.base)))


def fit(rows: list[tuple[int, str]], good: float = 0.5, seed: int = 7) -> Network:
    """Adam on the log loss of (label, text) rows; those of label 1 weigh `good` of all together."""
    rng = np.random.default_rng(seed)
    net = Network(
        rng.normal(0, 0.05, (2 * BLOCK, 256, FILTERS)).astype(np.float32),
        np.zeros(FILTERS, np.float32),
        rng.normal(0, 0.5, 2 * FILTERS).astype(np.float32),
        0.0,
    )
    if not rows:
        return net
    label = np.array([r[0] for r in rows], np.float64)
    weight = np.where(label == 1, good / max(1, (label == 1).sum()), (1 - good) / max(1, (label != 1).sum())) * len(rows)
    names = ("bytes_", "bias", "out", "base")
    m = {k: np.zeros_like(np.asarray(getattr(net, k), np.float64)) for k in names}
    v = {k: np.zeros_like(m[k]) for k in names}
    step = 0
    batches = [np.sort(b) for b in np.array_split(rng.permutation(len(rows)), max(1, len(rows) // BATCH))]
    prepared = [chunks(*flat(pa.array([rows[i][1] for i in b]))) for b in batches]
    last = EPOCHS * len(batches)
    for _ in range(EPOCHS):
        for at in rng.permutation(len(batches)).tolist():
            b, c = batches[at], prepared[at]
            raw = filtered(net, c)
            top = np.maximum.reduceat(raw, c.segment, axis=0)
            act = np.tanh(top)
            count = np.diff(np.append(c.document, len(act)))
            feature = np.concatenate([np.add.reduceat(act, c.document, axis=0) / count[:, None], np.maximum.reduceat(act, c.document, axis=0)], 1)
            p = 1 / (1 + np.exp(-(feature @ net.out + net.base)))
            g = (p - label[b]) * weight[b] / len(b)
            grad = {"out": feature.T @ g + DECAY * net.out, "base": g.sum()}
            back = np.repeat(g / count, count)[:, None] * net.out[:FILTERS]
            of = np.repeat(np.arange(len(b)), count)
            won = act == feature[:, FILTERS:][of]
            back += won * (g[:, None] * net.out[FILTERS:])[of]
            back *= 1 - act**2
            # the chunk of each segment and filter that won
            seg = np.repeat(np.arange(len(c.segment)), np.diff(np.append(c.segment, len(raw))))
            hit_chunk, hit_filter = np.nonzero(raw == top[seg])
            value = back[seg[hit_chunk], hit_filter]
            block = c.chunk[hit_chunk]
            grad["bias"] = np.bincount(hit_filter, value, FILTERS)
            grad["bytes_"] = np.stack([np.bincount(c.blocks[block + j // BLOCK, j % BLOCK].astype(np.int64) * FILTERS + hit_filter, value, 256 * FILTERS).reshape(256, FILTERS) for j in range(2 * BLOCK)]) + DECAY * net.bytes_
            step += 1
            rate = RATE * (1 - (step - 1) / last)
            for k in names:
                m[k] = 0.9 * m[k] + 0.1 * grad[k]
                v[k] = 0.999 * v[k] + 0.001 * grad[k] ** 2
                moved = getattr(net, k) - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
                setattr(net, k, float(moved) if k == "base" else moved.astype(np.float32))
    return net


def _scored(batches: Iterator[pa.RecordBatch], net: Network) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, 2, SLAB):
        score = probability(net, *flat(batch.column(2)))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Network:
    """Fits on at most QUOTA texts of each label, from rows outside the held-out fold: those whose ids have the smallest hashes.

    Ids with several labels take the lowest, ids with several texts the smallest. Without a labelled text the network stays as it was drawn. Of a text longer than a piece, PIECES pieces spread over it from start to end are learned.
    A label weighs as much as its share of all labelled rows outside the fold.
    """
    known = narrow(labels, doc_id=id_col, label=label_col).where(F.col("label").isin(0, 1)).where(samples.remainder("doc_id", DIVISOR) != HELD_OUT)
    known = known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("label").alias("label"))
    texts = narrow(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # which ids to take is settled without the texts; only theirs are then looked up
    drawn = samples.smallest(known.select("label", F.col("doc_id").alias("key")), QUOTA, of=texts.where(F.octet_length("text") > 0).select(F.col("doc_id").alias("key")))
    wanted = drawn.select("label", F.col("key").alias("doc_id"))  # at most QUOTA rows for each of two labels
    long = F.char_length("text")
    pieces = F.when(long <= PIECE, F.array("text")).otherwise(F.array(*[F.substring("text", F.floor((long - PIECE) * (k / (PIECES - 1))).cast("int") + F.lit(1), F.lit(PIECE)) for k in range(PIECES)]))
    one = texts.join(F.broadcast(wanted), "doc_id").groupBy("label", "doc_id").agg(F.min("text").alias("text"))
    rows = one.select("label", "doc_id", F.explode(pieces).alias("piece")).collect()
    counts = {int(r[0]): r[1] for r in known.groupBy("label").count().collect()}
    good = counts.get(1, 0) / max(1, sum(counts.values()))
    return fit([(int(r["label"]), r["piece"]) for r in sorted(rows, key=lambda r: (r["label"], r["doc_id"], r["piece"]))], good)


def scores(docs: DataFrame, net: Network, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted for every row, from its whole text of any length.

    Equal texts have equal scores wherever their rows lie. A null or empty text is one empty chunk and is scored like any other. A null id counts as empty text in the fold's
    checksum; repeated rows each give a row, an empty table none, other columns are ignored.
    """
    ship(docs.sparkSession)
    rows = narrow(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), (samples.remainder("doc_id", DIVISOR) == HELD_OUT).alias("held_out"), "text")
    return rows.mapInArrow(partial(_scored, net=net), SCHEMA)


def _accepted(batches: Iterator[pa.RecordBatch], net: Network, text: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, text, SLAB):
        yield batch.filter(pa.array(probability(net, *flat(batch.column(text))) >= THRESHOLD))


def accepted(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that are predicted to be good.

    Null and empty texts are scored as one empty chunk. Equal rows are kept or dropped together, a score of THRESHOLD exactly is kept, an
    empty table stays empty, and null ids and clashing other columns make no difference.
    """
    ship(docs.sparkSession)
    net = train(docs, labels, id_col, text_col)
    return docs.mapInArrow(partial(_accepted, net=net, text=docs.columns.index(text_col)), docs.schema)
