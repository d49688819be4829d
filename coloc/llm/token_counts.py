"""Token counts under a sentence-piece BPE vocabulary, by rank-synchronous merging of ragged arrays.

A text is cut before each space and around each line feed that no piece of the vocabulary reaches across; the
cuts are checked against the vocabulary when it is loaded. The distinct pre-tokens of a batch are merged
together: in every round each sequence applies its lowest-ranked pair. The symbols that survive are counted, those outside
the vocabulary as their UTF-8 bytes. A document's count is the sum over its pre-tokens.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from coloc.llm.ragged import Coded, Memo, flat, slices
from coloc.llm.rank_merge import NONE, PairTable, merge
from coloc.llm.tables import narrow, ship

SPACE = "▁"
LIMIT = 4096
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"
_LOADED: dict[str, "PieceCounter"] = {}


class PieceCounter:
    """Counts for distinct pre-tokens under one model file."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        plain = [i for i in range(model.vocab_size()) if not (model.is_unknown(i) or model.is_control(i) or model.is_byte(i))]
        piece = {model.id_to_piece(i): i for i in plain}
        chars = sorted({c for p in piece for c in p})
        ids = dict.fromkeys(chars) | dict.fromkeys(piece)
        self.symbol = {s: k for k, s in enumerate(ids)}
        self.cost = np.array([1 if s in piece else len(s.encode()) for s in self.symbol] or [1], np.int64)
        score = {s: model.get_score(i) for s, i in piece.items()}
        order = {v: k for k, v in enumerate(sorted(set(score.values()), reverse=True))}
        ranks = np.array([order[score[s]] if s in score and len(s) > 1 else NONE for s in self.symbol], np.int64)
        parts = [(self.symbol[p[:k]], self.symbol[p[k:]], self.symbol[p]) for p in piece for k in range(1, len(p)) if p[:k] in self.symbol and p[k:] in self.symbol]
        left, right, whole = np.array(parts, np.int64).reshape(-1, 3).T
        self.table = PairTable(left, right, whole, ranks)
        #: a cut before a space is safe if no piece has a space after another character
        self.space_safe = not any(SPACE in p.lstrip(SPACE) for p in piece)
        self.line_safe = not any("\n" in p for p in piece)
        self.by_char = {ord(c): self.symbol[c] for c in chars}
        self.memo = Memo(self._count, 300_000)
        # the library's own normaliser decides; other settings than these would need its rules
        probe = " a  b　ﬁ\n"
        if model.encode(probe, out_type=str) and "".join(model.encode(probe, out_type=str)).replace("<0x0A>", "\n") != SPACE + probe.replace(" ", SPACE):
            raise ValueError("the model's normaliser changes its text; only an identity normaliser is supported")

    def _count(self, keys: list[str]) -> list[int]:
        text = "".join(keys)
        lengths = np.fromiter(map(len, keys), np.int64, len(keys))
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        there = np.zeros(int(points.max()) + 1, bool)
        there[points] = True
        seen, at = np.flatnonzero(there), (np.cumsum(there) - 1)[points]
        known = np.array([self.by_char.get(int(c), -1) for c in seen], np.int64)
        extra = np.array([len(chr(int(c)).encode("utf-8", "surrogatepass")) for c in seen], np.int64)
        symbols = known[at]
        outside = symbols < 0
        run = np.zeros(len(points) + 1, np.int64)
        np.cumsum(np.where(outside, extra[at], 0), out=run[1:])
        ends = np.cumsum(lengths)
        lost = run[ends] - run[ends - lengths]
        base = len(self.symbol)
        got, sizes = merge(self.table, np.where(outside, base, symbols), lengths)
        cost = np.append(self.cost, 0)
        run = np.zeros(len(got) + 1, np.int64)
        np.cumsum(cost[got], out=run[1:])
        ends = np.cumsum(sizes)
        return (run[ends] - run[ends - sizes] + lost).tolist()

    def counts(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """For each document the number of tokens."""
        n = len(offsets) - 1
        cut = np.zeros(len(raw), bool)
        if len(raw) and self.space_safe:
            space = raw == 0x20
            cut[1:] = space[1:] & ~space[:-1]
            cut[0] = space[0]
            if self.line_safe:
                line = raw == 0x0A
                cut |= line
                cut[1:] |= line[:-1]
        coded = Coded(raw, offsets, cut)
        first = np.zeros(len(coded.codes), bool)
        first[coded.docs[:-1][coded.docs[1:] > coded.docs[:-1]]] = True
        # a first chunk has one space more than it shows; both forms are coded apart
        codes = coded.codes.astype(np.int64) * 2 + first
        distinct = coded.distinct
        seen = np.zeros(2 * len(distinct), bool)
        seen[codes] = True
        used = np.flatnonzero(seen)
        codes = (np.cumsum(seen) - 1)[codes]
        keys = [(SPACE if u & 1 else "") + distinct[u >> 1].decode("utf-8", "surrogatepass").replace(" ", SPACE) for u in used.tolist()]
        coded.codes = codes
        return coded.totals(np.array(self.memo(keys), np.int64)) if n and keys else np.zeros(n, np.int64)


def counter(path: str) -> PieceCounter:
    if path not in _LOADED:
        _LOADED[path] = PieceCounter(path)
    return _LOADED[path]


def token_counts(docs: DataFrame, model_path: str, limit: int = LIMIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row.

    Null and empty texts have no bytes and no tokens. A null id stays null, repeated rows each give a row, an
    empty table gives no rows, and other columns are ignored whatever their names. Texts of any length are counted whole; one
    pre-token without spaces is merged as one sequence.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = counter(model_path)
        for batch in slices(batches, 1):
            raw, offsets = flat(batch.column(1))
            tokens = own.counts(raw, offsets)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(offsets)), pa.array(tokens), pa.array(tokens > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return narrow(docs, doc_id=id_col, text=text_col).selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, SCHEMA)
