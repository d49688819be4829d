"""Token ids of a word-level BPE file for the tokenizers library, by distinct words.

The file's normaliser and splitter never reach across white space (checked for its added tokens and pattern in the tests),
so a text's ids are those of its words. Words of ASCII and Latin-1 letters, digits and signs are split here and
merged together in arrays; all others go through the library itself.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa

from coloc.llm.ragged import SPACE_, Coded, Kinds, Memo, as_binary, flat
from coloc.llm.rank_merge import NONE, PairTable, merge

_LOADED: dict[str, "WordIds"] = {}


def _byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class WordIds:
    def __init__(self, path: str, limit: int = 250_000):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        model = file["model"]
        vocab, suffix = model["vocab"], model["end_of_word_suffix"]
        size = max(vocab.values()) + 1
        ranks = np.full(size, NONE, np.int64)
        left, right, made = [], [], []
        for k, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            whole = vocab[a + b]
            left.append(vocab[a])
            right.append(vocab[b])
            made.append(whole)
            ranks[whole] = min(ranks[whole], k)
        # the arrays rank by the merged symbol; a vocabulary with two merges into one symbol goes to the library
        self.own = len(set(made)) == len(made)
        self.table = PairTable(np.array(left), np.array(right), np.array(made), ranks)
        letters = _byte_letters()
        self.inner = np.array([vocab.get(c, -1) for c in letters], np.int32)
        self.last = np.array([vocab.get(c + suffix, -1) for c in letters], np.int32)
        self.memo = Memo(self._library, limit)
        lower = np.arange(256, dtype=np.uint8)
        lower[65:91] += 32
        self.lower = lower

    def _library(self, keys: list[bytes]) -> list[bytes]:
        texts = [k.decode("utf-8", "surrogatepass") for k in keys]
        return [np.array(e.ids, "<u4").tobytes() for i in range(0, len(texts), 4096) for e in self.whole.encode_batch(texts[i : i + 4096], add_special_tokens=False)]

    def _distinct(self, table: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, number of ids) of the distinct chunks."""
        raw, offsets = flat(table)
        kinds = Kinds(raw, offsets)
        word = kinds.kind != SPACE_
        sizes = np.diff(offsets)
        easy = np.ones(len(sizes), bool)
        easy[sizes > 0] = kinds.easy[offsets[:-1][sizes > 0]]
        easy &= self.own
        use = word & np.repeat(easy, sizes)
        run = np.append(0, np.cumsum(use))
        lengths = run[offsets[1:]] - run[offsets[:-1]]
        letters = raw[use]
        symbols = self.inner[letters]
        ends = np.cumsum(lengths)[lengths > 0] - 1
        symbols[ends] = self.last[letters[ends]]
        got, counts = merge(self.table, symbols, lengths)
        hard = np.flatnonzero(~easy)
        if not len(hard):
            return got, counts
        more = self.memo(table.take(pa.array(hard)).to_pylist())
        counts[hard] = np.fromiter(map(len, more), np.int64, len(more)) // 4
        out = np.zeros(int(counts.sum()), np.int32)
        late = np.repeat(~easy, counts)
        out[~late] = got
        out[late] = np.frombuffer(b"".join(more), "<u4")
        return out, counts

    def ids(self, texts: pa.Array, end_id: int | None) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts in order, bounds of each text), each text's followed by end_id if that is given."""
        raw, offsets = flat(texts)
        kinds = Kinds(raw, offsets)
        small = np.where(kinds.second & (raw <= 0x9E), raw + 32, self.lower[raw])  # capital Latin-1 letters end in 80 to 9E
        coded = Coded(np.where(kinds.easy, small, raw).astype(np.uint8), offsets, kinds.changes(each_digit=True) | kinds.cut)
        ids, counts = self._distinct(coded.table)
        codes, docs = coded.codes, coded.docs
        if end_id is not None:
            ids, counts = np.append(ids, end_id), np.append(counts, 1)
            codes = np.insert(codes, docs[1:], len(counts) - 1)
            docs = docs + np.arange(len(docs))
        whole = as_binary(ids.astype("<u4").view(np.uint8), np.append(0, np.cumsum(counts)) * 4).take(pa.array(codes))
        data, bounds = flat(whole)
        return data.view("<u4"), bounds[docs] // 4


def word_ids(path: str) -> WordIds:
    if path not in _LOADED:
        _LOADED[path] = WordIds(path)
    return _LOADED[path]
