"""Tokenizing operators against their libraries, and packing's invariants."""

from __future__ import annotations

import base64
import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as vocabularies
import pytest

from coloc.llm import byte_bpe, packing, token_counts

random.seed(5)
ODD = [
    None, "", " ", "a   b", "it's I'LL 's don't", "a" * 3000, "😀😀 é́ Ⅷ", "\x1c\x1d x\x85 y", "<|endoftext|>a <|x", "ß ÿ Ÿ İ ª º ×", "１２ ³ ½ Σας", "a b c　d",
    "\n\n a \n b", "▁▁x ▁", "<s>a</s> <unk> <0x0A>", " " * 37 + "x" + " " * 64, "\t\r\n;\r\n", "".join(random.choice("abctheion") for _ in range(4000)), "same text", "same text",
]
ODD += ["".join(random.choice("   　\x85\n\tabcé'9.ÀßSs<|>!*#") for _ in range(50)) for _ in range(300)]
ODD += ["".join(random.choice("theinrsaoußäé") for _ in range(random.randint(1, 40))) for _ in range(300)]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(None if i == 3 else i, t, "x", i) for i, t in enumerate(ODD)]
    return spark.createDataFrame(rows, "doc_id long, text string, n_tokens string, TEXT_ long").withColumnRenamed("TEXT_", "Doc_Id2")


def test_byte_bpe_equals_tiktoken(docs):
    import tiktoken

    path = vocabularies.path("byte_bpe_multi_50k.tiktoken")
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    lib = tiktoken.Encoding("own", pat_str=vocabularies.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rows = byte_bpe.digests(docs, path, vocabularies.PATTERN).collect()
    assert len(rows) == len(ODD)
    want = []
    for t in ODD:
        ids = lib.encode_ordinary(t or "")
        want.append((len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert [(r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in rows] == want


def test_byte_bpe_round_trip_and_join(docs):
    path = vocabularies.path("byte_bpe_multi_50k.tiktoken")
    back = byte_bpe.decode(byte_bpe.encode(docs, path, vocabularies.PATTERN), path, vocabularies.PATTERN).collect()
    assert [bytes(r["decoded"]).decode() for r in back] == [t or "" for t in ODD]


def test_token_counts_equal_sentencepiece(docs):
    import sentencepiece

    path = vocabularies.path("piece_bpe_32k.model")
    lib = sentencepiece.SentencePieceProcessor(model_file=path)
    rows = token_counts.token_counts(docs, path, limit=100).collect()
    want = [len(lib.encode(t or "")) for t in ODD]
    assert [r["n_tokens"] for r in rows] == want
    assert [r["over_limit"] for r in rows] == [n > 100 for n in want]
    assert [r["n_bytes"] for r in rows] == [len((t or "").encode()) for t in ODD]


def test_packed_pieces(docs):
    from tokenizers import Tokenizer

    path = vocabularies.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    rows = packing.packed(docs.where("doc_id is not null"), path, capacity=256).collect()
    ids = {i: lib.encode(t or "", add_special_tokens=False).ids + [2] for i, t in enumerate(ODD) if i != 3}
    by_doc: dict[int, list] = {}
    by_seq: dict[int, list] = {}
    for r in rows:
        assert r["doc_tokens"] == len(ids[r["doc_id"]])
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"] and len(part) == r["length"] > 0
        by_doc.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        by_seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for d, parts in by_doc.items():
        at = 0
        for start, n in sorted(parts):
            assert start == at
            at += n
        assert at == len(ids[d])
    assert len(by_doc) == len(ids)
    for parts in by_seq.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at <= 256 and (at & (at - 1)) == 0


def test_best_fill_is_best():
    for _ in range(200):
        sizes = sorted((random.randint(1, 60) for _ in range(8)), reverse=True)
        counts: dict[int, int] = {}
        for n in sizes:
            counts[n] = counts.get(n, 0) + 1
        lengths = sorted(counts, reverse=True)
        got = packing.best_fill(counts, lengths, 64)
        assert all(v <= counts[n] for n, v in got.items()) and got[lengths[0]] >= 1
        rest = list(sizes)
        rest.remove(lengths[0])
        sums = {0}
        for n in rest:
            sums |= {s + n for s in sums if s + n <= 64 - lengths[0]}
        assert sum(n * v for n, v in got.items()) == lengths[0] + max(sums)


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert packing.packed(none, vocabularies.path("word_bpe_49k.json")).count() == 0
    assert token_counts.token_counts(none, vocabularies.path("piece_bpe_32k.model")).count() == 0
    assert byte_bpe.digests(none, vocabularies.path("byte_bpe_multi_50k.tiktoken"), vocabularies.PATTERN).count() == 0
