"""Rules against brute force, models by held-out accuracy."""

from __future__ import annotations

import random
import re

import pytest

from coloc.llm import language_id, quality_model, quality_rules
from tests.conftest import DATA

random.seed(6)
TEXTS = [None, "", "a b c", "a b a b a b a b", "x\n\nx\n x\n", "one two three one two three four", "# $ % & | < > *", "\x0b\x0c a\x1cb é́", "a a a a a a"]
TEXTS += [" ".join(random.choice("abcd") for _ in range(random.randint(1, 40))) for _ in range(60)]
TEXTS += ["\n".join(random.choice(["p q", "r", " ", ""]) for _ in range(12)) for _ in range(20)]


def _brute(text: str | None) -> tuple:
    t = text or ""
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", t) if w]
    wins = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = {i + k for i, w in enumerate(wins) if wins.count(w) > 1 for k in range(3)}
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit)


@pytest.mark.parametrize("bits", [20, 2])
def test_measures_equal_brute_force(spark, monkeypatch, bits):
    """With two place bits most texts are too long for them, so the windows themselves are compared."""
    monkeypatch.setattr(quality_rules, "PLACE_BITS", bits)
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    rows = quality_rules.verdicts(docs).orderBy("doc_id").collect()
    got = [(r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in rows]
    assert got == [_brute(t) for t in TEXTS]
    for r in rows:
        assert r["base_failed"] == (r["n_words"] < 50 or 100 * r["n_repeat_words"] > 50 * r["n_words"])
        assert not (r["kept"] and r["base_failed"])


def test_ablations_follow_from_the_ledger(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    book = quality_rules.ledger(docs).cache()
    bits = [r["fail_bits"] for r in book.select("fail_bits").collect()]
    mask = quality_rules.STANDARD.mask
    for r in quality_rules.ablations(book).collect():
        bit = 1 << [x.name for x in quality_rules.RULES].index(r["rule"])
        assert r["n_failed"] == sum(b & bit != 0 for b in bits)
        assert r["kept_without"] == sum(b & mask & ~bit == 0 for b in bits)
    kept = quality_rules.applied(book).agg({"kept_lenient_v1": "count"}).first()[0]
    assert kept == len(bits)


def test_language_held_out(spark):
    docs = spark.read.parquet(f"{DATA[:-5]}0.01/documents.parquet")
    rows = language_id.languages(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang_pred"] == r["lang"] for r in rows) >= 0.95 * len(rows)


def test_language_of_odd_texts(spark):
    rows = [(1, "the cat and the dog", "en"), (2, "der Hund und die Katze", "de"), (3, None, "en"), (4, "", "en"), (5, "123 !!", None), (None, "the end of the day", "en"), (1, "the cat and the dog", "en"), (8, "und der Mann", "de"), (9, "on the of and to", "en")]
    got = language_id.languages(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert len(got) == len(rows)
    assert {r["doc_id"]: r["lang_pred"] for r in got if r["doc_id"] in (3, 4, 5)} == {3: "und", 4: "und", 5: "und"}
    assert all(0 <= r["score"] <= 1 for r in got)
    none = language_id.languages(spark.createDataFrame([(1, "abc", None)], "doc_id long, text string, lang string")).collect()
    assert none[0]["lang_pred"] == "und"


def test_quality_held_out(spark):
    sf = f"{DATA[:-5]}0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    net = quality_model.train(docs, labels)
    rows = quality_model.scores(docs, net).join(labels, "doc_id").where("held_out").collect()
    good, bad = [r["score"] for r in rows if r["quality"] == 1], [r["score"] for r in rows if r["quality"] == 0]
    assert sum(g > b for g in good for b in bad) >= 0.98 * len(good) * len(bad)
    assert sum(s >= quality_model.THRESHOLD for s in good) >= 0.97 * len(good)


def test_quality_of_odd_texts(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (None, "a"), (4, "x" * 50_000), (4, "x" * 50_000)], "doc_id long, text string")
    labels = spark.createDataFrame([(4, 1, 0), (9, None, 0)], "doc_id long, quality int, toxic int")
    rows = quality_model.scores(docs, quality_model.train(docs, labels)).collect()
    assert len(rows) == 5 and all(0 <= r["score"] <= 1 for r in rows)
