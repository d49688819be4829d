"""Every operator and stage on empty tables, nulls, repeated rows, very long texts and clashing columns."""

from __future__ import annotations

import random
import zlib

import numpy as np
import pyarrow as pa
import public_tokenizers as vocabularies
import pytest

import corpus_pipeline
from coloc.llm import byte_bpe, exact_topk, language_id, near_dedup, packing, quality_model, quality_rules, token_counts, url_filters, warc
from coloc.llm.ragged import flat
from coloc.llm.tables import shared_dir

random.seed(11)
PLAIN = ["the cat and the dog sat on the mat", "der Hund und die Katze sind im Haus", "le chat et le chien sont dans la maison"]
LONG = " ".join(f"word{i % 997} and {i}" for i in range(150_000))
TEXTS = [*PLAIN, None, "", "   ", "123", PLAIN[0], LONG]
ROWS = [(None if i == 2 else (1 if i == 7 else i), t, ("en", "de", "fr")[i % 3], f"s{i}", -i, "x", i) for i, t in enumerate(TEXTS)]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _spare string, _in0 long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).withColumnRenamed("n_chars", "N_Words").select("*", "source").toDF("doc_id", "text", "lang", "source", "n_words", "_spare", "_in0", "print")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, 0) for i in range(9)] + [(None, 1, 0), (3, None, 0), (1, 0, 0)], "doc_id long, quality int, toxic int")


OPS = {
    "packing": lambda d, labels: packing.packed(d, vocabularies.path("word_bpe_49k.json")),
    "rules": lambda d, labels: quality_rules.verdicts(d),
    "near": lambda d, labels: near_dedup.groups(d, near_dedup.Likeness(2, 80)),
    "bpe": lambda d, labels: byte_bpe.digests(d, vocabularies.path("byte_bpe_multi_50k.tiktoken"), vocabularies.PATTERN),
    "counts": lambda d, labels: token_counts.token_counts(d, vocabularies.path("piece_bpe_32k.model")),
    "quality": lambda d, labels: quality_model.scores(d, quality_model.train(d, labels)),
    "language": lambda d, labels: language_id.languages(d),
}


@pytest.mark.parametrize("name", OPS)
def test_text_operators(docs, labels, name):
    rows = OPS[name](docs, labels).collect()
    ids = sorted((r["doc_id"] for r in rows if name != "packing" or r["start"] == 0), key=str)
    assert ids == sorted((r[0] for r in ROWS), key=str)
    assert OPS[name](docs.limit(0), labels.limit(0)).count() == 0


def test_near_groups_of_odd_rows(docs):
    got = {(r["doc_id"], r["n_shingles"] > 0): (r["component_id"], r["kept"]) for r in near_dedup.groups(docs, near_dedup.Likeness(2, 80)).collect()}
    assert got[0, True] == (0, True) and got[1, True] == (0, False)  # id 1 has a copy of 0 in one of its rows, so both its rows go
    assert got[3, False] == (3, True) and got[4, False] == (4, True) and got[None, True] == (None, True)


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages(spark, docs, labels, name, tmp_path):
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    stage = dict(corpus_pipeline.STAGES)[name]
    for rows in (docs, docs.limit(0)):
        out = stage(spark, rows, str(tmp_path))
        got = out.collect()
        if name != "packing":
            assert out.columns == docs.columns and {r["_in0"] for r in got} <= {r[6] for r in ROWS}
    if name == "language_id":
        assert {r["text"] for r in stage(spark, docs, str(tmp_path)).collect()} <= {t for t in TEXTS if t and any(c.isalpha() for c in t)}
    if name == "near_dedup":
        assert sorted(r["_in0"] for r in stage(spark, docs, str(tmp_path)).collect()) == [0, 2, 3, 4, 5, 6, 8]  # both rows of id 1, of which one is a copy of 0, go


def test_pages(spark, labels):
    rows = [(None, None, None, 1), (1, "http://a.com/x", "p" * 200, 2), (1, "http://a.com/x", "p" * 200, 3), (2, "http://b.com/" + "y" * 200_000, "q" * 3_000_000, 4), (3, "", "", 5)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, host long").select("*", "host").toDF("page_id", "url", "html", "digest", "tokens")
    got = warc.archived(pages, f"{shared_dir(spark)}/edge-archives").collect()
    assert sorted((r["page_id"] is None, r["page_id"], r["record_type"]) for r in got if r["page_id"] is not None) == [(False, 1, "response"), (False, 1, "response"), (False, 2, "response"), (False, 3, "response")]
    judged = url_filters.verdicts(pages, labels).collect()
    assert len(judged) == 5 and {r["verdict"] for r in judged} == {"allow"}
    assert warc.archived(pages.limit(0)).count() == 0 and url_filters.verdicts(pages.limit(0), labels.limit(0)).count() == 0


def test_vectors(spark):
    big = [float(1 << 40)] * 3
    rows = [(0, big, 1), (50, big, 2), (1, [1.0, 2.0, 3.0], 3), (None, [1.0, 1.0, 1.0], 4), (2, [1e300, 0.0, 0.0], 5), (100, [1.0, 2.0], 6), (101, [0.5, 0.5], 7), (101, [0.5, 0.5], 8)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank int").select("*", "rank").toDF("vec_id", "embedding", "rank", "score")
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in exact_topk.nearest(table).collect()}
    top = (1 << 63) - 1
    assert got[0, 1] == (2, top) and got[0, 2] == (50, top) and got[0, 3] == (1, 6 * 256 * (1 << 48))
    assert got[100, 1] == (101, 256 * 128 + 512 * 128) and got[100, 2] == got[100, 1]
    assert exact_topk.nearest(table.limit(0)).count() == 0


def test_top_k_in_many_shards(spark, monkeypatch):
    monkeypatch.setattr(exact_topk, "SHARD", 40)
    rng = np.random.default_rng(2)
    x = rng.normal(0, 0.3, (400, 5))
    got: dict = {}
    for r in exact_topk.nearest(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    q = np.floor(256 * x).astype(int)
    for i in range(0, 400, 50):
        best = sorted((-int(q[i] @ q[j]), j) for j in range(400) if j != i)[:5]
        assert got[i] == {k: (j, -s) for k, (s, j) in enumerate(best, 1)}


def _by_hand(net: quality_model.Network, text: str | None) -> float:
    raw = (text or "").encode()
    n = max(1, -(-len(raw) // 8))
    raw = raw + bytes((n + 1) * 8 - len(raw))
    acts = []
    for a in range(0, n, 64):
        values = [[sum(float(net.bytes_[j, raw[8 * c + j], f]) for j in range(16)) + float(net.bias[f]) for f in range(quality_model.FILTERS)] for c in range(a, min(n, a + 64))]
        acts.append(np.tanh(np.max(values, axis=0)))
    feature = np.concatenate([np.mean(acts, axis=0), np.max(acts, axis=0)])
    return 1 / (1 + np.exp(-(feature @ net.out + net.base)))


def test_quality_scores_are_of_each_text_alone(spark, monkeypatch):
    texts = [None, "", "a", "z" * 16, *(" ".join(random.choice(["one", "two", "é!", "&&&"]) for _ in range(random.randint(1, 400))) for _ in range(60))]
    net = quality_model.fit([(i % 2, t or "") for i, t in enumerate(texts)])
    one = {t: quality_model.probability(net, *flat(pa.array([t], pa.string())))[0] for t in texts}
    assert [one[t] for t in texts] == quality_model.probability(net, *flat(pa.array(texts, pa.string()))).tolist()
    assert all(one[t] == pytest.approx(_by_hand(net, t), abs=1e-5) for t in texts)
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for moved in (rows, rows.orderBy(-rows["doc_id"]), rows.repartition(5)):
        assert {r["doc_id"]: r["score"] for r in quality_model.scores(moved, net).collect()} == {i: one[t] for i, t in enumerate(texts)}
    monkeypatch.setattr(quality_model, "SLAB", 512)
    assert all(quality_model.probability(net, *flat(pa.array([t, "x"], pa.string())))[0] == pytest.approx(one[t], abs=1e-6) for t in texts)


def test_every_language_is_learned_whatever_is_repeated(spark):
    letters = ["abcdef", "ghijkl", "mnopqr", "stuvwx", "yzabgh", "cdijmn", "opstyz", "uvefkl"]
    say = lambda k: " ".join("".join(random.choice(letters[k]) for _ in range(5)) for _ in range(30))
    rows = [(i, say(0) if i % 2 else "same text " * 5, "l0") for i in range(600)]
    rows += [(1000 * k + i, t, f"l{k}") for k in range(1, 8) for t in [say(k)] for i in range(600)]
    model = language_id.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert model.languages == [f"l{k}" for k in range(8)]
    again = language_id.train(spark.createDataFrame(rows[::-1], "doc_id long, text string, lang string").repartition(7))
    assert again.grams.tolist() == model.grams.tolist() and np.array_equal(again.weights, model.weights)


def test_long_urls_do_not_stop_mining(spark):
    keys = "&".join(f"k{i}=1" for i in range(200))
    rows = [(i, f"http://bad.io/win?{keys}&z{i % 3}=1", 0) for i in range(40)] + [(100 + i, f"http://fine.io/read?f{i % 200}=1", 1) for i in range(400)]
    rows += [(600 + i, "http://odd.io/x?" + "&".join(f"m{j}=1" for j in range(60) if j != i), i % 2) for i in range(60)]
    pages = spark.createDataFrame(rows, "page_id long, url string, quality int")
    got = url_filters.verdicts(pages, pages.selectExpr("page_id as doc_id", "quality")).collect()
    assert {r["verdict"] for r in got if r["page_id"] < 100} == {"block"} and {r["verdict"] for r in got if 100 <= r["page_id"] < 600} == {"allow"}


def test_mined_rules_catch_what_brute_force_catches(spark):
    from itertools import combinations

    baskets = [(sorted(random.sample("abcdefgh", random.randint(1, 5))),) for _ in range(400)]
    baskets = [(t, ("a" in t and "b" in t) or ("c" in t and "d" in t and "e" in t) or random.random() < 0.2) for (t,) in baskets]
    rows = spark.createDataFrame(baskets, "tokens array<string>, bad boolean")
    known, rules = url_filters.mine(rows, 0.0, 8, 0.7)
    caught = {tuple(r["tokens"]) for r in url_filters.caught(rows, known, rules).collect()}
    stats: dict = {}
    for t, bad in baskets:
        for n in range(1, len(t) + 1):
            for c in combinations(t, n):
                a, b = stats.get(c, (0, 0))
                stats[c] = (a + 1, b + bad)
    good = {c for c, (n, bad) in stats.items() if bad >= 8 and bad >= 0.7 * n}
    assert caught == {tuple(t) for t, _ in baskets if any(set(c) <= set(t) for c in good)}
    assert caught


def test_rules_of_long_baskets_are_those_of_short_ones(spark):
    """The bound on FP-growth's baskets changes no verdict: neither rules beyond it are lost nor rules found that do not hold."""
    rng = random.Random(5)
    baskets = [(sorted(rng.sample("abcdefghij", rng.randint(2, 8))),) for _ in range(500)]
    baskets = [(t, ("i" in t and "j" in t) or ("c" in t and "d" in t and "h" in t) or rng.random() < 0.3) for (t,) in baskets]
    rows = spark.createDataFrame(baskets, "tokens array<string>, bad boolean")
    got = []
    for most in (2, 4, 10):
        known, rules, search = url_filters.mined(rows, 0.0, 8, 0.7, most)
        assert (search is None) == (most == 10)
        got.append({tuple(r["tokens"]) for r in url_filters.caught(rows, known, rules, search).collect()})
    assert got[0] == got[1] == got[2] and 0 < len(got[2]) < len({tuple(t) for t, _ in baskets})


def test_decoding_tree(spark):
    own = byte_bpe.codec(vocabularies.path("byte_bpe_multi_50k.tiktoken"), vocabularies.PATTERN)
    lists = [own.encode(t) for t in ("", "a", "hello world", "x" * 99, "é😀 " * 7)]

    def tree(ids: list[int]) -> bytes:
        return b"" if not ids else own.bytes_of[ids[0]] if len(ids) == 1 else tree(ids[: len(ids) // 2]) + tree(ids[len(ids) // 2 :])

    text, at = own.decoded(np.array([i for x in lists for i in x]), np.append(0, np.cumsum([len(x) for x in lists])))
    assert [bytes(text[a:b]) for a, b in zip(at[:-1], at[1:])] == [tree(x) for x in lists]
    with pytest.raises(ValueError):
        own.decode([len(own.size) + 5])


def test_pipeline_keeps_what_brute_force_keeps(spark, tmp_path):
    """All stages over a small corpus, against each decision made text by text."""
    sf = str(tmp_path)
    source = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    spark.read.parquet("/root/testdata/sf0.001/labels.parquet").write.parquet(f"{sf}/labels.parquet")
    source.write.parquet(f"{sf}/documents.parquet")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = language_id.train(docs)
    grams = language_id.Grams(model.alphabet, model.grams)
    rows = [r for r in docs.collect()]

    def spoken(text):
        name, score = language_id.predict(model, grams, *flat(pa.array([text], pa.string())))
        return name[0] != language_id.UNKNOWN and score[0] >= 0.3

    left = [r for r in rows if spoken(r["text"])]
    net = quality_model.train(spark.createDataFrame(left, docs.schema), labels)
    left = [r for r in left if quality_model.probability(net, *flat(pa.array([r["text"]], pa.string())))[0] >= quality_model.THRESHOLD]
    from tests.llm.test_search_and_web import _brute

    groups = _brute([(r["doc_id"], r["text"]) for r in left], 5)
    left = [r for r in left if groups[r["doc_id"]][1] == r["doc_id"]]
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(vocabularies.path("word_bpe_49k.json"))
    want = {r["doc_id"]: [*lib.encode(r["text"] or "", add_special_tokens=False).ids, 2] for r in left}
    got: dict = {}
    for p in corpus_pipeline.run(spark, sf).collect():
        got.setdefault(p["doc_id"], []).append((p["start"], p["length"], p["ids_crc32"]))
    assert got.keys() == want.keys()
    for i, parts in got.items():
        assert sorted(parts)[-1][0] + sorted(parts)[-1][1] == len(want[i])
        assert all(zlib.crc32(np.array(want[i][a : a + n], "<u4").tobytes()) == c for a, n, c in parts)


def test_padding(spark):
    """Full windows of 4096, and powers of two at the end: nothing is padded."""
    docs = spark.createDataFrame([(i, " ".join(random.choice(["alpha", "beta", "gamma"]) for _ in range(random.randint(1, 6000)))) for i in range(60)], "doc_id long, text string").coalesce(1)
    per = packing.packed(docs, vocabularies.path("word_bpe_49k.json")).groupBy("sequence_id").sum("length").collect()
    sizes = [r[1] for r in per]
    assert all(n == 4096 or (n < 4096 and n & (n - 1) == 0) for n in sizes) and sum(n < 4096 for n in sizes) <= 13
