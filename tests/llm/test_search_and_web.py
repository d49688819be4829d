"""Near duplicates, top-k, archives and URL rules against brute force."""

from __future__ import annotations

import io
import random

import numpy as np
import pytest

from coloc.llm import components, exact_topk, near_dedup, url_filters, warc
from coloc.llm.tables import shared_dir

random.seed(7)


def _vary(words: list[str], k: int) -> str:
    out = list(words)
    for i in random.sample(range(len(out)), k):
        out[i] = f"z{random.randint(0, 10**6)}"
    return " ".join(out)


def _sets(text: str | None, n: int) -> set:
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    import re

    w = [x for x in re.split(r"[\x20\x09-\x0D]+", low) if x]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


def _brute(rows: list, n: int) -> dict:
    sets = {i: _sets(t, n) for i, t in rows}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                one, two = find(a), find(b)
                root[max(one, two)] = min(one, two)
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_duplicates_equal_brute_force(spark):
    rows: list[tuple] = []
    for g in range(12):
        base = [f"g{g}w{random.randint(0, 400)}" for _ in range(random.choice([3, 12, 60, 200]))]
        rows += [_vary(base, random.randint(0, max(1, len(base) // 8))) for _ in range(9)]
    chain = [f"c{i}" for i in range(100)]
    for k in range(12):  # each near the one before, the ends far apart
        rows.append(" ".join(chain))
        chain[8 * k % 100] = f"d{k}"
        chain[(8 * k + 1) % 100] = f"e{k}"
    rows += ["one", "ONE", "one two", "One  Two\n", "", None, "a b", "b a"]
    docs = [(i * 3 % 10_007, t) for i, t in enumerate(rows, 1)]
    got = near_dedup.groups(spark.createDataFrame(docs, "doc_id long, text string"), near_dedup.Likeness(2, 80)).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == _brute(docs, 2)
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_near_duplicates_of_odd_rows(spark):
    rows = [(None, "a b c"), (1, "a b c"), (1, "a b c"), (2, None), (None, None)]
    got = sorted(near_dedup.groups(spark.createDataFrame(rows, "doc_id long, text string"), near_dedup.Likeness(2, 80)).collect(), key=str)
    assert len(got) == 5 and {r["component_id"] for r in got if r["doc_id"] == 1} == {1}
    assert all(r["component_id"] is None and r["kept"] for r in got if r["doc_id"] is None)
    assert near_dedup.groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_keys_of_pairs_within_distance():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 1 << 16, near_dedup.SYMBOLS).astype("<u2")
    for _ in range(200):
        b = a.copy()
        b[rng.choice(near_dedup.SYMBOLS, near_dedup.DISTANCE, replace=False)] ^= 1
        one, two = near_dedup.chunk_keys(np.stack([a, b]), True)
        assert set(one.tolist()) & set(two.tolist())


def test_components_carry_linked_nodes_only(spark):
    comp = spark.createDataFrame([], "node long, comp long")
    with near_dedup.Scratch(spark) as scratch:
        job = near_dedup._Search(spark.createDataFrame([], "doc_id long, text string"), near_dedup.Likeness(2, 80), scratch)
        for links in ([(5, 3), (9, 8)], [(5, 8), (7, 6)], [(3, 2)], []):
            comp = job.merged(spark.createDataFrame(links, "a long, b long"), comp)
        assert {tuple(r) for r in comp.collect()} == {(3, 2), (5, 2), (7, 6), (8, 2), (9, 2)}
        nodes = spark.createDataFrame([(n,) for n in range(1, 10)], "node long")
        assert {tuple(r) for r in near_dedup._own_or(nodes, comp).collect()} == {(1, 1), (2, 2), (3, 2), (4, 4), (5, 2), (6, 6), (7, 6), (8, 2), (9, 2)}


def test_odd_sketches_lose_no_link(spark):
    """Bits that differ never outnumber shingles that differ, however large the sets."""
    rng = np.random.default_rng(4)
    like, rows = near_dedup.Likeness(2, 80), []
    for n in (1, 5, 60, 500, 1024, 1025, 3000, 9000):
        for _ in range(20):
            a = rng.integers(0, 1 << 63, n, dtype=np.uint64)
            b = np.append(a[n // 10 :], rng.integers(0, 1 << 63, n // 10, dtype=np.uint64))
            one, two = near_dedup.odd_sketch(a), near_dedup.odd_sketch(b)
            assert sum(int(x).bit_count() for x in (one ^ two).view(np.uint64)) <= 2 * (n // 10)
            rows.append((n, one.tolist(), n, two.tolist()))
    pairs = spark.createDataFrame(rows, "n long, odd array<long>, n_ long, odd_ array<long>")
    assert pairs.where(near_dedup._may_link(like)).count() == len(rows)
    far = [(600, near_dedup.odd_sketch(rng.integers(0, 1 << 63, 600, dtype=np.uint64)).tolist(), 600, near_dedup.odd_sketch(rng.integers(0, 1 << 63, 600, dtype=np.uint64)).tolist()) for _ in range(20)]
    assert spark.createDataFrame(far, pairs.schema).where(near_dedup._may_link(like)).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 99), (7, 200), (5, 5)]
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 99, 99: 99, 200: 0}


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(0, 0.3, (300, 6)).astype(np.float32)
    x[10] = x[20] = x[30]
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(400, None), (450, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (500, [float("nan")] * 6), (550, [0.0] * 6)]
    got: dict = {}
    for r in exact_topk.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    q = {i: np.floor(256 * np.asarray(r, np.float64)).astype(int) for i, r in enumerate(x)} | {550: np.zeros(6, int)}
    want = {}
    for i in (i for i in q if i % 50 == 0):
        best = sorted(((-int(q[i] @ q[j]), j) for j in q if j != i))[:5]
        want[i] = {k: (j, -s) for k, (s, j) in enumerate(best, 1)}
    assert got == want


def test_archives_round_trip(spark):
    rows = [(3, "http://a/\r\nx", "p" * 200), (1, None, "p" * 200), (2, "http://b", None), (4, "http://c", "short"), (5, "http://d", "short"), (None, "http://e", "é" * 80), (7, "u", "q" * 700_000), (8, "v", "q" * 700_000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: (r["payload_bytes"], r["record_type"], r["refers_to"]) for r in warc.archived(pages, f"{shared_dir(spark)}/test-archives").collect()}
    assert got == {3: (200, "revisit", 1), 1: (200, "response", None), 2: (0, "response", None), 4: (5, "response", None), 5: (5, "response", None), None: (160, "response", None), 7: (700_000, "response", None), 8: (700_000, "revisit", 7)}


def test_reader_notices_damage():
    good = warc.record(1, "http://a", b"payload" * 50, None) + warc.record(2, "http://b", b"x", 1)
    seen = list(warc.read(io.BytesIO(good), payloads=True))
    assert [r["payload"] for r in seen] == [b"payload" * 50, b""] and seen[1]["refers_to"] == 1
    with pytest.raises(ValueError):
        list(warc.read(io.BytesIO(good[:-9])))
    import zlib

    plain = zlib.decompress(warc.record(1, "http://a", b"payload" * 50, None), 31).replace(b"payloadp", b"PAYLOADp", 1)
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    with pytest.raises(ValueError, match="digest"):
        list(warc.read(io.BytesIO(packer.compress(plain) + packer.flush())))


def test_url_rules(spark):
    urls = [("http://X.Example.COM/en/7a?q", "x.example.com", "/en/7a", "example.com/en/7", "allow"), ("https://b.com/en/1#t", "b.com", "/en/1", "com/en/", "block"), ("http://acom/en/1", "acom", "/en/1", None, "allow"), ("nothing", "", "", None, "allow"), (None, "", "", None, "allow"), ("ftp://m.example.net/de/81", "m.example.net", "/de/81", "example.net/de/8", "block"), ("x://org", "org", "", None, "allow")]
    pages = spark.createDataFrame([(i, u[0]) for i, u in enumerate(urls)], "page_id long, url string")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filters.verdicts(pages, labels).collect()}
    assert got == {i: u[1:] for i, u in enumerate(urls)}


def test_url_rules_are_those_of_the_contract(spark):
    """Each rule alone, with its own verdict and that of the URLs that only the shorter rule fits."""
    assert set(url_filters.RULES) == {("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block")}
    urls = [("https://a.net/de/9", "net/de/", "allow"), ("https://example.net/de/79", "net/de/", "allow"), ("https://example.net/de/8", "example.net/de/8", "block"), ("https://example.com/en/6", "com/en/", "block"), ("https://example.com/en/70", "example.com/en/7", "allow"), ("https://a.org/es/", "org/es/", "block")]
    pages = spark.createDataFrame([(i, u[0]) for i, u in enumerate(urls)], "page_id long, url string")
    got = url_filters.verdicts(pages, spark.createDataFrame([], "doc_id long, quality int")).collect()
    assert {r["page_id"]: (r["rule"], r["verdict"]) for r in got} == {i: u[1:] for i, u in enumerate(urls)}


def test_url_rules_are_mined(spark):
    rows = [(i, f"http://{'spam' if i % 3 == 0 else 'fine'}.site.io/{'win' if i % 2 else 'read'}/{i}", 0 if i % 3 == 0 and i % 2 else 1) for i in range(300)]
    pages = spark.createDataFrame(rows, "page_id long, url string, quality int")
    labels = pages.selectExpr("page_id as doc_id", "quality")
    got = url_filters.verdicts(pages.unionByName(spark.createDataFrame([(900, "http://spam.site.io/win/x9", None)], pages.schema)), labels).collect()
    assert {r["page_id"]: r["verdict"] for r in got if r["page_id"] in (3, 1, 6, 900)} == {3: "block", 1: "allow", 6: "allow", 900: "block"}
