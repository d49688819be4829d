"""Near-duplicate groups by a multi-index Hamming join of b-bit MinHash signatures, confirmed on full shingle sets.

A signature has SYMBOLS minimum hashes of 16 bits. Two sets of similarity 0.8 differ in a fifth of them on average; DISTANCE is
4.6 standard deviations above that, so a pair is missed with a chance of about one in 10^5 at 0.8 exactly and far less above.
The symbols are split into CHUNKS; by the pigeonhole principle two signatures within DISTANCE agree in some chunk but for at most
DISTANCE // CHUNKS = 1 symbol. Enumerating the place of that error gives a key for each place, from the chunk's other symbols, so every pair
within DISTANCE shares a key: none is lost.

Texts with equal sets are one node. No group is expanded into all its pairs: first each key of an error-free chunk ties its
nodes to the one that shares most chunks, and confirmed ties merge into components; then only pairs from different components that share any key are
compared, with a few members of a key's largest component first. A pair inside one component would not change the result, so the components are those of all links.

Before a pair becomes a row its odd sketches are compared: ODD_BITS bits of which each shingle flips one. Bits that differ are at most as many as
shingles that only one of the two sets has, and a link bounds those by the sizes, so no link is lost whatever the sizes; large sets fill their sketches, which then
drop little.

Keys that many nodes have are dealt out in blocks, and what hangs on one key is sent to its rows' tasks instead of the rows to one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coloc.llm.components import components
from coloc.llm.ragged import WHITE, Coded, flat, slices
from coloc.llm.tables import Scratch, joined_by_hot_key, narrow, ship, staged

SYMBOLS, DISTANCE, CHUNKS = 64, 27, 14
EDGES = [SYMBOLS * c // CHUNKS for c in range(CHUNKS + 1)]
#: Of each symbol whether it is its chunk's first.
FIRST = np.isin(np.arange(SYMBOLS), EDGES[:-1])
#: Rounds in which nodes outside a key's largest component are compared with a few of its members only.
ROUNDS = 2
#: Ids that are sent to all executors at once, at most; beyond, tables are joined by shuffling.
SMALL = 1_000_000
ODD_BITS = 2048
#: Members outside a key's largest component that one task compares with all its members.
SIDE = 4096
#: Parts of all pairs above which a document's set is sent to all executors: there are fewer such documents.
HOT_SETS = 100
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_rng = np.random.default_rng(20240229)
_A = (_rng.integers(0, 1 << 31, SYMBOLS, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
_B = _rng.integers(0, 1 << 32, SYMBOLS, dtype=np.uint32)
_SALT = _rng.integers(0, 1 << 63, (CHUNKS, 8), dtype=np.uint64) | np.uint64(1)


@dataclass(frozen=True)
class Likeness:
    """Shingles of `words` words; linked if 100 * intersection >= percent * union."""

    words: int = 5
    percent: int = 80


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def shingle_sets(texts: pa.Array, words: int) -> list[np.ndarray]:
    """For each text the sorted 64-bit hashes of its distinct shingles."""
    raw, offsets = flat(texts)
    raw = _LOWER[raw]
    cut = np.zeros(len(raw), bool)
    white = WHITE[raw]
    cut[1:] = white[1:] & ~white[:-1]
    coded = Coded(raw, offsets, cut)
    bare = [k.lstrip(b" \t\n\x0b\x0c\r") for k in coded.distinct]
    hashed = np.fromiter(map(xxhash.xxh3_64_intdigest, bare), np.uint64, len(bare))
    real = np.fromiter(map(bool, bare), bool, len(bare))
    there = real[coded.codes] if len(bare) else np.zeros(0, bool)
    seq = hashed[coded.codes][there] if len(bare) else np.zeros(0, np.uint64)
    at = np.append(0, np.cumsum(there))[coded.docs]
    with np.errstate(over="ignore"):
        rolled = seq[: max(0, len(seq) - words + 1)].copy()
        for k in range(1, words):
            rolled = _mix(rolled) + seq[k : k + len(rolled)]
        rolled = _mix(rolled)
        out = []
        for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
            if b - a >= words:
                out.append(np.unique(rolled[a : b - words + 1]))
            elif b > a:
                h = np.uint64(b - a)
                for w in seq[a:b]:
                    h = _mix(h) + w
                out.append(np.array([_mix(h)], np.uint64))
            else:
                out.append(seq[:0])
    return out


def signature(hashes: np.ndarray) -> np.ndarray:
    """SYMBOLS values of 16 bits."""
    best = np.full(SYMBOLS, 0xFFFFFFFF, np.uint32)
    x = (hashes >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(x), 2048):
        h = x[i : i + 2048][None, :] * _A[:, None]
        h += _B[:, None]
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(13)
        np.minimum(best, h.min(1), out=best)
    return ((best ^ (best >> np.uint32(16))) & np.uint32(0xFFFF)).astype("<u2")


def odd_sketch(hashes: np.ndarray) -> np.ndarray:
    """ODD_BITS bits as longs: of each place whether an odd number of the set's shingles fall there."""
    places = (hashes >> np.uint64(16)) % np.uint64(ODD_BITS)
    odd = np.bincount(places.astype(np.int64), minlength=ODD_BITS) & 1
    return np.packbits(odd.astype(np.uint8)).view("<i8")


def _may_link(like: Likeness) -> Column:
    """Of a pair with columns n, odd and n_, odd_: whether the sketches allow a link."""
    differ = sum((F.bit_count(F.col("odd")[i].bitwiseXOR(F.col("odd_")[i])) for i in range(1, ODD_BITS // 64)), F.bit_count(F.col("odd")[0].bitwiseXOR(F.col("odd_")[0])))
    return differ * (100 + like.percent) <= (F.col("n") + F.col("n_")) * (100 - like.percent)


def _signed(batches: Iterator[pa.RecordBatch], words: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, 1, 4_000_000):
        sets = shingle_sets(batch.column(1), words)
        prints = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets]
        marks = [signature(s).tobytes() if len(s) else None for s in sets]
        odd = np.concatenate([odd_sketch(s) for s in sets]) if sets else np.zeros(0, np.int64)
        bounds = pa.array(np.arange(len(sets) + 1, dtype=np.int32) * (ODD_BITS // 64))
        columns = [batch.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(prints, pa.binary()), pa.array(marks, pa.binary())]
        yield pa.RecordBatch.from_arrays([*columns, pa.ListArray.from_arrays(bounds, pa.array(odd))], ["doc_id", "n", "print", "mark", "odd"])


def _with_sets(batches: Iterator[pa.RecordBatch], words: int) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, 1, 4_000_000):
        sets = shingle_sets(batch.column(1), words)
        ends = np.append(0, np.cumsum([len(s) for s in sets])).astype(np.int32)
        values = np.concatenate(sets).view(np.int64) if sets else np.zeros(0, np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(values))], ["doc_id", "shingles"])


def chunk_keys(marks: np.ndarray, errors: bool) -> np.ndarray:
    """Keys (rows x keys) of signatures: of each chunk, or of each chunk without one of its symbols."""
    out = []
    with np.errstate(over="ignore"):
        for c in range(CHUNKS):
            part = marks[:, EDGES[c] : EDGES[c + 1]].astype(np.uint64)
            terms = _mix(part * np.uint64(0x9E3779B97F4A7C15) + _SALT[c, : part.shape[1]])
            whole = terms.sum(1, dtype=np.uint64)
            for j in range(part.shape[1] if errors else 1):
                out.append(_mix(whole - (terms[:, j] if errors else np.uint64(0)) + np.uint64(c * 16 + (j + 1 if errors else 0))))
    return np.stack(out, 1)


def _keyed(batches: Iterator[pa.RecordBatch], errors: bool) -> Iterator[pa.RecordBatch]:
    """node, comp, n, mark -> key, node, comp, n and, with errors, the symbol that the key leaves out and whether it is the chunk's
    first."""
    for batch in batches:
        for start in range(0, batch.num_rows, 5_000):
            part = batch.slice(start, 5_000)
            marks = np.frombuffer(b"".join(part.column(3).to_pylist()), "<u2").reshape(-1, SYMBOLS)
            keys = chunk_keys(marks, errors)
            times = np.repeat(np.arange(len(marks)), keys.shape[1])
            columns, names = [pa.array(keys.view(np.int64).ravel())] + [part.column(k).take(pa.array(times)) for k in range(3)], ["key", "node", "comp", "n"]
            if errors:
                columns += [pa.array(marks.astype(np.int32).ravel()), pa.array(np.tile(FIRST, len(marks)))]
                names += ["out", "head"]
            yield pa.RecordBatch.from_arrays(columns, names)


def _keys(nodes: DataFrame, errors: bool) -> DataFrame:
    schema = "key long, node long, comp long, n long" + (", out int, head boolean" if errors else "")
    return nodes.select("node", "comp", "n", "mark").mapInArrow(partial(_keyed, errors=errors), schema)


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """a, b, ma, mb -> a, b and the number of symbols that differ, of the pairs within DISTANCE."""
    for batch in batches:
        one, two = (np.frombuffer(b"".join(batch.column(k).to_pylist()), "<u2").reshape(-1, SYMBOLS) for k in (2, 3))
        apart = (one != two).sum(1)
        out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(apart.astype(np.int32))], ["a", "b", "apart"])
        yield out.filter(pa.array(apart <= DISTANCE))


def _some(rows: DataFrame, keys: DataFrame, name: str) -> DataFrame:
    """rows whose `name` is in keys (a staged table of distinct values): sent to all executors if it is SMALL, else shuffled."""
    return rows.join(F.broadcast(keys) if keys.count() <= SMALL else keys, name, "left_semi").select(*rows.columns)


def _alike_sizes(a: str, b: str, like: Likeness) -> Column:
    return F.least(a, b) * 100 >= F.greatest(a, b) * like.percent


class _Search:
    """One search for groups: its texts, nodes and staged folders."""

    def __init__(self, texts: DataFrame, like: Likeness, scratch: Scratch):
        self.texts, self.like, self.scratch = texts, like, scratch

    def staged(self, df: DataFrame, name: str) -> DataFrame:
        return staged(df, name, self.scratch)

    def confirmed(self, pairs: DataFrame) -> DataFrame:
        """Of the pairs (a, b) of ids those whose full shingle sets are alike enough."""
        with Scratch(pairs.sparkSession) as own:
            pairs = staged(pairs.select("a", "b").distinct(), "pairs", own)
            ids = staged(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), "pair-ids", own)
            sets = _some(self.texts.where("doc_id is not null"), ids, "doc_id").mapInArrow(partial(_with_sets, words=self.like.words), "doc_id long, shingles array<long>")
            sets = staged(sets, "sets", own)
            both = pairs
            for side in ("a", "b"):
                times = staged(pairs.groupBy(side).agg(F.count(F.lit(1)).alias("n")), "pair-counts", own)
                # ids that are repeated with other texts have several sets, of which any may confirm
                some = sets.groupBy(F.col("doc_id").alias(side)).agg(F.collect_set("shingles").alias(f"of_{side}"))
                both = joined_by_hot_key(both, some, side, "b" if side == "a" else "a", times, HOT_SETS)
            common = lambda x, y: F.size(F.array_intersect(x, y))
            enough = lambda x, y: common(x, y) * 100 >= (F.size(x) + F.size(y) - common(x, y)) * self.like.percent
            return self.staged(both.where(F.exists("of_a", lambda x: F.exists("of_b", lambda y: enough(x, y)))).select("a", "b"), "links")

    def measured(self, pairs: DataFrame, nodes: DataFrame) -> DataFrame:
        """a, b, apart of the pairs within DISTANCE and of sizes that allow a link."""
        marks = nodes.select("node", "n", "mark")
        one = pairs.join(marks.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("mark").alias("ma")), "a")
        two = one.join(marks.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("mark").alias("mb")), "b")
        return self.staged(two.where(_alike_sizes("na", "nb", self.like)).select("a", "b", "ma", "mb").mapInArrow(_compared, "a long, b long, apart int"), "measured")

    def merged(self, links: DataFrame, comp: DataFrame) -> DataFrame:
        """node, comp after the links joined their components: as in comp, of nodes that are not their own component only, so that a round
        carries what is linked and not all nodes."""
        with Scratch(comp.sparkSession) as own:
            joined = components(_labelled(links, comp).select(F.col("ca").alias("a"), F.col("cb").alias("b")), own)
            moved = joined.where("node <> root").select(F.col("node").alias("comp"), "root")
            older = comp.join(moved, "comp", "left").select("node", F.coalesce("root", "comp").alias("comp"))
            return self.staged(older.unionByName(moved.select(F.col("comp").alias("node"), F.col("root").alias("comp"))), "components")

    def sided(self, members: DataFrame, turn: int = 0) -> DataFrame:
        """members with main, their key's largest component, picks, a few nodes of it, and others, the number of rows outside it."""
        order = F.xxhash64("key", "node", F.lit(turn))  # other picks at each turn
        per = members.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("c"), F.min_by("node", order).alias("one"), F.max_by("node", order).alias("two"))
        of_key = per.groupBy("key").agg(F.sum("c").alias("n"), F.max(F.struct("c", "comp", "one", "two")).alias("m"))
        facts = of_key.select("key", "n", F.col("m.comp").alias("main"), F.array_distinct(F.array("m.one", "m.two")).alias("picks"), (F.col("n") - F.col("m.c")).alias("others"))
        return joined_by_hot_key(members, self.staged(facts, "key-sides"), "key", "node")

    def mixed(self, members: DataFrame, name: str) -> DataFrame:
        """members of the keys whose members are of several components."""
        several = members.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("key")
        return self.staged(_some(members, self.staged(several, "mixed-keys"), "key"), name)

    def same_ids(self, known: DataFrame, nodes: DataFrame) -> DataFrame:
        """a, b: nodes that hold different texts of one id."""
        repeated = known.groupBy("doc_id").agg(F.min("print").alias("low"), F.max("print").alias("high")).where("low < high").select("doc_id")
        own = _some(known, self.staged(repeated, "repeated-ids"), "doc_id").select("doc_id", "print").distinct().join(nodes.select("print", "node"), "print")
        return own.join(own.groupBy("doc_id").agg(F.min("node").alias("a")), "doc_id").select("a", F.col("node").alias("b"))

    def tied(self, nodes: DataFrame) -> DataFrame:
        """a, b: each key of an error-free chunk ties its nodes to the one that shares the most chunks with others, as an original does with its copies."""
        plain = _keys(nodes.withColumn("comp", F.col("node")), errors=False).select("key", "node")
        several = plain.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
        shared = self.staged(plain.join(several, "key"), "shared-chunks")
        score = shared.groupBy("node").agg(F.sum("c").alias("score"))
        lead = shared.join(score, "node").groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.max(F.struct("score", (-F.col("node")).alias("node"))).alias("m"))
        lead = self.staged(lead.select("key", "n", (-F.col("m.node")).alias("a")), "leads")
        return joined_by_hot_key(shared, lead, "key", "node").where("node <> a").select("a", F.col("node").alias("b")).distinct()

    def crossed(self, members: DataFrame, nodes: DataFrame) -> DataFrame:
        """a, b: pairs of nodes from different components that share a key and whose sketches allow a link."""
        sided = self.sided(self.staged(members.join(nodes.select("node", "odd"), "node"), "sketched-members")).withColumn("blocks", F.ceil(F.col("others") / SIDE).cast("int"))
        sided = self.staged(sided.drop("picks", "others"), "sided-members")
        minor = sided.where("comp <> main").withColumn("block", F.pmod(F.hash("node"), "blocks"))
        minor = minor.select("key", "block", *[F.col(c).alias(f"{c}_") for c in ("node", "comp", "n", "out", "odd")])
        every = sided.withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        once = (F.col("comp") == F.col("main")) | (F.col("node") < F.col("node_"))
        # two that agree in a whole chunk meet in all its keys; only its first is for them
        own_key = F.col("head") | (F.col("out") != F.col("out_"))
        pair = every.alias("x").join(minor.alias("y"), (F.col("x.key") == F.col("y.key")) & (F.col("x.block") == F.col("y.block")) & (F.col("comp") != F.col("comp_")) & once & own_key & _alike_sizes("n", "n_", self.like) & _may_link(self.like))
        return pair.select(F.least("node", "node_").alias("a"), F.greatest("node", "node_").alias("b")).distinct()


def _labelled(pairs: DataFrame, comp: DataFrame) -> DataFrame:
    """Pairs with their components ca and cb; a node without a row in comp is its own."""
    one = pairs.join(comp.select(F.col("node").alias("a"), F.col("comp").alias("ca")), "a", "left").withColumn("ca", F.coalesce("ca", "a"))
    return one.join(comp.select(F.col("node").alias("b"), F.col("comp").alias("cb")), "b", "left").withColumn("cb", F.coalesce("cb", "b"))


def _own_or(rows: DataFrame, comp: DataFrame) -> DataFrame:
    """rows (node) with comp, the node itself where comp has none."""
    return rows.join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))


def _closest(pairs: DataFrame, *by: str) -> DataFrame:
    """For each value of `by` the pair least far apart, ties to the smallest ids."""
    return pairs.groupBy(*by).agg(F.min(F.struct("apart", "a", "b")).alias("p")).select("p.a", "p.b")


def groups(docs: DataFrame, like: Likeness = Likeness(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row.

    Letters A to Z are lower-cased and words are runs of other bytes than space and the controls from tab to carriage return. A text with fewer words than a shingle
    has its whole sequence as one; without words, or null, it has none, is its own component and kept. Rows that share an id are one document: a link of one is a link of all.
    Rows without an id take no part: their component is null and they are kept. Texts of any length are taken whole. An empty table gives no rows; other columns are ignored.
    """
    ship(docs.sparkSession)
    texts = narrow(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    with Scratch(docs.sparkSession) as scratch:
        return staged(_grouped(_Search(texts, like, scratch)), "near-groups")


def _grouped(job: _Search) -> DataFrame:
    rows = job.staged(job.texts.mapInArrow(partial(_signed, words=job.like.words), "doc_id long, n long, print binary, mark binary, odd array<long>"), "signed")
    known = rows.where("doc_id is not null and n > 0")
    nodes = job.staged(known.groupBy("print").agg(F.count(F.lit(1)).alias("copies"), F.min("doc_id").alias("node"), *[F.first(c).alias(c) for c in ("n", "mark", "odd")]), "nodes")
    comp = job.staged(nodes.select("node", F.col("node").alias("comp")).where(F.lit(False)), "components")
    comp = job.merged(job.same_ids(known, nodes), comp)
    comp = job.merged(job.confirmed(_closest(job.measured(job.tied(nodes), nodes), "b")), comp)

    # pairs from different components that share any key
    members = job.mixed(_keys(_own_or(nodes, comp), errors=True), "mixed-members")
    for turn in range(ROUNDS):
        few = job.sided(members, turn).where("comp <> main").select(F.explode("picks").alias("a"), F.col("node").alias("b")).distinct()
        comp = job.merged(job.confirmed(_closest(job.measured(few, nodes), "b")), comp)
        moved = job.staged(_own_or(members.drop("comp"), comp).select(*members.columns), "moved-members")
        members = job.mixed(moved, "mixed-members")
    far = job.measured(job.crossed(members, nodes), nodes)
    if not far.isEmpty():
        # the closest pair of each two components first; what still lies between different ones after that is confirmed in full
        comp = job.merged(job.confirmed(_closest(_labelled(far, comp), "ca", "cb")), comp)
        rest = job.staged(_labelled(far, comp).where("ca <> cb").select("a", "b"), "rest")
        if not rest.isEmpty():
            comp = job.merged(job.confirmed(rest), comp)
    # a text that no other row shares and that nothing moved is its own component; only the others are looked up
    of_print = _own_or(nodes.select("print", "node", "copies"), comp).where("copies > 1 or comp <> node").groupBy("print").agg(F.max("copies").alias("n"), F.min("comp").alias("comp"))
    out = joined_by_hot_key(rows.select("doc_id", F.col("n").alias("n_shingles"), "print"), job.staged(of_print, "print-components"), "print", "doc_id")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def first_of_each(docs: DataFrame, like: Likeness = Likeness(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that keep their group's smallest id.

    All rows of that id stay, also repeated ones; rows without an id, and null, empty and wordless texts, stay. An empty table stays
    empty; texts of any length are compared whole, and clashing names of other columns make no difference.
    """
    spare = staged(groups(docs, like, id_col, text_col).where(~F.col("kept")).select(F.col("doc_id").alias("_spare")).distinct(), "spare")
    names = docs.columns
    own = docs.toDF(*[f"_in{i}" for i in range(len(names))])
    found = F.col(f"_in{names.index(id_col)}").cast("long") == F.col("_spare")
    kept = own.join(F.broadcast(spare) if spare.count() <= SMALL else spare, found, "left_anti")
    return kept.toDF(*names)


def groups_sql(words: int, percent: int, source: str = "documents") -> str:
    """DuckDB SQL for groups() on tables of distinct ids."""
    return f"""
    WITH RECURSIVE d AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS text FROM {source}),
    w AS (SELECT doc_id, list_filter(string_split_regex(text, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM d),
    g AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {words} THEN [array_to_string(w, ' ')]
                 ELSE list_distinct(list_transform(range(1, len(w) - {words} + 2), lambda i: array_to_string(w[i:i + {words} - 1], ' '))) END AS g FROM w),
    s AS (SELECT doc_id, unnest(g) AS g FROM g),
    c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS n FROM s x JOIN s y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY ALL),
    l AS (SELECT a, b FROM c JOIN g x ON x.doc_id = a JOIN g y ON y.doc_id = b WHERE 100 * n >= {percent} * (len(x.g) + len(y.g) - n)),
    e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
    r AS (SELECT doc_id AS a, doc_id AS b FROM g UNION SELECT r.a, e.b FROM r JOIN e ON e.a = r.b),
    m AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY a)
    SELECT g.doc_id, len(g.g)::BIGINT AS n_shingles, m.component_id, g.doc_id = m.component_id AS kept FROM g JOIN m USING (doc_id)
    """
