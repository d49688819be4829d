"""Quality rules as a bitmask ledger, in DataFrame functions only.

Every rule is evaluated once for each document; the ledger keeps the measurements and one bit for each rule that fails. A policy is a
named, versioned set of rules, so it is a mask: a document is kept if its bits and the mask have none in common. Ablations need no
second look at the texts: the ledger is summed into one row per distinct bit pattern, and what a rule decides alone, or what a
policy would keep without it, follows from those patterns.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coloc.llm.tables import narrow

#: Words are runs of other bytes than space and the controls from tab to carriage return.
BETWEEN_WORDS = r"[\x20\x09-\x0D]+"
SYMBOLS = r"[#*$%&|<>]"
MIN_WORDS = 50
PLACE_BITS = 20


@dataclass(frozen=True)
class Rule:
    name: str
    fails: str  # SQL over the measurements


#: Bit k is rule k; add at the end only, as stored ledgers keep their bits.
RULES = (
    Rule("few_words", f"n_words < {MIN_WORDS}"),
    Rule("repeated_words", "100 * n_repeat_words > 50 * n_words"),
    Rule("many_symbols", "100 * n_symbols > 20 * n_words"),
    Rule("duplicate_lines", "100 * n_dup_lines > 60 * n_lines"),
    Rule("word_length", "word_chars < 2 * n_words OR word_chars > 15 * n_words"),
    Rule("many_exclamations", "100 * n_exclamations > 50 * n_words"),
)


@dataclass(frozen=True)
class Policy:
    name: str
    version: int
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        names = [r.name for r in RULES]
        return sum(1 << names.index(r) for r in self.rules)


BASE = Policy("base", 1, ("few_words", "repeated_words"))
STANDARD = Policy("standard", 1, tuple(r.name for r in RULES))
LENIENT = Policy("lenient", 1, ("few_words", "repeated_words", "many_symbols"))


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and the measurements of every row."""
    rows = narrow(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    words = F.array_remove(F.split("text", BETWEEN_WORDS), "")
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    rows = rows.select("doc_id", "text", words.alias("words"), lines.alias("lines"))
    # each window's hash with its place in the low bits, so that equal windows are neighbours once these numbers are sorted
    keyed = F.transform(F.sequence(F.lit(0), F.size("words") - 3), lambda i: F.shiftleft(F.xxhash64(*_window("words", i)), PLACE_BITS).bitwiseOR(i.cast("long")))
    fits = F.size("words").between(3, 1 << PLACE_BITS)
    rows = rows.select("doc_id", "text", "words", "lines", F.when(fits, F.sort_array(keyed)).alias("keyed"))
    near = F.filter("keyed", lambda x, i: (_key(x) == _key(F.get("keyed", i - 1))) | (_key(x) == _key(F.get("keyed", i + 1))))
    rows = rows.select("doc_id", "text", "words", "lines", near.alias("near"))
    return rows.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        F.char_length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.regexp_count("text", F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        _repeat_words().cast("long").alias("n_repeat_words"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.char_length("text") - F.char_length(F.replace("text", F.lit("!"), F.lit("")))).cast("long").alias("n_exclamations"),
    )


def _window(words: str, i: Column) -> list[Column]:
    return [F.get(words, i + k) for k in range(3)]


def _key(x: Column) -> Column:
    return F.shiftright(x, PLACE_BITS)


def _place(x: Column) -> Column:
    return x.bitwiseAND(F.lit((1 << PLACE_BITS) - 1)).cast("int")


def _covered(places: Column) -> Column:
    """Words in the three-word windows that begin at these places, given in order."""
    start = F.struct(F.lit(-3).alias("last"), F.lit(0).alias("n"))
    return F.aggregate(places, start, lambda a, i: F.struct(i.alias("last"), (a["n"] + F.least(F.lit(3), i - a["last"])).alias("n")), lambda a: a["n"])


def _repeat_words() -> Column:
    """Words in windows found twice or more: `near` has the keyed windows that share their hash with another.

    If two different windows share one, or the text has too many words for the place bits, the windows themselves are compared.
    """
    same = lambda x, y: F.array(*_window("words", _place(x))) == F.array(*_window("words", _place(y)))
    clash = F.exists(F.transform("near", lambda x, i: (_key(x) == _key(F.get("near", i - 1))) & ~same(x, F.get("near", i - 1))), lambda x: x)
    by_hash = _covered(F.sort_array(F.transform("near", _place)))
    placed = F.sort_array(F.transform(F.sequence(F.lit(0), F.size("words") - 3), lambda i: F.struct(F.array(*_window("words", i)).alias("w"), i.alias("i"))))
    pairs = F.zip_with(F.slice(placed, 1, F.size("words") - 3), F.slice(placed, 2, F.size("words") - 3), lambda a, b: F.when(a["w"] == b["w"], F.array(a["i"], b["i"])).otherwise(F.array().cast("array<int>")))
    by_words = _covered(F.sort_array(F.array_distinct(F.flatten(pairs))))
    return F.when(F.size("words") < 4, 0).when(F.col("near").isNull(), by_words).when(F.size("near") == 0, 0).when(clash, by_words).otherwise(by_hash)


def ledger(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the measurements and fail_bits for every row: each rule evaluated once.

    A null text counts as empty: it has no words, so few_words fails. Null ids and repeated rows each keep their
    row, an empty table gives an empty ledger, other columns are ignored.
    """
    bits = sum((F.when(F.expr(r.fails), 1 << k).otherwise(0) for k, r in enumerate(RULES)), F.lit(0))
    return measured(docs, id_col, text_col).withColumn("fail_bits", bits.cast("long"))


def failed(policy: Policy) -> Column:
    return F.col("fail_bits").bitwiseAND(F.lit(policy.mask)) != 0


def applied(book: DataFrame, policies: tuple[Policy, ...] = (BASE, STANDARD, LENIENT)) -> DataFrame:
    """The ledger with a column kept_<name>_v<version> for each policy."""
    return book.withColumns({f"kept_{p.name}_v{p.version}": ~failed(p) for p in policies})


def ablations(book: DataFrame, policy: Policy = STANDARD) -> DataFrame:
    """For each rule of the policy: documents it fails, fails alone, and kept with all rules, without it and with it only.

    The documents are first counted by bit pattern, of which there are at most 2^rules; the rest works on those.
    """
    patterns = book.groupBy("fail_bits").agg(F.count(F.lit(1)).alias("n"))
    names = [r.name for r in RULES]
    bits = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(1 << names.index(r)).cast("long").alias("bit")) for r in policy.rules]))
    rows = patterns.select("fail_bits", "n", bits.alias("r")).select("fail_bits", "n", "r.*")
    in_policy = F.col("fail_bits").bitwiseAND(F.lit(policy.mask))
    count = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0))
    return rows.groupBy("rule").agg(
        count(F.col("fail_bits").bitwiseAND(F.col("bit")) != 0).alias("n_failed"),
        count(in_policy == F.col("bit")).alias("n_failed_alone"),
        count(in_policy == 0).alias("kept_with_all"),
        count(in_policy.bitwiseAND(F.bitwise_not("bit")) == 0).alias("kept_without"),
        count(F.col("fail_bits").bitwiseAND(F.col("bit")) == 0).alias("kept_with_it_only"),
    )


def verdicts(docs: DataFrame, policy: Policy = STANDARD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, fail_bits for every row."""
    book = ledger(docs, id_col, text_col)
    base = failed(BASE)
    return book.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), (~base & ~failed(policy)).alias("kept"), "fail_bits")


_MEASURES_SQL = """
    d AS (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS text FROM documents),
    w0 AS (SELECT k, unnest(string_split_regex(text, '[\\x20\\x09-\\x0D]+')) AS w, generate_subscripts(string_split_regex(text, '[\\x20\\x09-\\x0D]+'), 1) AS p FROM d),
    w AS (SELECT k, w, row_number() OVER (PARTITION BY k ORDER BY p) AS i FROM w0 WHERE w <> ''),
    g AS (SELECT k, i, w || ' ' || lead(w) OVER o || ' ' || lead(w, 2) OVER o AS g FROM w WINDOW o AS (PARTITION BY k ORDER BY i)),
    r AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY k, g) AS n FROM g WHERE g IS NOT NULL) WHERE n > 1),
    c AS (SELECT k, count(DISTINCT j) AS n FROM (SELECT k, unnest([i, i + 1, i + 2]) AS j FROM r) GROUP BY k),
    s AS (SELECT k, count(*) AS n_words, sum(length(w)) AS word_chars FROM w GROUP BY k),
    l AS (SELECT k, count(*) AS n_lines, count(*) - count(DISTINCT x) AS n_dup_lines FROM (SELECT k, unnest(string_split(text, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^\\x20\\x09-\\x0D]') GROUP BY k),
    m AS (SELECT d.doc_id, coalesce(s.n_words, 0)::BIGINT AS n_words, coalesce(s.word_chars, 0)::BIGINT AS word_chars,
                 len(regexp_extract_all(d.text, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(l.n_dup_lines, 0)::BIGINT AS n_dup_lines,
                 coalesce(c.n, 0)::BIGINT AS n_repeat_words, coalesce(l.n_lines, 0)::BIGINT AS n_lines, len(regexp_extract_all(d.text, '!'))::BIGINT AS n_exclamations
          FROM d LEFT JOIN s USING (k) LEFT JOIN l USING (k) LEFT JOIN c USING (k))
"""
_BITS_SQL = " + ".join(f"CASE WHEN {r.fails} THEN {1 << k} ELSE 0 END" for k, r in enumerate(RULES))
LEDGER_SQL = f"WITH {_MEASURES_SQL}, b AS (SELECT *, ({_BITS_SQL})::BIGINT AS fail_bits FROM m)"
VERDICTS_SQL = f"""{LEDGER_SQL} SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (fail_bits & {BASE.mask}) <> 0 AS base_failed,
    (fail_bits & {BASE.mask | STANDARD.mask}) = 0 AS kept, fail_bits FROM b"""
ABLATIONS_SQL = f"""{LEDGER_SQL}, q AS (SELECT unnest([{", ".join(f"{{'rule': '{r.name}', 'bit': {1 << k}}}" for k, r in enumerate(RULES))}], recursive := true))
    SELECT rule, count(*) FILTER (fail_bits & bit <> 0) AS n_failed, count(*) FILTER (fail_bits & {STANDARD.mask} = bit) AS n_failed_alone,
           count(*) FILTER (fail_bits & {STANDARD.mask} = 0) AS kept_with_all, count(*) FILTER (fail_bits & {STANDARD.mask} & ~bit = 0) AS kept_without,
           count(*) FILTER (fail_bits & bit = 0) AS kept_with_it_only FROM b, q GROUP BY rule"""
