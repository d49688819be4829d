"""URL filtering: given host and path rules first, then association rules that FP-growth mines from labelled URLs.

A labelled URL is a basket of tokens (host labels, path words, query keys) plus an item for a bad label. Frequent itemsets that hold
that item give rules; confidence and support prune them. Each rule is filed under one of its items; a URL's items look rules up
there, and a rule matches if the URL has all its items. Only distinct token sets are matched, so a frequent host costs one row.

Itemsets are bounded before they are mined. A rule blocks whatever a longer rule around it would, so a token that is a rule by itself
leaves the baskets. Tokens that are in the same labelled URLs are in the same itemsets, so they are one item. Tokens that are too rare
among bad URLs are in no rule. No verdict changes by these three. FP-growth then takes a basket's MAX_ITEMS items that are in most bad
URLs, so a basket has at most 2^MAX_ITEMS itemsets however long its URL is. If that cut any basket, the rules found are counted again on
the whole baskets, and a token set that none of them matches is searched for a rule of its own (class Search), so the cut changes no verdict.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coloc.llm.tables import joined_by_hot_key, narrow, staged

#: The given rules: (host, path, verdict).
RULES = (
    ("com", "/en/", "block"),
    ("example.com", "/en/7", "allow"),
    ("net", "/de/", "allow"),
    ("example.net", "/de/8", "block"),
    ("org", "/es/", "block"),
)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BAD = "label=bad"
#: A rule needs this share of the labelled URLs and at least this many, and this confidence.
MIN_SHARE, MIN_COUNT, MIN_CONFIDENCE = 0.002, 20, 0.6
#: Items of a basket that FP-growth takes together, at most; longer baskets are searched exactly.
MAX_ITEMS = 10


def host(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_after(url), r"^[^/?#]*", 0), UPPER, LOWER), F.lit(""))


def path(url: Column) -> Column:
    rest = _after(url)
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def _after(url: Column) -> Column:
    at = F.instr(url, F.lit("://"))
    return F.when(at > 0, F.substring(url, at + F.lit(3), F.length(url)))


def rule_name(of_host: str, of_path: str) -> str:
    return of_host + of_path


def matched(host_col: Column, path_col: Column, rules: tuple) -> tuple[Column, Column]:
    """(name, verdict) of the longest rule that fits; ties go to the name first in order."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    ordered = sorted(rules, key=lambda r: (-len(rule_name(r[0], r[1])), rule_name(r[0], r[1])))
    for h, p, v in reversed(ordered):
        fits = ((host_col == h) | host_col.endswith("." + h)) & path_col.startswith(p)
        name, verdict = F.when(fits, F.lit(rule_name(h, p))).otherwise(name), F.when(fits, F.lit(v)).otherwise(verdict)
    return name, verdict


def tokens(url: Column, host_col: Column, path_col: Column) -> Column:
    """Sorted distinct tokens: host labels, path words that are not numbers, query keys."""
    labels = F.transform(F.filter(F.split(host_col, r"\."), lambda x: x != ""), lambda x: F.concat(F.lit("host="), x))
    words = F.transform(F.filter(F.split(path_col, r"[/._-]"), lambda x: x.rlike("[^0-9]")), lambda x: F.concat(F.lit("path="), x))
    query = F.regexp_extract(F.coalesce(url, F.lit("")), r"^[^?#]*\?([^#]*)", 1)
    keys = F.transform(F.filter(F.split(query, "[&;]"), lambda x: x != ""), lambda x: F.concat(F.lit("query="), F.split(x, "=", 2)[0]))
    return F.array_sort(F.array_distinct(F.concat(labels, words, keys)))


def items(baskets: DataFrame, least: int, min_confidence: float) -> DataFrame:
    """token, item, alone, n_bad of the tokens that at least `least` bad URLs have: `alone` if the token is a rule by itself, and
    `item` the smallest of the tokens that are in the same URLs. baskets: tokens, bad and a row_id of its own for each URL."""
    at = baskets.select("row_id", "bad", F.explode("tokens").alias("token"))
    # tokens of as many rows, whose hashes have the same two checksums, are in the same rows
    marks = [F.bit_xor(F.xxhash64("row_id", F.lit(salt))).alias(f"mark{salt}") for salt in (1, 2)]
    known = at.groupBy("token").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("bad").cast("long")).alias("n_bad"), *marks).where(F.col("n_bad") >= least)
    known = staged(known, "url-tokens")
    first = known.groupBy("n", "n_bad", "mark1", "mark2").agg(F.min("token").alias("item"))
    alone = F.col("n_bad") >= F.col("n") * min_confidence
    return staged(known.join(first, ["n", "n_bad", "mark1", "mark2"]).select("token", "item", alone.alias("alone"), "n_bad"), "url-items")


class Search:
    """Whether an item set has a subset that is a rule: at least `least` bad URLs have it and at least min_confidence of those that have it are bad.

    sets: rows (items, n, n_bad), the whole labelled baskets. The search adds items to a set or rules them out. An item that all its bad URLs have is
    added at once, as it can only lower the number of good ones; one that all its good URLs have is ruled out, as it can only lower the number
    of bad ones; and a set is given up when the good URLs that have all that may still be added are too many already.
    """

    def __init__(self, sets: list, least: int, min_confidence: float):
        self.least, self.confidence = least, min_confidence
        names = sorted({i for r in sets for i in r["items"]})
        self.at = {name: k for k, name in enumerate(names)}
        self.has = np.zeros((len(sets), len(names)), bool)
        for k, r in enumerate(sets):
            self.has[k, [self.at[i] for i in r["items"]]] = True
        self.bad = np.array([r["n_bad"] for r in sets], np.int64)
        self.good = np.array([r["n"] for r in sets], np.int64) - self.bad

    def _is_rule(self, bad: int, good: int) -> bool:
        return bad >= self.least and bad / (bad + good) >= self.confidence

    def finds(self, items: list[str]) -> bool:
        at = [self.at[i] for i in items if i in self.at]
        has, some = self.has[:, at], self.has[:, at].any(1)
        return self._grow(has[some], self.bad[some], self.good[some], False)

    def _grow(self, has: np.ndarray, bad: np.ndarray, good: np.ndarray, started: bool) -> bool:
        """has, bad, good: the baskets with the set so far, by the items that may be added."""
        while True:
            n_bad, n_good = int(bad.sum()), int(good.sum())
            if started and self._is_rule(n_bad, n_good):
                return True
            with_bad, with_good = bad @ has, good @ has
            keep = (with_bad >= self.least) & ((with_good < n_good) if started else True)
            has, with_bad, with_good = has[:, keep], with_bad[keep], with_good[keep]
            if not has.shape[1]:
                return False
            most, fewest = int(with_bad.max()), int(good[has.all(1)].sum())
            if not self._is_rule(most, fewest):
                return False
            free = with_bad == n_bad
            if free.any():
                rows = has[:, free].all(1)
                has, bad, good, started = has[rows][:, ~free], bad[rows], good[rows], True
                continue
            one = int(np.argmax(with_bad / (with_bad + with_good)))
            rows, others = has[:, one], np.arange(has.shape[1]) != one
            if self._grow(has[rows][:, others], bad[rows], good[rows], True):
                return True
            has = has[:, others]


def mine(labelled: DataFrame, min_share: float = MIN_SHARE, min_count: int = MIN_COUNT, min_confidence: float = MIN_CONFIDENCE, max_items: int = MAX_ITEMS) -> tuple[DataFrame, DataFrame]:
    """(token, item of the tokens that rules know; rule_id, items (array<string>), confidence) from rows (tokens, bad)."""
    return mined(labelled, min_share, min_count, min_confidence, max_items)[:2]


def mined(labelled: DataFrame, min_share: float = MIN_SHARE, min_count: int = MIN_COUNT, min_confidence: float = MIN_CONFIDENCE, max_items: int = MAX_ITEMS) -> tuple[DataFrame, DataFrame, Search | None]:
    """As mine(), and the search for what FP-growth may have missed, if it did not see all baskets whole."""
    from pyspark.ml.fpm import FPGrowth

    spark = labelled.sparkSession
    baskets = staged(labelled.select("tokens", "bad").where(F.size("tokens") > 0).withColumn("row_id", F.monotonically_increasing_id()), "url-baskets")
    n = baskets.count()
    nothing = spark.createDataFrame([], "token string, item string"), spark.createDataFrame([], "rule_id long, items array<string>, confidence double"), None
    least = int(max(min_count, -(-n * min_share // 1)))
    if n < least:
        return nothing
    known = items(baskets, least, min_confidence)
    ruled = baskets.select("row_id", "bad", F.explode("tokens").alias("token")).join(known.where("alone"), "token").groupBy("item").agg(F.avg(F.col("bad").cast("double")).alias("confidence"))
    single = ruled.select(F.xxhash64(F.array("item")).alias("rule_id"), F.array("item").alias("items"), "confidence")
    # the other tokens' items, those in most bad URLs first
    left = known.where(~F.col("alone")).groupBy("item").agg(F.max("n_bad").alias("n_bad"))
    per = baskets.select("row_id", "bad", F.explode("tokens").alias("token")).join(known.where("token = item and not alone").select("token"), "token").join(left.withColumnRenamed("item", "token"), "token")
    ranked = F.array_sort(F.collect_list(F.struct((-F.col("n_bad")).alias("k"), "token")))
    whole = per.groupBy("row_id", "bad").agg(F.transform(ranked, lambda x: x["token"]).alias("items"))
    # equal baskets once
    whole = staged(whole.groupBy("items").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("bad").cast("long")).alias("n_bad")), "url-itemsets")
    cut = F.slice("items", 1, max_items)
    each = whole.select(F.explode(F.array(F.struct(F.concat(cut, F.array(F.lit(BAD))).alias("items"), F.col("n_bad").alias("times")), F.struct(cut.alias("items"), (F.col("n") - F.col("n_bad")).alias("times")))).alias("s")).where("s.times > 0")
    sets = each.select("s.items", F.explode(F.sequence(F.lit(1).cast("long"), "s.times"))).select("items")
    m, longest = whole.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max(F.size("items")), F.lit(0))).first()
    rules, search = single, None
    if m >= least:
        model = FPGrowth(itemsCol="items", minSupport=least / m, minConfidence=min_confidence).fit(sets)
        found = model.associationRules.where(F.array_contains("consequent", BAD))
        found = found.select(F.xxhash64(F.array_sort("antecedent")).alias("rule_id"), F.array_sort("antecedent").alias("items"), "confidence")
        if longest > max_items:
            found = recounted(found, whole, least, min_confidence)
            search = Search(whole.collect(), least, min_confidence)
        rules = single.unionByName(found)
    return known.select("token", "item"), rules, search


def recounted(rules: DataFrame, sets: DataFrame, least: int, min_confidence: float) -> DataFrame:
    """Those of the rules that hold over sets (items, n, n_bad), with their confidence there."""
    rules = staged(rules, "url-candidates")
    filed = rules.select("rule_id", F.col("items").alias("rule"), F.element_at("items", -1).alias("item"))
    at = sets.select("items", "n", "n_bad", F.explode("items").alias("item")).join(filed, "item").where(F.size(F.array_except("rule", "items")) == 0)
    true = at.groupBy("rule_id").agg(F.sum("n").alias("n"), F.sum("n_bad").alias("n_bad")).where((F.col("n_bad") >= least) & (F.col("n_bad") / F.col("n") >= min_confidence))
    return rules.drop("confidence").join(true.select("rule_id", (F.col("n_bad") / F.col("n")).alias("confidence")), "rule_id").select("rule_id", "items", "confidence")


def index(rules: DataFrame) -> DataFrame:
    """The rules filed under their last item in order: item, items."""
    return rules.select(F.element_at(F.array_sort("items"), -1).alias("item"), F.col("items").alias("rule"))


def caught(baskets: DataFrame, known: DataFrame, rules: DataFrame, search: Search | None = None) -> DataFrame:
    """tokens, n of the distinct token sets in `baskets` (column tokens) that some rule matches, with their numbers of rows."""
    sets = staged(baskets.where(F.size("tokens") > 0).groupBy("tokens").agg(F.count(F.lit(1)).alias("n")).withColumn("set_id", F.monotonically_increasing_id()), "url-sets")
    named = sets.select("set_id", F.explode("tokens").alias("token")).join(known, "token").groupBy("set_id").agg(F.collect_set("item").alias("items"))
    named = staged(named, "url-named") if search else named
    at = named.select("set_id", "items", F.explode("items").alias("item")).join(index(rules), "item")
    hit = at.where(F.size(F.array_except("rule", "items")) == 0).select("set_id").distinct()
    if search:
        hit = staged(hit, "url-hit")
        shared = baskets.sparkSession.sparkContext.broadcast(search)

        def searched(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for part in parts:
                yield part[[shared.value.finds(list(i)) for i in part["items"]]][["set_id"]]

        hit = hit.unionByName(named.join(hit, "set_id", "left_anti").mapInPandas(searched, "set_id long"))
    return sets.join(hit, "set_id").select("tokens", "n")


def verdicts(pages: DataFrame, labels: DataFrame, rules: tuple = RULES, id_col: str = "page_id", url_col: str = "url", label_id: str = "doc_id", label_col: str = "quality") -> DataFrame:
    """page_id, host, path, rule, verdict for every row.

    A null url, or one without "://", has an empty host and path and no tokens, so no rule fits and it is allowed. Labels belong to pages
    by id: 0 is bad; of several labels of an id the lowest counts, null labels do not. Repeated rows and null ids
    each keep their row, empty tables give no rows or no mined rules, other columns are ignored. Of a very long url all tokens are learned from and looked up. Equal longest rules do not occur, as a host and a path are named once.
    """
    rows = narrow(pages, page_id=id_col, url=url_col).select(F.col("page_id").cast("long").alias("page_id"), "url")
    rows = rows.select("page_id", "url", host(F.col("url")).alias("host"), path(F.col("url")).alias("path"))
    rows = rows.withColumn("tokens", tokens(F.col("url"), F.col("host"), F.col("path")))
    labelled = narrow(labels, label_id=label_id, label=label_col).where("label is not null").groupBy(F.col("label_id").cast("long").alias("page_id")).agg((F.min("label") == 0).alias("bad"))
    known, learned_rules, search = mined(rows.join(labelled, "page_id").select("tokens", "bad"))
    bad = staged(caught(rows, known, staged(learned_rules, "url-rules"), search), "url-caught").withColumn("caught", F.lit(True))
    name, verdict = matched(F.col("host"), F.col("path"), rules)
    judged = joined_by_hot_key(rows.drop("url"), bad, "tokens", "page_id")
    learned = F.when(F.col("caught"), "block").otherwise("allow")
    return judged.select("page_id", "host", "path", name.alias("rule"), F.coalesce(verdict, learned).alias("verdict"))
