"""Bounded samples of labelled rows for the models that are trained here."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coloc.llm.tables import staged

#: A draw passes this many times the keys that are wanted, as counts of distinct keys are estimates; of keys that must also be
#: elsewhere, so many times more.
SPARE, ELSEWHERE = 1.5, 3.0
_RANGE = 1 << 62


def remainder(id_col: str, divisor: int) -> Column:
    """crc32 of the id as text, modulo divisor; null ids count as empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % divisor


def smallest(rows: DataFrame, quota: int, of: DataFrame | None = None) -> DataFrame:
    """label, key: for each label the `quota` distinct keys (long) with the smallest hashes, of those that are also in `of`.

    How a key is repeated, and how rows lie in partitions, makes no difference. Distinct keys are counted first by estimate; only keys
    whose hash lies under SPARE times a label's share go to the driver to be put in order, a few quotas for each label.
    """
    spark = rows.sparkSession
    known = rows.where(F.col("label").isNotNull() & F.col("key").isNotNull())
    spare = SPARE if of is None else ELSEWHERE * SPARE
    counts = {r[0]: r[1] for r in known.groupBy("label").agg(F.approx_count_distinct("key")).collect()}
    if not counts:
        return spark.createDataFrame([], known.select("label", "key").schema)
    h = F.pmod(F.xxhash64("key", F.lit(17)), F.lit(_RANGE))
    limit = F.lit(0)
    for value, n in sorted(counts.items(), key=str):
        limit = F.when(F.col("label") == F.lit(value), F.lit(int(min(1.0, (spare * quota + 100) / max(n, 1)) * _RANGE))).otherwise(limit)
    few = known.select("label", "key", h.alias("h")).where(F.col("h") < limit).distinct()
    if of is not None:
        few = staged(few, "drawn-keys")
        there = staged(of.join(F.broadcast(few.select("key").distinct()), "key", "left_semi").distinct(), "present-keys")
        few = few.join(F.broadcast(there), "key", "left_semi")
    by_label: dict = {}
    for r in sorted(few.collect(), key=lambda r: (r["h"], r["key"])):
        by_label.setdefault(r["label"], []).append(r["key"])
    return spark.createDataFrame([(label, key) for label, keys in by_label.items() for key in keys[:quota]], known.select("label", "key").schema)


def per_class(rows: DataFrame, label: str, text: str, quota: int, pieces: int, size: int) -> list[tuple]:
    """(label, text) of at most `quota` distinct texts of each label, those with the smallest hashes, in the order of labels and hashes.

    No text is left out for its length: of one with more than `size` characters, `pieces` pieces spread over it from start to
    end are taken instead, one after the other.
    """
    full = rows.where(F.col(label).isNotNull() & (F.octet_length(text) > 0)).select(F.col(label).alias("label"), F.xxhash64(text).alias("key"), F.col(text).alias("text"))
    drawn = smallest(full.select("label", "key"), quota)
    long = F.char_length("text")
    parts = F.when(long <= size, F.array("text")).otherwise(F.array(*[F.substring("text", F.floor((long - size) * (k / max(1, pieces - 1))).cast("int") + F.lit(1), F.lit(size)) for k in range(pieces)]))
    found = full.join(F.broadcast(drawn), ["label", "key"]).select("label", "key", F.posexplode(parts).alias("nth", "piece")).distinct()
    return [(r["label"], r["piece"]) for r in sorted(found.collect(), key=lambda r: (r["label"], r["key"] % (1 << 64), r["nth"], r["piece"]))]
