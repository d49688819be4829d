"""Reproducible draws and order-free sums."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PROBABILITY = "decimal(18,12)"


def draw(tag: Column | str, *parts: Column) -> Column:
    """A number in [0, 1) from the md5 of the parts after a tag: any node, and DuckDB, gets the same."""
    text = F.concat(F.lit(tag) if isinstance(tag, str) else tag, *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def draw_sql(tag: str, *parts: str) -> str:
    """The same in DuckDB; tag and parts are SQL expressions for text."""
    return f"(('0x' || substr(md5({' || '.join([tag, *parts])}), 1, 8))::BIGINT / 4294967296.0)"


def exact(p: Column) -> Column:
    """A probability as a decimal, so that its sums do not depend on the order of rows."""
    return p.cast(PROBABILITY)
