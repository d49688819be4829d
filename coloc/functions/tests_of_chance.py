"""p-values of randomisation tests, and decisions in whole numbers."""

from __future__ import annotations

from decimal import ROUND_FLOOR, Decimal

from pyspark.sql import Column


def p_value(exceed: Column, sims: int | Column) -> Column:
    """The observed data counts once above and below."""
    return (exceed + 1) / (sims + 1)


def most_exceedances(alpha: float, sims: int, strict: bool = False) -> int:
    """The largest number of exceedances with a p-value of at most alpha (below it if strict); -1 if none."""
    bound = Decimal(str(alpha)) * (sims + 1)
    whole = int(bound.to_integral_value(ROUND_FLOOR))
    return whole - 1 - (1 if strict and bound == whole else 0)
