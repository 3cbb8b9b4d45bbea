"""Aggregates over pools, as columns that combine before they move."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def entropy_bits(n: Column) -> Column:
    """Entropy in bits of a distribution given by its counts."""
    total = F.sum(n)
    return F.log2(total) - F.sum(n * F.log2(n)) / total


def effective_bases(n: Column) -> Column:
    """How many equally common bases would have the same entropy."""
    return F.pow(F.lit(2.0), entropy_bits(n))
