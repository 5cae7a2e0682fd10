"""Samples of a vector set."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def uniform(items: DataFrame, n_prime: int, seed: int = 42) -> DataFrame:
    """About ``n_prime`` rows; every partition gives in proportion to its rows, in one scan."""
    n = items.count()
    return items if n <= n_prime else items.sample(fraction=n_prime / n, seed=seed)


def by_hash(items: DataFrame, modulus: int, keep: int = 0) -> DataFrame:
    """The rows whose hashed id leaves a remainder: the same rows on every run and any layout."""
    return items.where(F.pmod(F.conv(F.substring(F.md5(F.col("item_id").cast("string")), 1, 8), 16, 10).cast("long"), F.lit(modulus)) == keep)


def by_modulus(items: DataFrame, modulus: int, keep: int = 0) -> DataFrame:
    return items.where(F.col("item_id") % modulus == keep)
