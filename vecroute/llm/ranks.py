"""Distributed ranks within strata of any size, by DataFrame operations alone.

A window over a whole stratum would put a source that holds a third of all rows
into one task. Here rows are spread over key buckets, ranked inside their bucket,
and shifted by the bucket's offset from a small table of counts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEY_BITS = 60
#: Rows per (stratum, bucket) aimed at, and the most buckets, which bounds the offset table.
BUCKET_ROWS = 256
MAX_BUCKETS = 1 << 16


def seeded_key(seed: int, column: Column) -> Column:
    """A 60-bit shuffle key from the first hex digits of an md5, the same in any engine."""
    text = F.concat(F.lit(f"{seed}|"), F.coalesce(column.cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(text), 1, KEY_BITS // 4), 16, 10).cast("long")


def stratum_key(column: Column) -> Column:
    """The stratum as text that is never null; null forms a stratum of its own."""
    return F.coalesce(F.concat(F.lit("s"), column.cast("string")), F.lit("n"))


def bucket_bits(rows: int) -> int:
    return min(MAX_BUCKETS, max(1, -(-rows // BUCKET_ROWS))).bit_length() - 1


def bucket_counts(df: DataFrame, bits: int) -> DataFrame:
    """``stratum, bucket, n`` of a frame with ``stratum`` and ``shuffle_key``."""
    return df.groupBy("stratum", F.shiftright("shuffle_key", KEY_BITS - bits).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def rank_in_stratum(df: DataFrame, counts: DataFrame, bits: int, ties: list[Column], facts: DataFrame | None = None) -> DataFrame:
    """Adds ``stratum_rank`` (from 0, by shuffle key) and ``stratum_rows``.

    ``df`` has ``stratum`` and ``shuffle_key``; ``counts`` is what
    ``bucket_counts`` gives for the same rows and bits. ``ties`` orders rows of equal key. ``facts``
    has a row per stratum, whose columns ride along with the offsets, so that rows
    meet them without a join by stratum.
    """
    by_stratum = Window.partitionBy("stratum")
    offsets = counts.select("stratum", "bucket", (F.sum("n").over(by_stratum.orderBy("bucket")) - F.col("n")).alias("bucket_start"), F.sum("n").over(by_stratum).alias("stratum_rows"))
    if facts is not None:
        offsets = offsets.join(facts, "stratum")
    inside = Window.partitionBy("stratum", "bucket").orderBy("shuffle_key", *ties)
    numbered = df.withColumn("bucket", F.shiftright("shuffle_key", KEY_BITS - bits)).withColumn("in_bucket", F.row_number().over(inside))
    joined = numbered.join(offsets, ["stratum", "bucket"])
    return joined.withColumn("stratum_rank", F.col("bucket_start") + F.col("in_bucket") - 1).drop("bucket", "in_bucket", "bucket_start")
