"""Broadcasts behind a check of their size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes of one table or query block that may be sent to every executor.
MAX_BROADCAST_BYTES = 256 << 20


def small(df: DataFrame, most: int = MAX_BROADCAST_BYTES) -> DataFrame:
    """``df`` marked for broadcast if it is small enough, else as it is, so that the join exchanges it.

    The optimiser's estimate decides where it is below the bound; it never
    underestimates a scan of files but grows with every join, so beyond the bound the rows are measured.
    """
    if int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) <= most:
        return F.broadcast(df)
    size = df.agg(F.sum(F.length(F.to_json(F.struct("*"))))).first()[0] or 0
    return F.broadcast(df) if size <= most else df


def query_blocks(queries: DataFrame, most: int = MAX_BROADCAST_BYTES) -> list[DataFrame]:
    """The query set in blocks by hash, so that the numbers of one stay below the bound; counted before anything is collected."""
    numbers = queries.agg(F.sum(F.size("vec"))).first()[0] or 0
    n = max(1, -(-8 * numbers // most))
    return [queries] if n == 1 else [queries.where(F.pmod(F.xxhash64("query_id"), F.lit(n)) == i) for i in range(n)]
