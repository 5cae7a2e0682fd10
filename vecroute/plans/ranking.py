"""Exact global ranks without a window over the whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecroute.plans.sizes import small


def global_rank(df: DataFrame, key: Column, order: list[Column], bucket_rows: int = 1 << 20, name: str = "global_rank") -> DataFrame:
    """Adds the rank (from 1) of each row under ``order``, whose first term is ``key`` ascending.

    Rows are dealt to buckets at approximate quantiles of the key, as many as the row
    count asks for (2 to the power of 12 at most), ranked inside, and shifted by the rows of the buckets before; any cut points give exact ranks.
    """
    finest = 1 << 12
    n, cuts = df.select(F.count(F.lit(1)), F.percentile_approx(key, [i / finest for i in range(1, finest)], 2 * finest)).first()
    buckets = min(finest, max(8, 1 << max(0, -(-n // bucket_rows) - 1).bit_length()))
    edges = sorted(set((cuts or [])[finest // buckets - 1 :: finest // buckets]))
    # The key is taken once a row; edges at most as many as buckets.
    bucket = F.size(F.filter(F.array(*[F.lit(e) for e in edges]), lambda e: F.col("_key") > e)) if edges else F.lit(0)
    dealt = df.withColumn("_key", key).withColumn("_bucket", bucket).drop("_key")
    counts = dealt.groupBy("_bucket").agg(F.count(F.lit(1)).alias("_n"))
    starts = counts.select("_bucket", (F.sum("_n").over(Window.orderBy("_bucket")) - F.col("_n")).alias("_start"))
    inside = F.row_number().over(Window.partitionBy("_bucket").orderBy(*order))
    return dealt.withColumn("_r", inside).join(small(starts), "_bucket").withColumn(name, (F.col("_start") + F.col("_r")).cast("long")).drop("_bucket", "_r", "_start")
