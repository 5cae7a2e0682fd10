"""Proportional stratified interleaving.

Rows are shuffled by a seeded key and ranked within their source. Row ``r`` of a
source with ``n`` rows has fractional rank ``(r + 1/2) / n``; in the order of these
fractions every stretch holds the sources in the proportion of the whole, and
cutting it into equal stretches gives shards that all match the mixture, with
sizes at most one row apart (the ``rows`` law).

Only narrow rows are exchanged: twice, first by (source, key bucket), then by a
bucket of the fraction. Offsets come from two small tables of counts: per (source,
bucket), and per bucket of the fraction, of which there are ``MAX_BUCKETS`` at most.

Defined cases: null source is a source of its own; null text has size 1 and the
checksum of the empty text; rows with equal ids each get a slot of their own; fewer
rows than shards leave shards empty; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecroute.llm.ranks import bucket_bits, bucket_counts, rank_in_stratum, seeded_key, stratum_key
from vecroute.runtime import Workspace

SEED = 20


def interleave(docs: DataFrame, n_shards: int = 8, seed: int = SEED) -> DataFrame:
    """``doc_id, source, size, text_crc32, position, law, shard, slot, grown_shard``."""
    if n_shards < 1:
        raise ValueError("at least one shard")
    workspace = Workspace(docs.sparkSession, "shards")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    keyed = docs.select("doc_id", "source", (F.octet_length(text).cast("long") + 1).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), stratum_key(F.col("source")).alias("stratum"), seeded_key(seed, F.col("doc_id")).alias("shuffle_key"))
    total = docs.count()
    bits = bucket_bits(total)
    counts = bucket_counts(keyed, bits)
    cells = 1 << bits
    odd = 2 * F.col("stratum_rank") + 1
    ranked = rank_in_stratum(keyed, counts, bits, [F.col("doc_id"), F.col("size"), F.col("text_crc32")])
    # Written, since the cells are counted before rows are numbered inside them.
    ranked = workspace.keep(ranked.withColumn("cell", F.expr(f"((2 * stratum_rank + 1) * {cells}) div (2 * stratum_rows)")).drop("shuffle_key"), "ranked")
    sizes = ranked.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))
    starts = sizes.select("cell", (F.sum("n").over(Window.orderBy("cell")) - F.col("n")).alias("cell_start"))

    # Fractions are compared as doubles; equal ones go by stratum.
    inside = Window.partitionBy("cell").orderBy(odd / F.col("stratum_rows"), "stratum", "stratum_rank")
    placed = ranked.withColumn("in_cell", F.row_number().over(inside)).join(starts, "cell").withColumn("position", F.col("cell_start") + F.col("in_cell") - 1)
    shard = F.expr(f"(position * {n_shards}) div {max(total, 1)}")
    first = F.expr(f"(shard * {total} + {n_shards} - 1) div {n_shards}")
    placed = placed.withColumn("shard", shard.cast("int")).withColumn("slot", F.col("position") - first)
    return placed.select("doc_id", "source", "size", "text_crc32", "position", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def mixture_by_shard(placed: DataFrame) -> DataFrame:
    """Share of each source in each shard, to hold against its share of the whole."""
    per = placed.groupBy("shard", "source").agg(F.count(F.lit(1)).alias("rows"))
    return per.withColumn("share", F.col("rows") / F.sum("rows").over(Window.partitionBy("shard")))
