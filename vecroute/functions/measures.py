"""Accuracy and cost measures as small aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecroute.functions import vectors
from vecroute.plans.ranking import global_rank


def precision(result: DataFrame, truth: DataFrame, k: int, by: list[str] | None = None) -> DataFrame:
    """``precision``: found share of the true top ``k``, averaged over queries; without a hit a query counts 0.

    ``by`` names columns of ``result`` (say the branching factor) to report apart.
    """
    by = by or []
    n = truth.select("query_id").distinct().count()
    want = truth.where(F.col("rank") <= k).select("query_id", "item_id")
    hits = result.where(F.col("rank") <= k).join(want, ["query_id", "item_id"], "left_semi").groupBy(*by).agg(F.count(F.lit(1)).alias("hits"))
    if by:
        hits = result.select(*by).distinct().join(hits, by, "left")
    return hits.select(*by, (F.coalesce("hits", F.lit(0)) / F.lit(float(max(1, k * n)))).alias("precision"))


def recall_top1(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """``recall``: share of queries whose best item is among the ``k`` returned."""
    best = truth.where("rank = 1").select("query_id", "item_id")
    found = result.where(F.col("rank") <= k).select("query_id", "item_id").withColumn("hit", F.lit(1))
    return best.join(found, ["query_id", "item_id"], "left").agg((F.count("hit") / F.count(F.lit(1))).alias("recall"))


def access_rate(routed: DataFrame, w: int, by: list[str] | None = None) -> DataFrame:
    per = routed.groupBy(*(by or []), "query_id").agg(F.countDistinct("sub_id").alias("n"))
    return per.groupBy(*(by or [])).agg((F.avg("n") / w).alias("access_rate"))


def throughput(n_queries: int, seconds: float) -> float:
    return n_queries / seconds if seconds > 0 else float("inf")


def throughput_series(finished: DataFrame, ts: str = "ts", width: str = "1 second") -> DataFrame:
    return finished.groupBy(F.window(ts, width).alias("w")).agg(F.count(F.lit(1)).alias("queries")).select(F.col("w.start").alias("start"), "queries")


def latency_pct(latencies: DataFrame, share: float = 0.9, exact: bool = True) -> DataFrame:
    f = F.percentile("latency", share) if exact else F.percentile_approx("latency", share, 10_000)
    return latencies.agg(f.alias("latency"))


def storage(placement: DataFrame, n: int, m: int = 0, r: int = 0) -> DataFrame:
    """Stored rows, overhead by distinct copies (net) and by requested ones (gross)."""
    return placement.agg(F.count(F.lit(1)).alias("stored"), (F.count(F.lit(1)) / F.lit(float(n)) - 1).alias("net_overhead"), F.lit(m * r / n).alias("gross_overhead"))


def balance(df: DataFrame, key: str, weight: Column | None = None) -> DataFrame:
    per = df.groupBy(key).agg((F.sum(weight) if weight is not None else F.count(F.lit(1))).alias("n"))
    return per.agg((F.max("n") / F.avg("n")).alias("peak"), F.stddev_pop("n").alias("spread"), F.count(F.lit(1)).alias("parts"))


def edge_cut(edges: DataFrame, part_of: DataFrame) -> DataFrame:
    """Crossing share of ``a, b`` edges under ``node, sub_id``."""
    a, b = part_of.select(F.col("node").alias("a"), F.col("sub_id").alias("pa")), part_of.select(F.col("node").alias("b"), F.col("sub_id").alias("pb"))
    return edges.join(a, "a").join(b, "b").agg(F.sum((F.col("pa") != F.col("pb")).cast("long")).alias("crossing"), F.count(F.lit(1)).alias("edges"))


def norm_share(truth: DataFrame, items: DataFrame, bins: int = 20) -> DataFrame:
    """``bin, share``: result rows by norm bin of their item, largest norms first; bins as ``ntile`` cuts them."""
    minus = -F.round(vectors.norm(F.col("vec")), 6)
    ranked = global_rank(items.select("item_id", minus.alias("minus")), F.col("minus"), [F.col("minus"), F.col("item_id")])
    n = items.count()
    size, extra = divmod(n, bins)
    r = F.col("global_rank") - 1
    # The first n mod bins bins hold one row more.
    bin_of = F.when(r < extra * (size + 1), F.expr(f"(global_rank - 1) div {size + 1}")).otherwise(extra + F.expr(f"(global_rank - 1 - {extra * (size + 1)}) div {max(size, 1)}")) + 1
    per = truth.select("item_id").join(ranked.select("item_id", bin_of.cast("int").alias("bin")), "item_id").groupBy("bin").agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy(F.lit(1)))
    return per.select("bin", (F.col("n") / total).alias("share"))


def raw_bytes(n: int, d: int) -> int:
    """Uncompressed 4-byte features."""
    return n * d * 4


def index_bytes(graphs: DataFrame) -> DataFrame:
    links = F.aggregate("levels", F.lit(0).cast("long"), lambda acc, y: acc + F.size(y["targets"]))
    return graphs.agg(F.sum(F.octet_length("vectors")).alias("vector_bytes"), F.sum(links * 4).alias("link_bytes"))


def speedup(throughput_more: float, throughput_less: float) -> float:
    return throughput_more / throughput_less


def loss_split(scanned: DataFrame, walked: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Precision lost by routing (parts never visited) and by walking graphs inside parts."""
    a = precision(scanned, truth, k).select(F.col("precision").alias("scan"))
    b = precision(walked, truth, k).select(F.col("precision").alias("walk"))
    return a.crossJoin(b).select((1 - F.col("scan")).alias("routing_loss"), (F.col("scan") - F.col("walk")).alias("graph_loss"))
