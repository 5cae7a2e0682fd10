"""The graph walk as DataFrame supersteps: all queries advance one hop per join.

Frontier and visited sets are tables; each superstep joins the frontier to the
adjacency, scores the new vertices, and keeps the best ``l`` per query. For graphs that
fit no single task.
"""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import vectors
from vecroute.plans.router import top_rank
from vecroute.runtime import Workspace


def search(queries: DataFrame, edges: DataFrame, items: DataFrame, entry: int, k: int, l: int, metric: str = "l2", max_hops: int | None = None, expand: int = 8, workspace: Workspace | None = None) -> DataFrame:  # noqa: E741
    """``query_id, rank, item_id, score`` over ``edges(node, neighbour)``.

    ``expand`` open vertices per query advance at once, so hops are few. The walk ends
    when no query has an open vertex; ``max_hops`` ends it before, as a budget. Every step
    is written, which cuts the lineage for good.
    """
    workspace = workspace or Workspace(queries.sparkSession, "walk")
    q = queries.select("query_id", F.col("vec").alias("q"))
    x = items.select("item_id", "vec")

    def scored(pairs: DataFrame) -> DataFrame:
        return pairs.join(x, "item_id").join(q, "query_id").select("query_id", "item_id", vectors.score(F.col("q"), F.col("vec"), metric).alias("score"), F.lit(True).alias("open"))

    beam = workspace.keep(scored(q.select("query_id", F.lit(entry).cast("long").alias("item_id"))), "beam")
    for _ in itertools.count() if max_hops is None else range(max_hops):
        front = top_rank(beam.where("open"), "query_id", expand).select("query_id", F.col("item_id").alias("node"))
        nxt = front.join(edges, "node").select("query_id", F.col("neighbour").alias("item_id")).distinct()
        seen = beam.select("query_id", "item_id")
        fresh = scored(nxt.join(seen, ["query_id", "item_id"], "left_anti"))
        closed = beam.join(front.select("query_id", F.col("node").alias("item_id"), F.lit(1).alias("now")), ["query_id", "item_id"], "left").select("query_id", "item_id", "score", (F.col("open") & F.col("now").isNull()).alias("open"))
        both = closed.unionByName(fresh)
        # What falls out of the best l stays known but is never expanded.
        ranked = top_rank(both, "query_id", 1 << 30).withColumn("open", F.col("open") & (F.col("rank") <= l)).drop("rank")
        after = workspace.keep(ranked, "beam")
        workspace.drop(beam)
        beam = after
        if beam.where("open").isEmpty():
            break
    return top_rank(beam, "query_id", k).select("query_id", "rank", "item_id", "score")
