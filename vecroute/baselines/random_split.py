"""Random split, all parts searched: with layered graphs, or with one part, or replicated whole."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import vectors
from vecroute.plans import router, search
from vecroute.runtime import Workspace, ship


@dataclass
class Split:
    """Parts by hash of the id, with a graph each."""

    w: int
    metric: str
    placement: DataFrame
    graphs: DataFrame
    phases: dict[str, float] = field(default_factory=dict)

    def ask(self, queries: DataFrame, k: int, l: int = 100, max_evals: int | None = None) -> DataFrame:  # noqa: E741
        return search.merge_top_k(self.partials(queries, k, l, max_evals), k)

    def partials(self, queries: DataFrame, k: int, l: int = 100, max_evals: int | None = None) -> DataFrame:  # noqa: E741
        q = queries.select("query_id", vectors.normalise(F.col("vec")).alias("vec")) if self.metric == "cosine" else queries
        return search.search_subs(router.every_part(q, self.w), self.graphs, k, l, max_evals)


def build(items: DataFrame, w: int, metric: str = "l2", builder: str = "insert", l: int = 100, seed: int = 42) -> Split:  # noqa: E741
    """``w = 1`` is the single-machine graph."""
    ship(items.sparkSession)
    workspace = Workspace(items.sparkSession, "split")
    if metric == "cosine":
        items = items.select("item_id", vectors.normalise(F.col("vec")).alias("vec"))
    clock = time.perf_counter()
    placement = workspace.keep(router.random_parts(items, w), "placement")
    placed = time.perf_counter()
    graphs = workspace.keep(search.build_all(placement, w, metric, l=l, seed=seed, builder=builder), "graphs")
    return Split(w, metric, placement, graphs, {"partition": placed - clock, "graphs": time.perf_counter() - placed})


def replicated(items: DataFrame, queries: DataFrame, workers: int, k: int, l: int = 100, metric: str = "l2", most_rows: int = 1_000_000) -> DataFrame:  # noqa: E741
    """One whole graph on every worker, queries dealt round: memory ``n`` per worker.

    Refuses sets of more than ``most_rows`` items, as every worker holds them all.
    """
    n = items.count()
    if n > most_rows:
        raise ValueError(f"{n} items are too many to hold on every worker")
    one = build(items, 1, metric, l=l)
    dealt = queries.select("query_id", "vec", F.lit(0).alias("sub_id"))
    return search.merge_top_k(search.search_subs(dealt, one.graphs, k, l, chunks=workers), k)
