"""Single-layer nearest-neighbour graphs, built by a join and walked from a far start."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import kernels
from vecroute.graphs import hnsw
from vecroute.plans.search import exact_topk


def build_rows(items: DataFrame, degree: int, metric: str = "l2") -> DataFrame:
    """``node, rank, neighbour, score`` by exact self-join; for sets whose items may be broadcast."""
    found = exact_topk(items.select(F.col("item_id").alias("query_id"), "vec"), items, degree, metric, exclude_self=True)
    return found.select(F.col("query_id").alias("node"), "rank", F.col("item_id").alias("neighbour"), "score")


def build(ids: np.ndarray, x: np.ndarray, degree: int = 16, metric: str = "l2", mutual: bool = True, near: np.ndarray | None = None) -> hnsw.Graph:
    """The same graph for a numpy walk; ``mutual`` also links each node back.

    ``near`` holds the positions that ``kernels.nearest_rows`` gives for the items in id order, where they are known.
    """
    order = np.argsort(ids)
    ids, x = np.asarray(ids)[order], kernels.prepared(np.asarray(x)[order], metric)
    n, k = len(ids), max(0, min(degree, len(ids) - 1))
    near = (kernels.nearest_rows(x, k, metric)[0] if near is None else near)[:, :k]
    source, target = np.repeat(np.arange(n), k), near.reshape(-1)
    pairs = np.unique(np.concatenate([source * n + target, target * n + source] if mutual else [source * n + target]))
    row, col = np.divmod(pairs, max(1, n))
    place = np.arange(row.size) - np.searchsorted(row, row, "left")
    width = int(place.max(initial=0)) + 1
    links = np.full((n, width), -1, np.int64)
    links[row, place] = col
    return hnsw.Graph(ids, x, metric, [hnsw.Layer(np.arange(n), links)], 0, width, width)


def search(graph: hnsw.Graph, queries: np.ndarray, k: int, l: int, start: int | None = None):  # noqa: E741
    """A walk from ``start`` (a position; the first node by default)."""
    from dataclasses import replace

    return hnsw.search(graph if start is None else replace(graph, entry=start), queries, k, l)
