"""KD-trees: randomised trees per part of a random split, and a space cut at cluster level."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.plans import router, search
from vecroute.plans.sizes import small


@dataclass
class Tree:
    axis: np.ndarray
    value: np.ndarray
    left: np.ndarray
    right: np.ndarray
    leaf: list[np.ndarray]


def grow(x: np.ndarray, rng: np.random.Generator, leaf_size: int = 16, choices: int = 5) -> Tree:
    """Median splits on an axis drawn from those of largest variance."""
    axis, value, left, right, leaf = [], [], [], [], []

    def node(at: np.ndarray) -> int:
        me = len(axis)
        axis.append(-1), value.append(0.0), left.append(-1), right.append(-1), leaf.append(at)
        if at.size > leaf_size:
            spread = x[at].var(axis=0)
            top = np.argsort(-spread, kind="stable")[:choices]
            a = int(top[rng.integers(min(choices, top.size))])
            order = np.argsort(x[at, a], kind="stable")
            half = at.size // 2
            cut = x[at[order[half]], a]
            lower = x[at, a] < cut
            if lower.any() and not lower.all():
                axis[me], value[me], leaf[me] = a, float(cut), at[:0]
                left[me] = node(at[lower])
                right[me] = node(at[~lower])
        return me

    node(np.arange(len(x)))
    return Tree(np.array(axis), np.array(value), np.array(left), np.array(right), leaf)


def search_trees(trees: list[Tree], x: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, max_leaves: int | None = None) -> tuple[np.ndarray, np.ndarray, int]:
    """(ids, scores, evals) by one queue of branches over all trees; exact for one tree without a bound on leaves."""
    queue = [(0.0, i, t, 0, ()) for i, t in enumerate(range(len(trees)))]
    best: dict[int, float] = {}
    kth, seen, leaves, tick = np.inf, set(), 0, len(queue)
    while queue:
        bound, _, t, at, gaps = heapq.heappop(queue)
        if bound > kth or max_leaves is not None and leaves >= max_leaves:
            break
        tree = trees[t]
        while tree.axis[at] >= 0:
            a = int(tree.axis[at])
            gap = q[a] - tree.value[at]
            near, far = (tree.left[at], tree.right[at]) if gap < 0 else (tree.right[at], tree.left[at])
            known = dict(gaps)
            known[a] = max(known.get(a, 0.0), gap * gap)
            tick += 1
            heapq.heappush(queue, (sum(known.values()), tick, t, int(far), tuple(known.items())))
            at = int(near)
        leaves += 1
        fresh = [i for i in tree.leaf[at].tolist() if i not in seen]
        if fresh:
            seen.update(fresh)
            d = ((x[fresh] - q) ** 2).sum(axis=1)
            best.update(zip(fresh, d.tolist(), strict=True))
            if len(best) >= k:
                values = np.fromiter(best.values(), float)
                kth = np.partition(values, k - 1)[k - 1]
    at = np.array(list(best), np.int64)
    d = np.array([best[i] for i in at.tolist()])
    order = np.lexsort((ids[at], d))[:k] if at.size else at
    return ids[at[order]], -np.sqrt(d[order]), len(seen)


def ask(items: DataFrame, queries: DataFrame, w: int, k: int, trees: int = 1, max_leaves: int | None = None, seed: int = 42) -> DataFrame:
    """``query_id, rank, item_id, score`` under L2; for cosine pass unit vectors, for inner product augmented ones."""
    return search.merge_top_k(partials(items, queries, w, k, trees, max_leaves, seed), k)


def partials(items: DataFrame, queries: DataFrame, w: int, k: int, trees: int = 1, max_leaves: int | None = None, seed: int = 42) -> DataFrame:
    placed = router.random_parts(items, w).select("sub_id", "item_id", F.col("vec").cast("array<double>").alias("vec"))

    def matrix(t: pa.Table) -> np.ndarray:
        return np.asarray(t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(t.num_rows, -1)

    def run(asked: pa.Table, rows: pa.Table) -> pa.Table:
        out = []
        if asked.num_rows and rows.num_rows:
            ids = rows.column("item_id").to_numpy()
            order = np.argsort(ids)
            ids, x = ids[order], matrix(rows)[order]
            forest = [grow(x, np.random.default_rng([seed, t]), choices=5 if trees > 1 else 1) for t in range(trees)]
            sub = rows.column("sub_id")[0].as_py()
            for qid, q in zip(asked.column("query_id").to_pylist(), matrix(asked), strict=True):
                got, scores, evals = search_trees(forest, x, ids, q, k, max_leaves)
                out += [(qid, sub, int(i), float(s), 0, evals) for i, s in zip(got, scores, strict=True)]
        names = ("query_id", "sub_id", "item_id", "score", "hops", "evals")
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64())
        columns = list(zip(*out, strict=True)) if out else [()] * 6
        return pa.table({n: pa.array(list(c), t) for n, c, t in zip(names, columns, kinds, strict=True)})

    asked = router.every_part(queries.select("query_id", F.col("vec").cast("array<double>").alias("vec")), w)
    return asked.groupBy("sub_id").cogroup(placed.groupBy("sub_id")).applyInArrow(run, search.PARTIAL_DDL)


def build(items: DataFrame, w: int, trees: int = 1, seed: int = 42) -> DataFrame:
    """``sub_id, tree_nodes``: the trees of every part, grown and counted."""
    placed = router.random_parts(items, w).select("sub_id", F.col("vec").cast("array<double>").alias("vec"))

    def run(rows: pa.Table) -> pa.Table:
        x = np.asarray(rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(rows.num_rows, -1)
        nodes = sum(len(grow(x, np.random.default_rng([seed, t]), choices=5 if trees > 1 else 1).axis) for t in range(trees))
        return pa.table({"sub_id": rows.column("sub_id").slice(0, 1).cast(pa.int32()), "tree_nodes": pa.array([nodes], pa.int64())})

    return placed.groupBy("sub_id").applyInArrow(run, "sub_id int, tree_nodes long")


def kd_route(items: DataFrame, depth: int, dimension: int) -> DataFrame:
    """``item_id, vec, sub_id``: the space cut by medians to ``2 ** depth`` cells, axes in turn.

    Each level is one aggregate of exact medians per cell, joined back as a small table.
    """
    out = items.select("item_id", F.col("vec").cast("array<double>").alias("vec"), F.lit(0).alias("sub_id"))
    for level in range(depth):
        axis = F.col("vec")[level % dimension]
        cuts = out.groupBy("sub_id").agg(F.percentile(axis, 0.5).alias("cut"))
        out = out.join(small(cuts), "sub_id").select("item_id", "vec", (F.col("sub_id") * 2 + (axis > F.col("cut")).cast("int")).cast("int").alias("sub_id"))
    return out
