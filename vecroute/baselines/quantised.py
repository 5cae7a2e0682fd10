"""Compressed search: product quantisation, a learned rotation, re-ranking, and inverted lists."""

from __future__ import annotations

import functools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import kernels, vectors
from vecroute.plans import centers as center_plans
from vecroute.plans.router import nearest_centers, top_rank
from vecroute.plans.sizes import query_blocks


def _lloyd(x: np.ndarray, k: int, rng: np.random.Generator, iters: int) -> tuple[np.ndarray, np.ndarray]:
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(iters):
        at = kernels.rank_matrix(x, c, "l2").argmax(axis=1)
        for j in np.unique(at):
            c[j] = x[at == j].mean(axis=0)
    return c, kernels.rank_matrix(x, c, "l2").argmax(axis=1)


@dataclass
class Quantiser:
    books: np.ndarray  # sub-space, code, width
    rotation: np.ndarray

    def encode(self, x: np.ndarray) -> np.ndarray:
        parts = np.split(x @ self.rotation, len(self.books), axis=1)
        return np.stack([kernels.rank_matrix(p, b, "l2").argmax(axis=1) for p, b in zip(parts, self.books, strict=True)], axis=1).astype(np.uint8)

    def decode(self, code: np.ndarray) -> np.ndarray:
        return np.concatenate([b[code[:, j]] for j, b in enumerate(self.books)], axis=1) @ self.rotation.T

    def scores(self, q: np.ndarray, code: np.ndarray, metric: str) -> np.ndarray:
        """Asymmetric scores by one table look-up per sub-space."""
        parts = np.split(q @ self.rotation, len(self.books), axis=1)
        total = np.zeros((len(q), len(code)))
        for j, (p, b) in enumerate(zip(parts, self.books, strict=True)):
            table = p @ b.T if metric != "l2" else -((p[:, None, :] - b[None]) ** 2).sum(axis=2)
            total += table[:, code[:, j]]
        return -np.sqrt(np.maximum(-total, 0)) if metric == "l2" else total


def fit(sample: np.ndarray, codebooks: int = 8, codes: int = 256, rotate: bool = False, iters: int = 10, seed: int = 42) -> Quantiser:
    """Codebooks from a sample; ``rotate`` alternates them with an orthogonal Procrustes step."""
    rng = np.random.default_rng(seed)
    d = sample.shape[1]
    if d % codebooks:
        raise ValueError("codebooks divide the dimension")
    codes = min(codes, max(2, len(sample) // 4))
    rotation = np.eye(d)
    for _ in range(6 if rotate else 1):
        parts = np.split(sample @ rotation, codebooks, axis=1)
        books = np.stack([_lloyd(p, codes, rng, iters)[0] for p in parts])
        q = Quantiser(books, rotation)
        if rotate:
            coded = q.encode(sample)
            u, _, vt = np.linalg.svd(sample.T @ np.concatenate([b[coded[:, j]] for j, b in enumerate(books)], axis=1))
            rotation = u @ vt
    return q


def fit_items(items: DataFrame, codebooks: int = 8, rotate: bool = False, sample: int = 20_000, seed: int = 42) -> Quantiser:
    """Fitted on at most ``sample`` items, the first by hash."""
    rows = items.select("vec", F.xxhash64("item_id", F.lit(seed)).alias("h")).orderBy("h").limit(sample).select("vec").toArrow()
    x = np.asarray(rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(rows.num_rows, -1)
    return fit(x, codebooks, rotate=rotate, seed=seed)


def ask(items: DataFrame, queries: DataFrame, quantiser: Quantiser, k: int, metric: str = "l2", rerank: int = 0) -> DataFrame:
    """``query_id, rank, item_id, score`` by compressed scores; ``rerank`` of them are scored again on raw vectors."""
    blocks = query_blocks(queries)
    if len(blocks) > 1:
        out = [ask(items, b, quantiser, k, metric, rerank) for b in blocks]
        return functools.reduce(DataFrame.unionByName, out)
    rows = queries.select("query_id", F.col("vec").cast("array<double>").alias("vec")).orderBy("query_id").toArrow()
    qid = rows.column("query_id").to_numpy()
    q = np.asarray(rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(qid), -1)
    shared = items.sparkSession.sparkContext.broadcast((quantiser, qid, q))
    depth = max(k, rerank)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pq, qid, q = shared.value
        best_ids, best = np.zeros((len(qid), 0), np.int64), np.zeros((len(qid), 0))
        for whole in batches:
            for s in range(0, whole.num_rows if len(qid) else 0, 4096):
                b = whole.slice(s, 4096)
                x = np.asarray(b.column(1).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(b.num_rows, -1)
                code, item = pq.encode(x), b.column(0).to_numpy()
                found = [kernels.top_k(pq.scores(q[a : a + 512], code, metric), item, depth) for a in range(0, len(qid), 512)]
                ids = np.concatenate([best_ids, np.concatenate([f[0] for f in found])], axis=1)
                scores = np.concatenate([best, np.concatenate([f[1] for f in found])], axis=1)
                order = np.lexsort((ids, -scores), axis=1)[:, :depth]
                best_ids, best = np.take_along_axis(ids, order, 1), np.take_along_axis(scores, order, 1)
        if best.size:
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qid, best.shape[1])), pa.array(best_ids.reshape(-1)), pa.array(best.reshape(-1))], ["query_id", "item_id", "score"])

    partial = items.select("item_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "query_id long, item_id long, score double")
    best = top_rank(partial, "query_id", depth)
    if rerank:
        again = best.select("query_id", "item_id").join(items.select("item_id", "vec"), "item_id").join(queries.select("query_id", F.col("vec").alias("q")), "query_id")
        best = top_rank(again.select("query_id", "item_id", vectors.score(F.col("q"), F.col("vec"), metric).alias("score")), "query_id", k)
    return best.where(F.col("rank") <= k).select("query_id", "rank", "item_id", "score")


def ivf(items: DataFrame, queries: DataFrame, centers: DataFrame, nprobe: int, k: int, metric: str = "l2") -> DataFrame:
    """Inverted lists: items under their nearest centre, queries look into ``nprobe`` lists."""
    lists = center_plans.nearest(items, centers, metric)
    probes = nearest_centers(queries, centers, nprobe, metric).select("query_id", F.col("vec").alias("q"), "center_id")
    scored = probes.join(lists, "center_id").select("query_id", "item_id", vectors.score(F.col("q"), F.col("vec"), metric).alias("score"))
    return top_rank(scored, "query_id", k).select("query_id", "rank", "item_id", "score")
