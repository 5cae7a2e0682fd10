"""Which parts a query visits, and which part an item is put into."""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecroute.functions import kernels
from vecroute.graphs import hnsw
from vecroute.plans.sizes import query_blocks, small
from vecroute.runtime import ship


def nearest_centers(queries: DataFrame, centers: DataFrame, branching: int, metric: str = "l2") -> DataFrame:
    """``query_id, vec, center_id, rank`` of the best centres, ties to the smaller id.

    Centres are sent to the queries, which are ranked where they lie, in as many passes
    as the bound of a broadcast asks for.
    """
    ship(queries.sparkSession)
    passes = [_centers_pass(queries, block, branching, metric) for block in query_blocks(centers.select(F.col("center_id").alias("query_id"), "vec"))]
    if len(passes) == 1:
        return passes[0].drop("score")
    whole = top_rank(functools.reduce(DataFrame.unionByName, passes).drop("rank"), "query_id", branching, tie="center_id")
    return whole.select("query_id", "vec", "center_id", F.col("rank").cast("int").alias("rank"))


def _centers_pass(queries: DataFrame, centers: DataFrame, branching: int, metric: str) -> DataFrame:
    rows = centers.select("query_id", F.col("vec").cast("array<double>").alias("vec")).orderBy("query_id").toArrow()
    ids = rows.column("query_id").to_numpy().astype(np.int64)
    shared = queries.sparkSession.sparkContext.broadcast((ids, _matrix(rows.column("vec").combine_chunks()) if len(ids) else np.zeros((0, 1))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, c = shared.value
        for whole in batches:
            for s in range(0, whole.num_rows if len(ids) else 0, 1024):
                b = whole.slice(s, 1024)
                q = _matrix(b.column(1))
                at = kernels.best_columns(q, c, branching, metric)
                row, place = np.nonzero(at >= 0)
                col, take = at[row, place], pa.array(row)
                score = kernels.pair_scores(q, c, row, col, metric)
                yield pa.RecordBatch.from_arrays([b.column(0).take(take), b.column(1).take(take), pa.array(ids[col].astype(np.int32)), pa.array((place + 1).astype(np.int32)), pa.array(score)], ["query_id", "vec", "center_id", "rank", "score"])

    return queries.select(F.col("query_id").cast("long").alias("query_id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "query_id long, vec array<double>, center_id int, rank int, score double")


def route_sql(queries: DataFrame, centers: DataFrame, branching: int, metric: str = "l2") -> DataFrame:
    """``query_id, sub_id``: the distinct parts of the ``branching`` best centres."""
    found = nearest_centers(queries, centers.select("center_id", "vec"), branching, metric)
    return found.join(small(centers.select("center_id", "sub_id")), "center_id").select("query_id", "sub_id").distinct()


class MetaIndex:
    """The routing graph over centres with the part of each; small, and broadcast."""

    def __init__(self, ids: np.ndarray, matrix: np.ndarray, sub_of: np.ndarray, metric: str, degree: int = 16, degree0: int = 32, l: int = 100, seed: int = 42, bulk: bool = False):  # noqa: E741
        self.metric, self.l = metric, l
        make = hnsw.build_bulk if bulk else hnsw.build
        extra = {} if make is hnsw.build_bulk else {"l": l}
        self.graph = make(ids, matrix, metric, degree=degree, degree0=degree0, seed=seed, **extra)
        order = np.argsort(ids, kind="stable")
        self.ids, self.matrix, self.sub_of = ids[order], kernels.prepared(matrix[order], metric), sub_of[order]

    @property
    def bytes(self) -> int:
        return self.matrix.nbytes * 2 + sum(y.links.nbytes for y in self.graph.layers)

    def rank(self, q: np.ndarray, k: int, mode: str) -> np.ndarray:
        """Positions of the ``k`` best centres per row, padded with -1."""
        if mode == "graph":
            found, _, _ = hnsw.search(self.graph, q, k, max(self.l, k) if k > 1 else self.l)
            return np.where(found >= 0, np.searchsorted(self.ids, found), -1)
        return kernels.best_columns(q, self.matrix, k, self.metric)


#: A broadcast larger than this is refused: go to two levels of centres instead.
MAX_META_BYTES = 512 << 20


def share(items: DataFrame, meta: MetaIndex):
    if meta.bytes > MAX_META_BYTES:
        raise ValueError(f"a routing graph of {meta.bytes} bytes is too large to broadcast; use hierarchical centres")
    return items.sparkSession.sparkContext.broadcast(meta)


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return np.asarray(flat, np.float64).reshape(len(column), -1)


def route(queries: DataFrame, meta: MetaIndex, branching: int, mode: str = "graph", keep_rank: bool = False) -> DataFrame:
    """``query_id, vec, sub_id`` (and the best ``rank`` of a centre of that part), one row per part visited.

    With ``keep_rank`` one routing pass serves every smaller branching factor: a
    part is visited at K if its rank is at most K.
    """
    shared = share(queries, meta)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            at = m.rank(_matrix(b.column(1)), min(branching, len(m.ids)), mode)
            subs = np.where(at >= 0, m.sub_of[np.maximum(at, 0)], -1)
            first = subs >= 0
            for j in range(1, subs.shape[1]):
                first[:, j] &= ~(subs[:, :j] == subs[:, j : j + 1]).any(axis=1)
            row, col = np.nonzero(first)
            take = pa.array(row)
            yield pa.RecordBatch.from_arrays([b.column(0).take(take), b.column(1).take(take), pa.array(subs[row, col].astype(np.int32)), pa.array((col + 1).astype(np.int32))], ["query_id", "vec", "sub_id", "rank"])

    out = queries.select("query_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "query_id long, vec array<double>, sub_id int, rank int")
    return out if keep_rank else out.drop("rank")


def assign(items: DataFrame, meta: MetaIndex, mode: str = "graph", copies: int = 1) -> DataFrame:
    """``sub_id, item_id, vec, via``: the part of the nearest centre, or of the ``copies`` nearest parts.

    Routing needs no exchange. ``mode='graph'`` walks the routing graph; ``'exact'``
    scores a block against all centres in one matrix product.
    """
    shared = share(items, meta)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for whole in batches:
            for s in range(0, whole.num_rows, 1024):
                b = whole.slice(s, 1024)
                at = m.rank(_matrix(b.column(1)), 1 if copies == 1 else min(len(m.ids), 8 * copies), mode)
                subs = np.where(at >= 0, m.sub_of[np.maximum(at, 0)], -1)
                first = subs >= 0
                for j in range(1, subs.shape[1]):
                    first[:, j] &= ~(subs[:, :j] == subs[:, j : j + 1]).any(axis=1)
                first &= np.cumsum(first, axis=1) <= copies
                row, col = np.nonzero(first)
                take = pa.array(row)
                via = pa.array(np.where(col == 0, "primary", "copy").tolist(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(subs[row, col].astype(np.int32)), b.column(0).take(take), b.column(1).take(take), via], ["sub_id", "item_id", "vec", "via"])

    return items.select("item_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "sub_id int, item_id long, vec array<double>, via string")


def assign_sql(items: DataFrame, centers: DataFrame, metric: str = "l2") -> DataFrame:
    """The same placement as expressions: ``sub_id, item_id, vec, via``."""
    from vecroute.plans.centers import nearest

    near = nearest(items, centers, metric)
    return near.join(small(centers.select("center_id", "sub_id")), "center_id").select("sub_id", "item_id", "vec", F.lit("primary").alias("via"))


def random_parts(items: DataFrame, w: int) -> DataFrame:
    """The naive placement: parts by hash of the id."""
    return items.select(F.pmod(F.xxhash64("item_id"), F.lit(w)).cast("int").alias("sub_id"), "item_id", "vec", F.lit("primary").alias("via"))


def every_part(queries: DataFrame, w: int) -> DataFrame:
    """``query_id, vec, sub_id`` for a search of all parts."""
    return queries.select("query_id", "vec", F.explode(F.sequence(F.lit(0), F.lit(w - 1))).alias("sub_id"))


def top_rank(df: DataFrame, by: str, k: int, score: str = "score", tie: str = "item_id") -> DataFrame:
    """Best ``k`` rows per key with their ``rank``; Spark cuts to ``k`` before the exchange too."""
    w = Window.partitionBy(by).orderBy(F.col(score).desc(), tie)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
