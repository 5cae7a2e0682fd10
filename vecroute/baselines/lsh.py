"""Locality-sensitive hashing: sign codes for cosine and inner product, random projections for L2."""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecroute.functions import kernels, vectors
from vecroute.plans import mips
from vecroute.plans.router import top_rank
from vecroute.plans.sizes import query_blocks
from vecroute.runtime import ship


def planes(dimension: int, tables: int, bits: int, seed: int = 42) -> np.ndarray:
    """Hyperplanes rounded to 4 digits, so they can be written into a query as they are."""
    return np.round(np.random.default_rng(seed).standard_normal((tables, bits, dimension)), 4)


def codes(vec: Column, p: np.ndarray) -> Column:
    """One sign code per table, as an array of longs."""
    def bit(row: np.ndarray, at: int) -> Column:
        side = vectors.dot(vec, F.array(*[F.lit(float(v)) for v in row]))
        return F.when(side > 0, F.lit(1 << at)).otherwise(F.lit(0)).cast("long")

    return F.array(*[sum((bit(r, i) for i, r in enumerate(t)), F.lit(0).cast("long")) for t in p])


def sign_candidates(queries: DataFrame, items: DataFrame, p: np.ndarray) -> DataFrame:
    """``query_id, item_id`` pairs that share a code in some table: one equi-join on (table, code)."""
    a = queries.select("query_id", F.posexplode(codes(F.col("vec"), p)).alias("table", "code"))
    b = items.select("item_id", F.posexplode(codes(F.col("vec"), p)).alias("table", "code"))
    return a.join(b, ["table", "code"]).select("query_id", "item_id").distinct()


def sign_codes(rows: DataFrame, key: str, p: np.ndarray, keep: int) -> DataFrame:
    """``key, vec, code``: the sign codes of whole vectors by one matrix product; ``keep`` components of a vector are handed on."""
    tables, bits, _ = p.shape
    weights = 1 << np.arange(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column(1))
            code = ((x @ p.reshape(tables * bits, -1).T > 0).reshape(len(x), tables, bits) * weights).sum(axis=2)
            yield pa.RecordBatch.from_arrays([b.column(0), _lists(x[:, :keep], pa.float64()), _lists(code.astype(np.float64), pa.float64())], [key, "vec", "code"])

    return rows.select(F.col(key).cast("long").alias(key), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, f"{key} long, vec array<double>, code array<double>")


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def _lists(x: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(x.reshape(-1), kind))


def best_of_buckets(queries: DataFrame, items: DataFrame, k: int, metric: str, least: float = -np.inf) -> DataFrame:
    """``query_id, rank, item_id, score``: of the items that share a code with a query in some table, the best ``k`` above ``least``.

    Both tables have ``vec`` and ``code``, one number a table. Pairs of a bucket are looked
    at in blocks and are never rows, so that a large bucket costs no exchange.
    """
    ship(items.sparkSession)
    passes = [_bucket_pass(block, items, k, metric, least) for block in query_blocks(queries)]
    return top_rank(functools.reduce(DataFrame.unionByName, passes), "query_id", k).select("query_id", "rank", "item_id", "score")


def _bucket_pass(queries: DataFrame, items: DataFrame, k: int, metric: str, least: float) -> DataFrame:
    rows = queries.select("query_id", "vec", "code").orderBy("query_id").toArrow().combine_chunks()
    whole = lambda name: rows.column(name).combine_chunks()
    shared = items.sparkSession.sparkContext.broadcast((whole("query_id").to_numpy(), _matrix(whole("vec")), _matrix(whole("code"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q, q_code = shared.value
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        for whole in batches:
            for at in range(0, whole.num_rows if len(qid) else 0, 4096):
                b = whole.slice(at, 4096)
                ids, x, x_code = b.column(0).to_numpy(), _matrix(b.column(1)), _matrix(b.column(2))
                for s in range(0, len(qid), 1024):
                    apart = np.ones((len(q[s : s + 1024]), len(ids)), bool)
                    for j in range(x_code.shape[1]):
                        apart &= q_code[s : s + 1024, j][:, None] != x_code[:, j][None, :]
                    row, found, score = kernels.best_pairs(q[s : s + 1024], x, ids, k, metric, apart)
                    near = score > least
                    held.append((row[near] + s, found[near], score[near]))
                if sum(len(h[0]) for h in held) > 8 * k * len(qid):
                    held = [_reduced(held, k)]
        if held:
            row, ids, score = _reduced(held, k)
            yield pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array(ids), pa.array(score)], ["query_id", "item_id", "score"])

    return items.select("item_id", "vec", "code").mapInArrow(run, "query_id long, item_id long, score double")


def _reduced(held: list[tuple[np.ndarray, np.ndarray, np.ndarray]], k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    row, ids, score = (np.concatenate(c) for c in zip(*held, strict=True))
    order = np.lexsort((ids, -score, row))
    row, ids, score = row[order], ids[order], score[order]
    keep = np.arange(row.size) - np.searchsorted(row, row, "left") < k
    return row[keep], ids[keep], score[keep]


def ask(queries: DataFrame, items: DataFrame, k: int, metric: str = "cosine", tables: int = 8, bits: int = 6, seed: int = 42) -> DataFrame:
    """``query_id, rank, item_id, score``: candidates by code, ranked by the true score.

    Inner product hashes items augmented to equal norms, which is cosine again.
    """
    ship(items.sparkSession)
    d = keep = len(items.select("vec").first()[0])
    if metric == "ip":
        items, queries, d = mips.augment(items), mips.augment_queries(queries), d + 1
    p = planes(d, tables, bits, seed)
    return best_of_buckets(sign_codes(queries, "query_id", p, keep), sign_codes(items, "item_id", p, keep), k, metric)


def ask_l2(queries: DataFrame, items: DataFrame, k: int, threshold: float, bucket: float = 2.0, tables: int = 4, seed: int = 42) -> DataFrame:
    """L2 by bucketed random projections; partners not nearer than ``threshold`` are left out."""
    features = array_to_vector(F.col("vec").cast("array<double>")).alias("features")
    q, x = queries.select("query_id", "vec", features), items.select("item_id", "vec", features)
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=seed).fit(x)
    code = F.array(*[vector_to_array(F.col("hashes")[j])[0] for j in range(tables)])
    q, x = (model.transform(r).select(F.col(c).cast("long").alias(c), F.col("vec").cast("array<double>").alias("vec"), code.alias("code")) for r, c in ((q, "query_id"), (x, "item_id")))
    return best_of_buckets(q, x, k, "l2", -threshold)
