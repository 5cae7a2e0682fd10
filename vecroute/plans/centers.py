"""Routing centres: k-means in several forms, and their weights."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecroute.functions import kernels, vectors

SCHEMA = "center_id int, vec array<double>, weight double"


def as_frame(spark: SparkSession, centers: np.ndarray, weight: np.ndarray | None = None) -> DataFrame:
    weight = np.ones(len(centers)) if weight is None else weight
    return spark.createDataFrame([(i, [float(v) for v in c], float(w)) for i, (c, w) in enumerate(zip(centers, weight, strict=True))], SCHEMA)


def as_matrix(centers: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors) of a centre table; its rows are bounded by the parameter ``m``."""
    rows = centers.select("center_id", "vec").orderBy("center_id").collect()
    return np.array([r.center_id for r in rows], np.int64), np.array([r.vec for r in rows], np.float64).reshape(len(rows), -1)


def kmeans(sample: DataFrame, m: int, iters: int = 10, seed: int = 42, spherical: bool = False) -> DataFrame:
    """``m`` centres by k-means||; ``spherical`` keeps them at unit length for inner product."""
    features = sample.select(array_to_vector(F.col("vec").cast("array<double>")).alias("features"))
    if spherical:
        features = sample.select(array_to_vector(vectors.normalise(F.col("vec"))).alias("features"), vectors.norm(F.col("vec")).alias("n")).where("n > 0").drop("n")
    model = KMeans(k=m, maxIter=iters, seed=seed, distanceMeasure="cosine" if spherical else "euclidean").fit(features)
    found = np.array(model.clusterCenters())
    return as_frame(sample.sparkSession, kernels.unit(found) if spherical else found)


def spherical(sample: DataFrame, m: int, iters: int = 10, seed: int = 42) -> DataFrame:
    return kmeans(sample, m, iters, seed, spherical=True)


def sampled(items: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """Items taken as centres: the alternative that k-means is compared with."""
    key = F.xxhash64("item_id", F.lit(seed))
    rows = items.select("item_id", F.col("vec").cast("array<double>").alias("vec"), key.alias("h")).orderBy("h", "item_id").limit(m)
    number = (F.row_number().over(Window.orderBy("item_id")) - 1).cast("int")  # of m rows
    return rows.select(number.alias("center_id"), "vec", F.lit(1.0).alias("weight"))


def lloyd_step(items: DataFrame, centers: DataFrame, metric: str = "l2") -> DataFrame:
    """One assignment and averaging in DataFrame operations: ``center_id, vec, weight``.

    Centres are broadcast; sums go out as one row per centre, not per component.
    Centres without items stay where they are.
    """
    near = nearest(items, centers, metric)
    parts = near.select("center_id", F.posexplode(vectors.doubles(F.col("vec"))).alias("i", "v")).groupBy("center_id", "i").agg(F.avg("v").alias("v"), F.count(F.lit(1)).alias("n"))
    moved = parts.groupBy("center_id").agg(F.sort_array(F.collect_list(F.struct("i", "v"))).alias("a"), F.max("n").alias("n"))
    moved = moved.select("center_id", F.transform("a", lambda s: s["v"]).alias("moved"), "n")
    out = centers.select("center_id", "vec").join(moved, "center_id", "left")
    vec = F.coalesce("moved", vectors.doubles(F.col("vec")))
    return out.select("center_id", (vectors.normalise(vec) if metric != "l2" else vec).alias("vec"), F.coalesce("n", F.lit(0)).cast("double").alias("weight"))


def nearest(items: DataFrame, centers: DataFrame, metric: str = "l2") -> DataFrame:
    """``item_id, vec, center_id``: the best centre of each item, ties to the smaller id."""
    from vecroute.plans.router import nearest_centers

    found = nearest_centers(items.select(F.col("item_id").alias("query_id"), "vec"), centers, 1, metric)
    return found.select(F.col("query_id").alias("item_id"), "vec", "center_id")


def hierarchical(sample: DataFrame, m1: int, m2: int, iters: int = 8, seed: int = 42) -> DataFrame:
    """Two levels: ``m1`` branches, then up to ``m2`` centres in each, every branch in a task of its own.

    Branch samples are bounded by ``256 * m2`` rows by hash, so no branch outgrows its task.
    """
    top = kmeans(sample, m1, iters, seed)
    _, matrix = as_matrix(top)
    shared = sample.sparkSession.sparkContext.broadcast(matrix)

    def route(batches):
        for b in batches:
            x = np.array(b.column(1).to_pylist(), np.float64)
            at = kernels.rank_matrix(x, shared.value, "l2").argmax(axis=1) if len(x) else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), b.column(0), b.column(1)], ["branch", "item_id", "vec"])

    routed = sample.select("item_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(route, "branch int, item_id long, vec array<double>")
    rank = F.row_number().over(Window.partitionBy("branch").orderBy(F.xxhash64("item_id", F.lit(seed))))
    bounded = routed.withColumn("r", rank).where(F.col("r") <= 256 * m2).drop("r")

    def split(key: tuple, t: pa.Table) -> pa.Table:
        x = np.array(t.column("vec").to_pylist(), np.float64)
        c = x[np.argsort(t.column("item_id").to_numpy())][:: max(1, len(x) // m2)][:m2].copy()
        for _ in range(iters):
            at = kernels.rank_matrix(x, c, "l2").argmax(axis=1)
            for j in np.unique(at):
                c[j] = x[at == j].mean(axis=0)
        count = np.bincount(at, minlength=len(c)).astype(float)
        return pa.table({"branch": pa.array([key[0].as_py()] * len(c), pa.int32()), "local": pa.array(range(len(c)), pa.int32()), "vec": pa.array(c.tolist(), pa.list_(pa.float64())), "weight": pa.array(count)})

    local = bounded.groupBy("branch").applyInArrow(split, "branch int, local int, vec array<double>, weight double")
    return local.select((F.col("branch") * m2 + F.col("local")).cast("int").alias("center_id"), "vec", "weight", "branch")


def weight_by_count(sample: DataFrame, centers: DataFrame, metric: str = "l2") -> DataFrame:
    """Members in the sample; centres without any keep weight 0."""
    n = nearest(sample, centers, metric).groupBy("center_id").agg(F.count(F.lit(1)).cast("double").alias("weight"))
    return centers.drop("weight").join(n, "center_id", "left").select("center_id", "vec", F.coalesce("weight", F.lit(0.0)).alias("weight"))


def weight_by_queries(queries: DataFrame, centers: DataFrame, k: int, metric: str = "l2", smoothing: float = 1.0) -> DataFrame:
    """How often a centre is among the ``k`` best of sample queries, plus ``smoothing``.

    A column ``n`` of ``queries`` says how often each was asked; without it, once.
    """
    from vecroute.plans.router import nearest_centers

    near = nearest_centers(queries, centers, k, metric).select("query_id", "center_id")
    if "n" in queries.columns:
        near = near.join(queries.select("query_id", "n"), "query_id")
    asked = F.sum("n") if "n" in queries.columns else F.count(F.lit(1))
    n = near.groupBy("center_id").agg(asked.cast("double").alias("hits"))
    return centers.drop("weight").join(n, "center_id", "left").select("center_id", "vec", (F.coalesce("hits", F.lit(0.0)) + smoothing).alias("weight"))
