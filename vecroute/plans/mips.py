"""Indexing for inner product: unit centres, and copies of strong items in every part that wants them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import vectors
from vecroute.plans.router import MetaIndex, share, top_rank
from vecroute.plans.sizes import small

#: One in so many items sets the floor of a centre's replicas.
FLOOR_SHARE = 64


def replicate_sql(items: DataFrame, centers: DataFrame, r: int) -> DataFrame:
    """``sub_id, item_id, vec, via``: the ``r`` items of largest inner product with each centre, in that centre's part."""
    from vecroute.plans.search import exact_topk

    found = exact_topk(centers.select(F.col("center_id").cast("long").alias("query_id"), "vec"), items, r, "ip")
    parts = centers.select(F.col("center_id").cast("long").alias("query_id"), "sub_id")
    return _with_vectors(found.join(small(parts), "query_id").select("sub_id", "item_id").distinct(), items)


def _with_vectors(chosen: DataFrame, items: DataFrame) -> DataFrame:
    return chosen.join(items.select("item_id", "vec"), "item_id").select("sub_id", "item_id", "vec", F.lit("replica").alias("via"))


def replicate(items: DataFrame, meta: MetaIndex, r: int, mode: str = "exact", top_share: float = 0.05, tables: int = 8, bits: int = 6, seed: int = 42) -> DataFrame:
    """The same by matrix products; a partition hands on its best ``r`` per centre above a floor that a sample gives.

    ``mode='norm_top'`` scores only the items of largest norm (``top_share`` of all),
    which hold nearly all results when norms vary; ``'lsh'`` scores items that share a
    sign code with the centre in some table.
    """
    if r == 0:
        return items.select(F.lit(0).alias("sub_id"), "item_id", "vec", F.lit("replica").alias("via")).where("false")
    pool = items.select("item_id", F.col("vec").cast("array<double>").alias("vec"))
    if mode == "norm_top":
        least = pool.select(vectors.norm(F.col("vec")).alias("n")).agg(F.percentile_approx("n", 1 - top_share, 10_000)).first()[0]
        pool = pool.where(vectors.norm(F.col("vec")) >= F.lit(least))
    shared = share(items, meta)

    def scan(rows: DataFrame, floor: np.ndarray) -> DataFrame:
        """Best ``r`` per centre of each partition, of scores that reach the centre's floor."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m = shared.value
            least = floor.copy()
            planes = np.random.default_rng(seed).standard_normal((tables * bits, m.matrix.shape[1]))
            code = lambda x: ((x @ planes.T > 0).reshape(len(x), tables, bits) * (1 << np.arange(bits))).sum(axis=2)
            own = code(m.matrix) if mode == "lsh" else None
            held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
            size = 0

            def reduced() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
                c, ids, s = (np.concatenate(z) for z in zip(*held, strict=True))
                order = np.lexsort((ids, -s, c))
                c, ids, s = c[order], ids[order], s[order]
                place = np.arange(c.size) - np.searchsorted(c, c, "left")
                last = place == r - 1
                least[c[last]] = s[last]
                return c[place < r], ids[place < r], s[place < r]

            for whole in batches:
                for at in range(0, whole.num_rows, 2048):
                    b = whole.slice(at, 2048)
                    ids = b.column(0).to_numpy()
                    x = np.asarray(b.column(1).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(ids), -1)
                    g = m.matrix @ x.T
                    if own is not None:
                        g = np.where((own[:, None, :] == code(x)[None, :, :]).any(axis=2), g, -np.inf)
                    if len(ids) > r:
                        # Of a block at most the best r of a centre, and their ties.
                        least_here = np.partition(g, len(ids) - r, axis=1)[:, len(ids) - r]
                        c, i = np.nonzero((g >= np.maximum(least, least_here)[:, None]) & np.isfinite(g))
                    else:
                        c, i = np.nonzero((g >= least[:, None]) & np.isfinite(g))
                    held.append((c, ids[i], g[c, i]))
                    size += c.size
                    if size > 4 * r * len(m.ids):
                        held = [reduced()]
                        size = held[0][0].size
            if held:
                c, ids, s = reduced()
                yield pa.RecordBatch.from_arrays([pa.array(m.ids[c].astype(np.int32)), pa.array(m.sub_of[c].astype(np.int32)), pa.array(ids), pa.array(s)], ["center_id", "sub_id", "item_id", "score"])

        return rows.mapInArrow(run, "center_id int, sub_id int, item_id long, score double")

    # The r-th best of a sample is a floor for the r-th best of all, so partitions hand on few rows that cannot win.
    n = len(meta.ids)
    sample = pool.where(F.pmod(F.xxhash64("item_id"), F.lit(FLOOR_SHARE)) == 0).coalesce(8)
    lowest = top_rank(scan(sample, np.full(n, -np.inf)), "center_id", r).groupBy("center_id").agg(F.count(F.lit(1)).alias("n"), F.min("score").alias("s")).where(F.col("n") == r).collect()
    floor = np.full(n, -np.inf)
    if lowest:
        floor[np.searchsorted(meta.ids, [row.center_id for row in lowest])] = [row.s - 1e-9 * (1 + abs(row.s)) for row in lowest]
    best = top_rank(scan(pool, floor), "center_id", r)
    return _with_vectors(best.select("sub_id", "item_id").distinct(), items)


def union_placement(primary: DataFrame, replicas: DataFrame) -> DataFrame:
    """Both, each item once per part; the primary row wins.

    Only keys of the placed rows are looked up, so their vectors stay where they are.
    """
    key = ["sub_id", "item_id"]
    there = primary.select(*key).join(replicas.select(*key), key, "left_semi")
    more = replicas.join(there, key, "left_anti")
    return primary.select("sub_id", "item_id", "vec", "via").unionByName(more.select("sub_id", "item_id", "vec", "via"))


def augment(items: DataFrame, largest: float | None = None) -> DataFrame:
    """Items with one more coordinate that makes all norms equal, so L2 ranks as inner product does."""
    if largest is None:
        largest = items.select(F.max(vectors.dot(F.col("vec"), F.col("vec")))).first()[0] or 0.0
    extra = F.sqrt(F.greatest(F.lit(float(largest)) - vectors.dot(F.col("vec"), F.col("vec")), F.lit(0.0)))
    return items.select("item_id", F.concat(vectors.doubles(F.col("vec")), F.array(extra)).alias("vec"))


def augment_queries(queries: DataFrame) -> DataFrame:
    return queries.select("query_id", F.concat(vectors.doubles(F.col("vec")), F.array(F.lit(0.0))).alias("vec"))
