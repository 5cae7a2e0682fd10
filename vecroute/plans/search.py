"""Sub-indexes: their graphs, searching them, and merging what they return."""

from __future__ import annotations

import functools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import kernels
from vecroute.graphs import hnsw
from vecroute.plans.router import top_rank
from vecroute.plans.sizes import query_blocks, small
from vecroute.runtime import ship

GRAPH_DDL = f"sub_id int, {hnsw.ROW_DDL}"
#: Items of a part, and queries that visit it, which a task of a scan holds at a time.
SCAN_ITEMS, SCAN_QUERIES = 1 << 17, 1 << 14


def build_all(placement: DataFrame, w: int, metric: str = "l2", degree: int = 16, degree0: int = 32, l: int = 100, seed: int = 42, builder: str = "insert") -> DataFrame:  # noqa: E741
    """One graph row per part, by insertion or with ``builder='bulk'`` from blocked neighbours.

    The exchange by part is the only one of the whole data set.
    """
    if builder not in ("insert", "bulk"):
        raise ValueError(f"no builder {builder!r}")

    def make(key: tuple, t: pa.Table) -> pa.Table:
        ids = t.column("item_id").to_numpy()
        x = np.asarray(t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(ids), -1)
        ids, first = np.unique(ids, return_index=True)
        x = x[first]
        graph = hnsw.build_bulk(ids, x, metric, degree, degree0, seed) if builder == "bulk" else hnsw.build(ids, x, metric, degree, degree0, l, seed)
        row = {"sub_id": key[0].as_py(), **hnsw.to_row(graph)}
        return pa.Table.from_pylist([row], schema=_arrow_schema())

    return placement.select("sub_id", "item_id", "vec").groupBy("sub_id").applyInArrow(make, GRAPH_DDL)


@functools.cache
def _arrow_schema() -> pa.Schema:
    level = pa.struct([("layer", pa.int32()), ("width", pa.int32()), ("nodes", pa.list_(pa.int32())), ("targets", pa.list_(pa.int32()))])
    return pa.schema([("sub_id", pa.int32()), ("entry", pa.int32()), ("metric", pa.string()), ("degree", pa.int32()), ("degree0", pa.int32()), ("n", pa.int32()), ("d", pa.int32()), ("item_ids", pa.list_(pa.int64())), ("vectors", pa.binary()), ("levels", pa.list_(level))])


PARTIAL_DDL = "query_id long, sub_id int, item_id long, score double, hops long, evals long"


def search_subs(routed: DataFrame, graphs: DataFrame, k: int, l: int = 100, max_evals: int | None = None, chunks: int = 1) -> DataFrame:  # noqa: E741
    """``query_id, sub_id, item_id, score, hops, evals``: the best ``k`` of each visited part.

    All queries of a part meet its graph in one task, which decodes the graph once.
    ``chunks`` splits the queries of every part over that many tasks.
    """
    asked = routed.select("query_id", "vec", "sub_id", F.pmod(F.xxhash64("query_id"), F.lit(chunks)).cast("int").alias("chunk"))
    index = graphs.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))))

    def run(queries: pa.Table, rows: pa.Table) -> pa.Table:
        out = {"query_id": [], "sub_id": [], "item_id": [], "score": [], "hops": [], "evals": []}
        if rows.num_rows and queries.num_rows:
            row = rows.slice(0, 1).to_pylist()[0]
            graph = hnsw.from_row(row)
            qid = queries.column("query_id").to_numpy()
            q = np.asarray(queries.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(qid), -1)
            ids, scores, stats = hnsw.search(graph, q, k, l, max_evals)
            good = ids >= 0
            at, _ = np.nonzero(good)
            out = {"query_id": qid[at], "sub_id": np.full(at.size, row["sub_id"], np.int32), "item_id": ids[good], "score": scores[good], "hops": stats.hops[at], "evals": stats.evals[at]}
        return pa.table({n: pa.array(v, t) for (n, v), t in zip(out.items(), (pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64()), strict=True)})

    return asked.groupBy("sub_id", "chunk").cogroup(index.groupBy("sub_id", "chunk")).applyInArrow(run, PARTIAL_DDL)


def _matrix(t: pa.Table) -> np.ndarray:
    return np.asarray(t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(t.num_rows, -1)


def scan_subs(routed: DataFrame, placement: DataFrame, k: int, metric: str = "l2", scan_items: int = SCAN_ITEMS, scan_queries: int = SCAN_QUERIES) -> DataFrame:
    """The same by scoring every item of the visited parts: routing loss without graph loss."""
    found = _scan(routed, placement, lambda q, x, ids: kernels.best_pairs(q, x, ids, k, metric), scan_items, scan_queries)
    return top_rank(found.withColumn("qs", F.struct("query_id", "sub_id")), "qs", k).drop("qs", "rank")


def radius_subs(routed: DataFrame, placement: DataFrame, least: float, metric: str = "l2", scan_items: int = SCAN_ITEMS, scan_queries: int = SCAN_QUERIES) -> DataFrame:
    """``query_id, sub_id, item_id, score`` of every item of the visited parts whose similarity is ``least`` or more; nothing is cut."""
    return _scan(routed, placement, lambda q, x, ids: kernels.pairs_from(q, x, ids, least, metric), scan_items, scan_queries)


def _scan(routed: DataFrame, placement: DataFrame, pick: Callable[[np.ndarray, np.ndarray, np.ndarray], tuple], scan_items: int, scan_queries: int) -> DataFrame:
    """``query_id, sub_id, item_id, score`` of what ``pick(queries, items, ids)`` takes of each part.

    Queries and items of a part meet once, in blocked matrix products. A part of many
    items or queries is dealt to as many tasks as its counts ask for.
    """
    ship(placement.sparkSession)
    items = placement.groupBy("sub_id").agg(F.count(F.lit(1)).alias("n")).select("sub_id", F.ceil(F.col("n") / scan_items).cast("int").alias("item_chunks"))
    asked = routed.groupBy("sub_id").agg(F.count(F.lit(1)).alias("n")).select("sub_id", F.ceil(F.col("n") / scan_queries).cast("int").alias("query_chunks"))
    plan = small(items.join(asked, "sub_id"))
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    mine = lambda key, c: F.pmod(F.xxhash64(key), F.col(c)).cast("int")
    own = F.col("sub_id").alias("sub_id")  # both sides may take parts from one table
    left = routed.select("query_id", F.col("vec").cast("array<double>").alias("vec"), "sub_id").join(plan, "sub_id").select("query_id", "vec", own, mine("query_id", "query_chunks").alias("qc"), every("item_chunks").alias("ic"))
    right = placement.select("sub_id", "item_id", F.col("vec").cast("array<double>").alias("vec")).join(plan, "sub_id").select(own, "item_id", "vec", mine("item_id", "item_chunks").alias("ic"), every("query_chunks").alias("qc"))

    def run(queries: pa.Table, rows: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if queries.num_rows and rows.num_rows:
            qid, q = queries.column("query_id").to_numpy(), _matrix(queries)
            ids, x = rows.column("item_id").to_numpy(), _matrix(rows)
            step = max(1, (1 << 24) // len(ids))
            for at in range(0, len(qid), step):
                row, found, scores = pick(q[at : at + step], x, ids)
                out.append((qid[at + row], found, scores))
        parts = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        sub = queries.column("sub_id")[0].as_py() if queries.num_rows else 0
        return pa.table({"query_id": pa.array(parts[0], pa.int64()), "sub_id": pa.array(np.full(len(parts[0]), sub, np.int32)), "item_id": pa.array(parts[1], pa.int64()), "score": pa.array(parts[2], pa.float64())})

    keys = ["sub_id", "ic", "qc"]
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "query_id long, sub_id int, item_id long, score double")


def merge_top_k(partials: DataFrame, k: int) -> DataFrame:
    """``query_id, rank, item_id, score``: copies count once, then the best ``k``."""
    once = partials.groupBy("query_id", "item_id").agg(F.max("score").alias("score"))
    return top_rank(once, "query_id", k).select("query_id", "rank", "item_id", "score")


def as_lists(result: DataFrame) -> DataFrame:
    """One row per query with its ranked answers."""
    return result.groupBy("query_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("rank", "item_id", "score"))), lambda s: F.struct(s["item_id"].alias("item_id"), s["score"].alias("score"))).alias("answers"))


def exact_topk(queries: DataFrame, items: DataFrame, k: int, metric: str = "l2", exclude_self: bool = False) -> DataFrame:
    """The linear scan: the truth that measures refer to. Pairs are never rows of a plan; only the best are."""
    return exact_topk_blocks(queries, items, k, metric, exclude_self)


def exact_within(queries: DataFrame, items: DataFrame, least: float, metric: str = "l2") -> DataFrame:
    """``query_id, item_id, score`` of all pairs whose similarity is ``least`` or more, by matrix products; nothing is cut."""
    ship(items.sparkSession)
    return functools.reduce(DataFrame.unionByName, [_within_pass(block, items, least, metric) for block in query_blocks(queries)])


def _sent(queries: DataFrame):
    """The ids and vectors of a query block, broadcast."""
    rows = queries.select(F.col("query_id").cast("long").alias("query_id"), F.col("vec").cast("array<double>").alias("vec")).orderBy("query_id").toArrow()
    qid = rows.column("query_id").to_numpy()
    return queries.sparkSession.sparkContext.broadcast((qid, _matrix(rows) if len(qid) else np.zeros((0, 1))))


def _within_pass(queries: DataFrame, items: DataFrame, least: float, metric: str) -> DataFrame:
    shared = _sent(queries)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = shared.value
        for whole in batches:
            for at in range(0, whole.num_rows if len(qid) else 0, 2048):
                b = whole.slice(at, 2048)
                ids = b.column(0).to_numpy()
                x = np.asarray(b.column(1).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(ids), -1)
                for a in range(0, len(qid), 1024):
                    row, found, s = kernels.pairs_from(q[a : a + 1024], x, ids, least, metric)
                    yield pa.RecordBatch.from_arrays([pa.array(qid[row + a]), pa.array(found), pa.array(s)], ["query_id", "item_id", "score"])

    return items.select(F.col("item_id").cast("long").alias("item_id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "query_id long, item_id long, score double")


def exact_topk_blocks(queries: DataFrame, items: DataFrame, k: int, metric: str = "l2", exclude_self: bool = False) -> DataFrame:
    """The linear scan by matrix products: each item batch keeps its best ``k`` per query.

    Queries are sent to the items, in as many passes as the bound of a broadcast asks for.
    """
    ship(items.sparkSession)
    passes = [_scan_pass(block, items, k, metric, exclude_self) for block in query_blocks(queries)]
    out = passes[0]
    for p in passes[1:]:
        out = out.unionByName(p)
    return out


def _scan_pass(queries: DataFrame, items: DataFrame, k: int, metric: str, exclude_self: bool) -> DataFrame:
    shared = _sent(queries)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = shared.value
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def reduced() -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
            row, ids, s = (np.concatenate(c) for c in zip(*held, strict=True))
            order = np.lexsort((ids, -s, row))
            row, ids, s = row[order], ids[order], s[order]
            keep = np.arange(row.size) - np.searchsorted(row, row, "left") < k
            return [(row[keep], ids[keep], s[keep])]

        for whole in batches:
            for at in range(0, whole.num_rows if len(qid) else 0, 8192):
                b = whole.slice(at, 8192)
                ids = b.column(0).to_numpy()
                x = np.asarray(b.column(1).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(ids), -1)
                for a in range(0, len(qid), 1024):
                    skip = qid[a : a + 1024][:, None] == ids[None, :] if exclude_self else None
                    row, found, s = kernels.best_pairs(q[a : a + 1024], x, ids, k, metric, skip)
                    held.append((row + a, found, s))
                if sum(len(h[0]) for h in held) > 8 * k * len(qid):
                    held = reduced()
        if held:
            row, ids, s = reduced()[0]
            yield pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array(ids), pa.array(s)], ["query_id", "item_id", "score"])

    partial = items.select(F.col("item_id").cast("long").alias("item_id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, "query_id long, item_id long, score double")
    return top_rank(partial, "query_id", k).select("query_id", "rank", "item_id", "score")
