"""Embedding near-duplicates by collision-counting projections.

Vectors of unit length are projected onto many random directions and each projection
is sorted. A pair collides in a projection if one lies in the window centred on the
other; pairs that collide often enough are verified by their cosine in double
precision. Window width and count threshold are calibrated: for two vectors exactly
at the wanted cosine the difference of a Gaussian projection is normal with known
spread, so the count is binomial and its low quantile is the threshold.

Counting over all pairs would be quadratic whatever the window, as a projection's
window holds a fixed share of all vectors. So pairs are counted inside pools: cells
that further projections cut, each at the projection of the mean of all vectors, so
that a common offset of the vectors leaves the cells even. Each of ``tables``
independent pool sets catches a pair at the wanted cosine with known probability: it
follows from the angle at which the pair is seen from the mean, and is taken at a
low quantile (``NEAR_MEAN``) of the vectors' measured distance from it. Cuts and
tables are those of least cost for the wanted recall. Vectors nearer to the mean than
that quantile keep the same pools at a lower recall.

Vectors are first collapsed to classes of equal vectors. A pair of classes is counted
in the first table whose pool holds both, so no list of pairs is ever exchanged or
made distinct: tasks return, per class, its number of links and a forest that spans
them. What is exchanged, once a table, is the vector in its own type and a bit for
each cut; the vectors must travel, since a dense group has far more pairs than members.

Defined cases: null, empty, zero and non-finite vectors and those with null
components link with nothing and are components of their own; vectors of different
length are never compared; equal ids are separate rows that share a class only
if their vectors are equal; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecroute.llm.components import BLOCK, Forest, block_pairs, components, stream_groups
from vecroute.runtime import Workspace

COSINE = 0.95
RECALL = 0.9995
PROJECTIONS = 16
#: Window half-width in standard deviations of the difference at the wanted cosine.
WINDOW = 2.0
#: Comparisons that cost as much as one more row in a pool set.
POOL_ROWS = 1024
#: Share of the vectors that may lie nearer to the mean than the calibration takes.
NEAR_MEAN = 0.01
MOST_CUTS = 48
MOST_TABLES = 4096
SEED = 7


@dataclass(frozen=True)
class Plan:
    """What the number of classes, their spread and the wanted recall fix."""

    cosine: float
    meet: float
    cuts: int
    tables: int
    projections: int
    half_width: float
    least_count: int
    seed: int

    @property
    def expected_recall(self) -> float:
        return (1 - (1 - self.meet**self.cuts) ** self.tables) * (1 - _binomial_below(self.projections, 2 * NormalDist().cdf(WINDOW) - 1, self.least_count))


def _binomial_below(n: int, p: float, k: int) -> float:
    return sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k))


def calibrate(classes: int, cosine: float = COSINE, recall: float = RECALL, spread: float = 1.0, projections: int = PROJECTIONS, pool_rows: int = POOL_ROWS, seed: int = SEED) -> Plan:
    """Half of the allowed loss goes to the pools, half to the count threshold.

    ``spread`` is the squared distance of a vector from the mean: 1 for centred
    vectors of unit length.
    """
    loss = (1 - recall) / 2
    # Two vectors so far from the mean and at the wanted cosine: a cut through the mean parts them in proportion to their angle.
    angle = math.acos(max(-1.0, 1 - (1 - cosine) / max(spread, 1e-9)))
    meet = 1 - angle / math.pi
    best = None
    for cuts in range(MOST_CUTS + 1):
        together = meet**cuts
        tables = 1 if together >= 1 - loss else math.ceil(math.log(loss) / math.log1p(-together)) if together > 1e-12 else MOST_TABLES + 1
        if tables > MOST_TABLES:
            break
        cost = tables * (classes / 2**cuts + pool_rows)
        if best is None or cost < best[0]:
            best = cost, cuts, tables
    p = 2 * NormalDist().cdf(WINDOW) - 1
    least = max(k for k in range(projections + 1) if _binomial_below(projections, p, k) <= loss)
    return Plan(cosine, meet, best[1], best[2], projections, WINDOW * math.sqrt(2 - 2 * cosine), least, seed)


def stored(embedding: Column, kind: str) -> Column:
    """A vector's little-endian numbers; null for vectors that link with nothing."""

    def run(vectors: pa.Array) -> pa.Array:
        out: list[bytes | None] = []
        for v in vectors.to_pylist():
            x = np.array(v, kind) + 0 if v and None not in v else np.zeros(1, kind)
            out.append(x.tobytes() if np.isfinite(x).all() and x.any() else None)
        return pa.array(out, pa.binary())

    return F.arrow_udf(run, "binary")(embedding)


def _units(raw: list[bytes], kind: str) -> np.ndarray:
    """Rows of unit length in double precision, of vectors of equal length."""
    x = np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1).astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


@functools.lru_cache(maxsize=8)
def _directions(plan: Plan, d: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng([plan.seed, d])
    return rng.standard_normal((plan.tables * plan.cuts, d)), rng.standard_normal((plan.projections, d))


def _by_length(batches: Iterator[pa.RecordBatch], at_once: int = 2048) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Slices of the batches with vectors of one length, which the first column holds."""
    for whole in batches:
        for start in range(0, whole.num_rows, at_once):
            batch = whole.slice(start, at_once)
            raw = batch.column(0).to_pylist()
            sizes = np.array([len(b) for b in raw])
            for size in np.unique(sizes):
                at = np.flatnonzero(sizes == size)
                yield batch.take(pa.array(at)), [raw[i] for i in at]


def _mean_vectors(classes: DataFrame, kind: str) -> DataFrame:
    """``size, mean`` of the unit vectors of each length, from a sum per partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, list] = {}
        for _, raw in _by_length(batches):
            held = sums.setdefault(len(raw[0]), [0, 0.0])
            held[0] += len(raw)
            held[1] = held[1] + _units(raw, kind).sum(axis=0)
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([n for n, _ in sums.values()], pa.int64()), pa.array([x.tolist() for _, x in sums.values()], pa.list_(pa.float64()))], ["size", "n", "total"])

    parts = classes.select("raw").mapInArrow(run, "size int, n long, total array<double>")
    places = parts.select("size", "n", F.posexplode("total").alias("at", "x")).groupBy("size", "at").agg((F.sum("x") / F.sum("n")).alias("x"))
    return places.groupBy("size").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda p: p["x"]).alias("mean"))


def _spread(centred: DataFrame, kind: str) -> float:
    """A low quantile of the squared distances from the mean, over all classes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, raw in _by_length(batches):
            away = _units(raw, kind) - np.array(batch.column(1)[0].as_py())
            yield pa.RecordBatch.from_arrays([pa.array((away * away).sum(axis=1))], ["away"])

    low = centred.select("raw", "mean").mapInArrow(run, "away double").agg(F.percentile_approx("away", F.lit(NEAR_MEAN), F.lit(1000))).first()[0]
    return 1.0 if low is None else float(low)


def _pools(plan: Plan, kind: str, whole: bool):
    """Each class once per table: its pool, and with ``whole`` its vector and the sides of all cuts."""
    width = -(-plan.cuts // 8)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, raw in _by_length(batches):
            x, n = _units(raw, kind), batch.num_rows
            away = x - np.array(batch.column(1)[0].as_py())
            side = (away @ _directions(plan, x.shape[1])[0].T > 0).reshape(n, plan.tables, plan.cuts)
            keys = (side * (1 << np.arange(plan.cuts, dtype=np.int64))).sum(axis=2)
            sizes = pa.array(np.full(n, len(raw[0]), np.int32))
            packed = [p.tobytes() for p in np.packbits(side, axis=2)] if width else [b""] * n
            for t in range(plan.tables):
                group = [pa.array(np.full(n, t, np.int32)), sizes, pa.array(keys[:, t])]
                if whole:
                    yield pa.RecordBatch.from_arrays([*group, batch.column(2), batch.column(3), batch.column(0), pa.array(packed, pa.binary())], ["pool_table", "size", "pool", "class_id", "copies", "raw", "sides"])
                else:
                    yield pa.RecordBatch.from_arrays(group, ["pool_table", "size", "pool"])

    return run


def count_collisions(projected: np.ndarray, queries: np.ndarray, others: np.ndarray, half_width: float) -> np.ndarray:
    """For each (query, other), the projections in whose query-centred window the other lies.

    ``projected`` has a row per vector and a column per projection. Every column is
    sorted once; a window is then a run of ranks, and membership a comparison of ranks.
    """
    counts = np.zeros((queries.size, others.size), np.uint8)
    whole = np.uint16 if len(projected) < 1 << 16 else np.uint32
    for column in projected.T:
        order = np.argsort(column, kind="stable")
        in_order = column[order]
        rank = np.empty(order.size, whole)
        rank[order] = np.arange(order.size, dtype=whole)
        low = np.searchsorted(in_order, column[queries] - half_width, "left").astype(whole)
        high = np.searchsorted(in_order, column[queries] + half_width, "right").astype(whole)
        # Ranks below the window wrap round to large ones.
        counts += rank[others][None, :] - low[:, None] < (high - low)[:, None]
    return counts


def _pool_links(plan: Plan, kind: str):
    width = -(-plan.cuts // 8)

    def work(rows: pa.Table) -> pa.RecordBatch | None:
        n = rows.num_rows
        if n < 2:
            return None
        table = rows.column("pool_table")[0].as_py()
        x = _units(rows.column("raw").to_pylist(), kind)
        ids, copies = rows.column("class_id").to_numpy(), rows.column("copies").to_numpy()
        sides = np.frombuffer(b"".join(rows.column("sides").to_pylist()), np.uint8).reshape(n, plan.tables, width)[:, :table]
        left = rows.column("is_left").to_numpy(zero_copy_only=False)
        own_block = rows.column("left_block")[0].as_py() == rows.column("right_block")[0].as_py()
        one, two = (np.arange(n), np.arange(n)) if own_block else (np.flatnonzero(left), np.flatnonzero(~left))
        projected = x @ _directions(plan, x.shape[1])[1].T
        forest, links = Forest(n), np.zeros(n, np.int64)
        for at in range(0, one.size, 512):
            part = one[at : at + 512]
            often = count_collisions(projected, part, two, plan.half_width) >= plan.least_count
            if own_block:
                often &= two[None, :] > part[:, None]
            if 32 * np.count_nonzero(often) > often.size:
                # Many to verify, as among vectors of a common offset: one product leaves those at the wanted cosine but for rounding.
                often &= x[part] @ x[two].T >= plan.cosine - 1e-9
            q, o = np.nonzero(often)
            for s in range(0, q.size, 1 << 14):
                a, b = part[q[s : s + (1 << 14)]], two[o[s : s + (1 << 14)]]
                near = np.einsum("ij,ij->i", x[a], x[b]) >= plan.cosine
                a, b = a[near], b[near]
                if table:
                    fresh = ~(sides[a] == sides[b]).all(axis=2).any(axis=1)
                    a, b = a[fresh], b[fresh]
                np.add.at(links, a, copies[b])
                np.add.at(links, b, copies[a])
                forest.link(a, b)
        some = links > 0
        if not some.any():
            return None
        roots = forest.roots()
        smallest = np.full(n, np.iinfo(np.int64).max)
        np.minimum.at(smallest, roots, ids)
        return pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(smallest[roots][some]), pa.array(links[some])], ["a", "b", "links"])

    return work


def near_vectors(vectors: DataFrame, cosine: float = COSINE, recall: float = RECALL, pool_rows: int = POOL_ROWS, block: int = BLOCK, seed: int = SEED, workspace: Workspace | None = None) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` of every row of ``vec_id, embedding``."""
    workspace = workspace or Workspace(vectors.sparkSession, "collisions")
    single = vectors.schema["embedding"].dataType.simpleString() == "array<float>"
    kind = "<f4" if single else "<f8"
    embedding = F.col("embedding") if single else F.col("embedding").cast("array<double>")
    named_raw = workspace.keep(vectors.select("vec_id", stored(embedding, kind).alias("raw")), "vectors")
    classes = workspace.keep(named_raw.where("raw is not null and vec_id is not null").groupBy("raw").agg(F.min("vec_id").alias("class_id"), F.count(F.lit(1)).alias("copies")), "classes")
    means = workspace.keep(_mean_vectors(classes, kind), "means")
    centred = classes.withColumn("size", F.octet_length("raw")).join(means, "size").select("raw", "mean", "class_id", "copies")
    plan = calibrate(classes.count(), cosine, recall, _spread(centred, kind), pool_rows=pool_rows, seed=seed)
    group = ["pool_table", "size", "pool"]
    keys = centred.select("raw", "mean").mapInArrow(_pools(plan, kind, False), "pool_table int, size int, pool long")
    pooled = centred.mapInArrow(_pools(plan, kind, True), "pool_table int, size int, pool long, class_id long, copies long, raw binary, sides binary")
    paired = block_pairs(pooled, group, "class_id", workspace, block, keys=keys)
    found = workspace.keep(stream_groups(paired, [*group, "left_block", "right_block"], _pool_links(plan, kind), "a long, b long, links long"), "links")
    links = found.groupBy(F.col("a").alias("class_id")).agg(F.sum("links").alias("links"))
    groups = components(found.select("a", "b"), workspace).select(F.col("node").alias("class_id"), "component")
    named = workspace.keep(classes.join(links, "class_id", "left").join(groups, "class_id", "left").select("raw", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "class_id").alias("component_id")), "named")
    out = named_raw.join(named, "raw", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))
