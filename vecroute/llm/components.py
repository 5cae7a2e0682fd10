"""Connected components and grouped work for near-duplicate search.

Nothing here collects links, components or group members to the driver, and no task
holds more than two blocks of a group at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.runtime import Workspace

#: Most members of a block; a group of ``g`` members is compared as pairs of ``g / BLOCK`` blocks.
BLOCK = 2048


def block_pairs(rows: DataFrame, group: list[str], member: str, workspace: Workspace, block: int = BLOCK, keys: DataFrame | None = None) -> DataFrame:
    """Rows by group, once for each pair of blocks they take part in.

    Adds ``left_block`` and ``right_block`` (left <= right) and ``is_left``. A
    group larger than a block is split by a hash of the member, so that its work
    spreads over tasks. Group sizes are counted before anything is exchanged by
    group and written, so that the join can split a group that is hot.

    Without ``keys`` rows of groups of one are left out before the exchange. ``keys``
    holds the group columns of all rows at less cost; then only the sizes of groups
    beyond a block are joined to the rows, which for wide rows saves an exchange.
    """
    sizes = (rows if keys is None else keys).groupBy(*group).agg(F.count(F.lit(1)).alias("group_rows"))
    if keys is None:
        placed = rows.join(workspace.keep(sizes.where("group_rows > 1"), "groups"), group)
    else:
        placed = rows.join(workspace.keep(sizes.where(F.col("group_rows") > block), "groups"), group, "left").fillna(1, ["group_rows"])
    blocks = F.ceil(F.col("group_rows") / F.lit(block)).cast("int")
    own = F.pmod(F.xxhash64(F.col(member), F.lit(7)), F.col("blocks")).cast("int")
    placed = placed.withColumn("blocks", blocks).withColumn("own", own).withColumn("other", F.explode(F.expr("sequence(0, blocks - 1)")))
    return placed.withColumns({"left_block": F.least("own", "other"), "right_block": F.greatest("own", "other"), "is_left": F.col("own") <= F.col("other")}).drop("group_rows", "blocks", "own", "other")


def stream_groups(rows: DataFrame, group: list[str], work: Callable[[pa.Table], pa.RecordBatch | None], schema: str) -> DataFrame:
    """``work`` on each group's rows, in one pass over partitions sorted by group.

    Cheaper than a grouped Python function where most groups hold a few rows;
    ``work`` gets the rows of one group and may return rows.
    """
    names = rows.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        out: list[pa.RecordBatch] = []
        size = 0

        def finish() -> Iterator[pa.RecordBatch]:
            nonlocal held
            if held:
                result = work(pa.Table.from_batches(held))
                held = []
                if result is not None and result.num_rows:
                    out.append(result)

        for batch in batches:
            keys = [batch.column(names.index(g)) for g in group]
            change = np.zeros(batch.num_rows, bool)
            for k in keys:
                v = k.to_numpy(zero_copy_only=False)
                change[1:] |= v[1:] != v[:-1]
            cuts = [0, *np.flatnonzero(change).tolist(), batch.num_rows]
            for at, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                if b == a:
                    continue
                piece = batch.slice(a, b - a)
                if at == 0 and held and any(held[-1].column(names.index(g))[-1].as_py() != piece.column(names.index(g))[0].as_py() for g in group):
                    finish()
                elif at > 0:
                    finish()
                held.append(piece)
                size += b - a
                if out and size > 50_000:
                    yield from pa.Table.from_batches(out).combine_chunks().to_batches()
                    out, size = [], 0
        finish()
        if out:
            yield from pa.Table.from_batches(out).combine_chunks().to_batches()

    return rows.repartition(*group).sortWithinPartitions(*group).mapInArrow(run, schema)


class Forest:
    """Union-find over positions, fed with arrays of linked pairs."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def roots(self) -> np.ndarray:
        p = self.parent
        while True:
            q = p[p]
            if np.array_equal(p, q):
                self.parent = p
                return p
            p = q

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while True:
            p = self.roots()
            ra, rb = p[a], p[b]
            differ = ra != rb
            if not differ.any():
                return
            low, high = np.minimum(ra[differ], rb[differ]), np.maximum(ra[differ], rb[differ])
            order = np.lexsort((low, high))
            first = np.r_[True, np.diff(high[order]) != 0]
            self.parent[high[order][first]] = low[order][first]
            a, b = a[differ], b[differ]


def components(edges: DataFrame, workspace: Workspace) -> DataFrame:
    """``node, component`` for every node with an edge ``a, b``; the component is its smallest node.

    Large-star and small-star rounds: each node hands its larger, then its
    smaller neighbours to the smallest node it knows, until every node points to
    its component. Every step is written before it is joined, so that a node with
    a third of all edges is split by the join rather than held by one task.
    """

    def settle(pairs: DataFrame, label: str) -> DataFrame:
        return workspace.keep(pairs.where("u <> v").distinct(), label)

    def state(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count(F.lit(1)), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 30)))).first())

    current = settle(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")), "edges")
    before = state(current)
    while before[0]:
        both = current.select("u", "v").union(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = workspace.keep(both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low")), "low")
        large = settle(both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v")), "large")
        workspace.drop(low)
        low = workspace.keep(large.groupBy("u").agg(F.min("v").alias("low")), "low")
        # The node itself also goes to the smallest, as do its other smaller neighbours.
        small = settle(large.join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v")).union(low.select("u", F.col("low").alias("v"))), "small")
        for done in (low, large, current):
            workspace.drop(done)
        current, after = small, state(small)
        if after == before:
            break
        before = after
    return current.select(F.col("u").alias("node"), F.col("v").alias("component")).union(current.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
