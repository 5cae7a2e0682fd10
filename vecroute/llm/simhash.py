"""SimHash near-duplicates with BK-trees.

Fingerprints are 64-bit simhashes of three-word shingles. Documents of equal
fingerprint are one class. Classes are dealt to shards so that any two within the
radius share a shard: the 64 bits are cut into bands, and if at most ``radius`` bits
differ, ``bands - radius`` of the bands agree. Each shard of bounded size becomes a
BK-tree (children keyed by their Hamming distance to the parent) that is walked
along edges within the radius only. Shard trees go to their queries by the exchange;
a broadcast would grow with the corpus.

Links join into components by star rounds; a document's component is the smallest
``doc_id`` it reaches.

Defined cases: null and empty text have no shingles and fingerprint zero, which
links like any other; rows of equal id have the component of their own text; rows of
null id take part like others, and a component without ids has a null one; an empty
table gives no rows; extra columns are ignored, and survive in ``keep_one``.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecroute.llm.components import BLOCK, Forest, block_pairs, components, stream_groups
from vecroute.runtime import Workspace

RADIUS = 3
SHINGLE = 3
HASH_SEED = 42
#: Most (query, node) pairs that a walk holds at a time.
FRONTIER = 1 << 15


def shingle_hashes(text: str | None, width: int = SHINGLE, seed: int = HASH_SEED) -> np.ndarray:
    """XXH64 of each run of ``width`` words, repeats included; of the whole if there are fewer."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([digest(joined, seed)], np.uint64)
    ends = list(itertools.accumulate(map(len, words), lambda a, n: a + 1 + n))
    starts = [0, *(e + 1 for e in ends[: len(words) - width])]
    return np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts, ends[width - 1 :], strict=True)), np.uint64, len(words) - width + 1)


def fingerprint_of(hashes: np.ndarray) -> int:
    """Bits set in over half the hashes; zero without any."""
    if hashes.size == 0:
        return 0
    set_in = np.zeros(64, np.int64)
    for at in range(0, hashes.size, 1 << 16):
        part = hashes[at : at + (1 << 16)].astype("<u8")
        set_in += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = 2 * set_in > hashes.size
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprint(text: Column) -> Column:
    """The fingerprint as a long with the same 64 bits."""

    def run(texts: pa.Array) -> pa.Array:
        values = np.array([fingerprint_of(shingle_hashes(t.as_py())) for t in texts], np.uint64)
        return pa.array(values.view(np.int64))

    return F.arrow_udf(run, "long")(text.cast("string"))


class BKTree:
    """A BK-tree over 64-bit values, built and walked one level at a time."""

    def __init__(self, values: np.ndarray):
        self.values = values
        n = values.size
        self.child = np.full((n, 65), -1, np.int32)
        items = np.arange(1, n)
        at = np.zeros(items.size, np.int64)
        while items.size:
            d = np.bitwise_count(values[items] ^ values[at]).astype(np.int64)
            slot = at * 65 + d
            flat = self.child.reshape(-1)
            free = flat[slot] < 0
            _, first = np.unique(np.where(free, slot, -1), return_index=True)
            first = first[free[first]]
            flat[slot[first]] = items[first]
            rest = np.ones(items.size, bool)
            rest[first] = False
            at, items = flat[slot[rest]].astype(np.int64), items[rest]

    def within(self, queries: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, node) positions at most ``radius`` bits apart."""
        q, node = np.arange(queries.size), np.zeros(queries.size, np.int64)
        found: list[tuple[np.ndarray, np.ndarray]] = []
        while q.size:
            d = np.bitwise_count(queries[q] ^ self.values[node]).astype(np.int64)
            hit = d <= radius
            if hit.any():
                found.append((q[hit], node[hit]))
            reach = d[:, None] + np.arange(-radius, radius + 1)
            inside = (reach >= 0) & (reach <= 64)
            nxt = np.where(inside, self.child[node[:, None], np.clip(reach, 0, 64)], -1)
            row, col = np.nonzero(nxt >= 0)
            q, node = q[row], nxt[row, col].astype(np.int64)
        if not found:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        return np.concatenate([a for a, _ in found]), np.concatenate([b for _, b in found])


def _shard_links(radius: int):
    def work(rows: pa.Table) -> pa.RecordBatch | None:
        n = rows.num_rows
        if n < 2:
            return None
        ids = rows.column("fp").to_numpy()
        values = ids.view(np.uint64)
        left, forest = rows.column("is_left").to_numpy(), Forest(n)
        own_block = rows.column("left_block")[0].as_py() == rows.column("right_block")[0].as_py()
        tree_at, query_at = (np.arange(n), np.arange(n)) if own_block else (np.flatnonzero(left), np.flatnonzero(~left))
        if not tree_at.size or not query_at.size:
            return None
        tree = BKTree(values[tree_at])
        # In a shard of near copies a walk visits most of the tree: bound its frontier.
        at_once = max(1, FRONTIER // tree_at.size)
        for at in range(0, query_at.size, at_once):
            part = query_at[at : at + at_once]
            q, x = tree.within(values[part], radius)
            forest.link(part[q], tree_at[x])
        roots = forest.roots()
        # Positions carry no order of fingerprints: a tree's smallest stands for it.
        smallest = np.full(n, np.iinfo(np.int64).max)
        np.minimum.at(smallest, roots, ids)
        low = smallest[roots]
        linked = low != ids
        return pa.RecordBatch.from_arrays([pa.array(ids[linked]), pa.array(low[linked])], ["a", "b"]) if linked.any() else None

    return work


def band_masks(bands: int, radius: int) -> list[int]:
    """Masks of all choices of ``bands - radius`` bands; one of them agrees if at most ``radius`` bits differ."""
    edges = [round(64 * i / bands) for i in range(bands + 1)]
    parts = [((1 << (b - a)) - 1) << a for a, b in itertools.pairwise(edges)]
    return [sum(c) for c in itertools.combinations(parts, bands - radius)]


def bands_for(classes: int, radius: int) -> int:
    """Bands so that a shard's key has bits enough for the number of classes."""
    for bands in range(radius + 1, radius + 4):
        if 64 * (bands - radius) / bands >= math.log2(max(classes, 2)) - 6:
            return bands
    return radius + 3


def _grouped(docs: DataFrame, facts: list[Column], radius: int, block: int, workspace: Workspace) -> tuple[DataFrame, DataFrame]:
    """Every row's ``doc_id``, ``fp`` and ``facts``; and of every fingerprint the component.

    A component is a set of fingerprints, named by its smallest one (``root``), so that
    rows of equal id whose texts differ stay apart.
    """
    prints = workspace.keep(docs.select("doc_id", fingerprint(F.col("text")).alias("fp"), *facts), "prints")
    classes = workspace.keep(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "classes")
    masks = band_masks(bands_for(classes.count(), radius), radius)
    banded = classes.select("fp", F.posexplode(F.array(*[F.lit(m - (1 << 64) if m >> 63 else m).bitwiseAND(F.col("fp")) for m in masks])).alias("band", "shard"))
    paired = block_pairs(banded, ["band", "shard"], "fp", workspace, block)
    links = workspace.keep(stream_groups(paired, ["band", "shard", "left_block", "right_block"], _shard_links(radius), "a long, b long"), "links")
    groups = components(links, workspace)
    rooted = workspace.keep(classes.join(groups, classes["fp"] == groups["node"], "left").select("fp", "first_id", F.coalesce("component", "fp").alias("root")), "rooted")
    return prints, rooted


def near_duplicates(docs: DataFrame, radius: int = RADIUS, block: int = BLOCK, workspace: Workspace | None = None) -> DataFrame:
    """``doc_id, fp, component_id`` of every row; ``fp`` has the fingerprint's bits as a long."""
    workspace = workspace or Workspace(docs.sparkSession, "simhash")
    prints, rooted = _grouped(docs, [], radius, block, workspace)
    smallest = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = workspace.keep(rooted.join(smallest, "root").select("fp", "component_id"), "components")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The rows and columns of ``docs`` with one row of each component: the smallest by ``doc_id``, then text.

    Rows count by id and text: rows of equal id whose texts are no near-duplicates
    all stay. A null id comes after all others, so such a row stays only in a
    component without ids. Of rows equal in id and text the first by the other columns stays.
    """
    workspace = Workspace(docs.sparkSession, "keep-one")
    digest = lambda c: F.coalesce(F.md5(c.cast("string").cast("binary")), F.lit(""))
    id_key = lambda c: F.coalesce(F.concat(F.lit("i"), c.cast("string")), F.lit("n"))
    prints, rooted = _grouped(docs, [digest(F.col("text")).alias("digest")], radius, BLOCK, workspace)
    order = F.struct(F.col("doc_id").isNull(), "doc_id", "digest")
    heads = prints.join(rooted.select("fp", "root"), "fp").groupBy("root").agg(F.min(order).alias("head"))
    heads = workspace.keep(heads.select(id_key(F.col("head.doc_id")).alias("id_key"), F.col("head.digest").alias("digest")), "heads")
    plain = [f.name for f in docs.schema.fields if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    known = packed.withColumns({"id_key": id_key(F.col("row.doc_id")), "digest": digest(F.col("row.text"))})
    first = Window.partitionBy("id_key", "digest").orderBy(F.xxhash64(*[F.col(f"row.`{c}`") for c in plain]))
    return known.join(heads, ["id_key", "digest"], "left_semi").withColumn("n", F.row_number().over(first)).where("n = 1").select("row.*")
