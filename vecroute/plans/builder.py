"""Building an index end to end, storing it by version, and querying it."""

from __future__ import annotations

import json
import time
import uuid
from dataclasses import asdict, dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecroute.functions import kernels, vectors
from vecroute.plans import centers as center_plans
from vecroute.plans import cutgraph, mips, router, sampling, search
from vecroute.runtime import Workspace, ship
from vecroute.serving import planner


@dataclass(frozen=True)
class Params:
    """Everything that fixes an index."""

    metric: str = "l2"
    m: int = 100
    w: int | None = 10  #: None: as many parts as the item count asks for
    n_prime: int | None = None
    degree: int = 16
    degree0: int = 32
    l: int = 100  # noqa: E741
    r: int = 0
    imbalance: float = 0.05
    copies: int = 1
    cut: str = "multilevel"
    centers: str = "kmeans"
    route: str = "graph"
    replicas: str = "exact"
    fix_ip: bool = True
    kmeans_iters: int = 10
    seed: int = 42
    builder: str = "insert"
    hot_k: int = 1
    split_heavy: bool = True

    def __post_init__(self) -> None:
        if self.metric not in vectors.METRICS:
            raise ValueError(f"no metric {self.metric!r}")
        if self.w is not None and (self.m < self.w or self.w < 1):
            raise ValueError("at least one part, and a centre for each")


@dataclass
class Index:
    params: Params
    n: int
    d: int
    centers: DataFrame
    placement: DataFrame
    graphs: DataFrame
    meta: router.MetaIndex
    phases: dict[str, float] = field(default_factory=dict)

    @property
    def spark(self) -> SparkSession:
        return self.graphs.sparkSession


def choose_centers(items: DataFrame, p: Params, sample_queries: DataFrame | None = None) -> DataFrame:
    """``center_id, vec, weight`` by the chosen way."""
    sample = sampling.uniform(items, p.n_prime or 256 * p.m, p.seed)
    spherical = p.metric == "cosine" or p.metric == "ip" and p.fix_ip
    if p.centers == "sampled":
        found = center_plans.sampled(items, p.m, p.seed)
        if spherical:
            found = found.withColumn("vec", vectors.normalise(F.col("vec")))
    elif p.centers == "hierarchical":
        branches = max(2, round(p.m**0.5))
        found = center_plans.hierarchical(sample, branches, -(-p.m // branches), p.kmeans_iters, p.seed)
        if spherical:
            found = found.withColumn("vec", vectors.normalise(F.col("vec")))
    else:
        found = center_plans.kmeans(sample, p.m, p.kmeans_iters, p.seed, spherical)
    ids, matrix = center_plans.as_matrix(found)
    ids = np.arange(len(matrix))
    if p.split_heavy and p.centers in ("kmeans", "hierarchical") and p.w > 1:
        matrix = split_heavy(sample, matrix, p, spherical)
        ids = np.arange(len(matrix))
    fixed = center_plans.as_frame(items.sparkSession, matrix)
    if sample_queries is not None:
        return center_plans.weight_by_queries(sample_queries, fixed, p.hot_k, p.metric)
    if p.centers == "unweighted":
        return fixed
    meta = router.MetaIndex(ids, matrix, ids.astype(np.int32), p.metric, bulk=True)
    members = router.assign(sample, meta, "exact").groupBy(F.col("sub_id").alias("center_id")).agg(F.count(F.lit(1)).cast("double").alias("weight"))
    return fixed.drop("weight").join(members, "center_id", "left").select("center_id", "vec", F.coalesce("weight", F.lit(0.0)).alias("weight"))


#: Most sample rows of a heavy centre that its split looks at, and rounds of splitting.
SPLIT_ROWS, SPLIT_ROUNDS = 4000, 6


def split_heavy(sample: DataFrame, matrix: np.ndarray, p: Params, spherical: bool) -> np.ndarray:
    """Centres with more than half an ideal part are split in two, so that parts can be balanced.

    Members come from the sample, at most ``SPLIT_ROWS`` by hash; copies of one vector
    cannot be split.
    """
    done: set[int] = set()
    for _ in range(SPLIT_ROUNDS):
        meta = router.MetaIndex(np.arange(len(matrix)), matrix, np.arange(len(matrix), dtype=np.int32), p.metric, bulk=True)
        near = router.assign(sample, meta, "exact")
        counts = {r.sub_id: r.n for r in near.groupBy("sub_id").agg(F.count(F.lit(1)).alias("n")).collect()}
        most = sum(counts.values()) / p.w / 2
        heavy = [c for c, n in sorted(counts.items()) if n > most and c not in done]
        if not heavy:
            break
        # Fewer than twice as many centres as parts are heavy, and each gives rows of its own.
        mine = Window.partitionBy("sub_id").orderBy(F.xxhash64("item_id"), "item_id")
        rows = near.where(F.col("sub_id").isin(heavy)).withColumn("n", F.row_number().over(mine)).where(F.col("n") <= SPLIT_ROWS).select("sub_id", "vec").collect()
        for c in heavy:
            x = np.array([r.vec for r in rows if r.sub_id == c])
            x = kernels.unit(x) if spherical else x
            spread = ((x - x.mean(axis=0)) ** 2).sum(axis=1) if len(x) else np.zeros(0)
            if not len(x) or spread.max() < 1e-12:
                done.add(c)
                continue
            a, b = x[spread.argmax()], x[((x - x[spread.argmax()]) ** 2).sum(axis=1).argmax()]
            for _ in range(8):
                side = ((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1)
                if side.all() or not side.any():
                    break
                a, b = x[side].mean(axis=0), x[~side].mean(axis=0)
            a, b = (kernels.unit(a), kernels.unit(b)) if spherical else (a, b)
            matrix = np.concatenate([matrix, b[None, :]])
            matrix[c] = a
    return matrix


def cut_centers(centers: DataFrame, p: Params) -> tuple[DataFrame, router.MetaIndex, dict]:
    """Centres with their part, the routing graph, and what the cut measured."""
    rows = centers.orderBy("center_id").collect()  # m rows, a parameter
    ids = np.array([r.center_id for r in rows], np.int64)
    matrix = np.array([r.vec for r in rows], np.float64)
    weight = np.array([r.weight for r in rows], np.float64)
    meta = router.MetaIndex(ids, matrix, np.zeros(len(ids), np.int32), p.metric, p.degree, p.degree0, p.l, p.seed, p.builder == "bulk")
    adjacency = cutgraph.symmetric(meta.graph.layers[0].links)
    w = min(p.w, len(ids))
    if p.cut == "random":
        part = cutgraph.random(len(ids), w, p.seed)
    elif p.cut == "modulo":
        part = cutgraph.modulo(ids, w)
    elif p.cut == "coarse_kmeans":
        part = cutgraph.coarse_kmeans(meta.matrix, w, p.seed)
    else:
        part = cutgraph.partition(adjacency, weight, w, p.imbalance, p.seed)
    meta.sub_of = part.astype(np.int32)
    load = np.bincount(part, weights=weight, minlength=w)
    facts = {"edge_cut": cutgraph.cut_size(adjacency, part), "edges": sum(map(len, adjacency)) / 2, "peak_load": float(load.max() / max(load.mean(), 1e-9))}
    frame = centers.sparkSession.createDataFrame([(int(i), [float(v) for v in c], float(wt), int(s)) for i, c, wt, s in zip(ids, matrix, weight, part, strict=True)], "center_id int, vec array<double>, weight double, sub_id int")
    return frame, meta, facts


def build(items: DataFrame, p: Params, sample_queries: DataFrame | None = None, workspace: Workspace | None = None) -> Index:
    """Sample, centres, routing graph, cut, placement (with copies and replicas), one graph per part."""
    spark = items.sparkSession
    ship(spark)
    workspace = workspace or Workspace(spark, "index")
    phases, clock = {}, time.perf_counter()

    def lap(name: str) -> None:
        nonlocal clock
        phases[name] = time.perf_counter() - clock
        clock = time.perf_counter()

    if p.metric == "cosine":
        items = items.select("item_id", vectors.normalise(F.col("vec")).alias("vec"))
    items = workspace.keep(items.select("item_id", F.col("vec").cast("array<double>").alias("vec")), "items")
    first = items.first()
    n, d = items.count(), len(first.vec) if first else 0
    if p.w is None:
        p = replace(p, w=min(p.m, planner.parts_for(n, d)))
    chosen = choose_centers(items, p, sample_queries)
    lap("centers")
    cut, meta, facts = cut_centers(chosen, p)
    lap("meta")
    placed = router.assign(items, meta, p.route, p.copies)
    if p.r:
        if p.metric != "ip" and p.metric != "l2":
            raise ValueError("replicas are for inner product or L2")
        placed = mips.union_placement(placed, mips.replicate(items, meta, p.r, p.replicas))
    placed = workspace.keep(placed, "placement")
    lap("partition")
    graphs = workspace.keep(search.build_all(placed, p.w, p.metric, p.degree, p.degree0, p.l, p.seed, p.builder), "graphs")
    lap("graphs")
    index = Index(p, n, d, cut, placed, graphs, meta, phases)
    index.phases |= {f"fact_{k}": v for k, v in facts.items()}
    return index


def ask(index: Index, queries: DataFrame, branching: int, k: int, l: int | None = None, mode: str = "graph", max_evals: int | None = None, exact: bool = False, chunks: int = 1) -> DataFrame:  # noqa: E741
    """``query_id, rank, item_id, score`` by routing, searching the visited parts, and merging."""
    p = index.params
    q = queries.select("query_id", vectors.normalise(F.col("vec")).alias("vec")) if p.metric == "cosine" else queries
    routed = router.route(q, index.meta, branching, mode)
    return search.merge_top_k(partials(index, routed, k, l, max_evals, exact, chunks), k)


def within(index: Index, queries: DataFrame, branching: int, least: float, mode: str = "graph") -> DataFrame:
    """``query_id, item_id, score`` of every item of similarity ``least`` or more in the parts a query is routed to; copies count once."""
    p = index.params
    q = queries.select("query_id", vectors.normalise(F.col("vec")).alias("vec")) if p.metric == "cosine" else queries
    found = search.radius_subs(router.route(q, index.meta, branching, mode), index.placement, least, p.metric)
    return found.groupBy("query_id", "item_id").agg(F.max("score").alias("score"))


def partials(index: Index, routed: DataFrame, k: int, l: int | None = None, max_evals: int | None = None, exact: bool = False, chunks: int = 1) -> DataFrame:  # noqa: E741
    p = index.params
    if exact:
        return search.scan_subs(routed, index.placement, k, p.metric)
    return search.search_subs(routed, index.graphs, k, p.l if l is None else l, max_evals, chunks)


class Catalog:
    """Index versions under one folder. A version is whole once its manifest says so; readers take the newest."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def commit(self, index: Index) -> str:
        version = f"{time.time_ns():020d}-{uuid.uuid4().hex[:8]}"
        at = f"{self.path}/{version}"
        index.centers.write.parquet(f"{at}/centers")
        index.placement.write.partitionBy("sub_id").parquet(f"{at}/placement")
        index.graphs.write.parquet(f"{at}/graphs")
        manifest = [(version, index.params.metric, index.d, index.n, json.dumps(asdict(index.params)), json.dumps(index.phases), "ready")]
        self.spark.createDataFrame(manifest, "version string, metric string, d int, n long, params string, phases string, state string").coalesce(1).write.mode("append").parquet(f"{self.path}/manifest")
        return version

    def versions(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/manifest").where("state = 'ready'")

    def newest(self) -> str:
        return self.versions().agg(F.max("version")).first()[0]

    def load(self, version: str | None = None) -> Index:
        version = version or self.newest()
        row = self.versions().where(F.col("version") == version).first()
        p = Params(**json.loads(row.params))
        at = f"{self.path}/{version}"
        centers = self.spark.read.parquet(f"{at}/centers")
        rows = centers.orderBy("center_id").collect()
        meta = router.MetaIndex(np.array([r.center_id for r in rows]), np.array([r.vec for r in rows]), np.array([r.sub_id for r in rows], np.int32), p.metric, p.degree, p.degree0, p.l, p.seed, p.builder == "bulk")
        return Index(p, row.n, row.d, centers, self.spark.read.parquet(f"{at}/placement"), self.spark.read.parquet(f"{at}/graphs"), meta, json.loads(row.phases))

    def refresh(self, items: DataFrame, params: Params | None = None) -> str:
        """Rebuilds from ``items`` and makes the result the newest version; older ones stay readable."""
        p = params or self.load().params
        return self.commit(build(items, p))


def describe(index: Index) -> DataFrame:
    """Nodes and links per layer: of the routing graph, then of all parts together."""
    meta = [("routing", t, int(y.nodes.size), int((y.links >= 0).sum())) for t, y in enumerate(index.meta.graph.layers)]
    top = index.spark.createDataFrame(meta, "part string, layer int, nodes long, links long")
    levels = index.graphs.select(F.explode("levels").alias("y"))
    subs = levels.groupBy(F.col("y.layer").alias("layer")).agg(F.sum(F.size("y.nodes")).cast("long").alias("nodes"), F.sum(F.size(F.filter("y.targets", lambda t: t >= 0))).cast("long").alias("links"))
    return top.unionByName(subs.select(F.lit("parts").alias("part"), "layer", "nodes", "links"))


def with_params(p: Params, **changes) -> Params:
    return replace(p, **changes)
