"""The experiment workloads with the engine's real ingredients: k-means, cuts, graphs.

Results depend on k-means and are held to accuracy gates in the tests, not to SQL.
Each query returns the rows of a curve or a comparison; work is counted in
similarity evaluations, which do not depend on the machine.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecroute.baselines import kdtree, lsh, quantised, random_split
from vecroute.functions import kernels, measures, vectors
from vecroute.graphs import hnsw, knn_graph
from vecroute.plans import builder, router, search
from vecroute.registry import query
from vecroute.runtime import Workspace, ship, table
from vecroute.serving import dispatch, tuning
from vecroute.sources import datasets

K = 10
KS = (1, 5, 10, 20, 50, 100)
#: Every so many ids ask, against all items.
STEP = 20
SETS = {"emb": "l2", "line5": "l2"}
#: Rows of a part: where two kinds of graph are walked, and on the curve by size.
WALK_ROWS, SIZE_ROWS = 4000, 16_000


def prepared(spark: SparkSession, d: str, name: str, metric: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Items, queries and exact truth, written once."""
    ship(spark)
    ws = Workspace(spark, "experiment")
    items = ws.keep(datasets.items(spark, d, name), "items")
    queries = ws.keep(items.where(F.col("item_id") % STEP == 0).select(F.col("item_id").alias("query_id"), "vec"), "queries")
    truth = ws.keep(search.exact_topk_blocks(queries, items, K, metric), "truth")
    return items, queries, truth


def ladder(n: int) -> list[int]:
    """Numbers of centres as 1 : 10 : 100, as far as the set has five items for each."""
    return [m for m in (10, 100, 1000) if 5 * m <= n] or [10]


def curve(index: builder.Index, queries: DataFrame, truth: DataFrame, ks: tuple[int, ...] = KS) -> DataFrame:
    """``branching, access_rate, precision, evals``: one routing and one search pass for all branching factors."""
    ws = Workspace(index.spark, "curve")
    p = index.params
    q = queries
    if p.metric == "cosine":
        q = queries.select("query_id", vectors.normalise(F.col("vec")).alias("vec"))
    ks = tuple(k for k in ks if k <= p.m)
    routed = ws.keep(router.route(q, index.meta, max(ks), keep_rank=True), "routed")
    found = ws.keep(search.search_subs(routed.drop("rank"), index.graphs, K, p.l), "found").join(routed.select("query_id", "sub_id", "rank"), ["query_id", "sub_id"])
    n = queries.count()
    grid = F.explode(F.array(*[F.lit(k) for k in ks])).alias("branching")
    reach = routed.select("query_id", "sub_id", "rank", grid).where("rank <= branching")
    access = measures.access_rate(reach, p.w, ["branching"])
    wide = found.select("query_id", "sub_id", "item_id", "score", "evals", "rank", grid).where("rank <= branching")
    work = wide.select("branching", "query_id", "sub_id", "evals").distinct().groupBy("branching").agg((F.sum("evals") / n).alias("evals"))
    once = wide.groupBy("branching", "query_id", "item_id").agg(F.max("score").alias("score")).withColumn("bq", F.struct("branching", "query_id"))
    best = router.top_rank(once, "bq", K)
    precision = measures.precision(best, truth, K, ["branching"])
    return access.join(precision, "branching").join(work, "branching").select("branching", "access_rate", "precision", "evals")


def stacked(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def params(metric: str, m: int, **more) -> builder.Params:
    return builder.Params(metric=metric, m=m, w=min(10, m), kmeans_iters=6, builder="bulk", **more)


for _name in SETS:

    @query(f"w_branching_curves_{_name}")
    def _curves(spark: SparkSession, d: str, name: str = _name) -> DataFrame:
        """Access rate, precision and work by branching factor, for several numbers of centres."""
        items, queries, truth = prepared(spark, d, name, SETS[name])
        return stacked([curve(builder.build(items, params(SETS[name], m)), queries, truth).select(F.lit(m).alias("m"), "*") for m in ladder(items.count())])


def single_times(index: builder.Index, routed: DataFrame, k: int, l: int) -> DataFrame:  # noqa: E741
    """``query_id, sub_id, seconds`` of every visit, one query at a time, in the task that holds the part."""

    def run(queries: pa.Table, rows: pa.Table) -> pa.Table:
        seconds = []
        if rows.num_rows and queries.num_rows:
            graph = hnsw.from_row(rows.slice(0, 1).to_pylist()[0])
            for v in queries.column("vec").to_pylist():
                clock = time.perf_counter()
                hnsw.search(graph, np.array([v]), k, l)
                seconds.append(time.perf_counter() - clock)
            return pa.table({"query_id": queries.column("query_id"), "sub_id": queries.column("sub_id"), "seconds": pa.array(seconds)})
        return pa.table({"query_id": pa.array([], pa.int64()), "sub_id": pa.array([], pa.int32()), "seconds": pa.array([], pa.float64())})

    return routed.select("query_id", "sub_id", "vec").groupBy("sub_id").cogroup(index.graphs.groupBy("sub_id")).applyInArrow(run, "query_id long, sub_id int, seconds double")


@query("w_throughput_latency")
def _throughput(spark: SparkSession, d: str) -> DataFrame:
    """By centres and branching: queries a second of a batch, the 90th percentile over all queries of the slowest part's kernel time, and search time in the routing graph; of this machine only."""
    items, queries, _ = prepared(spark, d, "emb", "l2")
    ws, n, rows = Workspace(spark, "latency"), queries.count(), []
    for m in ladder(items.count()):
        index = builder.build(items, params("l2", m))
        ks = [k for k in KS if k <= m]
        routed = ws.keep(router.route(queries, index.meta, max(ks), keep_rank=True), "routed")
        times = ws.keep(single_times(index, routed, K, 100).join(routed.select("query_id", "sub_id", "rank"), ["query_id", "sub_id"]), "times")
        q = np.array(routed.where("rank = 1").select("vec").limit(256).toPandas().vec.tolist())  # a block of the kernel
        for branching in ks:
            clock = time.perf_counter()
            builder.ask(index, queries, branching, K).write.format("noop").mode("overwrite").save()
            seconds = time.perf_counter() - clock
            slowest = times.where(F.col("rank") <= branching).groupBy("query_id").agg(F.max("seconds").alias("latency"))
            clock = time.perf_counter()
            index.meta.rank(q, branching, "graph")
            rows.append((m, branching, measures.throughput(n, seconds), measures.latency_pct(slowest).first()[0], (time.perf_counter() - clock) / len(q) * 1000))
    return spark.createDataFrame(rows, "m int, branching int, queries_per_s double, kernel_p90_s double, meta_search_ms double")


def _work(partials: DataFrame, n: int) -> float:
    per = partials.select("query_id", "sub_id", "evals").distinct().agg(F.sum("evals")).first()[0] or 0
    return per / max(1, n)


@query("w_systems_at_equal_precision")
def _systems(spark: SparkSession, d: str) -> DataFrame:
    """Routed, random split and KD-trees on three sets, all queries each, every system tuned down to 90 %.

    ``evals`` are similarities per query; ``work_ratio`` is that of the random split over
    the system's own, null where the system does not reach 90 %.
    """
    rows = []
    for name, metric in (("line5", "l2"), ("emb", "l2"), ("hashtext", "cosine")):
        items, queries, truth = prepared(spark, d, name, metric)
        if metric == "cosine":
            items = items.select("item_id", vectors.normalise(F.col("vec")).alias("vec"))
            queries = queries.select("query_id", vectors.normalise(F.col("vec")).alias("vec"))
        ws = Workspace(spark, "systems")
        items, queries, n = ws.keep(items, "items"), ws.keep(queries, "queries"), queries.count()
        index = builder.build(items, params("l2", 100 if items.count() >= 2000 else 50))
        split = random_split.build(items, 10, "l2", builder="bulk")
        systems = {"random split": [lambda cap: split.partials(queries, K, K, cap)], "routed": [], "kd-trees": [lambda cap: kdtree.partials(items, queries, 10, K, 4, -(-cap // 16))]}
        for branching in (2, 10):
            routed = ws.keep(router.route(queries, index.meta, branching), "routed")
            systems["routed"].append(lambda cap, r=routed: builder.partials(index, r, K, K, cap))
        best = {s: min((tuning.least_work(a, queries, truth, 0.9, K) for a in asks), key=lambda f: (f.precision < 0.9 - 1e-9, f.evals)) for s, asks in systems.items()}
        for s, f in best.items():
            ratio = best["random split"].evals / max(f.evals, 1e-9) if f.precision >= 0.9 - 1e-9 else None
            rows.append((name, s, f.precision, f.evals, ratio))
    return spark.createDataFrame(rows, "dataset string, system string, precision double, evals double, work_ratio double")


@query("w_build_phases")
def _phases(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of each build phase, here: routed, random split, KD-trees."""
    items = Workspace(spark, "phases").keep(datasets.items(spark, d, "line5"), "items")
    index = builder.build(items, params("l2", 100))
    rows = [("routed", k, float(v)) for k, v in index.phases.items() if not k.startswith("fact_")]
    split = random_split.build(items, 10, "l2", builder="bulk")
    rows += [("random split", k, float(v)) for k, v in split.phases.items()]
    clock = time.perf_counter()
    kdtree.build(items, 10, 4).write.format("noop").mode("overwrite").save()
    rows.append(("kd-trees", "trees", time.perf_counter() - clock))
    return spark.createDataFrame(rows, "system string, phase string, seconds double")


@query("w_inner_product_replicas")
def _ip(spark: SparkSession, d: str) -> DataFrame:
    """Inner product: precision at one part visited, stored copies, and skew, by replication depth and against the unfixed build."""
    rows = []
    for name in ("hashtext", "emb_scaled", "letters"):
        items, queries, truth = prepared(spark, d, name, "ip")
        n = items.count()
        m = 100 if n >= 2000 else 50
        for label, p in (("r=0", params("ip", m)), ("r=5", params("ip", m, r=5)), ("r=20", params("ip", m, r=20)), ("r=20 by norm", params("ip", m, r=20, replicas="norm_top")), ("unfixed", params("ip", m, fix_ip=False))):
            index = builder.build(items, p)
            c = curve(index, queries, truth, (1, 5)).collect()
            peak = measures.balance(index.placement, "sub_id").first().peak
            visits = measures.balance(router.route(queries, index.meta, 1), "sub_id").first()
            for r in c:
                rows.append((name, label, r.branching, r.precision, r.evals, index.placement.count() / n - 1, m * p.r / n, peak, visits.peak * p.w / visits.parts))
        split = random_split.build(items, 10, "ip", builder="bulk")
        found = split.partials(queries, K, 20)
        rows.append((name, "random split", 0, measures.precision(search.merge_top_k(found, K), truth, K).first().precision, _work(found, queries.count()), 0.0, 0.0, 1.0, 1.0))
    return spark.createDataFrame(rows, "dataset string, method string, branching int, precision double, evals double, net_overhead double, gross_overhead double, part_peak double, traffic_peak double")


@query("w_scale_out")
def _scale(spark: SparkSession, d: str) -> DataFrame:
    """Work of the busiest part at equal precision, with five and with ten parts: its inverse is the throughput a cluster of that many machines could reach."""
    items, queries, truth = prepared(spark, d, "line5", "l2")
    rows = []
    for target in (0.8, 0.9):
        for w in (5, 10):
            index = builder.build(items, builder.Params(m=100, w=w, kmeans_iters=6, builder="bulk"))
            s = tuning.match_precision(index, queries, truth, target, [1, 2, 3, 5, 10], [10, 30, 60])
            found = search.search_subs(router.route(queries, index.meta, s.branching), index.graphs, K, s.l)
            per = found.select("query_id", "sub_id", "evals").distinct().groupBy("sub_id").agg(F.sum("evals").alias("e"))
            rows.append((target, w, s.precision, float(per.agg(F.max("e")).first()[0])))
    return spark.createDataFrame(rows, "target double, parts int, precision double, busiest_evals double")


@query("w_straggler")
def _straggler(spark: SparkSession, d: str) -> DataFrame:
    """Throughput by the share of its rate that one of ten executors keeps, under the requests of the event log."""
    from vecroute.served import logged_requests

    ship(spark)
    shares = [0.1, 0.2, 0.3, 0.5, 0.7, 1.0]
    run = dispatch.run_scenarios(spark, dispatch.straggler_scenarios(shares, offered=logged_requests(spark, d, 60)))
    late = dispatch.served_per_second(run).where("t >= 30").groupBy("scenario").agg(F.avg("served").alias("served"))
    return late.select(F.col("scenario").cast("double").alias("share"), "served")


@query("w_failure")
def _failure(spark: SparkSession, d: str) -> DataFrame:
    """Served requests a second of the event log while an executor dies and comes back."""
    from vecroute.served import logged_requests

    ship(spark)
    return dispatch.served_per_second(dispatch.run_scenarios(spark, dispatch.failure_scenario(offered=logged_requests(spark, d, 700)))).select("t", "served", "queued")


@query("w_hot_weights")
def _hot(spark: SparkSession, d: str) -> DataFrame:
    """Traffic of the busiest part under a skewed log, with parts balanced by members or by use."""
    ship(spark)
    ws = Workspace(spark, "hot")
    items = ws.keep(datasets.items(spark, d, "emb"), "items")
    log = ws.keep(datasets.hot_log(spark, d).withColumn("query_id", F.xxhash64(F.monotonically_increasing_id())).join(items, "item_id").select("query_id", "vec"), "log")
    rows = []
    for label, sample in (("members", None), ("use", log)):
        index = builder.build(items, params("l2", 50), sample)
        b = measures.balance(router.route(log, index.meta, 1, "exact"), "sub_id").first()
        rows.append((label, b.peak * index.params.w / b.parts))
    return spark.createDataFrame(rows, "weights string, traffic_peak double")


@query("w_center_kinds")
def _kinds(spark: SparkSession, d: str) -> DataFrame:
    """Ablations: centres by k-means or sampled, cut balanced or at random, weights or none."""
    items, queries, truth = prepared(spark, d, "line5", "l2")
    rows = []
    for label, more in (("k-means", {}), ("sampled centres", {"centers": "sampled"}), ("random cut", {"cut": "random"}), ("unweighted", {"centers": "unweighted"}), ("centres grouped by k-means", {"cut": "coarse_kmeans"})):
        index = builder.build(items, params("l2", 100, **more))
        peak = measures.balance(index.placement, "sub_id").first().peak
        for r in curve(index, queries, truth, (1, 5)).collect():
            rows.append((label, r.branching, r.access_rate, r.precision, r.evals, peak))
    return spark.createDataFrame(rows, "variant string, branching int, access_rate double, precision double, evals double, part_peak double")


@query("w_multi_assignment")
def _multi(spark: SparkSession, d: str) -> DataFrame:
    """Items in one or two parts under L2: precision at one part visited against storage."""
    rows = []
    for name in SETS:
        items, queries, truth = prepared(spark, d, name, "l2")
        n = items.count()
        for copies in (1, 2):
            index = builder.build(items, params("l2", 50, copies=copies))
            r = curve(index, queries, truth, (1,)).first()
            rows.append((name, copies, r.precision, index.placement.count() / n - 1))
    return spark.createDataFrame(rows, "dataset string, copies int, precision double, net_overhead double")


@query("w_compressed")
def _compressed(spark: SparkSession, d: str) -> DataFrame:
    """Product quantisation, rotated, and re-ranked, against graph search."""
    items, queries, truth = prepared(spark, d, "emb", "l2")
    rows = []
    for label, rotate, rerank in (("quantised", False, 0), ("rotated", True, 0), ("re-ranked", False, 50)):
        q = quantised.fit_items(items, 8, rotate)
        rows.append((label, measures.precision(quantised.ask(items, queries, q, K, rerank=rerank), truth, K).first().precision))
    rows.append(("graph", measures.precision(random_split.build(items, 1, builder="bulk").ask(queries, K), truth, K).first().precision))
    rows.append(("sign codes", measures.precision(lsh.ask(queries, items, K, "cosine", 16, 4), truth, K).first().precision))
    rows.append(("projection buckets", measures.precision(lsh.ask_l2(queries, items, K, 1.3, 0.5, 6), truth, K).first().precision))
    return spark.createDataFrame(rows, "method string, precision double")


@query("w_flat_and_layered_walks")
def _walks(spark: SparkSession, d: str) -> DataFrame:
    """Hops and evaluations of a far start, per part over the whole set: single-layer graph against layers."""
    ship(spark)
    items = Workspace(spark, "walks").keep(datasets.items(spark, d, "line5"), "items")
    w = max(1, -(-items.count() // WALK_ROWS))
    # A part costs far more than its bytes tell, so tasks are dealt by parts: eight each.
    parts = router.random_parts(items, w).repartition(-(-w // 8), "sub_id")

    def run(part: pa.Table) -> pa.Table:
        part = part.sort_by("item_id")
        ids = part.column("item_id").to_numpy()
        x = part.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        q = x[ids % 20 == 0]
        if not len(q):
            return pa.table({c: pa.array([], t) for c, t in zip(("graph", "hops", "evals", "n"), (pa.string(), pa.float64(), pa.float64(), pa.int64()), strict=True)})
        far = int(((x - x.mean(axis=0)) ** 2).sum(axis=1).argmax())
        near = kernels.nearest_rows(x, min(64, len(ids) - 1), "l2")  # both graphs are made of these
        flat, layered = knn_graph.build(ids, x, 16, near=near[0]), hnsw.build_bulk(ids, x, near0=near)
        walks = [("flat", knn_graph.search(flat, q, 1, 1, far)), ("layered", hnsw.search(layered, q, 1, 1)), ("flat, beam", knn_graph.search(flat, q, K, 50, far)), ("layered, beam", hnsw.search(layered, q, K, 50))]
        return pa.table({"graph": [w for w, _ in walks], "hops": [float(r[2].hops.sum()) for _, r in walks], "evals": [float(r[2].evals.sum()) for _, r in walks], "n": [len(q)] * len(walks)})

    sums = parts.groupBy("sub_id").applyInArrow(run, "graph string, hops double, evals double, n long").groupBy("graph")
    return sums.agg((F.sum("hops") / F.sum("n")).alias("hops"), (F.sum("evals") / F.sum("n")).alias("evals"))


@query("w_work_by_size")
def _work_by_size(spark: SparkSession, d: str) -> DataFrame:
    """Evaluations per query, summed over as many parts at every size, as the set doubles up to all rows: far below linear."""
    items = Workspace(spark, "sizes").keep(datasets.items(spark, d, "line5"), "items")
    whole, rows = items.count(), []
    w = max(10, -(-whole // SIZE_ROWS))
    draw = F.pmod(F.xxhash64(F.lit(11), F.col("item_id")), F.lit(1 << 32))
    for size in sorted(whole >> k for k in range(64) if whole >> k >= min(whole, 50 * w)):
        some = items if size == whole else items.where(draw < (size << 32) // whole)
        queries = some.where("item_id % 20 = 0").select(F.col("item_id").alias("query_id"), "vec")
        found = random_split.build(some, w, "l2", builder="bulk").partials(queries, K, 20)
        rows.append((some.count(), w, _work(found, queries.count())))
    return spark.createDataFrame(rows, "n int, parts int, evals double")


@query("w_loss_split")
def _loss(spark: SparkSession, d: str) -> DataFrame:
    """What routing loses and what the walk inside parts loses."""
    items, queries, truth = prepared(spark, d, "emb", "l2")
    index = builder.build(items, params("l2", 50))
    walked = builder.ask(index, queries, 10, K, mode="exact")
    scanned = builder.ask(index, queries, 10, K, mode="exact", exact=True)
    return measures.loss_split(scanned, walked, truth, K)


@query("w_refresh")
def _refresh(spark: SparkSession, d: str) -> DataFrame:
    """Versions before and after a rebuild on changed data, with what each answers."""
    ship(spark)
    ws = Workspace(spark, "refresh")
    items = ws.keep(datasets.items(spark, d, "emb"), "items")
    catalog = builder.Catalog(spark, f"{ws.base}/catalog")
    q = items.where("item_id % 10 = 3").select(F.col("item_id").alias("query_id"), "vec")
    rows = []
    for label, some in (("all", items), ("a tenth dropped", items.where("item_id % 10 <> 3")), ("all again", items)):
        version = catalog.commit(builder.build(some, params("l2", 20)))
        index = catalog.load()
        found = builder.ask(index, q, 20, 1, mode="exact")
        rows.append((label, int(index.n), found.where("query_id = item_id").count(), catalog.newest() == version))
    return spark.createDataFrame(rows, "data string, items int, self_found long, newest boolean")


@query("w_sql_table_functions")
def _table_functions(spark: SparkSession, d: str) -> DataFrame:
    """Routed and exact answers of the SQL table functions, side by side."""
    from vecroute.serving import sqlext

    ship(spark)
    items = datasets.items(spark, d, "emb")
    sqlext.register(spark, builder.build(items, params("l2", 20)), "vr")
    items.where("item_id % 20 = 0").select(F.col("item_id").alias("query_id"), "vec").createOrReplaceTempView("vr_asked")
    return spark.sql("SELECT a.query_id, e.rank, e.item_id AS exact_id, n.item_id AS routed_id FROM vr_asked a, LATERAL exact_search(a.vec, 3) e JOIN (SELECT query_id, f.rank, f.item_id FROM vr_asked, LATERAL ann_search(vec, 3, 20, 500) f) n ON n.query_id = a.query_id AND n.rank = e.rank")


@query("w_index_layers")
def _layers(spark: SparkSession, d: str) -> DataFrame:
    """Nodes and links per layer: the routing graph over the parts' graphs."""
    return builder.describe(builder.build(datasets.items(spark, d, "emb"), params("l2", 50)))


@query("w_page_neighbours")
def _pages(spark: SparkSession, d: str) -> DataFrame:
    """Pages nearest to pages by the hashed words of their markup-free text, under cosine."""
    ship(spark)
    ws = Workspace(spark, "pages")
    plain = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</\\1>", " "), "<[^>]*>", " ")
    table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), plain.alias("text")).write.parquet(f"{ws.base}/p/documents.parquet")
    items = ws.keep(datasets.items(spark, f"{ws.base}/p", "hashtext"), "items")
    q = items.where("item_id % 20 = 0").select(F.col("item_id").alias("query_id"), "vec")
    return builder.ask(builder.build(items, params("cosine", 20)), q, 5, 3, mode="exact")


@query("w_conversation_retrieval")
def _retrieval(spark: SparkSession, d: str) -> DataFrame:
    """Documents nearest to conversation turns of users, by hashed words under cosine."""
    ship(spark)
    turns = table(spark, d, "conversations").where("role = 'user'").select((F.col("conv_id") * 1_000 + F.col("turn")).alias("doc_id"), "text")
    ws = Workspace(spark, "retrieval")
    at = f"{ws.base}/turns/documents.parquet"
    turns.write.parquet(at)
    q = datasets.items(spark, f"{ws.base}/turns", "hashtext").select(F.col("item_id").alias("query_id"), "vec")
    index = builder.build(datasets.items(spark, d, "hashtext"), params("cosine", 50))
    return builder.ask(index, q, 5, 3, mode="exact")
