"""What only shows with more centres than a beam, with copies, or with many pairs."""

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from vecroute import workloads  # noqa: F401  registers the queries
from vecroute.functions import kernels
from vecroute.graphs import hnsw, knn_graph
from vecroute.plans import centers, mips, router, search
from vecroute.registry import QUERIES


@pytest.fixture(scope="module")
def wide(tmp_path_factory):
    """5,000 vectors, a third of them copies, so that 500 of them are centres; and a log of 20,000 hits."""
    at = tmp_path_factory.mktemp("wide")
    rng = np.random.default_rng(5)
    x = rng.standard_normal((5000, 64))
    x[3300:] = x[:1700]
    x = x.astype(np.float32)
    pq.write_table(pa.table({"vec_id": np.arange(5000), "embedding": pa.array(list(x), pa.list_(pa.float32())), "label": pa.array(np.arange(5000) % 4, pa.int32())}), at / "embeddings.parquet")
    hits = rng.integers(0, 100, 20_000)
    pq.write_table(pa.table({"event_id": np.arange(20_000), "value": hits + 0.5}), at / "events.parquet")
    return str(at), x.astype(float), hits


def ranked(x, c, metric):
    """Centres of each row by differences, ties to the smaller id."""
    a, b = (kernels.unit(x), kernels.unit(c)) if metric == "cosine" else (x, c)
    cost = ((a[:, None, :] - b[None, :, :]) ** 2).sum(axis=2) if metric != "ip" else -(a @ b.T)
    return np.argsort(np.round(cost, 9), axis=1, kind="stable")


@pytest.mark.parametrize("metric", ["l2", "cosine"])
@pytest.mark.parametrize("kind", ["_blocks", ""])
def test_items_go_to_the_nearest_of_many_centers(spark, wide, metric, kind):
    at, x, _ = wide
    want = ranked(x, x[::10], metric)[:, 0] % 10
    got = {r.item_id: r.sub_id for r in QUERIES[f"route_items_{metric}{kind}"](spark, at).collect()}
    assert [got[i] for i in range(5000)] == want.tolist()


def test_hot_weights_rank_an_item_once(spark, wide):
    at, x, hits = wide
    near = ranked(x[:100], x[::10], "l2")[:, :3]
    want = np.ones(500)
    np.add.at(want, near[hits].reshape(-1), 1)
    got = {r.center_id: r.weight for r in QUERIES["center_weight_hot"](spark, at).collect()}
    assert [got[10 * i] for i in range(500)] == want.tolist()


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["exact_l2_topk", "exact_cosine_topk", "exact_ip_topk", "exact_topk_exclude_self", "cosine_by_normalising", "filtered_search_after", "ip_augmented_rank", "ip_replicas", "radius_search", "route_items_l2", "route_items_ip", "center_weight_count", "lloyd_step", "route_queries", "ivf_det"])
def test_pairs_are_not_rows_of_a_plan(spark, wide, name):
    plan = plan_of(QUERIES[name](spark, wide[0]))
    assert "MapInArrow" in plan and "NestedLoopJoin" not in plan and "CartesianProduct" not in plan


def test_center_blocks_are_merged(spark, monkeypatch):
    """Centres beyond one broadcast are ranked in passes, with the same ranks."""
    x = np.random.default_rng(1).integers(-2, 3, (300, 3)).astype(float)
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "query_id long, vec array<double>")
    c = items.where("query_id % 3 = 0").select(F.col("query_id").cast("int").alias("center_id"), "vec")
    blocks = router.query_blocks
    monkeypatch.setattr(router, "query_blocks", lambda q: blocks(q, 600))
    got = {(r.query_id, r.rank): r.center_id for r in router.nearest_centers(items, c, 7).collect()}
    want = ranked(x, x[::3], "l2")[:, :7] * 3
    assert got == {(i, j + 1): int(want[i, j]) for i in range(300) for j in range(7)}


def test_all_pairs_within_a_radius(spark):
    x = np.random.default_rng(2).integers(-2, 3, (200, 4)).astype(float)
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "item_id long, vec array<double>")
    got = {(r.query_id, r.item_id) for r in search.exact_within(items.select(F.col("item_id").alias("query_id"), "vec"), items, -2.0).collect()}
    d = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    assert got == {(int(a), int(b)) for a, b in np.argwhere(d <= 4)}


def test_replicas_of_a_center_without_pairs(spark):
    x = np.random.default_rng(3).standard_normal((60, 4))
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "item_id long, vec array<double>")
    c = items.where("item_id < 6").select(F.col("item_id").cast("int").alias("center_id"), "vec", (F.col("item_id") % 2).cast("int").alias("sub_id"))
    got = {(r.sub_id, r.item_id) for r in mips.replicate_sql(items, c, 3).collect()}
    best = np.argsort(-(x[:6] @ x.T), axis=1)[:, :3]
    assert got == {(i % 2, int(j)) for i in range(6) for j in best[i]}


def test_asked_counts_weigh_as_rows_do(spark):
    x = np.random.default_rng(4).standard_normal((20, 3))
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "query_id long, vec array<double>")
    c = items.where("query_id < 5").select(F.col("query_id").cast("int").alias("center_id"), "vec", F.lit(1.0).alias("weight"))
    counted = items.withColumn("n", F.col("query_id") + 1)
    listed = counted.select(F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i"), "query_id", "vec").select((F.col("query_id") * 100 + F.col("i")).alias("query_id"), "vec")
    a, b = (sorted((r.center_id, r.weight) for r in centers.weight_by_queries(q, c, 2).collect()) for q in (counted, listed))
    assert a == b and sum(w for _, w in a) == 5 + 2 * 210


def test_a_beam_of_all_vertices_finds_all(monkeypatch):
    """In one dimension with copies the upper layers lead to vertices from which not all others are reached."""
    x = np.random.default_rng(0).integers(-3, 4, (47, 1)).astype(float)
    g = hnsw.build_bulk(np.arange(47), x, "l2", degree=4, degree0=8)
    walked = []
    monkeypatch.setattr(hnsw, "_walk", lambda graph, layer, *a, f=hnsw._walk: walked.append(layer is graph.layers[0]) or f(graph, layer, *a))
    ids, scores, stats = hnsw.search(g, x[:5], 5, 47)
    d = np.abs(x[:5] - x.T)
    want = np.lexsort((np.broadcast_to(np.arange(47), d.shape), d), axis=1)[:, :5]
    assert ids.tolist() == want.tolist() and (scores == -np.take_along_axis(d, want, 1)).all()
    assert not any(walked) and (stats.evals >= 47).all() and (stats.hops >= 47).all()


@pytest.mark.parametrize("k", [1, 7])
@pytest.mark.parametrize("metric", ["l2", "ip"])
def test_many_centers_are_ranked_in_small_blocks(monkeypatch, metric, k):
    """No block of scores outgrows a cache, and copies still go to the smaller position, pairs that are left out included."""
    rng = np.random.default_rng(9)
    q, x = rng.integers(-2, 3, (700, 4)).astype(float), rng.integers(-2, 3, (5000, 4)).astype(float)
    skip, cells = rng.random((700, 5000)) < 0.3, []
    monkeypatch.setattr(kernels, "rank_matrix", lambda *a, f=kernels.rank_matrix: cells.append(len(a[0]) * len(a[1])) or f(*a))
    row, col, score = kernels.best_pairs(q, x, np.arange(5000), k, metric, skip)
    assert max(cells) <= 1 << 20 and sum(cells) == 700 * 5000
    true = q @ x.T if metric == "ip" else -np.sqrt(((q[:, None] - x) ** 2).sum(axis=2))
    want = np.argsort(-np.where(skip, -np.inf, true), axis=1, kind="stable")[:, :k]
    assert (row.reshape(700, k) == np.arange(700)[:, None]).all() and (col.reshape(700, k) == want).all()
    assert (score.reshape(700, k) == np.take_along_axis(true, want, 1)).all()


@pytest.mark.parametrize("metric", ["l2", "ip"])
def test_nearest_rows_equal_a_full_sort(metric):
    """Copies tie exactly and go to the smaller position, also where columns are folded and where all rows are one."""
    rng = np.random.default_rng(7)
    for x, k in ((rng.integers(-4, 5, (700, 3)).astype(float), 5), (rng.integers(-4, 5, (90, 3)).astype(float), 89), (np.ones((300, 2)), 4), (np.ones((1, 2)), 0)):
        g = kernels.rank_matrix(x, x, metric)
        np.fill_diagonal(g, -np.inf)
        at, worth = kernels.nearest_rows(x, k, metric)
        assert (at == np.argsort(-g, axis=1, kind="stable")[:, :k]).all() and (worth == np.take_along_axis(g, at, 1)).all()


def test_both_graphs_of_a_part_share_neighbours(monkeypatch):
    """Blocks of a few rows are scored, once for both graphs, which are what each builds alone."""
    x = np.random.default_rng(8).standard_normal((1500, 5))
    ids, cells = np.arange(1500), []
    monkeypatch.setattr(kernels, "rank_matrix", lambda q, y, m, f=kernels.rank_matrix: cells.append(len(q) * len(y)) or f(q, y, m))
    alone = knn_graph.build(ids, x, 16), hnsw.build_bulk(ids, x)
    assert max(cells) <= 64 * 1500
    near = kernels.nearest_rows(x, 64, "l2")
    cells.clear()
    shared = knn_graph.build(ids, x, 16, near=near[0]), hnsw.build_bulk(ids, x, near0=near)
    assert sum(cells) < 1500 * 150
    for a, b in zip(alone, shared, strict=True):
        assert all((p.links == q.links).all() for p, q in zip(a.layers, b.layers, strict=True))


def test_models_follow_the_event_log(spark, tmp_path):
    """Requests, copies and paced batches come from the given tables, whatever their size."""
    import datetime

    n = 137
    ts = [datetime.datetime(2024, 1, 1) + datetime.timedelta(seconds=97 * i) for i in range(n)]
    pq.write_table(pa.table({"event_id": np.arange(n), "ts": pa.array(ts, pa.timestamp("us")), "value": np.arange(n) % 23 + 0.5}), tmp_path / "events.parquet")
    pq.write_table(pa.table({"o_orderkey": np.arange(n), "o_totalprice": np.arange(n) / 2}), tmp_path / "orders.parquet")
    at = str(tmp_path)
    assert {r.offered for r in QUERIES["dispatch_conserves_requests"](spark, at).collect()} == {n}
    assert QUERIES["failure_conserves_requests"](spark, at).first().offered == n
    run = QUERIES["w_failure"](spark, at)
    assert run.count() == 700 and round(run.agg(F.sum("served")).first()[0] + run.where("t = 699").first().queued) == n
    assert QUERIES["w_straggler"](spark, at).count() == 6
    copies = QUERIES["replica_placement"](spark, at).collect()
    assert sum(r.asked for r in copies) == 2 * n and len({(r.sub_id, r.executor_id) for r in copies}) == 20
    assert sorted(r.value for r in QUERIES["stream_rate_source"](spark, at).collect()) == list(range(n))


def test_bucket_search_ranks_all_that_share_a_code(spark):
    """The block search equals the join on codes followed by ranking, and makes no pairs."""
    from vecroute.baselines import lsh

    x = np.random.default_rng(6).standard_normal((400, 6))
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "item_id long, vec array<double>")
    q = items.where("item_id % 20 = 0").select(F.col("item_id").alias("query_id"), "vec")
    found = lsh.ask(q, items, 5, "cosine", 3, 4)
    plan = plan_of(found)
    assert "Join" not in plan and "MapInArrow" in plan
    pairs = {(r.query_id, r.item_id) for r in lsh.sign_candidates(q, items, lsh.planes(6, 3, 4)).collect()}
    u = kernels.unit(x)
    want = {(int(a), n + 1, int(i)) for a in range(0, 400, 20) for n, i in enumerate(sorted((i for b, i in pairs if b == a), key=lambda i: -(u[a] @ u[i]))[:5])}
    assert {(r.query_id, r.rank, r.item_id) for r in found.collect()} == want
