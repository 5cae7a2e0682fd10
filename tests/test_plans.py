"""Cuts, placement, routing, replicas, merging and whole indexes."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecroute import experiments
from vecroute.baselines import kdtree, lsh, quantised, random_split
from vecroute.functions import kernels, measures, vectors
from vecroute.graphs import walk_df
from vecroute.plans import builder, centers, cutgraph, mips, router, sampling, search
from vecroute.runtime import table
from vecroute.serving import planner, tuning
from vecroute.sources import datasets, files


@pytest.fixture(scope="module")
def emb(spark, sf):
    items = datasets.items(spark, sf, "emb").cache()
    queries = items.where("item_id % 7 = 3").select(F.col("item_id").alias("query_id"), "vec").cache()
    return items, queries, search.exact_topk_blocks(queries, items, 10).cache()


@pytest.fixture(scope="module")
def index(emb):
    return builder.build(emb[0], builder.Params(m=30, w=5, kmeans_iters=5))


# --- cuts ---


def ring(n):
    return [{(i - 1) % n: 1.0, (i + 1) % n: 1.0} for i in range(n)]


def test_ring_is_cut_in_three_places():
    part = cutgraph.partition(ring(12), np.ones(12), 3)
    assert np.bincount(part).tolist() == [4, 4, 4] and cutgraph.cut_size(ring(12), part) == 3


def test_blobs_are_kept_whole():
    near = [{j: 1.0 for j in range(30) if j != i} for i in range(30)] + [{30 + j: 1.0 for j in range(30) if j != i} for i in range(30)]
    part = cutgraph.partition(near, np.ones(60), 2)
    assert cutgraph.cut_size(near, part) == 0


@pytest.mark.parametrize("w", [2, 5, 10])
def test_cut_is_balanced_and_beats_chance(w):
    rng = np.random.default_rng(w)
    x = rng.standard_normal((300, 4))
    links = np.argsort(((x[:, None] - x[None]) ** 2).sum(axis=2), axis=1)[:, 1:9]
    near, weight = cutgraph.symmetric(links), rng.integers(1, 20, 300).astype(float)
    part = cutgraph.partition(near, weight, w)
    load = np.bincount(part, weights=weight, minlength=w)
    assert (load > 0).all() and load.max() <= 1.06 * load.mean() + weight.max()
    assert cutgraph.cut_size(near, part) < 0.7 * cutgraph.cut_size(near, cutgraph.random(300, w))


def test_label_propagation(spark):
    edges = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (0, 2, 1.0), (3, 4, 1.0), (4, 5, 1.0), (3, 5, 1.0), (2, 3, 0.1)], "a int, b int, weight double")
    labels = spark.createDataFrame([(i, i) for i in range(6)], "node int, sub_id int")
    got = {r.node: r.sub_id for r in cutgraph.label_prop(edges, labels, 4).collect()}
    assert got[0] == got[1] == got[2] and got[3] == got[4] == got[5] != got[0]


# --- placement and routing ---


def test_every_item_is_placed_once(emb, index):
    n = emb[0].count()
    assert index.placement.count() == n == index.placement.select("item_id").distinct().count()
    assert index.graphs.agg(F.sum("n")).first()[0] == n


def test_assignment_ways_agree(emb, index):
    ways = [router.assign(emb[0], index.meta, m).select("item_id", "sub_id") for m in ("exact", "graph")] + [router.assign_sql(emb[0], index.centers).select("item_id", "sub_id")]
    assert ways[0].exceptAll(ways[2]).isEmpty()
    assert ways[0].exceptAll(ways[1]).count() <= 0.02 * emb[0].count()


def test_access_grows_with_branching(emb, index):
    sets = {}
    for k in (1, 2, 5, 30):
        rows = router.route(emb[1], index.meta, k, "exact").collect()
        sets[k] = {(r.query_id, r.sub_id) for r in rows}
    assert sets[1] < sets[2] < sets[5] < sets[30]
    assert len(sets[1]) == emb[1].count() and len(sets[30]) == 5 * emb[1].count()


def test_scaling_an_item_leaves_its_part(spark, sf):
    items = datasets.items(spark, sf, "emb_scaled")
    c = centers.spherical(items, 20, 4).withColumn("sub_id", F.col("center_id") % 4)
    a = router.assign_sql(items, c, "ip").select("item_id", "sub_id")
    b = router.assign_sql(items.withColumn("vec", vectors.scale(F.col("vec"), F.lit(5.0))), c, "ip").select("item_id", "sub_id")
    assert a.exceptAll(b).isEmpty()
    assert c.select(F.abs(vectors.norm(F.col("vec")) - 1).alias("e")).agg(F.max("e")).first()[0] < 1e-9


def test_precision_never_falls_with_branching(emb, index):
    p = [measures.precision(builder.ask(index, emb[1], k, 10, mode="exact", exact=True), emb[2], 10).first()[0] for k in (1, 3, 10, 30)]
    assert p == sorted(p) and p[-1] == 1.0


def test_radius_search_by_routing(emb, index):
    every = {(q.query_id, x.item_id) for q in emb[1].collect() for x in emb[0].collect() if math.dist(q.vec, x.vec) <= 1.2}
    found = [{(r.query_id, r.item_id): r.score for r in builder.within(index, emb[1], k, -1.2, "exact").collect()} for k in (1, 30)]
    assert set(found[0]) <= set(found[1]) == every
    assert min(found[1].values()) >= -1.2


@pytest.mark.parametrize("metric", ["l2", "cosine", "ip"])
def test_pairs_from_a_threshold(metric):
    rng = np.random.default_rng(5)
    q, x = rng.normal(size=(7, 4)), rng.normal(size=(90, 4))
    x[1] = q[0]
    least = {"l2": -1.0, "cosine": 0.7, "ip": 2.0}[metric]
    row, ids, s = kernels.pairs_from(q, x, np.arange(90) + 100, least, metric)
    want = kernels.score_matrix(q, x, metric)
    assert set(zip(row.tolist(), (ids - 100).tolist(), strict=True)) == set(map(tuple, np.argwhere(want >= least).tolist()))
    assert np.allclose(s, want[row, ids - 100], atol=1e-7) and (s >= least).all()
    if metric == "l2":
        assert kernels.pairs_from(q, x, np.arange(90), 0.0, "l2")[1].tolist() == [1] and not kernels.pairs_from(q, x, np.arange(90), 0.1, "l2")[1].size
    assert not kernels.pairs_from(q[:0], x, np.arange(90), least, metric)[0].size
    assert not kernels.pairs_from(q, x[:0], np.arange(0), least, metric)[0].size


def test_curve_in_one_pass_equals_single_runs(emb, index):
    got = {r.branching: r for r in experiments.curve(index, emb[1], emb[2], (1, 5)).collect()}
    for k in (1, 5):
        one = measures.precision(builder.ask(index, emb[1], k, 10), emb[2], 10).first()[0]
        assert got[k].precision == pytest.approx(one, abs=0.02)
    assert got[1].access_rate == pytest.approx(0.2)


def test_copies(emb):
    two = builder.build(emb[0], builder.Params(m=30, w=5, kmeans_iters=5, copies=2))
    assert two.placement.groupBy("item_id").count().where("count <> 2").isEmpty()
    assert measures.storage(two.placement, emb[0].count()).first().net_overhead == 1


def test_merge_counts_copies_once(spark):
    rows = [(1, 0, 10, -1.0), (1, 1, 10, -1.0), (1, 0, 11, -2.0), (1, 1, 12, -2.0), (2, 0, 5, -3.0)]
    got = search.merge_top_k(spark.createDataFrame(rows, "query_id long, sub_id int, item_id long, score double"), 2).collect()
    assert sorted((r.query_id, r.rank, r.item_id) for r in got) == [(1, 1, 10), (1, 2, 11), (2, 1, 5)]
    lists = search.as_lists(search.merge_top_k(spark.createDataFrame(rows, "query_id long, sub_id int, item_id long, score double"), 3)).collect()
    assert {r.query_id: [a.item_id for a in r.answers] for r in lists} == {1: [10, 11, 12], 2: [5]}


# --- inner product ---


def test_strong_item_goes_everywhere(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((20, 8))
    x /= np.linalg.norm(x, axis=1)[:, None]
    x = np.vstack([x, 50 * np.ones(8) / 8**0.5])
    items = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "item_id long, vec array<double>")
    c = spark.createDataFrame([(i, x[i].tolist(), 1.0, i % 3) for i in range(6)], "center_id int, vec array<double>, weight double, sub_id int")
    got = {(r.sub_id, r.item_id) for r in mips.replicate_sql(items, c, 2).collect()}
    for r in range(6):
        if x[r] @ x[20] > sorted(x[:20] @ x[r])[-2]:
            assert (r % 3, 20) in got
    ids, matrix = centers.as_matrix(c)
    meta = router.MetaIndex(ids, matrix, np.array([i % 3 for i in range(6)], np.int32), "ip")
    assert {(r.sub_id, r.item_id) for r in mips.replicate(items, meta, 2).collect()} == got
    assert mips.replicate(items, meta, 0).isEmpty()
    assert 20 in {r.item_id for r in mips.replicate(items, meta, 2, "norm_top", 0.2).collect()}
    assert mips.replicate(items, meta, 2, "lsh").count() > 0


def test_replicas_raise_precision(spark, sf01):
    items = datasets.items(spark, sf01, "hashtext").cache()
    q = items.where("item_id % 11 = 3").select(F.col("item_id").alias("query_id"), "vec").cache()
    t = search.exact_topk_blocks(q, items, 10, "ip").cache()
    p = {}
    for r in (0, 5, 20):
        index = builder.build(items, builder.Params(metric="ip", m=50, w=10, r=r, kmeans_iters=6, builder="bulk"))
        p[r] = measures.precision(builder.ask(index, q, 1, 10), t, 10).first()[0]
    assert p[0] < p[5] < p[20] and p[20] >= 0.9 and p[20] - p[0] >= 0.3


# --- gates of whole methods ---


def test_routed_line5_gates(spark, sf01):
    items = datasets.items(spark, sf01, "line5").where("item_id % 3 = 0").cache()
    q = items.where("item_id % 120 = 3").select(F.col("item_id").alias("query_id"), "vec").cache()
    t = search.exact_topk_blocks(q, items, 10).cache()
    index = builder.build(items, builder.Params(m=200, w=10, kmeans_iters=6, builder="bulk"))
    c = {r.branching: r.precision for r in experiments.curve(index, q, t, (1, 5, 10)).collect()}
    assert c[1] >= 0.75 and c[5] >= 0.93 and c[10] >= 0.95
    assert measures.balance(index.placement, "sub_id").first().peak <= 1.15
    best = tuning.match_precision(index, q, t, 0.9, [1, 2, 5], [20, 100])
    split = random_split.build(items, 10, builder="bulk")
    work = experiments._work(split.partials(q, 10, 5), q.count())
    assert best.precision >= 0.9 and best.evals < work


def test_cosine_index_equals_cosine_scan(spark, sf):
    items = datasets.items(spark, sf, "emb_scaled")
    q = datasets.sampled_queries(items)
    index = builder.build(items, builder.Params(metric="cosine", m=20, w=4, kmeans_iters=4))
    t = search.exact_topk(q, items, 5, "cosine").select("query_id", "rank", "item_id")
    assert builder.ask(index, q, 1_000, 5, l=10_000, mode="exact").select("query_id", "rank", "item_id").exceptAll(t).isEmpty()


def test_catalog_and_versions(spark, emb, index, tmp_path):
    catalog = builder.Catalog(spark, str(tmp_path / "idx"))
    first = catalog.commit(index)
    a = builder.ask(catalog.load(), emb[1], 5, 10, mode="exact")
    b = builder.ask(index, emb[1], 5, 10, mode="exact")
    assert a.exceptAll(b).isEmpty()
    second = catalog.refresh(emb[0].where("item_id % 2 = 0"), builder.with_params(index.params, m=10))
    assert catalog.newest() == second != first
    assert catalog.load(first).n == emb[0].count() and catalog.load().n == emb[0].where("item_id % 2 = 0").count()


# --- baselines ---


def test_baselines(spark, emb):
    items, q, t = emb
    assert measures.precision(lsh.ask(q, items, 10, "cosine", 12, 3), t, 10).first()[0] > 0.7
    pq = quantised.fit_items(items, 8)
    plain = measures.precision(quantised.ask(items, q, pq, 10), t, 10).first()[0]
    again = measures.precision(quantised.ask(items, q, pq, 10, rerank=60), t, 10).first()[0]
    graph = measures.precision(random_split.build(items, 1).ask(q, 10), t, 10).first()[0]
    assert plain < again <= 1 and plain < graph and graph > 0.95
    rotated = quantised.fit_items(items, 8, rotate=True)
    assert np.allclose(rotated.rotation @ rotated.rotation.T, np.eye(64), atol=1e-8)
    bounded = measures.precision(kdtree.ask(items, q, 2, 10, trees=4, max_leaves=4), t, 10).first()[0]
    assert bounded < 1
    ip = lsh.ask(q, datasets.items(spark, "/root/testdata/sf0.001", "emb_scaled"), 10, "ip", 8, 3)
    assert ip.count() > 0
    with pytest.raises(ValueError):
        random_split.replicated(items, q, 2, 5, most_rows=10)


def test_kd_cells_are_balanced(spark, sf):
    cells = kdtree.kd_route(datasets.items(spark, sf, "line5"), 3, 5)
    assert measures.balance(cells, "sub_id").first().peak < 1.3


def test_supersteps_find_what_the_kernel_finds(spark, emb):
    from vecroute.graphs import knn_graph

    items = emb[0].where("item_id < 120").cache()
    edges = knn_graph.build_rows(items, 8).select("node", "neighbour")
    both = edges.union(edges.select(F.col("neighbour").alias("node"), F.col("node").alias("neighbour"))).distinct()
    q = items.where("item_id % 40 = 3").select(F.col("item_id").alias("query_id"), "vec")
    got = walk_df.search(q, both, items, 0, 5, 200, max_hops=40, expand=16)
    want = search.exact_topk(q, items, 5)
    assert got.select("query_id", "item_id").exceptAll(want.select("query_id", "item_id")).isEmpty()


# --- the rest ---


def test_samples(spark, sf):
    x = datasets.items(spark, sf, "line5")
    assert 700 < sampling.uniform(x, 1000).count() < 1300
    assert sampling.by_hash(x, 4).count() == sampling.by_hash(x.repartition(7), 4).count()


def test_two_levels_of_centres(spark, sf):
    c = centers.hierarchical(datasets.items(spark, sf, "line5"), 4, 6, 3).collect()
    assert 12 <= len(c) <= 24 and len({r.center_id for r in c}) == len(c)


def test_rejects(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [float("nan"), 0.0]), (5, [0.0, 0.0]), (6, [None, 1.0]), (7, [float("inf"), 1.0])]
    good, bad = vectors.split_valid(spark.createDataFrame(rows, "item_id long, vec array<double>"), 2, "cosine")
    assert [r.item_id for r in good.collect()] == [1]
    assert {r.item_id: r.reason for r in bad.collect()} == {2: "null", 3: "length", 4: "not finite", 5: "zero norm", 6: "null component", 7: "not finite"}


def test_vector_files(spark, tmp_path):
    x = np.arange(12, dtype=float).reshape(4, 3)
    for kind in ("f", "b"):
        assert (files.decode_vecs(files.encode_vecs(x, kind), kind) == x).all()
    (tmp_path / "a.fvecs").write_bytes(files.encode_vecs(x))
    got = files.read_vecs(spark, str(tmp_path / "a.fvecs")).orderBy("item_id").collect()
    assert [r.vec for r in got] == x.tolist()
    with pytest.raises(ValueError):
        files.decode_vecs(files.encode_vecs(x)[:-1])


def test_planner():
    assert planner.choose(1000, 64, 10) == "scan" and planner.choose(10**9, 96, 1000) == "routed"
    assert planner.choose(10**9, 96, 1000, selectivity=1e-7) == "scan"
    assert planner.over_fetch(10, 0.1) > 100 and planner.parts_for(10**9, 96) > 1000


def test_measures(emb):
    _, _, t = emb
    assert measures.precision(t, t, 10).first()[0] == 1 and measures.recall_top1(t, t, 1).first()[0] == 1
    assert measures.precision(t.where("query_id = 3"), t, 10).first()[0] == pytest.approx(1 / t.select("query_id").distinct().count())
    assert measures.raw_bytes(10**9, 128) == 512 * 10**9 and measures.speedup(3, 2) == 1.5


def test_unindexable_params():
    for bad in ({"metric": "hamming"}, {"m": 3, "w": 5}):
        with pytest.raises(ValueError):
            builder.Params(**bad)


def test_size_curve_and_walks_take_all_rows(spark, sf):
    whole = table(spark, sf, "lineitem").count()
    curve = experiments._work_by_size(spark, sf).orderBy("n").collect()
    assert curve[-1].n == whole and all(r.evals < r.n * 1.01 for r in curve)
    assert curve[-1].evals / curve[0].evals < 0.5 * curve[-1].n / curve[0].n
    walks = {r.graph: r for r in experiments._walks(spark, sf).collect()}
    assert set(walks) == {"flat", "layered", "flat, beam", "layered, beam"} and walks["layered"].evals < walks["flat"].evals
