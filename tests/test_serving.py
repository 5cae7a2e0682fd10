"""Front end, workers, dispatch, leases, streams and SQL functions."""

import threading
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecroute.plans import builder
from vecroute.serving import api, dispatch, sqlext
from vecroute.sources import datasets
from vecroute.streaming import flows


@pytest.fixture(scope="module")
def served(spark, sf, tmp_path_factory):
    at = tmp_path_factory.mktemp("serving")
    items = datasets.items(spark, sf, "emb")
    items.write.parquet(str(at / "data"))
    maker = api.IndexConstructor(spark, str(at / "data"), str(at), "emb", builder.Params(m=20, w=4, kmeans_iters=4))
    version = maker.construct()
    queries = datasets.sampled_queries(items, 50).cache()
    return at, maker, version, api.QueryFrontend(spark, str(at), "emb", "l2"), queries


def test_front_end(served):
    _, _, _, front, queries = served
    para = api.QueryPara(branching=5, k=3)
    want = sorted(map(tuple, front.execute(queries, para).collect()))
    got, seen = [], threading.Event()
    future = front.execute_async(queries, para, lambda rows, error: (got.extend(rows), seen.set()))
    assert sorted(map(tuple, future.result(120))) == want == sorted(map(tuple, got)) and seen.wait(5)
    assert sorted(map(tuple, front.execute(queries, para).collect())) == want
    assert front.execute_planned(queries, para).count() == len(want)
    assert "plan" in sqlext.explain_choice(front.index(), 5)


def test_errors_reach_the_callback(served):
    front = served[3]
    caught = []
    with pytest.raises(Exception):  # noqa: B017, PT011
        front.execute_async(served[4].drop("vec"), callback=lambda rows, error: caught.append(error)).result(60)
    assert caught and caught[0] is not None
    with pytest.raises(ValueError):
        api.QueryFrontend(front.spark, str(served[0]), "emb", "ip").index()


def test_retry_is_whole():
    calls = []

    def flaky():
        calls.append(1)
        if len(calls) < 3:
            raise OSError("lost")
        return [1, 2]

    assert api.with_retry(flaky, 3, 0) == [1, 2]
    with pytest.raises(OSError):
        api.with_retry(lambda: (_ for _ in ()).throw(OSError()), 2, 0)


def test_refresh_is_seen(served):
    _, maker, first, front, queries = served
    assert front.catalog.newest() == first
    second = maker.refresh()
    assert front.catalog.newest() == second != first
    assert front.execute(queries, api.QueryPara(20, 1)).where("query_id = item_id").count() == queries.count()


def test_worker(served, spark, tmp_path):
    front, queries = served[3], served[4]
    queries.write.parquet(str(tmp_path / "asked"))
    worker = api.SubIndexWorker(front.index(), 0, str(tmp_path / "asked"), str(tmp_path / "out"), str(tmp_path / "ck"))
    worker.start(k=2).awaitTermination()
    worker.stop()
    assert spark.read.parquet(str(tmp_path / "out")).where("sub_id = 0").count() == 2 * queries.count()


# --- dispatch ---


def test_copies_lie_apart(spark):
    for subs, executors, copies in ((10, 10, 2), (7, 5, 3)):
        p = dispatch.place(spark, subs, executors, copies).collect()
        assert len({(r.sub_id, r.executor_id) for r in p}) == subs * copies
    with pytest.raises(ValueError):
        dispatch.place(spark, 2, 2, 3)


def test_straggler_shape():
    out = {}
    for name, scenario in dispatch.straggler_scenarios([0.1, 0.3, 0.5, 1.0]).items():
        s = dispatch.simulate(*scenario)
        out[float(name)] = s[s.t >= 30].groupby("t").served.sum().mean()
    assert out[1.0] == pytest.approx(700) and out[0.5] > 0.99 * 700 and out[0.3] > 0.98 * 700 and out[0.1] < out[0.3]


def test_equal_shares_lose_more_than_backlog():
    lost = {}
    for policy in ("equal", "backlog"):
        s = dispatch.simulate(*dispatch.straggler_scenarios([0.3], policy=policy)["0.30"])
        lost[policy] = s[s.t >= 30].groupby("t").served.sum().mean()
    assert lost["backlog"] > lost["equal"]


def test_failure_dips_and_recovers():
    s = dispatch.simulate(*dispatch.failure_scenario()["failure"]).groupby("t").served.sum()
    assert s[250] == pytest.approx(700) and s[300:305].min() < 650 and s[500:505].min() < 650 and s[620:].min() >= 699
    total = dispatch.simulate(*dispatch.failure_scenario()["failure"])
    assert total.served.sum() + total[total.t == 699].queued.sum() == pytest.approx(700 * 700)


def test_a_group_without_members_queues():
    import pandas as pd

    offered = pd.DataFrame([(t, 0, 10) for t in range(5)], columns=["t", "sub_id", "requests"])
    hosts = pd.DataFrame([(0, 0), (0, 1)], columns=["sub_id", "executor_id"])
    down = pd.DataFrame([(t, e, 0.0) for t in range(5) for e in range(2)], columns=["t", "executor_id", "rate"])
    out = dispatch.simulate(offered, hosts, down)
    assert out.served.sum() == 0 and out[out.t == 4].queued.sum() == 50


def test_leases():
    r = dispatch.Registry(ttl=10)
    a = r.acquire("sub0", "a", 0)
    assert r.acquire("sub0", "b", 5) is None and r.renew("sub0", a, 9) and not r.renew("sub0", a, 30)
    main, spare = dispatch.Monitor(r, "main"), dispatch.Monitor(r, "spare")
    restarted = main.tick(30)
    assert [i for i, _ in restarted] == ["sub0"] and spare.tick(31) == []
    assert not r.renew("sub0", a, 32) and r.renew("sub0", restarted[0][1], 32)
    assert spare.tick(45) and main.tick(46) == []  # the master lease lapsed and the spare took over


# --- streams ---


def request_files(spark, index_items, folder, order=None):
    rows = index_items.where("item_id % 40 = 3").select(F.col("item_id").alias("query_id"), F.timestamp_seconds(F.col("item_id")).alias("ts"), "vec")
    rows.repartition(3).write.parquet(folder)
    return rows


def test_stream_equals_batch(served, spark, sf, tmp_path):
    index, items = served[3].index(), datasets.items(spark, sf, "emb")
    rows = request_files(spark, items, str(tmp_path / "in"))
    flows.serve(flows.requests(spark, str(tmp_path / "in")), index, 5, 3, str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).select("query_id", "rank", "item_id")
    want = builder.ask(index, rows.select("query_id", "vec"), 5, 3).select("query_id", "rank", "item_id")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    q = flows.routed(flows.requests(spark, str(tmp_path / "in")), index, 2).writeStream.format("memory").queryName("routed_requests").option("checkpointLocation", str(tmp_path / "ck2")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("routed_requests").select("query_id").distinct().count() == rows.count()


def test_retried_requests_count_once(spark, sf, tmp_path):
    items = datasets.items(spark, sf, "emb")
    for k in range(2):
        request_files(spark, items, str(tmp_path / f"in/{k}"))
    stream = spark.readStream.schema(flows.REQUEST_DDL).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    q = flows.without_retries(stream, "10000 seconds").writeStream.format("memory").queryName("deduped").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("deduped").count() == items.where("item_id % 40 = 3").count()


def test_gather(spark, tmp_path):
    ddl = "query_id long, ts timestamp, sub_id int, expected int, item_id long, score double"
    rows = [(1, 0, 2, 10, 0.5), (1, 1, 2, 11, 0.9), (1, 1, 2, 10, 0.5), (2, 0, 2, 20, 0.1), (3, 0, 1, None, None)]
    df = spark.createDataFrame([(q, None, s, e, i, x) for q, s, e, i, x in rows], ddl)
    df.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(ddl).parquet(str(tmp_path / "in"))
    q = flows.gather(stream, 2, timeout_ms=3000).writeStream.format("memory").queryName("gathered").option("checkpointLocation", str(tmp_path / "ck")).trigger(processingTime="1 second").start()
    got, until = [], time.time() + 45
    try:
        while len(got) < 3 and time.time() < until and q.exception() is None:
            time.sleep(1)
            got = sorted((r.query_id, r.rank, r.item_id, r.complete) for r in spark.table("gathered").collect())
    finally:
        q.stop()
    assert got == [(1, 1, 11, True), (1, 2, 10, True), (2, 1, 20, False)]


def test_late_requests_and_sessions(spark, tmp_path):
    ts = F.timestamp_seconds(F.col("id") * 60)
    spark.range(0, 100).select(F.col("id").alias("query_id"), ts.alias("ts"), F.array(F.lit(1.0)).alias("vec")).coalesce(1).write.parquet(str(tmp_path / "in"))
    counted = flows.windowed_counts(flows.requests(spark, str(tmp_path / "in")), "10 minutes", "5 minutes", "1 minute")
    q = counted.writeStream.outputMode("complete").format("memory").queryName("sliding").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination()
    batch = flows.windowed_counts(spark.read.parquet(str(tmp_path / "in")), "10 minutes", "5 minutes")
    assert spark.table("sliding").exceptAll(batch).isEmpty() and spark.table("sliding").agg(F.sum("n")).first()[0] == 200
    sessions = flows.session_counts(spark.read.parquet(str(tmp_path / "in")).withColumn("k", F.floor(F.col("query_id") / 50)), "k", "2 minutes").collect()
    assert [r.n for r in sessions] == [50, 50]


def test_matched_within(spark):
    asked = spark.sql("SELECT id AS query_id, timestamp_seconds(id) AS ts FROM range(10)")
    answered = spark.sql("SELECT id AS query_id, timestamp_seconds(id + id) AS ts FROM range(10)")
    assert flows.matched_within(asked, answered, "5 seconds").count() == 6


def test_hot_items(spark, sf):
    log = datasets.hot_log(spark, sf)
    assert len(flows.hot_sketch(log).first()[0]) > 100
    timed = log.withColumn("ts", F.timestamp_seconds(F.lit(0)))
    assert flows.hot_items(timed).agg(F.sum("n")).first()[0] == log.count()


# --- SQL functions ---


def test_sql_functions(served, spark, sf):
    sqlext.register(spark, served[3].index(), "t")
    items = datasets.items(spark, sf, "emb")
    items.createOrReplaceTempView("items")
    datasets.sampled_queries(items, 100).createOrReplaceTempView("queries")
    exact = spark.sql("SELECT q.query_id, e.rank, e.item_id FROM queries q, LATERAL exact_search(q.vec, 3) e")
    want = sqlext.exact_sql(spark, 3).select("query_id", "rank", "item_id")
    assert exact.exceptAll(want).isEmpty()
    routed = spark.sql("SELECT q.query_id, e.rank, e.item_id FROM queries q, LATERAL ann_search(q.vec, 3, 20, 500) e")
    assert routed.exceptAll(want).isEmpty()
    parts = spark.sql("SELECT q.query_id, r.sub_id FROM queries q, LATERAL route(q.vec, 20) r")
    assert parts.count() == 4 * spark.table("queries").count()
    ranked = spark.sql("SELECT top_ids(item_id, score_ip(vec, vec)) AS ids FROM items WHERE item_id < 5").first().ids
    assert sorted(ranked) == [0, 1, 2, 3, 4]
    assert np.allclose(spark.sql("SELECT vec_mean(vec) AS m FROM items").first().m, np.mean([r.vec for r in items.collect()], axis=0))
    assert spark.table("t_centers").count() >= 20
