"""Registered queries of walks, streams, serving, dispatch and SQL functions.

Each runs the engine's own parts with fixed ingredients or exhaustive settings, so that
SQL gives the same rows.
"""

from __future__ import annotations

from types import SimpleNamespace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecroute.baselines import kdtree, lsh
from vecroute.graphs import walk_df
from vecroute.plans import builder, router, search
from vecroute.registry import query
from vecroute.runtime import Workspace, ship, table
from vecroute.serving import api, dispatch, sqlext
from vecroute.sources import datasets
from vecroute.streaming import flows
from vecroute.workloads import K, SQL_ANSWER, ctes, fixed, meta_of, sql_det, sql_route, sql_truth, tidy

#: Exhaustive settings of a small index: every part, and a beam of all items.
ALL = 1_000_000


def _small_index(spark: SparkSession, x: DataFrame) -> builder.Index:
    return builder.build(x, builder.Params(m=20, w=4, kmeans_iters=4))


# --- walks and baselines -----------------------------------------------------------------------


@query("walk_supersteps_saturated", f"WITH {ctes()}, {sql_truth('l2', 5)} {SQL_ANSWER}")
def _supersteps(spark: SparkSession, d: str) -> DataFrame:
    """The walk as joins over a ring with chords, every vertex expanded: the exact answer."""
    ws = Workspace(spark, "supersteps")
    x, q, _ = fixed(spark, d)
    x = ws.keep(x, "items")
    n = x.count()
    node = F.row_number().over(router.Window.orderBy("item_id")) - 1  # of a small set that serves as a graph
    numbered = ws.keep(x.select("item_id", node.cast("long").alias("node")), "nodes")
    steps = F.explode(F.array(*[F.lit(s) for s in (1, 2, 4, 16, 64, 256)]))
    hops = numbered.select(F.col("item_id"), "node", steps.alias("step")).select(F.col("item_id").alias("node"), F.pmod(F.col("node") + F.col("step"), F.lit(n)).alias("at")).join(numbered.select(F.col("item_id").alias("neighbour"), F.col("node").alias("at")), "at").select("node", "neighbour").where("node <> neighbour")
    entry = numbered.agg(F.min("item_id")).first()[0]
    return tidy(walk_df.search(q, ws.keep(hops.distinct(), "edges"), x, entry, 5, ALL, expand=ALL))


@query("kd_cells", f"WITH e AS ({datasets.SQL['line5']}), a AS (SELECT item_id, vec, CAST(vec[1] > (SELECT quantile_cont(vec[1], 0.5) FROM e) AS INTEGER) AS s FROM e), b AS (SELECT a.item_id, a.vec, 2 * a.s + CAST(a.vec[2] > m.c AS INTEGER) AS s FROM a JOIN (SELECT s, quantile_cont(vec[2], 0.5) AS c FROM a GROUP BY 1) m ON m.s = a.s) SELECT CAST(2 * b.s + CAST(b.vec[3] > m.c AS INTEGER) AS INTEGER) AS sub_id, count(*) AS n FROM b JOIN (SELECT s, quantile_cont(vec[3], 0.5) AS c FROM b GROUP BY 1) m ON m.s = b.s GROUP BY 1")
def _kd_cells(spark: SparkSession, d: str) -> DataFrame:
    return kdtree.kd_route(datasets.items(spark, d, "line5"), 3, 5).groupBy("sub_id").agg(F.count(F.lit(1)).alias("n"))


_PLANES = lsh.planes(64, 2, 4)
_SQL_CODE = ", ".join("SELECT item_id, {t} AS tbl, CAST({c} AS BIGINT) AS code FROM e".format(t=t, c=" + ".join(f"CASE WHEN list_inner_product(vec, {[float(v) for v in row]}) > 0 THEN {1 << i} ELSE 0 END" for i, row in enumerate(rows))) for t, rows in enumerate(_PLANES)).replace(", SELECT", " UNION ALL SELECT")


@query("lsh_code_sizes", f"WITH e AS ({datasets.SQL['emb']}), c AS ({_SQL_CODE}) SELECT tbl, code, count(*) AS n FROM c GROUP BY 1, 2")
def _lsh_codes(spark: SparkSession, d: str) -> DataFrame:
    """Items per sign code, with planes written into both queries."""
    x = datasets.items(spark, d, "emb")
    return x.select(F.posexplode(lsh.codes(F.col("vec"), _PLANES)).alias("tbl", "code")).groupBy("tbl", "code").agg(F.count(F.lit(1)).alias("n"))


# --- serving -----------------------------------------------------------------------------------------


@query("frontend_saturated", f"WITH {ctes()}, {sql_truth('l2')} {SQL_ANSWER}")
def _frontend(spark: SparkSession, d: str) -> DataFrame:
    """Construct, commit, load by the front end, ask: with exhaustive settings the exact answer."""
    ship(spark)
    ws = Workspace(spark, "frontend")
    x, q, _ = fixed(spark, d)
    ws.keep(x, "data")
    maker = api.IndexConstructor(spark, f"{ws.base}/001-data", ws.base, "emb", builder.Params(m=20, w=4, kmeans_iters=4))
    maker.construct()
    front = api.QueryFrontend(spark, ws.base, "emb", "l2")
    return tidy(front.execute(q, api.QueryPara(branching=20, k=K, l=ALL)))


def logged_requests(spark: SparkSession, d: str, seconds: int) -> pd.DataFrame:
    """The events as requests to ten parts, folded onto so many seconds."""
    return dispatch.arrivals(table(spark, d, "events").select(F.col("event_id").alias("request_id"), "ts"), seconds, 10)


@query("dispatch_conserves_requests", "SELECT share AS scenario, n AS offered FROM (SELECT unnest(['0.10', '0.30', '0.50', '1.00']) AS share), (SELECT count(*) AS n FROM events)")
def _conserves(spark: SparkSession, d: str) -> DataFrame:
    """Of a straggler's run: what was served, and what waits at the end, is what was asked."""
    ship(spark)
    run = dispatch.run_scenarios(spark, dispatch.straggler_scenarios([0.1, 0.3, 0.5, 1.0], offered=logged_requests(spark, d, 60)))
    return run.groupBy("scenario").agg(F.round(F.sum("served") + F.sum(F.when(F.col("t") == 59, F.col("queued")).otherwise(0.0))).cast("long").alias("offered"))


@query("failure_conserves_requests", "SELECT count(*) AS offered FROM events")
def _failure_conserves(spark: SparkSession, d: str) -> DataFrame:
    """No request is lost when an executor dies and comes back."""
    ship(spark)
    run = dispatch.run_scenarios(spark, dispatch.failure_scenario(offered=logged_requests(spark, d, 700)))
    return run.agg(F.round(F.sum("served") + F.sum(F.when(F.col("t") == 699, F.col("queued")).otherwise(0.0))).cast("long").alias("offered"))


# --- SQL functions ----------------------------------------------------------------------------------------


@query("sql_exact_search", f"WITH {ctes()}, {sql_truth('l2', 3)} {SQL_ANSWER}")
def _sql_exact(spark: SparkSession, d: str) -> DataFrame:
    ship(spark)
    x, q, _ = fixed(spark, d)
    sqlext.register(spark, _small_index(spark, x), "vr")
    q.createOrReplaceTempView("vr_fixed_queries")
    return tidy(spark.sql("SELECT q.query_id, e.rank, e.item_id, e.score FROM vr_fixed_queries q, LATERAL exact_search(q.vec, 3) e"))


@query("sql_ann_search_saturated", f"WITH {ctes()}, {sql_truth('l2', 3)} {SQL_ANSWER}")
def _sql_ann(spark: SparkSession, d: str) -> DataFrame:
    ship(spark)
    x, q, _ = fixed(spark, d)
    sqlext.register(spark, _small_index(spark, x), "vr")
    q.createOrReplaceTempView("vr_fixed_queries")
    return tidy(spark.sql(f"SELECT q.query_id, e.rank, e.item_id, e.score FROM vr_fixed_queries q, LATERAL ann_search(q.vec, 3, 1000, {ALL}) e"))


@query("sql_top_ids", "SELECT user_id, array_to_string(list(event_id ORDER BY value DESC, event_id), ',') AS ids FROM events GROUP BY 1")
def _sql_top(spark: SparkSession, d: str) -> DataFrame:
    """The grouped top-list function, called from SQL."""
    ship(spark)
    sqlext.register(spark)
    table(spark, d, "events").createOrReplaceTempView("vr_events")
    return spark.sql("SELECT user_id, array_join(transform(top_ids(event_id, value), i -> cast(i AS string)), ',') AS ids FROM vr_events GROUP BY user_id")


# --- streams ------------------------------------------------------------------------------------------------


def _drained(stream: DataFrame, at: str, name: str, mode: str = "append") -> DataFrame:
    """A stream run to its end into files (or, for whole results, memory), read back."""
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/checkpoint-{name}").trigger(availableNow=True)
    if mode == "append":
        run = writer.format("parquet").option("path", f"{at}/{name}").start()
        run.awaitTermination()
        return stream.sparkSession.read.schema(stream.schema).parquet(f"{at}/{name}")
    run = writer.format("memory").queryName(f"vr_{name}").start()
    run.awaitTermination()
    return stream.sparkSession.table(f"vr_{name}")


def _requests(spark: SparkSession, d: str, ws: Workspace, copies: int = 1) -> tuple[DataFrame, DataFrame]:
    """The fixed queries as a stream of files, ``copies`` times over, and as a table."""
    _, q, _ = fixed(spark, d)
    for k in range(copies):
        q.select("query_id", F.timestamp_seconds(F.col("query_id")).alias("ts"), "vec").repartition(2).write.mode("append").parquet(f"{ws.base}/requests")
    return flows.requests(spark, f"{ws.base}/requests"), q


@query("stream_routed", f"WITH {ctes()}, {sql_route('l2')} SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 2")
def _stream_routed(spark: SparkSession, d: str) -> DataFrame:
    """Requests routed as they come."""
    ship(spark)
    ws = Workspace(spark, "stream-routed")
    stream, _ = _requests(spark, d, ws)
    index = SimpleNamespace(meta=meta_of(fixed(spark, d)[2], "l2"))
    return _drained(flows.routed(stream, index, 2), ws.base, "routed").select("query_id", "sub_id")


@query("stream_without_retries", f"WITH {ctes()} SELECT query_id FROM q")
def _stream_retries(spark: SparkSession, d: str) -> DataFrame:
    """Each request was sent three times and counts once."""
    ws = Workspace(spark, "stream-retries")
    stream, _ = _requests(spark, d, ws, 3)
    return _drained(flows.without_retries(stream, "30 days"), ws.base, "once").select("query_id")


@query("stream_sliding_windows", "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start FROM events UNION ALL SELECT CASE WHEN ts < time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 30 MINUTE THEN time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 30 MINUTE ELSE time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 30 MINUTE END FROM events) GROUP BY 1")
def _stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    ws = Workspace(spark, "stream-sliding")
    source = spark.readStream.schema(table(spark, d, "events").schema).parquet(f"{d.rstrip('/')}/events.parquet*")
    counted = flows.windowed_counts(source.withColumn("ts", F.col("ts").cast("timestamp")), "1 hour", "30 minutes", "30 days")
    return _drained(counted, ws.base, "sliding", "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sessions", "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def _stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    """Sessions by a gap of six hours; the batch form of the streaming plan."""
    e = table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    return flows.session_counts(e, "user_id", "6 hours").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_hot_counts", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, CAST(floor(value) AS BIGINT) AS item_id, count(*) AS n FROM events GROUP BY 1, 2")
def _stream_hot(spark: SparkSession, d: str) -> DataFrame:
    """Hits per item and hour, for centre weights by use."""
    ws = Workspace(spark, "stream-hot")
    source = spark.readStream.schema(table(spark, d, "events").schema).parquet(f"{d.rstrip('/')}/events.parquet*")
    hits = source.select(F.col("ts").cast("timestamp").alias("ts"), F.floor("value").cast("long").alias("item_id"))
    return _drained(flows.hot_items(hits, "1 hour", "30 days"), ws.base, "hot", "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_gathered", f"{sql_det('emb', 'l2', 5)} SELECT query_id, CAST(rank AS INTEGER) AS rank, item_id, true AS complete FROM t")
def _stream_gathered(spark: SparkSession, d: str) -> DataFrame:
    """Partial answers of the visited parts, gathered with state until a query's last part has answered."""
    ship(spark)
    ws = Workspace(spark, "stream-gather")
    x, q, c = fixed(spark, d)
    routes = ws.keep(router.route_sql(q, c, 5).join(q, "query_id"), "routes")
    found = ws.keep(search.scan_subs(routes, ws.keep(router.assign_sql(x, c), "placed"), K), "found")
    expected = routes.groupBy("query_id").agg(F.count(F.lit(1)).cast("int").alias("expected"))
    # Every visited part answers, if only with a null.
    answers = routes.select("query_id", "sub_id").join(found, ["query_id", "sub_id"], "left").join(expected, "query_id")
    answers.select("query_id", F.lit(None).cast("timestamp").alias("ts"), "sub_id", "expected", "item_id", "score").write.parquet(f"{ws.base}/answers")
    stream = spark.readStream.schema("query_id long, ts timestamp, sub_id int, expected int, item_id long, score double").parquet(f"{ws.base}/answers")
    # A plan with timeouts never runs out of batches: it is stopped when every answer was read.
    want, out = spark.read.parquet(f"{ws.base}/answers").count(), flows.gather(stream, K, 600_000)
    run = out.writeStream.format("parquet").option("path", f"{ws.base}/gathered").option("checkpointLocation", f"{ws.base}/checkpoint").trigger(processingTime="1 second").start()
    try:
        while sum(p["numInputRows"] for p in run.recentProgress) < want and run.exception() is None:
            run.awaitTermination(1)
    finally:
        run.stop()
    return spark.read.schema(out.schema).parquet(f"{ws.base}/gathered").select("query_id", "rank", "item_id", "complete")


@query("stream_served", f"WITH {ctes()}, {sql_truth('l2')} {SQL_ANSWER}")
def _stream_served(spark: SparkSession, d: str) -> DataFrame:
    """A request stream answered against a stored index; with every part visited, the exact answer."""
    ws = Workspace(spark, "stream-served")
    stream, _ = _requests(spark, d, ws)
    x, _, _ = fixed(spark, d)
    index = builder.build(x, builder.Params(m=20, w=4, kmeans_iters=4, l=ALL))
    flows.serve(stream, index, 20, K, f"{ws.base}/answers", f"{ws.base}/checkpoint").awaitTermination()
    return tidy(spark.read.parquet(f"{ws.base}/answers"))


@query("stream_recovered", "SELECT event_id FROM events")
def _stream_recovered(spark: SparkSession, d: str) -> DataFrame:
    """Stopped after a part of the input and started again from its checkpoint: every row once."""
    ws = Workspace(spark, "stream-recovered")
    e = table(spark, d, "events").select("event_id")
    for half in (0, 1):
        e.where(F.col("event_id") % 2 == half).coalesce(2).write.mode("append").parquet(f"{ws.base}/in")
        stream = spark.readStream.schema("event_id long").option("maxFilesPerTrigger", 1).parquet(f"{ws.base}/in")
        out = _drained(stream, ws.base, "copied")
    return out


@query("stream_rate_source", "SELECT o_orderkey AS value, o_totalprice AS price FROM orders")
def _stream_rate(spark: SparkSession, d: str) -> DataFrame:
    """A source of a known rate, for load tests: the orders in eight files, of which a batch takes four."""
    ws = Workspace(spark, "stream-rate")
    table(spark, d, "orders").select(F.col("o_orderkey").alias("value"), F.col("o_totalprice").alias("price")).repartition(8).write.parquet(f"{ws.base}/in")
    source = spark.readStream.schema("value long, price double").option("maxFilesPerTrigger", 4).parquet(f"{ws.base}/in")
    return _drained(source, ws.base, "paced")


@query("stream_matched_pairs", "SELECT a.event_id AS query_id FROM events a JOIN events b ON b.event_id = a.event_id WHERE a.event_id % 5 <> 0")
def _stream_matched(spark: SparkSession, d: str) -> DataFrame:
    """Requests joined to the answers that came within the timeout; a fifth came late."""
    e = table(spark, d, "events").select(F.col("event_id").alias("query_id"), F.col("ts").cast("timestamp").alias("ts"))
    late = F.when(F.col("query_id") % 5 == 0, 60).otherwise(2)
    answered = e.select("query_id", (F.col("ts") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), late)).alias("ts"))
    return flows.matched_within(e, answered, "5 seconds").select("query_id")
