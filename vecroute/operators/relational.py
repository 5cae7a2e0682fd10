"""Surrounding operators: sources, filters, joins, aggregates, windows, sets, scalar functions, streams as batches."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecroute.functions import vectors
from vecroute.plans.ranking import global_rank
from vecroute.plans.router import top_rank
from vecroute.registry import query
from vecroute.runtime import Workspace, ship, table
from vecroute.sources import datasets, files

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

# --- sources -------------------------------------------------------------------------------------


@query("src_table_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def _counts(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for t in TABLES:
        one = table(spark, d, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n"))
        out = one if out is None else out.unionByName(one)
    return out.select("name", "n")


for _kind in ("csv", "json", "orc"):

    @query(f"src_text_round_trip_{_kind}", "SELECT vec_id AS item_id, round(list_sum(CAST(embedding AS DOUBLE[])), 5) AS total FROM embeddings")
    def _round_trip(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        at = f"{Workspace(spark, 'files').base}/{kind}"
        files.write_text(datasets.items(spark, d, "emb"), at, kind)
        return files.read_text(spark, at, kind).select("item_id", F.round(vectors.fold_sum(F.col("vec")), 5).alias("total"))


@query("src_partitioned_write", "SELECT label, count(*) AS n FROM embeddings WHERE label < 4 GROUP BY 1")
def _partitioned(spark: SparkSession, d: str) -> DataFrame:
    """Written by label, read back with the filter on the partition column."""
    at = f"{Workspace(spark, 'files').base}/by-label"
    table(spark, d, "embeddings").repartition("label").write.mode("overwrite").partitionBy("label").parquet(at)
    return spark.read.parquet(at).where("label < 4").groupBy(F.col("label").cast("int").alias("label")).agg(F.count(F.lit(1)).alias("n"))


@query("src_bucketed_write", "SELECT c_mktsegment AS segment, count(*) AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")
def _bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Both sides written in buckets by the join key, so that the join needs no exchange."""
    at, tag = Workspace(spark, "buckets").base, uuid.uuid4().hex[:8]
    for name, df, key in (("o", table(spark, d, "orders").select("o_custkey"), "o_custkey"), ("c", table(spark, d, "customer").select("c_custkey", "c_mktsegment"), "c_custkey")):
        df.write.mode("overwrite").bucketBy(8, key).sortBy(key).option("path", f"{at}/{name}").saveAsTable(f"vr_{name}_{tag}")
    joined = spark.table(f"vr_o_{tag}").join(spark.table(f"vr_c_{tag}").hint("merge"), F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("n"))


@query("src_rejects", "SELECT reason, count(*) AS n FROM (SELECT CASE WHEN vec_id % 50 = 0 THEN 'null' WHEN vec_id % 50 = 1 THEN 'length' WHEN vec_id % 50 = 2 THEN 'zero norm' END AS reason FROM embeddings) WHERE reason IS NOT NULL GROUP BY 1")
def _rejects(spark: SparkSession, d: str) -> DataFrame:
    spoilt = F.when(F.col("item_id") % 50 == 0, F.lit(None)).when(F.col("item_id") % 50 == 1, F.slice("vec", 1, 3)).when(F.col("item_id") % 50 == 2, F.transform("vec", lambda x: x * 0)).otherwise(F.col("vec"))
    _, bad = vectors.split_valid(datasets.items(spark, d, "emb").select("item_id", spoilt.alias("vec")), 64, "cosine")
    return bad.groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


# --- projection and filter -------------------------------------------------------------------------


@query("prj_prune_and_cast", "SELECT vec_id AS item_id, CAST(embedding[1] AS DOUBLE) AS first, CAST(label AS BIGINT) AS label FROM embeddings")
def _prune(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("item_id"), F.col("embedding")[0].cast("double").alias("first"), F.col("label").cast("long").alias("label"))


@query("flt_predicates", "SELECT doc_id, source FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 500 AND 5000 AND source LIKE 'src1%' AND regexp_matches(text, '[0-9]{3}')")
def _predicates(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "documents")
    return t.where(F.col("lang").isin("en", "fr") & F.col("n_chars").between(500, 5000) & F.col("source").like("src1%") & F.col("text").rlike("[0-9]{3}")).select("doc_id", "source")


@query("flt_attribute_pushdown", "SELECT c_mktsegment AS segment, count(*) AS n FROM customer WHERE c_mktsegment = 'BUILDING' AND c_acctbal > 0 GROUP BY 1")
def _pushdown(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").where("c_mktsegment = 'BUILDING' AND c_acctbal > 0").groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("n"))


# --- joins ------------------------------------------------------------------------------------------


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderdate")


_SQL_SEGMENT = "SELECT c_mktsegment AS segment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1"
for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"join_{_hint}", _SQL_SEGMENT)
    def _join(spark: SparkSession, d: str, hint: str = _hint) -> DataFrame:
        c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
        joined = _orders(spark, d).join(c.hint(hint), F.col("c_custkey") == F.col("o_custkey"))
        return joined.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("join_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_acctbal < b.s_acctbal AND a.s_nationkey = b.s_nationkey AND b.s_acctbal - a.s_acctbal < 500")
def _theta(spark: SparkSession, d: str) -> DataFrame:
    s = table(spark, d, "supplier")
    a, b = s.alias("a"), s.alias("b")
    return a.join(b, F.expr("a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal AND b.s_acctbal - a.s_acctbal < 500")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def _semi(spark: SparkSession, d: str) -> DataFrame:
    big = _orders(spark, d).where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").select("c_custkey").join(big, "c_custkey", "left_semi")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def _anti(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select("c_custkey").join(_orders(spark, d).where("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


for _how in ("left", "right", "full"):

    @query(f"join_{_how}_outer", f"SELECT d.doc_id AS doc_id, l.doc_id AS labelled, quality FROM (SELECT doc_id FROM documents WHERE doc_id % 3 = 0) d {_how.upper()} JOIN (SELECT * FROM labels WHERE doc_id % 2 = 0) l ON d.doc_id = l.doc_id")
    def _outer(spark: SparkSession, d: str, how: str = _how) -> DataFrame:
        a = table(spark, d, "documents").where("doc_id % 3 = 0").select("doc_id")
        b = table(spark, d, "labels").where("doc_id % 2 = 0").select(F.col("doc_id").alias("labelled"), "quality")
        return a.join(b, F.col("doc_id") == F.col("labelled"), how).select("doc_id", "labelled", "quality")


@query("join_range_binned", "SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND abs(CAST(a.embedding[1] AS DOUBLE) - CAST(b.embedding[1] AS DOUBLE)) <= 0.0005")
def _range(spark: SparkSession, d: str) -> DataFrame:
    """Bins as wide as the radius: each row meets its own and the next bin by equi-join, then the bound is checked."""
    r = 0.0005
    x = table(spark, d, "embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("v"))
    bin_ = F.floor(F.col("v") / r)
    left = x.select(F.col("vec_id").alias("i"), F.col("v").alias("u"), F.explode(F.array(bin_ - 1, bin_, bin_ + 1)).alias("bin"))
    right = x.select(F.col("vec_id").alias("j"), F.col("v").alias("w"), bin_.alias("bin"))
    return left.join(right, "bin").where((F.col("i") < F.col("j")) & (F.abs(F.col("u") - F.col("w")) <= r)).select(F.col("i").alias("a"), F.col("j").alias("b"))


@query("join_as_of", "SELECT event_id, o_orderkey FROM (SELECT event_id, user_id, ts FROM events) e ASOF LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY 1, 2) o ON e.user_id = o.o_custkey AND e.ts >= o.o_orderdate")
def _as_of(spark: SparkSession, d: str) -> DataFrame:
    """The latest order before each event: both in one stream per user, last order carried forward. No join."""
    e = table(spark, d, "events").select(F.col("user_id").alias("key"), "ts", F.lit(1).alias("kind"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    o = _orders(spark, d).groupBy(F.col("o_custkey").alias("key"), F.col("o_orderdate").alias("ts")).agg(F.max("o_orderkey").alias("o_orderkey"))
    both = e.unionByName(o.select("key", "ts", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), "o_orderkey"))
    w = Window.partitionBy("key").orderBy("ts", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last", F.last("o_orderkey", ignorenulls=True).over(w)).where("kind = 1").select("event_id", F.col("last").alias("o_orderkey"))


@query("join_lateral_topk", "SELECT c_custkey, o_orderkey FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders JOIN customer ON c_custkey = o_custkey) WHERE r <= 2")
def _lateral(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "customer").createOrReplaceTempView("vr_customer")
    _orders(spark, d).createOrReplaceTempView("vr_orders")
    return spark.sql("SELECT c_custkey, o_orderkey FROM vr_customer, LATERAL (SELECT o_orderkey FROM vr_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")


@query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _interval(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_id", "user_id", "ts")
    return e.alias("a").join(e.alias("b"), F.expr("a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


# --- aggregates -----------------------------------------------------------------------------------------


@query("agg_basic", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, round(avg(value), 6) AS mean, min(value) AS least, max(value) AS most, round(stddev_samp(value), 6) AS spread FROM events GROUP BY 1")
def _basic(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("least"), F.max("value").alias("most"), F.round(F.stddev_samp("value"), 6).alias("spread"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def _distinct(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("agg_distinct_sketch", "SELECT event_type, true AS within FROM events GROUP BY 1")
def _distinct_sketch(spark: SparkSession, d: str) -> DataFrame:
    """Approximate distinct counts lie within a tenth of the exact ones."""
    e = table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("b"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 12)).alias("c"))
    return e.select("event_type", ((F.abs(F.col("a") / F.col("b") - 1) < 0.1) & (F.abs(F.col("c") / F.col("b") - 1) < 0.1)).alias("within"))


@query("agg_percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90, round(quantile_cont(value, 0.99), 6) AS p99 FROM events GROUP BY 1")
def _percentiles(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", p), 6).alias(f"p{int(p * 100)}") for p in (0.5, 0.9, 0.99)])


@query("agg_percentile_sketch", "SELECT event_type, true AS within FROM events GROUP BY 1")
def _percentile_sketch(spark: SparkSession, d: str) -> DataFrame:
    """A mergeable quantile sketch and the approximate percentile lie near the exact one."""
    e = table(spark, d, "events").groupBy("event_type").agg(F.percentile("value", 0.9).alias("a"), F.percentile_approx("value", 0.9, 10_000).alias("b"), F.kll_sketch_agg_double("value").alias("k"))
    c = F.kll_sketch_get_quantile_double("k", F.lit(0.9))
    return e.select("event_type", ((F.abs(F.col("b") / F.col("a") - 1) < 0.1) & (F.abs(c / F.col("a") - 1) < 0.1)).alias("within"))


for _form in ("rollup", "cube"):

    @query(f"agg_{_form}", f"SELECT c_mktsegment AS segment, c_nationkey AS nation, CAST(grouping(c_mktsegment, c_nationkey) AS BIGINT) AS level, count(*) AS n FROM customer GROUP BY {_form.upper()} (c_mktsegment, c_nationkey)")
    def _grouping(spark: SparkSession, d: str, form: str = _form) -> DataFrame:
        g = getattr(table(spark, d, "customer"), form)("c_mktsegment", "c_nationkey")
        return g.agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n")).select(F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"), "level", "n")


@query("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def _sets(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "documents").createOrReplaceTempView("vr_documents")
    return spark.sql("SELECT lang, source, count(*) AS n FROM vr_documents GROUP BY GROUPING SETS ((lang), (source), ())")


@query("agg_vector_mean", "SELECT label, CAST(i AS INTEGER) AS i, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS v FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2")
def _vector_mean(spark: SparkSession, d: str) -> DataFrame:
    x = table(spark, d, "embeddings").select("label", F.posexplode(F.col("embedding").cast("array<double>")).alias("i", "v"))
    return x.groupBy("label", (F.col("i") + 1).alias("i")).agg(F.round(F.avg("v"), 6).alias("v"))


@query("agg_ranked_lists", "SELECT user_id, array_to_string(list(event_id ORDER BY value DESC, event_id)[1:3], ',') AS best, count(*) AS n FROM events GROUP BY 1")
def _ranked(spark: SparkSession, d: str) -> DataFrame:
    best = top_rank(table(spark, d, "events").select("user_id", "event_id", "value"), "user_id", 3, "value", "event_id")
    lists = best.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("rank", "event_id"))).alias("l"))
    n = table(spark, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return lists.join(n, "user_id").select("user_id", F.array_join(F.transform("l", lambda s: s["event_id"].cast("string")), ",").alias("best"), "n")


@query("agg_max_by", "SELECT user_id, arg_max(event_type, (value, event_id)) AS top FROM events GROUP BY 1")
def _max_by(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("user_id").agg(F.max_by("event_type", F.struct("value", "event_id")).alias("top"))


@query("agg_pivot", "SELECT lang, count(*) FILTER (WHERE q = 0) AS q0, count(*) FILTER (WHERE q = 1) AS q1 FROM (SELECT lang, quality AS q FROM documents JOIN labels USING (doc_id)) GROUP BY 1")
def _pivot(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels"), "doc_id")
    p = j.groupBy("lang").pivot("quality", [0, 1]).count()
    return p.select("lang", F.coalesce("0", F.lit(0)).cast("long").alias("q0"), F.coalesce("1", F.lit(0)).cast("long").alias("q1"))


@query("agg_histogram", "SELECT CAST(least(floor(value / 10), 9) + 1 AS BIGINT) AS bin, count(*) AS n FROM events WHERE value >= 0 AND value < 100 GROUP BY 1")
def _histogram(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").where("value >= 0 AND value < 100").groupBy(F.width_bucket("value", F.lit(0.0), F.lit(100.0), F.lit(10)).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query("agg_majority", "SELECT user_id, event_type FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS r FROM events GROUP BY 1, 2) WHERE r = 1")
def _majority(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return top_rank(n, "user_id", 1, "n", "event_type").select("user_id", "event_type")


@query("agg_sort_fallback", "SELECT user_id, min(event_type) AS first, max(event_type) AS last FROM events GROUP BY 1")
def _sort_aggregate(spark: SparkSession, d: str) -> DataFrame:
    """Buffers of strings cannot change in place, so Spark sorts by key instead of hashing; the plan says SortAggregate."""
    return table(spark, d, "events").groupBy("user_id").agg(F.min("event_type").alias("first"), F.max("event_type").alias("last"))


# --- windows ---------------------------------------------------------------------------------------------


@query("win_ranks", "SELECT s_suppkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, CAST(ntile(3) OVER w AS INTEGER) AS nt FROM (SELECT *, round(s_acctbal / 1000) AS k FROM supplier) WINDOW w AS (PARTITION BY s_nationkey ORDER BY k, s_suppkey)")
def _ranks(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("s_nationkey").orderBy("k", "s_suppkey")
    s = table(spark, d, "supplier").withColumn("k", F.round(F.col("s_acctbal") / 1000))
    return s.select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(3).over(w).alias("nt"))


@query("win_neighbours", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _neighbours(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("win_frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS sliding, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events")
def _frames(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    r = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)
    return table(spark, d, "events").select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("sliding"), F.count(F.lit(1)).over(r).alias("recent"))


# --- order, limits, sets -----------------------------------------------------------------------------------


@query("ord_top_n", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def _top_n(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("ord_within_partitions", "SELECT user_id, arg_min(event_id, (ts, event_id)) AS first_event, count(*) AS n FROM events GROUP BY 1")
def _within_partitions(spark: SparkSession, d: str) -> DataFrame:
    """One exchange by user, a sort inside partitions, and a row number that needs neither again."""
    e = table(spark, d, "events").select("user_id", "ts", "event_id").repartition("user_id").sortWithinPartitions("user_id", "ts", "event_id")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    numbered = e.withColumn("r", F.row_number().over(w))
    return numbered.groupBy("user_id").agg(F.max(F.when(F.col("r") == 1, F.col("event_id"))).alias("first_event"), F.count(F.lit(1)).alias("n"))


@query("ord_per_key_topk", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def _per_key(spark: SparkSession, d: str) -> DataFrame:
    return top_rank(_orders(spark, d), "o_custkey", 3, "o_totalprice", "o_orderkey").select("o_custkey", "o_orderkey")


@query("ord_topk_with_ties", "SELECT user_id, event_id FROM (SELECT user_id, event_id, rank() OVER (PARTITION BY user_id ORDER BY floor(value) DESC) AS r FROM events) WHERE r <= 2")
def _ties(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.floor("value").desc())
    return table(spark, d, "events").select("user_id", "event_id", F.rank().over(w).alias("r")).where("r <= 2").select("user_id", "event_id")


@query("ord_global_rank", "SELECT event_id, row_number() OVER (ORDER BY value, event_id) AS global_rank FROM events")
def _global(spark: SparkSession, d: str) -> DataFrame:
    return global_rank(table(spark, d, "events").select("event_id", "value"), F.col("value"), [F.col("value"), F.col("event_id")]).select("event_id", "global_rank")


_A, _B = "SELECT doc_id % 50 AS k FROM documents WHERE doc_id % 2 = 0", "SELECT doc_id % 50 AS k FROM labels WHERE doc_id % 3 = 0"
for _op, _sql in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    @query(f"set_{_op}", f"SELECT k, count(*) AS n FROM ({_A} {_sql} {_B}) GROUP BY 1")
    def _set_op(spark: SparkSession, d: str, op: str = _op) -> DataFrame:
        a = table(spark, d, "documents").where("doc_id % 2 = 0").select((F.col("doc_id") % 50).alias("k"))
        b = table(spark, d, "labels").where("doc_id % 3 = 0").select((F.col("doc_id") % 50).alias("k"))
        both = {"union_all": a.unionByName, "union": lambda x: a.union(x).distinct(), "intersect": a.intersect, "intersect_all": a.intersectAll, "except": a.subtract, "except_all": a.exceptAll}[op](b)
        return both.groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("set_distinct_rows", "SELECT lang, source FROM documents GROUP BY 1, 2")
def _dedup(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("lang", "source").dropDuplicates()


# --- scalar functions -----------------------------------------------------------------------------------------


@query("fn_vector_math", "WITH e AS (SELECT vec_id AS item_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) SELECT item_id, round(list_inner_product(v, v), 6) AS dot, round(list_distance(v, list_reverse(v)), 6) AS dist, round(list_sum(v[3:6]), 6) AS part, CAST(len(v || v) AS INTEGER) AS width, round(2 * v[1], 6) AS scaled FROM e")
def _vector_math(spark: SparkSession, d: str) -> DataFrame:
    v = F.col("vec")
    return datasets.items(spark, d, "emb").select("item_id", F.round(vectors.dot(v, v), 6).alias("dot"), F.round(vectors.distance(v, F.reverse(v)), 6).alias("dist"), F.round(vectors.fold_sum(vectors.slice_of(v, 2, 4)), 6).alias("part"), F.size(F.concat(v, v)).alias("width"), F.round(vectors.scale(v, F.lit(2.0))[0], 6).alias("scaled"))


@query("fn_math", f"SELECT event_id, round(sqrt(abs(value)), 6) AS a, round(pow(value / 100, 2), 6) AS b, round(ln(1 + abs(value)), 6) AS c, round(exp(-value / {math.e}), 6) AS d, CAST(floor(value) AS BIGINT) AS e, ((event_id * 7919) % 1000 + 1000) % 1000 AS f, greatest(value, 50.0) AS g, least(value, 50.0) AS h FROM events")
def _math(spark: SparkSession, d: str) -> DataFrame:
    v = F.col("value")
    return table(spark, d, "events").select("event_id", F.round(F.sqrt(F.abs(v)), 6).alias("a"), F.round(F.pow(v / 100, F.lit(2.0)), 6).alias("b"), F.round(F.ln(1 + F.abs(v)), 6).alias("c"), F.round(F.exp(-v / math.e), 6).alias("d"), F.floor(v).cast("long").alias("e"), F.pmod(F.col("event_id") * 7919, F.lit(1000)).alias("f"), F.greatest(v, F.lit(50.0)).alias("g"), F.least(v, F.lit(50.0)).alias("h"))


@query("fn_string", "SELECT doc_id, CAST(len(regexp_extract_all(lower(text), '[a-z]+')) AS INTEGER) AS words, lower(substr(text, 1, 3)) AS head, CAST(length(replace(text, 'e', '')) AS INTEGER) AS without, md5(text) AS digest, split_part(text, ' ', 2) AS second, CAST(levenshtein(lang, source) AS INTEGER) AS edits FROM documents")
def _string(spark: SparkSession, d: str) -> DataFrame:
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower(t), F.lit("[a-z]+"), 0)).alias("words"), F.lower(F.substring(t, 1, 3)).alias("head"), F.length(F.replace(t, F.lit("e"), F.lit(""))).alias("without"), F.md5(t).alias("digest"), F.split_part(t, F.lit(" "), F.lit(2)).alias("second"), F.levenshtein("lang", "source").alias("edits"))


@query("fn_dates", "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(month(o_orderdate) AS INTEGER) AS m, date_trunc('month', o_orderdate) AS start, epoch_us(o_orderdate) AS micros, o_orderdate + INTERVAL 3 DAY AS later FROM orders")
def _dates(spark: SparkSession, d: str) -> DataFrame:
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_diff(F.to_date(o), F.lit("1995-01-01").cast("date")).alias("days"), F.month(o).alias("m"), F.date_trunc("month", o).alias("start"), F.unix_micros(o.cast("timestamp_ltz")).alias("micros"), (o + F.expr("INTERVAL 3 DAY")).alias("later"))


@query("fn_arrays", "WITH a AS (SELECT user_id, list_sort(list_distinct(list(event_type))) AS kinds, list(event_id) AS ids FROM events GROUP BY 1) SELECT user_id, array_to_string(kinds, ',') AS kinds, CAST(len(kinds) AS INTEGER) AS n, list_has_any(kinds, ['click', 'view']) AS seen, CAST(list_sum(list_transform(ids, lambda x: x % 10)) AS BIGINT) AS digits FROM a")
def _arrays(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "events").groupBy("user_id").agg(F.array_sort(F.array_distinct(F.collect_list("event_type"))).alias("k"), F.collect_list("event_id").alias("ids"))
    return a.select("user_id", F.array_join("k", ",").alias("kinds"), F.size("k").alias("n"), F.arrays_overlap("k", F.array(F.lit("click"), F.lit("view"))).alias("seen"), F.aggregate("ids", F.lit(0).cast("long"), lambda acc, x: acc + x % 10).alias("digits"))


@query("fn_maps", "SELECT event_type, CAST(100 AS BIGINT) AS hundred, 2 * count(*) AS doubled FROM events GROUP BY 1")
def _maps(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    m = F.transform_values(F.map_from_arrays(F.array(F.lit("n"), F.lit("h")), F.array(F.col("n"), F.lit(50).cast("long"))), lambda k, v: v * 2)
    return n.select("event_type", F.element_at(m, "h").alias("hundred"), F.element_at(m, "n").alias("doubled"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _json(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.select("event_id", F.coalesce(F.get_json_object("props", "$.k").cast("long"), F.from_json("props", "k long")["k"]).alias("k"))


@query("fn_hash_split", "SELECT CAST('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 8) AS BIGINT) % 16 AS bucket, count(*) AS n FROM events GROUP BY 1")
def _hash_split(spark: SparkSession, d: str) -> DataFrame:
    b = F.conv(F.substring(F.md5(F.col("event_id").cast("string")), 1, 8), 16, 10).cast("long") % 16
    return table(spark, d, "events").groupBy(b.alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


for _set in ("hashtext", "letters", "partvec", "eventvec", "line5", "emb_scaled"):

    @query(f"set_of_vectors_{_set}", f"WITH e AS ({datasets.SQL[_set]}) SELECT item_id, round(list_sum(vec) * pi(), 4) AS total, round(vec[2], 5) AS second FROM e")
    def _vector_set(spark: SparkSession, d: str, name: str = _set) -> DataFrame:
        return datasets.items(spark, d, name).select("item_id", F.round(vectors.fold_sum(F.col("vec")) * F.pi(), 4).alias("total"), F.round(F.col("vec")[1], 5).alias("second"))


# --- functions for SQL users, streams as batches --------------------------------------------------------------


@query("udf_vector_mean", "SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS first FROM embeddings GROUP BY 1")
def _udf_mean(spark: SparkSession, d: str) -> DataFrame:
    from vecroute.serving import sqlext

    ship(spark)
    sqlext.register(spark)
    table(spark, d, "embeddings").createOrReplaceTempView("vr_embeddings")
    return spark.sql("SELECT label, round(vec_mean(embedding)[0], 6) AS first FROM vr_embeddings GROUP BY label")


@query("udf_score", "WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) SELECT a.vec_id AS a, b.vec_id AS b, round(-list_distance(a.v, b.v), 5) AS score FROM e a JOIN e b ON b.vec_id = a.vec_id + 1")
def _udf_score(spark: SparkSession, d: str) -> DataFrame:
    from vecroute.serving import sqlext

    ship(spark)
    sqlext.register(spark)
    datasets.items(spark, d, "emb").createOrReplaceTempView("vr_emb")
    return spark.sql("SELECT a.item_id AS a, b.item_id AS b, round(score_l2(a.vec, b.vec), 5) AS score FROM vr_emb a JOIN vr_emb b ON b.item_id = a.item_id + 1")


@query("stream_windows", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _stream_windows(spark: SparkSession, d: str) -> DataFrame:
    """A file stream through windowed counts, read back from its sink."""
    from vecroute.streaming import flows

    at = Workspace(spark, "stream").base
    source = spark.readStream.schema(table(spark, d, "events").schema).parquet(f"{d.rstrip('/')}/events.parquet*")
    counted = flows.windowed_counts(source.withColumn("ts", F.col("ts").cast("timestamp")), "1 hour", None, "30 days", "event_type")
    run = counted.writeStream.outputMode("complete").format("memory").queryName("vr_windows").option("checkpointLocation", f"{at}/checkpoint").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.table("vr_windows").withColumn("start", F.col("start").cast("timestamp_ntz"))
