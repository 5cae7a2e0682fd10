"""Registered queries of the methods and measures, with fixed ingredients so that each has a DuckDB twin.

Fixed ingredients: centres are the vectors whose id is divisible by ten, the part of a
centre is its ordinal modulo the number of parts, queries are the ids that leave three
modulo seven. Everything else is the engine's own plan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecroute.baselines import kdtree, quantised, random_split
from vecroute.functions import measures, vectors
from vecroute.graphs import knn_graph
from vecroute.plans import builder, centers, mips, router, sampling, search
from vecroute.plans.sizes import small
from vecroute.registry import query
from vecroute.runtime import Workspace, ship, table
from vecroute.serving import dispatch
from vecroute.sources import datasets

W, K, M_STEP = 10, 10, 10
BRANCHINGS = (1, 5, 10, 20, 50)

#: SQL for the similarity of two vectors.
SQL_SCORE = {"l2": "-list_distance({0}, {1})", "cosine": "list_cosine_similarity({0}, {1})", "ip": "list_inner_product({0}, {1})"}


def fixed(spark: SparkSession, d: str, name: str = "emb") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Items, queries and centres (with parts)."""
    x = datasets.items(spark, d, name)
    c = x.where(F.col("item_id") % M_STEP == 0).select(F.col("item_id").cast("int").alias("center_id"), "vec", F.lit(1.0).alias("weight"), F.expr(f"cast((item_id div {M_STEP}) % {W} as int)").alias("sub_id"))
    return x, datasets.sampled_queries(x), c


def ctes(name: str = "emb") -> str:
    return f"e AS ({datasets.SQL[name]}), q AS (SELECT item_id AS query_id, vec FROM e WHERE item_id % 7 = 3), c AS (SELECT CAST(item_id AS INTEGER) AS center_id, vec, CAST((item_id // {M_STEP}) % {W} AS INTEGER) AS sub_id FROM e WHERE item_id % {M_STEP} = 0)"


def sql_route(metric: str) -> str:
    """``r(query_id, center_id, sub_id, rank)``."""
    return f"r AS (SELECT query_id, center_id, sub_id, row_number() OVER (PARTITION BY query_id ORDER BY {SQL_SCORE[metric].format('q.vec', 'c.vec')} DESC, center_id) AS rank FROM q, c)"


def sql_placed(metric: str) -> str:
    """``p(item_id, vec, center_id, sub_id)``."""
    return f"p AS (SELECT item_id, vec, center_id, sub_id FROM (SELECT e.item_id, e.vec, c.center_id, c.sub_id, row_number() OVER (PARTITION BY e.item_id ORDER BY {SQL_SCORE[metric].format('e.vec', 'c.vec')} DESC, center_id) AS n FROM e, c) WHERE n = 1)"


def sql_truth(metric: str, k: int = K, where: str = "true") -> str:
    return f"t AS (SELECT * FROM (SELECT query_id, item_id, s, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM (SELECT query_id, item_id, {SQL_SCORE[metric].format('q.vec', 'e.vec')} AS s FROM q, e WHERE {where})) WHERE rank <= {k})"


SQL_ANSWER = "SELECT query_id, CAST(rank AS INTEGER) AS rank, item_id, round(s, 6) AS score FROM t"


def tidy(result: DataFrame) -> DataFrame:
    return result.select("query_id", F.col("rank").cast("int").alias("rank"), "item_id", F.round("score", 6).alias("score"))


# --- exact scan (the yardstick) and kernels ---------------------------------------------------

for _metric, _set in (("l2", "emb"), ("cosine", "emb"), ("ip", "emb_scaled")):

    @query(f"exact_{_metric}_topk", f"WITH {ctes(_set)}, {sql_truth(_metric)} {SQL_ANSWER}")
    def _exact(spark: SparkSession, d: str, metric: str = _metric, name: str = _set) -> DataFrame:
        x, q, _ = fixed(spark, d, name)
        return tidy(search.exact_topk(q, x, K, metric))

    @query(f"exact_{_metric}_topk_blocks", f"WITH {ctes(_set)}, {sql_truth(_metric)} {SQL_ANSWER}")
    def _exact_blocks(spark: SparkSession, d: str, metric: str = _metric, name: str = _set) -> DataFrame:
        ship(spark)
        x, q, _ = fixed(spark, d, name)
        return tidy(search.exact_topk_blocks(q, x, K, metric))

    @query(f"route_items_{_metric}", f"WITH {ctes(_set)}, {sql_placed(_metric)} SELECT item_id, sub_id FROM p")
    def _route_items(spark: SparkSession, d: str, metric: str = _metric, name: str = _set) -> DataFrame:
        x, _, c = fixed(spark, d, name)
        return router.assign_sql(x, c, metric).select("item_id", "sub_id")

    @query(f"route_items_{_metric}_blocks", f"WITH {ctes(_set)}, {sql_placed(_metric)} SELECT item_id, sub_id FROM p")
    def _route_items_blocks(spark: SparkSession, d: str, metric: str = _metric, name: str = _set) -> DataFrame:
        ship(spark)
        x, _, c = fixed(spark, d, name)
        return router.assign(x, meta_of(c, metric), "exact").select("item_id", "sub_id")


def meta_of(c: DataFrame, metric: str) -> router.MetaIndex:
    import numpy as np

    ids, matrix = centers.as_matrix(c)
    subs = np.array([r.sub_id for r in c.orderBy("center_id").select("sub_id").collect()], np.int32)
    return router.MetaIndex(ids, matrix, subs, metric, bulk=True)


@query("exact_topk_exclude_self", f"WITH {ctes()}, {sql_truth('l2', K, 'query_id <> item_id')} {SQL_ANSWER}")
def _exclude_self(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    return tidy(search.exact_topk(q, x, K, exclude_self=True))


@query("unit_norm_rank_equivalence", f"WITH {ctes()}, s AS (SELECT query_id, item_id, row_number() OVER (PARTITION BY query_id ORDER BY list_distance(q.vec, e.vec), item_id) AS a, row_number() OVER (PARTITION BY query_id ORDER BY list_cosine_similarity(q.vec, e.vec) DESC, item_id) AS b, row_number() OVER (PARTITION BY query_id ORDER BY list_inner_product(q.vec, e.vec) DESC, item_id) AS c FROM q, e) SELECT query_id, CAST(count(*) FILTER (WHERE a <= 10 AND b <= 10 AND c <= 10) AS BIGINT) AS agreeing FROM s GROUP BY 1")
def _unit_norm(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    found = [search.exact_topk(q, x, K, m).select("query_id", "item_id") for m in ("l2", "cosine", "ip")]
    return found[0].intersect(found[1]).intersect(found[2]).groupBy("query_id").agg(F.count(F.lit(1)).alias("agreeing"))


@query("unit_normalise", "WITH e AS (SELECT vec_id AS item_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) SELECT item_id, round(sqrt(list_inner_product(v, v)), 6) AS norm, round(v[1] / sqrt(list_inner_product(v, v)), 6) AS first FROM e")
def _normalise(spark: SparkSession, d: str) -> DataFrame:
    x = datasets.items(spark, d, "emb")
    return x.select("item_id", F.round(vectors.norm(F.col("vec")), 6).alias("norm"), F.round(vectors.normalise(F.col("vec"))[0], 6).alias("first"))


@query("cosine_by_normalising", f"WITH {ctes('emb_scaled')}, {sql_truth('cosine')} SELECT query_id, CAST(rank AS INTEGER) AS rank, item_id FROM t")
def _cosine_normalised(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d, "emb_scaled")
    return search.exact_topk(q.select("query_id", vectors.normalise(F.col("vec")).alias("vec")), x.select("item_id", vectors.normalise(F.col("vec")).alias("vec")), K).select("query_id", "rank", "item_id")


# --- sampling, centres, weights -----------------------------------------------------------------


@query("sample_by_hash", "SELECT vec_id AS item_id FROM embeddings WHERE CAST('0x' || substr(md5(CAST(vec_id AS VARCHAR)), 1, 8) AS BIGINT) % 5 = 0")
def _sample_hash(spark: SparkSession, d: str) -> DataFrame:
    return sampling.by_hash(datasets.items(spark, d, "emb"), 5).select("item_id")


@query("det_centers", f"WITH {ctes()} SELECT center_id, sub_id, round(vec[1], 6) AS first FROM c")
def _det_centers(spark: SparkSession, d: str) -> DataFrame:
    return fixed(spark, d)[2].select("center_id", "sub_id", F.round(F.col("vec")[0], 6).alias("first"))


_SQL_LLOYD = f"WITH {ctes()}, {sql_placed('l2')}, u AS (SELECT center_id, i, avg(vec[i]) AS v, count(*) AS n FROM p, (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2) SELECT c.center_id, CAST(i AS INTEGER) AS i, round(coalesce(v, c.vec[i]), 6) AS v, CAST(coalesce(n, 0) AS DOUBLE) AS weight FROM c LEFT JOIN u ON u.center_id = c.center_id"


@query("lloyd_step", _SQL_LLOYD)
def _lloyd(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    moved = centers.lloyd_step(x, c)
    return moved.select("center_id", F.posexplode("vec").alias("i", "v"), "weight").select("center_id", (F.col("i") + 1).alias("i"), F.round("v", 6).alias("v"), "weight")


@query("center_weight_count", f"WITH {ctes()}, {sql_placed('l2')} SELECT c.center_id, CAST(count(p.item_id) AS DOUBLE) AS weight FROM c LEFT JOIN p ON p.center_id = c.center_id GROUP BY 1")
def _weight_count(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    return centers.weight_by_count(x, c).select("center_id", "weight")


@query("center_weight_hot", f"WITH {ctes()}, l AS (SELECT event_id AS query_id, e.vec FROM events JOIN e ON e.item_id = CAST(floor(value) AS BIGINT)), h AS (SELECT center_id, count(*) AS n FROM (SELECT l.query_id, c.center_id, row_number() OVER (PARTITION BY l.query_id ORDER BY list_distance(l.vec, c.vec), c.center_id) AS r FROM l, c) WHERE r <= 3 GROUP BY 1) SELECT c.center_id, CAST(coalesce(n, 0) + 1 AS DOUBLE) AS weight FROM c LEFT JOIN h ON h.center_id = c.center_id")
def _weight_hot(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    # An item is ranked once, however often it was asked for.
    asked = table(spark, d, "events").groupBy(F.floor("value").cast("long").alias("item_id")).agg(F.count(F.lit(1)).alias("n"))
    hits = asked.join(x, "item_id").select(F.col("item_id").alias("query_id"), "vec", "n")
    return centers.weight_by_queries(hits, c, 3).select("center_id", "weight")


# --- routing, searching the visited parts, merging ---------------------------------------------


@query("route_queries", f"WITH {ctes()}, {sql_route('l2')} SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 5")
def _route_queries(spark: SparkSession, d: str) -> DataFrame:
    _, q, c = fixed(spark, d)
    return router.route_sql(q, c, 5)


@query("route_queries_blocks", f"WITH {ctes()}, {sql_route('l2')} SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 5")
def _route_queries_blocks(spark: SparkSession, d: str) -> DataFrame:
    ship(spark)
    _, q, c = fixed(spark, d)
    return router.route(q, meta_of(c, "l2"), 5, "exact").select("query_id", "sub_id")


@query("part_sizes", f"WITH {ctes()}, {sql_placed('l2')} SELECT sub_id, count(*) AS n FROM p GROUP BY 1")
def _part_sizes(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    return router.assign_sql(x, c).groupBy("sub_id").agg(F.count(F.lit(1)).alias("n"))


@query("part_balance", f"WITH {ctes()}, {sql_placed('l2')}, s AS (SELECT sub_id, count(*) AS n FROM p GROUP BY 1) SELECT round(max(n) / avg(n), 6) AS peak, round(stddev_pop(n), 6) AS spread, count(*) AS parts FROM s")
def _balance(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    return measures.balance(router.assign_sql(x, c), "sub_id").select(F.round("peak", 6).alias("peak"), F.round("spread", 6).alias("spread"), "parts")


_SQL_KS = "(SELECT unnest([" + ", ".join(map(str, BRANCHINGS)) + "]) AS branching) k"


def _ranked_routes(q: DataFrame, c: DataFrame) -> DataFrame:
    """One routing pass for all branching factors: the best rank of each part per query."""
    found = router.nearest_centers(q, c.select("center_id", "vec"), max(BRANCHINGS)).join(small(c.select("center_id", "sub_id")), "center_id")
    reach = found.groupBy("query_id", "sub_id").agg(F.min("rank").alias("reach"))
    ks = F.explode(F.array(*[F.lit(b) for b in BRANCHINGS])).alias("branching")
    return reach.select("query_id", "sub_id", "reach", ks).where("reach <= branching")


@query("access_rate_curve", f"WITH {ctes()}, {sql_route('l2')}, a AS (SELECT branching, query_id, count(DISTINCT sub_id) AS n FROM r JOIN {_SQL_KS} ON rank <= branching GROUP BY 1, 2) SELECT CAST(branching AS INTEGER) AS branching, round(avg(n) / {W}, 6) AS access_rate FROM a GROUP BY 1")
def _access_curve(spark: SparkSession, d: str) -> DataFrame:
    _, q, c = fixed(spark, d)
    return measures.access_rate(_ranked_routes(q, c), W, ["branching"]).select("branching", F.round("access_rate", 6).alias("access_rate"))


_SQL_CURVE = f"WITH {ctes()}, {sql_route('l2')}, {sql_placed('l2')}, {sql_truth('l2')}, v AS (SELECT DISTINCT branching, query_id, sub_id FROM r JOIN {_SQL_KS} ON rank <= branching), f AS (SELECT branching, v.query_id, p.item_id, row_number() OVER (PARTITION BY branching, v.query_id ORDER BY list_distance(q.vec, p.vec), p.item_id) AS n FROM v JOIN p ON p.sub_id = v.sub_id JOIN q ON q.query_id = v.query_id) SELECT CAST(branching AS INTEGER) AS branching, round(count(t.item_id) / ({K}.0 * (SELECT count(*) FROM q)), 6) AS precision FROM f LEFT JOIN t ON t.query_id = f.query_id AND t.item_id = f.item_id WHERE n <= {K} GROUP BY 1"


@query("precision_curve_exact_sub", _SQL_CURVE)
def _precision_curve(spark: SparkSession, d: str) -> DataFrame:
    """One scan of the visited parts serves all branching factors: a part's best are the same in each."""
    ws = Workspace(spark, "curve")
    x, q, c = fixed(spark, d)
    x, q = ws.keep(x, "items"), ws.keep(q, "queries")
    routes = ws.keep(_ranked_routes(q, c), "routes")
    reached = routes.select("query_id", "sub_id").distinct().join(q, "query_id")
    found = ws.keep(search.scan_subs(reached, ws.keep(router.assign_sql(x, c), "placed"), K), "found")
    wide = found.join(routes, ["query_id", "sub_id"]).withColumn("bq", F.struct("branching", "query_id"))
    best = router.top_rank(wide.select("bq", "branching", "query_id", "item_id", "score"), "bq", K).select("branching", "query_id", "rank", "item_id")
    return measures.precision(best, search.exact_topk_blocks(q, x, K), K, ["branching"]).select("branching", F.round("precision", 6).alias("precision"))


def _det_answer(spark: SparkSession, d: str, name: str, metric: str, branching: int) -> DataFrame:
    ws = Workspace(spark, "routed")
    x, q, c = fixed(spark, d, name)
    x, q, c = ws.keep(x, "items"), ws.keep(q, "queries"), ws.keep(c, "centers")
    routed = ws.keep(router.route_sql(q, c, branching, metric).join(q, "query_id"), "routes")
    return search.merge_top_k(search.scan_subs(routed, ws.keep(router.assign_sql(x, c, metric), "placed"), K, metric), K)


def sql_det(name: str, metric: str, branching: int) -> str:
    """``t`` as the routed answer with fixed ingredients."""
    return f"WITH {ctes(name)}, {sql_route(metric)}, {sql_placed(metric)}, v AS (SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= {branching}), t AS (SELECT * FROM (SELECT query_id, item_id, s, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM (SELECT v.query_id, p.item_id, {SQL_SCORE[metric].format('q.vec', 'p.vec')} AS s FROM v JOIN p ON p.sub_id = v.sub_id JOIN q ON q.query_id = v.query_id)) WHERE rank <= {K})"


for _metric, _set in (("l2", "emb"), ("cosine", "emb"), ("ip", "emb_scaled")):

    @query(f"routed_{_metric}_det", f"{sql_det(_set, _metric, 5)} {SQL_ANSWER}")
    def _routed_det(spark: SparkSession, d: str, metric: str = _metric, name: str = _set) -> DataFrame:
        return tidy(_det_answer(spark, d, name, metric, 5))


@query("recall_top1", f"{sql_det('emb', 'l2', 5)}, b AS (SELECT * FROM (SELECT query_id, item_id, row_number() OVER (PARTITION BY query_id ORDER BY list_distance(q.vec, e.vec), item_id) AS n FROM q, e WHERE query_id <> item_id) WHERE n = 1) SELECT round(count(t.item_id) / count(*), 6) AS recall FROM b LEFT JOIN t ON t.query_id = b.query_id AND t.item_id = b.item_id")
def _recall(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    truth = search.exact_topk(q, x, 1, exclude_self=True)
    return measures.recall_top1(_det_answer(spark, d, "emb", "l2", 5), truth, K).select(F.round("recall", 6).alias("recall"))


_SQL_TWO = "p2 AS (SELECT item_id, vec, center_id, sub_id FROM (SELECT e.item_id, e.vec, c.center_id, c.sub_id, row_number() OVER (PARTITION BY e.item_id ORDER BY list_distance(e.vec, c.vec), center_id) AS n FROM e, c) WHERE n <= 3)"


@query("merge_dedup_topk", f"WITH {ctes()}, {sql_route('l2')}, {_SQL_TWO}, v AS (SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 5), u AS (SELECT DISTINCT v.query_id, p2.item_id, round(-list_distance(q.vec, p2.vec), 6) AS s FROM v JOIN p2 ON p2.sub_id = v.sub_id JOIN q ON q.query_id = v.query_id) SELECT query_id, CAST(rank AS INTEGER) AS rank, item_id, s AS score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM u) WHERE rank <= {K}")
def _merge_dedup(spark: SparkSession, d: str) -> DataFrame:
    x, q, c = fixed(spark, d)
    near = router.nearest_centers(x.select(F.col("item_id").alias("query_id"), "vec"), c.select("center_id", "vec"), 3).join(small(c.select("center_id", "sub_id")), "center_id")
    placed = near.select("sub_id", F.col("query_id").alias("item_id"), "vec")
    routed = router.route_sql(q, c, 5).join(q, "query_id")
    found = search.scan_subs(routed, placed.dropDuplicates(["sub_id", "item_id"]), K).withColumn("score", F.round("score", 6))
    return search.merge_top_k(found, K).select("query_id", F.col("rank").cast("int").alias("rank"), "item_id", "score")


@query("multi_assign_l2", f"WITH {ctes()}, o AS (SELECT e.item_id, c.sub_id, min(list_distance(e.vec, c.vec)) AS s FROM e, c GROUP BY 1, 2) SELECT item_id, sub_id FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY s, sub_id) AS n FROM o) WHERE n <= 2")
def _multi_assign(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d)
    pool = c.agg(F.collect_list(F.struct("center_id", "sub_id", F.col("vec").alias("cv"))).alias("pool"))
    scored = x.join(small(pool)).select("item_id", F.explode(F.transform("pool", lambda p: F.struct(p["sub_id"].alias("sub_id"), vectors.score(F.col("vec"), p["cv"], "l2").alias("s")))).alias("o"))
    best = scored.groupBy("item_id", "o.sub_id").agg(F.max("o.s").alias("s"))
    return router.top_rank(best, "item_id", 2, "s", "sub_id").select("item_id", "sub_id")


# --- inner product --------------------------------------------------------------------------------


def _unit_centers(c: DataFrame) -> DataFrame:
    return c.withColumn("vec", vectors.normalise(F.col("vec")))


def sql_unit(name: str) -> str:
    return ctes(name).replace("CAST(item_id AS INTEGER) AS center_id, vec,", "CAST(item_id AS INTEGER) AS center_id, list_transform(vec, lambda z: z / sqrt(list_inner_product(vec, vec))) AS vec,")


_SQL_REPLICA = "x AS (SELECT sub_id, item_id FROM (SELECT c.center_id, c.sub_id, e.item_id, row_number() OVER (PARTITION BY c.center_id ORDER BY list_inner_product(c.vec, e.vec) DESC, e.item_id) AS n FROM c, e) WHERE n <= {r})"


@query("ip_replicas", f"WITH {sql_unit('emb_scaled')}, {_SQL_REPLICA.format(r=5)} SELECT DISTINCT sub_id, item_id FROM x")
def _replicas(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d, "emb_scaled")
    return mips.replicate_sql(x, _unit_centers(c), 5).select("sub_id", "item_id")


@query("ip_replicas_blocks", f"WITH {sql_unit('emb_scaled')}, {_SQL_REPLICA.format(r=5)} SELECT DISTINCT sub_id, item_id FROM x")
def _replicas_blocks(spark: SparkSession, d: str) -> DataFrame:
    ship(spark)
    x, _, c = fixed(spark, d, "emb_scaled")
    return mips.replicate(x, meta_of(_unit_centers(c), "ip"), 5).select("sub_id", "item_id")


@query("ip_storage_overhead", f"WITH {sql_unit('emb_scaled')}, {sql_placed('ip')}, {_SQL_REPLICA.format(r=5)}, a AS (SELECT sub_id, item_id FROM p UNION SELECT sub_id, item_id FROM x) SELECT count(*) AS stored, round(count(*) / (SELECT count(*) FROM e) - 1, 6) AS net_overhead, round((SELECT count(*) FROM c) * 5 / (SELECT count(*) FROM e), 6) AS gross_overhead FROM a")
def _storage(spark: SparkSession, d: str) -> DataFrame:
    x, _, c = fixed(spark, d, "emb_scaled")
    c = _unit_centers(c)
    ws = Workspace(spark, "storage")
    placed = mips.union_placement(ws.keep(router.assign_sql(x, c, "ip"), "placed"), ws.keep(mips.replicate_sql(x, c, 5), "replicas"))
    return measures.storage(placed, x.count(), c.count(), 5).select("stored", F.round("net_overhead", 6).alias("net_overhead"), F.round("gross_overhead", 6).alias("gross_overhead"))


def _sql_by_r(r: int) -> str:
    return f"SELECT CAST({r} AS INTEGER) AS r, * FROM (WITH {sql_unit('emb_scaled')}, {sql_route('ip')}, {sql_placed('ip')}, {_SQL_REPLICA.format(r=r)}, a AS (SELECT sub_id, item_id FROM p UNION SELECT sub_id, item_id FROM x), {sql_truth('ip')}, v AS (SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 1), u AS (SELECT DISTINCT v.query_id, a.item_id FROM v JOIN a ON a.sub_id = v.sub_id), f AS (SELECT u.query_id, u.item_id, row_number() OVER (PARTITION BY u.query_id ORDER BY list_inner_product(q.vec, e.vec) DESC, u.item_id) AS n FROM u JOIN q ON q.query_id = u.query_id JOIN e ON e.item_id = u.item_id) SELECT round(count(t.item_id) / ({K}.0 * (SELECT count(*) FROM q)), 6) AS precision FROM f LEFT JOIN t ON t.query_id = f.query_id AND t.item_id = f.item_id WHERE n <= {K})"


@query("ip_precision_by_r", " UNION ALL ".join(map(_sql_by_r, (0, 5, 20))))
def _precision_by_r(spark: SparkSession, d: str) -> DataFrame:
    x, q, c = fixed(spark, d, "emb_scaled")
    c = _unit_centers(c)
    truth = search.exact_topk(q, x, K, "ip")
    primary = router.assign_sql(x, c, "ip")
    routed = router.route_sql(q, c, 1, "ip").join(q, "query_id")
    out = None
    for r in (0, 5, 20):
        placed = mips.union_placement(primary, mips.replicate_sql(x, c, r)) if r else primary
        p = measures.precision(search.merge_top_k(search.scan_subs(routed, placed, K, "ip"), K), truth, K).select(F.lit(r).alias("r"), F.round("precision", 6).alias("precision"))
        out = p if out is None else out.unionByName(p)
    return out


for _set in ("emb", "emb_scaled", "letters", "hashtext"):

    @query(f"ip_norm_share_{_set}", f"WITH {ctes(_set)}, {sql_truth('ip')}, b AS (SELECT item_id, ntile(20) OVER (ORDER BY round(sqrt(list_inner_product(vec, vec)), 6) DESC, item_id) AS bin FROM e) SELECT CAST(bin AS INTEGER) AS bin, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM t JOIN b USING (item_id) GROUP BY 1")
    def _norm_share(spark: SparkSession, d: str, name: str = _set) -> DataFrame:
        """Vectors are computed once and written, since they are scanned, ranked and counted."""
        x = Workspace(spark, "norms").keep(datasets.items(spark, d, name), "items")
        truth = search.exact_topk_blocks(datasets.sampled_queries(x), x, K, "ip")
        return measures.norm_share(truth, x).select("bin", F.round("share", 6).alias("share"))


@query("ip_augmented_rank", f"WITH {ctes('emb_scaled')}, {sql_truth('ip')} SELECT query_id, CAST(rank AS INTEGER) AS rank, item_id FROM t")
def _augmented(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d, "emb_scaled")
    return search.exact_topk(mips.augment_queries(q), mips.augment(x), K).select("query_id", "rank", "item_id")


# --- saturated: approximate methods at exhaustive settings equal the scan -------------------------

_SQL_SAT = f"WITH {ctes()}, {sql_truth('l2')} {SQL_ANSWER}"


@query("hnsw_saturated", _SQL_SAT)
def _hnsw_sat(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    return tidy(random_split.build(x, 1).ask(q, K, l=100_000))


@query("routed_l2_saturated", _SQL_SAT)
def _routed_sat(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    index = builder.build(x, builder.Params(m=20, w=4, kmeans_iters=4))
    return tidy(builder.ask(index, q, 1_000, K, l=100_000, mode="exact"))


@query("routed_ip_saturated", f"WITH {ctes('emb_scaled')}, {sql_truth('ip')} {SQL_ANSWER}")
def _routed_ip_sat(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d, "emb_scaled")
    index = builder.build(x, builder.Params(metric="ip", m=20, w=4, r=5, kmeans_iters=4))
    return tidy(builder.ask(index, q, 1_000, K, l=100_000, mode="exact"))


@query("random_split_saturated", _SQL_SAT)
def _split_sat(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    return tidy(random_split.build(x, 4).ask(q, K, l=100_000))


@query("replicated_saturated", _SQL_SAT)
def _replicated_sat(spark: SparkSession, d: str) -> DataFrame:
    x, q, _ = fixed(spark, d)
    return tidy(random_split.replicated(x, q, 3, K, l=100_000))


@query("kdtree_saturated", _SQL_SAT)
def _kdtree_sat(spark: SparkSession, d: str) -> DataFrame:
    ship(spark)
    x, q, _ = fixed(spark, d)
    return tidy(kdtree.ask(x, q, 4, K))


@query("ivf_det", f"WITH {ctes()}, {sql_route('l2')}, {sql_placed('l2')}, t AS (SELECT * FROM (SELECT query_id, item_id, s, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM (SELECT r.query_id, p.item_id, -list_distance(q.vec, p.vec) AS s FROM r JOIN p ON p.center_id = r.center_id JOIN q ON q.query_id = r.query_id WHERE r.rank <= 8)) WHERE rank <= {K}) {SQL_ANSWER}")
def _ivf(spark: SparkSession, d: str) -> DataFrame:
    x, q, c = fixed(spark, d)
    return tidy(quantised.ivf(x, q, c.select("center_id", "vec"), 8, K))


@query("knn_graph_self", f"WITH {ctes()} SELECT node, CAST(rank AS INTEGER) AS rank, neighbour FROM (SELECT a.item_id AS node, b.item_id AS neighbour, row_number() OVER (PARTITION BY a.item_id ORDER BY list_distance(a.vec, b.vec), b.item_id) AS rank FROM e a, e b WHERE a.item_id <> b.item_id) WHERE rank <= 8")
def _knn_graph(spark: SparkSession, d: str) -> DataFrame:
    return knn_graph.build_rows(datasets.items(spark, d, "emb"), 8).select("node", "rank", "neighbour")


@query("edge_cut_modulo", f"WITH {ctes()}, g AS (SELECT a, b FROM (SELECT x.center_id AS a, y.center_id AS b, row_number() OVER (PARTITION BY x.center_id ORDER BY list_distance(x.vec, y.vec), y.center_id) AS n FROM c x, c y WHERE x.center_id <> y.center_id) WHERE n <= 8) SELECT CAST(count(*) FILTER (WHERE x.sub_id <> y.sub_id) AS BIGINT) AS crossing, count(*) AS edges FROM g JOIN c x ON x.center_id = a JOIN c y ON y.center_id = b")
def _edge_cut(spark: SparkSession, d: str) -> DataFrame:
    _, _, c = fixed(spark, d)
    g = knn_graph.build_rows(c.select(F.col("center_id").alias("item_id"), "vec"), 8).select(F.col("node").alias("a"), F.col("neighbour").alias("b"))
    return measures.edge_cut(g, c.select(F.col("center_id").alias("node"), "sub_id"))


# --- serving model and cost measures ----------------------------------------------------------------


@query("replica_placement", "SELECT CAST(s AS INTEGER) AS sub_id, CAST(c AS INTEGER) AS copy, CAST((s + c * 5) % 10 AS INTEGER) AS executor_id, n AS asked FROM (SELECT CAST(floor(value) AS BIGINT) % 10 AS s, count(*) AS n FROM events WHERE value >= 0 GROUP BY 1), range(2) b(c)")
def _placement(spark: SparkSession, d: str) -> DataFrame:
    """Copies of every part that the event log asks for, with the requests of the part."""
    item = F.floor("value").cast("long")
    asked = table(spark, d, "events").where("value >= 0").groupBy((item % W).cast("int").alias("sub_id")).agg(F.count(F.lit(1)).alias("asked"))
    return dispatch.place_parts(asked, W, 2)


@query("coordinator_modulo", "SELECT CAST(event_id % 7 AS INTEGER) AS coordinator, count(*) AS n FROM events GROUP BY 1")
def _coordinator(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select(dispatch.coordinator(F.col("event_id"), 7, "modulo").alias("coordinator"))
    return e.groupBy("coordinator").agg(F.count(F.lit(1)).alias("n"))


@query("latency_p90", "SELECT round(quantile_cont(value, 0.9), 6) AS latency FROM events")
def _latency(spark: SparkSession, d: str) -> DataFrame:
    return measures.latency_pct(table(spark, d, "events").select(F.col("value").alias("latency"))).select(F.round("latency", 6).alias("latency"))


@query("throughput_windows", "SELECT date_trunc('hour', ts) AS start, count(*) AS queries FROM events GROUP BY 1")
def _throughput(spark: SparkSession, d: str) -> DataFrame:
    return measures.throughput_series(table(spark, d, "events"), "ts", "1 hour")


@query("raw_bytes", "SELECT count(*) * 64 * 4 AS bytes FROM embeddings")
def _bytes(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").agg((F.count(F.lit(1)) * F.lit(measures.raw_bytes(1, 64))).alias("bytes"))


# --- applications --------------------------------------------------------------------------------------


@query("radius_search", f"WITH {ctes()} SELECT query_id, item_id, round(-list_distance(q.vec, e.vec), 6) AS score FROM q, e WHERE list_distance(q.vec, e.vec) <= 1.2")
def _radius(spark: SparkSession, d: str) -> DataFrame:
    """Every item against the stated query set."""
    x, q, _ = fixed(spark, d)
    return search.exact_within(q, x, -1.2).select("query_id", "item_id", F.round("score", 6).alias("score"))


@query("radius_search_routed", f"WITH {ctes()}, {sql_route('l2')}, {sql_placed('l2')}, v AS (SELECT DISTINCT query_id, sub_id FROM r WHERE rank <= 5) SELECT v.query_id, p.item_id, round(-list_distance(q.vec, p.vec), 6) AS score FROM v JOIN p ON p.sub_id = v.sub_id JOIN q ON q.query_id = v.query_id WHERE list_distance(q.vec, p.vec) <= 1.2")
def _radius_routed(spark: SparkSession, d: str) -> DataFrame:
    """All items within the radius in the parts that hold one of a query's five nearest centres."""
    x, q, c = fixed(spark, d)
    ws = Workspace(spark, "radius")
    routed = ws.keep(router.route_sql(q, c, 5).join(q, "query_id"), "routed")
    found = search.radius_subs(routed, ws.keep(router.assign_sql(x, c), "placed"), -1.2)
    return found.select("query_id", "item_id", F.round("score", 6).alias("score"))


@query("filtered_search", f"WITH {ctes()}, f AS (SELECT e.* FROM e JOIN embeddings ON vec_id = item_id WHERE label IN (1, 3)), t AS (SELECT * FROM (SELECT query_id, item_id, s, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM (SELECT query_id, f.item_id, -list_distance(q.vec, f.vec) AS s FROM q, f)) WHERE rank <= {K}) {SQL_ANSWER}")
def _filtered(spark: SparkSession, d: str) -> DataFrame:
    _, q, _ = fixed(spark, d)
    some = table(spark, d, "embeddings").where(F.col("label").isin(1, 3)).select(F.col("vec_id").alias("item_id"), F.col("embedding").cast("array<double>").alias("vec"))
    return tidy(search.exact_topk(q, some, K))


@query("filtered_search_after", f"WITH {ctes()}, t AS (SELECT query_id, item_id, s, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY s DESC, item_id) AS n FROM (SELECT query_id, item_id, -list_distance(q.vec, e.vec) AS s FROM q, e)) JOIN embeddings ON vec_id = item_id WHERE n <= 40 AND label IN (1, 3)) {SQL_ANSWER} WHERE rank <= {K}")
def _filtered_after(spark: SparkSession, d: str) -> DataFrame:
    """Over-fetch, then filter: fewer than ``k`` answers may be left."""
    x, q, _ = fixed(spark, d)
    some = table(spark, d, "embeddings").where(F.col("label").isin(1, 3)).select(F.col("vec_id").alias("item_id"))
    wide = search.exact_topk(q, x, 40).drop("rank").join(some, "item_id", "left_semi")
    return tidy(router.top_rank(wide, "query_id", K))


@query("knn_label_vote", f"WITH e AS ({datasets.SQL['letters']}), l AS (SELECT e.item_id, e.vec, quality FROM e JOIN labels ON doc_id = item_id), n AS (SELECT q.item_id AS query_id, l.quality, row_number() OVER (PARTITION BY q.item_id ORDER BY round(list_cosine_similarity(q.vec, l.vec), 6) DESC, l.item_id) AS r FROM l q, l WHERE q.item_id % 20 = 0 AND q.item_id <> l.item_id), v AS (SELECT query_id, quality, count(*) AS n FROM n WHERE r <= 5 GROUP BY 1, 2) SELECT query_id, CAST(quality AS INTEGER) AS voted FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY n DESC, quality) AS r FROM v) WHERE r = 1")
def _vote(spark: SparkSession, d: str) -> DataFrame:
    known = datasets.items(spark, d, "letters").join(table(spark, d, "labels").select(F.col("doc_id").alias("item_id"), "quality"), "item_id")
    q = known.where("item_id % 20 = 0").select(F.col("item_id").alias("query_id"), F.col("vec").alias("q"))
    s = F.round(vectors.cosine(F.col("q"), F.col("vec")), 6)
    near = router.top_rank(known.crossJoin(small(q)).where("query_id <> item_id").select("query_id", "item_id", "quality", s.alias("score")), "query_id", 5)
    votes = near.groupBy("query_id", "quality").agg(F.count(F.lit(1)).alias("n"))
    return votes.groupBy("query_id").agg(F.max(F.struct("n", (-F.col("quality")).alias("m"))).alias("b")).select("query_id", (-F.col("b.m")).cast("int").alias("voted"))


@query("edit_distance_neighbours", "WITH n AS (SELECT DISTINCT p_name FROM part) SELECT name, CAST(rank AS INTEGER) AS rank, neighbour, distance FROM (SELECT a.p_name AS name, b.p_name AS neighbour, CAST(levenshtein(a.p_name, b.p_name) AS INTEGER) AS distance, row_number() OVER (PARTITION BY a.p_name ORDER BY levenshtein(a.p_name, b.p_name), b.p_name) AS rank FROM n a, n b WHERE a.p_name <> b.p_name) WHERE rank <= 3")
def _edit(spark: SparkSession, d: str) -> DataFrame:
    names = table(spark, d, "part").select("p_name").distinct()
    pairs = names.select(F.col("p_name").alias("name")).crossJoin(small(names.select(F.col("p_name").alias("neighbour")))).where("name <> neighbour")
    scored = pairs.select("name", "neighbour", F.levenshtein("name", "neighbour").alias("distance"), (-F.levenshtein("name", "neighbour")).alias("score"))
    return router.top_rank(scored, "name", 3, tie="neighbour").select("name", F.col("rank").cast("int").alias("rank"), "neighbour", "distance")


@query("recommend_user_item", f"WITH u AS ({datasets.SQL['uservec']}), p AS ({datasets.SQL['partvec']}) SELECT user_id, CAST(rank AS INTEGER) AS rank, item_id FROM (SELECT u.item_id AS user_id, p.item_id, row_number() OVER (PARTITION BY u.item_id ORDER BY round(list_inner_product(u.vec, p.vec), 4) DESC, p.item_id) AS rank FROM u, p WHERE u.item_id % 20 = 0) WHERE rank <= 5")
def _recommend(spark: SparkSession, d: str) -> DataFrame:
    u = datasets.items(spark, d, "uservec").where("item_id % 20 = 0").select(F.col("item_id").alias("user_id"), F.col("vec").alias("u"))
    s = F.round(vectors.dot(F.col("u"), F.col("vec")), 4)
    scored = datasets.items(spark, d, "partvec").crossJoin(small(u)).select("user_id", "item_id", s.alias("score"))
    return router.top_rank(scored, "user_id", 5).select("user_id", F.col("rank").cast("int").alias("rank"), "item_id")


@query("passage_lookup", "SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def _passages(spark: SparkSession, d: str) -> DataFrame:
    """Passages found whole in documents: an equi-join on a passage's second to fifth words, then a check of the text."""
    cut = lambda c: F.split(c, "[ \n]")
    b = table(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"), F.array_join(F.slice(cut("text"), 2, 4), " ").alias("key"))
    docs = table(spark, d, "documents").select("doc_id", "text")
    runs = lambda t: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(t) - 3, F.lit(1))), lambda i: F.array_join(F.slice(t, i, 4), " ")))
    # Bound once a row: a split inside the inner lambda would be repeated for every word.
    keys = F.transform(F.array(cut("text")), runs)[0]
    found = docs.select("doc_id", F.explode(keys).alias("key")).join(small(b), "key").select("item_id", "doc_id", "passage")
    return found.join(docs, "doc_id").where(F.contains("text", "passage")).select("item_id", "doc_id").distinct()


@query("near_copies", f"WITH e AS ({datasets.SQL['letters']}) SELECT item_id, class_id FROM (SELECT item_id, min(item_id) OVER (PARTITION BY vec) AS class_id, count(*) OVER (PARTITION BY vec) AS n FROM e) WHERE n > 1")
def _near_copies(spark: SparkSession, d: str) -> DataFrame:
    """Items of equal vectors with the smallest id of their class: membership, not pairs."""
    x = Workspace(spark, "copies").keep(datasets.items(spark, d, "letters"), "items")
    classes = x.groupBy("vec").agg(F.min("item_id").alias("class_id"), F.count(F.lit(1)).alias("n")).where("n > 1").select("vec", "class_id")
    return x.join(classes, "vec").select("item_id", "class_id")


from vecroute import experiments  # noqa: E402,F401  registers the experiment workloads
from vecroute import served  # noqa: E402,F401  registers walks, streams, serving and SQL functions
from vecroute.operators import relational  # noqa: E402,F401  registers the surrounding operators
