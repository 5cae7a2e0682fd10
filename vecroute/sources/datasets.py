"""Vector sets derived from the given tables, each with the DuckDB query that gives the same rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecroute.plans.ranking import global_rank
from vecroute.runtime import table

LETTERS = "abcdefghijklmnopqrstuvwxyz"
DIMENSION = {"emb": 64, "emb_scaled": 64, "line5": 5, "letters": 26, "hashtext": 64, "partvec": 12, "uservec": 12, "eventvec": 8}

SQL = {
    "emb": "SELECT vec_id AS item_id, CAST(embedding AS DOUBLE[]) AS vec FROM embeddings",
    "emb_scaled": "SELECT vec_id AS item_id, list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * pow(2.0, ((vec_id * 7919) % 1000) / 250.0 - 2)) AS vec FROM embeddings",
    "line5": "SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) AS item_id, [l_quantity / 50, l_extendedprice / 105000, l_discount * 10, l_tax * 12.5, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) / 2500.0] AS vec FROM lineitem",
    "letters": "SELECT doc_id AS item_id, [" + ", ".join(f"CAST(length(lower(text)) - length(replace(lower(text), '{c}', '')) AS DOUBLE)" for c in LETTERS) + "] AS vec FROM documents",
    "hashtext": "WITH t AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents), h AS (SELECT doc_id, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) AS h FROM t), b AS (SELECT doc_id, h % 64 AS b, SUM(CASE WHEN (h // 65536) % 2 = 1 THEN 1e0 ELSE -1e0 END) AS s FROM h GROUP BY 1, 2), m AS (SELECT doc_id, map_from_entries(list((b, s))) AS m FROM b GROUP BY 1) SELECT d.doc_id AS item_id, list_transform(range(0, 64), lambda i: coalesce(m.m[i], 0e0)) AS vec FROM documents d LEFT JOIN m ON d.doc_id = m.doc_id",
    "partvec": "SELECT p_partkey AS item_id, [p_size / 50.0, p_retailprice / 1000.0] || list_transform(range(0, 6), lambda i: CASE WHEN i = list_position(['STANDARD', 'SMALL', 'MEDIUM', 'LARGE', 'ECONOMY', 'PROMO'], split_part(p_type, ' ', 1)) - 1 THEN 1.0 ELSE 0.0 END) || list_transform(range(0, 4), lambda i: CASE WHEN i = CAST('0x' || substr(md5(p_brand), 1, 8) AS BIGINT) % 4 THEN 1.0 ELSE 0.0 END) AS vec FROM part",
    "eventvec": "SELECT event_id AS item_id, [value / 100.0, hour(ts) / 24.0, COALESCE(CAST(json_extract_string(props, '$.k') AS DOUBLE), 0.0) / 100.0] || list_transform(range(0, 5), lambda i: CASE WHEN i = CAST('0x' || substr(md5(event_type), 1, 8) AS BIGINT) % 5 THEN 1.0 ELSE 0.0 END) AS vec FROM events",
}
SQL["uservec"] = f"""WITH p AS ({SQL['partvec']}), e AS (SELECT o_custkey, i, SUM(l_quantity * p.vec[i]) AS s FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN p ON p.item_id = l_partkey, (SELECT unnest(range(1, 13)) AS i) GROUP BY 1, 2)
SELECT o_custkey AS item_id, list(s ORDER BY i) AS vec FROM e GROUP BY 1"""


def _hash_of(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def _one_hot(width: int, at: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.when(i == at, 1.0).otherwise(0.0))


def _emb(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("item_id"), F.col("embedding").cast("array<double>").alias("vec"))


def _emb_scaled(spark: SparkSession, d: str) -> DataFrame:
    factor = F.pow(F.lit(2.0), F.expr("((vec_id * 7919) % 1000) / 250.0D - 2"))
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("item_id"), F.transform(F.col("embedding").cast("array<double>"), lambda x: x * factor).alias("vec"))


def line5_vector() -> Column:
    days = F.date_diff(F.to_date("l_shipdate"), F.lit("1995-01-01").cast("date"))
    return F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") * 10, F.col("l_tax") * 12.5, days / F.lit(2500.0))


_LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")


def _line5(spark: SparkSession, d: str) -> DataFrame:
    """Ids are the exact rank by the six columns."""
    rows = table(spark, d, "lineitem").select(*_LINE_KEY, line5_vector().alias("vec"))
    return global_rank(rows, F.col("l_orderkey"), [F.col(c) for c in _LINE_KEY], name="item_id").select("item_id", "vec")


def line5_at_scale(spark: SparkSession, d: str) -> DataFrame:
    """The same vectors under hashed ids: no ordering of the whole table."""
    return table(spark, d, "lineitem").select(F.xxhash64(*_LINE_KEY).alias("item_id"), line5_vector().alias("vec"))


def _letters(spark: SparkSession, d: str) -> DataFrame:
    t = F.lower("text")
    return table(spark, d, "documents").select(F.col("doc_id").alias("item_id"), F.array(*[(F.length(t) - F.length(F.replace(t, F.lit(c), F.lit("")))).cast("double") for c in LETTERS]).alias("vec"))


def _hashtext(spark: SparkSession, d: str) -> DataFrame:
    """Counts per word first, so the exchange carries distinct words and buckets only."""
    docs = table(spark, d, "documents").select(F.col("doc_id").alias("item_id"), "text")
    words = docs.select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0)).alias("w"))
    h = _hash_of(F.col("w"))
    sign = F.when(F.floor(h / 65536) % 2 == 1, 1.0).otherwise(-1.0)
    sums = words.select("item_id", (h % 64).cast("int").alias("b"), sign.alias("s")).groupBy("item_id", "b").agg(F.sum("s").alias("s"))
    maps = sums.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("b", "s"))).alias("m"))
    wide = docs.select("item_id").join(maps, "item_id", "left")
    return wide.select("item_id", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0))).alias("vec"))


def _partvec(spark: SparkSession, d: str) -> DataFrame:
    kinds = F.array(*[F.lit(k) for k in ("STANDARD", "SMALL", "MEDIUM", "LARGE", "ECONOMY", "PROMO")])
    kind = F.array_position(kinds, F.split_part("p_type", F.lit(" "), F.lit(1))) - 1
    return table(spark, d, "part").select(F.col("p_partkey").alias("item_id"), F.concat(F.array(F.col("p_size") / F.lit(50.0), F.col("p_retailprice") / 1000.0), _one_hot(6, kind), _one_hot(4, _hash_of(F.col("p_brand")) % 4)).alias("vec"))


def _uservec(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    bought = lines.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey", "l_partkey").agg(F.sum("l_quantity").alias("q"))
    joined = bought.join(_partvec(spark, d), F.col("l_partkey") == F.col("item_id"))
    sums = joined.groupBy("o_custkey").agg(*[F.sum(F.col("q") * F.col("vec")[i]).alias(f"v{i}") for i in range(12)])
    return sums.select(F.col("o_custkey").alias("item_id"), F.array(*[f"v{i}" for i in range(12)]).alias("vec"))


def _eventvec(spark: SparkSession, d: str) -> DataFrame:
    k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)) / 100.0
    return table(spark, d, "events").select(F.col("event_id").alias("item_id"), F.concat(F.array(F.col("value") / 100.0, F.hour("ts") / F.lit(24.0), k), _one_hot(5, _hash_of(F.col("event_type")) % 5)).alias("vec"))


_BUILD = {"emb": _emb, "emb_scaled": _emb_scaled, "line5": _line5, "letters": _letters, "hashtext": _hashtext, "partvec": _partvec, "uservec": _uservec, "eventvec": _eventvec}


def items(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``item_id, vec`` of a named vector set; vectors are double."""
    return _BUILD[name](spark, sf_dir)


def sampled_queries(vectors: DataFrame, modulus: int = 7, keep: int = 3) -> DataFrame:
    """``query_id, vec``: the items whose id leaves a remainder."""
    return vectors.where(F.col("item_id") % modulus == keep).select(F.col("item_id").alias("query_id"), "vec")


def hot_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``item_id``: a skewed access log, one row per event that hits an existing vector."""
    hits = table(spark, sf_dir, "events").select(F.floor("value").cast("long").alias("item_id"))
    return hits.join(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id")), "item_id", "left_semi")
