"""The engine from SQL: registered functions, table functions and views."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType

from vecroute.functions import kernels
from vecroute.graphs import hnsw
from vecroute.plans import builder

#: An index that the table functions hold in memory may have this many items.
MAX_LOCAL_ITEMS = 2_000_000


@F.pandas_udf(DoubleType())
def score_l2(q: pd.Series, x: pd.Series) -> pd.Series:
    a, b = np.stack(q.to_numpy()).astype(float), np.stack(x.to_numpy()).astype(float)
    return pd.Series(-np.sqrt(((a - b) ** 2).sum(axis=1)))


@F.pandas_udf(DoubleType())
def score_ip(q: pd.Series, x: pd.Series) -> pd.Series:
    a, b = np.stack(q.to_numpy()).astype(float), np.stack(x.to_numpy()).astype(float)
    return pd.Series((a * b).sum(axis=1))


@F.pandas_udf(ArrayType(DoubleType()))
def vec_mean(v: pd.Series) -> list[float]:
    """Grouped aggregate: the mean vector."""
    return np.stack(v.to_numpy()).astype(float).mean(axis=0).tolist()


@F.pandas_udf(ArrayType(LongType()))
def top_ids(item_id: pd.Series, score: pd.Series) -> list[int]:
    """Grouped aggregate: ids by falling score, ties to the smaller."""
    return item_id.to_numpy()[np.lexsort((item_id.to_numpy(), -score.to_numpy()))].tolist()


def register(spark: SparkSession, index: builder.Index | None = None, name: str = "idx") -> None:
    """``score_l2``, ``score_ip``, ``vec_mean``, ``top_ids``; with an index also ``ann_search``, ``exact_search``, ``route`` and views ``{name}_centers|placement|graphs``."""
    for f, n in ((score_l2, "score_l2"), (score_ip, "score_ip"), (vec_mean, "vec_mean"), (top_ids, "top_ids")):
        spark.udf.register(n, f)
    if index is None:
        return
    if index.placement.count() > MAX_LOCAL_ITEMS:
        raise ValueError("table functions hold the index in each task; query larger ones through the front end")
    index.centers.createOrReplaceTempView(f"{name}_centers")
    index.placement.createOrReplaceTempView(f"{name}_placement")
    index.graphs.createOrReplaceTempView(f"{name}_graphs")
    graphs = [r.asDict(recursive=True) for r in index.graphs.collect()]
    shared = spark.sparkContext.broadcast((graphs, index.meta, index.params.metric))
    cache: dict[str, list] = {}

    def loaded() -> tuple[dict[int, hnsw.Graph], object, str]:
        if "g" not in cache:
            rows, meta, metric = shared.value
            cache["g"] = [{r["sub_id"]: hnsw.from_row(r) for r in rows}, meta, metric]
        return tuple(cache["g"])

    class AnnSearch:
        def eval(self, query: list[float], k: int, branching: int, l: int) -> Iterator[tuple]:  # noqa: E741
            parts, meta, _ = loaded()
            q = np.array([query], float)
            at = meta.rank(q, min(branching, len(meta.ids)), "graph")[0]
            best: dict[int, float] = {}
            for sub in sorted({int(meta.sub_of[a]) for a in at if a >= 0}):
                if sub in parts:
                    ids, scores, _ = hnsw.search(parts[sub], q, k, l)
                    best.update((int(i), float(s)) for i, s in zip(ids[0], scores[0], strict=True) if i >= 0)
            for rank, (i, s) in enumerate(sorted(best.items(), key=lambda p: (-p[1], p[0]))[:k], 1):
                yield rank, i, s

    class ExactSearch:
        def eval(self, query: list[float], k: int) -> Iterator[tuple]:
            parts, _, metric = loaded()
            best: dict[int, float] = {}
            for g in parts.values():
                s = kernels.score_matrix(kernels.prepared(np.array([query], float), metric), g.x, metric)[0]
                best.update(zip(g.ids.tolist(), s.tolist(), strict=True))
            for rank, (i, s) in enumerate(sorted(best.items(), key=lambda p: (-p[1], p[0]))[:k], 1):
                yield rank, i, s

    class Route:
        def eval(self, query: list[float], branching: int) -> Iterator[tuple]:
            _, meta, _ = loaded()
            at = meta.rank(np.array([query], float), min(branching, len(meta.ids)), "exact")[0]
            for sub in sorted({int(meta.sub_of[a]) for a in at if a >= 0}):
                yield (sub,)

    answers = "rank int, item_id long, score double"
    spark.udtf.register("ann_search", F.udtf(AnnSearch, returnType=answers))
    spark.udtf.register("exact_search", F.udtf(ExactSearch, returnType=answers))
    spark.udtf.register("route", F.udtf(Route, returnType="sub_id int"))


def explain_choice(index: builder.Index, queries: int) -> str:
    from vecroute.serving import planner

    c = planner.cost(index.n, index.d, queries)
    return json.dumps({"scan_s": c.scan_s, "routed_s": c.routed_s, "plan": planner.choose(index.n, index.d, queries)})


def exact_sql(spark: SparkSession, k: int) -> object:
    """Top ``k`` per query in one SQL statement over views ``queries`` and ``items``, with a parameter."""
    return spark.sql("SELECT query_id, rank, item_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, item_id) AS rank FROM (SELECT query_id, item_id, -sqrt(aggregate(zip_with(q.vec, i.vec, (a, b) -> (a - b) * (a - b)), 0D, (acc, x) -> acc + x)) AS score FROM queries q CROSS JOIN items i)) WHERE rank <= :k", args={"k": k})


__all__ = ["exact_sql", "explain_choice", "register", "score_ip", "score_l2", "top_ids", "vec_mean"]
