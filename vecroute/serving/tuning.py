"""The least work that reaches a wanted precision."""

from __future__ import annotations

import functools
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecroute.functions import measures
from vecroute.plans import builder, router, search
from vecroute.runtime import Workspace


@dataclass(frozen=True)
class Setting:
    branching: int
    l: int  # noqa: E741
    precision: float
    evals: float


def sweep(index: builder.Index, queries: DataFrame, truth: DataFrame, branchings: list[int], beams: list[int], k: int = 10) -> list[Setting]:
    """Precision and evaluations per query of every pair; one routing pass serves all branching factors."""
    workspace = Workspace(index.spark, "tuning")
    n = queries.count()
    routed = workspace.keep(router.route(queries, index.meta, max(branchings), keep_rank=True), "routed")
    out = []
    for beam in beams:
        found = workspace.keep(search.search_subs(routed.drop("rank"), index.graphs, k, beam), "partials").join(routed.select("query_id", "sub_id", F.col("rank").alias("reach")), ["query_id", "sub_id"])
        for b in branchings:
            seen = found.where(F.col("reach") <= b)
            p = measures.precision(search.merge_top_k(seen, k), truth, k).first().precision
            per = seen.select("query_id", "sub_id", "evals").distinct().agg(F.sum("evals")).first()[0] or 0
            out.append(Setting(b, beam, p, per / max(1, n)))
    return out


def least_work(ask: Callable[[int], DataFrame], queries: DataFrame, truth: DataFrame, target: float, k: int = 10, rungs: int = 5, factor: float = 2.4) -> Setting:
    """Evaluations per query at ``target``, over a ladder of caps per visited part from ``k`` upwards.

    Between the last cap below the target and the first that reaches it, evaluations
    are interpolated, so that systems are compared at equal precision; ``l`` holds the latter cap.

    ``ask(cap)`` gives partial answers with their ``evals``; all caps are asked in one
    job. If none reaches the target, the setting of the largest is returned.
    """
    workspace, n = Workspace(queries.sparkSession, "least"), queries.count()
    caps = sorted({round(k * factor**i) for i in range(rungs)})
    frames = [ask(c).select(F.lit(c).alias("cap"), "query_id", "sub_id", "item_id", "score", "evals") for c in caps]
    found = workspace.keep(functools.reduce(DataFrame.unionByName, frames), "partials")
    once = found.groupBy("cap", "query_id", "item_id").agg(F.max("score").alias("score")).withColumn("cq", F.struct("cap", "query_id"))
    reached = measures.precision(router.top_rank(once, "cq", k), truth, k, ["cap"])
    work = found.groupBy("cap", "query_id", "sub_id").agg(F.max("evals").alias("evals")).groupBy("cap").agg(F.sum("evals").alias("evals"))
    settings = [Setting(0, r.cap, r.precision, r.evals / max(1, n)) for r in reached.join(work, "cap").orderBy("cap").collect()]
    at = next((i for i, x in enumerate(settings) if x.precision >= target), None)
    if at is None or at == 0:
        return settings[-1 if at is None else 0]
    below, above = settings[at - 1], settings[at]
    part = (target - below.precision) / (above.precision - below.precision)
    return Setting(0, above.l, target, below.evals + part * (above.evals - below.evals))


def match_precision(index: builder.Index, queries: DataFrame, truth: DataFrame, target: float, branchings: list[int], beams: list[int], k: int = 10) -> Setting:
    """Of the settings that reach ``target``, the one of fewest evaluations; else the most precise."""
    all_ = sweep(index, queries, truth, branchings, beams, k)
    good = [s for s in all_ if s.precision >= target]
    return min(good, key=lambda s: s.evals) if good else max(all_, key=lambda s: s.precision)
