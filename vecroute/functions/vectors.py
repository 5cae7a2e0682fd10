"""Vector expressions that stay in the JVM, and their checks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

METRICS = ("l2", "cosine", "ip")


def doubles(v: Column) -> Column:
    """Scores are never accumulated in 32 bits."""
    return v.cast("array<double>")


def fold_sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def dot(a: Column, b: Column) -> Column:
    return fold_sum(F.zip_with(doubles(a), doubles(b), lambda x, y: x * y))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def distance(a: Column, b: Column) -> Column:
    return F.sqrt(fold_sum(F.zip_with(doubles(a), doubles(b), lambda x, y: (x - y) * (x - y))))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def score(q: Column, x: Column, metric: str) -> Column:
    """Similarity, larger is closer: negative distance, cosine or inner product."""
    if metric not in METRICS:
        raise ValueError(f"no metric {metric!r}")
    return {"l2": lambda: -distance(q, x), "cosine": lambda: cosine(q, x), "ip": lambda: dot(q, x)}[metric]()


def normalise(v: Column) -> Column:
    """Unit length; a zero vector stays zero."""
    # Bound once a row: a norm inside the lambda would be summed for every component.
    both = F.array(F.struct(doubles(v).alias("v"), norm(v).alias("n")))
    return F.transform(both, lambda b: F.transform(b["v"], lambda x: F.when(b["n"] > 0, x / b["n"]).otherwise(F.lit(0.0))))[0]


def add(a: Column, b: Column) -> Column:
    return F.zip_with(doubles(a), doubles(b), lambda x, y: x + y)


def scale(a: Column, by: Column) -> Column:
    return F.transform(doubles(a), lambda x: x * by)


def slice_of(a: Column, start: int, length: int) -> Column:
    return F.slice(doubles(a), start + 1, length)


def pad(a: Column, width: int) -> Column:
    return F.concat(doubles(a), F.array_repeat(F.lit(0.0), F.greatest(F.lit(width) - F.size(a), F.lit(0)).cast("int")))


def reject_reason(v: Column, dimension: int, metric: str = "l2") -> Column:
    """Why a vector cannot be indexed, or null."""
    d = doubles(v)
    odd = F.exists(d, lambda x: x.isNull())
    wild = F.exists(d, lambda x: F.isnan(x) | (F.abs(x) == float("inf")))
    reason = F.when(v.isNull(), "null").when(F.size(v) != dimension, "length").when(odd, "null component").when(wild, "not finite")
    return reason.when(fold_sum(F.transform(d, lambda x: x * x)) == 0, "zero norm") if metric == "cosine" else reason


def split_valid(items: DataFrame, dimension: int, metric: str = "l2") -> tuple[DataFrame, DataFrame]:
    """Indexable rows, and rejects with a ``reason``."""
    checked = items.withColumn("reason", reject_reason(F.col("vec"), dimension, metric))
    return checked.where("reason is null").drop("reason"), checked.where("reason is not null")
