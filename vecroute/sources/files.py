"""Vector files in and out: text forms, and dimension-prefixed binary."""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TEXT_DDL = "item_id long, vec string"


def write_text(items: DataFrame, path: str, kind: str = "csv") -> None:
    """Vectors as ``[..]`` strings in csv or json; orc and parquet keep the array."""
    if kind in ("orc", "parquet"):
        getattr(items.select("item_id", "vec").write.mode("overwrite"), kind)(path)
    else:
        getattr(items.select("item_id", F.to_json("vec").alias("vec")).write.mode("overwrite"), kind)(path)


def read_text(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    if kind in ("orc", "parquet"):
        return getattr(spark.read.schema("item_id long, vec array<double>"), kind)(path)
    raw = getattr(spark.read.schema(TEXT_DDL), kind)(path)
    return raw.select("item_id", F.from_json("vec", "array<double>").alias("vec"))


def encode_vecs(x: np.ndarray, kind: str = "f") -> bytes:
    """``f`` for 4-byte floats, ``b`` for bytes; each vector follows its dimension."""
    head = struct.pack("<i", x.shape[1])
    body = x.astype("<f4" if kind == "f" else "u1")
    return b"".join(head + row.tobytes() for row in body)


def decode_vecs(raw: bytes, kind: str = "f") -> np.ndarray:
    if not raw:
        return np.zeros((0, 0))
    d = struct.unpack_from("<i", raw)[0]
    width = 4 + d * (4 if kind == "f" else 1)
    if len(raw) % width:
        raise ValueError("the file ends inside a vector, or dimensions differ")
    table = np.frombuffer(raw, np.uint8).reshape(-1, width)
    if (table[:, :4] != table[0, :4]).any():
        raise ValueError("dimensions differ")
    body = np.ascontiguousarray(table[:, 4:])
    return (body.view("<f4") if kind == "f" else body).astype(np.float64).reshape(-1, d)


def read_vecs(spark: SparkSession, path: str, kind: str = "f") -> DataFrame:
    """``path, item_id, vec`` of all files under a path; ids count from 0 in each file. One file is one task: write many."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                x = decode_vecs(raw, kind)
                for s in range(0, len(x), 4096):
                    part = x[s : s + 4096]
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(part)), pa.array(np.arange(s, s + len(part))), pa.array(part.tolist(), pa.list_(pa.float64()))], ["path", "item_id", "vec"])

    files = spark.read.format("binaryFile").load(path).select("path", "content")
    return files.mapInArrow(run, "path string, item_id long, vec array<double>")
