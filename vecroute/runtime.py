"""What every operator shares: shipping the code, and tables that cut lineage."""

from __future__ import annotations

import atexit
import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = Path(__file__).resolve().parent
_shipped: dict[str, str] = {}


def ship(spark: SparkSession) -> None:
    """Hand this package to the executors once per Spark application.

    Python workers then import it whatever folder the driver was started in.
    """
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(ROOT.rglob("*.py")):
            z.write(p, str(Path(ROOT.name) / p.relative_to(ROOT)))
    folder = tempfile.mkdtemp(prefix="vecroute-")
    path = os.path.join(folder, f"{ROOT.name}_pkg.zip")
    Path(path).write_bytes(buffer.getvalue())
    spark.sparkContext.addPyFile(path)
    _shipped[app] = path


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    ``spark.checkpoint.dir`` where the cluster names one; else, as in tests, a
    folder of our own.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    return f"{named.rstrip('/')}" if named else "/tmp/checkpoints"


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    hadoop = jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


class Workspace:
    """Written tables of one call; each cuts the lineage at the shared folder.

    A table is written whole before it is read, so a lost executor costs a
    re-read and nothing is computed twice with another outcome. ``drop`` frees a
    table that no later step reads; what is left goes when the driver ends.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.base = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        self._n = 0
        atexit.register(self._quiet_close)

    def keep(self, df: DataFrame, label: str = "t") -> DataFrame:
        self._n += 1
        path = f"{self.base}/{self._n:03d}-{label}"
        df.write.mode("overwrite").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._kept_at = path
        return out

    def drop(self, df: DataFrame) -> None:
        path = getattr(df, "_kept_at", None)
        if path:
            _remove(self.spark, path)

    def close(self) -> None:
        _remove(self.spark, self.base)

    def _quiet_close(self) -> None:
        try:
            if self.spark.sparkContext._jsc is not None:
                self.close()
        except Exception:  # the driver is ending; the folder may be gone already
            pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; works for any path that Spark can read."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")
