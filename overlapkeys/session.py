"""Session-wide helpers: the shared folder, cutting lineage, worker import path."""

from __future__ import annotations

import atexit
import gc
import os
import re
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


SWEEP_S = 3.0  # seconds between two collections of garbage at least
_swept = 0.0
_settled: dict[str, SparkSession] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only in local mode, where that is unset, a temporary folder of this machine stands in.
    """
    there = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not there:
        master = spark.sparkContext.master
        if not re.fullmatch(r"local(\[.*\])?", master):
            raise RuntimeError(f"spark.checkpoint.dir is unset; executors of {master} share no folder")
        there = f"file://{tempfile.mkdtemp(prefix='overlapkeys-')}"
        spark.conf.set("spark.checkpoint.dir", there)
    return there.rstrip("/")


def discard(spark: SparkSession, path: str) -> None:
    """Delete a table written to the shared folder."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _settled.pop(path, None)


@atexit.register
def _discard_all() -> None:
    """What settle wrote for results that are read by now; a session that has ended can't delete any more."""
    for path, spark in list(_settled.items()):
        try:
            if spark.sparkContext._jsc is not None:
                discard(spark, path)
        except Exception:  # noqa: BLE001  the JVM may have gone first
            return


def scratch(spark: SparkSession, name: str) -> str:
    """A path of its own in the shared folder; what is written there goes when the driver ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _settled[path] = spark
    return path


def sweep(spark: SparkSession) -> None:
    """Collect garbage here and in the JVM, so that Spark's cleaner deletes shuffle files that no plan holds."""
    global _swept
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    _swept = time.monotonic()


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors.

    What was shuffled to make it is garbage then; a collection, every SWEEP_S seconds at most, lets Spark's
    cleaner delete those files. The written table goes when the driver ends.
    """
    spark, schema = df.sparkSession, df.schema
    path = scratch(spark, name)
    df.write.parquet(path)
    del df
    if time.monotonic() - _swept > SWEEP_S:
        sweep(spark)
    out = spark.read.schema(schema).parquet(path)
    out.settled_at = path
    return out


def drop(*frames: DataFrame) -> None:
    """Delete what settle wrote for these frames, which no plan that is still to run may read."""
    for df in frames:
        if path := getattr(df, "settled_at", None):
            discard(df.sparkSession, path)


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package where it isn't installed (local mode, tests)."""
    env = spark.sparkContext.environment
    if ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (ROOT, env.get("PYTHONPATH", "")) if x)
