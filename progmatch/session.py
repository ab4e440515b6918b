"""Session-dependent helpers: the shared folder, settled tables, shuffle width."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; only where it is unset and all runs in one process, as in tests, one of our own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="progmatch-shared-")
        spark.conf.set("spark.checkpoint.dir", named)
    return named if "://" in named else f"file://{named}"


def settle(df: DataFrame, what: str, compression: str | None = None) -> DataFrame:
    """Written to the shared folder and read again: later steps don't compute it anew and lost executors don't matter."""
    path = f"{shared_root(df.sparkSession)}/progmatch/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression=compression)
    made = df.sparkSession.read.schema(df.schema).parquet(path)
    made.settled_at = path
    return made


def release(spark: SparkSession) -> None:
    """Shuffle files of finished plans go once the driver collects its garbage; a plan just run is referred to for a moment."""
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.2)


def drop(*settled: DataFrame) -> None:
    """Deletes settled tables that no later step reads."""
    for df in settled:
        with contextlib.suppress(AttributeError):
            path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df.settled_at)
            path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
