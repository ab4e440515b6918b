"""Shared helpers of the training-data operators: shared-folder tables, id ranges, Arrow batches."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import time
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Fixed value: the white space that separates words in every contract of this subpackage.
SPACE = r"[\x20\x09-\x0D]+"
SHINGLE_WORDS = 5


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share. Only where the session names none and all runs in one process (tests) is one made up here."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="progmatch-shared-")
        spark.conf.set("spark.checkpoint.dir", named)
    return named if "://" in named else f"file://{named}"


def shared_path(spark: SparkSession, what: str) -> str:
    return f"{shared_root(spark)}/progmatch/{what}-{uuid.uuid4().hex}"


def settle(df: DataFrame, what: str, large: bool = False) -> DataFrame:
    """Writes a table to the shared folder and reads it again: cuts lineage and outlives any executor.

    large: texts or most rows were shuffled for it, and their files go before the next step. A plan just run is still
    referred to for a moment, so that takes a second release. Such a table is packed more tightly.
    """
    spark = df.sparkSession
    path = shared_path(spark, what)
    df.write.parquet(path, compression="zstd" if large else None)
    release(spark)
    if large:
        time.sleep(0.2)
        release(spark)
    made = spark.read.schema(df.schema).parquet(path)
    made.settled_at = path
    return made


def trim() -> None:
    """Gives memory that this Python process has freed back to the system, where its allocators can."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def release(spark: SparkSession) -> None:
    """Gives back what finished plans held: shuffle files and broadcasts go once the driver collects its garbage.

    The driver's native memory is trimmed where its virtual machine has that command.
    """
    gc.collect()
    trim()
    jvm = spark._jvm
    jvm.System.gc()
    with contextlib.suppress(Exception):
        beans = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        beans.invoke(jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap", None, None)


def discard(*settled: DataFrame) -> None:
    """Deletes settled tables that no later step reads."""
    for df in settled:
        drop_path(df.sparkSession, df.settled_at)


def drop_path(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def extended(df: DataFrame, more: str) -> StructType:
    """The schema of df and further fields."""
    return StructType(df.schema.fields + StructType.fromDDL(more).fields)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def gathered(batches: Iterable[pa.RecordBatch], column: str, most: int = 3 << 20) -> Iterator[pa.Table]:
    """Arrow batches put together until their text has about `most` bytes; a longer single text comes alone or last."""
    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        values = batch.column(batch.schema.get_field_index(column))
        start = 0
        if values.nbytes > 2 * most and batch.num_rows > 1:
            lengths = pc.fill_null(pc.binary_length(values), 0).to_numpy(zero_copy_only=False)
            ends = np.flatnonzero(np.diff(np.cumsum(lengths) // most, prepend=0))
            for end in ends:
                if end > start:
                    yield pa.Table.from_batches([*held, batch.slice(start, end - start)])
                    held, size, start = [], 0, int(end)
        rest = batch.slice(start)
        held.append(rest)
        size += rest.column(rest.schema.get_field_index(column)).nbytes
        if size >= most:
            yield pa.Table.from_batches(held)
            held, size = [], 0
    if held and sum(b.num_rows for b in held):
        yield pa.Table.from_batches(held)
    held.clear()
    trim()  # a worker lives on after its task, beside those of other tasks


def texts_of(part: pa.Table, column: str = "text") -> pa.Array:
    """The texts as one Arrow array with 64-bit offsets, null as empty."""

    whole = part.column(column).cast(pa.large_string()).combine_chunks()
    if isinstance(whole, pa.ChunkedArray):
        whole = pa.concat_arrays(whole.chunks) if whole.num_chunks else pa.array([], pa.large_string())
    return pc.fill_null(whole, "")


def word_codes(texts: pa.Array) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """(code of each word, distinct words, first word of each text and the end): words as SPACE splits them."""

    lists = pc.ascii_split_whitespace(texts)
    flat, offsets = lists.flatten(), lists.offsets.to_numpy() - lists.offsets[0].as_py()
    full = pc.greater(pc.binary_length(flat), 0)
    coded = flat.dictionary_encode()
    codes, words = coded.indices.to_numpy(), coded.dictionary
    keep = full.to_numpy(zero_copy_only=False)
    if not keep.all():
        kept_before = np.concatenate(([0], np.cumsum(keep)))
        codes, offsets = codes[keep], kept_before[offsets]
    return codes, words, np.asarray(offsets, dtype=np.int64)


def mixed64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads any bits over all bits."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(32)
    return x


def word_hashes(words: pa.Array) -> np.ndarray:
    """64-bit hash of each distinct word, the same in every process."""
    import xxhash

    digest = xxhash.xxh3_64_intdigest
    return np.fromiter((digest(w) for w in words.to_pylist()), dtype=np.uint64, count=len(words))
