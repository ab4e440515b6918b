"""Global positions without one task that sorts everything."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.session import settle, shuffle_width

#: A result of at most so many rows is put in order in one task.
ONE_TASK_ROWS = 200_000


def positioned(df: DataFrame, keys: list[str], limit: int | None = None, ranges: int | None = None) -> DataFrame:
    """Adds pos from 1, by `keys` ascending (together unique); with limit, the first `limit` rows only.

    A small limit is a top-k: a heap in each task, one merge. Else rows are range-partitioned by the keys and settled with
    their partition's number; a row's position is its place in the partition plus the rows of the partitions before, of which
    the driver sees one count each.
    """
    if limit is not None and limit < 0:
        raise ValueError(f"negative limit: {limit}")
    if limit is not None and limit <= ONE_TASK_ROWS:
        top = df.orderBy(*keys).limit(limit)
        return top.withColumn("pos", F.row_number().over(Window.orderBy(*keys)).cast("long"))
    n = ranges or shuffle_width(df.sparkSession)
    spread = settle(df.repartitionByRange(n, *keys).withColumn("__at", F.spark_partition_id()), "ordered")
    counts = {r["__at"]: r["count"] for r in spread.groupBy("__at").count().collect()}
    numbers = sorted(counts)
    starts = [0, *accumulate(counts[k] for k in numbers)][:-1]
    if not numbers:
        return spread.withColumn("pos", F.lit(0).cast("long")).drop("__at")
    start = F.map_from_arrays(F.array(*[F.lit(k) for k in numbers]), F.array(*[F.lit(s).cast("long") for s in starts]))
    if limit is not None:
        spread = spread.where(F.element_at(start, F.col("__at")) < limit)
    placed = spread.withColumn("pos", F.row_number().over(Window.partitionBy("__at").orderBy(*keys)) + F.element_at(start, F.col("__at"))).drop("__at")
    return placed if limit is None else placed.where(F.col("pos") <= limit)
