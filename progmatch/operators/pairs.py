"""Pairs of rows that share a key, without one task for a very frequent key."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a key that meet in one task at most.
KEY_ROWS = 20_000


def with_cells(rows: DataFrame, key: str, sizes: DataFrame, limit: int = KEY_ROWS) -> DataFrame:
    """Adds part, a, b: a key with more rows than `limit` is cut into parts, and its rows go to every pair of parts of theirs."""
    parts = F.ceil(F.col("__n") / limit).cast("int")
    rows = rows.join(sizes.select(key, F.col("n").alias("__n")), key)
    rows = rows.withColumn("__parts", parts).withColumn("part", F.pmod(F.xxhash64("source", "pid"), F.col("__parts")).cast("int"))
    others = F.transform(F.sequence(F.lit(0), F.col("__parts") - 1), lambda o: F.struct(F.least(o, F.col("part")).alias("a"), F.greatest(o, F.col("part")).alias("b")))
    return rows.withColumn("__cell", F.explode(others)).select("*", F.col("__cell.a").alias("a"), F.col("__cell.b").alias("b")).drop("__cell", "__n", "__parts")


def meet(rows: DataFrame, key: str, linkage: bool, carried: list[str], shared: list[str], cells: bool = False) -> DataFrame:
    """(l, r, carried columns as <c>_l and <c>_r, shared columns of the key) of rows (key, source, pid, ...) with equal keys."""
    left = rows.where("source = 'L'") if linkage else rows
    right = rows.where("source = 'R'") if linkage else rows
    on = [key, *(("a", "b") if cells else ())]
    part = ["part"] if cells else []
    left = left.select(*on, *shared, F.col("pid").alias("l"), *[F.col(c).alias(f"{c}_l") for c in [*carried, *part]])
    right = right.select(*on, F.col("pid").alias("r"), *[F.col(c).alias(f"{c}_r") for c in [*carried, *part]])
    joined = left.join(right, on)
    if not linkage:
        joined = joined.where("l < r")
    if cells:  # parts a and b meet in the cell (a, b) only, a part with itself in (a, a)
        joined = joined.where("least(part_l, part_r) = a and greatest(part_l, part_r) = b")
    return joined.select("l", "r", *shared, *[f"{c}_{s}" for c in carried for s in "lr"])


def meet_evenly(rows: DataFrame, key: str, sizes: DataFrame, linkage: bool, carried: list[str], shared: list[str], limit: int = KEY_ROWS) -> DataFrame:
    """meet, with keys of over `limit` rows cut into cells. sizes: (key, n); only such keys make the cut necessary."""
    hot = sizes.where(F.col("n") > limit).limit(1).count() > 0
    return meet(with_cells(rows.drop("n"), key, sizes, limit) if hot else rows, key, linkage, carried, shared, cells=hot)
