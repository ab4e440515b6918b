"""Word and shingle columns made of built-in expressions only.

Each step is a projection of its own: an array that several later expressions use is computed once, because the
optimizer does not inline an expensive expression that is referenced more than once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from progmatch.llm.common import SHINGLE_WORDS, SPACE


def words(text: Column) -> Column:
    """The words of a text; null and blank texts have none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE), lambda w: w != "")


def with_word_hashes(df: DataFrame, text: str, out: str) -> DataFrame:
    return df.withColumn(out, F.transform(words(F.col(text)), lambda w: F.xxhash64(w)))


def with_shingle_hashes(df: DataFrame, hashes: str, out: str, size: int = SHINGLE_WORDS) -> DataFrame:
    """A hash for each run of `size` words, in text order; empty where there are fewer words."""
    at = F.col(hashes)
    runs = F.transform(F.sequence(F.lit(0), F.size(at) - size), lambda i: F.xxhash64(*[F.get(at, i + k) for k in range(size)]))
    return df.withColumn(out, F.when(F.size(at) >= size, runs).otherwise(F.array().cast("array<bigint>")))
