"""The Python side of the function surface: table functions and Arrow functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udf, udtf
from pyspark.sql.types import DoubleType


@udtf(returnType="gram string")
class CharGrams:
    """One row for each run of n characters of a text."""

    def eval(self, text: str, n: int):
        if text:
            for i in range(max(1, len(text) - n + 1)):
                yield (text[i : i + n],)


@udtf(returnType="first bigint, second bigint, distance int")
class WindowPairs:
    """Pairs of different ids at most w places apart in an array."""

    def eval(self, ids: list, w: int):
        for i, a in enumerate(ids or []):
            for d in range(1, w + 1):
                if i + d < len(ids) and ids[i + d] != a:
                    yield min(a, ids[i + d]), max(a, ids[i + d]), d


@udf(returnType=DoubleType())
def overlap_ratio(a, b):
    """Row at a time: shared distinct tokens over all; the slow form, for small inputs."""
    x, y = set(a or []), set(b or [])
    return len(x & y) / len(x | y) if x | y else 0.0


@pandas_udf(DoubleType())
def length_ratio(a: pd.Series, b: pd.Series) -> pd.Series:
    """Shorter length over longer, batch at a time."""
    x, y = a.fillna("").str.len(), b.fillna("").str.len()
    top = pd.concat([x, y], axis=1).max(axis=1)
    return (pd.concat([x, y], axis=1).min(axis=1) / top.where(top > 0, 1)).astype("float64")


@pandas_udf(DoubleType())
def mean_weight(w: pd.Series) -> float:
    """An aggregate of one group's batch."""
    return float(w.mean()) if len(w) else 0.0


def register(spark: SparkSession) -> None:
    spark.udtf.register("char_grams", CharGrams)
    spark.udtf.register("window_pairs", WindowPairs)
    spark.udf.register("overlap_ratio", overlap_ratio)
    spark.udf.register("length_ratio", length_ratio)
