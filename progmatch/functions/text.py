"""Tokenizers as column work on whole tables, and the same as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD_BREAK = r"[^\p{L}\p{N}]+"
TOKENIZERS = {"word1": ("word", 1), "word2": ("word", 2), "word3": ("word", 3), "char3": ("char", 3), "char4": ("char", 4), "char5": ("char", 5)}


def words(text: Column) -> Column:
    """Runs of letters and digits in lower case; null has none."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), WORD_BREAK), lambda w: w != "")


def normalised(text: Column) -> Column:
    """Lower case, everything but letters and digits as single spaces."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), WORD_BREAK, " "))


def with_grams(df: DataFrame, tokenizer: str, text: str = "text", out: str = "grams") -> DataFrame:
    """Adds the array of a text's grams, repeats included; a text shorter than a gram is one gram, an empty one has none."""
    if tokenizer not in TOKENIZERS:
        raise ValueError(f"unknown tokenizer: {tokenizer}")
    kind, n = TOKENIZERS[tokenizer]
    parts = words(F.col(text)) if kind == "word" else F.split(normalised(F.col(text)), "")
    if (kind, n) == ("word", 1):
        return df.withColumn(out, parts)
    return df.withColumn(out, _runs(F.filter(parts, lambda p: p != ""), n, " " if kind == "word" else ""))


def _runs(parts: Column, n: int, between: str) -> Column:
    """Joined runs of n parts. The parts are a lambda's variable: as a plain expression they would be made anew for each run."""

    def of(p: Column) -> Column:
        runs = F.transform(F.sequence(F.lit(0), F.size(p) - n), lambda i: F.concat_ws(between, *[F.get(p, i + k) for k in range(n)]))
        return F.when(F.size(p) >= n, runs).when(F.size(p) > 0, F.array(F.array_join(p, between))).otherwise(F.array().cast("array<string>"))

    return F.get(F.transform(F.array(parts), of), 0)


def register_sql(spark: SparkSession) -> None:
    """SQL functions word_ngrams(s, n), char_ngrams(s, n), sim_cosine(a, b), sim_euclid(a, b)."""
    ws = r"filter(split(lower(coalesce(s, '')), '[^\\p{L}\\p{N}]+'), w -> w <> '')"
    chars = r"filter(split(trim(regexp_replace(lower(coalesce(s, '')), '[^\\p{L}\\p{N}]+', ' ')), ''), c -> c <> '')"

    def runs(parts: str, between: str) -> str:  # the parts are a lambda's variable: made once for each text
        some = f"transform(sequence(0, size(p) - n), i -> array_join(slice(p, i + 1, n), '{between}'))"
        return f"get(transform(array({parts}), p -> CASE WHEN size(p) >= n THEN {some} WHEN size(p) > 0 THEN array(array_join(p, '{between}')) ELSE CAST(array() AS ARRAY<STRING>) END), 0)"

    dot = "aggregate(zip_with(%s, %s, (x, y) -> cast(x as double) * cast(y as double)), cast(0 as double), (t, v) -> t + v)"
    for sql in (
        f"word_ngrams(s STRING, n INT) RETURNS ARRAY<STRING> RETURN {runs(ws, ' ')}",
        f"char_ngrams(s STRING, n INT) RETURNS ARRAY<STRING> RETURN {runs(chars, '')}",
        f"sim_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN coalesce(try_divide({dot % ('a', 'b')}, sqrt({dot % ('a', 'a')}) * sqrt({dot % ('b', 'b')})), 0)",
        "sim_euclid(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 / (1 + sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), cast(0 as double), (t, v) -> t + v)))",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {sql}")
