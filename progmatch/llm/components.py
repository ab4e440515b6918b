"""Connected components of links between string keys, by rounds of joins over settled tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from progmatch.llm.common import discard, settle


def components(links: DataFrame) -> DataFrame:
    """links: (a, b); returns (node, root), root being the least key of the node's component; only linked nodes have rows.

    Every round links each node's larger neighbours, then its smaller ones, to the least key in sight, until nothing moves.
    Minimums are aggregated before they are shuffled, and no node's neighbours are ever gathered, so a node with very many
    links is no hot spot beyond its rows.
    """
    now = settle(links.where("a <> b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct(), "links")
    seen = _digest(now)
    while True:
        both = now.select(F.col("v").alias("x"), F.col("u").alias("y")).union(now.select(F.col("u").alias("x"), F.col("v").alias("y")))
        least = both.groupBy("x").agg(F.least(F.min("y"), F.first("x")).alias("m"))
        large = both.where("y > x").join(least, "x").select(F.col("y").alias("v"), F.col("m").alias("u")).where("v <> u").distinct()
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        joined = large.join(low, "v")
        small = joined.select(F.col("v"), F.col("m").alias("u")).union(joined.where("u <> m").select(F.col("u").alias("v"), F.col("m").alias("u"))).distinct()
        after = settle(small, "links")
        discard(now)
        before, now, seen = seen, after, _digest(after)
        if seen == before:
            return now.select(F.col("v").alias("node"), F.col("u").alias("root"))


def _digest(links: DataFrame) -> tuple:
    """Number and two 64-bit digests of distinct links, whatever their order: a table that has not moved has the same."""
    return tuple(links.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("v", "u")), F.bit_xor(F.xxhash64("u", "v", F.lit(1)))).first())
