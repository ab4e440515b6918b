"""Sorted-list family: profiles in the order of their tokens, pairs inside a sliding window, and their weights."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.functions.text import words
from progmatch.operators.order import positioned
from progmatch.sources.profiles import Task

SORTED_WEIGHTS = ("acf", "ncf", "dncf", "cncf", "id")
SCOPES = ("local", "global")
#: Weights that are sums over the position pairs, without any number of the profiles.
PLAIN_WEIGHTS = ("acf", "id")
BUCKET_ROWS = 50_000


def sorted_list(task: Task, seed: int = 0, ranges: int | None = None) -> DataFrame:
    """(pos, token, source, pid), pos from 1: tokens ascending, profiles of one token in a repeatable random order."""
    rows = task.profiles.select(F.explode(F.array_distinct(words(F.col("text")))).alias("token"), "source", "pid")
    tie = F.md5(F.concat("token", F.lit("|"), "source", F.lit(":"), F.col("pid").cast("string"), F.lit(f"|{seed}")))
    return positioned(rows.withColumn("tie", tie), ["token", "tie"], ranges=ranges).select("pos", "token", "source", "pid")


def window_pairs(listed: DataFrame, window: int, linkage: bool, strict: bool = False, bucket: int = BUCKET_ROWS) -> DataFrame:
    """(l, r, d): positions at most `window` apart (strict: less) of different profiles, from both sources in linkage.

    Positions are dealt in buckets; each bucket also gets the first `window` positions of the next, and a pair belongs to the
    bucket of its lower position, so no window is cut and none is seen twice.
    """
    if window < 1:
        raise ValueError(f"window must be 1 or more: {window}")
    reach = window - 1 if strict else window
    at = F.floor((F.col("pos") - 1) / bucket)
    edge = F.pmod(F.col("pos") - 1, F.lit(bucket)) < reach
    rows = listed.select("pos", "source", "pid", F.explode(F.when(edge & (at > 0), F.array(at, at - 1)).otherwise(F.array(at))).alias("b"), at.alias("own"))
    order = Window.partitionBy("b").orderBy("pos")
    # one frame for each distance: a profile is its id, and in linkage its side as the lowest bit
    left = F.col("source") == "L"
    rows = rows.withColumn("key", 2 * F.col("pid") + F.when(left, 0).otherwise(1) if linkage else F.col("pid"))
    ahead = {f"__{d}": F.lead("key", d).over(order) for d in range(1, reach + 1)}
    seen = rows.withColumns(ahead).where("b = own")
    nexts = F.array(*[F.struct(F.lit(d).alias("d"), F.col(f"__{d}").alias("key")) for d in range(1, reach + 1)]) if reach else F.array().cast("array<struct<d:int,key:bigint>>")
    pairs = seen.select("key", F.explode(nexts).alias("n")).select("key", F.col("n.d").alias("d"), F.col("n.key").alias("next")).where(F.col("next").isNotNull())
    if linkage:
        first = F.col("key").bitwiseAND(1) == 0
        pairs = pairs.where(F.col("key").bitwiseAND(1) != F.col("next").bitwiseAND(1))
        return pairs.select(F.shiftright(F.when(first, F.col("key")).otherwise(F.col("next")), 1).alias("l"), F.shiftright(F.when(first, F.col("next")).otherwise(F.col("key")), 1).alias("r"), "d")
    return pairs.where(F.col("key") != F.col("next")).select(F.least("key", "next").alias("l"), F.greatest("key", "next").alias("r"), "d")


def pair_histogram(pairs: DataFrame, window: int) -> DataFrame:
    """(l, r, h): h[d-1] position pairs at distance d. One shuffle that serves every weight, scope and smaller window."""
    sums = [F.sum((F.col("d") == d).cast("long")) for d in range(1, window + 1)]
    return pairs.groupBy("l", "r").agg(F.array(*sums).alias("h"))


def histogram_of(listed: DataFrame, window: int, linkage: bool) -> DataFrame:
    return pair_histogram(window_pairs(listed, window, linkage), window)


def plain_weights(listed: DataFrame, weight: str, scope: str, window: int, linkage: bool, strict: bool = False) -> DataFrame:
    """(l, r, w) of a weight in PLAIN_WEIGHTS: added up at once, without a histogram."""
    reach = window - 1 if strict else window
    pairs = window_pairs(listed, window, linkage, strict)
    share = F.lit(1.0) if weight == "acf" else 1 / F.col("d")
    times = reach + 1 - F.col("d") if scope == "global" else F.lit(1)
    return pairs.groupBy("l", "r").agg(F.round(F.sum(share * times), 9).alias("w"))


def list_nodes(listed: DataFrame) -> DataFrame:
    """(source, pid, p): positions of each profile."""
    return listed.groupBy("source", "pid").agg(F.count(F.lit(1)).alias("p"))


def with_positions(histogram: DataFrame, nodes: DataFrame, linkage: bool) -> DataFrame:
    for side in "lr":
        own = nodes.where(F.col("source") == side.upper()) if linkage else nodes
        histogram = histogram.join(own.select(F.col("pid").alias(side), F.col("p").alias(f"p_{side}")), side)
    return histogram


def sorted_weight(weight: str, scope: str, window: int) -> Column:
    """The weight from h, p_l and p_r. Global scope adds up the windows from 1: in closed form where the weight is linear in h."""
    if weight not in SORTED_WEIGHTS or scope not in SCOPES:
        raise ValueError(f"unknown weight or scope: {weight}, {scope}")
    h = [F.get("h", F.lit(d - 1)).cast("double") for d in range(1, window + 1)]
    times = [window - d + 1 if scope == "global" else 1 for d in range(1, window + 1)]
    if weight == "acf":
        return sum((x * t for x, t in zip(h[1:], times[1:], strict=True)), h[0] * times[0])
    if weight == "id":
        return sum((x * t / d for d, (x, t) in enumerate(zip(h[1:], times[1:], strict=True), 2)), h[0] * times[0])
    p, q = F.col("p_l").cast("double"), F.col("p_r").cast("double")

    def norm(acf: Column) -> Column:
        if weight == "dncf":
            return 2 * acf / (p + q)
        if weight == "cncf":
            return acf / F.sqrt(p * q)
        below = p + q - acf  # can vanish or be negative where both profiles' positions lie side by side
        return F.when(below > 0, F.try_divide(acf, below)).otherwise(acf)

    upto = [h[0]]
    for x in h[1:]:
        upto.append(upto[-1] + x)
    return sum((norm(a) for a in upto[1:]), norm(upto[0])) if scope == "global" else norm(upto[-1])


def sorted_candidates(task: Task, weight: str = "id", window: int = 10, scope: str = "global", strict: bool = False, seed: int = 0) -> DataFrame:
    """(l, r, w) edges."""
    listed = sorted_list(task, seed)
    reach = window - 1 if strict else window
    if weight in PLAIN_WEIGHTS and scope in SCOPES:
        return plain_weights(listed, weight, scope, window, task.linkage, strict).where("w > 0")
    found = with_positions(histogram_of(listed, reach, task.linkage), list_nodes(listed), task.linkage)
    return found.select("l", "r", F.round(sorted_weight(weight, scope, reach), 9).alias("w")).where("w > 0")


def sorted_grid(task: Task, window: int = 10, seed: int = 0) -> DataFrame:
    """(l, r, a column <weight>_<scope>_<w> for each of the 100 configurations) from one shuffle of pairs."""
    listed = sorted_list(task, seed)
    found = with_positions(pair_histogram(window_pairs(listed, window, task.linkage), window), list_nodes(listed), task.linkage)
    return found.select("l", "r", *[F.round(sorted_weight(x, s, w), 9).alias(f"{x}_{s}_{w}") for x in SORTED_WEIGHTS for s in SCOPES for w in range(1, window + 1)])
