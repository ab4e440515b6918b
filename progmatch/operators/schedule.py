"""Schedulers: the order in which weighted pairs are compared, cut at a budget.

A node's score is the mean weight of its edges; its rank is by score descending, then id. An edge's place in a node's list
is by weight descending, then the other id. In dedup an edge takes its least key over both ends; in linkage only the nodes
of the anchor side count.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.operators.order import positioned

SCHEDULERS = ("edge", "depth", "breadth", "hybrid")


def _ends(edges: DataFrame, linkage: bool, anchor: str) -> DataFrame:
    """(node, other, l, r, w)"""
    if anchor not in ("left", "right"):
        raise ValueError(f"unknown anchor: {anchor}")
    if linkage:
        node, other = ("l", "r") if anchor == "left" else ("r", "l")
        return edges.select(F.col(node).alias("node"), F.col(other).alias("other"), "l", "r", "w")
    both = F.array(F.struct(F.col("l").alias("node"), F.col("r").alias("other")), F.struct(F.col("r").alias("node"), F.col("l").alias("other")))
    return edges.select(F.explode(both).alias("e"), "l", "r", "w").select("e.*", "l", "r", "w")


def node_score(mean: Column) -> Column:
    """The negative mean weight to nine places, rounded as doubles are: scaled, to the nearest whole, back. Means of two
    weights of nine places often lie half-way, where rounding their decimal text gives another order than the SQL has."""
    return -(F.round(mean * 1e9, 0) / 1e9)


def _placed(edges: DataFrame, linkage: bool, anchor: str, nodes_limit: int | None = None, rounds: int | None = None) -> DataFrame:
    """Ends with s (negative node score) and t (place in the node's list)."""
    ends = _ends(edges, linkage, anchor)
    scores = ends.groupBy("node").agg(node_score(F.avg("w")).alias("s"))
    if nodes_limit is not None:
        scores = scores.orderBy("s", "node").limit(nodes_limit)
    ends = ends.withColumn("t", F.row_number().over(Window.partitionBy("node").orderBy(F.desc("w"), "other")))
    if rounds is not None:
        ends = ends.where(F.col("t") <= rounds)
    return ends.join(scores, "node")


def _rounds(edges: DataFrame, linkage: bool, anchor: str, budget: int) -> int:
    """So many rounds hold 2 * budget ends: the driver sees a row for each degree."""
    degrees = _ends(edges, linkage, anchor).groupBy("node").count().groupBy("count").agg(F.count(F.lit(1)).alias("n"))
    rows = sorted((r["count"], r["n"]) for r in degrees.collect())
    held, before, nodes = 0, 0, sum(n for _, n in rows)
    for degree, n in rows:
        gain = (degree - before) * nodes
        if held + gain >= 2 * budget:
            return before + -(-(2 * budget - held) // nodes)
        held, before, nodes = held + gain, degree, nodes - n
    return before


def schedule(edges: DataFrame, kind: str, budget: int, linkage: bool = False, anchor: str = "left", prune: bool = True) -> DataFrame:
    """(pos, l, r, w): the first `budget` pairs in the scheduler's order. With prune, nodes or rounds beyond the budget are left out before ranking."""
    if kind not in SCHEDULERS:
        raise ValueError(f"unknown scheduler: {kind}")
    if budget < 0:
        raise ValueError(f"negative budget: {budget}")
    edges = edges.select("l", "r", F.round("w", 9).alias("w"))
    if kind == "edge":
        keyed, keys = edges.withColumn("k1", -F.col("w")), ["k1", "l", "r"]
    elif kind == "depth":
        # every node before the budget has all its edges in it, and those have at most 2 * budget ends
        placed = _placed(edges, linkage, anchor, 2 * budget if prune and budget <= 100_000 else None)
        keyed, keys = _least(placed, F.struct("s", "node", "t")), ["k.s", "k.node", "k.t"]
    elif kind == "breadth":
        placed = _placed(edges, linkage, anchor, rounds=_rounds(edges, linkage, anchor, budget) if prune else None)
        keyed, keys = _least(placed, F.struct("t", "s", "node")), ["k.t", "k.s", "k.node"]
    else:
        placed = _placed(edges, linkage, anchor)
        both = placed.groupBy("l", "r").agg(F.first("w").alias("w"), F.min("t").alias("best"), F.min(F.struct("s", "node", "t")).alias("k"))
        first = F.col("best") == 1
        keyed = both.select("l", "r", "w", F.when(first, 1).otherwise(2).alias("p"), F.when(first, -F.col("w")).otherwise(F.col("k.s")).alias("k1"), F.when(first, F.col("l")).otherwise(F.col("k.node")).alias("k2"), F.when(first, F.col("r")).otherwise(F.col("k.t").cast("long")).alias("k3"))
        keys = ["p", "k1", "k2", "k3"]
    flat = keyed.select("l", "r", "w", *[F.col(k).alias(f"o{i}") for i, k in enumerate(keys)])
    return positioned(flat, [*[f"o{i}" for i in range(len(keys))], "l", "r"], limit=budget).select("pos", "l", "r", "w")


def _least(placed: DataFrame, key) -> DataFrame:
    return placed.groupBy("l", "r").agg(F.first("w").alias("w"), F.min(key).alias("k"))


def schedule_ideal(edges: DataFrame, truth: DataFrame, budget: int) -> DataFrame:
    """True pairs first."""
    marked = edges.join(truth.select("l", "r").withColumn("hit", F.lit(0)), ["l", "r"], "left").withColumn("o", F.coalesce("hit", F.lit(1)))
    return positioned(marked.select("l", "r", "w", "o"), ["o", "l", "r"], limit=budget).select("pos", "l", "r", "w")


def schedule_batch(edges: DataFrame, budget: int, by: str = "id", seed: int = 0) -> DataFrame:
    """No priorities: by id or by a repeatable random order."""
    key = F.md5(F.concat_ws("|", F.col("l").cast("string"), F.col("r").cast("string"), F.lit(str(seed)))) if by == "hash" else F.lit("")
    return positioned(edges.select("l", "r", "w", key.alias("o")), ["o", "l", "r"], limit=budget).select("pos", "l", "r", "w")
