"""Block-graph family: token blocks, purging, filtering, and the graph of co-blocked profiles with its statistics."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.functions.text import words
from progmatch.operators.pairs import KEY_ROWS, meet_evenly
from progmatch.session import drop, release, settle
from progmatch.sources.profiles import Task


def token_blocks(task: Task, block_fn: Callable[[Column], Column] | None = None) -> DataFrame:
    """(bkey, source, pid): a block for each distinct token; block_fn gives other keys of a text."""
    keys = (block_fn or (lambda t: words(t)))(F.col("text"))
    return task.profiles.select(F.explode(F.array_distinct(keys)).alias("bkey"), "source", "pid")


def block_stats(blocks: DataFrame, linkage: bool) -> DataFrame:
    """(bkey, n, card): profiles and pairs of each block that has pairs."""
    if linkage:
        left, right = (F.sum((F.col("source") == s).cast("long")) for s in "LR")
        stats = blocks.groupBy("bkey").agg(left.alias("nl"), right.alias("nr")).select("bkey", (F.col("nl") + F.col("nr")).alias("n"), (F.col("nl") * F.col("nr")).alias("card"))
    else:
        n = F.col("n")
        stats = blocks.groupBy("bkey").agg(F.count(F.lit(1)).alias("n")).select("bkey", "n", ((n * (n - 1)) / 2).cast("long").alias("card"))
    return stats.where("card > 0")


def purge_limit(stats: DataFrame, factor: float = 1.025) -> int | None:
    """Adaptive purging: the largest cardinality to keep, or None for all. Cardinalities, a row for each, are ordered in one task."""
    levels = stats.groupBy("card").agg(F.sum("n").alias("a"), (F.count(F.lit(1)) * F.col("card")).alias("k"))
    order = Window.orderBy("card")
    sums = levels.select("card", *[F.sum(c).over(order).cast("double").alias(c) for c in ("a", "k")])
    behind = sums.withColumns({f"{c}0": F.lag(c).over(order) for c in ("a", "k")})
    return behind.where(F.col("a0") * F.col("k") < factor * F.col("a") * F.col("k0")).agg(F.max("card")).first()[0]


def purge_blocks(blocks: DataFrame, stats: DataFrame, mode: str = "size", records: int | None = None, max_card: int | None = None) -> DataFrame:
    """Statistics of the blocks that stay. size: at most half the records; adaptive: by the ratio of profiles to pairs; max_card; none."""
    if mode == "none":
        return stats
    if mode == "size":
        if records is None:
            raise ValueError("size purging needs the number of records")
        return stats.where(2 * F.col("n") <= records)
    if mode == "adaptive":
        cut = purge_limit(stats)
        return stats if cut is None else stats.where(F.col("card") <= cut)
    if mode == "max_card":
        return stats.where(F.col("card") <= max_card)
    raise ValueError(f"unknown purging: {mode}")


def filter_blocks(blocks: DataFrame, stats: DataFrame, ratio: float = 0.8) -> DataFrame:
    """Each profile stays in the ceil(ratio * blocks) smallest of its blocks."""
    if not 0 < ratio <= 1:
        raise ValueError(f"ratio must lie in (0, 1]: {ratio}")
    own = Window.partitionBy("source", "pid")
    ranked = blocks.join(stats.select("bkey", "card"), "bkey")
    ranked = ranked.withColumn("place", F.row_number().over(own.orderBy("card", "bkey"))).withColumn("m", F.count(F.lit(1)).over(own))
    return ranked.where(F.col("place") <= F.ceil(F.lit(ratio) * F.col("m"))).select("bkey", "source", "pid")


def refined(task: Task, purge: str = "size", ratio: float | None = 0.8, max_block_size: int | None = None, block_fn=None) -> tuple[DataFrame, DataFrame]:
    """(blocks, stats) after purging and filtering; blocks carry n and card. The tokens are settled, as each step reads them, and
    so is what is kept, behind which tokens and shuffle files go."""
    blocks = settle(token_blocks(task, block_fn), "tokens")
    records = task.profiles.count() if purge == "size" else None
    stats = settle(purge_blocks(blocks, block_stats(blocks, task.linkage), purge, records), "stats")
    if max_block_size:
        stats = stats.where(F.col("n") <= max_block_size)
    kept = settle(filter_blocks(blocks, stats, ratio) if ratio else blocks.join(stats.select("bkey"), "bkey", "left_semi"), "kept")
    release(kept.sparkSession)
    drop(blocks)
    stats = settle(block_stats(kept, task.linkage), "stats")
    return kept.join(stats, "bkey"), stats


def block_graph(blocks: DataFrame, stats: DataFrame, linkage: bool, limit: int = KEY_ROWS) -> DataFrame:
    """(l, r, cb, sn, cn): one row for each pair that shares a block; sums are combined before they are shuffled."""
    number = lambda df: df.withColumn("bkey", F.xxhash64("bkey"))  # noqa: E731  what is joined are 64-bit ids of the keys
    rows = number(blocks).select("bkey", "source", "pid", (1 / F.col("n")).alias("sn"), (1 / F.col("card")).alias("cn"))
    met = meet_evenly(rows, "bkey", number(stats.select("bkey", "n")), linkage, [], ["sn", "cn"], limit)
    return met.groupBy("l", "r").agg(F.count(F.lit(1)).alias("cb"), F.sum("sn").alias("sn"), F.sum("cn").alias("cn"))


def block_nodes(blocks: DataFrame) -> DataFrame:
    """(source, pid, nb, snb, cnb): blocks of each profile and their normalised sums."""
    return blocks.groupBy("source", "pid").agg(F.count(F.lit(1)).alias("nb"), F.sum(1 / F.col("n")).alias("snb"), F.sum(1 / F.col("card")).alias("cnb"))


BLOCK_WEIGHTS = ("cb", "cosine", "dice", "jaccard", "sn_cb", "sn_cosine", "sn_dice", "sn_jaccard", "cn_cb", "cn_cosine", "cn_dice", "cn_jaccard", "ecb", "ejs")


def block_grid(graph: DataFrame, blocks: DataFrame, stats: DataFrame, linkage: bool, weights: tuple[str, ...] = BLOCK_WEIGHTS) -> DataFrame:
    """(l, r, a column for each weight): all weights from one pass over the pairs; statistics that no weight needs aren't joined."""
    if unknown := set(weights) - set(BLOCK_WEIGHTS):
        raise ValueError(f"unknown weight: {sorted(unknown)}")
    if set(weights) - {"cb", "sn_cb", "cn_cb"}:
        nodes = block_nodes(blocks)
        for side in "lr":
            own = nodes.where(F.col("source") == side.upper()) if linkage else nodes
            graph = graph.join(own.select(F.col("pid").alias(side), *[F.col(c).alias(f"{c}_{side}") for c in ("nb", "snb", "cnb")]), side)
    if "ejs" in weights:
        ends = graph.select(F.explode(F.array(*[F.struct(F.lit(s).alias("side" if linkage else "side"), F.col(s).alias("pid")) for s in "lr"])).alias("e"))
        degree = ends.groupBy(F.col("e.side").alias("side") if linkage else F.lit("x").alias("side"), F.col("e.pid").alias("pid")).agg(F.count(F.lit(1)).alias("deg"))
        n_nodes = degree.count()
        for side in "lr":
            own = degree.where(F.col("side") == side) if linkage else degree
            graph = graph.join(own.select(F.col("pid").alias(side), F.col("deg").alias(f"deg_{side}")), side)
    n_blocks = stats.count() if "ecb" in weights else 0
    col = F.col

    def trio(shared: str, a: str, b: str) -> dict[str, Column]:
        s, x, y = col(shared), col(a), col(b)
        return {"cosine": s / F.sqrt(x * y), "dice": 2 * s / (x + y), "jaccard": F.try_divide(s.cast("double"), (x + y - s).cast("double"))}

    found = {"cb": col("cb").cast("double"), "sn_cb": col("sn"), "cn_cb": col("cn")}
    if "nb_l" in graph.columns:
        found |= trio("cb", "nb_l", "nb_r") | {f"sn_{k}": v for k, v in trio("sn", "snb_l", "snb_r").items()} | {f"cn_{k}": v for k, v in trio("cn", "cnb_l", "cnb_r").items()}
    if n_blocks:
        found["ecb"] = col("cb") * F.ln(F.lit(float(n_blocks)) / col("nb_l")) * F.ln(F.lit(float(n_blocks)) / col("nb_r"))
    if "ejs" in weights:
        found["ejs"] = found["jaccard"] * F.ln(F.lit(float(max(n_nodes, 1))) / col("deg_l")) * F.ln(F.lit(float(max(n_nodes, 1))) / col("deg_r"))
    return graph.select("l", "r", *[F.round(found[w], 9).alias(w) for w in weights])


def block_candidates(task: Task, weight: str = "cn_cb", purge: str = "size", ratio: float | None = 0.8, max_block_size: int | None = None, keep_nonpositive: bool = False) -> DataFrame:
    """(l, r, w) edges."""
    blocks, stats = refined(task, purge, ratio, max_block_size)
    edges = block_grid(block_graph(blocks, stats, task.linkage), blocks, stats, task.linkage, (weight,)).select("l", "r", F.col(weight).alias("w"))
    return edges if keep_nonpositive else edges.where("w > 0")
