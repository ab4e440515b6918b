"""Baselines: BM25 top-k, self-supervised re-weighted vectors, block by block, profile- and window-progressive."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.operators import postings
from progmatch.operators.blocking import block_graph, refined
from progmatch.operators.dense import dense_candidates
from progmatch.operators.encoders import encode
from progmatch.operators.order import positioned
from progmatch.operators.pairs import meet_evenly
from progmatch.operators.schedule import schedule
from progmatch.operators.sortedlist import sorted_candidates
from progmatch.operators.sparse import doc_freq, encode_grams, nearest, term_counts
from progmatch.session import release, settle
from progmatch.sources.profiles import Task


def baseline_bm25(task: Task, k: int = 5, index: str = "largest", tokenizer: str = "char3", k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """(l, r, w): each query's k best by BM25 of the grams it shares. In dedup every profile queries all others.

    Packed blocks of profiles meet each other, as nearly every pair shares a gram; with too many grams for that, postings are joined.
    """
    packed = postings.packed_postings(task, tokenizer, "bm25", k1=k1, b=b)
    if packed is None:
        return _joined_bm25(task, k, index, tokenizer, k1, b)
    release(packed.sparkSession)
    sizes = task.sizes()
    small = 0 if sizes.get("L", 0) <= sizes.get("R", 0) else 1
    sides = {"both": (0, 1), "largest": (small,), "smallest": (1 - small,)}[index] if task.linkage else (0,)
    left, right = (packed.where(F.col("source") == s) if task.linkage else packed for s in "LR")
    return postings.edges_of_side(postings.nearest_cosine(left, right, k, not task.linkage, sides, True), task.linkage, index, sizes)


def _joined_bm25(task: Task, k: int, index: str, tokenizer: str, k1: float, b: float) -> DataFrame:
    counts = encode_grams(term_counts(task, tokenizer))
    lengths = counts.groupBy("source", "pid").agg(F.sum("cnt").alias("len"))
    stats = lengths.agg(F.avg("len").alias("avg"), F.count(F.lit(1)).alias("n")).first()
    n, avg = float(stats["n"]), float(stats["avg"] or 1)
    idf = F.ln(1 + (n - F.col("df") + 0.5) / (F.col("df") + 0.5))
    tf = F.col("cnt") * (k1 + 1) / (F.col("cnt") + k1 * (1 - b + b * F.col("len") / avg))
    sizes = doc_freq(counts)
    rows = counts.join(sizes, "gram").join(lengths, ["source", "pid"]).select("gram", "source", "pid", (idf * tf).alias("s"))
    met = meet_evenly(rows, "gram", sizes.withColumnRenamed("df", "n"), task.linkage, ["s"], [])
    sums = met.groupBy("l", "r").agg(F.round(F.sum("s_r"), 9).alias("as_query_l"), F.round(F.sum("s_l"), 9).alias("as_query_r"))
    if not task.linkage:
        ends = sums.select(F.explode(F.array(F.struct(F.col("l").alias("q"), F.col("r").alias("i"), F.col("as_query_l").alias("w")), F.struct(F.col("r").alias("q"), F.col("l").alias("i"), F.col("as_query_r").alias("w")))).alias("e")).select("e.*")
        best = ends.withColumn("t", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("w"), "i"))).where(F.col("t") <= k)
        return best.groupBy(F.least("q", "i").alias("l"), F.greatest("q", "i").alias("r")).agg(F.max("w").alias("w"))
    sizes = task.sizes()
    small_is_left = sizes.get("L", 0) <= sizes.get("R", 0)
    found = None
    for side, use in (("l", index == "both" or (index == "largest") == small_is_left), ("r", index == "both" or (index == "smallest") == small_is_left)):
        if use:
            part = sums.select("l", "r", F.col(f"as_query_{side}").alias("w"))
            best = nearest(part, k, True, "largest" if (side == "l") == small_is_left else "smallest", sizes)
            found = best if found is None else found.union(best)
    return found.groupBy("l", "r").agg(F.max("w").alias("w"))


#: Profiles of the first pairs are sent to every task up to so many.
BROADCAST_ROWS = 500_000


def _first_pairs(blocks: DataFrame, stats: DataFrame, linkage: bool, budget: int) -> DataFrame:
    """Settled (l, r): all pairs of the smallest blocks, of so many blocks that there are `budget` different ones, or of all blocks."""
    n_blocks, wanted = stats.count(), max(1, budget)
    while True:
        # a block has a pair at least: the first `wanted` blocks hold the first `wanted` pairs, repeats counted
        heads = stats.select("bkey", "n", "card").orderBy("card", "bkey").limit(wanted)
        before = F.sum("card").over(Window.orderBy("card", "bkey")) - F.col("card")
        heads = settle(heads.withColumn("before", before).where(F.col("before") < wanted).drop("before"), "heads")
        rows = blocks.select("bkey", "source", "pid").join(heads.select("bkey"), "bkey", "left_semi")
        pairs = settle(meet_evenly(rows, "bkey", heads.select("bkey", "n"), linkage, [], []).distinct(), "first-pairs")
        if pairs.count() >= budget or heads.count() >= n_blocks:
            return pairs
        wanted *= 4


def baseline_block_progressive(task: Task, budget: int, purge: str = "size", ratio: float | None = 0.8) -> DataFrame:
    """(pos, l, r, w): blocks from the smallest on; a pair belongs to its first block; inside a block by CN-CB.

    Pairs of the smallest blocks only are made, as many as the budget needs; each then gets its weight from all the blocks it has.
    """
    blocks, stats = refined(task, purge, ratio)
    pairs = _first_pairs(blocks, stats, task.linkage, budget)
    ends = F.array(*[F.struct(F.lit(s.upper() if task.linkage else None).cast("string").alias("source"), F.col(s).alias("pid")) for s in "lr"])
    own = pairs.select(F.explode(ends).alias("e")).select("e.*").distinct()
    own = own if task.linkage else own.drop("source")
    few = own.count() <= BROADCAST_ROWS
    rows = settle(blocks.join(F.broadcast(own) if few else own, own.columns, "left_semi").select("bkey", "source", "pid", "card"), "rows")
    left, right = (rows.where(F.col("source") == s) if task.linkage else rows for s in "LR")
    shared = pairs.join(left.select("bkey", "card", F.col("pid").alias("l")), "l").join(right.select("bkey", F.col("pid").alias("r")), ["r", "bkey"])
    first = shared.groupBy("l", "r").agg(F.min(F.struct("card", "bkey")).alias("k"), F.round(F.sum(1 / F.col("card")), 9).alias("w"))
    flat = first.select("l", "r", "w", F.col("k.card").alias("c"), F.col("k.bkey").alias("b"), (-F.col("w")).alias("o"))
    return positioned(flat, ["c", "b", "o", "l", "r"], limit=budget).select("pos", "l", "r", "w")


def baseline_profile_progressive(task: Task, budget: int, **options) -> DataFrame:
    """The earlier scheduler on blocks: hybrid over CN-CB."""
    blocks, stats = refined(task, **options)
    edges = block_graph(blocks, stats, task.linkage).select("l", "r", F.round("cn", 9).alias("w"))
    return schedule(edges, "hybrid", budget, task.linkage)


def baseline_window_progressive(task: Task, budget: int, scope: str = "global", window: int = 10) -> DataFrame:
    """The earlier variant on the sorted list: normalised counts, best first."""
    return schedule(sorted_candidates(task, "ncf", window, scope), "edge", budget, task.linkage)


def self_supervised_vectors(task: Task, encoder: str = "hash-words", dims: int = 128, seed: int = 1, sample_rows: int = 4_000) -> DataFrame:
    """(source, pid, vec): stand-in vectors re-weighted by what a sample, labelled automatically, teaches.

    Positives are a vector and itself with a part of its places dropped, negatives two random vectors; a logistic model of
    the absolute differences gives each place a weight. The sample is bounded by sample_rows.
    """
    vectors = encode(task, encoder, dims)
    n = max(1, task.profiles.count())
    draw = F.xxhash64("source", "pid", F.lit(seed))
    picked = vectors.where(F.pmod(draw, F.lit(1_000_000)) < int(min(1.0, sample_rows / n) * 1_000_000) + 1).orderBy(draw, "source", "pid").limit(2 * sample_rows)
    x = np.array([r["vec"] for r in picked.select("vec").collect()], dtype=np.float64)
    if len(x) < 4:
        return vectors
    rng = np.random.default_rng(seed)
    copies = x * (rng.random(x.shape) > 0.2)
    copies /= np.maximum(np.linalg.norm(copies, axis=1, keepdims=True), 1e-12)
    d = np.abs(np.concatenate((x - copies, x - x[rng.permutation(len(x))])))
    y = np.concatenate((np.ones(len(x)), np.zeros(len(x))))
    w, bias = np.zeros(x.shape[1]), 0.0
    for _ in range(300):
        p = 1 / (1 + np.exp(-np.clip(d @ w + bias, -30, 30)))
        w -= 2.0 * (d.T @ (p - y) / len(y) + 1e-3 * w)
        bias -= 2.0 * (p - y).mean()
    weight = np.sqrt(np.maximum(-w, 0) + 0.05)
    weight /= weight.mean()
    scale = F.array(*[F.lit(float(v)) for v in weight])
    return vectors.withColumn("vec", F.zip_with("vec", scale, lambda a, b: a * b))


def baseline_sse(task: Task, k: int = 5, index: str = "smallest", encoder: str = "hash-words", dims: int = 128, seed: int = 1) -> DataFrame:
    """(l, r, w): cosine neighbours of self-supervised vectors; an approximation, as no deep model is at hand. Average several seeds."""
    return dense_candidates(self_supervised_vectors(task, encoder, dims, seed), task.kind, "cosine", k, index)
