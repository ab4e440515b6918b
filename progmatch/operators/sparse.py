"""Sparse-join family: n-gram vectors in long form, an inverted index as an equi-join, and the k nearest of each query."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.functions.text import with_grams
from progmatch.operators.pairs import KEY_ROWS, meet, with_cells
from progmatch.sources.profiles import Task

SCORINGS, SIMILARITIES, SIDES = ("bool", "tf", "tfidf"), ("cosine", "euclid"), ("smallest", "largest", "both")
SAME = 1e-12  # a squared distance of less, as a share of both squared norms, is the rounding of sums: equal vectors


def term_counts(task: Task, tokenizer: str) -> DataFrame:
    """(source, pid, gram, cnt)"""
    grams = with_grams(task.profiles, tokenizer).select("source", "pid", F.explode("grams").alias("gram"))
    return grams.groupBy("source", "pid", "gram").agg(F.count(F.lit(1)).alias("cnt"))


def encode_grams(counts: DataFrame) -> DataFrame:
    """The same rows with 64-bit ids for grams: what posting joins shuffle. Two of V grams share an id with odds of V^2 / 2^65."""
    return counts.withColumn("gram", F.xxhash64("gram"))


def doc_freq(counts: DataFrame) -> DataFrame:
    return counts.groupBy("gram").agg(F.count(F.lit(1)).alias("df"))


def scored(counts: DataFrame, n_records: int, scorings: tuple[str, ...] = SCORINGS, max_df: int | None = None, log_base: float | None = None) -> DataFrame:
    """(source, pid, gram, a column for each scoring): present; count over the profile's largest; that times ln(N / df).

    max_df drops grams of more profiles; the default drops none.
    """
    if unknown := set(scorings) - set(SCORINGS):
        raise ValueError(f"unknown scoring: {sorted(unknown)}")
    out = counts
    if "tfidf" in scorings or max_df:
        out = out.join(doc_freq(counts), "gram")
        out = out.where(F.col("df") <= max_df) if max_df else out
    tf = F.col("cnt") / F.max("cnt").over(Window.partitionBy("source", "pid")) if set(scorings) & {"tf", "tfidf"} else F.lit(1.0)
    out = out.withColumn("__tf", tf)
    base = F.lit(1.0) if log_base is None else F.ln(F.lit(float(log_base)))
    made = {"bool": F.lit(1.0), "tf": F.col("__tf")}
    if "tfidf" in scorings:
        made["tfidf"] = F.col("__tf") * F.ln(F.lit(float(n_records)) / F.col("df")) / base
    return out.select("source", "pid", "gram", *[made[s].alias(s) for s in scorings])


def dot_products(vectors: DataFrame, linkage: bool, scorings: tuple[str, ...], limit: int = KEY_ROWS) -> DataFrame:
    """(l, r, x_<scoring>): every scoring from one join on the gram; only pairs that share a gram."""
    sizes = vectors.groupBy("gram").agg(F.count(F.lit(1)).alias("n"))
    hot = sizes.where(F.col("n") > limit).limit(1).count() > 0
    rows = with_cells(vectors, "gram", sizes, limit) if hot else vectors
    met = meet(rows, "gram", linkage, list(scorings), [], cells=hot)
    return met.groupBy("l", "r").agg(*[F.sum(F.col(f"{s}_l") * F.col(f"{s}_r")).alias(f"x_{s}") for s in scorings])


def norms_of(vectors: DataFrame, scorings: tuple[str, ...]) -> DataFrame:
    """(source, pid, a column of the squared norm for each scoring)"""
    return vectors.groupBy("source", "pid").agg(*[F.sum(F.col(s) * F.col(s)).alias(s) for s in scorings])


def with_norms(dots: DataFrame, norms: DataFrame, linkage: bool, scorings: tuple[str, ...]) -> DataFrame:
    for side in "lr":
        own = norms.where(F.col("source") == side.upper()) if linkage else norms
        dots = dots.join(own.select(F.col("pid").alias(side), *[F.col(s).alias(f"{side}2_{s}") for s in scorings]), side)
    return dots


def similarity(sim: str, scoring: str) -> Column:
    x, a, b = (F.col(f"{k}_{scoring}") for k in ("x", "l2", "r2"))
    if sim == "cosine":
        return F.round(F.coalesce(F.try_divide(x, F.sqrt(a * b)), F.lit(0.0)), 9)
    if sim == "euclid":
        square = a + b - 2 * x
        return F.round(1 / (1 + F.sqrt(F.when(square > SAME * (a + b), square).otherwise(0.0))), 9)
    raise ValueError(f"unknown similarity: {sim}")


def _likely(pairs: DataFrame, q: str, i: str, k: int) -> DataFrame:
    """Pairs that can be among the k best of q: not below the least of the best weights in k lots of neighbours.

    The bound is exact and is combined before it is shuffled; what is left to be ranked are a few pairs of each query.
    """
    lot = F.pmod(F.xxhash64(i), F.lit(k))
    tops = [F.coalesce(F.max(F.when(lot == b, F.col("w"))), F.lit(0.0)) for b in range(k)]
    floors = pairs.groupBy(q).agg((F.least(*tops) if k > 1 else tops[0]).alias("__floor"))
    return pairs.join(floors, q).where(F.col("w") >= F.col("__floor")).drop("__floor")


def nearest(pairs: DataFrame, k: int, linkage: bool, side: str, sizes: dict[str, int]) -> DataFrame:
    """(l, r, w): pairs that are among the k best of a query, similarity first, then the neighbour's id.

    Linkage: the side that is not indexed queries; `both` is the union. Dedup: both ends query, whatever `side`.
    """
    if k < 1:
        raise ValueError(f"k must be 1 or more: {k}")
    if side not in SIDES:
        raise ValueError(f"unknown index side: {side}")
    small = "l" if sizes.get("L", 0) <= sizes.get("R", 0) else "r"
    large = "r" if small == "l" else "l"
    queries = "lr" if not linkage or side == "both" else large if side == "smallest" else small
    if not linkage:  # one ranking over both directions
        ends = pairs.select(F.explode(F.array(F.struct(F.col("l").alias("q"), F.col("r").alias("i")), F.struct(F.col("r").alias("q"), F.col("l").alias("i")))).alias("e"), "w").select("e.*", "w")
        best = _likely(ends, "q", "i", k).withColumn("t", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("w"), "i"))).where(F.col("t") <= k)
        return best.groupBy(F.least("q", "i").alias("l"), F.greatest("q", "i").alias("r")).agg(F.max("w").alias("w"))
    found = None
    for q in queries:
        i = "r" if q == "l" else "l"
        best = _likely(pairs, q, i, k).withColumn("t", F.row_number().over(Window.partitionBy(q).orderBy(F.desc("w"), i))).where(F.col("t") <= k).select("l", "r", "w")
        found = best if found is None else found.union(best)
    return found.groupBy("l", "r").agg(F.max("w").alias("w")) if len(queries) > 1 else found


def nearest_stack(stacked: DataFrame, ks: tuple[int, ...], linkage: bool, sizes: dict[str, int]) -> DataFrame:
    """(config, l, r, w): what `nearest` gives for every index side and k, of many configurations (config, l, r, w) at once."""
    place = lambda q, i: F.row_number().over(Window.partitionBy("config", q).orderBy(F.desc("w"), i))
    if linkage:
        small, large = "lr" if sizes.get("L", 0) <= sizes.get("R", 0) else "rl"
        pairs = stacked.withColumn("t_l", place("l", "r")).withColumn("t_r", place("r", "l"))
        places = {"smallest": F.col(f"t_{large}"), "largest": F.col(f"t_{small}"), "both": F.least("t_l", "t_r")}
    else:
        ends = stacked.select("config", F.explode(F.array(F.struct(F.col("l").alias("q"), F.col("r").alias("i")), F.struct(F.col("r").alias("q"), F.col("l").alias("i")))).alias("e"), "w").select("config", "e.*", "w")
        ends = ends.withColumn("t", place("q", "i")).where(F.col("t") <= max(ks))
        pairs = ends.groupBy("config", F.least("q", "i").alias("l"), F.greatest("q", "i").alias("r")).agg(F.max("w").alias("w"), F.min("t").alias("t"))
        places = {"both": F.col("t")}
    choices = F.array(*[F.struct(F.lit(f"{side}_{k}").alias("name"), (t <= k).alias("near")) for side, t in places.items() for k in ks])
    near = pairs.where(F.least(*places.values(), F.lit(max(ks) + 1)) <= max(ks)) if len(places) > 1 else pairs
    return near.select("config", "l", "r", "w", F.explode(F.filter(choices, lambda c: c["near"])).alias("c")).select(F.concat_ws("_", "config", "c.name").alias("config"), "l", "r", "w")


def sparse_vectors(task: Task, tokenizer: str, scorings: tuple[str, ...], max_df: int | None = None) -> DataFrame:
    """(source, pid, gram id, a column for each scoring)"""
    return scored(encode_grams(term_counts(task, tokenizer)), sum(task.sizes().values()), scorings, max_df)


def sparse_pairs(task: Task, tokenizer: str, scorings: tuple[str, ...], max_df: int | None = None) -> DataFrame:
    """(l, r, x_<scoring>, l2 and r2 norms)"""
    vectors = sparse_vectors(task, tokenizer, scorings, max_df)
    return with_norms(dot_products(vectors, task.linkage, scorings), norms_of(vectors, scorings), task.linkage, scorings)


def sparse_candidates(task: Task, tokenizer: str = "word1", scoring: str = "tfidf", sim: str = "cosine", k: int = 5, index: str = "largest", max_df: int | None = None) -> DataFrame:
    """(l, r, w) edges: pairs of profiles with a common gram, the k nearest of each query."""
    pairs = sparse_pairs(task, tokenizer, (scoring,), max_df).select("l", "r", similarity(sim, scoring).alias("w")).where("w > 0")
    return nearest(pairs, k, task.linkage, index, task.sizes())


def sparse_grid(task: Task, tokenizer: str, ks: tuple[int, ...] = (1, 5, 10), sides: tuple[str, ...] = SIDES, max_df: int | None = None) -> dict[tuple, DataFrame]:
    """Edges of all scorings, similarities, index sides and k of a tokenizer, from one join of postings, settled once."""
    from progmatch.session import settle

    pairs = settle(sparse_pairs(task, tokenizer, SCORINGS, max_df), "postings")
    sizes, found = task.sizes(), {}
    for scoring in SCORINGS:
        for sim in SIMILARITIES:
            weighted = pairs.select("l", "r", similarity(sim, scoring).alias("w")).where("w > 0")
            for k in ks:
                for side in sides if task.linkage else ("both",):
                    found[tokenizer, scoring, sim, k, side] = nearest(weighted, k, task.linkage, side, sizes)
    return found
