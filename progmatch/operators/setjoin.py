"""Exact set-similarity self-join: pairs of texts whose sets of runs of words have a Jaccard similarity of a least value or more.

A set is put in one global order, rare grams first. Two sets that are similar enough share some grams among the first of the
larger and the still fewer first of the smaller, so only those places are shuffled and counted, and sizes too far apart never
meet. What is left are few candidates: their components are found, each text goes to its component's task once, and every candidate is
settled there on the whole sets. Equal texts are one text until the end. The order of grams comes from counts in a bounded
sample of texts; any order gives the same pairs, a good one gives few candidates.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from progmatch.functions.text import words
from progmatch.operators.matching import connected_components
from progmatch.operators.pairs import meet_evenly
from progmatch.session import drop, release, settle, shuffle_width

#: Texts from whose grams the order is estimated, and grams that it ranks; the others count as equally rare.
ORDER_TEXTS, ORDER_GRAMS = 8_000, 200_000
#: Components are sent to every task up to so many texts.
BROADCAST_ROWS = 500_000
#: Pairs held in a task until they are added up and given on.
HELD_PAIRS = 1 << 20
#: Texts whose rows are packed together: their number fits 15 bits.
BATCH_TEXTS = 1 << 15
EPS = 1e-9


#: An odd factor, and what stands for a word that a short text has not.
FACTOR, NO_WORD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0x2545F4914F6CDD1D)


def _words(df: DataFrame) -> DataFrame:
    """Adds `words`, 64-bit ids of the text's words in their order."""
    return df.withColumn("words", F.transform(words(F.col("text")), lambda w: F.xxhash64(w)))


def runs(flat: np.ndarray, ends: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all runs of n words, end of each text's runs); a text of fewer words is one run. Two of V runs share an id with odds of about V^2 / 2^65."""
    sizes = np.diff(ends, prepend=0)
    own, here = np.repeat(np.arange(len(ends)), sizes), np.arange(len(flat))
    left = ends[own] - here
    at = np.flatnonzero((left >= n) | ((sizes[own] < n) & (left == sizes[own])))
    w, x = flat.view(np.uint64), np.zeros(len(at), np.uint64)
    for k in range(n):
        x = x * FACTOR + np.where(left[at] > k, w[np.minimum(at + k, max(len(w) - 1, 0))], NO_WORD)
    return x.view(np.int64), np.cumsum(np.bincount(own[at], minlength=len(ends)))


def _lists(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """(values, end of each list)"""
    offsets = column.offsets.to_numpy()
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.int64), (offsets - offsets[0])[1:].astype(np.int64)


def usual_grams(profiles: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids ascending, counts) of the most frequent runs of n words in a sample of texts."""
    share = min(1.0, ORDER_TEXTS / max(1, profiles.count()))
    some = profiles.where(F.pmod(F.xxhash64("pid", F.lit(3)), F.lit(1_000_000)) < int(share * 1_000_000) + 1)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, ends = runs(*_lists(batch.column(0)), n)
            own = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
            order = np.lexsort((own, flat))
            flat, own = flat[order], own[order]
            new = np.ones(len(flat), bool)
            new[1:] = (flat[1:] != flat[:-1]) | (own[1:] != own[:-1])
            ids, counts = np.unique(flat[new], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(counts.astype(np.int64))], ["g", "c"])

    df = _words(some).select("words").mapInArrow(each, "g long, c long").groupBy("g").agg(F.sum("c").alias("c")).where("c > 2")
    rows = df.orderBy(F.desc("c"), "g").limit(ORDER_GRAMS).toPandas()
    ids, counts = rows["g"].to_numpy(np.int64), rows["c"].to_numpy(np.int64)
    by_id = np.argsort(ids)
    return ids[by_id], counts[by_id]


def needed(sizes: np.ndarray) -> np.ndarray:
    """So many grams two similar sets share among the first ones, by the size of the smaller set: what the first places are more than one sees."""
    return 1 + sizes // 10


def prefixes(flat: np.ndarray, ends: np.ndarray, usual: tuple[np.ndarray, np.ndarray], least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, gram, whether among the first as the smaller set, size of each text): the first grams of each text, made distinct."""
    text = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
    ids, counts = usual
    rank = np.zeros(len(flat), np.int64)
    if len(ids):
        at = np.minimum(np.searchsorted(ids, flat), len(ids) - 1)
        rank = np.where(ids[at] == flat, counts[at], 0)
    order = np.lexsort((flat, rank, text))
    text, flat = text[order], flat[order]
    new = np.ones(len(flat), bool)
    new[1:] = (text[1:] != text[:-1]) | (flat[1:] != flat[:-1])
    text, flat = text[new], flat[new]
    sizes = np.bincount(text, minlength=len(ends))
    place = np.arange(len(text)) - (np.cumsum(sizes) - sizes)[text]
    shared = needed(sizes)
    asks = (sizes - np.ceil(least * sizes - EPS) + shared)[text]
    holds = (sizes - np.ceil(2 * least / (1 + least) * sizes - EPS) + shared)[text]
    kept = place < asks
    return text[kept], flat[kept], (place < holds)[kept], sizes


def group_pairs(g: np.ndarray, t: np.ndarray, n: np.ndarray, holds: np.ndarray, least: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Pairs (t, t, size of the smaller set) of rows with equal g, sizes not too far apart, the smaller set's place among its first."""
    order = np.lexsort((t, n, g))
    g, t, n, holds = g[order], t[order], n[order], holds[order]
    new = np.ones(len(g), bool)
    new[1:] = (g[1:] != g[:-1]) | (t[1:] != t[:-1])  # a text that several rows have
    g, t, n, holds = g[new], t[new], n[new], holds[new]
    low, d = np.flatnonzero(holds), 1
    while len(low):
        low = low[low + d < len(g)]
        low = low[(g[low + d] == g[low]) & (n[low] >= least * n[low + d] - EPS)]
        if len(low):
            yield t[low], t[low + d], n[low]
        d += 1


def _counted(held: list[np.ndarray]) -> np.ndarray:
    """Rows (a, b, size, count): pairs a < b, their counts added up."""
    rows = np.concatenate(held)
    rows[:, :2].sort(axis=1)
    rows = rows[np.lexsort((rows[:, 1], rows[:, 0]))]
    new = np.ones(len(rows), bool)
    new[1:] = (rows[1:, :2] != rows[:-1, :2]).any(1)
    made = rows[new]
    if len(rows):
        made[:, 3] = np.add.reduceat(rows[:, 3], np.flatnonzero(new))
    return made


def candidates(profiles: DataFrame, n: int, least: float) -> DataFrame:
    """(a, b): ids of different texts, a < b, that can be similar enough; each once. profiles: (pid, text)."""
    spark = profiles.sparkSession
    usual = spark.sparkContext.broadcast(usual_grams(profiles, n))
    release(spark)  # the sample's shuffle would else lie beside the next
    deals = max(8, shuffle_width(spark) // 2)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(k, BATCH_TEXTS) for b in batches for k in range(0, b.num_rows, BATCH_TEXTS)):
            text, flat, holds, sizes = prefixes(*runs(*_lists(batch.column(1)), n), usual.value, least)
            ids = batch.column(0).to_numpy()
            bucket = (flat.astype(np.uint64) >> np.uint64(17)) % np.uint64(deals)
            order = np.argsort(bucket, kind="stable")
            text, flat, holds, bucket = text[order], flat[order], holds[order], bucket[order]
            cuts = np.searchsorted(bucket, np.arange(deals + 1, dtype=np.uint64))
            rows = []
            for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                if b > a:
                    own, at = np.unique(text[a:b], return_inverse=True)
                    head = np.array([b - a, len(own)], "<i8").tobytes()
                    rows.append((k, head + flat[a:b].tobytes() + ids[own].tobytes() + sizes[own].astype("<i4").tobytes() + (at * 2 + holds[a:b]).astype("<u2").tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["bucket", "packed"])

    def unpacked(data: bytes) -> tuple[np.ndarray, ...]:
        rows, texts = np.frombuffer(data, "<i8", 2)
        flat = np.frombuffer(data, "<i8", rows, 16)
        at = 16 + 8 * rows
        ids, sizes = np.frombuffer(data, "<i8", texts, at), np.frombuffer(data, "<i4", texts, at + 8 * texts)
        where = np.frombuffer(data, "<u2", rows, at + 12 * texts)
        return flat, ids[where >> 1], sizes[where >> 1], (where & 1).astype(bool)

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def of(parts: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
            held, size = [], 0
            for x, y, n in group_pairs(*[np.concatenate(c) for c in zip(*parts, strict=True)], least):
                held.append(np.stack((x, y, n.astype(np.int64), np.ones(len(x), np.int64)), 1))
                size += len(x)
                if size >= HELD_PAIRS:
                    held = [_counted(held)]
                    size = len(held[0])
                    if 2 * size >= HELD_PAIRS:
                        yield given(held[0])
                        held, size = [], 0
            if held:
                yield given(_counted(held))

        def given(rows: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(rows[:, 0]), pa.array(rows[:, 1]), pa.array(needed(rows[:, 2])), pa.array(rows[:, 3])], ["a", "b", "need", "c"])

        now, parts = None, []
        for batch in batches:
            for k, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if parts and k != now:
                    yield from of(parts)
                    parts = []
                now = k
                parts.append(unpacked(data.as_buffer().to_pybytes()))
        if parts:
            yield from of(parts)

    sets = _words(profiles).select(F.xxhash64("text").alias("t"), "words")
    dealt = sets.mapInArrow(deal, "bucket int, packed binary").repartition(deals, "bucket").sortWithinPartitions("bucket")
    sums = dealt.mapInArrow(pair, "a long, b long, need long, c long").groupBy("a", "b").agg(F.sum("c").alias("c"), F.max("need").alias("need"))
    found = settle(sums.where("c >= need").select("a", "b"), "candidates")
    release(spark)
    return found


def _verified(rows: DataFrame, n: int, least: float) -> DataFrame:
    """(a, b) of rows (root, a, b, words), the component's texts (b null) before its pairs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, sets = None, {}
        for batch in batches:
            roots, a, b = (batch.column(k).to_pylist() for k in range(3))
            flat, ends = runs(*_lists(batch.column(3)), n)
            starts, found = np.concatenate(([0], ends)), []
            for k in range(len(a)):
                if roots[k] != now:
                    now, sets = roots[k], {}
                if b[k] is None:
                    sets[a[k]] = np.unique(flat[starts[k] : starts[k + 1]])
                    continue
                x, y = sets[a[k]], sets[b[k]]
                at = np.minimum(np.searchsorted(x, y), len(x) - 1)
                both = int((x[at] == y).sum())
                if both >= least * (len(x) + len(y) - both):
                    found.append((a[k], b[k]))
            yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in found], pa.int64()), pa.array([p[1] for p in found], pa.int64())], ["a", "b"])

    return rows.repartition(shuffle_width(rows.sparkSession), "root").sortWithinPartitions("root", F.col("b").asc_nulls_first(), "a").mapInArrow(run, "a long, b long")


def similar_texts(profiles: DataFrame, n: int, least: float) -> DataFrame:
    """(l, r): pids l < r of all pairs of texts whose sets of runs of n words have a Jaccard similarity of `least` or more. profiles: (source, pid, text)."""
    if not 0 < least <= 1:
        raise ValueError(f"least must lie in (0, 1]: {least}")
    spark = profiles.sparkSession
    texts = profiles.select("source", "pid", "text").where(F.col("text").rlike(r"[\p{L}\p{N}]"))
    members = settle(texts.select("source", "pid", F.xxhash64("text").alias("t")), "members")
    found = candidates(texts, n, least)
    roots = connected_components(found.select(F.col("a").alias("l"), F.col("b").alias("r")))
    # one row of each candidate text carries its words
    heads = settle(members.join(roots.select(F.col("pid").alias("t"), F.col("cluster").alias("root")), "t").groupBy("t", "root").agg(F.min(F.struct("source", "pid")).alias("m")).select("t", "root", "m.*"), "heads")
    few = heads.count() <= BROADCAST_ROWS
    own = texts.join(F.broadcast(heads) if few else heads, ["source", "pid"])
    sets = _words(own).select("root", F.col("t").alias("a"), F.lit(None).cast("long").alias("b"), "words")
    asked = found.join(heads.select(F.col("t").alias("a"), "root"), "a").select("root", "a", "b", F.array().cast("array<long>").alias("words"))
    near = settle(_verified(sets.unionByName(asked), n, least), "similar")
    release(spark)
    drop(found, heads)
    ends = near.join(members.select(F.col("t").alias("a"), F.col("pid").alias("x")), "a").join(members.select(F.col("t").alias("b"), F.col("pid").alias("y")), "b")
    equal = meet_evenly(members, "t", members.groupBy("t").agg(F.count(F.lit(1)).alias("n")), False, [], [])
    return ends.select(F.least("x", "y").alias("l"), F.greatest("x", "y").alias("r")).unionByName(equal.select("l", "r"))
