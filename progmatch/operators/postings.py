"""The sparse join in packed form: blocks of vectors as bytes, whose products are added up in the task where two blocks meet."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from progmatch.functions.text import normalised, with_grams
from progmatch.operators.dense import _Best, _offer, merged_best
from progmatch.session import drop, release, settle
from progmatch.sources.profiles import Task

BLOCK_ROWS = 2048
#: Products that are added up at once.
HELD_PRODUCTS = 1 << 22
#: A gram is multiplied as a column if its products are more than this part of all pairs of rows; so many columns at once.
DENSE_SHARE, SLAB = 400, 1024
#: Grams of two profiles and more whose frequencies are sent to every task; beyond, they are joined.
MOST_GRAMS = 6_000_000


def _lists(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """(values, the list each belongs to)"""
    ends = column.offsets.to_numpy()
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.int64), np.repeat(np.arange(len(column)), np.diff(ends))


def gram_ids(task: Task, tokenizer: str) -> DataFrame:
    """(source, pid, ids): 64-bit ids of a profile's grams, repeats included."""
    if tokenizer == "char3":
        return task.profiles.select("source", "pid", normalised(F.col("text")).alias("text")).mapInArrow(_char3, "source string, pid long, ids array<long>")
    return with_grams(task.profiles, tokenizer).select("source", "pid", F.transform("grams", lambda g: F.xxhash64(g)).alias("ids"))


def _char3(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A gram of three characters is its three code points of 21 bits; a shorter text is one gram."""
    for batch in batches:
        ids = []
        for text in batch.column(2).to_pylist():
            c = np.frombuffer(text.encode("utf-32-le"), "<u4").astype(np.int64)
            c = np.pad(c, (0, 3 - len(c))) if 0 < len(c) < 3 else c
            ids.append(c[:-2] | c[1:-1] << 21 | c[2:] << 42)
        offsets = np.cumsum([0, *map(len, ids)]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids) if ids else np.empty(0, np.int64)))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), lists], ["source", "pid", "ids"])


def gram_frequencies(texts: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """(ids ascending, profiles) of grams that two profiles or more have; None if they are too many to be sent."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, own = _lists(batch.column(0))
            order = np.lexsort((own, ids))
            ids, own = ids[order], own[order]
            new = np.ones(len(ids), bool)
            new[1:] = (ids[1:] != ids[:-1]) | (own[1:] != own[:-1])
            found, n = np.unique(ids[new], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found), pa.array(n.astype(np.int64))], ["g", "df"])

    counts = settle(texts.select("ids").mapInArrow(each, "g long, df long").groupBy("g").agg(F.sum("df").alias("df")).where("df > 1"), "frequencies")
    release(counts.sparkSession)
    if counts.count() > MOST_GRAMS:
        return None
    rows = counts.orderBy("g").toArrow()
    drop(counts)
    return rows.column(0).to_numpy(), rows.column(1).to_numpy()


def packed_postings(task: Task, tokenizer: str, scoring: str, block: int = BLOCK_ROWS, k1: float = 1.2, b: float = 0.75) -> DataFrame | None:
    """Settled (source, at, ids, grams, rows, weights): unit vectors of up to `block` profiles of a source in a row, as bytes,
    by gram; ids ascend. Grams that one profile alone has count in its length only. None if the other grams are too many to be sent.
    scoring bm25: the weights of BM25 instead, with k1 and b, which are no unit vectors."""
    texts = gram_ids(task, tokenizer)
    if scoring == "bm25":
        stats = texts.where(F.size("ids") > 0).agg(F.avg(F.size("ids")).alias("avg"), F.count(F.lit(1)).alias("n")).first()
        n_records, mean = stats["n"], float(stats["avg"] or 1)
    else:
        n_records, mean = task.profiles.count(), 1.0
    frequencies = gram_frequencies(texts)
    if frequencies is None:
        return None
    known = task.profiles.sparkSession.sparkContext.broadcast(frequencies)

    def weighed(ids: np.ndarray, own: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, gram, weight) of grams that others have too, rows in order."""
        lengths = np.bincount(own, minlength=n)
        order = np.lexsort((ids, own))
        ids, own = ids[order], own[order]
        new = np.ones(len(ids), bool)
        new[1:] = (ids[1:] != ids[:-1]) | (own[1:] != own[:-1])
        counts = np.diff(np.flatnonzero(new), append=len(ids))
        ids, own = ids[new], own[new]
        grams, df = known.value
        at = np.minimum(np.searchsorted(grams, ids), max(len(grams) - 1, 0))
        shared = grams[at] == ids if len(grams) else np.zeros(len(ids), bool)
        if scoring == "bm25":
            own, ids, counts, df = own[shared], ids[shared], counts[shared], df[at[shared]] if len(grams) else np.empty(0)
            idf = np.log(1 + (n_records - df + 0.5) / (df + 0.5))
            return own, ids, idf * (counts * (k1 + 1) / (counts + k1 * (1 - b + b * lengths[own] / mean)))
        largest = np.ones(n)
        np.maximum.at(largest, own, counts)
        w = np.ones(len(ids)) if scoring == "bool" else counts / largest[own]
        if scoring == "tfidf":
            w = w * np.log(float(n_records) / np.where(shared, df[at] if len(grams) else 1, 1))
        norm = np.sqrt(np.bincount(own, w * w, n))
        w = w / np.where(norm > 0, norm, 1)[own]
        return own[shared], ids[shared], w[shared]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {}
        at, k = TaskContext.get().partitionId() << 32, 0

        def out(source: str) -> pa.RecordBatch:
            parts = held.pop(source)
            pids = np.concatenate([p[0] for p in parts])
            starts = np.cumsum([0, *[len(p[0]) for p in parts]])
            rows = np.concatenate([p[1] + s for p, s in zip(parts, starts, strict=False)])
            grams, w = (np.concatenate([p[c] for p in parts]) for c in (2, 3))
            place = np.empty(len(pids), np.int64)
            by_id = np.argsort(pids, kind="stable")
            place[by_id] = np.arange(len(pids))
            rows = place[rows]
            order = np.lexsort((rows, grams))
            blobs = [c.tobytes() for c in (pids[by_id].astype("<i8"), grams[order].astype("<i8"), rows[order].astype("<i4"), w[order])]
            return pa.RecordBatch.from_arrays([pa.array([source]), pa.array([at + k]), *[pa.array([b], pa.binary()) for b in blobs]], ["source", "at", "ids", "grams", "rows", "weights"])

        for batch in batches:
            sources, pids = np.array(batch.column(0).to_pylist(), object), batch.column(1).to_numpy()
            own, grams, w = weighed(*_lists(batch.column(2)), batch.num_rows)
            for source in dict.fromkeys(sources):
                mine = np.flatnonzero(sources == source)
                while len(mine):
                    some = mine[: block - sum(len(x[0]) for x in held.get(source, ()))]
                    row_of = np.full(batch.num_rows, -1)
                    row_of[some] = np.arange(len(some))
                    use = row_of[own] >= 0
                    held.setdefault(source, []).append((pids[some], row_of[own[use]], grams[use], w[use]))
                    mine = mine[len(some) :]
                    if sum(len(x[0]) for x in held[source]) >= block:
                        yield out(source)
                        k += 1
        for source in list(held):
            yield out(source)
            k += 1

    return settle(texts.mapInArrow(run, "source string, at long, ids binary, grams binary, rows binary, weights binary"), "packed-postings", "zstd")


def _heads(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct grams, where each begins, how many) of ascending grams."""
    begin = np.flatnonzero(np.diff(grams, prepend=grams[:1] - 1)) if len(grams) else np.empty(0, np.int64)
    return grams[begin], begin, np.diff(begin, append=len(grams))


def products(q: tuple[np.ndarray, ...], x: tuple[np.ndarray, ...], n: int, m: int) -> np.ndarray:
    """Dot products, of shape (n, m), of two blocks (grams ascending, rows, weights). Grams that many rows of both have are
    columns of two matrices that are multiplied; the products of the others are added up one by one."""
    s = np.zeros(n * m)
    (qg, qr, qw), (xg, xr, xw) = q, x
    (q_grams, _, q_counts), (x_grams, x_begin, x_counts) = _heads(qg), _heads(xg)
    _, i, j = np.intersect1d(q_grams, x_grams, True, True)
    dense = q_counts[i] * x_counts[j] * DENSE_SHARE > n * m
    place = np.full(len(q_grams), -1)
    place[i[~dense]] = j[~dense]
    q_own, x_own = np.repeat(np.arange(len(q_grams)), q_counts), np.repeat(np.arange(len(x_grams)), x_counts)
    met = np.flatnonzero(place[q_own] >= 0)
    begin, counts = x_begin[place[q_own[met]]], x_counts[place[q_own[met]]]
    ends = np.cumsum(counts)
    a = 0
    while a < len(met):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + HELD_PRODUCTS, "right")))
        c = counts[a:b]
        there = np.arange(c.sum()) + np.repeat(begin[a:b] - (np.cumsum(c) - c), c)
        own = met[a:b]
        s += np.bincount(np.repeat(qr[own].astype(np.int64) * m, c) + xr[there], np.repeat(qw[own], c) * xw[there], n * m)
        a = b
    s = s.reshape(n, m)

    def columns(some: np.ndarray, of: np.ndarray, own: np.ndarray, r: np.ndarray, w: np.ndarray, rows: int) -> np.ndarray:
        column = np.full(len(of), -1)
        column[some] = np.arange(len(some))
        c = column[own]
        use = c >= 0
        return np.bincount(r[use].astype(np.int64) * len(some) + c[use], w[use], rows * len(some)).reshape(rows, len(some))

    i, j = i[dense], j[dense]
    for a in range(0, len(i), SLAB):
        some = slice(a, a + SLAB)
        s += columns(i[some], q_grams, q_own, qr, qw, n) @ columns(j[some], x_grams, x_own, xr, xw, m).T
    return s


def nearest_cosine(left: DataFrame, right: DataFrame, k: int, dedup: bool, sides: tuple[int, ...] = (0, 1), plain: bool = False) -> DataFrame:
    """(side, q, i, w): the k best of every vector by cosine, of side 0 (left, asking right) and 1 (right, asking left), positive ones
    only. Dedup: left and right are the same, every vector asks all others, on side 0. left, right: packed_postings. plain: the
    weights of the one that asks count as 1, and its k best share a gram with it, whatever their rounded weight."""

    def scores(q: list[np.ndarray], x: list[np.ndarray], qi: np.ndarray, xi: np.ndarray, same: bool) -> np.ndarray:
        s = products((*q[:2], np.ones(len(q[2]))) if plain else q, x, len(qi), len(xi))
        s[s <= 0] = -np.inf
        if same:
            np.fill_diagonal(s, -np.inf)
        return s

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[tuple[int, int], tuple[np.ndarray, _Best]] = {}
        for batch in batches:
            for row in range(batch.num_rows):
                qa, xa = batch.column(0)[row].as_py(), batch.column(5)[row].as_py()
                qi, xi = (np.frombuffer(batch.column(c)[row].as_buffer(), "<i8") for c in (1, 6))
                blocks = [[np.frombuffer(batch.column(c + j)[row].as_buffer(), t) for j, t in enumerate(("<i8", "<i4", "<f8"))] for c in (2, 7)]
                other = 0 if dedup else 1
                for side, at, ids in ((0, qa, qi), (other, xa, xi)):
                    if side in sides and (side, at) not in found:
                        found[side, at] = (ids.copy(), _Best(len(ids), k))
                s, turn = None, other in sides and not (dedup and qa == xa)
                if 0 in sides:
                    _offer(found[0, qa][1], 0, s := scores(*blocks, qi, xi, dedup and qa == xa), xi, "cosine")
                if turn:
                    back = scores(*blocks[::-1], xi, qi, False) if plain else np.ascontiguousarray((scores(*blocks, qi, xi, False) if s is None else s).T)
                    _offer(found[other, xa][1], 0, back, qi, "cosine")
        for (side, at), (ids, best) in found.items():
            yield pa.RecordBatch.from_arrays([pa.array([side], pa.int32()), pa.array([at], pa.int64()), *[pa.array([c.tobytes()], pa.binary()) for c in (ids, best.w, best.i)]], ["side", "at", "ids", "w", "i"])

    named = lambda df, p: df.select(*[F.col(c).alias(f"{p}_{c}") for c in ("at", "ids", "grams", "rows", "weights")])
    a, b = named(left, "q"), named(right, "x").hint("shuffle_replicate_nl")
    met = a.join(b, F.col("q_at") <= F.col("x_at")) if dedup else a.crossJoin(b)
    best = merged_best(met.mapInArrow(run, "side int, at long, ids binary, w binary, i binary"), k)
    return best if plain else best.where("w > 0")


def edges_of_side(found: DataFrame, linkage: bool, index: str, sizes: dict[str, int]) -> DataFrame:
    """(l, r, w) of neighbours (side, q, i, w), as sparse.nearest gives them for an index side."""
    if not linkage:
        return found.groupBy(F.least("q", "i").alias("l"), F.greatest("q", "i").alias("r")).agg(F.max("w").alias("w"))
    small = 0 if sizes.get("L", 0) <= sizes.get("R", 0) else 1
    asks = {"both": (0, 1), "smallest": (1 - small,), "largest": (small,)}[index]
    turned = F.col("side") == 1
    some = found.where(F.col("side").isin(*asks))
    return some.groupBy(F.when(turned, F.col("i")).otherwise(F.col("q")).alias("l"), F.when(turned, F.col("q")).otherwise(F.col("i")).alias("r")).agg(F.max("w").alias("w"))
