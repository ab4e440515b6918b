"""Dense-vector family: exact nearest neighbours by blocks, cells of a coarse quantiser, sign-projection hashing."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from progmatch.operators.sparse import nearest
from progmatch.session import settle, shuffle_width
from progmatch.sources.profiles import Task

BLOCK_ROWS = 4096
PAIRS = "l long, r long, w double"


def _similarities(q: np.ndarray, x: np.ndarray, sim: str) -> np.ndarray:
    if sim == "cosine":
        qn, xn = np.linalg.norm(q, axis=1), np.linalg.norm(x, axis=1)
        return (q / np.where(qn > 0, qn, 1)[:, None]) @ (x / np.where(xn > 0, xn, 1)[:, None]).T
    if sim == "euclid":
        d2 = (q * q).sum(1)[:, None] + (x * x).sum(1)[None] - 2 * q @ x.T
        return 1 / (1 + np.sqrt(np.maximum(d2, 0)))
    raise ValueError(f"unknown similarity: {sim}")


def _best(groups: pd.DataFrame, sim: str, k: int, dedup: bool) -> pd.DataFrame:
    """The k best of each query row among the index rows of a group, ties by id."""
    q, x = groups[groups["side"] == 0], groups[groups["side"] == 1]
    if not len(q) or not len(x):
        return pd.DataFrame({"q": [], "i": [], "w": []}).astype({"q": "int64", "i": "int64", "w": "float64"})
    w = np.round(_similarities(np.stack(q["vec"]).astype(np.float64), np.stack(x["vec"]).astype(np.float64), sim), 9)
    qi, xi = q["pid"].to_numpy(), x["pid"].to_numpy()
    by_id = np.argsort(xi, kind="stable")
    w, xi = w[:, by_id], xi[by_id]
    if dedup:
        w = np.where(qi[:, None] == xi[None], -np.inf, w)
    top = np.argsort(-w, axis=1, kind="stable")[:, :k]
    rows = np.repeat(np.arange(len(qi)), top.shape[1])
    found = pd.DataFrame({"q": qi[rows], "i": xi[top.ravel()], "w": w[rows, top.ravel()]})
    return found[np.isfinite(found["w"])]


def _by_group(rows: DataFrame, keys: list[str], sim: str, k: int, dedup: bool) -> DataFrame:
    def run(group: pd.DataFrame) -> pd.DataFrame:
        return _best(group, sim, k, dedup)

    return rows.groupBy(*keys).applyInPandas(run, "q long, i long, w double")


#: Rows of a block of queries that meet a block of the index at once.
TILE_ROWS = 1024


def packed_vectors(vectors: DataFrame, block: int = BLOCK_ROWS) -> DataFrame:
    """Settled (source, at, ids, vecs): up to `block` vectors of a source in a row, as bytes in ascending order of ids. vectors: (source, pid, vec)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {}
        at, k = TaskContext.get().partitionId() << 32, 0

        def out(source: str) -> pa.RecordBatch:
            ids, vecs = (np.concatenate(c) for c in zip(*held.pop(source), strict=True))
            order = np.argsort(ids, kind="stable")
            return pa.RecordBatch.from_arrays([pa.array([source]), pa.array([at + k]), pa.array([ids[order].astype("<i8").tobytes()], pa.binary()), pa.array([vecs[order].astype("<f8").tobytes()], pa.binary())], ["source", "at", "ids", "vecs"])

        for batch in batches:
            sources = np.array(batch.column(0).to_pylist(), object)
            pids = batch.column(1).to_numpy()
            lists = batch.column(2)
            vecs = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(pids), -1) if len(pids) else None
            for source in dict.fromkeys(sources):
                mine = np.flatnonzero(sources == source)
                while len(mine):
                    room = block - sum(len(x[0]) for x in held.get(source, ()))
                    held.setdefault(source, []).append((pids[mine[:room]], vecs[mine[:room]]))
                    if len(mine) >= room:
                        yield out(source)
                        k += 1
                    mine = mine[room:]
        for source in list(held):
            yield out(source)
            k += 1

    return settle(vectors.select("source", "pid", "vec").mapInArrow(run, "source string, at long, ids binary, vecs binary"), "packed-vectors")


class _Best:
    """The k best neighbours of each row of a block so far: weight first, then the smaller id."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.w, self.i = np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)

    def add(self, rows: np.ndarray, ids: np.ndarray, w: np.ndarray) -> None:
        """Candidates: weights and ids of rows; each id once for a row."""
        use = np.isfinite(w)
        rows, ids, w = rows[use], ids[use], w[use]
        touched = np.unique(rows)
        rows = np.concatenate((rows, np.repeat(touched, self.k)))
        ids, w = np.concatenate((ids, self.i[touched].ravel())), np.concatenate((w, self.w[touched].ravel()))
        order = np.lexsort((ids, -w, rows))
        rows, ids, w = rows[order], ids[order], w[order]
        place = np.arange(len(rows)) - np.searchsorted(rows, rows)
        top = place < self.k
        self.w[rows[top], place[top]], self.i[rows[top], place[top]] = w[top], ids[top]


def _scores(q: np.ndarray, x: np.ndarray, sim: str) -> np.ndarray:
    """Rises with the similarity: the cosine of unit vectors, or the negative squared distance."""
    s = q @ x.T
    if sim == "euclid":
        s *= 2
        s -= (q * q).sum(1)[:, None] + (x * x).sum(1)[None]
    return s


def _weight(s: np.ndarray, sim: str) -> np.ndarray:
    return np.round(s if sim == "cosine" else np.where(np.isfinite(s), 1 / (1 + np.sqrt(np.maximum(-s, 0))), -np.inf), 9)


def _floor(w: np.ndarray, sim: str) -> np.ndarray:
    """Scores below have smaller weights than w, rounding included."""
    low = w - 1e-9
    return low if sim == "cosine" else np.where(low > 0, -((1 / np.where(low > 0, low, 1) - 1) ** 2), -np.inf)


def _offer(best: _Best, base: int, s: np.ndarray, ids: np.ndarray, sim: str) -> None:
    """Rows of scores for the rows of `best` from `base` on; ids ascend. What can't be among the k best is neither rounded nor ranked."""
    here = slice(base, base + len(s))
    if s.shape[1] > best.k:
        least = np.maximum(best.w[here, -1], _weight(np.partition(s, -best.k, axis=1)[:, -best.k], sim)) if not np.isfinite(best.w[here, -1]).all() else best.w[here, -1]
        near = s >= _floor(least, sim)[:, None]
    else:
        near = np.ones(s.shape, bool)
    many = np.flatnonzero(np.count_nonzero(near, axis=1) > 8 * best.k)
    for a in range(0, len(many), 64):  # many that are equally near, such as copies
        own = many[a : a + 64]
        w = _weight(s[own], sim)
        top = np.argsort(-w, axis=1, kind="stable")[:, : best.k]
        best.add(base + np.repeat(own, top.shape[1]), ids[top.ravel()], np.take_along_axis(w, top, 1).ravel())
    near[many] = False
    r, c = np.nonzero(near)
    if len(r):
        best.add(base + r, ids[c], _weight(s[r, c], sim))


def merged_best(parts: DataFrame, k: int) -> DataFrame:
    """(side, q, i, w): the k best of every row of the blocks (side, at, ids, w, i) that tasks have found."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(key: tuple[int, int], ids: np.ndarray, best: _Best) -> Iterator[pa.RecordBatch]:
            rows, place = np.nonzero(np.isfinite(best.w))
            for a in range(0, len(rows), 1 << 16):
                r, p = rows[a : a + (1 << 16)], place[a : a + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), key[0], np.int32)), pa.array(ids[r]), pa.array(best.i[r, p]), pa.array(best.w[r, p])], ["side", "q", "i", "w"])

        now, ids, best = None, None, None
        for batch in batches:
            for row in range(batch.num_rows):
                key = (batch.column(0)[row].as_py(), batch.column(1)[row].as_py())
                own = np.frombuffer(batch.column(2)[row].as_buffer(), "<i8")
                if key != now:
                    if now is not None:
                        yield from out(now, ids, best)
                    now, ids, best = key, own.copy(), _Best(len(own), k)
                w, i = (np.frombuffer(batch.column(c)[row].as_buffer(), t) for c, t in ((3, "<f8"), (4, "<i8")))
                best.add(np.repeat(np.arange(len(own)), k), i, w)
        if now is not None:
            yield from out(now, ids, best)

    return parts.repartition(shuffle_width(parts.sparkSession), "side", "at").sortWithinPartitions("side", "at").mapInArrow(merge, "side int, q long, i long, w double")


def exact_neighbours(left: DataFrame, right: DataFrame, sim: str, k: int, dedup: bool, sides: tuple[int, ...] = (0, 1)) -> DataFrame:
    """(side, q, i, w): the k best of every vector, of side 0 (left, asking right) and 1 (right, asking left). Dedup: left and right
    are the same, every vector asks all others, on side 0.

    Blocks are packed rows; each partition of the left ones meets each of the right ones in a task, and nothing but the k best of
    each vector so far leaves it. Work is the product of both sides by definition, disk grows with their sum.
    """
    if sim not in ("cosine", "euclid"):
        raise ValueError(f"unknown similarity: {sim}")

    def vectors(data: bytes, n: int) -> np.ndarray:
        x = np.frombuffer(data, "<f8").reshape(n, -1)
        norm = np.linalg.norm(x, axis=1) if sim == "cosine" else None
        return x if norm is None else x / np.where(norm > 0, norm, 1)[:, None]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[tuple[int, int], tuple[np.ndarray, _Best]] = {}
        held, q = None, None
        for batch in batches:
            for row in range(batch.num_rows):
                qa, xa = batch.column(0)[row].as_py(), batch.column(3)[row].as_py()
                qi, xi = (np.frombuffer(batch.column(c)[row].as_buffer(), "<i8") for c in (1, 4))
                if qa != held:
                    held, q = qa, vectors(batch.column(2)[row].as_buffer(), len(qi))
                x = vectors(batch.column(5)[row].as_buffer(), len(xi))
                ask = (0, 0) if dedup else (0, 1)
                for side, at, ids in ((ask[0], qa, qi), (ask[1], xa, xi)):
                    if side in sides and (side, at) not in found:
                        found[side, at] = (ids.copy(), _Best(len(ids), k))
                for a in range(0, len(qi), TILE_ROWS):
                    s, ids = _scores(q[a : a + TILE_ROWS], x, sim), qi[a : a + TILE_ROWS]
                    if dedup:
                        for r in np.flatnonzero(np.isin(ids, xi)):
                            s[r, xi == ids[r]] = -np.inf
                    if ask[0] in sides:
                        _offer(found[ask[0], qa][1], a, s, xi, sim)
                    if ask[1] in sides and not (dedup and qa == xa):
                        _offer(found[ask[1], xa][1], 0, np.ascontiguousarray(s.T), ids, sim)
        for (side, at), (ids, best) in found.items():
            yield pa.RecordBatch.from_arrays([pa.array([side], pa.int32()), pa.array([at], pa.int64()), *[pa.array([c.tobytes()], pa.binary()) for c in (ids, best.w, best.i)]], ["side", "at", "ids", "w", "i"])

    a = left.select(F.col("at").alias("qa"), F.col("ids").alias("qi"), F.col("vecs").alias("q"))
    b = right.select(F.col("at").alias("xa"), F.col("ids").alias("xi"), F.col("vecs").alias("x"))
    met = a.join(b.hint("shuffle_replicate_nl"), F.col("qa") <= F.col("xa")) if dedup else a.crossJoin(b.hint("shuffle_replicate_nl"))
    parts = met.mapInArrow(run, "side int, at long, ids binary, w binary, i binary")
    return merged_best(parts, k)


def exact_pairs(queries: DataFrame, index: DataFrame, sim: str, k: int, dedup: bool, block: int = BLOCK_ROWS) -> DataFrame:
    """(q, i, w): the k best of each query among all rows of the index; dedup: both are the same. queries, index: (pid, vec)."""
    x = packed_vectors(index.select(F.lit("R").alias("source"), "pid", "vec"), block)
    q = x if dedup else packed_vectors(queries.select(F.lit("L").alias("source"), "pid", "vec"), block)
    return exact_neighbours(q, x, sim, k, dedup, (0,)).select("q", "i", "w")


def kmeans_cells(index: DataFrame, cells: int, seed: int = 1, sample_rows: int = 50_000) -> np.ndarray:
    """Centres of a coarse quantiser, fitted on a sample of at most about sample_rows vectors."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    n = index.count()
    picked = index if n <= sample_rows else index.where(F.pmod(F.xxhash64("pid"), F.lit(1_000_000)) < F.lit(int(1e6 * sample_rows / n)))
    model = KMeans(k=max(1, min(cells, n)), seed=seed, maxIter=10).fit(picked.select(array_to_vector("vec").alias("features")))
    return np.array(model.clusterCenters())


def with_cells_of(df: DataFrame, centres: np.ndarray, probes: int) -> DataFrame:
    """A row for each of the `probes` nearest cells of each vector."""
    p = min(probes, len(centres))

    def assign(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                d = _similarities(np.stack(b["vec"]).astype(np.float64), centres, "euclid")
                top = np.argsort(-d, axis=1, kind="stable")[:, :p]
                out = b.loc[b.index.repeat(p)].copy()
                out["cell"] = top.ravel().astype("int32")
                yield out

    return df.select("pid", "vec").mapInPandas(assign, "pid long, vec array<double>, cell int")


def cell_pairs(queries: DataFrame, index: DataFrame, sim: str, k: int, dedup: bool, cells: int = 16, probes: int = 4, block: int = BLOCK_ROWS) -> DataFrame:
    """(q, i, w): a query sees the index rows of its nearest cells only; a large cell is cut into parts of about `block` rows."""
    centres = kmeans_cells(index, cells)
    own = with_cells_of(index, centres, 1)
    sizes = {r["cell"]: -(-r["count"] // block) for r in own.groupBy("cell").count().collect()}  # a row for each cell
    parts = F.coalesce(F.element_at(F.map_from_arrays(F.array(*[F.lit(c) for c in sizes]), F.array(*[F.lit(int(n)) for n in sizes.values()])), F.col("cell")), F.lit(1)) if sizes else F.lit(1)
    hashed = F.xxhash64("pid")
    x = own.select("pid", "vec", F.lit(1).alias("side"), "cell", F.pmod(hashed, parts).cast("int").alias("part"))
    asked = with_cells_of(queries, centres, probes)
    q = asked.select("pid", "vec", F.lit(0).alias("side"), "cell", F.explode(F.sequence(F.lit(0), (parts - 1).cast("int"))).alias("part"))
    return _by_group(q.unionByName(x), ["cell", "part"], sim, k, dedup)


def lsh_pairs(queries: DataFrame, index: DataFrame, sim: str, k: int, dedup: bool, bands: int = 16, bits: int = 6, seed: int = 5, block: int = BLOCK_ROWS) -> DataFrame:
    """(q, i, w): vectors meet if they agree on the signs of `bits` projections of a band."""
    first = index.select("vec").first()
    if first is None:
        return queries.select(F.col("pid").alias("q"), F.col("pid").alias("i"), F.lit(0.0).alias("w")).limit(0)
    planes = np.random.default_rng(seed).normal(size=(len(first["vec"]), bands * bits))

    def hashed(df: DataFrame, side: int) -> DataFrame:
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                if len(b):
                    signs = (np.stack(b["vec"]).astype(np.float64) @ planes > 0).reshape(len(b), bands, bits)
                    keys = signs @ (1 << np.arange(bits)) + (np.arange(bands) << bits)
                    out = b.loc[b.index.repeat(bands)].copy()
                    out["cell"] = keys.ravel().astype("int32")
                    yield out

        return df.select("pid", "vec").mapInPandas(run, "pid long, vec array<double>, cell int").withColumn("side", F.lit(side))

    x, q = hashed(index, 1), hashed(queries, 0)
    sizes = {r["cell"]: -(-r["count"] // block) for r in x.groupBy("cell").count().collect()}  # at most bands * 2^bits rows
    parts = F.coalesce(F.element_at(F.map_from_arrays(F.array(*[F.lit(c) for c in sizes]), F.array(*[F.lit(int(n)) for n in sizes.values()])), F.col("cell")), F.lit(1))
    x = x.withColumn("part", F.pmod(F.xxhash64("pid"), parts).cast("int"))
    q = q.withColumn("part", F.explode(F.sequence(F.lit(0), (parts - 1).cast("int"))))
    return _by_group(q.unionByName(x), ["cell", "part"], sim, k, dedup).distinct()


ENGINES = {"exact": exact_pairs, "cells": cell_pairs, "lsh": lsh_pairs}


def dense_candidates(vectors: DataFrame, kind: str, sim: str = "cosine", k: int = 5, index: str = "largest", engine: str = "exact", keep_nonpositive: bool = False, **options) -> DataFrame:
    """(l, r, w) edges. vectors: (source, pid, vec array<double>) of a dedup or linkage task."""
    if engine not in ENGINES:
        raise ValueError(f"unknown engine: {engine}")
    if k < 1:
        raise ValueError(f"k must be 1 or more: {k}")
    run = ENGINES[engine]
    if engine == "exact" and kind != "dedup":
        packed = packed_vectors(vectors, **options)
        left, right = (packed.where(F.col("source") == s) for s in "LR")
        n, m = (d.agg(F.coalesce(F.sum(F.length("ids")), F.lit(0))).first()[0] for d in (left, right))
        small_is_left = n <= m
        asks = (index == "both" or (index == "largest") == small_is_left, index == "both" or (index == "smallest") == small_is_left)
        found = exact_neighbours(left, right, sim, k, False, tuple(side for side in (0, 1) if asks[side]))
        turned = F.col("side") == 1
        edges = found.groupBy(F.when(turned, F.col("i")).otherwise(F.col("q")).alias("l"), F.when(turned, F.col("q")).otherwise(F.col("i")).alias("r")).agg(F.max("w").alias("w"))
    elif kind == "dedup":
        found = run(vectors.select("pid", "vec"), vectors.select("pid", "vec"), sim, k, True, **options)
        pairs = found.groupBy(F.least("q", "i").alias("l"), F.greatest("q", "i").alias("r"), "q", "i").agg(F.max("w").alias("w"))
        ranked = _ranked(pairs, k).select("l", "r", "w")
        edges = ranked.groupBy("l", "r").agg(F.max("w").alias("w"))
    else:
        left, right = (vectors.where(F.col("source") == s).select("pid", "vec") for s in "LR")
        n, m = left.count(), right.count()
        small_is_left = n <= m
        ask_left = index == "both" or (index == "largest") == small_is_left
        ask_right = index == "both" or (index == "smallest") == small_is_left
        edges = None
        for asked, (q, x), names in ((ask_left, (left, right), ("l", "r")), (ask_right, (right, left), ("r", "l"))):
            if asked:
                best = _ranked(run(q, x, sim, k, False, **options), k).select(F.col("q").alias(names[0]), F.col("i").alias(names[1]), "w").select("l", "r", "w")
                edges = best if edges is None else edges.union(best)
        edges = edges.groupBy("l", "r").agg(F.max("w").alias("w"))
    return edges if keep_nonpositive else edges.where("w > 0")


def _ranked(found: DataFrame, k: int) -> DataFrame:
    from pyspark.sql.window import Window

    return found.withColumn("t", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("w"), "i"))).where(F.col("t") <= k)


def index_recall(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """(recall): share of the exact edges that the approximate ones hold."""
    hits = exact.join(approximate.select("l", "r").withColumn("hit", F.lit(1)), ["l", "r"], "left")
    return hits.agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count(F.lit(1))).alias("recall"))


__all__ = ["Task", "cell_pairs", "dense_candidates", "exact_pairs", "index_recall", "lsh_pairs", "nearest"]
