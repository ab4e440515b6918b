"""Incremental baseline: profiles arrive in increments; every batch emits the globally best comparisons not yet emitted."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.functions.text import words
from progmatch.operators.order import positioned
from progmatch.operators.postings import BLOCK_ROWS, products
from progmatch.session import drop, settle, shared_root

PAIR, MET, ASKED, BIN = range(4)
#: Weights with the same sign, exponent and first five bits behind the point are counted together.
BIN_BITS = 47
STEP = 1e-9


class Incremental:
    """State: profiles so far as packed blocks of token ids, those of a batch with 1 / ||b|| of their blocks as known then.

    A batch's new blocks meet the old and new ones (`operators/postings.py: products`); pairs get 1 / ||b|| summed over the
    shared blocks. Every pair not yet emitted competes in every later batch, but only a pool of the best is written: all pairs
    left that weigh `end` and more, about `ahead` budgets at first. Where less than a budget of them is left, further ones are
    made from the blocks, so `ahead` changes no result. What is emitted of a batch's pairs is always the head of their order: the furthest
    key emitted since tells what is left of it. flush() emits the rest, so in the end every pair that shares a block has been
    emitted once; rest() only counts it.
    """

    def __init__(self, spark: SparkSession, budget: int, among: Column | None = None, asked: DataFrame | None = None, ahead: int = 10):
        """among: a condition on l and r, for instance that they are of different sources; other pairs are no candidates.
        asked: distinct pairs l < r; rest() tells how many of them are left."""
        if budget < 0:
            raise ValueError(f"negative budget: {budget}")
        if among is not None and asked is not None:
            raise ValueError("pairs are asked for among all pairs only")
        self.spark, self.budget, self.among, self.ahead = spark, budget, among, ahead
        self.asked = None if asked is None else settle(asked.select("l", "r"), "asked")
        self.counts: DataFrame | None = None
        #: Of each batch: packed blocks, tables of its pairs that weigh `end` and more, the furthest (w, l, r) emitted since.
        self.runs: list[tuple[DataFrame, list[DataFrame], tuple | None]] = []
        self.end = 0.0
        self.n_met = self.n_asked = 0
        self.emitted: list[DataFrame] = []
        self.n = self.n_emitted = 0

    def add(self, profiles: DataFrame) -> DataFrame:
        """(batch, pos, l, r, w) emitted for these profiles."""
        self._pack(profiles)
        if len(self.runs) == 1:
            self.end = self._end_below(None)
        found = settle(self._meet(len(self.runs) - 1, self.end, None), "pairs")
        met = found.where(F.col("kind") != PAIR).groupBy("kind").agg(F.sum("l").alias("n")).collect()
        self.n_met += sum(r["n"] for r in met if r["kind"] == MET)
        self.n_asked += sum(r["n"] for r in met if r["kind"] == ASKED)
        self.runs[-1][1].append(self._weighed(found, self.end, None))
        self._bound()
        return self._emit(self.budget)

    def _pack(self, profiles: DataFrame) -> None:
        """Packs new profiles: (at, ids, tokens, rows, weights, asked_rows, asked), tokens ascending."""
        keys = F.transform(F.array_distinct(words(F.col("text"))), lambda t: F.xxhash64(t))
        lists = settle(profiles.select("pid", keys.alias("ids")), "tokens")
        tokens = lists.select("pid", F.explode("ids").alias("t"))
        fresh = tokens.groupBy("t").agg(F.count(F.lit(1)).alias("n"))
        old = self.counts
        self.counts = settle(fresh if old is None else old.union(fresh).groupBy("t").agg(F.sum("n").alias("n")), "counts")
        weight = F.when(F.col("n") > 1, 2 / (F.col("n") * (F.col("n") - 1))).otherwise(0.0).alias("w")  # a later profile may share it
        rows = tokens.where("pid is not null").join(self.counts, "t").select("pid", "t", weight)
        if self.asked is not None:
            both = self.asked.union(self.asked.select("r", "l")).toDF("pid", "t")
            rows = rows.union(both.join(lists.select("pid").distinct(), "pid", "left_semi").withColumn("w", F.lit(-1.0)))
        few = max(1, -(-lists.count() // BLOCK_ROWS))
        rows = rows.withColumn("part", F.pmod(F.xxhash64("pid"), F.lit(few))).repartition(few, "part")
        base = len(self.runs) << 40

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = list(batches)
            if not held:
                return
            pid, t, w, part = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in range(4))
            held.clear()
            for k in np.unique(part):
                here = part == k
                ids, own = np.unique(pid[here], return_inverse=True)
                tokens, weights = t[here], w[here]
                asked = np.flatnonzero(weights < 0)
                order = np.lexsort((own, tokens))
                order = order[weights[order] >= 0]
                blobs = [ids.astype("<i8"), tokens[order].astype("<i8"), own[order].astype("<i4"), weights[order].astype("<f8"), own[asked].astype("<i4"), tokens[asked].astype("<i8")]
                yield pa.RecordBatch.from_arrays([pa.array([base + int(k)]), *[pa.array([x.tobytes()], pa.binary()) for x in blobs]], BLOCK)

        kinds = "at long, ids binary, tokens binary, rows binary, weights binary, asked_rows binary, asked binary"
        packed = settle(rows.coalesce(few).mapInArrow(run, kinds), "packed", "zstd")
        self.runs.append((packed, [], None))
        drop(lists)
        if old is not None:
            drop(old)

    def _meet(self, run: int, least: float, below: float | None, bins: bool = False) -> DataFrame:
        """(kind, l, r, w): pairs of a batch with the weights asked for, give or take STEP, and how many met; or bins of weights."""
        name = lambda df, p, cs: df.select(*[F.col(c).alias(f"{p}_{c}") for c in cs])
        q = name(self.runs[run][0], "q", BLOCK)
        x = name(reduce(DataFrame.union, [r[0] for r in self.runs[: run + 1]]), "x", BLOCK[:4])
        low, high = (least - STEP if least > 0 else 0.0), (np.inf if below is None else below + STEP)

        def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            made = {MET: 0, ASKED: 0}
            counted: dict[int, int] = {}
            for batch in batches:
                for i in range(batch.num_rows):
                    get = lambda c, kind: np.frombuffer(batch.column(c)[i].as_buffer(), kind)  # noqa: B023, E731
                    same = batch.column(0)[i] == batch.column(7)[i]
                    qi, xi = get(1, "<i8"), get(8, "<i8")
                    qt, qr, qw, xt, xr = get(2, "<i8"), get(3, "<i4"), get(4, "<f8"), get(9, "<i8"), get(10, "<i4")
                    met = qw > 0
                    s = products((qt[met], qr[met], qw[met]), (xt, xr, np.ones(len(xt))), len(qi), len(xi))
                    if same:
                        s[np.tril_indices(len(qi))] = 0
                    else:
                        _, a, b = np.intersect1d(qi, xi, True, True)
                        s[a, b] = 0
                    if bins:
                        found, n = np.unique(s[s > 0].view(np.int64) >> BIN_BITS, return_counts=True)
                        for b, k in zip(found.tolist(), n.tolist(), strict=True):
                            counted[b] = counted.get(b, 0) + k
                        continue
                    made[MET] += int(np.count_nonzero(s))
                    rows, others = get(5, "<i4"), get(6, "<i8")
                    at = np.minimum(np.searchsorted(xi, others), len(xi) - 1)
                    there = xi[at] == others
                    made[ASKED] += int(np.count_nonzero(s[rows[there], at[there]]))
                    for a in range(0, len(qi), 256):
                        part = s[a : a + 256]
                        here = (part > 0) & (part >= low) & (part < high)
                        r, c = np.nonzero(here)
                        if len(r):
                            l, m = qi[a + r], xi[c]
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), PAIR, np.int32)), pa.array(np.minimum(l, m)), pa.array(np.maximum(l, m)), pa.array(part[r, c])], PAIRS)
            if bins:
                made = counted
            kinds = np.full(len(made), BIN, np.int32) if bins else np.array(list(made), np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(kinds), pa.array(list(made.values()), pa.int64()), pa.array(list(made), pa.int64()), pa.array(np.zeros(len(made)))], PAIRS)

        met = q.join(x.hint("shuffle_replicate_nl"), F.col("q_at") >= F.col("x_at"))
        return met.select(*q.columns, *x.columns).mapInArrow(meet, "kind int, l long, r long, w double")

    def _weighed(self, found: DataFrame, least: float, below: float | None) -> DataFrame:
        pairs = found.where(F.col("kind") == PAIR).select("l", "r", F.round("w", 9).alias("w")).where(F.col("w") >= least)
        pairs = pairs if below is None else pairs.where(F.col("w") < below)
        return pairs if self.among is None else pairs.where(self.among)

    def _end_below(self, below: float | None) -> float:
        """A weight that about `ahead` budgets of pairs lie at or above, of those below a weight; 0 if all of them do."""
        runs = [self._meet(k, 0.0, below, True) for k in range(len(self.runs))]
        bins = reduce(DataFrame.union, runs).where(F.col("kind") == BIN).groupBy("r").agg(F.sum("l").alias("n")).orderBy(F.desc("r")).collect()
        return _edge([(float(np.int64(r["r"] << BIN_BITS).view(np.float64)), r["n"]) for r in bins], self.ahead * self.budget, below)

    def _bound(self) -> None:
        """Raises `end` where more than twice the pool's size is left, and lowers it where less than a budget is."""
        most, n = max(1, self.ahead * self.budget), self._pool().count()
        if n > 2 * most:
            level = F.floor(F.log2("w") * 32).alias("b")
            levels = self._pool().where("w > 0").groupBy(level).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("b")).collect()
            self.end = max(self.end, _edge([(2 ** (r["b"] / 32), r["n"]) for r in levels], most, None))
        while self.end > 0 and n < self.budget:
            below, self.end = self.end, self._end_below(self.end)
            for k, (_, parts, _) in enumerate(self.runs):
                # of the pairs that a raised `end` left out, some may still lie in a part
                parts[:] = [p.where(F.col("w") >= below) for p in parts] + [settle(self._weighed(self._meet(k, self.end, below), self.end, below), "pairs")]
            n = self._pool().count()

    def _pool(self) -> DataFrame:
        """(l, r, w) not yet emitted that weigh `end` and more."""
        return reduce(DataFrame.union, [_after(p, last) for _, parts, last in self.runs for p in parts]).where(F.col("w") >= self.end)

    def left(self) -> DataFrame | None:
        """(l, r, w) not yet emitted; None if nothing can be left."""
        if not self.runs:
            return None
        light = [_after(self._weighed(self._meet(k, 0.0, self.end), 0.0, self.end), last) for k, (_, _, last) in enumerate(self.runs)] if self.end > 0 else []
        return reduce(DataFrame.union, [self._pool(), *light])

    def rest(self) -> tuple[int, int]:
        """(pairs not yet emitted, how many of them are asked for): what flush() would emit, counted as the blocks met."""
        if not self.emitted:
            return 0, 0
        if self.among is not None:
            return self.left().count(), 0
        return self.n_met - self.n_emitted, self.n_asked - (self.schedule().join(self.asked, ["l", "r"], "left_semi").count() if self.asked is not None else 0)

    def _emit(self, budget: int | None) -> DataFrame:
        """The best `budget` pairs left, or all."""
        keyed = (self.left() if budget is None else self._pool()).withColumn("k", -F.col("w"))
        made = positioned(keyed, ["k", "l", "r"], limit=budget).select(F.lit(self.n).alias("batch"), "pos", "l", "r", "w")
        out = settle(made, "emitted")
        if last := out.orderBy(F.desc("pos")).select("w", "l", "r", "pos").first():
            self.n_emitted += last[3]
            key = tuple(last[:3])
            self.runs = [(df, parts, key if old is None else max(old, key, key=_place)) for df, parts, old in self.runs]
        self.emitted.append(out)
        self.n += 1
        return out

    def flush(self) -> DataFrame | None:
        """Everything not yet emitted, best first; no batch if nothing is left."""
        rest = self.left()
        return None if rest is None or rest.isEmpty() else self._emit(None)

    def schedule(self) -> DataFrame:
        """(batch, pos, l, r, w) of all batches."""
        out = self.emitted[0]
        for df in self.emitted[1:]:
            out = out.union(df)
        return out


BLOCK = ["at", "ids", "tokens", "rows", "weights", "asked_rows", "asked"]
PAIRS = ["kind", "l", "r", "w"]


def _after(pairs: DataFrame, last: tuple | None) -> DataFrame:
    return pairs if last is None else pairs.where(_behind(*last))


def _edge(bins: list[tuple[float, int]], most: int, below: float | None) -> float:
    """The weight at which the bins (least weight, pairs), from the heaviest, have `most` pairs below a weight; a multiple of
    STEP, 0 if they have fewer."""
    n = 0
    for edge, k in bins:
        if below is None or edge < below:
            n += k
            if n >= most:
                edge = round(float(np.floor(edge / STEP)) * STEP, 9)
                return edge if below is None or edge < below else 0.0
    return 0.0


def _place(key: tuple) -> tuple:
    return -key[0], key[1], key[2]


def _behind(w: float, l: int, r: int) -> Column:  # noqa: E741
    """Behind a pair in the order of emission."""
    return (F.col("w") < w) | ((F.col("w") == w) & ((F.col("l") > l) | ((F.col("l") == l) & (F.col("r") > r))))


def run_stream(spark: SparkSession, folder: str, schema: str, budget: int, files_per_batch: int = 1) -> Incremental:
    """Reads a growing folder of Parquet profiles (source, pid, text) to its present end, one batch after another, then the rest."""
    state = Incremental(spark, budget)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    checkpoint = os.path.join(shared_root(spark), f"progmatch/stream-{uuid.uuid4().hex}")
    query = stream.writeStream.foreachBatch(lambda df, _: state.add(df) and None).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    state.flush()
    return state


def windowed_counts(events: DataFrame, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """(window_start, window_end, event_type, n, total) of tumbling or sliding windows; with `late` as the watermark of a stream."""
    rows = events.withWatermark("ts", late) if late else events
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    made = rows.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return made.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """(user_id, session_start, session_end, n): a user's events less than `gap` apart."""
    rows = events.withWatermark("ts", late) if late else events
    made = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return made.select("user_id", F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "n")


def deduplicated(events: DataFrame, late: str) -> DataFrame:
    """First of each event_id within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def interval_join(left: DataFrame, right: DataFrame, key: str, seconds: int, late: str) -> DataFrame:
    """Pairs of two streams with equal keys, the right within `seconds` behind the left."""
    a = left.select(F.col(key), F.col("ts").alias("ts_l"), F.col("event_id").alias("event_l")).withWatermark("ts_l", late)
    b = right.select(F.col(key).alias("k_r"), F.col("ts").alias("ts_r"), F.col("event_id").alias("event_r")).withWatermark("ts_r", late)
    on = (F.col(key) == F.col("k_r")) & (F.col("ts_r") > F.col("ts_l")) & (F.col("ts_r") <= F.col("ts_l") + F.make_dt_interval(secs=F.lit(seconds)))
    return a.join(b, on).drop("k_r")


def running_best(events: DataFrame):
    """(user_id, n, best) after each batch: arbitrary state kept for each user by a Python function."""
    import pandas as pd

    def update(key, batches, state):
        n, best = state.get if state.exists else (0, 0.0)
        for b in batches:
            n, best = n + len(b), max(best, float(b["value"].max()))
        state.update((n, best))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "best": [best]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, best double", "n long, best double", "update", "NoTimeout")
