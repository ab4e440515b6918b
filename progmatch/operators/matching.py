"""The matching hook: decisions on scheduled pairs, in order, until a budget of pairs or seconds ends."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from progmatch.session import settle

Matcher = Callable[[DataFrame], DataFrame]  # (pos, l, r, w) -> the same, is_match and score


@dataclass(frozen=True)
class Budget:
    """pairs, or multiple of the number of true pairs; seconds on top of either."""

    pairs: int | None = None
    multiple: float | None = None
    seconds: float | None = None

    def of(self, n_truth: int | None = None) -> int:
        if self.pairs is not None:
            n = self.pairs
        elif self.multiple is not None and n_truth is not None:
            n = int(self.multiple * n_truth)
        else:
            raise ValueError("a budget needs pairs, or a multiple and the number of true pairs")
        if n < 0:
            raise ValueError(f"negative budget: {n}")
        return n


def oracle(truth: DataFrame) -> Matcher:
    """Perfect decisions."""
    known = truth.select("l", "r").withColumn("__hit", F.lit(True))
    return lambda s: s.join(known, ["l", "r"], "left").withColumn("is_match", F.coalesce("__hit", F.lit(False))).withColumn("score", F.col("is_match").cast("double")).drop("__hit")


def threshold(score: Column, least: float) -> Matcher:
    return lambda s: s.withColumn("score", score).withColumn("is_match", F.col("score") >= least)


def on_texts(left: DataFrame, right: DataFrame, score: Callable[[Column, Column], Column], least: float) -> Matcher:
    """Compares the texts of both profiles (pid, text), for instance by a pandas UDF."""

    def run(s: DataFrame) -> DataFrame:
        both = s.join(left.select(F.col("pid").alias("l"), F.col("text").alias("__a")), "l").join(right.select(F.col("pid").alias("r"), F.col("text").alias("__b")), "r")
        return both.withColumn("score", score(F.col("__a"), F.col("__b"))).withColumn("is_match", F.col("score") >= least).drop("__a", "__b")

    return run


def emit(schedule: DataFrame, size: int) -> Iterator[DataFrame]:
    """The schedule in chunks of positions; each is a filter that a table kept by position prunes."""
    last = schedule.agg(F.max("pos")).first()[0] or 0
    for start in range(0, last, size):
        yield schedule.where((F.col("pos") > start) & (F.col("pos") <= start + size))


def run_matching(schedule: DataFrame, matcher: Matcher, chunk: int = 10_000, seconds: float | None = None) -> DataFrame:
    """(pos, l, r, w, is_match, score) of the pairs verified: all, or chunk by chunk until the seconds are over."""
    if seconds is None:
        return matcher(schedule)
    began, done = time.monotonic(), None
    schedule = settle(schedule, "schedule")
    for part in emit(schedule, chunk):
        made = settle(matcher(part), "verified")
        done = made if done is None else done.unionByName(made)
        if time.monotonic() - began >= seconds:
            break
    return done if done is not None else matcher(schedule.limit(0))


def connected_components(matches: DataFrame) -> DataFrame:
    """(pid, cluster): least id of the component; labels fall along edges, settled each round."""
    edges = matches.select(F.col("l").alias("a"), F.col("r").alias("b"))
    both = settle(edges.union(edges.select("b", "a")).distinct(), "edges")
    labels = settle(both.groupBy("a").agg(F.least("a", F.min("b")).alias("c")), "labels")
    while True:
        near = both.join(labels.withColumnRenamed("a", "b"), "b").groupBy("a").agg(F.min("c").alias("m"))
        fallen = labels.join(near, "a").select("a", F.least("c", "m").alias("c"), (F.col("m") < F.col("c")).alias("moved"))
        # a label's own label: halves the way to the root
        jump = fallen.select(F.col("a").alias("c"), F.col("c").alias("d"))
        fallen = settle(fallen.join(jump, "c", "left").select("a", F.least("c", F.coalesce("d", "c")).alias("c"), "moved"), "labels")
        labels = fallen.select("a", "c")
        if not fallen.where("moved").limit(1).count():
            return labels.select(F.col("a").alias("pid"), F.col("c").alias("cluster"))
