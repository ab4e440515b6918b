"""Configurations, the pipeline that runs them, the parameter grid and the tuner."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import asdict, dataclass, field
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.operators import blocking, dense, encoders, measures, sortedlist, sparse
from progmatch.operators.matching import Budget, Matcher, run_matching
from progmatch.operators.schedule import SCHEDULERS, node_score, schedule
from progmatch.session import settle
from progmatch.sources.profiles import Linkage, MultiSource, Task


#: A configuration's pairs are ranked in so many lots first.
LOTS = 32


@dataclass(frozen=True)
class DenseConfig:
    encoder: str = "hash-words"
    sim: str = "cosine"
    k: int = 5
    index: str = "both"
    engine: str = "exact"
    cells: int = 16
    probes: int = 4
    family: str = field(default="dense", init=False)

    def candidates(self, task: Task) -> DataFrame:
        options = {"cells": self.cells, "probes": self.probes} if self.engine == "cells" else {}
        return dense.dense_candidates(encoders.encode(task, self.encoder), task.kind, self.sim, self.k, self.index, self.engine, **options)


@dataclass(frozen=True)
class SparseConfig:
    tokenizer: str = "word1"
    scoring: str = "tfidf"
    sim: str = "cosine"
    k: int = 5
    index: str = "both"
    max_df: int | None = None
    family: str = field(default="sparse", init=False)

    def candidates(self, task: Task) -> DataFrame:
        return sparse.sparse_candidates(task, self.tokenizer, self.scoring, self.sim, self.k, self.index, self.max_df)


@dataclass(frozen=True)
class BlockConfig:
    weight: str = "cn_cb"
    purge: str = "size"
    ratio: float | None = 0.8
    max_block_size: int | None = None
    family: str = field(default="block", init=False)

    def candidates(self, task: Task) -> DataFrame:
        return blocking.block_candidates(task, self.weight, self.purge, self.ratio, self.max_block_size)


@dataclass(frozen=True)
class SortedConfig:
    weight: str = "id"
    window: int = 10
    scope: str = "global"
    strict: bool = False
    seed: int = 0
    family: str = field(default="sorted", init=False)

    def candidates(self, task: Task) -> DataFrame:
        return sortedlist.sorted_candidates(task, self.weight, self.window, self.scope, self.strict, self.seed)


@dataclass(frozen=True)
class ScheduleConfig:
    kind: str = "edge"
    anchor: str = "left"


CONFIGS = {"dense": DenseConfig, "sparse": SparseConfig, "block": BlockConfig, "sorted": SortedConfig}


def to_json(config) -> str:
    return json.dumps(asdict(config), sort_keys=True)


def from_json(text: str):
    values = json.loads(text)
    return CONFIGS[values.pop("family")](**values)


#: The best configuration of each family under each scheduler, as published; encoders are stand-ins.
BEST = {
    ("dense", "edge"): DenseConfig("sent", "euclid", 5, "largest"),
    ("dense", "breadth"): DenseConfig("sent", "euclid", 5, "both"),
    ("dense", "depth"): DenseConfig("sent", "cosine", 1, "both"),
    ("dense", "hybrid"): DenseConfig("sent", "euclid", 5, "both"),
    ("sparse", "edge"): SparseConfig("word1", "tfidf", "cosine", 10, "largest"),
    ("sparse", "breadth"): SparseConfig("char5", "tfidf", "euclid", 5, "both"),
    ("sparse", "depth"): SparseConfig("word1", "tfidf", "cosine", 1, "both"),
    ("sparse", "hybrid"): SparseConfig("char5", "tfidf", "euclid", 5, "both"),
    ("block", "edge"): BlockConfig("cn_cb"),
    ("block", "breadth"): BlockConfig("cb"),
    ("block", "depth"): BlockConfig("sn_cb"),
    ("block", "hybrid"): BlockConfig("cb"),
    ("sorted", "edge"): SortedConfig("id", 10, "global"),
    ("sorted", "breadth"): SortedConfig("acf", 10, "global"),
    ("sorted", "depth"): SortedConfig("dncf", 1, "global"),
    ("sorted", "hybrid"): SortedConfig("acf", 10, "global"),
}
#: The family winners.
WINNERS = {"dense": "breadth", "sparse": "breadth", "block": "edge", "sorted": "edge"}


def best(family: str, scheduler: str):
    return BEST[family, scheduler]


def grid(family: str, linkage: bool = True) -> list:
    """Every configuration of a family: 180, 270, 14 and 100 for linkage; dedup has no index axis."""
    sides, ks = (sparse.SIDES if linkage else ("both",)), (1, 5, 10)
    if family == "dense":
        slots = ["hash-words", "hash-chars", "word2vec", "ctx", "sent"]
        return [DenseConfig(e, s, k, i) for i, s, k, e in product(sides, sparse.SIMILARITIES, ks, slots)]
    if family == "sparse":
        return [SparseConfig(t, c, s, k, i) for i, s, k, c, t in product(sides, sparse.SIMILARITIES, ks, sparse.SCORINGS, ("word1", "word2", "char3", "char4", "char5"))]
    if family == "block":
        return [BlockConfig(w) for w in blocking.BLOCK_WEIGHTS]
    if family == "sorted":
        return [SortedConfig(x, w, s) for w, x, s in product(range(1, 11), sortedlist.SORTED_WEIGHTS, sortedlist.SCOPES)]
    raise ValueError(f"unknown family: {family}")


def candidates(task: Task | MultiSource, config) -> DataFrame:
    return task.edges(config.candidates) if isinstance(task, MultiSource) else config.candidates(task)


@dataclass(frozen=True)
class Pipeline:
    """Filter and weight by `config`, schedule, then match."""

    config: object
    scheduler: ScheduleConfig = ScheduleConfig()

    def ordered(self, task: Task | MultiSource, budget: int) -> DataFrame:
        linkage = isinstance(task, Task) and task.linkage
        return schedule(candidates(task, self.config), self.scheduler.kind, budget, linkage, self.scheduler.anchor)

    def run(self, task: Task | MultiSource, budget: Budget, matcher: Matcher, n_truth: int | None = None) -> DataFrame:
        return run_matching(self.ordered(task, budget.of(n_truth)), matcher, seconds=budget.seconds)


def batch_resolve(task: Task, config, matcher: Matcher) -> DataFrame:
    """Filter, then verify every candidate, in no order."""
    edges = candidates(task, config)
    return matcher(edges.withColumn("pos", F.lit(None).cast("long")).select("pos", "l", "r", "w"))


def resolve_series(profiles: DataFrame, config, matcher: Callable[[DataFrame, Task], DataFrame], budget: int, scheduler: str = "edge") -> DataFrame:
    """(l, r, step): links of more than two sources, one source after another in the order of their names.

    Each step links what is known so far with the next source. A record of it that matches adds its text to the record it
    matches; the others join what is known. pids are unique over all sources; matcher decides on (pos, l, r, w) of a task.
    """
    names = sorted(r[0] for r in profiles.select("source").distinct().collect())
    of = lambda s: profiles.where(F.col("source") == s).select("pid", "text")
    known, parts = of(names[0]), []
    for step, name in enumerate(names[1:], 1):
        task = Linkage(known, of(name))
        order = schedule(candidates(task, config), scheduler, budget, True)
        found = matcher(order, task).where("is_match").groupBy("r").agg(F.min_by("l", "pos").alias("l"))
        links = settle(found.select("l", "r", F.lit(step).alias("step")), "links")
        own = known.withColumn("at", F.lit(0)).unionByName(of(name).join(links.select(F.col("r").alias("pid"), "l"), "pid", "left").select(F.coalesce("l", "pid").alias("pid"), "text", F.lit(1).alias("at")))
        texts = F.transform(F.sort_array(F.collect_list(F.struct("at", "text"))), lambda x: x["text"])
        known = settle(own.groupBy("pid").agg(F.array_join(texts, " ").alias("text")), "merged")
        parts.append(links)
    return reduce(DataFrame.unionByName, parts) if parts else profiles.select(F.col("pid").alias("l"), F.col("pid").alias("r"), F.lit(0).alias("step")).limit(0)


#: Pairs that one task of all_pairs looks at.
PAIRS_OF_A_TASK = 50_000_000


def all_pairs(task: Task, most_pairs: int | None = 10_000_000) -> DataFrame:
    """Every pair, in tasks of equal size; refused beyond most_pairs, None for any number."""
    sizes = task.sizes()
    n = sum(sizes.values())
    pairs = sizes.get("L", 0) * sizes.get("R", 0) if task.linkage else n * (n - 1) // 2
    if most_pairs is not None and pairs > most_pairs:
        raise ValueError(f"{pairs} pairs are more than {most_pairs}")
    a = task.profiles.where("source = 'L'") if task.linkage else task.profiles
    b = task.profiles.where("source = 'R'") if task.linkage else task.profiles
    tasks = max(1, -(-pairs * (1 if task.linkage else 2) // PAIRS_OF_A_TASK))
    both = a.select(F.col("pid").alias("l")).repartition(tasks).crossJoin(b.select(F.col("pid").alias("r")))
    return both if task.linkage else both.where("l < r")


def evaluate(dataset: str, family: str, name: str, edges: DataFrame, truth: DataFrame, budgets: list[int], linkage: bool, schedulers: tuple[str, ...] = SCHEDULERS) -> DataFrame:
    """(dataset, family, config, scheduler, budget, n_truth, found, recall, pr): one schedule to the largest budget serves all."""
    return reduce(DataFrame.unionByName, [evaluate_order(dataset, family, name, kind, schedule(edges, kind, max(budgets), linkage), truth, budgets) for kind in schedulers])


def evaluate_order(dataset: str, family: str, name: str, kind: str, order: DataFrame, truth: DataFrame, budgets: list[int]) -> DataFrame:
    """What evaluate gives for an order that is there."""
    rows = measures.recall_table(order, truth, budgets)
    return rows.select(F.lit(dataset).alias("dataset"), F.lit(family).alias("family"), F.lit(name).alias("config"), F.lit(kind).alias("scheduler"), *rows.columns)


def evaluate_stack(stacked: DataFrame, truth: DataFrame, budgets: list[int], linkage: bool, kind: str = "edge", anchor: str = "left") -> DataFrame:
    """(config, scheduler, budget, found, recall, pr) of many configurations at once. stacked: (config, l, r, w).

    Windows rank every configuration's pairs in lots and then the first of all lots, cut at the largest budget, and one aggregation of the hits
    serves all budgets: the cost of a grid is that of one run, not one plan for each configuration.
    """
    if kind not in SCHEDULERS:
        raise ValueError(f"unknown scheduler of stacks: {kind}")
    n, most = truth.count(), max(budgets)
    edges = stacked.where("w > 0")
    if kind == "edge":
        order = [F.desc("w"), F.col("l"), F.col("r")]
    else:
        end = lambda node, other: F.struct(F.col(node).alias("node"), F.col(other).alias("other"))
        sides = [end("l", "r"), end("r", "l")] if not linkage else [end("l", "r")] if anchor == "left" else [end("r", "l")]
        own = Window.partitionBy("config", "node")
        ends = edges.select("config", "l", "r", "w", F.explode(F.array(*sides)).alias("e")).select("config", "l", "r", "w", "e.*")
        ends = ends.withColumn("t", F.row_number().over(own.orderBy(F.desc("w"), "other"))).withColumn("s", node_score(F.avg("w").over(own)))
        keys = ("t", "s", "node") if kind == "breadth" else ("s", "node", "t")
        edges = ends.groupBy("config", "l", "r").agg(F.first("w").alias("w"), F.min("t").alias("best"), F.min(F.struct(*keys)).alias("k"))
        order = [F.col(f"k.{k}") for k in keys]
        if kind == "hybrid":
            first = F.col("best") == 1
            order = [F.when(first, 1).otherwise(2), F.when(first, -F.col("w")).otherwise(F.col("k.s")), F.when(first, F.col("l")).otherwise(F.col("k.node")), F.when(first, F.col("r")).otherwise(F.col("k.t").cast("long"))]
        order += [F.col("l"), F.col("r")]
    # what is not among the first of its lot is not among the first of its configuration, so no task ranks all pairs of one
    lot = F.pmod(F.xxhash64("l", "r"), F.lit(LOTS))
    first = edges.withColumn("pos", F.row_number().over(Window.partitionBy("config", lot).orderBy(*order))).where(F.col("pos") <= most)
    placed = first.withColumn("pos", F.row_number().over(Window.partitionBy("config").orderBy(*order))).where(F.col("pos") <= most)
    names = stacked.select("config").distinct()
    found = placed.join(truth.select("l", "r"), ["l", "r"], "left_semi").select("config", "pos")
    asked = names.withColumn("budget", F.explode(F.array(*[F.lit(b).cast("long") for b in sorted(set(budgets))])))
    hit = asked.join(found, "config", "left").withColumn("pos", F.when(F.col("pos") <= F.col("budget"), F.col("pos")))
    sums = hit.groupBy("config", "budget").agg(F.count("pos").alias("found"), F.coalesce(F.sum(F.col("budget") - F.col("pos") + 1), F.lit(0)).alias("area"))
    whole = F.lit(float(n)) if n else F.lit(None).cast("double")
    return sums.select("config", F.lit(kind).alias("scheduler"), "budget", "found", (F.col("found") / whole).alias("recall"), F.try_divide(F.col("area") / whole, F.col("budget").cast("double")).alias("pr"))


def tune(dataset: str, task: Task, configs: list, truth: DataFrame, budgets: list[int], schedulers: tuple[str, ...] = SCHEDULERS) -> DataFrame:
    """(family, config, scheduler, mean_dft), the least first. A driver loop over configurations; each one's edges are settled once."""
    parts = [evaluate(dataset, c.family, to_json(c), settle(candidates(task, c), "edges"), truth, budgets, task.linkage, schedulers) for c in configs]
    results = measures.distance_from_top(settle(reduce(DataFrame.unionByName, parts), "results"), by=("dataset", "budget", "family"))
    return measures.mean_dft(results).orderBy("mean_dft", "config", "scheduler")
