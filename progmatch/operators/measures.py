"""Measures: recall, progressive recall, distance from the best, filtering quality, significance."""

from __future__ import annotations

from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def hits(schedule: DataFrame, truth: DataFrame) -> DataFrame:
    """(pos): positions of true pairs."""
    return schedule.join(truth.select("l", "r"), ["l", "r"], "left_semi").select("pos")


def recall_table(schedule: DataFrame, truth: DataFrame, budgets: list[int], norm: str = "budget") -> DataFrame:
    """(budget, n_truth, found, recall, pr) for all budgets from one pass over the hits; null without truth.

    Progressive recall is the mean recall after 1 .. budget pairs, in closed form: a hit at p counts in budget - p + 1 of
    them. A schedule that ends early stays flat. norm ideal: over that of a perfect order.
    """
    if any(b < 0 for b in budgets):
        raise ValueError(f"negative budget: {budgets}")
    n = truth.count()
    spark = truth.sparkSession
    at = spark.createDataFrame([(b,) for b in sorted(set(budgets))], "budget long")
    found = hits(schedule, truth)
    sums = [(F.coalesce(F.sum((F.col("pos") <= b).cast("long")), F.lit(0)).alias(f"n{b}"), F.coalesce(F.sum(F.when(F.col("pos") <= b, b - F.col("pos") + 1)), F.lit(0)).alias(f"s{b}")) for b in sorted(set(budgets))]
    one = found.agg(*[c for pair in sums for c in pair])
    rows = one.select(F.explode(F.array(*[F.struct(F.lit(b).cast("long").alias("budget"), F.col(f"n{b}").alias("found"), F.col(f"s{b}").alias("area")) for b in sorted(set(budgets))])).alias("x")).select("x.*")
    area = F.col("area").cast("double") / F.lit(float(n)) if n else F.lit(None).cast("double")
    pr = F.try_divide(area, F.col("budget").cast("double"))
    if norm == "ideal" and n:
        most = F.least(F.col("budget"), F.lit(n))
        best = (most * F.col("budget") - most * (most - 1) / 2) / (F.lit(float(n)) * F.col("budget"))
        pr = F.try_divide(pr, best)
    recall = F.col("found") / F.lit(float(n)) if n else F.lit(None).cast("double")
    return at.join(rows, "budget").select("budget", F.lit(n).cast("long").alias("n_truth"), "found", recall.alias("recall"), pr.alias("pr"))


def recall_curve(schedule: DataFrame, truth: DataFrame) -> DataFrame:
    """(pos, recall) at each hit: a curve that is flat in between."""
    n = truth.count()
    found = hits(schedule, truth)
    return found.select("pos", (F.row_number().over(Window.orderBy("pos")) / F.lit(float(max(n, 1)))).alias("recall"))


def distance_from_top(results: DataFrame, measure: str = "pr", by: tuple[str, ...] = ("dataset", "budget")) -> DataFrame:
    """Adds dft: relative distance from the best of the group; null where the best is 0."""
    best = F.max(measure).over(Window.partitionBy(*by))
    return results.withColumn("dft", 1 - F.try_divide(F.col(measure), best))


def mean_dft(results: DataFrame, keys: tuple[str, ...] = ("family", "config", "scheduler")) -> DataFrame:
    """Mean distance over data sets and budgets; the least is the best configuration."""
    return results.groupBy(*keys).agg(F.avg("dft").alias("mean_dft"))


def best_configs(means: DataFrame, by: tuple[str, ...] = ("family", "scheduler")) -> DataFrame:
    return means.groupBy(*by).agg(F.min_by("config", F.struct("mean_dft", "config")).alias("config"), F.min("mean_dft").alias("mean_dft"))


def filtering_quality(edges: DataFrame, truth: DataFrame, cartesian: int) -> DataFrame:
    """(candidates, completeness, quality, reduction): recall and precision of the candidates, and what they save."""
    n = truth.count()
    found = edges.select("l", "r").join(truth.select("l", "r").withColumn("hit", F.lit(1)), ["l", "r"], "left")
    c = F.count(F.lit(1)).cast("double")
    h = F.coalesce(F.sum("hit"), F.lit(0)).cast("double")
    return found.agg(c.cast("long").alias("candidates"), F.try_divide(h, F.lit(float(n))).alias("completeness"), F.try_divide(h, c).alias("quality"), (1 - F.try_divide(c, F.lit(float(cartesian)))).alias("reduction"))


def schedule_overlap(a: DataFrame, b: DataFrame, n: int) -> DataFrame:
    """(overlap): share of the first n pairs that both schedules have."""
    x, y = (s.where(F.col("pos") <= n).select("l", "r") for s in (a, b))
    return x.join(y, ["l", "r"]).agg((F.count(F.lit(1)) / F.lit(float(max(n, 1)))).alias("overlap"))


def sign_counts(results: DataFrame, name: str, a: str, b: str, measure: str = "pr", keys: tuple[str, ...] = ("dataset", "budget")) -> DataFrame:
    """(up, down): on how many keys a (a value of column `name`) is above b, and below."""
    x, y = (results.where(F.col(name) == v).select(*keys, F.col(measure).alias(m)) for v, m in ((a, "x"), (b, "y")))
    count = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0)).cast("long")
    return x.join(y, list(keys)).agg(count(F.col("x") > F.col("y")).alias("up"), count(F.col("x") < F.col("y")).alias("down"))


def sign_test(results: DataFrame, name: str, a: str, b: str, measure: str = "pr", keys: tuple[str, ...] = ("dataset", "budget")) -> float:
    """Two-sided p-value that a and b (values of column `name`) are alike: the driver sees one row of counts."""
    up, down = sign_counts(results, name, a, b, measure, keys).first()
    n = up + down
    return min(1.0, 2 * sum(comb(n, k) for k in range(min(up, down) + 1)) / 2**n) if n else 1.0


def check_early(progressive: DataFrame, batch: DataFrame, truth: DataFrame, n: int) -> bool:
    """First requirement: more true pairs than the unordered run after n pairs."""
    early = lambda s: hits(s.where(F.col("pos") <= n), truth).count()
    return early(progressive) > early(batch)


def check_eventual(progressive: DataFrame, batch: DataFrame) -> bool:
    """Second requirement: the same pairs in the end."""
    a, b = progressive.select("l", "r"), batch.select("l", "r")
    return not a.exceptAll(b).limit(1).count() and not b.exceptAll(a).limit(1).count()
