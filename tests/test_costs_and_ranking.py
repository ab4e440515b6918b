"""Bounds before ranking, plain weights, series of sources, significance, costs, SQL functions."""

from math import comb

import numpy as np
import pytest
from pyspark.sql import functions as F

from progmatch.functions.text import register_sql
from progmatch.operators import costs, measures, sortedlist, sparse
from progmatch.operators.matching import oracle
from progmatch.operators.pairs import meet, meet_evenly
from progmatch.plans.config import BlockConfig, resolve_series
from progmatch.sources.profiles import Dedup, Linkage, to_profiles


@pytest.mark.parametrize("linkage", [True, False])
@pytest.mark.parametrize("k", [1, 3])
def test_nearest_is_brute_force(spark, linkage, k):
    rng = np.random.default_rng(k)
    pairs = [(i, j, float(rng.integers(1, 6)) / 8) for i in range(14) for j in range(11) if (linkage or i < j) and rng.random() < 0.6]
    df = spark.createDataFrame(pairs, "l long, r long, w double")
    got = {(r["l"], r["r"]): r["w"] for r in sparse.nearest(df, k, linkage, "both", {"L": 14, "R": 11}).collect()}
    lists = {}
    for l, r, w in pairs:  # noqa: E741
        lists.setdefault(("l", l) if linkage else l, []).append((-w, r, (l, r)))
        lists.setdefault(("r", r) if linkage else r, []).append((-w, l, (l, r)))
    want = {p: -w for some in lists.values() for w, _, p in sorted(some)[:k]}
    assert got == want


def test_plain_weights_are_those_of_the_histogram(spark):
    texts = ["a b c d", "b c a", "c d e a b", "e f g a", "a a b", "g f e d"]
    df = to_profiles(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "id")
    for task in (Dedup(df), Linkage(df.where("pid % 2 = 0"), df.where("pid % 2 = 1"))):
        listed = sortedlist.sorted_list(task)
        h = sortedlist.histogram_of(listed, 4, task.linkage)
        for weight in sortedlist.PLAIN_WEIGHTS:
            for scope in sortedlist.SCOPES:
                want = {(r["l"], r["r"]): r["w"] for r in h.select("l", "r", F.round(sortedlist.sorted_weight(weight, scope, 4), 9).alias("w")).collect()}
                got = {(r["l"], r["r"]): r["w"] for r in sortedlist.plain_weights(listed, weight, scope, 4, task.linkage).collect()}
                assert got == pytest.approx(want)


def test_meeting_evenly_is_meeting(spark):
    rows = spark.createDataFrame([("L" if i % 3 else "R", i, f"k{i % 4}") for i in range(60)], "source string, pid long, key string")
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    for linkage in (True, False):
        want = sorted(meet(rows, "key", linkage, [], []).collect())
        assert want and sorted(meet_evenly(rows, "key", sizes, linkage, [], [], limit=4).collect()) == want


def test_series_of_sources(spark):
    texts = {0: "red fox", 1: "blue whale song", 10: "red fox runs", 11: "green tree", 20: "runs fast fox", 21: "tree green tall"}
    df = spark.createDataFrame([(str(i // 10), i, t) for i, t in texts.items()], "source string, pid long, text string")
    truth = spark.createDataFrame([(0, 10), (0, 20), (11, 21)], "l long, r long")
    links = resolve_series(df, BlockConfig("cb", purge="none", ratio=None), lambda order, _: oracle(truth)(order), 100)
    assert {tuple(r) for r in links.collect()} == {(0, 10, 1), (0, 20, 2), (11, 21, 2)}
    assert resolve_series(df.where("source = '0'"), BlockConfig("cb"), lambda order, _: oracle(truth)(order), 5).count() == 0


def test_significance(spark):
    rows = [("d", b, c, pr) for b in range(10) for c, pr in (("a", 0.5 + 0.1 * (b > 1)), ("b", 0.55))]
    df = spark.createDataFrame(rows, "dataset string, budget int, config string, pr double")
    assert tuple(measures.sign_counts(df, "config", "a", "b").first()) == (8, 2)
    assert measures.sign_test(df, "config", "a", "b") == pytest.approx(2 * sum(comb(10, k) for k in range(3)) / 2**10)
    assert measures.sign_test(df.limit(0), "config", "a", "b") == 1.0


def test_requirements(spark):
    edges = spark.createDataFrame([(1, 2, 0.9), (1, 3, 0.1), (2, 3, 0.2)], "l long, r long, w double")
    ordered, other = (edges.withColumn("pos", F.lit(1) + F.col(c)) for c in ("l", "r"))
    assert measures.check_eventual(ordered, other) and not measures.check_eventual(ordered, other.where("r < 3"))
    truth = spark.createDataFrame([(1, 2)], "l long, r long")
    assert measures.check_early(edges.where("w > 0.5").withColumn("pos", F.lit(1)), edges.where("w < 0.15").withColumn("pos", F.lit(1)), truth, 1)


def test_costs(spark):
    df = spark.range(20_000).withColumn("k", F.col("id") % 101).groupBy("k").count().repartition(3, "k")
    cost = costs.memory_probe(spark, lambda: costs.timed(df))
    assert cost.seconds > 0 and cost.shuffle_bytes > 0 and cost.spill_bytes == 0
    assert costs.timed(df) > 0


def test_sql_grams(spark):
    register_sql(spark)
    row = spark.sql("SELECT word_ngrams('The red fox', 2), word_ngrams('one', 2), word_ngrams(NULL, 1), char_ngrams('Ab, c', 3), char_ngrams('ab', 3), char_ngrams('', 3)").first()
    assert list(row) == [["the red", "red fox"], ["one"], [], ["ab ", "b c"], ["ab"], []]
    long = spark.range(1).select(F.repeat(F.lit("word "), 40_000).alias("t"))
    long.createOrReplaceTempView("long_text")
    assert spark.sql("SELECT size(char_ngrams(t, 4)), size(word_ngrams(t, 2)) FROM long_text").first() == (199_999 - 3, 39_999)
