"""Worked examples and identities: schedulers, block weights, sorted lists, measures, configurations."""

import pytest
from pyspark.sql import functions as F

from progmatch.operators import blocking, measures, sortedlist
from progmatch.operators.order import positioned
from progmatch.operators.schedule import SCHEDULERS, schedule, schedule_ideal
from progmatch.plans.config import BlockConfig, SortedConfig, all_pairs, from_json, grid, to_json
from progmatch.sources.profiles import Dedup, Linkage, to_profiles

LINK = [("a", "x", 0.9), ("a", "y", 0.1), ("b", "x", 0.6), ("b", "z", 0.5), ("c", "z", 0.8), ("c", "y", 0.7)]
ID = {c: i for i, c in enumerate("abcxyz", 1)}
NAME = {i: c for c, i in ID.items()}


def names(df):
    return " ".join(f"{NAME[r['l']]}-{NAME[r['r']]}" for r in df.orderBy("pos").collect())


def linkage_edges(spark):
    return spark.createDataFrame([(ID[a], ID[b], w) for a, b, w in LINK], "l long, r long, w double")


@pytest.mark.parametrize(
    "kind,order,pr",
    [("edge", "a-x c-z c-y b-x b-z a-y", 0.75), ("depth", "c-z c-y b-x b-z a-x a-y", 0.5), ("breadth", "c-z b-x a-x c-y b-z a-y", 0.75), ("hybrid", "a-x c-z b-x c-y b-z a-y", 0.833333)],
)
def test_linkage_orders(spark, kind, order, pr):
    made = schedule(linkage_edges(spark), kind, 6, linkage=True)
    assert names(made) == order
    truth = spark.createDataFrame([(ID["a"], ID["x"]), (ID["b"], ID["x"])], "l long, r long")
    assert measures.recall_table(made, truth, [6]).first()["pr"] == pytest.approx(pr, abs=1e-5)


@pytest.mark.parametrize("kind,order", [("edge", "1-2 3-4 2-3 1-3"), ("depth", "3-4 1-2 2-3 1-3"), ("breadth", "3-4 1-2 2-3 1-3"), ("hybrid", "1-2 3-4 2-3 1-3")])
def test_dedup_orders(spark, kind, order):
    edges = spark.createDataFrame([(1, 2, 0.9), (1, 3, 0.4), (2, 3, 0.6), (3, 4, 0.8)], "l long, r long, w double")
    got = " ".join(f"{r['l']}-{r['r']}" for r in schedule(edges, kind, 4).orderBy("pos").collect())
    assert got == order


def test_budget_and_pruning(spark):
    rows = [(i, j, ((i * 7 + j * 13) % 97 + 1) / 100) for i in range(25) for j in range(i + 1, 25) if (i * j) % 3]
    edges = spark.createDataFrame(rows, "l long, r long, w double")
    for kind in SCHEDULERS:
        for budget in (0, 1, 17, 10_000):
            a = schedule(edges, kind, budget).orderBy("pos").collect()
            b = schedule(edges, kind, budget, prune=False).orderBy("pos").collect()
            assert a == b and len(a) == min(budget, len(rows))
    with pytest.raises(ValueError):
        schedule(edges, "edge", -1)


def test_positions_without_one_task(spark):
    df = spark.range(1000).select((F.col("id") * 37 % 1000).alias("k"), "id")
    big = positioned(df, ["k", "id"], ranges=7).collect()
    assert sorted(r["pos"] for r in big) == list(range(1, 1001))
    assert all(r["pos"] == r["k"] + 1 for r in big)


def test_block_weights_of_the_example(spark):
    left = spark.createDataFrame([(1, "alpha beta"), (2, "gamma delta shared")], "pid long, text string")
    right = spark.createDataFrame([(4, "alpha beta"), (5, "shared"), (7, "gamma delta shared")], "pid long, text string")
    task = Linkage(to_profiles(left, "pid", ["text"]), to_profiles(right, "pid", ["text"], "R"))
    blocks, stats = blocking.refined(task, "none", None)
    got = {(r["l"], r["r"]): r for r in blocking.block_grid(blocking.block_graph(blocks, stats, True), blocks, stats, True).collect()}
    assert (got[1, 4]["cb"], got[1, 4]["cn_cb"], got[1, 4]["sn_cb"]) == (2, 2, 1)
    assert got[2, 7]["cb"] == 3 and got[2, 7]["cn_cb"] == 2.5 and got[2, 7]["sn_cb"] == pytest.approx(4 / 3)
    assert got[2, 5]["cosine"] == pytest.approx(0.57735, abs=1e-5) and got[2, 5]["jaccard"] == pytest.approx(1 / 3) and got[2, 5]["cn_cb"] == 0.5


def test_block_split_gives_the_same_graph(spark):
    df = spark.createDataFrame([(i, f"common w{i % 5} v{i % 3}") for i in range(60)], "pid long, text string")
    task = Dedup(to_profiles(df, "pid", ["text"]))
    blocks, stats = blocking.refined(task, "none", None)
    whole = blocking.block_graph(blocks, stats, False)
    split = blocking.block_graph(blocks, stats, False, limit=7)
    r = lambda d: sorted((x["l"], x["r"], x["cb"], round(x["cn"], 9)) for x in d.collect())
    assert r(whole) == r(split)


def test_sorted_list_example(spark):
    listed = spark.createDataFrame([(1, "L", 1), (2, "L", 2), (3, "L", 1), (4, "L", 3), (5, "L", 2)], "pos long, source string, pid long")
    for bucket in (2, 3, 100):
        h = sortedlist.pair_histogram(sortedlist.window_pairs(listed, 2, False, bucket=bucket), 2)
        h = sortedlist.with_positions(h, sortedlist.list_nodes(listed), False)
        got = {(r["l"], r["r"]): r for r in h.select("l", "r", "h", *[sortedlist.sorted_weight(w, s, 2).alias(f"{w}_{s}") for w in sortedlist.SORTED_WEIGHTS for s in sortedlist.SCOPES]).collect()}
        ab, ac, bc = got[1, 2], got[1, 3], got[2, 3]
        assert (ab["h"], ac["h"], bc["h"]) == ([2, 1], [1, 0], [1, 1])
        assert (ab["acf_local"], ab["acf_global"], ab["id_local"], ab["id_global"]) == (3, 5, 2.5, 4.5)
        assert (ab["ncf_local"], ab["ncf_global"], ab["dncf_local"], ab["cncf_local"]) == (3, 4, 1.5, 1.5)
        assert ac["dncf_local"] == pytest.approx(0.6667, abs=1e-4) and bc["cncf_local"] == pytest.approx(1.4142, abs=1e-4)


def test_measures_without_truth_and_ideal_order(spark):
    edges = linkage_edges(spark)
    none = spark.createDataFrame([], "l long, r long")
    row = measures.recall_table(schedule(edges, "edge", 6, True), none, [6]).first()
    assert row["recall"] is None and row["pr"] is None
    truth = spark.createDataFrame([(ID["a"], ID["y"])], "l long, r long")
    ideal = measures.recall_table(schedule_ideal(edges, truth, 6), truth, [6], "ideal").first()
    assert ideal["pr"] == pytest.approx(1)
    assert measures.check_eventual(schedule(edges, "depth", 6, True), schedule(edges, "edge", 6, True))


def test_grids_and_configs():
    assert [len(grid(f)) for f in ("sparse", "block", "sorted")] == [270, 14, 100] and len(grid("sparse", False)) == 90
    assert len(grid("dense")) == 90  # five stand-ins for ten encoders
    for c in (BlockConfig("cb"), SortedConfig("acf", 3)):
        assert from_json(to_json(c)) == c


def test_edges_of_the_input(spark):
    empty = Dedup(to_profiles(spark.createDataFrame([], "id long, t string"), "id"))
    assert blocking.block_candidates(empty).count() == 0
    assert sortedlist.sorted_candidates(empty).count() == 0
    odd = Dedup(to_profiles(spark.createDataFrame([(1, None), (2, ""), (3, "one"), (4, "one")], "id long, t string"), "id"))
    assert [(r["l"], r["r"]) for r in blocking.block_candidates(odd, purge="none").collect()] == [(3, 4)]
    assert all_pairs(odd).count() == 6
    with pytest.raises(ValueError):
        all_pairs(odd, most_pairs=5)
    with pytest.raises(ValueError):
        Dedup(to_profiles(spark.createDataFrame([(1, "a"), (1, "b")], "id long, t string"), "id")).checked()
