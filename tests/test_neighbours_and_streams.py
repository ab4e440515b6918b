"""Nearest neighbours against brute force, baselines, matching, sources and streams."""

import json
import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from progmatch.operators import dense, sparse
from progmatch.operators.matching import connected_components, oracle, run_matching, threshold
from progmatch.operators.schedule import schedule
from progmatch.sources import jsonl
from progmatch.sources.profiles import Dedup, MultiSource, Task, to_profiles
from progmatch.streaming.incremental import Incremental, interval_join, run_stream, running_best

TEXTS = ["red green blue", "red green", "blue sky over green hills", "sky over hills", "nothing alike", "red red green"]


def profiles(spark, texts=TEXTS):
    return to_profiles(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "id")


def test_sparse_is_brute_force(spark):
    task = Dedup(profiles(spark))
    got = {(r["l"], r["r"]): r["w"] for r in sparse.sparse_candidates(task, "word1", "tfidf", "cosine", 10).collect()}
    docs = [Counter(t.split()) for t in TEXTS]
    df = Counter(w for d in docs for w in d)
    vec = [{w: c / max(d.values()) * math.log(len(docs) / df[w]) for w, c in d.items()} for d in docs]
    for i in range(len(docs)):
        for j in range(i + 1, len(docs)):
            dot = sum(v * vec[j].get(w, 0) for w, v in vec[i].items())
            if dot > 0:
                want = dot / math.sqrt(sum(v * v for v in vec[i].values()) * sum(v * v for v in vec[j].values()))
                assert got.pop((i, j)) == pytest.approx(want, abs=1e-8)
    assert not got


def test_dense_engines(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(120, 8))
    rows = [("L", i, x[i].tolist()) for i in range(120)] + [("R", i, (x[i] + rng.normal(size=8) * 0.05).tolist()) for i in range(120)]
    df = spark.createDataFrame(rows, "source string, pid long, vec array<double>")
    exact = dense.dense_candidates(df, "linkage", "cosine", 3, "largest", block=50)
    a, b = np.array([r[2] for r in rows[:120]]), np.array([r[2] for r in rows[120:]])
    s = (a / np.linalg.norm(a, axis=1)[:, None]) @ (b / np.linalg.norm(b, axis=1)[:, None]).T
    want = {(i, int(j)) for i in range(120) for j in np.argsort(-s[i])[:3] if s[i, j] > 0}
    assert {(r["l"], r["r"]) for r in exact.collect()} == want
    cells = dense.dense_candidates(df, "linkage", "cosine", 3, "largest", "cells", cells=8, probes=6)
    assert dense.index_recall(cells, exact).first()["recall"] >= 0.9
    lsh = dense.dense_candidates(df, "linkage", "cosine", 1, "largest", "lsh", bands=24, bits=4)
    assert dense.index_recall(lsh, dense.dense_candidates(df, "linkage", "cosine", 1, "largest")).first()["recall"] >= 0.9
    with pytest.raises(ValueError):
        dense.dense_candidates(df, "linkage", k=0)


def test_multi_source_strategies(spark):
    p = profiles(spark, ["a b", "a b", "a b c"]).withColumn("source", F.col("pid").cast("string"))
    many = lambda t: sparse.sparse_candidates(t, "word1", "bool", "cosine", 5, "both")
    one = {(r["l"], r["r"]) for r in MultiSource(p, "single").edges(many).collect()}
    assert one == {(0, 1), (0, 2), (1, 2)}
    assert len(MultiSource(p, "series").tasks()) == 3


def test_matching(spark):
    edges = spark.createDataFrame([(1, 2, 0.9), (2, 3, 0.8), (4, 5, 0.7), (6, 7, 0.1)], "l long, r long, w double")
    order = schedule(edges, "edge", 10)
    truth = spark.createDataFrame([(1, 2), (2, 3), (4, 5)], "l long, r long")
    found = run_matching(order, oracle(truth))
    assert found.where("is_match").count() == 3
    assert run_matching(order, threshold(F.col("w"), 0.75), chunk=2, seconds=60).where("is_match").count() == 2
    groups = {r["pid"]: r["cluster"] for r in connected_components(found.where("is_match")).collect()}
    assert groups == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4}


def test_json_lines(spark, tmp_path):
    (tmp_path / "a.jsonl").write_text("\n".join(json.dumps(r) for r in ({"id": 1, "name": "x", "tags": ["p", "q"]}, {"id": 2, "name": None, "more": {"k": "v"}})))
    jsonl.register(spark)
    got = {r["pid"]: r["text"] for r in spark.read.format("profile_lines").option("path", str(tmp_path)).load().collect()}
    assert got == {1: "x p q", 2: "v"}


def test_incremental_reaches_the_batch(spark, tmp_path):
    p = profiles(spark)
    for i in range(3):
        p.where(F.col("pid") % 3 == i).coalesce(1).write.parquet(str(tmp_path / f"in{i}"))
        for f in (tmp_path / f"in{i}").glob("*.parquet"):
            (tmp_path / "all").mkdir(exist_ok=True)
            f.rename(tmp_path / "all" / f"{i}-{f.name}")
    state = run_stream(spark, str(tmp_path / "all"), "source string, pid long, text string", budget=2)
    state.flush()
    got = [(r["l"], r["r"]) for r in state.schedule().collect()]
    words = [set(t.split()) for t in TEXTS]
    want = {(i, j) for i in range(len(TEXTS)) for j in range(i + 1, len(TEXTS)) if words[i] & words[j]}
    assert set(got) == want
    assert state.n == 4 and isinstance(state, Incremental)


def test_incremental_emits_the_best_left_and_the_rest(spark, tmp_path):
    texts = ["red green"] * 110 + ["red blue"] * 5 + ["white"] * 3
    p = profiles(spark, texts)
    state = Incremental(spark, 7)
    got = []
    for low, high, budget in ((0, 110, 7), (110, 118, 6000)):
        state.budget = budget
        got.append([(r["l"], r["r"], r["w"]) for r in state.add(p.where((F.col("pid") >= low) & (F.col("pid") < high))).orderBy("pos").collect()])
    old = 2 / (110 * 109 / 2)
    green = [(i, j, round(old, 9)) for i in range(110) for j in range(i + 1, 110)]
    red, blue, white = 1 / (115 * 114 / 2), 1 / 10, 1 / 3
    later = [(i, j, round(red + blue * (i >= 110), 9)) for i in range(115) for j in range(max(i + 1, 110), 115)] + [(i, j, round(white, 9)) for i in range(115, 118) for j in range(i + 1, 118)]
    order = sorted([*green[7:], *later], key=lambda x: (-x[2], x[0], x[1]))
    assert got == [green[:7], order[:6000]]
    assert [(r["l"], r["r"], r["w"]) for r in state.flush().orderBy("pos").collect()] == order[6000:]
    assert state.flush() is None and state.n == 3
    p.coalesce(1).write.parquet(str(tmp_path / "in"))
    assert run_stream(spark, str(tmp_path / "in"), "source string, pid long, text string", budget=2).schedule().count() == 115 * 114 // 2 + 3


@pytest.mark.parametrize("ahead", [1, 3, 50])
def test_incremental_emits_no_pair_twice(spark, ahead):
    """A later batch whose pairs are better than the last ones emitted must not bring those back; pairs left out of the pool return."""
    texts = ["red green"] * 6 + ["red blue"] * 2 + [f"x{i // 2} red" for i in range(8)] + ["blue y"] * 3 + ["red", "lone"]
    p, sets = profiles(spark, texts), [set(t.split()) for t in texts]
    truth = spark.createDataFrame([(0, 7), (8, 9), (3, 16)], "l long, r long")
    state, left, seen = Incremental(spark, 5, asked=truth, ahead=ahead), {}, []
    for low, high in ((0, 6), (6, 12), (12, 16), (16, len(texts))):
        rows = state.add(p.where((F.col("pid") >= low) & (F.col("pid") < high))).orderBy("pos").collect()
        seen += range(low, high)
        n = {t: sum(t in sets[i] for i in seen) for s in sets for t in s}
        left |= {(i, j): round(sum(2 / (n[t] * (n[t] - 1)) for t in sets[i] & sets[j]), 9) for j in range(low, high) for i in range(j) if sets[i] & sets[j]}
        best = sorted(left, key=lambda k: (-left[k], k))[:5]
        assert [(r["l"], r["r"], r["w"]) for r in rows] == [(*k, left.pop(k)) for k in best]
    assert state.rest() == (len(left), sum((r["l"], r["r"]) in left for r in truth.collect()))
    assert [(r["l"], r["r"]) for r in state.flush().orderBy("pos").collect()] == sorted(left, key=lambda k: (-left[k], k))
    assert state.rest() == (0, 0) and state.flush() is None


def test_incremental_query_emits_every_pair(spark):
    from progmatch.plans.fixtures import Fixtures
    from progmatch.plans.workloads import incremental

    d = "/root/testdata/sf0.001"
    rows = incremental(spark, d).collect()
    words = [set(r["text"].lower().split()) for r in Fixtures(spark, d).docs().profiles.select("text").collect()]
    truth = Fixtures(spark, d).docs_truth().count()
    assert sum(r["found"] for r in rows) == truth and max(r["n"] for r in rows if r["batch"] < 10) <= truth
    assert sum(r["n"] for r in rows) >= sum(bool(words[i] & words[j]) for i in range(len(words)) for j in range(i))


def test_join_curves_cover_every_data_set(spark):
    from progmatch.plans.workloads import MULTIPLES, SCHEDULERS, method_queries

    rows = method_queries()["wl_join_curves"](spark, "/root/testdata/sf0.001").select("dataset", "scheduler", "multiple").collect()
    assert {tuple(r) for r in rows} == {(d, s, m) for d in ("docs_linkage", "bench_linkage", "cust_linkage") for s in SCHEDULERS for m in MULTIPLES}


@pytest.mark.parametrize("linkage", [True, False])
def test_stacks_are_the_single_runs(spark, linkage):
    from progmatch.plans.config import SCHEDULERS, evaluate, evaluate_stack

    rng = np.random.default_rng(5)
    pairs = [(i, j) for i in range(12) for j in range(9) if linkage or i < j]
    rows = [(c, i, j, float(rng.integers(1, 9)) / 8) for c in ("a", "b") for i, j in pairs if rng.random() < 0.7]
    stacked = spark.createDataFrame(rows, "config string, l long, r long, w double")
    truth = spark.createDataFrame([p for p in pairs if sum(p) % 3 == 0], "l long, r long")
    one = stacked.where("config = 'a'").select("l", "r", "w")
    for kind in SCHEDULERS:
        want = evaluate("x", "y", "a", one, truth, [5, 20, 60], linkage, (kind,)).select("budget", "found", "recall", "pr").collect()
        got = evaluate_stack(stacked, truth, [5, 20, 60], linkage, kind).where("config = 'a'").select("budget", "found", "recall", "pr").collect()
        assert sorted(got) == sorted(want)
    near = sparse.nearest_stack(stacked, (1, 3), linkage, {"L": 12, "R": 9})
    sides = sparse.SIDES if linkage else ("both",)
    assert {r[0] for r in near.select("config").distinct().collect()} == {f"{c}_{s}_{k}" for c in "ab" for s in sides for k in (1, 3)}
    for side in sides:
        want = sparse.nearest(one, 3, linkage, side, {"L": 12, "R": 9}).collect()
        assert sorted(near.where(f"config = 'a_{side}_3'").select("l", "r", "w").collect()) == sorted(want)


def test_streams(spark, tmp_path):
    rows = [(1, 1, "2024-01-01 00:00:00", 1.0), (2, 1, "2024-01-01 00:00:05", 3.0), (3, 2, "2024-01-01 00:01:00", 2.0)]
    e = spark.createDataFrame(rows, "event_id long, user_id long, ts string, value double").withColumn("ts", F.to_timestamp("ts"))
    e.write.parquet(str(tmp_path / "e"))
    stream = lambda: spark.readStream.schema(e.schema).parquet(str(tmp_path / "e"))
    for name, df, mode in (("best", running_best(stream()), "update"), ("near", interval_join(stream(), stream(), "user_id", 10, "1 minute"), "append")):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination()
    assert {(r["user_id"], r["n"], r["best"]) for r in spark.table("best").collect()} == {(1, 2, 3.0), (2, 1, 2.0)}
    assert [(r["event_l"], r["event_r"]) for r in spark.table("near").collect()] == [(1, 2)]


def test_plans(spark):
    task = Dedup(profiles(spark))
    edges = sparse.sparse_candidates(Task(task.profiles, "dedup"), "word1", "bool", "cosine", 2)
    plan = schedule(edges, "edge", 5)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "TakeOrderedAndProject" in plan and "WindowGroupLimit" in plan
