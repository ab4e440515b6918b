"""What rounds on larger tables found: the same results by steps that hold fewer rows."""

from itertools import combinations

from progmatch.operators import setjoin
from progmatch.plans.fixtures import shingle_truth


def _shingles(text):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + 3]) for i in range(len(w) - 2)} if len(w) >= 3 else {" ".join(w)} if w else set()


def _texts():
    common = "this passage stands in every text of the table word for word"
    rows = [(i, f"{common} " + " ".join(f"w{i}x{k}" for k in range(6 + i % 9))) for i in range(60)]
    rows += [(100 + i, rows[i][1] + " and more") for i in range(0, 60, 3)] + [(200 + i, rows[i][1]) for i in range(0, 60, 7)]
    return [*rows, (300, None), (301, ""), (302, "one"), (303, "One"), (304, "one two"), (305, "...")]


def test_shingle_truth_is_brute_force_and_a_common_passage_makes_few_candidates(spark):
    rows = _texts()
    df = spark.createDataFrame([("L", i, t) for i, t in rows], "source string, pid long, text string")
    sets = {i: _shingles(t) for i, t in rows}
    for least in (0.5, 0.8):
        want = {(a, b) for a, b in combinations(sorted(sets), 2) if sets[a] and sets[b] and len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b])}
        got = [tuple(r) for r in shingle_truth(df, least).collect()]
        assert len(got) == len(set(got)) and set(got) == want
    sharing = sum(1 for a, b in combinations(sorted(sets), 2) if sets[a] & sets[b])
    assert setjoin.candidates(df.where("length(text) > 0 and text <> '...'"), 3, 0.8).count() < sharing / 10
    assert shingle_truth(df.limit(0)).count() == 0


def test_packed_pairs_have_the_weights_of_the_histogram(spark):
    from pyspark.sql import functions as F

    from progmatch.operators import packedlist, sortedlist
    from progmatch.sources.profiles import Dedup, Task

    rows = [(s, i, t) for s, k in (("L", 0), ("R", 1)) for i, t in _texts()[k:40:2]]
    df = spark.createDataFrame(rows, "source string, pid long, text string")
    for task in (Task(df, "linkage"), Dedup(df.where("source = 'L'"))):
        listed = sortedlist.sorted_list(task)
        packed = packedlist.packed_list(task, chunk=7)
        assert [k for r in packed.orderBy("at", "k").collect() for k in memoryview(r["keys"]).cast("q")] == [2 * r["pid"] + (r["source"] == "R") if task.linkage else r["pid"] for r in listed.orderBy("pos").collect()]
        made = sortedlist.with_positions(sortedlist.histogram_of(listed, 10, task.linkage), sortedlist.list_nodes(listed), task.linkage).collect()
        h = packedlist.histograms(packed, 10, task.linkage)
        assert sorted((r["l"], r["r"], *r["h"]) for r in made) == sorted(tuple(r) for r in h.collect())
        made = spark.createDataFrame(made)
        for weight, scope in (("id", "global"), ("acf", "local"), ("ncf", "global"), ("dncf", "local"), ("cncf", "global")):
            want = made.select("l", "r", F.round(sortedlist.sorted_weight(weight, scope, 10), 9).alias("w")).where("w > 0")
            assert sorted(tuple(r) for r in want.collect()) == sorted(tuple(r) for r in packedlist.packed_weights(packed, weight, scope, 10, task.linkage).collect())


def test_brute_force_takes_more_suppliers_than_the_guard(spark, tmp_path):
    from progmatch.plans.workloads import method_queries

    n = 4_600  # 10,577,700 pairs
    spark.range(1, n + 1).selectExpr("id as s_suppkey", "concat('Supplier#', id) as s_name").write.parquet(f"{tmp_path}/supplier.parquet")
    found = method_queries()["brute_force"](spark, str(tmp_path))
    assert tuple(found.selectExpr("count(*)", "count_if(l < r)", "sum(r - l)").first()) == (n * (n - 1) // 2, n * (n - 1) // 2, (n - 1) * n * (n + 1) // 6)


def test_half_way_scores_are_rounded_as_in_sql(spark):
    import duckdb
    from pyspark.sql import functions as F

    from progmatch.operators.schedule import node_score

    rows = [(i, w / 1e9) for i in range(400) for w in (1_000_003 * i % 999_983_777, 7_919 * i * i % 99_991_111 + i % 2)]
    df = spark.createDataFrame(rows, "node long, w double")
    got = {r["node"]: r["s"] for r in df.groupBy("node").agg(node_score(F.avg("w")).alias("s")).collect()}
    values = ", ".join(f"({i}, {w!r}::DOUBLE)" for i, w in rows)
    want = dict(duckdb.sql(f"SELECT node, -round(avg(w), 9) FROM (VALUES {values}) v(node, w) GROUP BY 1").fetchall())
    assert got == want
    assert any(r["s"] != want[r["node"]] for r in df.groupBy("node").agg((-F.round(F.avg("w"), 9)).alias("s")).collect())


def _first_blocks(rows, linkage, budget):
    """Pairs in the order of their first block, by brute force over (bkey, card, [(source, pid)])."""
    found = {}
    for bkey, card, members in rows:
        for a, b in ((a, b) for a in members for b in members):
            if (a[0] == "L" and b[0] == "R") if linkage else a[1] < b[1]:
                found.setdefault((a[1], b[1]), []).append((card, bkey))
    keyed = sorted((min(bs), -round(sum(1 / c for c, _ in bs), 9), *pair) for pair, bs in found.items())
    return [(i, left, right, -w) for i, (_, w, left, right) in enumerate(keyed[:budget], 1)], len(found)


def test_block_by_block_makes_the_pairs_of_the_smallest_blocks_only(spark):
    from progmatch.operators import baselines, blocking
    from progmatch.sources.profiles import Task

    texts = _texts()[:60]
    df = spark.createDataFrame([("L" if i % 2 else "R", i, t if i < 29 else f"{t} twin{i // 2} some{i // 5} other{i // 2}") for i, t in texts], "source string, pid long, text string")
    for task in (Task(df.where("source = 'L'"), "dedup"), Task(df, "linkage")):
        blocks, stats = blocking.refined(task, "none", None)
        rows = {}
        for r in blocks.collect():
            rows.setdefault((r["bkey"], r["card"]), []).append((r["source"], r["pid"]))
        for budget in (7, 10_000):
            want, every = _first_blocks([(*k, m) for k, m in rows.items()], task.linkage, budget)
            got = baselines.baseline_block_progressive(task, budget, "none", None)
            assert [tuple(r) for r in got.orderBy("pos").collect()] == want
            if budget == 7:
                assert 7 <= baselines._first_pairs(blocks, stats, task.linkage, 7).count() < every / 10


def test_exact_neighbours_are_brute_force_and_no_vector_is_shuffled(spark):
    import numpy as np

    from progmatch.operators import dense

    rng = np.random.default_rng(3)
    vecs = np.concatenate((rng.normal(size=(30, 4)), np.repeat(rng.normal(size=(2, 4)), 20, axis=0), np.zeros((3, 4))))
    ids = rng.permutation(len(vecs))
    df = spark.createDataFrame([("L" if i % 3 else "R", int(p), [float(x) for x in v]) for i, (p, v) in enumerate(zip(ids, vecs, strict=True))], "source string, pid long, vec array<double>").repartition(3)
    rows = {p: v for p, v in zip(ids, vecs, strict=True)}
    source = {int(p): "L" if i % 3 else "R" for i, p in enumerate(ids)}
    for sim in ("cosine", "euclid"):
        want, names = {0: set(), 1: set()}, sorted(rows)
        every = dict(zip(names, np.round(dense._similarities(np.stack([rows[p] for p in names]), np.stack([rows[p] for p in names]), sim), 9), strict=True))
        for side, own, other in ((0, "L", "R"), (1, "R", "L")):
            for q in (p for p in names if source[p] == own):
                best = sorted((-every[q][names.index(i)], i) for i in names if source[i] == other)[:4]
                want[side] |= {(side, q, i, -w) for w, i in best}
        packed = dense.packed_vectors(df, 7)
        assert packed.count() >= 9
        got = dense.exact_neighbours(packed.where("source = 'L'"), packed.where("source = 'R'"), sim, 4, False)
        assert {tuple(r) for r in got.collect()} == want[0] | want[1]
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" in plan and "FlatMapGroupsInPandas" not in plan
        alone = dense.exact_pairs(df.select("pid", "vec"), df.select("pid", "vec"), sim, 4, True, 7)
        best = {(q, i, -w) for q in names for w, i in sorted((-every[q][names.index(i)], i) for i in names if i != q)[:4]}
        assert {tuple(r) for r in alone.collect()} == best


def test_vectors_made_row_by_row_are_those_of_the_joined_weights(spark):
    import numpy as np

    from progmatch.operators import encoders
    from progmatch.operators.sparse import scored, term_counts
    from progmatch.sources.profiles import Dedup

    task = Dedup(spark.createDataFrame([("L", i, t) for i, t in _texts()], "source string, pid long, text string"))
    n = task.profiles.count()
    joined = encoders._hashed_vectors(scored(term_counts(task, "word1"), n, ("tfidf",)).withColumnRenamed("tfidf", "w"), task.profiles, 16)
    want = {r["pid"]: r["vec"] for r in joined.collect()}
    made = encoders.encode(task, "sent", 16)
    got = {r["pid"]: r["vec"] for r in made.collect()}
    assert set(got) == set(want) and all(np.allclose(got[p], want[p], atol=1e-12) for p in want)
    assert "Exchange" not in made._jdf.queryExecution().executedPlan().toString()


def test_packed_schedules_are_the_schedules_of_all_pairs(spark):
    from progmatch.operators import packedlist
    from progmatch.operators.schedule import SCHEDULERS, schedule
    from progmatch.session import settle
    from progmatch.sources.profiles import Task

    df = spark.createDataFrame([("LR"[i % 2], i, t) for i, t in _texts()], "source string, pid long, text string")
    packed = packedlist.packed_list(Task(df, "linkage"), chunk=50)
    for weight, window, kinds in (("acf", 10, SCHEDULERS), ("dncf", 3, ("depth",))):
        edges = settle(packedlist.packed_weights(packed, weight, "global", window, True), "edges")
        n = edges.count()
        for kind in kinds:
            want = [tuple(r) for r in schedule(edges, kind, n, True).orderBy("pos").collect()]
            for budget in (40, n + 5) if kind == "hybrid" else (40,):
                got = packedlist.packed_schedule(packed, weight, "global", window, kind, budget)
                assert [tuple(r) for r in got.orderBy("pos").collect()] == want[:budget]
    steps = packedlist._steps(*[c.repeat(4) for c in (packedlist.np.array([0, 0, 1]), packedlist.np.array([-2.0, 3.0, -9.0]))])
    assert (packedlist.np.diff(steps) >= 0).all() and len(set(steps.tolist())) == 3


def test_the_driver_sees_few_steps_of_a_packed_schedule(spark, monkeypatch):
    from progmatch.operators import packedlist
    from progmatch.operators.schedule import schedule
    from progmatch.session import settle
    from progmatch.sources.profiles import Task

    df = spark.createDataFrame([("LR"[i % 2], i, t) for i, t in _texts()], "source string, pid long, text string")
    packed = packedlist.packed_list(Task(df, "linkage"), chunk=50)
    edges = settle(packedlist.packed_weights(packed, "acf", "global", 10, True), "edges")
    want = [tuple(r) for r in schedule(edges, "breadth", 200, True).orderBy("pos").collect()]
    largest, seen, kind = edges.groupBy("l").count().agg({"count": "max"}).first()[0], [], type(df)
    for name in ("toPandas", "toArrow"):
        monkeypatch.setattr(kind, name, lambda self, f=getattr(kind, name): seen.append(self.count()) or f(self))
    got = packedlist.packed_schedule(packed, "acf", "global", 10, "breadth", 200)
    assert 0 < max(seen) <= largest
    assert [tuple(r) for r in got.orderBy("pos").collect()] == want


def test_packed_postings_give_the_nearest_of_the_joined_ones(spark, monkeypatch):
    from progmatch.operators import postings, sparse
    from progmatch.session import settle
    from progmatch.sources.profiles import Task

    df = spark.createDataFrame([("LR"[i % 3 == 0], i, t) for i, t in _texts()], "source string, pid long, text string").repartition(2)
    for task, scoring in ((Task(df, "linkage"), "tfidf"), (Task(df.where("source = 'L'"), "dedup"), "tf")):
        pairs = settle(sparse.sparse_pairs(task, "word2", (scoring,)).select("l", "r", sparse.similarity("cosine", scoring).alias("w")).where("w > 0"), "pairs")
        packed = postings.packed_postings(task, "word2", scoring, 7)
        left, right = (packed.where(f"source = '{s}'") if task.linkage else packed for s in "LR")
        met = postings.nearest_cosine(left, right, 3, not task.linkage)
        assert "CartesianProduct" in met._jdf.queryExecution().executedPlan().toString()
        near = settle(met, "near")
        for side in sparse.SIDES if task.linkage else ("both",):
            want = sorted(tuple(r) for r in sparse.nearest(pairs, 3, task.linkage, side, task.sizes()).collect())
            assert want and sorted(tuple(r) for r in postings.edges_of_side(near, task.linkage, side, task.sizes()).collect()) == want
    import numpy as np

    rng = np.random.default_rng(1)
    blocks = [(np.sort(rng.integers(0, 9, 40)), rng.integers(0, n, 40), rng.normal(size=40)) for n in (5, 6)]
    want = np.zeros((5, 6))
    for g, i, a in zip(*blocks[0], strict=True):
        for h, j, b in zip(*blocks[1], strict=True):
            want[i, j] += a * b * (g == h)
    monkeypatch.setattr(postings, "HELD_PRODUCTS", 3)
    assert np.allclose(postings.products(*blocks, 5, 6), want)
    assert postings.products(*[tuple(c[:0] for c in b) for b in blocks], 5, 6).sum() == 0
    monkeypatch.setattr(postings, "MOST_GRAMS", 3)
    assert postings.packed_postings(task, "word2", "tf") is None


def test_position_pairs_are_not_shuffled_and_longer_lists_give_the_same(spark, monkeypatch, tmp_path):
    from progmatch.operators import packedlist
    from progmatch.plans import fixtures
    from progmatch.sources.profiles import Dedup, Task

    df = spark.createDataFrame([("LR"[i % 2], i, t) for i, t in _texts()], "source string, pid long, text string")
    for task in (Task(df, "linkage"), Dedup(df)):
        packed = fixtures.once(spark, str(tmp_path), f"packed_{task.kind}", lambda t=task: packedlist.packed_list(t, chunk=7))
        assert "packed-list" in packed.settled_at  # written once
        read = packedlist.histograms(packed, 10, task.linkage)
        assert "CartesianProduct" in (plan := read._jdf.queryExecution().executedPlan().toString()) and "Exchange" not in plan
        want = sorted(tuple(r) for r in read.collect())
        with monkeypatch.context() as m:
            m.setattr(packedlist, "TASK_PAIRS", 500)  # more tasks than the session's width
            assert sorted(tuple(r) for r in packedlist.histograms(packed, 10, task.linkage).collect()) == want
            m.setattr(packedlist, "MOST_READ", 0)
            dealt = packedlist.histograms(packed, 10, task.linkage)
            assert "Exchange" in dealt._jdf.queryExecution().executedPlan().toString()
            assert sorted(tuple(r) for r in dealt.collect()) == want
    empty = packedlist.packed_list(Task(df.limit(0), "linkage"))
    assert packedlist.histograms(empty, 10, True).count() == 0


def test_passages_are_found_byte_for_byte_without_a_join(spark, monkeypatch):
    from progmatch.plans import fixtures
    from progmatch.plans.fixtures import holders

    monkeypatch.setattr(fixtures, "SEARCHED", 64)
    data = fixtures.np.frombuffer(b"ab12345678" * 30, fixtures.np.uint8)
    assert fixtures.places_of(data, fixtures.np.array([int.from_bytes(b"12345678", "little")], fixtures.np.uint64)).tolist() == list(range(2, 300, 10))

    texts = [(1, "a łong pâssage stands here"), (2, "łong pâssage"), (3, None), (4, ""), (5, "long passage"), (None, "a łong pâssage"), (6, "x" * 3000 + "łong pâssage" + "y" * 3000)]
    docs = spark.createDataFrame(texts, "r long, text string")
    items = spark.createDataFrame([(10, "łong pâssage"), (11, "x" * 150), (12, None), (13, ""), (14, "łong pâssage stands"), (15, "łong pâssagf")], "l long, passage string")
    got = holders(docs, items)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoopJoin" not in plan and "contains" not in plan.lower()
    want = [(r["l"], r["r"]) for r in docs.crossJoin(items).where("contains(text, passage)").collect()]
    key = lambda x: (x[0], x[1] or 0)
    assert len(want) == 12 and sorted((tuple(r) for r in got.collect()), key=key) == sorted(want, key=key)


def test_packed_bm25_gives_the_best_of_the_joined_postings(spark, monkeypatch):
    import numpy as np

    from progmatch.operators import baselines, postings
    from progmatch.sources.profiles import Dedup, Task

    rows = [("LR"[i % 3 == 0], i, t) for i, t in _texts()[:40]] + [("L", 400, "é"), ("R", 401, "É !"), ("L", 402, "né 𝒳𝒳"), ("R", 403, "né 𝒳𝒳"), ("L", 404, None), ("R", 405, "..")]
    df = spark.createDataFrame(rows, "source string, pid long, text string").repartition(2)
    monkeypatch.setattr(postings, "BLOCK_ROWS", 7)
    for task in (Task(df, "linkage"), Dedup(df.where("source = 'L'"))):
        for index in ("largest", "smallest", "both") if task.linkage else ("largest",):
            want = sorted(tuple(r) for r in baselines._joined_bm25(task, 3, index, "char3", 1.2, 0.75).collect())
            found = baselines.baseline_bm25(task, 3, index)
            assert "CartesianProduct" in found._jdf.queryExecution().executedPlan().toString()
            got = sorted(tuple(r) for r in found.collect())
            assert [r[:2] for r in got] == [r[:2] for r in want] and np.allclose([r[2] for r in got], [r[2] for r in want], atol=1.5e-9)
    rng = np.random.default_rng(5)
    blocks = [(np.sort(rng.integers(0, 9, 40)), rng.integers(0, n, 40), rng.normal(size=40)) for n in (5, 6)]
    every = []
    for share in (0, 1, 400):  # no gram, some, all as columns
        monkeypatch.setattr(postings, "DENSE_SHARE", share)
        every.append(postings.products(*blocks, 5, 6))
    assert np.allclose(every[0], every[1]) and np.allclose(every[0], every[2])


def test_the_shuffle_of_the_sample_goes_before_places_are_dealt(spark, monkeypatch):
    from progmatch.operators import setjoin

    done = []
    noted = lambda name, f: lambda *a, **k: (f(*a, **k), done.append(name))[0]
    for name in ("usual_grams", "release", "settle"):
        monkeypatch.setattr(setjoin, name, noted(name, getattr(setjoin, name)))
    df = spark.createDataFrame([("L", i, t) for i, t in _texts()[:20]], "source string, pid long, text string")
    setjoin.candidates(df, 3, 0.5)
    assert done[:3] == ["usual_grams", "release", "settle"]


def test_a_schedule_adds_up_all_pairs_once_and_is_right_where_the_guess_is_not(spark, monkeypatch):
    import numpy as np

    from progmatch.operators import packedlist
    from progmatch.operators.schedule import schedule
    from progmatch.session import settle
    from progmatch.sources.profiles import Task

    df = spark.createDataFrame([("LR"[i % 2], i, t) for i, t in _texts()], "source string, pid long, text string")
    packed = packedlist.packed_list(Task(df, "linkage"), chunk=50)
    edges = {w: settle(packedlist.packed_weights(packed, w, "global", 10, True), "edges") for w in ("id", "acf")}
    real, calls = packedlist.summed, []
    monkeypatch.setattr(packedlist, "summed", lambda *a: calls.append(made := real(*a)) or made)
    monkeypatch.setattr(packedlist, "TASK_PAIRS", 200)
    monkeypatch.setattr(packedlist, "TRIED", 2)
    for weight, kind, margin, passes in (("id", "edge", 2.0, 2), ("acf", "hybrid", -1000.0, 3)):
        calls.clear()
        want = [tuple(r) for r in schedule(edges[weight], kind, 150, True).orderBy("pos").collect()]
        monkeypatch.setattr(packedlist, "MARGIN", margin)
        got = [tuple(r) for r in packedlist.packed_schedule(packed, weight, "global", 10, kind, 150).orderBy("pos").collect()]
        assert got == want and calls[0].share < 0.5
        assert passes == 3 or sum(c.share for c in calls) < 1.5  # all pairs once, some owners before
        assert len(calls) >= passes
    ids = np.array([5, 5, 1 << 50, 3]), np.array([9, 2, 7, 1])
    parts = [packedlist._as_one(*(c[a:b] for c in ids), 4) for a, b in ((0, 2), (2, 4))]
    assert [len(p) for p in parts] == [1, 2]
    assert [c.tolist() for c in packedlist._in_order(parts, 4)] == [[3, 5, 5, 1 << 50], [1, 2, 9, 7]]
    node, w = np.array([0, 0, 0, 1, 1]), np.array([1.0, 2.5, 1.0, 0.5, 3.0])
    assert packedlist._heaviest_first(node, w).tolist() == [1, 0, 2, 4, 3]


def test_the_packed_list_is_made_in_one_pass_in_the_order_of_tokens_and_ties(spark, monkeypatch):
    from progmatch.operators import packedlist, sortedlist
    from progmatch.sources.profiles import Task

    df = spark.createDataFrame([("LR"[i % 2], i, t) for i, t in [*_texts(), (9001, "über Zoë ﬀ 漢字 𝒳"), (9002, "zoë 漢字 a"), (9003, None)]], "source string, pid long, text string")
    task = Task(df, "linkage")
    want = [2 * r["pid"] + (r["source"] == "R") for r in sortedlist.sorted_list(task).orderBy("pos").collect()]
    for name, value in (("DEALT_ROWS", 100), ("RANGE_ROWS", 150), ("CUT_TEXTS", 60), ("CUT_PART", 2)):
        monkeypatch.setattr(packedlist, name, value)
    plans, kind = [], type(df)
    real = kind.repartitionByRange
    monkeypatch.setattr(kind, "repartitionByRange", lambda self, *a: plans.append(a) or real(self, *a))
    packed = packedlist.packed_list(task, chunk=50)
    assert [k for r in packed.orderBy("at", "k").collect() for k in memoryview(r["keys"]).cast("q")] == want
    assert not plans  # a partition by ranges reads and splits all texts twice
    assert packed.select("at").distinct().count() > 4
