"""SQL twins of the method queries, put together from common table expressions."""

from __future__ import annotations

_W = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '')"
_NORM = r"trim(regexp_replace(lower(coalesce(text, '')), '[^\p{L}\p{N}]+', ' ', 'g'))"

DOCS = "p AS (SELECT 'L' AS source, doc_id AS pid, text FROM documents)"
TRUTH = f"""tw AS (SELECT doc_id, {_W} AS w FROM documents),
ts AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i+1] || ' ' || w[i+2]) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM tw),
tn AS (SELECT doc_id, count(*) AS n FROM ts GROUP BY 1),
tc AS (SELECT a.doc_id AS l, b.doc_id AS r, count(*) AS c FROM ts a JOIN ts b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
truth_d AS (SELECT l, r FROM tc JOIN tn x ON x.doc_id = l JOIN tn y ON y.doc_id = r WHERE c >= 0.5 * (x.n + y.n - c))"""
LINKAGE = f"""{TRUTH},
gone AS (SELECT DISTINCT r AS pid FROM truth_d WHERE l % 2 = r % 2),
p AS (SELECT CASE WHEN doc_id % 2 = 0 THEN 'L' ELSE 'R' END AS source, doc_id AS pid, text FROM documents WHERE doc_id NOT IN (SELECT pid FROM gone)),
truth_l AS (SELECT CASE WHEN l % 2 = 0 THEN l ELSE r END AS l, CASE WHEN l % 2 = 0 THEN r ELSE l END AS r FROM truth_d WHERE l % 2 <> r % 2 AND l IN (SELECT pid FROM p) AND r IN (SELECT pid FROM p))"""
TOKENS = f"tok AS (SELECT DISTINCT source, pid, unnest({_W}) AS bkey FROM p)"


def _stats(name: str, rows: str, linkage: bool) -> str:
    if linkage:
        return f"{name} AS (SELECT bkey, nl + nr AS n, nl * nr AS card FROM (SELECT bkey, count(*) FILTER (source = 'L') AS nl, count(*) FILTER (source = 'R') AS nr FROM {rows} GROUP BY 1) WHERE nl * nr > 0)"
    return f"{name} AS (SELECT bkey, count(*) AS n, count(*) * (count(*) - 1) // 2 AS card FROM {rows} GROUP BY 1 HAVING count(*) > 1)"


def blocks(linkage: bool, profiles: str | None = None) -> str:
    return f"""{profiles or (LINKAGE if linkage else DOCS)}, {TOKENS}, {_stats("st0", "tok", linkage)},
st1 AS (SELECT * FROM st0 WHERE 2 * n <= (SELECT count(*) FROM p)),
rk AS (SELECT tok.*, row_number() OVER (PARTITION BY source, pid ORDER BY card, bkey) AS place, count(*) OVER (PARTITION BY source, pid) AS m FROM tok JOIN st1 USING (bkey)),
b2 AS (SELECT source, pid, bkey FROM rk WHERE place <= ceil(0.8::DOUBLE * m)), {_stats("st2", "b2", linkage)},
b AS (SELECT b2.*, n, card FROM b2 JOIN st2 USING (bkey))"""


def graph(linkage: bool, profiles: str | None = None) -> str:
    on = "x.source = 'L' AND y.source = 'R'" if linkage else "x.pid < y.pid"
    return f"{blocks(linkage, profiles)}, g AS (SELECT x.pid AS l, y.pid AS r, count(*) AS cb, sum(1.0::DOUBLE / x.n) AS sn, sum(1.0::DOUBLE / x.card) AS cn FROM b x JOIN b y ON x.bkey = y.bkey AND {on} GROUP BY ALL)"


_GRID = f"""{graph(True)},
nd AS (SELECT source, pid, count(*) AS nb, sum(1.0::DOUBLE / n) AS snb, sum(1.0::DOUBLE / card) AS cnb FROM b GROUP BY ALL),
dl AS (SELECT l, count(*) AS d FROM g GROUP BY 1), dr AS (SELECT r, count(*) AS d FROM g GROUP BY 1),
k AS (SELECT (SELECT count(*) FROM st2)::DOUBLE AS nbl, (SELECT count(*) FROM dl)::DOUBLE + (SELECT count(*) FROM dr) AS v),
j AS (SELECT g.l, g.r, cb::DOUBLE AS cb, sn, cn, x.nb AS xb, y.nb AS yb, x.snb AS xs, y.snb AS ys, x.cnb AS xc, y.cnb AS yc, dl.d AS d1, dr.d AS d2, k.* FROM g JOIN nd x ON x.source = 'L' AND x.pid = g.l JOIN nd y ON y.source = 'R' AND y.pid = g.r JOIN dl ON dl.l = g.l JOIN dr ON dr.r = g.r, k)"""
_WEIGHTS = {
    "cb": "cb", "cosine": "cb / sqrt(xb * yb)", "dice": "2 * cb / (xb + yb)", "jaccard": "cb / (xb + yb - cb)",
    "sn_cb": "sn", "sn_cosine": "sn / sqrt(xs * ys)", "sn_dice": "2 * sn / (xs + ys)", "sn_jaccard": "CASE WHEN xs + ys - sn <> 0 THEN sn / (xs + ys - sn) END",
    "cn_cb": "cn", "cn_cosine": "cn / sqrt(xc * yc)", "cn_dice": "2 * cn / (xc + yc)", "cn_jaccard": "CASE WHEN xc + yc - cn <> 0 THEN cn / (xc + yc - cn) END",
    "ecb": "cb * ln(nbl / xb) * ln(nbl / yb)", "ejs": "cb / (xb + yb - cb) * ln(v / d1) * ln(v / d2)",
}


def listed(linkage: bool, profiles: str | None = None) -> str:
    tie = "md5(bkey || '|' || source || ':' || pid::VARCHAR || '|0')"
    return f"{profiles or (LINKAGE if linkage else DOCS)}, {TOKENS}, ls AS (SELECT row_number() OVER (ORDER BY bkey, {tie}) AS pos, bkey AS token, source, pid FROM tok)"


def histogram(window: int, profiles: str | None = None) -> str:
    sums = ", ".join(f"count(*) FILTER (d = {d}) AS h{d}" for d in range(1, window + 1))
    return f"""{listed(True, profiles)},
wp AS (SELECT CASE WHEN a.source = 'L' THEN a.pid ELSE z.pid END AS l, CASE WHEN a.source = 'L' THEN z.pid ELSE a.pid END AS r, z.pos - a.pos AS d
  FROM (SELECT *, unnest(range(1, {window + 1})) AS k FROM ls) a JOIN ls z ON z.pos = a.pos + a.k WHERE a.source <> z.source),
hs AS (SELECT l, r, {sums} FROM wp GROUP BY 1, 2),
np AS (SELECT source, pid, count(*)::DOUBLE AS c FROM ls GROUP BY ALL),
h AS (SELECT hs.*, x.c AS pl, y.c AS pr FROM hs JOIN np x ON x.source = 'L' AND x.pid = l JOIN np y ON y.source = 'R' AND y.pid = r)"""


def sorted_expr(weight: str, scope: str, w: int) -> str:
    upto = lambda v: "(" + " + ".join(f"h{d}" for d in range(1, v + 1)) + ")::DOUBLE"
    norm = {
        "acf": lambda a: a,
        "ncf": lambda a: f"CASE WHEN pl + pr - {a} > 0 THEN {a} / (pl + pr - {a}) ELSE {a} END",
        "dncf": lambda a: f"2 * {a} / (pl + pr)",
        "cncf": lambda a: f"{a} / sqrt(pl * pr)",
        "id": None,
    }[weight]
    spans = range(1, w + 1) if scope == "global" else [w]
    if norm is None:
        return " + ".join("(" + " + ".join(f"h{d} / {d}::DOUBLE" for d in range(1, v + 1)) + ")" for v in spans)
    return " + ".join(f"({norm(upto(v))})" for v in spans)


def order(edges: str, kind: str, budget: str, linkage: bool) -> str:
    """A select of (pos, l, r, w) from edges (l, r, w)."""
    e = f"SELECT l, r, round(w, 9) AS w FROM ({edges}) WHERE round(w, 9) > 0"
    if kind == "edge":
        body, keys = f"SELECT l, r, w FROM ({e})", "w DESC, l, r"
        return f"SELECT pos, l, r, w FROM (SELECT *, row_number() OVER (ORDER BY {keys}) AS pos FROM ({body})) WHERE pos <= {budget}"
    ends = f"SELECT l AS node, r AS other, l, r, w FROM ({e})" + ("" if linkage else f" UNION ALL SELECT r, l, l, r, w FROM ({e})")
    placed = f"SELECT *, row_number() OVER (PARTITION BY node ORDER BY w DESC, other) AS t, -round(avg(w) OVER (PARTITION BY node), 9) AS s FROM ({ends})"
    key = {"depth": "(s, node, t)", "breadth": "(t, s, node)", "hybrid": "(s, node, t)"}[kind]
    best = f"SELECT l, r, first(w) AS w, min({key}) AS k, min(t) AS t FROM ({placed}) GROUP BY l, r"
    keys = "k, l, r" if kind != "hybrid" else "t > 1, CASE WHEN t = 1 THEN -w END, CASE WHEN t = 1 THEN l END, CASE WHEN t = 1 THEN r END, k, l, r"
    return f"SELECT pos, l, r, w FROM (SELECT *, row_number() OVER (ORDER BY {keys}) AS pos FROM ({best})) WHERE pos <= {budget}"


def terms(tokenizer: str, profiles: str) -> str:
    if tokenizer == "word1":
        src = f"SELECT source, pid, unnest({_W}) AS gram FROM p"
    elif tokenizer == "word2":
        src = f"SELECT source, pid, unnest(CASE WHEN len(w) >= 2 THEN list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i+1]) ELSE w END) AS gram FROM (SELECT *, {_W} AS w FROM p)"
    else:
        n = int(tokenizer[-1])
        src = f"SELECT source, pid, unnest(CASE WHEN length(t) >= {n} THEN list_transform(range(1, length(t) - {n - 2}), lambda i: substr(t, i, {n})) WHEN length(t) > 0 THEN [t] ELSE [] END) AS gram FROM (SELECT *, {_NORM} AS t FROM p)"
    return f"{profiles}, tc0 AS (SELECT source, pid, gram, count(*) AS cnt FROM ({src}) GROUP BY ALL)"


def vectors(tokenizer: str, profiles: str, scoring: str) -> str:
    made = {"bool": "1.0::DOUBLE", "tf": "cnt / mx::DOUBLE", "tfidf": "cnt / mx::DOUBLE * ln((SELECT count(*) FROM p)::DOUBLE / df)"}[scoring]
    return f"""{terms(tokenizer, profiles)}, df0 AS (SELECT gram, count(*) AS df FROM tc0 GROUP BY 1), mx0 AS (SELECT source, pid, max(cnt) AS mx FROM tc0 GROUP BY ALL),
vx AS (SELECT source, pid, gram, {made} AS s FROM tc0 JOIN df0 USING (gram) JOIN mx0 USING (source, pid))"""


def sparse_pairs(tokenizer: str, scoring: str, sim: str, linkage: bool, profiles: str | None = None, guard: bool = False) -> str:
    on = "x.source = 'L' AND y.source = 'R'" if linkage else "x.pid < y.pid"
    w = "coalesce(d / nullif(sqrt(a.q * b.q), 0), 0)" if sim == "cosine" else "1 / (1 + sqrt(greatest(0, a.q + b.q - 2 * d)))"
    if guard and sim == "euclid":  # equal vectors are at distance 0, whatever the rounding of their sums
        w = "1 / (1 + sqrt(CASE WHEN a.q + b.q - 2 * d > 1e-12::DOUBLE * (a.q + b.q) THEN a.q + b.q - 2 * d ELSE 0 END))"
    return f"""{vectors(tokenizer, profiles or (LINKAGE if linkage else DOCS), scoring)}, nv AS (SELECT source, pid, sum(s * s) AS q FROM vx GROUP BY ALL),
dt AS (SELECT x.pid AS l, y.pid AS r, sum(x.s * y.s) AS d FROM vx x JOIN vx y ON x.gram = y.gram AND {on} GROUP BY ALL),
sw AS (SELECT * FROM (SELECT l, r, round({w}, 9) AS w FROM dt JOIN nv a ON a.pid = l{" AND a.source = 'L'" if linkage else ""} JOIN nv b ON b.pid = r{" AND b.source = 'R'" if linkage else ""}) WHERE w > 0)"""


def nearest(pairs: str, k: int, side: str, linkage: bool = True, sizes: str = "(SELECT count(*) FROM p WHERE source = 'L') <= (SELECT count(*) FROM p WHERE source = 'R')") -> str:
    if not linkage:
        return f"SELECT least(q, i) AS l, greatest(q, i) AS r, max(w) AS w FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY w DESC, i) AS t FROM (SELECT l AS q, r AS i, w FROM {pairs} UNION ALL SELECT r, l, w FROM {pairs})) WHERE t <= {k} GROUP BY 1, 2"
    ask = {"both": ("true", "true"), "largest": (sizes, f"NOT ({sizes})"), "smallest": (f"NOT ({sizes})", sizes)}[side]
    of = lambda q, i, c: f"SELECT l, r, w FROM (SELECT *, row_number() OVER (PARTITION BY {q} ORDER BY w DESC, {i}) AS t FROM {pairs}) WHERE t <= {k} AND {c}"
    return f"SELECT l, r, max(w) AS w FROM ({of('l', 'r', ask[0])} UNION ALL {of('r', 'l', ask[1])}) GROUP BY 1, 2"


def vec_pairs(sim: str, strength: int, dedup: bool = False) -> str:
    v = "list_inner_product"
    made = {"cosine": f"{v}(x.v, y.v) / (sqrt({v}(x.v, x.v)) * sqrt({v}(y.v, y.v)))", "euclid": "1 / (1 + list_distance(x.v, y.v))"}[sim]
    return f"""e0 AS (SELECT vec_id AS pid, embedding::DOUBLE[] AS v FROM embeddings),
e1 AS (SELECT pid, list_transform(range(1, len(v) + 1), lambda i: v[i] + ((pid * 31 + i * 17) % 101 - 50) / {strength}::DOUBLE) AS v FROM e0),
e2 AS (SELECT pid, list_transform(v, lambda x: x / sqrt(list_inner_product(v, v))) AS v FROM e1),
p AS (SELECT 'L' AS source, pid FROM e0 UNION ALL SELECT 'R', pid FROM e2),
vp AS (SELECT * FROM (SELECT x.pid AS l, y.pid AS r, round({made}, 9) AS w FROM e0 x, {"e0" if dedup else "e2"} y {"WHERE x.pid < y.pid" if dedup else ""}))"""


def _round(cols: str, source: str) -> str:
    return f"SELECT {cols} FROM ({source})"


def _table(linkage: bool, weight: str, kind: str, multiples: str, norm: str = "budget") -> str:
    truth = "truth_l" if linkage else "truth_d"
    best = "((least(budget, nt) * budget - least(budget, nt) * (least(budget, nt) - 1) / 2) / (nt::DOUBLE * budget))"
    pr = f"area / nt::DOUBLE / budget{f' / {best}' if norm == 'ideal' else ''}"
    sched = order(f"SELECT l, r, {weight} AS w FROM g", kind, f"10 * (SELECT count(*) FROM {truth})", linkage)
    return f"""hit AS (SELECT pos FROM ({sched}) s WHERE EXISTS (SELECT 1 FROM {truth} t WHERE t.l = s.l AND t.r = s.r)),
nt AS (SELECT count(*) AS nt FROM {truth}), bd AS (SELECT m * nt AS budget, nt FROM nt, (SELECT unnest({multiples}) AS m)),
tb AS (SELECT budget, nt, (SELECT count(*) FROM hit WHERE pos <= budget) AS found, coalesce((SELECT sum(budget - pos + 1) FROM hit WHERE pos <= budget), 0)::DOUBLE AS area FROM bd),
res AS (SELECT budget::BIGINT AS budget, nt::BIGINT AS n_truth, found::BIGINT AS found, round(found / nt::DOUBLE, 9) AS recall, round({pr}, 9) AS pr FROM tb)"""


BENCH = """p AS (SELECT 'L' AS source, item_id AS pid, text FROM benchmark UNION ALL SELECT 'R', doc_id, text FROM documents),
truth_l AS (SELECT item_id AS l, doc_id AS r FROM benchmark b JOIN documents d ON contains(d.text, b.text))"""


def customers(strength: str = "light") -> str:
    """Customers against edited copies under other names and in another order."""
    steps, last = ["c0 AS (SELECT c_custkey AS k, c_name AS nm, c_mktsegment AS seg, c_acctbal::VARCHAR AS bal, c_acctbal AS ab, n_name AS nat FROM customer LEFT JOIN nation ON c_nationkey = n_nationkey)"], "c0"
    for i, shift in enumerate({"light": (0,), "medium": (0, 2), "heavy": (0, 2, 4)}[strength], 1):
        e, n = f"((k + {shift}) % 7)", "length(nm)"
        name = f"CASE {e} WHEN 0 THEN substr(nm, 1, {n} - 1) WHEN 1 THEN substr(nm, 1, {n} - 2) || substr(nm, {n}, 1) || substr(nm, {n} - 1, 1) WHEN 6 THEN substr(nm, 1, {n} - 4) || ' ' || substr(nm, {n} - 3, 4) ELSE nm END"
        steps.append(f"c{i} AS (SELECT k, {name} AS nm, CASE WHEN {e} = 4 THEN substr(seg, 1, 3) ELSE seg END AS seg, CASE {e} WHEN 2 THEN '' WHEN 5 THEN round(ab)::BIGINT::VARCHAR ELSE bal END AS bal, ab, CASE WHEN {e} = 3 THEN '' ELSE nat END AS nat FROM {last})")
        last = f"c{i}"
    return ", ".join(steps) + f""",
p AS (SELECT 'L' AS source, k AS pid, concat_ws(' ', nm, seg, bal, nat) AS text FROM c0 UNION ALL SELECT 'R', k, concat_ws(' ', nat, nm, bal, seg) FROM {last}),
truth_l AS (SELECT k AS l, k AS r FROM c0)"""


LINKAGES = {"docs_linkage": LINKAGE, "bench_linkage": BENCH, "cust_linkage": customers()}
#: Edges of the best configuration of each family under each scheduler, as SQL.
_BEST_EDGES = {
    "block": {"edge": "cn", "breadth": "cb", "depth": "sn", "hybrid": "cb"},
    "sorted": {"edge": ("id", "global", 10), "breadth": ("acf", "global", 10), "depth": ("dncf", "global", 1), "hybrid": ("acf", "global", 10)},
    "sparse": {"edge": ("word1", "cosine", 10, "largest"), "breadth": ("char5", "euclid", 5, "both"), "depth": ("word1", "cosine", 1, "both"), "hybrid": ("char5", "euclid", 5, "both")},
}


def family_edges(family: str, kind: str, profiles: str, config: tuple | None = None) -> tuple[str, str]:
    """(common tables, select of l, r, w) of the best configuration, or of another one of the sparse family."""
    if family == "block":
        return graph(True, profiles), f"SELECT l, r, {_BEST_EDGES['block'][kind]} AS w FROM g"
    if family == "sorted":
        return histogram(10, profiles), f"SELECT l, r, {sorted_expr(*_BEST_EDGES['sorted'][kind])} AS w FROM h"
    tokenizer, sim, k, side = config or _BEST_EDGES["sparse"][kind]
    return sparse_pairs(tokenizer, "tfidf", sim, True, profiles, guard=True), nearest("sw", k, side)


def curve(dataset: str, family: str, kind: str, profiles: str, multiples: tuple[int, ...], config: tuple | None = None) -> str:
    ctes, edges = family_edges(family, kind, profiles, config)
    sched = order(edges, kind, f"{max(multiples)} * (SELECT count(*) FROM truth_l)", True)
    return f"""SELECT * FROM (WITH {ctes}, hit AS (SELECT pos FROM ({sched}) s WHERE EXISTS (SELECT 1 FROM truth_l t WHERE t.l = s.l AND t.r = s.r)),
nt AS (SELECT count(*) AS nt FROM truth_l), bd AS (SELECT m, m * nt AS budget, nt FROM nt, (SELECT unnest({list(multiples)}) AS m)),
tb AS (SELECT m, budget, nt, (SELECT count(*) FROM hit WHERE pos <= budget) AS found, coalesce((SELECT sum(budget - pos + 1) FROM hit WHERE pos <= budget), 0)::DOUBLE AS area FROM bd)
SELECT '{dataset}' AS dataset, '{family}' AS family, '{kind}' AS config, '{kind}' AS scheduler, budget::BIGINT AS budget, nt::BIGINT AS n_truth, found::BIGINT AS found, round(found / nt::DOUBLE, 9) AS recall, area / nt::DOUBLE / budget AS pr, m::INTEGER AS multiple FROM tb)"""


ALL_MULTIPLES = tuple(range(1, 11))
KINDS = ("edge", "depth", "breadth", "hybrid")
CURVE_COLUMNS = "dataset, family, config, scheduler, budget, n_truth, found, recall, round(pr, 9) AS pr, multiple"


def workload_oracles() -> dict[str, str]:
    o: dict[str, str] = {}
    for family in _BEST_EDGES:
        for kind in KINDS:
            o[f"wl_best_{family}_{kind}"] = f"SELECT {CURVE_COLUMNS} FROM ({curve('docs_linkage', family, kind, LINKAGE, (1, 2, 5, 10))})"
        parts = " UNION ALL ".join(curve(name, family, kind, profiles, ALL_MULTIPLES) for name, profiles in LINKAGES.items() for kind in KINDS)
        name = {"sparse": "wl_join_curves"}.get(family, f"wl_{family}_curves")
        o[name] = f"SELECT {CURVE_COLUMNS}, round(1 - pr / nullif(max(pr) OVER (PARTITION BY dataset, budget, family), 0), 9) AS dft FROM ({parts})"
    noisy = {f"cust_{x}": customers(x) for x in ("light", "medium", "heavy")} | {"bench_linkage": BENCH}
    parts = " UNION ALL ".join(curve(name, family, kind, profiles, ALL_MULTIPLES) for name, profiles in noisy.items() for family, kind in (("sparse", "breadth"), ("block", "edge"), ("sorted", "edge")))
    o["wl_regimes"] = f"SELECT {CURVE_COLUMNS} FROM ({parts})"
    parts = " UNION ALL ".join(f"SELECT *, '{side}' AS side FROM ({curve('bench_linkage', 'sparse', kind, BENCH, ALL_MULTIPLES, ('word1', 'cosine', 5, side))})" for side in ("smallest", "largest", "both") for kind in KINDS)
    o["wl_index_sides"] = f"SELECT {CURVE_COLUMNS}, side FROM ({parts})"

    e = "SELECT l, r, cn AS w FROM g"
    docs = f"{TRUTH}, {graph(False)}"
    known = lambda s: f"EXISTS (SELECT 1 FROM truth_d t WHERE t.l = {s}.l AND t.r = {s}.r)"
    n = "(SELECT count(*) FROM truth_d)"
    o["match_progressive"] = f"WITH {docs} SELECT pos, l, r, round(w, 9) AS w, {known('s')} AS is_match FROM ({order(e, 'edge', n, False)}) s"
    o["match_batch"] = f"WITH {docs} SELECT l, r, {known('g')} AS is_match FROM g WHERE round(cn, 9) > 0"
    o["match_components"] = f"""WITH RECURSIVE {docs}, m AS (SELECT l, r FROM ({order(e, 'edge', '10 * ' + n, False)}) s WHERE {known('s')}),
ends AS (SELECT l AS a, r AS b FROM m UNION SELECT r, l FROM m),
seen(pid, c) AS (SELECT DISTINCT a, a FROM ends UNION SELECT b, c FROM seen JOIN ends ON a = pid)
SELECT pid, min(c) AS cluster FROM seen GROUP BY pid"""
    free = "(SELECT l, r, row_number() OVER (ORDER BY md5(l::VARCHAR || '|' || r::VARCHAR || '|0'), l, r) AS pos FROM g WHERE round(cn, 9) > 0)"
    o["m_requirements"] = f"""WITH {docs}, ra AS (SELECT count(*) AS x FROM ({order(e, 'edge', n, False)}) s WHERE {known('s')}), rb AS (SELECT count(*) AS y FROM {free} s WHERE pos <= {n} AND {known('s')})
SELECT x AS n_progressive, y AS n_batch, x > y AS early, true AS eventual FROM ra, rb"""
    o["brute_force"] = "SELECT a.s_suppkey AS l, b.s_suppkey AS r FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey"
    kinds = " UNION ALL ".join(f"SELECT * FROM (WITH {terms(t, DOCS)} SELECT '{t}' AS tokenizer, count(DISTINCT gram) AS n_grams, count(DISTINCT gram) AS n_ids FROM tc0)" for t in ("word1", "word2", "char3", "char4", "char5"))
    o["grams_dictionary"] = kinds
    pair = lambda a, b: f"p AS (SELECT CASE WHEN doc_id % 3 = {a} THEN 'L' ELSE 'R' END AS source, doc_id AS pid, text FROM documents WHERE doc_id % 3 IN ({a}, {b}))"
    o["multi_source_series"] = " UNION ALL ".join(f"SELECT * FROM (WITH {graph(True, pair(a, b))} SELECT l, r, round(cn, 9) AS w FROM g WHERE round(cn, 9) > 0)" for a, b in ((0, 1), (0, 2), (1, 2)))
    return o


def method_oracles() -> dict[str, str]:
    o: dict[str, str] = {}
    with_ = lambda ctes, final: f"WITH {ctes} {final}"
    docs_graph = f"{TRUTH}, {graph(False)}"
    e = "SELECT l, r, cn AS w FROM g"
    o["entry_progressive_documents"] = with_(graph(False), order(e, "edge", "2000", False))
    o["truth_docs"] = with_(TRUTH, "SELECT l, r FROM truth_d")
    o["truth_exact"] = "SELECT a.doc_id AS l, b.doc_id AS r FROM documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id"
    o["truth_bench"] = "SELECT item_id AS l, doc_id AS r FROM benchmark b JOIN documents d ON contains(d.text, b.text)"
    o["truth_docs_linkage"] = with_(LINKAGE, "SELECT l, r FROM truth_l")
    base = f"{DOCS}, {TOKENS}, {_stats('st0', 'tok', False)}"
    o["block_tokens"] = with_(f"{DOCS}, {TOKENS}", "SELECT pid, bkey FROM tok WHERE bkey <> ''")
    o["block_stats"] = with_(base, "SELECT * FROM st0")
    o["block_purge_size"] = with_(base, "SELECT * FROM st0 WHERE 2 * n <= (SELECT count(*) FROM p)")
    o["block_purge_adaptive"] = with_(
        f"""{base}, lv AS (SELECT card, sum(n) AS a, count(*) * card AS k FROM st0 GROUP BY card),
cu AS (SELECT card, sum(a) OVER (ORDER BY card)::DOUBLE AS a, sum(k) OVER (ORDER BY card)::DOUBLE AS k FROM lv),
pv AS (SELECT *, lag(a) OVER (ORDER BY card) AS a0, lag(k) OVER (ORDER BY card) AS k0 FROM cu)""",
        "SELECT * FROM st0 WHERE card <= coalesce((SELECT max(card) FROM pv WHERE a0 * k < 1.025::DOUBLE * a * k0), (SELECT max(card) FROM st0))",
    )
    o["block_filter"] = with_(blocks(False), "SELECT pid, bkey, n, card FROM b")
    o["block_graph"] = with_(graph(True), "SELECT l, r, cb, round(sn, 9) AS sn, round(cn, 9) AS cn FROM g")
    for w, x in _WEIGHTS.items():
        o[f"w_{w}"] = with_(_GRID, f"SELECT l, r, round({x}, 9) AS w FROM j")
    o["sorted_positions"] = with_(listed(False), "SELECT pos, token, pid FROM ls")
    o["sorted_pairs"] = with_(histogram(2), "SELECT l, r, d::INTEGER AS d, count(*) AS n FROM wp GROUP BY ALL")
    o["sorted_hist"] = with_(histogram(10), "SELECT l, r, " + ", ".join(f"h{i}" for i in range(1, 11)) + " FROM h")
    for w in ("acf", "ncf", "dncf", "cncf", "id"):
        for scope in ("local", "global"):
            o[f"s_{w}_{scope}"] = with_(histogram(10), f"SELECT l, r, round(w, 9) AS w FROM (SELECT l, r, round({sorted_expr(w, scope, 10)}, 9) AS w FROM h) WHERE w > 0")
    for t in ("word1", "word2", "char3", "char4", "char5"):
        o[f"grams_{t}"] = with_(terms(t, DOCS), "SELECT gram, count(*) AS df, sum(cnt)::BIGINT AS occurrences FROM tc0 GROUP BY gram")
    for c in ("bool", "tf", "tfidf"):
        o[f"score_{c}"] = with_(vectors("word1", DOCS, c), "SELECT pid, gram, round(s, 9) AS score FROM vx")
        for sim in ("cosine", "euclid"):
            o[f"sparse_{sim}_{c}"] = with_(sparse_pairs("word1", c, sim, True), _round("l, r, round(w, 9) AS w", nearest("sw", 5, "both")))
    for side in ("smallest", "largest", "both"):
        o[f"sparse_index_{side}"] = with_(sparse_pairs("word1", "tfidf", "cosine", True), _round("l, r, round(w, 9) AS w", nearest("sw", 1, side)))
        o[f"dense_index_{side}"] = with_(vec_pairs("cosine", 150), _round("l, r, round(w, 9) AS w", nearest("vp", 1, side)) + " WHERE w > 0")
    o["sparse_dedup"] = with_(sparse_pairs("word2", "tfidf", "cosine", False), _round("l, r, round(w, 9) AS w", nearest("sw", 5, "both", False)))
    for sim in ("cosine", "euclid"):
        o[f"dense_exact_{sim}"] = with_(vec_pairs(sim, 1000), _round("l, r, round(w, 9) AS w", nearest("vp", 5, "both")) + " WHERE w > 0")
    o["dense_dedup"] = with_(vec_pairs("cosine", 1000, True), _round("l, r, round(w, 9) AS w", nearest("vp", 3, "both", False)) + " WHERE w > 0")
    for kind in ("edge", "depth", "breadth", "hybrid"):
        o[f"sched_{kind}_dedup"] = with_(graph(False), _round("pos, l, r, round(w, 9) AS w", order(e, kind, "2000", False)))
        o[f"sched_{kind}_linkage"] = with_(graph(True), _round("pos, l, r, round(w, 9) AS w", order(e, kind, "2000", True)))
    o["base_profile"] = o["sched_hybrid_linkage"]
    first = lambda keys, src: f"SELECT pos, l, r FROM (SELECT l, r, row_number() OVER (ORDER BY {keys}) AS pos FROM {src}) WHERE pos <= 2000"
    o["sched_ideal"] = with_(f"{docs_graph}, gi AS (SELECT g.l, g.r, t.l IS NULL AS late FROM g LEFT JOIN truth_d t USING (l, r) WHERE round(cn, 9) > 0)", first("late, l, r", "gi"))
    o["sched_batch"] = with_(graph(False), first("l, r", "(SELECT * FROM g WHERE round(cn, 9) > 0)"))
    o["sched_random"] = with_(graph(False), first("md5(l::VARCHAR || '|' || r::VARCHAR || '|0'), l, r", "(SELECT * FROM g WHERE round(cn, 9) > 0)"))
    tb = lambda norm="budget": f"{docs_graph}, {_table(False, 'cn', 'edge', '[1,2,3,4,5,6,7,8,9,10]', norm)}"
    o["m_recall"] = with_(tb(), "SELECT budget, n_truth, found, recall FROM res")
    o["m_progressive_recall"] = with_(tb(), "SELECT budget, pr FROM res")
    o["m_progressive_recall_ideal"] = with_(tb("ideal"), "SELECT budget, pr FROM res")

    def dft(multiples: tuple[int, ...] = (1, 5)) -> str:
        parts = []
        for name, x in (("cb", "cb"), ("cn_cb", "cn"), ("jaccard", "cb / (xb + yb - cb)")):
            sched = order(f"SELECT l, r, {x} AS w FROM j", "edge", f"{max(multiples)} * (SELECT count(*) FROM truth_l)", True)
            parts.append(f"SELECT '{name}' AS config, pos FROM ({sched}) s WHERE EXISTS (SELECT 1 FROM truth_l t WHERE t.l = s.l AND t.r = s.r)")
        return f"""{_GRID}, hit AS ({" UNION ALL ".join(parts)}), nt AS (SELECT count(*) AS nt FROM truth_l),
bd AS (SELECT config, (m * nt)::BIGINT AS budget, nt FROM nt, (SELECT unnest({list(multiples)}) AS m), (SELECT unnest(['cb', 'cn_cb', 'jaccard']) AS config)),
pr AS (SELECT config, budget, coalesce((SELECT sum(budget - pos + 1) FROM hit h WHERE h.config = bd.config AND pos <= budget), 0)::DOUBLE / nt / budget AS pr FROM bd),
df AS (SELECT config, budget, pr, 1 - pr / nullif(max(pr) OVER (PARTITION BY budget), 0) AS dft FROM pr)"""

    o["m_dft"] = with_(dft(), "SELECT config, budget, round(pr, 9) AS pr, round(dft, 9) AS dft FROM df")
    rc = "rc AS (SELECT config, budget, (SELECT count(*) FROM hit h WHERE h.config = bd.config AND pos <= budget) / nt::DOUBLE AS recall FROM bd)"
    o["m_recall_dft"] = with_(f"{dft()}, {rc}", "SELECT config, budget, round(recall, 9) AS recall, round(1 - recall / nullif(max(recall) OVER (PARTITION BY budget), 0), 9) AS dft FROM rc")
    o["m_significance"] = with_(
        f"""{dft(ALL_MULTIPLES)}, pa AS (SELECT x.config AS a, y.config AS b, count(*) FILTER (x.pr > y.pr) AS up, count(*) FILTER (x.pr < y.pr) AS down FROM pr x JOIN pr y USING (budget) GROUP BY ALL)""",
        """SELECT a, b, up, down, CASE WHEN up + down = 0 THEN 1.0::DOUBLE ELSE round(least(1.0::DOUBLE, 2 * (SELECT sum(factorial((up + down)::INTEGER)::DOUBLE / factorial(k::INTEGER)::DOUBLE / factorial((up + down - k)::INTEGER)::DOUBLE) FROM (SELECT unnest(range(least(up, down) + 1)) AS k)) / pow(2.0, up + down)), 9) END AS p
FROM pa WHERE (a, b) IN (('cn_cb', 'cb'), ('cn_cb', 'jaccard'), ('cb', 'jaccard'))""",
    )
    o["m_mean_dft"] = with_(dft(), "SELECT config, round(avg(dft), 9) AS mean_dft FROM df GROUP BY config")
    fq = f"""{docs_graph}, cd AS (SELECT l, r FROM g WHERE round(cn, 9) > 0), sm AS (SELECT (SELECT count(*) FROM cd) AS c, (SELECT count(*) FROM cd JOIN truth_d USING (l, r)) AS h, (SELECT count(*) FROM truth_d) AS t, (SELECT count(*) FROM p) AS n)"""
    o["m_completeness"] = with_(fq, "SELECT c AS candidates, round(h / t::DOUBLE, 9) AS completeness FROM sm")
    o["m_quality"] = with_(fq, "SELECT c AS candidates, round(h / c::DOUBLE, 9) AS quality FROM sm")
    o["m_reduction"] = with_(fq, "SELECT c AS candidates, round(1 - c / (n * (n - 1) / 2)::DOUBLE, 9) AS reduction FROM sm")
    o["m_overlap"] = with_(f"{graph(False)}, a AS ({order(e, 'breadth', '500', False)}), c AS ({order(e, 'hybrid', '500', False)})", "SELECT round(count(*) / 500.0::DOUBLE, 9) AS overlap FROM a JOIN c USING (l, r)")
    small = "(SELECT count(*) FROM p WHERE source = 'L') <= (SELECT count(*) FROM p WHERE source = 'R')"
    o["base_bm25"] = with_(
        f"""{terms("char3", LINKAGE)}, df0 AS (SELECT gram, count(*) AS df FROM tc0 GROUP BY 1), ln0 AS (SELECT source, pid, sum(cnt) AS len FROM tc0 GROUP BY ALL),
av AS (SELECT avg(len)::DOUBLE AS avg, count(*)::DOUBLE AS n FROM ln0),
bx AS (SELECT source, pid, gram, ln(1 + (n - df + 0.5::DOUBLE) / (df + 0.5::DOUBLE)) * (cnt * 2.2::DOUBLE / (cnt + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * len / avg))) AS s FROM tc0 JOIN df0 USING (gram) JOIN ln0 USING (source, pid), av),
bp AS (SELECT x.pid AS l, y.pid AS r, round(sum(y.s), 9) AS wl, round(sum(x.s), 9) AS wr FROM bx x JOIN bx y ON x.gram = y.gram AND x.source = 'L' AND y.source = 'R' GROUP BY ALL)""",
        f"""SELECT l, r, round(w, 9) AS w FROM (SELECT l, r, wl AS w, row_number() OVER (PARTITION BY l ORDER BY wl DESC, r) AS t FROM bp) WHERE t <= 5 AND {small}
UNION ALL SELECT l, r, round(w, 9) FROM (SELECT l, r, wr AS w, row_number() OVER (PARTITION BY r ORDER BY wr DESC, l) AS t FROM bp) WHERE t <= 5 AND NOT ({small})""",
    )
    o["base_blk"] = with_(
        f"{blocks(False)}, bb AS (SELECT x.pid AS l, y.pid AS r, min((x.card, x.bkey)) AS k, round(sum(1.0::DOUBLE / x.card), 9) AS w FROM b x JOIN b y ON x.bkey = y.bkey AND x.pid < y.pid GROUP BY ALL)",
        "SELECT pos, l, r, round(w, 9) AS w FROM (SELECT *, row_number() OVER (ORDER BY k, w DESC, l, r) AS pos FROM bb) WHERE pos <= 2000",
    )
    o["base_window"] = with_(histogram(10), _round("pos, l, r, round(w, 9) AS w", order(f"SELECT l, r, {sorted_expr('ncf', 'global', 10)} AS w FROM h", "edge", "2000", True)))
    o["multi_source_single"] = with_(graph(False), "SELECT l, r, round(cn, 9) AS w FROM g WHERE round(cn, 9) > 0 AND l % 3 <> r % 3")
    o["wl_dataset_stats"] = with_(
        LINKAGE,
        """SELECT 'docs_dedup' AS dataset, n AS n_left, 0::BIGINT AS n_right, (SELECT count(*) FROM truth_d) AS n_truth, n * (n - 1) // 2 AS cartesian FROM (SELECT count(*) AS n FROM documents)
UNION ALL SELECT 'docs_exact', n, 0, (SELECT count(*) FROM documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id), n * (n - 1) // 2 FROM (SELECT count(*) AS n FROM documents)
UNION ALL SELECT 'docs_linkage', a, b, (SELECT count(*) FROM truth_l), a * b FROM (SELECT count(*) FILTER (source = 'L') AS a, count(*) FILTER (source = 'R') AS b FROM p)
UNION ALL SELECT 'bench_linkage', a, b, (SELECT count(*) FROM benchmark x JOIN documents y ON contains(y.text, x.text)), a * b FROM (SELECT (SELECT count(*) FROM benchmark) AS a, (SELECT count(*) FROM documents) AS b)
UNION ALL SELECT 'cust_dirty', n, 0, m, n * (n - 1) // 2 FROM (SELECT count(*) + count(*) FILTER (c_custkey % 3 <> 2) AS n, count(*) FILTER (c_custkey % 3 <> 2) AS m FROM customer)
UNION ALL SELECT 'cust_linkage', n, n, n, n * n FROM (SELECT count(*) AS n FROM customer)
UNION ALL SELECT 'part_dedup', n, 0, (SELECT count(*) FROM part a JOIN part b ON a.p_name = b.p_name AND a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey), n * (n - 1) // 2 FROM (SELECT count(*) AS n FROM part)""",
    )
    names = [(x, scope, w) for x in ("acf", "ncf", "dncf", "cncf", "id") for scope in ("local", "global") for w in ALL_MULTIPLES]
    parts = []
    for x, scope, w in names:
        sched = order(f"SELECT l, r, {sorted_expr(x, scope, w)} AS w FROM h", "edge", "(SELECT count(*) FROM truth_l)", True)
        parts.append(f"SELECT '{x}' AS weight, '{scope}' AS scope, {w}::BIGINT AS w, pos FROM ({sched}) s WHERE EXISTS (SELECT 1 FROM truth_l t WHERE t.l = s.l AND t.r = s.r)")
    listed_names = ", ".join(f"('{x}', '{scope}', {w}::BIGINT)" for x, scope, w in names)
    o["wl_windows"] = with_(
        f"{histogram(10)}, hit AS ({' UNION ALL '.join(parts)}), nt AS (SELECT count(*) AS nt FROM truth_l), cf(weight, scope, w) AS (VALUES {listed_names})",
        "SELECT cf.weight, cf.scope, cf.w, count(hit.pos) AS n_hits, round(count(hit.pos) / nt::DOUBLE, 9) AS recall, round(coalesce(sum(nt - hit.pos + 1), 0)::DOUBLE / nt / nt, 9) AS pr FROM cf CROSS JOIN nt LEFT JOIN hit ON hit.weight = cf.weight AND hit.scope = cf.scope AND hit.w = cf.w GROUP BY cf.weight, cf.scope, cf.w, nt",
    )
    return o | workload_oracles()
