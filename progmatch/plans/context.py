"""The relational operators around the methods, on the given tables, each with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.functions import udfs
from progmatch.functions.text import register_sql
from progmatch.plans.fixtures import Fixtures, table
from progmatch.streaming.incremental import sessions, windowed_counts

Query = Callable[[SparkSession, str], DataFrame]
_FOUND: dict[str, tuple[Query, str | None]] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        _FOUND[name] = (f, sql)
        return f

    return keep


def context_queries() -> dict[str, Query]:
    return {k: f for k, (f, _) in _FOUND.items()}


def context_oracles() -> dict[str, str]:
    return {k: sql for k, (_, sql) in _FOUND.items() if sql}


# --- scans, projections, filters

for _name, _cols in {"documents": "doc_id, lang, source, n_chars", "pages": "page_id, url", "events": "event_id, user_id, event_type", "part": "p_partkey, p_name, p_brand, p_size"}.items():
    query(f"scan_{_name}", f"SELECT {_cols} FROM {_name}")(lambda s, d, n=_name, c=_cols: table(s, d, n).select(*c.split(", ")))


@query("op_filter_docs", "SELECT doc_id, lang FROM documents WHERE n_chars BETWEEN 100 AND 5000 AND lang IN ('en', 'fr') AND regexp_matches(text, '[0-9]') AND source IS NOT DISTINCT FROM source")
def _filter_docs(s: SparkSession, d: str) -> DataFrame:
    docs = table(s, d, "documents")
    return docs.where(F.col("n_chars").between(100, 5000) & F.col("lang").isin("en", "fr") & F.col("text").rlike("[0-9]") & F.col("source").eqNullSafe(F.col("source"))).select("doc_id", "lang")


@query("op_project_profile", "SELECT 'L' AS source, c_custkey AS pid, concat_ws(' ', c_name, c_mktsegment, c_nationkey::VARCHAR) AS text FROM customer")
def _profile(s: SparkSession, d: str) -> DataFrame:
    from progmatch.sources.profiles import to_profiles

    return to_profiles(table(s, d, "customer"), "c_custkey", ["c_name", "c_mktsegment", "c_nationkey"])


# --- joins

_HASH = "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey"
query("op_join_hash", _HASH)(lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"))
_SMJ = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"
query("op_join_smj", _SMJ)(lambda s, d: table(s, d, "orders").hint("merge").join(table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"))
query("op_join_shuffle_hash", _SMJ)(lambda s, d: table(s, d, "orders").join(table(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"))


@query("op_join_bnlj", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey")
def _bnlj(s: SparkSession, d: str) -> DataFrame:
    n = table(s, d, "nation")
    a, b = n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")), n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb"))
    return a.join(F.broadcast(b), F.col("ra") < F.col("rb")).select("a", "b")


@query("op_join_range", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON b.s_acctbal > a.s_acctbal AND b.s_acctbal <= a.s_acctbal + 100")
def _range(s: SparkSession, d: str) -> DataFrame:
    """A row goes to its bin of width 100, the other side to its bin and the one before: an equi-join instead of all pairs."""
    p = table(s, d, "supplier").select("s_suppkey", "s_acctbal", F.floor(F.col("s_acctbal") / 100).alias("bin"))
    a = p.select(F.col("s_suppkey").alias("a"), F.col("s_acctbal").alias("x"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    b = p.select(F.col("s_suppkey").alias("b"), F.col("s_acctbal").alias("y"), "bin")
    return a.join(b, "bin").where("y > x and y <= x + 100").select("a", "b")


query("op_join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
query("op_join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
query("op_join_left", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", "o_orderkey"))
query("op_join_full", "SELECT s_suppkey, n_nationkey FROM supplier FULL JOIN nation ON s_nationkey = n_nationkey")(lambda s, d: table(s, d, "supplier").join(table(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"), "full").select("s_suppkey", "n_nationkey"))
query("op_join_cross", "SELECT r_regionkey, n_nationkey FROM region CROSS JOIN nation")(lambda s, d: table(s, d, "region").select("r_regionkey").crossJoin(F.broadcast(table(s, d, "nation").select("n_nationkey"))))


@query(
    "op_join_asof",
    """SELECT event_id, (SELECT arg_max(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'click' AND p.ts < e.ts) AS last_click
FROM events e WHERE event_type = 'purchase'""",
)
def _asof(s: SparkSession, d: str) -> DataFrame:
    """The last click of the user before each purchase: one window over the union of both, clicks behind purchases of the same time."""
    e = table(s, d, "events").where(F.col("event_type").isin("click", "purchase")).select("event_id", "user_id", "ts", "event_type")
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 1).otherwise(0), "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("last_click", F.last(click, ignorenulls=True).over(order)).where("event_type = 'purchase'").select("event_id", "last_click")


@query(
    "op_join_interval",
    "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR",
)
def _interval(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    a = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return a.join(b, "user_id").where(F.expr("tb > ta and tb <= ta + interval 6 hours")).select("a", "b")


# --- aggregation

query("op_agg_group", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, count(*) AS n, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY ALL")(
    lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.count(F.lit(1)).alias("n"), F.round(F.avg("l_discount"), 6).alias("disc"))
)
query("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
query("op_agg_approx")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median")))
for _kind in ("rollup", "cube"):
    query(f"op_agg_{_kind}", f"SELECT lang, source, count(*) AS n FROM documents GROUP BY {_kind}(lang, source)")(lambda s, d, k=_kind: getattr(table(s, d, "documents"), k)("lang", "source").agg(F.count(F.lit(1)).alias("n")))
query("op_agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")(
    lambda s, d: table(s, d, "documents").groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))
)
query("op_agg_maxby", "SELECT c_nationkey, arg_max(c_name, (c_acctbal, c_name)) AS richest, arg_min(c_name, (c_acctbal, c_name)) AS poorest FROM customer GROUP BY 1")(
    lambda s, d: table(s, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_name", F.struct("c_acctbal", "c_name")).alias("richest"), F.min_by("c_name", F.struct("c_acctbal", "c_name")).alias("poorest"))
)
query("op_agg_pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY 1")(
    lambda s, d: table(s, d, "documents").groupBy("source").pivot("lang", ["en", "fr"]).agg(F.count(F.lit(1))).na.fill(0, ["en", "fr"])
)
query("op_agg_filter", "SELECT lang, count(*) FILTER (n_chars > 1000) AS long_docs, array_to_string(list_sort(list_distinct(list(source))), ',') AS sources FROM documents GROUP BY 1")(
    lambda s, d: table(s, d, "documents").groupBy("lang").agg(F.expr("count(*) filter (where n_chars > 1000)").alias("long_docs"), F.array_join(F.sort_array(F.collect_set("source")), ",").alias("sources"))
)

# --- windows, order, sets



def _w():
    return Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")


query(
    "op_win_rank",
    """SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr
FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)""",
)(lambda s, d: table(s, d, "customer").select("c_custkey", F.row_number().over(_w()).alias("rn"), F.rank().over(_w()).alias("rk"), F.dense_rank().over(_w()).alias("dr"), F.ntile(4).over(_w()).alias("nt"), F.round(F.percent_rank().over(_w()), 6).alias("pr")))
query("op_win_leadlag", "SELECT c_custkey, lag(c_custkey) OVER w AS before, lead(c_custkey, 2) OVER w AS after, first_value(c_custkey) OVER w AS top FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")(
    lambda s, d: table(s, d, "customer").select("c_custkey", F.lag("c_custkey").over(_w()).alias("before"), F.lead("c_custkey", 2).over(_w()).alias("after"), F.first("c_custkey").over(_w()).alias("top"))
)
query("op_win_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3 FROM events")(
    lambda s, d: table(s, d, "events").select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 4).alias("last3"))
)
query("op_win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.count(F.lit(1)).over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-2, 2)).alias("near"))
)
query("op_win_running", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey), 2) AS running FROM orders")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(Window.partitionBy("o_custkey").orderBy("o_orderkey")), 2).alias("running"))
)
query("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")(lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey", "o_totalprice"))
query("op_topk_group", "SELECT c_custkey, c_nationkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")(
    lambda s, d: table(s, d, "customer").withColumn("rn", F.row_number().over(_w())).where("rn <= 3").select("c_custkey", "c_nationkey")
)
query("op_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 100")(lambda s, d: table(s, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(100).limit(50))
query("op_set_union", "SELECT n_name AS name FROM nation UNION SELECT r_name FROM region")(lambda s, d: table(s, d, "nation").select(F.col("n_name").alias("name")).union(table(s, d, "region").select("r_name")).distinct())
query("op_set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")(lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(s, d, "supplier").select("s_nationkey")))
query("op_set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")(lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(s, d, "supplier").select("s_nationkey")))
query("op_set_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier")(lambda s, d: table(s, d, "nation").select(F.col("n_nationkey").alias("k")).subtract(table(s, d, "supplier").select("s_nationkey")))
query("op_set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")(lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(table(s, d, "supplier").select("s_nationkey")))

# --- functions

query(
    "op_string",
    "SELECT c_custkey, lower(c_name) AS lo, substr(c_name, 1, 4) AS head, length(c_name) AS n, md5(c_name) AS h, regexp_replace(c_name, '[0-9]+', '#', 'g') AS masked, regexp_extract(c_name, '([0-9]+)', 1) AS digits, translate(c_mktsegment, 'AEIOU', '12345') AS t, levenshtein(c_name, c_mktsegment) AS lev, concat_ws('-', c_name, c_mktsegment) AS joined FROM customer",
)(
    lambda s, d: table(s, d, "customer").select("c_custkey", F.lower("c_name").alias("lo"), F.substring("c_name", 1, 4).alias("head"), F.length("c_name").alias("n"), F.md5("c_name").alias("h"), F.regexp_replace("c_name", "[0-9]+", "#").alias("masked"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("digits"), F.translate("c_mktsegment", "AEIOU", "12345").alias("t"), F.levenshtein("c_name", "c_mktsegment").alias("lev"), F.concat_ws("-", "c_name", "c_mktsegment").alias("joined"))
)
query(
    "op_math",
    "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS sq, round(ln(p_retailprice), 6) AS lg, round(pow(p_size, 1.5), 6) AS pw, greatest(p_size, 10) AS g, abs(10 - p_size) AS ab, ceil(p_retailprice)::BIGINT AS c, round(p_retailprice / nullif(p_size - 5, 0), 6) AS q FROM part",
)(
    lambda s, d: table(s, d, "part").select("p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("sq"), F.round(F.ln("p_retailprice"), 6).alias("lg"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("pw"), F.greatest("p_size", F.lit(10)).alias("g"), F.abs(10 - F.col("p_size")).alias("ab"), F.ceil("p_retailprice").alias("c"), F.round(F.try_divide("p_retailprice", F.col("p_size") - 5), 6).alias("q"))
)
query(
    "op_date",
    "SELECT event_id, date_trunc('day', ts)::TIMESTAMP AS day, extract('hour' FROM ts)::INTEGER AS hour, date_diff('day', DATE '2020-01-01', ts::DATE)::INTEGER AS days, ts + INTERVAL 90 MINUTE AS later FROM events",
)(
    lambda s, d: table(s, d, "events").select("event_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"), F.hour("ts").alias("hour"), F.datediff(F.col("ts").cast("date"), F.lit("2020-01-01").cast("date")).alias("days"), F.expr("ts + interval 90 minutes").alias("later"))
)
query(
    "op_array",
    "SELECT vec_id, len(embedding)::INTEGER AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, round(list_max(embedding)::DOUBLE, 5) AS top FROM embeddings",
)(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda t, x: t + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max("embedding").cast("double"), 5).alias("top"))
)
query("op_explode", "SELECT doc_id, w, i FROM (SELECT doc_id, unnest(string_split(lower(source) || ' ' || lang, ' ')) AS w, unnest(range(2))::INTEGER AS i FROM documents)")(
    lambda s, d: table(s, d, "documents").select("doc_id", F.posexplode(F.split(F.concat_ws(" ", F.lower("source"), "lang"), " ")).alias("i", "w"))
)
query("op_map")(lambda s, d: table(s, d, "documents").select("doc_id", F.map_from_arrays(F.array(F.lit("lang"), F.lit("source")), F.array("lang", "source")).alias("m")).select("doc_id", F.array_join(F.map_values("m"), " ").alias("text"), F.size(F.map_keys("m")).alias("n")))
query("op_json", "SELECT event_id, json_keys(props)[1] AS first_key, length(props) AS n FROM events")(
    lambda s, d: table(s, d, "events").select("event_id", F.get(F.json_object_keys("props"), F.lit(0)).alias("first_key"), F.length("props").alias("n"))
)
query("op_html_title", "SELECT page_id, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) AS title FROM pages")(lambda s, d: table(s, d, "pages").select("page_id", F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1)).alias("title")))

# --- streams as batches, functions of our own

query("st_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS window_start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS window_end, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")(
    lambda s, d: windowed_counts(table(s, d, "events"), "1 hour").withColumn("total", F.round("total", 4))
)
query(
    "st_sliding",
    "SELECT b AS window_start, b + INTERVAL 1 HOUR AS window_end, event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT event_type, value, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS b FROM events) GROUP BY ALL",
)(lambda s, d: windowed_counts(table(s, d, "events"), "1 hour", "30 minutes").withColumn("total", F.round("total", 4)))
query(
    "st_session",
    """WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 1 ELSE 0 END AS brk FROM events),
k AS (SELECT *, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
SELECT user_id, min(ts) AS session_start, max(ts) + INTERVAL 1 HOUR AS session_end, count(*) AS n FROM k GROUP BY user_id, sid""",
)(lambda s, d: sessions(table(s, d, "events"), "1 hour"))


@query("udf_sql_ngrams", r"SELECT page_id, list_transform(range(1, length(t) - 1), lambda i: substr(t, i, 3)) AS grams FROM (SELECT page_id, trim(regexp_replace(lower(url), '[^\p{L}\p{N}]+', ' ', 'g')) AS t FROM pages)")
def _sql_ngrams(s: SparkSession, d: str) -> DataFrame:
    register_sql(s)
    table(s, d, "pages").createOrReplaceTempView("progmatch_pages")
    return s.sql("SELECT page_id, char_ngrams(url, 3) AS grams FROM progmatch_pages")


@query("udf_pandas", "SELECT doc_id, round(least(length(lang), length(source)) / greatest(length(lang), length(source), 1)::DOUBLE, 6) AS ratio FROM documents")
def _pandas(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "documents").select("doc_id", F.round(udfs.length_ratio("lang", "source"), 6).alias("ratio"))


@query("udf_table", "SELECT c_custkey, unnest(list_transform(range(1, length(c_mktsegment) - 1), lambda i: substr(c_mktsegment, i, 3))) AS gram FROM customer")
def _table_function(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    table(s, d, "customer").createOrReplaceTempView("progmatch_customer")
    return s.sql("SELECT c_custkey, gram FROM progmatch_customer, LATERAL char_grams(c_mktsegment, 3)")


@query("udf_aggregate", "SELECT c_nationkey, round(avg(c_acctbal), 4) AS mean FROM customer GROUP BY 1")
def _aggregate(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "customer").groupBy("c_nationkey").agg(F.round(udfs.mean_weight("c_acctbal"), 4).alias("mean"))


@query("view_progressive_pairs")
def _views(s: SparkSession, d: str) -> DataFrame:
    """Temp views profiles, blocks, edges and schedule, and SQL over them."""
    from progmatch.plans.workloads import block_edges, docs_blocks, schedule

    fx = Fixtures(s, d)
    fx.docs().profiles.createOrReplaceTempView("profiles")
    docs_blocks(fx, False)[0].createOrReplaceTempView("blocks")
    edges = block_edges(fx, "cn_cb", False)
    edges.createOrReplaceTempView("edges")
    schedule(edges, "edge", 100).createOrReplaceTempView("schedule")
    return s.sql("SELECT pos, s.l, s.r, s.w, length(a.text) AS n_l, length(b.text) AS n_r FROM schedule s JOIN profiles a ON a.pid = s.l JOIN profiles b ON b.pid = s.r")
