"""Mixing sources to target weights, made of DataFrame functions only.

Sizes are counted per source with partial aggregation, each source's repetition rate is target / size, and a document is
emitted floor(rate) times plus once more if its hash-seeded draw falls below the rate's fraction. A digest of doc_id, text
and seed holds DRAWS draws of each document; each source takes the one by which its words come nearest to its target (the
first of equals), as a few long texts could else miss it by far. Reruns agree; rows with equal ids and texts draw alike. Null
texts have size 0, a null source is a source of its own and comes last; a source without words has rate 0. An empty table
gives an empty result. Columns of docs with the names of results (size, source_size, target, copies) are replaced by
with_copies; mixed returns the rows as they were.

The table of sources has one row for each source and is ordered in one task; documents are never ordered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.llm.common import SPACE, settle, table

WEIGHTS = (3, 1, 2)
SHARE = 1.5
CEILING = 2.0
#: A table of sources of at most this many rows is broadcast; a larger one is joined by a shuffle.
BROADCAST_ROWS = 10_000
DRAWS = 16
RESULTS = ("size", "source_size", "target", "copies")


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(SPACE.replace("[", "[^"))), F.lit(0)).cast("long")


def source_targets(sized: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, ceiling: float = CEILING) -> DataFrame:
    """(source, source_size, target): `share` of all sizes dealt by weight; a target stops at `ceiling` times its source.

    Resharing the excess by weight among the rest until none is above ends at min(ceiling * size, level * weight) for one
    level. A source is at its ceiling if the ceilings up to its own ratio of ceiling to weight, and that ratio times the
    weights beyond, fit into what is dealt: one pass instead of rounds.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int"))
    per = per.withColumn("w", weight).withColumn("cap", ceiling * F.col("source_size")).withColumn("ratio", F.col("cap") / F.col("w"))
    upto, whole = Window.orderBy("ratio"), Window.partitionBy()
    per = per.withColumn("dealt", share * F.sum("source_size").over(whole))
    per = per.withColumn("fill", F.sum("cap").over(upto) + F.col("ratio") * (F.sum("w").over(whole) - F.sum("w").over(upto)))
    per = per.withColumn("full", F.col("fill") <= F.col("dealt"))
    left = F.col("dealt") - F.coalesce(F.sum(F.when(F.col("full"), F.col("cap"))).over(whole), F.lit(0.0))
    open_w = F.sum(F.when(~F.col("full"), F.col("w"))).over(whole)
    level = F.try_divide(left, open_w)
    return per.select("source", "source_size", F.when(F.col("full"), F.col("cap")).otherwise(F.least("cap", level * F.col("w"))).alias("target"))


def draw(digest: Column, k: int) -> Column:
    """A number in [0, 1) from 52 bits of a digest, from its k-th hexadecimal digit on."""
    return F.conv(F.substring(digest, k + 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def with_copies(docs: DataFrame, seed: int = 7, **shares) -> DataFrame:
    """Adds size, source_size, target and copies, the number of times the mix takes the document."""
    sized = docs.drop(*RESULTS).withColumn("size", n_words(F.col("text")))
    per = settle(source_targets(sized.select("source", "size"), **shares), "sources").withColumnRenamed("source", "__source")
    few = per.count() <= BROADCAST_ROWS
    rate = F.coalesce(F.try_divide(F.col("target"), F.col("source_size").cast("double")), F.lit(0.0))
    per = per.withColumn("__whole", F.floor(rate)).withColumn("__part", rate - F.floor(rate))
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit(":"), F.md5(F.coalesce("text", F.lit("")))))
    beside = lambda df, table: df.join(F.broadcast(table) if few else table, df["source"].eqNullSafe(table["__source"]), "left")

    drawn = beside(sized.select("source", "size", digest.alias("__digest")), per.select("__source", "__part"))
    extras = drawn.groupBy(F.col("source").alias("__of")).agg(*[F.sum(F.when(draw(F.col("__digest"), k) < F.col("__part"), F.col("size")).otherwise(0)).alias(f"x{k}") for k in range(DRAWS)])
    misses = F.array(*[F.round(F.abs(F.col("__whole") * F.col("source_size") + F.col(f"x{k}") - F.col("target")), 3) for k in range(DRAWS)])
    per = per.join(extras, per["__source"].eqNullSafe(extras["__of"])).select("__source", "source_size", "target", "__whole", "__part", (F.array_position(misses, F.array_min(misses)) - 1).cast("int").alias("__k"))
    per = settle(per, "draws")

    joined = beside(sized.withColumn("__digest", digest), per).drop("__source")
    own = F.element_at(F.array(*[draw(F.col("__digest"), k) for k in range(DRAWS)]), F.col("__k") + 1)
    return joined.withColumn("copies", (F.col("__whole") + (own < F.col("__part")).cast("int")).cast("int")).drop("__whole", "__part", "__k", "__digest")


def mixed(docs: DataFrame, seed: int = 7, **shares) -> DataFrame:
    """The documents of the mix: each row as often as its copies say."""
    carried = docs.select("doc_id", "source", "text", F.struct("*").alias("__row"))
    taken = with_copies(carried, seed, **shares).where("copies > 0")
    return taken.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("__row.*")


def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    made = with_copies(docs)
    return made.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), (F.col("size") * F.col("copies")).alias("taken"), F.col("copies").cast("long").alias("copies"))


OP4_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, md5('7:' || coalesce(doc_id::VARCHAR, 'null') || ':' || md5(coalesce(text, ''))) AS h, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, CASE (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0 WHEN 1 THEN 1.0 ELSE 2.0 END::DOUBLE AS w FROM per),
capped AS (SELECT *, 2.0::DOUBLE * source_size AS cap, 2.0::DOUBLE * source_size / w AS ratio, 1.5::DOUBLE * (SELECT sum(source_size) FROM per)::DOUBLE AS dealt FROM ranked),
filled AS (SELECT c.*, (SELECT sum(x.cap) FROM capped x WHERE x.ratio <= c.ratio) + c.ratio * coalesce((SELECT sum(x.w) FROM capped x WHERE x.ratio > c.ratio), 0) <= dealt AS is_full FROM capped c),
level AS (SELECT (max(dealt) - coalesce(sum(cap) FILTER (is_full), 0)) / sum(w) FILTER (NOT is_full) AS v FROM filled),
targets AS (SELECT source, source_size, CASE WHEN is_full THEN cap ELSE least(cap, (SELECT v FROM level) * w) END AS target FROM filled),
rated AS (SELECT s.*, t.source_size, t.target, CASE WHEN t.source_size = 0 THEN 0.0 ELSE t.target / t.source_size END AS rate
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
tried AS (SELECT source, k, any_value(rate) AS rate, any_value(source_size) AS source_size, any_value(target) AS target,
  sum(CASE WHEN ('0x' || substr(h, k + 1, 13))::BIGINT / 4503599627370496.0::DOUBLE < rate - floor(rate) THEN size ELSE 0 END) AS extra
  FROM rated, (SELECT unnest(range(16)) AS k) GROUP BY source, k),
chosen AS (SELECT source, k FROM tried QUALIFY row_number() OVER (PARTITION BY source ORDER BY round(abs(floor(rate) * source_size + extra - target), 3), k) = 1),
counted AS (SELECT r.*, (floor(rate) + CASE WHEN ('0x' || substr(h, c.k + 1, 13))::BIGINT / 4503599627370496.0::DOUBLE < rate - floor(rate) THEN 1 ELSE 0 END)::BIGINT AS copies
  FROM rated r JOIN chosen c ON r.source IS NOT DISTINCT FROM c.source)
SELECT doc_id, size, source_size, round(target, 6) AS target, size * copies AS taken, copies FROM counted
"""
