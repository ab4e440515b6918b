"""Document fingerprints as threshold-scaled sketches, made of DataFrame functions only.

A sketch keeps every shingle hash below a fixed fraction of the hash range, so its size follows the document, two
sketches can be merged by union, and the share of one that lies in the other estimates containment even between very
unequal documents. Shingles have five words; a text of one to four words is one shingle, an empty text is the shingle of
no words. A sketch that would be empty keeps its lowest hash, so that equal texts always have equal, non-empty sketches.
Null texts count as empty, repeated rows give repeated results, further columns are kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.llm.common import SHINGLE_WORDS, settle, shuffle_width, table
from progmatch.llm.native_text import with_shingle_hashes, with_word_hashes

FRACTION = 0.25


def _top(fraction: float) -> int:
    return min(2**63 - 1, -(2**63) + int(fraction * 2**64))


def with_sketch(df: DataFrame, text: str, out: str, fraction: float = FRACTION, size: int = SHINGLE_WORDS) -> DataFrame:
    """Adds `out`: the ascending array of the distinct shingle hashes below `fraction` of the 64-bit range."""
    if not 0 < fraction <= 1:
        raise ValueError(f"fraction must lie in (0, 1]: {fraction}")
    top = _top(fraction)
    h, g, s = f"__{out}_h", f"__{out}_g", f"__{out}_s"
    df = with_shingle_hashes(with_word_hashes(df, text, h), h, g, size)
    short = F.array(F.xxhash64(F.array_join(F.transform(F.col(h), lambda x: x.cast("string")), ",")))
    df = df.withColumn(g, F.when(F.size(g) > 0, F.col(g)).otherwise(short))
    df = df.withColumn(s, F.array_distinct(F.filter(F.col(g), lambda x: x <= F.lit(top))))
    kept = F.when(F.size(s) > 0, F.sort_array(F.col(s))).otherwise(F.array(F.array_min(F.col(g))))
    return df.withColumn(out, kept).drop(h, g, s)


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard similarity of the shingle sets."""
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def containment(a: Column, b: Column, fraction: float = FRACTION) -> Column:
    """Estimated share of the first document's shingles that the second has; null where the first kept only its lowest hash.

    Such a hash lies above the limit, so a longer document's sketch could not hold it.
    """
    return F.when(F.get(a, F.lit(0)) <= _top(fraction), F.size(F.array_intersect(a, b)) / F.size(a))


def merged(sketches: DataFrame, key: str, sketch: str) -> DataFrame:
    """The sketch of each key's documents together, as rows (key, hash): one row for each hash, never one huge array."""
    return sketches.select(key, F.explode(sketch).alias("hash")).distinct()


def as_text(sketch: Column) -> Column:
    return F.array_join(F.transform(sketch, lambda x: F.lpad(F.hex(x), 16, "0")), "")


def with_follower(docs: DataFrame, carried: list[str], ranges: int) -> DataFrame:
    """Adds next_<c> for each carried column: its value in the next document, by descending doc_id; after the last, the first.

    The documents are dealt to ranges of (doc_id, text hash) and settled with their range's number; the first row of each
    range is also sent to the range before it (that of the first to the last), so a range finds the follower of its last row.
    Documents without an id come last; equal or missing ids follow one another by their text's hash, and can fill many
    ranges. Columns of the names added are replaced.
    """
    docs = docs.drop(*[f"next_{c}" for c in carried])
    key = [F.col("doc_id").desc_nulls_last(), F.col("__h")]
    ranged = docs.withColumn("__h", F.xxhash64("text")).repartitionByRange(ranges, *key).withColumn("__at", F.spark_partition_id())
    ranged = settle(ranged, "ranged", large=True)
    place = F.row_number().over(Window.partitionBy("__at").orderBy(*key))
    heads = ranged.withColumn("__n", place).where("__n = 1").drop("__n")  # a row for each range: the group limit comes before the shuffle
    number = Window.orderBy("__at")
    last = F.max("__at").over(Window.partitionBy())
    lent = heads.withColumn("__at", F.coalesce(F.lag("__at").over(number), last)).withColumn("__halo", F.lit(1))
    order = Window.partitionBy("__at").orderBy("__halo", *key)
    seen = ranged.withColumn("__halo", F.lit(0)).unionByName(lent).repartition(ranges, "__at")
    seen = seen.withColumn("__next", F.lead(F.struct(*carried)).over(order)).where("__halo = 0")
    return seen.select(*docs.columns, *[F.col(f"__next.{c}").alias(f"next_{c}") for c in carried])


def op2_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    pairs = with_follower(docs, ["text"], shuffle_width(spark))
    pairs = pairs.withColumn("n_chars", F.length("text").cast("long"))
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    pairs = pairs.withColumn("edited", F.concat(F.substring("text", F.lit(1), F.col("n_chars").cast("int") - cut), F.substring("next_text", F.lit(1), cut)))
    made = with_sketch(with_sketch(with_sketch(pairs, "text", "a"), "edited", "b"), "next_text", "c")
    return made.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        as_text(F.col("a")).alias("fingerprint"),
        as_text(F.col("b")).alias("edited_fingerprint"),
        likeness(F.col("a"), F.col("b")).alias("near_edited"),
        likeness(F.col("a"), F.col("c")).alias("near_next"),
        containment(F.col("a"), F.col("b")).alias("contained_edited"),
        containment(F.col("a"), F.col("c")).alias("contained_next"),
        F.size("a").cast("long").alias("n_kept"),
    )
