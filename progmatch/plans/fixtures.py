"""Matching tasks and ground truth on the given tables; each is settled once for a session and folder."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.operators import setjoin
from progmatch.operators.encoders import jittered
from progmatch.operators.pairs import meet_evenly
from progmatch.session import settle
from progmatch.sources.profiles import Task, to_profiles

_KEPT: dict[tuple, DataFrame] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def once(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        made = make()
        _KEPT[key] = made if "settled_at" in vars(made) else settle(made, name)  # what is settled is not written twice
    return _KEPT[key]


def kept(spark: SparkSession, sf_dir: str, name: str) -> bool:
    return (spark.sparkContext.applicationId, sf_dir, name) in _KEPT


def forget() -> None:
    """Everything is computed anew from here on."""
    _KEPT.clear()


def shingle_truth(profiles: DataFrame, least: float = 0.5) -> DataFrame:
    """(l, r): pairs whose sets of three-word shingles have a Jaccard similarity of `least` or more."""
    return setjoin.similar_texts(profiles, 3, least)


#: Bytes of texts that are searched at once; passages are looked for by their first ANCHOR bytes.
SEARCHED, ANCHOR = 1 << 22, 8


def places_of(data: np.ndarray, anchors: np.ndarray) -> np.ndarray:
    """Where in the bytes one of the anchors (64-bit numbers, ascending) begins."""
    found, seen = [], np.zeros(1 << 16, bool)
    mixed = lambda x: (x * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(48)).astype(np.int64)
    seen[mixed(anchors)] = True
    for a in range(0, len(data) - ANCHOR + 1, SEARCHED):
        here = data[a : a + SEARCHED + ANCHOR - 1]
        x = np.ndarray((len(here) - ANCHOR + 1,), "<u8", here, strides=(1,)).copy()
        at = np.flatnonzero(seen[mixed(x)])
        found.append(a + at[np.isin(x[at], anchors)])
    return np.concatenate(found) if found else np.empty(0, np.int64)


def holders(docs: DataFrame, items: DataFrame) -> DataFrame:
    """(l, r): texts r that hold the passage l byte for byte. docs: (r, text); items: (l, passage), sent to every task."""
    rows = [(r["l"], bytes(r["p"])) for r in items.select("l", F.encode("passage", "UTF-8").alias("p")).where("p is not null").collect()]
    by_head: dict[bytes, list[tuple[int, bytes]]] = {}
    for row in rows:
        by_head.setdefault(row[1][:ANCHOR], []).append(row)
    anchors = np.sort(np.array([int.from_bytes(x, "little") for x in by_head if len(x) == ANCHOR], np.uint64))
    known = docs.sparkSession.sparkContext.broadcast((by_head, anchors, [x for x in rows if len(x[1]) < ANCHOR]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_head, anchors, short = known.value
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist()
            ends = np.cumsum([len(t or b"") for t in texts])
            data = b"".join(t or b"" for t in texts)
            found = {(k, l): None for k, t in enumerate(texts) if t is not None for l, passage in short if passage in t}  # noqa: E741
            places = places_of(np.frombuffer(data, np.uint8), anchors) if len(anchors) else ()
            for at, k in zip(places, np.searchsorted(ends, places, "right"), strict=True):
                for l, passage in by_head[data[at : at + ANCHOR]]:  # noqa: E741
                    if at + len(passage) <= ends[k] and data.startswith(passage, at):
                        found[int(k), l] = None
            yield pa.RecordBatch.from_arrays([pa.array([l for _, l in found], pa.int64()), pa.array([ids[k] for k, _ in found], pa.int64())], ["l", "r"])

    return docs.select("r", "text").mapInArrow(run, "l long, r long")


class Fixtures:
    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def _once(self, name: str, make: Callable[[], DataFrame]) -> DataFrame:
        return once(self.spark, self.sf_dir, name, make)

    def _table(self, name: str) -> DataFrame:
        return table(self.spark, self.sf_dir, name)

    def docs(self) -> Task:
        return Task(to_profiles(self._table("documents"), "doc_id", ["text"]), "dedup")

    def docs_truth(self) -> DataFrame:
        return self._once("docs_truth", lambda: shingle_truth(self.docs().profiles))

    def exact_truth(self) -> DataFrame:
        """Equal texts: pairs of the ids of each text."""
        d = self._table("documents").where("text is not null").select(F.lit("L").alias("source"), F.col("doc_id").alias("pid"), F.sha2("text", 256).alias("t"))
        return meet_evenly(d, "t", d.groupBy("t").agg(F.count(F.lit(1)).alias("n")), False, [], [])

    def docs_linkage(self) -> Task:
        """Texts are read from the table each time: only the ids left out are settled."""
        gone = self._once("docs_gone", lambda: self.docs_truth().where("l % 2 = r % 2").select(F.col("r").alias("pid")).distinct())
        few = gone.count() <= 500_000
        left = self.docs().profiles.join(F.broadcast(gone) if few else gone, "pid", "left_anti")
        return Task(left.select(F.when(F.col("pid") % 2 == 0, "L").otherwise("R").alias("source"), "pid", "text"), "linkage")

    def docs_linkage_truth(self) -> DataFrame:
        def make() -> DataFrame:
            p = self.docs_linkage().profiles.select("pid", "source")
            t = self.docs_truth().where("l % 2 <> r % 2")
            t = t.select(F.when(F.col("l") % 2 == 0, F.col("l")).otherwise(F.col("r")).alias("l"), F.when(F.col("l") % 2 == 0, F.col("r")).otherwise(F.col("l")).alias("r"))
            return t.join(p.select(F.col("pid").alias("l")), "l", "left_semi").join(p.select(F.col("pid").alias("r")), "r", "left_semi").select("l", "r")

        return self._once("docs_linkage_truth", make)

    def bench_linkage(self) -> Task:
        b = to_profiles(self._table("benchmark"), "item_id", ["text"], "L")
        return Task(b.unionByName(to_profiles(self._table("documents"), "doc_id", ["text"], "R")), "linkage")

    def bench_truth(self) -> DataFrame:
        """Documents that hold a passage word for word. Passages are few: they are broadcast behind a check of their number."""
        items = self._table("benchmark").select(F.col("item_id").alias("l"), F.col("text").alias("passage"))
        if items.count() > 10_000:
            raise ValueError("too many passages to look for one by one")
        docs = self._table("documents").select(F.col("doc_id").cast("long").alias("r"), "text")
        return self._once("bench_truth", lambda: holders(docs, items))

    # --- customers and edited copies

    def _originals(self) -> DataFrame:
        c, n = self._table("customer"), self._table("nation").select("n_nationkey", "n_name")
        return c.join(n, F.col("c_nationkey") == F.col("n_nationkey"), "left").select("c_custkey", "c_name", "c_mktsegment", F.col("c_acctbal").cast("string").alias("bal"), "c_acctbal", "n_name")

    def _edited(self, strength: str) -> DataFrame:
        """Edits by c_custkey % 7, more of them with strength: all plain string functions."""
        c = self._originals()
        for shift in {"light": (0,), "medium": (0, 2), "heavy": (0, 2, 4)}[strength]:
            e = (F.col("c_custkey") + shift) % 7
            n = F.length("c_name")
            sub = lambda a, b=None: F.substring("c_name", a, b) if b is not None else F.substring("c_name", a, n)
            name = (
                F.when(e == 0, sub(F.lit(1), n - 1))
                .when(e == 1, F.concat(sub(F.lit(1), n - 2), sub(n, F.lit(1)), sub(n - 1, F.lit(1))))
                .when(e == 6, F.concat(sub(F.lit(1), n - 4), F.lit(" "), sub(n - 3, F.lit(4))))
                .otherwise(F.col("c_name"))
            )
            c = c.select("c_custkey", name.alias("c_name"), F.when(e == 4, F.substring("c_mktsegment", 1, 3)).otherwise(F.col("c_mktsegment")).alias("c_mktsegment"), F.when(e == 2, "").when(e == 5, F.round("c_acctbal").cast("long").cast("string")).otherwise(F.col("bal")).alias("bal"), "c_acctbal", F.when(e == 3, "").otherwise(F.col("n_name")).alias("n_name"))
        return c

    def cust_dirty(self, strength: str = "light", replicas: int = 1) -> Task:
        text = lambda d: d.select("c_custkey", F.concat_ws(" ", "c_name", "c_mktsegment", "bal", "n_name").alias("text"))
        rows = text(self._originals()).union(text(self._edited(strength)).where("c_custkey % 3 <> 2").select(F.col("c_custkey") + 10_000_000, "text"))
        rows = rows.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(replicas - 1))))
        name = F.when(F.col("rep") == 0, F.col("text")).otherwise(F.regexp_replace("text", F.lit("#"), F.concat(F.lit("#"), F.col("rep").cast("string"))))
        return Task(rows.select(F.lit("L").alias("source"), (F.col("c_custkey") + 20_000_000 * F.col("rep")).alias("pid"), name.alias("text")), "dedup")

    def cust_truth(self, replicas: int = 1) -> DataFrame:
        keys = self._table("customer").where("c_custkey % 3 <> 2").select("c_custkey", F.explode(F.sequence(F.lit(0), F.lit(replicas - 1))).alias("rep"))
        l = F.col("c_custkey") + 20_000_000 * F.col("rep")  # noqa: E741
        return keys.select(l.alias("l"), (l + 10_000_000).alias("r"))

    def cust_linkage(self, strength: str = "light") -> Task:
        left = self._originals().select(F.lit("L").alias("source"), F.col("c_custkey").alias("pid"), F.concat_ws(" ", "c_name", "c_mktsegment", "bal", "n_name").alias("text"))
        packed = self._edited(strength).select("c_custkey", F.to_json(F.struct(F.col("n_name").alias("country"), F.col("c_name").alias("who"), F.col("bal").alias("amount"), F.col("c_mktsegment").alias("line"))).alias("j"))
        right = packed.select(F.lit("R").alias("source"), F.col("c_custkey").alias("pid"), F.array_join(F.map_values(F.from_json("j", "map<string,string>")), " ").alias("text"))
        return Task(left.unionByName(right), "linkage")

    def cust_linkage_truth(self) -> DataFrame:
        return self._table("customer").select(F.col("c_custkey").alias("l"), F.col("c_custkey").alias("r"))

    # --- others

    def vec_linkage(self, strength: float = 1000) -> DataFrame:
        """(source, pid, vec)"""
        e = self._table("embeddings").select(F.col("vec_id").alias("pid"), F.col("embedding").cast("array<double>").alias("vec"))
        return e.select(F.lit("L").alias("source"), "pid", "vec").unionByName(jittered(e, strength).select(F.lit("R").alias("source"), "pid", "vec"))

    def vec_truth(self) -> DataFrame:
        return self._table("embeddings").select(F.col("vec_id").alias("l"), F.col("vec_id").alias("r"))

    def part(self) -> Task:
        return Task(to_profiles(self._table("part"), "p_partkey", ["p_name", "p_brand", "p_type", "p_size"]), "dedup")

    def part_truth(self) -> DataFrame:
        p = self._table("part")
        key = ["p_name", "p_brand", "p_type", "p_size"]
        return p.select(F.col("p_partkey").alias("l"), *key).join(p.select(F.col("p_partkey").alias("r"), *key), key).where("l < r").select("l", "r")

    def pages(self) -> Task:
        title = F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1))
        return Task(to_profiles(self._table("pages").select("page_id", title.alias("title")), "page_id", ["title"]), "dedup")

    def conversations(self) -> Task:
        c = self._table("conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("pid"), "text")
        return Task(to_profiles(c, "pid", ["text"]), "dedup")

    def multi_source(self) -> DataFrame:
        return self.docs().profiles.withColumn("source", (F.col("pid") % 3).cast("string"))
