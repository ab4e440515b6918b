"""Text to vectors. No pre-trained model is at hand offline, so the named encoders stand in for the families of models.

hash-words, hash-chars: static word and sub-word vectors (feature-hashed n-grams with signs); word2vec: trained on the
corpus; ctx: token vectors averaged with their neighbours; sent: TF-IDF under a seeded random projection. Any other model
comes in through `plugged`.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from progmatch.functions.text import words
from progmatch.operators.postings import _lists, gram_frequencies, gram_ids
from progmatch.operators.sparse import scored, term_counts
from progmatch.sources.profiles import Task

ENCODERS = ("hash-words", "hash-chars", "word2vec", "ctx", "sent")


def _hashed_vectors(weighted: DataFrame, profiles: DataFrame, dims: int) -> DataFrame:
    """(source, pid, vec): weighted rows (source, pid, gram, w) under a signed hash to `dims` places, of unit length."""
    h = F.xxhash64("gram")
    places = weighted.select("source", "pid", F.pmod(h, F.lit(dims)).cast("int").alias("at"), (F.when(F.shiftrightunsigned(h, 40) % 2 == 0, 1.0).otherwise(-1.0) * F.col("w")).alias("v"))
    sums = places.groupBy("source", "pid", "at").agg(F.sum("v").alias("v"))
    packed = sums.groupBy("source", "pid").agg(F.collect_list(F.struct("at", "v")).alias("s"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))  # at most dims entries
    return profiles.select("source", "pid").join(_spread(packed, dims), ["source", "pid"], "left").withColumn("vec", F.coalesce("vec", F.array_repeat(F.lit(0.0), dims)))


def _spread(packed: DataFrame, dims: int) -> DataFrame:
    by_place = packed.withColumn("m", F.map_from_entries("s"))
    vec = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.try_divide(F.element_at("m", i.cast("int")), F.col("norm")), F.lit(0.0)))
    return by_place.select("source", "pid", vec.alias("vec"))


def _hashed_rows(texts: DataFrame, dims: int, weights: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """(source, pid, vec) of rows (source, pid, ids), ids the 64-bit hashes of a profile's grams: what `_hashed_vectors` gives, made
    row by row. weights: (ids, rows they belong to) -> a weight for each; without it 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, own = _lists(batch.column(2))
            sign = np.where(ids.view(np.uint64) >> np.uint64(40) & np.uint64(1), -1.0, 1.0)
            w = sign if weights is None else sign * weights(ids, own)
            vec = np.bincount(own * dims + ids % dims, w, batch.num_rows * dims).reshape(-1, dims)
            norm = np.sqrt((vec * vec).sum(1))
            vec = vec / np.where(norm > 0, norm, 1.0)[:, None]
            lists = pa.ListArray.from_arrays(np.arange(0, vec.size + 1, dims, dtype=np.int32), pa.array(vec.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), lists], ["source", "pid", "vec"])

    return texts.mapInArrow(run, "source string, pid long, vec array<double>")


def _tfidf(n_records: int, known: Broadcast) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """Weights whose sums over a profile's grams are count over the profile's largest, times ln(N / df)."""

    def weights(ids: np.ndarray, own: np.ndarray) -> np.ndarray:
        order = np.lexsort((ids, own))
        i, o = ids[order], own[order]
        new = np.ones(len(i), bool)
        new[1:] = (i[1:] != i[:-1]) | (o[1:] != o[:-1])
        counts = np.diff(np.flatnonzero(new), append=len(i))
        largest = np.zeros(int(own.max(initial=-1)) + 1)
        np.maximum.at(largest, o[new], counts)
        grams, df = known.value
        at = np.minimum(np.searchsorted(grams, ids), max(len(grams) - 1, 0))
        shared = grams[at] == ids if len(grams) else np.zeros(len(ids), bool)
        return np.log(n_records / np.where(shared, df[at] if len(grams) else 1, 1)) / largest[own]

    return weights


def plugged(task: Task, encode: Callable[[list[str]], np.ndarray]) -> DataFrame:
    """(source, pid, vec) from any model: encode gets a batch of texts and gives a row for each."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield pd.DataFrame({"source": b["source"], "pid": b["pid"], "vec": list(np.asarray(encode(b["text"].fillna("").tolist()), dtype=np.float64))})

    return task.profiles.select("source", "pid", "text").mapInPandas(run, "source string, pid long, vec array<double>")


def encode(task: Task, encoder: str = "hash-words", dims: int = 128) -> DataFrame:
    """(source, pid, vec array<double>)."""
    if encoder in ("hash-words", "hash-chars"):
        return _hashed_rows(gram_ids(task, "word1" if encoder == "hash-words" else "char4"), dims)
    if encoder == "sent":
        texts, n = gram_ids(task, "word1"), task.profiles.count()
        if (known := gram_frequencies(texts)) is not None:
            return _hashed_rows(texts, dims, _tfidf(n, task.profiles.sparkSession.sparkContext.broadcast(known)))
        vectors = scored(term_counts(task, "word1"), n, ("tfidf",))
        return _hashed_vectors(vectors.withColumnRenamed("tfidf", "w"), task.profiles, dims)
    if encoder == "ctx":  # a token and what stands within two places of it, nearer ones more
        w = task.profiles.withColumn("ws", words(F.col("text"))).select("source", "pid", F.posexplode("ws").alias("i", "gram"))
        shifts = F.array(*[F.struct(F.lit(d).alias("d"), F.lit(1.0 / (1 + abs(d))).alias("w")) for d in range(-2, 3)])
        near = w.withColumn("s", F.explode(shifts)).select("source", "pid", F.concat("gram", F.lit("|"), F.col("s.d").cast("string")).alias("gram"), F.col("s.w").alias("w"))
        return _hashed_vectors(near, task.profiles, dims)
    if encoder == "word2vec":
        from pyspark.ml.feature import Word2Vec
        from pyspark.ml.functions import vector_to_array

        df = task.profiles.withColumn("ws", words(F.col("text")))
        model = Word2Vec(vectorSize=min(dims, 32), minCount=2, maxIter=1, seed=1, inputCol="ws", outputCol="v").fit(df)
        return model.transform(df).select("source", "pid", vector_to_array("v").alias("vec"))
    raise ValueError(f"no such model here: {encoder}; give it to plugged()")


def jittered(vectors: DataFrame, strength: Column | float) -> DataFrame:
    """Copies of (pid, vec) moved by plain arithmetic on (pid, place), of unit length again."""
    moved = F.transform("vec", lambda x, i: x.cast("double") + ((F.col("pid") * 31 + (i + 1) * 17) % 101 - 50) / F.lit(float(strength)))
    out = vectors.withColumn("vec", moved)
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda t, x: t + x * x))
    return out.withColumn("__n", norm).withColumn("vec", F.transform("vec", lambda x: x / F.col("__n"))).drop("__n")
