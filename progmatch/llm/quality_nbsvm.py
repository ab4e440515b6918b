"""Quality classifier: naive Bayes features under a linear support vector machine.

Features are indicators of word n-grams: each word by itself, each word's form (case, length, punctuation around it), and
each pair of neighbouring forms with whether the words are the same. Their log-count ratios between the classes are counted
over all labelled training rows. Indicators scaled by these ratios are fitted with hinge loss by dual coordinate descent
on a sample of training rows of bounded size, chosen by a hash of doc_id; the margin is mapped to [0, 1] by a logistic
curve fitted on the last fifth of the sample.

Null and empty texts have no feature and get the score of the intercept; repeated rows get equal scores; labels, lang,
source and doc_id never enter a score. Without training rows of both classes the score is their share, or 0.5.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import extended, gathered, mixed64, table, texts_of, word_codes, word_hashes

BUCKET_BITS = 17
FIT_ROWS = 12_000
#: A table of labels of at most this many rows is broadcast; a larger one is joined by a shuffle.
BROADCAST_ROWS = 2_000_000
THRESHOLD = 0.3
LEAST_SEEN = 5

_FORM = re.compile(r"^(\W*)(.*?)([\W_]*)$", re.DOTALL)


def _form(word: str) -> str:
    """Case, length class and the marks before and behind a word."""
    before, core, after = _FORM.match(word).groups()
    if not core:
        return f"-{before[:3]}"
    case = "9" if core[0].isdigit() else "A" if core.isupper() and len(core) > 1 else "a" if core.islower() else "Aa" if core[0].isupper() and (len(core) == 1 or core[1:].islower()) else "x"
    size = 0 if len(core) < 3 else 1 if len(core) < 8 else 2 if len(core) < 20 else 3
    return f"{before[:2]}{case}{size}{after[:3]}"


def features(texts: pa.Array, bits: int = BUCKET_BITS) -> tuple[np.ndarray, np.ndarray]:
    """(feature buckets, the text of each): each bucket once for each text that has it, by text."""
    codes, words, offsets = word_codes(texts)
    words_list = words.to_pylist()
    own = word_hashes(words)
    forms: dict[str, int] = {}
    form_of = np.fromiter((forms.setdefault(_form(w), len(forms)) for w in words_list), np.int64, len(words_list))
    form_hash = word_hashes(pa.array(list(forms), pa.string()))[form_of] if forms else np.empty(0, np.uint64)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    f = form_hash[codes]
    follows = np.flatnonzero(doc[1:] == doc[:-1])
    same = (codes[follows] == codes[follows + 1]).astype(np.uint64)
    pair = mixed64(f[follows] * np.uint64(3) + f[follows + 1] * np.uint64(0x9E3779B97F4A7C15) + same)
    shift, width = np.uint64(64 - bits), np.int64(bits)
    keys = []
    for d, h in ((doc, own[codes]), (doc, mixed64(f + np.uint64(1))), (doc[follows], pair)):
        keys.append((d << width) | (h >> shift).astype(np.int64))
    found = np.unique(np.concatenate([np.unique(k) for k in keys]))
    return found & ((1 << bits) - 1), found >> width


@dataclass(frozen=True)
class Model:
    """Weight of each bucket (log-count ratio times SVM weight), intercept, and the logistic curve of the margin."""

    weights: np.ndarray
    intercept: float
    slope: float
    offset: float
    bits: int = BUCKET_BITS

    def scores(self, texts: pa.Array) -> np.ndarray:
        bucket, doc = features(texts, self.bits)
        return self.curve(margins(self.weights, self.intercept, bucket, doc, len(texts)))

    def curve(self, margin: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.offset, -30, 30)))


def margins(weights: np.ndarray, intercept: float, bucket: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(doc, weights[bucket], minlength=n) + intercept


def log_count_ratios(low: np.ndarray, high: np.ndarray, alpha: float = 1.0) -> np.ndarray:
    """Of the share of each indicator in class 1 to that in class 0; buckets seen in few documents weigh nothing."""
    p, q = high + alpha, low + alpha
    ratios = np.log(p / p.sum()) - np.log(q / q.sum())
    return np.where(low + high >= LEAST_SEEN, ratios, 0.0)


def dual_coordinate_descent(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, size: int, c: np.ndarray, rounds: int = 12, seed: int = 3) -> tuple[np.ndarray, float]:
    """Hinge-loss linear SVM on sparse rows (buckets, values); c: bound of each row's dual variable. Returns weights, intercept."""
    w, bias, alpha = np.zeros(size), 0.0, np.zeros(len(rows))
    norms = np.array([float(v @ v) + 1.0 for _, v in rows])
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        most = 0.0
        for i in rng.permutation(len(rows)):
            at, v = rows[i]
            slack = y[i] * (float(w[at] @ v) + bias) - 1.0
            new = min(max(alpha[i] - slack / norms[i], 0.0), c[i])
            step = (new - alpha[i]) * y[i]
            if step:
                w[at] += step * v
                bias += step
                alpha[i] = new
                most = max(most, abs(step) * norms[i])
        if most < 1e-3:
            break
    return w, bias


def _logistic(margin: np.ndarray, label: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the logistic curve, by Newton steps with smoothed targets."""
    n1, n0 = label.sum(), len(label) - label.sum()
    target = np.where(label == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        r, s = p - target, np.maximum(p * (1 - p), 1e-9)
        h = np.array([[(s * margin * margin).sum() + 1e-6, (s * margin).sum()], [(s * margin).sum(), s.sum() + 1e-6]])
        step = np.linalg.solve(h, [(r * margin).sum(), r.sum()])
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-8:
            break
    return float(max(a, 1e-3)), float(b)


def fitted(ratios: np.ndarray, rows: list[np.ndarray], label: np.ndarray, bits: int = BUCKET_BITS, c: float = 1.0, blend: float = 1.0) -> Model:
    scaled = []
    for at in rows:
        at = at[ratios[at] != 0]
        scaled.append((at, ratios[at]))
    y = np.where(label == 1, 1.0, -1.0)
    cut = max(1, len(rows) * 4 // 5)
    share = np.maximum([(y[:cut] < 0).mean(), (y[:cut] > 0).mean()], 1e-3)
    bounds = np.where(y > 0, 0.5 / share[1], 0.5 / share[0]) * c / 100
    w, bias = dual_coordinate_descent(scaled[:cut], y[:cut], len(ratios), bounds[:cut])
    w = (1 - blend) * np.abs(w).mean() + blend * w
    m = np.array([float(w[at] @ v) + bias for at, v in scaled])
    late = slice(cut, None) if len(rows) - cut >= 50 and len(set(label[cut:])) == 2 else slice(None)
    slope, offset = _logistic(m[late], label[late])
    return Model((w * ratios).astype(np.float64), bias, slope, offset, bits)


def fold(doc_id: Column, n: int) -> Column:
    """Remainder of the crc32 of the id as text; a null id is the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % n


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, bits: int = BUCKET_BITS) -> Model:
    """docs: doc_id, text; labels: doc_id, quality. Rows in fold 0 of 5 and rows without a label of 0 or 1 don't count."""
    marks = labels.select("doc_id", F.col("quality").cast("int").alias("quality")).where("quality in (0, 1) and doc_id is not null").where(fold(F.col("doc_id"), 5) != 0)
    marks = marks.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    n = marks.count()
    joined = docs.select("doc_id", "text").join(F.broadcast(marks) if n <= BROADCAST_ROWS else marks, "doc_id")
    share = min(1.0, fit_rows / max(n, 1))
    picked = F.xxhash64("doc_id") <= F.lit(min(2**63 - 1, int(-(2**63) + share * 2**64)))
    rows = joined.select("text", "quality", picked.alias("picked"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros((2, 1 << bits), np.int64)
        for part in gathered(batches, "text"):
            label, keep = part.column("quality").to_numpy(), part.column("picked").to_numpy()
            bucket, doc = features(texts_of(part), bits)
            for k in (0, 1):
                seen[k] += np.bincount(bucket[label[doc] == k], minlength=1 << bits)
            ends = np.searchsorted(doc, np.arange(len(label) + 1))
            chosen = np.flatnonzero(keep)
            if len(chosen):
                lists = [bucket[ends[i] : ends[i + 1]].astype("<i4").tobytes() for i in chosen]
                none = pa.nulls(len(chosen), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.nulls(len(chosen), pa.int32()), none, none, pa.array(label[chosen], pa.int32()), pa.array(lists, pa.binary())], names)
        some = np.flatnonzero(seen.sum(0))
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(seen[0][some]), pa.array(seen[1][some]), pa.nulls(len(some), pa.int32()), pa.nulls(len(some), pa.binary())], names)

    names = ["bucket", "low", "high", "label", "row"]
    made = rows.mapInArrow(count, "bucket int, low long, high long, label int, row binary")
    # one row for each bucket and one for each row of the sample: both bounded by parameters
    out = made.groupBy("bucket", "label", "row").agg(F.sum("low").alias("low"), F.sum("high").alias("high")).toArrow()
    sums = out.filter(pc.is_valid(out["bucket"]))
    low, high = np.zeros(1 << bits), np.zeros(1 << bits)
    low[sums["bucket"].to_numpy()], high[sums["bucket"].to_numpy()] = sums["low"].to_numpy(), sums["high"].to_numpy()
    picks = sorted(zip(*(out.filter(pc.is_valid(out["row"]))[c].to_pylist() for c in ("row", "label")), strict=True))
    np.random.default_rng(1).shuffle(picks)
    label = np.array([x for _, x in picks], np.int64)
    if len(set(label.tolist())) < 2:
        return Model(np.zeros(1 << bits), 0.0, 1.0, 0.0 if not len(label) else 4.0 if label[0] else -4.0, bits)
    return fitted(log_count_ratios(low, high), [np.frombuffer(r, "<i4") for r, _ in picks], label, bits)


def with_scores(docs: DataFrame, model: Model, threshold: float = THRESHOLD, score: str = "score", predicted: str = "predicted") -> DataFrame:
    """Adds a score and a predicted class to docs, which has a column text; columns of these names are replaced."""
    docs = docs.drop(score, predicted)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text"):
            s = model.scores(texts_of(part))
            made = part.append_column(score, pa.array(s)).append_column(predicted, pa.array((s >= threshold).astype(np.int32)))
            yield from made.to_batches()

    return docs.mapInArrow(judge, extended(docs, f"`{score}` double, `{predicted}` int"))


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    return with_scores(docs, model).select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), "score", "predicted")
