"""Language identification of mixed text: script ranges narrow the candidates, Viterbi labels the words.

Training counts, over all training documents, how often each language has each character n-gram of its words and which
scripts its letters come from. A word's score in a language is the sum of its n-grams' log probabilities; languages that do
not use the script of the word's letters are no candidates for it; words without letters score alike. The best sequence of
languages under a penalty for each switch gives spans; a text's language is that with most letters in its spans, and its
score that language's share of the letters.

A null text and a text without letters are `und` with score 0. Ties go to the first language by code point. Repeated rows
are predicted alike. Without training rows everything is `und`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import extended, gathered, mixed64, table, texts_of, word_codes
from progmatch.llm.quality_nbsvm import fold

BUCKET_BITS, SIZES, PENALTY, LEAST_SHARE, MOST_LANGUAGES = 16, (1, 2, 3, 4), 10.0, 0.01, 512
#: Bytes of text looked at together.
BATCH_BYTES = 3 << 20
#: First code point of script ranges and the script, "" where there is none of its own.
SCRIPT_RANGES = (
    (0x0000, ""), (0x0041, "Latin"), (0x0370, "Greek"), (0x0400, "Cyrillic"), (0x0530, "Armenian"), (0x0590, "Hebrew"),
    (0x0600, "Arabic"), (0x0700, ""), (0x0900, "Devanagari"), (0x0980, "Bengali"), (0x0A00, "Gurmukhi"), (0x0A80, "Gujarati"),
    (0x0B00, ""), (0x0B80, "Tamil"), (0x0C00, "Telugu"), (0x0C80, "Kannada"), (0x0D00, "Malayalam"), (0x0D80, ""), (0x0E00, "Thai"),
    (0x0E80, ""), (0x10A0, "Georgian"), (0x1100, "Hangul"), (0x1200, "Ethiopic"), (0x1380, ""), (0x1E00, "Latin"), (0x1F00, "Greek"),
    (0x2000, ""), (0x3040, "Kana"), (0x3100, ""), (0x3400, "Han"), (0xA000, ""), (0xAC00, "Hangul"), (0xD7B0, ""), (0xF900, "Han"),
    (0xFB00, "Latin"), (0xFB13, ""), (0xFF21, "Latin"), (0xFF66, "Kana"), (0xFFA0, ""), (0x20000, "Han"), (0x30000, ""),
)
SCRIPTS = sorted({s for _, s in SCRIPT_RANGES})
_STARTS = np.array([a for a, _ in SCRIPT_RANGES], np.uint32)
_SCRIPT_AT = np.array([SCRIPTS.index(s) for _, s in SCRIPT_RANGES], np.int64)


@dataclass(frozen=True)
class Words:
    """Of distinct words: which have letters, how many, their script, and their n-gram buckets one after another."""

    letters: np.ndarray
    script: np.ndarray
    buckets: np.ndarray
    word: np.ndarray


def examined(words: pa.Array, bits: int = BUCKET_BITS) -> Words:
    """n-grams are taken of the letters of a word, in lower case, between two edges."""
    n = len(words)
    letters = pc.replace_substring_regex(pc.utf8_lower(words), r"[^\p{L}]+", "")
    counts = pc.fill_null(pc.utf8_length(letters), 0).to_numpy().astype(np.int64)
    joined = "".join(f"\x02{w}\x03" for w in letters.to_pylist())
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    sizes = counts + 2
    ends = np.cumsum(sizes)
    word = np.repeat(np.arange(n), sizes)
    inner = np.ones(len(points), bool)
    if n:
        inner[ends - 1] = inner[ends - sizes] = False
    script = np.zeros(n, np.int64)
    firsts = (ends - sizes + 1)[counts > 0]
    script[counts > 0] = _SCRIPT_AT[np.searchsorted(_STARTS, points[firsts], side="right") - 1]
    buckets, owner = [], []
    for k in SIZES:
        if len(points) < k:
            break
        h = np.full(len(points) - k + 1, k, np.uint64)
        for j in range(k):
            h = h * np.uint64(0x100000001B3) + points[j : len(points) - k + 1 + j].astype(np.uint64)
        keep = word[: len(h)] == word[k - 1 :]
        if k == 1:
            keep &= inner
        buckets.append((mixed64(h[keep]) >> np.uint64(64 - bits)).astype(np.int64))
        owner.append(word[: len(h)][keep])
    return Words(counts, script, np.concatenate(buckets) if buckets else np.empty(0, np.int64), np.concatenate(owner) if owner else np.empty(0, np.int64))


def viterbi(scores: np.ndarray, offsets: np.ndarray, penalty: float) -> np.ndarray:
    """The best language of each word: scores has a row for each word, offsets the first word of each text and the end.

    A text is labelled by one language at once where that is provably best: no other language gains more than half the
    penalty over it on any run of its words, and it is best over the whole. The rest are run side by side, word by word.
    """
    n, k = scores.shape
    label = np.zeros(n, np.int64)
    texts = np.flatnonzero(np.diff(offsets) > 0)
    if not len(texts) or k < 2:
        return label
    firsts, sizes = offsets[:-1][texts], np.diff(offsets)[texts]
    whole = np.add.reduceat(scores, firsts, axis=0)
    best = whole.argmax(1)
    label[:] = np.repeat(best, sizes)
    part = np.repeat(np.arange(len(texts)), sizes)
    gain = np.zeros(len(texts))
    own = scores[np.arange(n), label]
    for other in range(k):
        run = np.cumsum(scores[:, other] - own)
        start = np.concatenate(([0.0], run))[firsts]
        run = run - start[part]
        span = float(np.abs(run).max()) * 4 + 1
        low = np.minimum.accumulate(np.minimum(run, 0) - part * span) + part * span
        before = np.concatenate(([0.0], low[:-1]))
        before[firsts] = 0.0
        gain = np.maximum(gain, np.maximum.reduceat(run - before, firsts))
    hard = np.flatnonzero(gain > penalty / 2)
    if not len(hard):
        return label
    hard = hard[np.argsort(-sizes[hard], kind="stable")]
    first, size = firsts[hard], sizes[hard]
    most = int(size[0])
    alive = np.searchsorted(-size, -np.arange(most), side="left")  # texts with more words than this step
    back = np.zeros((int(size.sum()), k), np.int16)
    rows = np.concatenate(([0], np.cumsum(alive)))
    value = scores[first].copy()
    for t in range(1, most):
        m = alive[t]
        top = value[:m].argmax(1)
        switched = value[np.arange(m), top] - penalty
        stay = value[:m] >= switched[:, None]
        back[rows[t] : rows[t] + m] = np.where(stay, np.arange(k), top[:, None])
        value[:m] = np.where(stay, value[:m], switched[:, None]) + scores[first[:m] + t]
    state = value.argmax(1)
    for t in range(most - 1, -1, -1):
        m = alive[t]
        label[first[:m] + t] = state[:m]
        if t:
            state[:m] = back[rows[t] + np.arange(m), state[:m]]
    return label


@dataclass(frozen=True)
class Model:
    languages: tuple[str, ...]
    logs: np.ndarray  # bucket x language
    uses: np.ndarray  # script x language
    bits: int = BUCKET_BITS
    penalty: float = PENALTY

    def word_scores(self, words: pa.Array) -> tuple[np.ndarray, Words]:
        w = examined(words, self.bits)
        scores = np.zeros((len(words), len(self.languages)))
        for j in range(len(self.languages)):
            scores[:, j] = np.bincount(w.word, self.logs[w.buckets, j], minlength=len(words))
        scores[w.letters == 0] = 0
        open_to = self.uses[w.script]
        open_to[~open_to.any(1)] = True
        scores = np.where(open_to | (w.letters == 0)[:, None], scores, scores.min(1, keepdims=True) - 50.0)
        return scores, w

    def labelled(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(language of each word, letters of each word, first word of each text and the end)."""
        codes, words, offsets = word_codes(texts)
        scores, w = self.word_scores(words)
        return viterbi(scores[codes], offsets, self.penalty), w.letters[codes], offsets

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        n, k = len(texts), len(self.languages)
        if not k:
            return ["und"] * n, np.zeros(n)
        label, letters, offsets = self.labelled(texts)
        doc = np.repeat(np.arange(n), np.diff(offsets))
        held = np.bincount(doc * k + label, letters, minlength=n * k).reshape(n, k)
        best, total = held.argmax(1), held.sum(1)
        return [self.languages[b] if t else "und" for b, t in zip(best, total, strict=True)], np.divide(held.max(1), total, out=np.zeros(n), where=total > 0)

    def spans(self, text: str) -> list[tuple[str, str]]:
        """(language, text) of each run of words in one language."""
        label, _, _ = self.labelled(pa.array([text], pa.large_string()))
        out: list[list] = []
        for word, at in zip(pc.utf8_split_whitespace(pa.array([text]))[0].as_py() if text else [], label, strict=False):
            if out and out[-1][0] == at:
                out[-1][1].append(word)
            else:
                out.append([at, [word]])
        return [(self.languages[a], " ".join(ws)) for a, ws in out]


def train(docs: DataFrame, bits: int = BUCKET_BITS, penalty: float = PENALTY) -> Model:
    """docs: text, lang. Null languages don't count; there may be MOST_LANGUAGES languages."""
    known = docs.where("lang is not null").select("text", "lang")
    languages = sorted(r[0] for r in known.select("lang").distinct().limit(MOST_LANGUAGES + 1).collect())
    if len(languages) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    if not languages:
        return Model((), np.zeros((1 << bits, 0)), np.zeros((len(SCRIPTS), 0), bool), bits, penalty)
    number = {x: i for i, x in enumerate(languages)}
    k = len(languages)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, scripts = np.zeros((k, 1 << bits)), np.zeros((k, len(SCRIPTS)))
        for part in gathered(batches, "text", BATCH_BYTES):
            codes, words, offsets = word_codes(texts_of(part))
            w = examined(words, bits)
            lang = np.repeat([number[x] for x in part.column("lang").to_pylist()], np.diff(offsets)).astype(np.int64)
            for j in range(k):
                times = np.bincount(codes[lang == j], minlength=len(words))
                grams[j] += np.bincount(w.buckets, times[w.word], minlength=1 << bits)
                scripts[j] += np.bincount(w.script, times * w.letters, minlength=len(SCRIPTS))
        for kind, made in ((0, grams), (1, scripts)):
            at_l, at = np.nonzero(made)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), kind), pa.int32()), pa.array(at_l, pa.int32()), pa.array(at, pa.int32()), pa.array(made[at_l, at].astype(np.int64))], ["kind", "lang", "at", "n"])

    sums = known.mapInArrow(count, "kind int, lang int, at int, n long").groupBy("kind", "lang", "at").agg(F.sum("n").alias("n")).toArrow()
    kind, lang, at, n = (sums[c].to_numpy() for c in ("kind", "lang", "at", "n"))
    grams, scripts = np.zeros((1 << bits, k)), np.zeros((len(SCRIPTS), k))
    grams[at[kind == 0], lang[kind == 0]], scripts[at[kind == 1], lang[kind == 1]] = n[kind == 0], n[kind == 1]
    logs = np.log((grams + 0.5) / (grams.sum(0) + 0.5 * (grams > 0).any(1).sum() + 1))
    return Model(tuple(languages), logs, scripts >= LEAST_SHARE * np.maximum(scripts.sum(0), 1), bits, penalty)


def with_language(docs: DataFrame, model: Model) -> DataFrame:
    """Adds lang_pred and score to docs, which has a column text; columns of these names are replaced."""
    docs = docs.drop("lang_pred", "score")
    fields = extended(docs, "lang_pred string, score double")

    def predict(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text", BATCH_BYTES):
            langs, scores = model.predict(texts_of(part))
            yield from part.append_column("lang_pred", pa.array(langs, pa.string())).append_column("score", pa.array(scores)).to_batches()

    return docs.mapInArrow(predict, fields)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs.where(fold(F.col("doc_id"), 3) != 1).select("text", "lang"))
    return with_language(docs.select("doc_id", "text"), model).select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), "lang_pred", "score")
