"""Removal of repeated passages by prefix-free parsing.

Texts are read as symbols on one or two scales: bytes, of which those go that lie in a string of 400 which also starts
elsewhere (copies in one document included), and words, of which passages of 51 or more that other documents have too are
counted. The method is the same on both. A rolling hash of a few symbols triggers: the trigger of a window of `span` symbols
is the place of its least hash among its first `window`, the rightmost of equals, so equal windows have their trigger at
the same offset, wherever they lie. Windows that follow one another and share a trigger are a phrase; its text runs from its
first window's start to its last one's end, so phrases overlap by span - 1 symbols.

The dictionary has each phrase once, with the number of places it occurs at; the parse has, for each document, its phrases.
Only phrases whose part common to all their windows occurs twice go on. The corpus order of suffixes, as deep as a repeat
is long, has two parts. Because of the overlap, the parse's suffixes are told apart by their first phrase: in this order
the places of one phrase are neighbours, and a phrase of two places is repeated as a whole. Where phrases differ, their
suffixes do: the suffix array of the dictionary, made by prefix doubling, is cut where neighbours' common prefix is shorter
than `span`; what is left in one run repeats. Suffixes of phrases without a common part can't be neighbours as deep, so
the dictionary is sorted in slices, each of whole groups with one common part. A group of over HOT phrases (a passage that
a large share of all documents enters from different texts) fits no slice: its suffixes are named by hashes instead, which
are counted before they are shuffled.

Null texts are empty; texts shorter than `span` lose nothing; rows with equal texts are repeats of one another, however
their ids; an empty table gives an empty result. Further columns are kept by without_repeats; columns with the names of its
results are replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import discard, extended, gathered, mixed64, settle, shuffle_width, table, texts_of, word_codes, word_hashes

PIECE, SLICE, HOT = 2 << 20, 1 << 20, 2048
#: Up to so many rows of keys (of 24 bytes at most) are broadcast; more are joined by a shuffle.
BROADCAST_ROWS = 200_000
_MULTIPLY = 0x9E3779B97F4A7C15
_VALUES = np.random.default_rng(77).integers(1, 2**63, 256, dtype=np.uint64)
_POWERS = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


@dataclass(frozen=True)
class Scale:
    """span: symbols of the shortest repeat; a trigger is a place of `gram` symbols among the first `window` places."""

    words: bool
    span: int
    window: int
    gram: int

    def __post_init__(self) -> None:
        if not self.gram + self.window < self.span:
            raise ValueError(f"span must exceed {self.gram + self.window}: {self.span}")


BYTES, WORDS = Scale(False, 400, 160, 16), Scale(True, 51, 28, 4)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    for name, base in (("up", _MULTIPLY), ("down", pow(_MULTIPLY, -1, 2**64))):
        have = _POWERS[name]
        while len(have) < n:
            have = np.concatenate((have, have * np.uint64(pow(base, len(have), 2**64))))
        _POWERS[name] = have
    return _POWERS["up"][:n], _POWERS["down"][:n]


class Hashed:
    """Polynomial hashes of any substrings of some symbols, equal for equal strings wherever they lie."""

    def __init__(self, symbols: np.ndarray):
        n = len(symbols)
        up, self.down = _powers(n + 1)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum((_VALUES[symbols] if symbols.dtype == np.uint8 else symbols) * up[:n], out=self.sums[1:])

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mixed64((self.sums[end] - self.sums[start]) * self.down[start])


def triggers(hashed: Hashed, n: int, scale: Scale) -> np.ndarray:
    """For each place with `window` grams at and behind it: where the least gram hash is."""
    grams, window = n - scale.gram + 1, scale.window
    if grams < window:
        return np.empty(0, np.int64)
    at = np.arange(grams)
    key = (hashed(at, at + scale.gram) & np.uint64(0xFFFFFFFF00000000)) | (np.uint64(0xFFFFFFFF) - at.astype(np.uint64))
    grid = np.concatenate((key, np.full(-grams % window, ~np.uint64(0)))).reshape(-1, window)
    ahead = np.minimum.accumulate(grid[:, ::-1], 1)[:, ::-1].ravel()[: grams - window + 1]
    behind = np.minimum.accumulate(grid, 1).ravel()[window - 1 : grams]
    return (np.uint64(0xFFFFFFFF) - (np.minimum(ahead, behind) & np.uint64(0xFFFFFFFF))).astype(np.int64)


def phrases(symbols: np.ndarray, ends: np.ndarray, scale: Scale = BYTES) -> tuple[np.ndarray, ...]:
    """(text, start, windows, hash of the part common to the windows, hash of the phrase) of the phrases of texts side by side."""
    hashed, span = Hashed(symbols), scale.span
    trigger = triggers(hashed, len(symbols), scale)
    text = np.searchsorted(ends, np.arange(len(trigger)), side="right")
    place = np.flatnonzero(np.arange(len(trigger)) + span <= ends[text]) if len(trigger) else np.empty(0, np.int64)
    if not len(place):
        return tuple(np.empty(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.uint64))
    trigger, text = trigger[place], text[place]
    new = np.ones(len(place), bool)
    new[1:] = (trigger[1:] != trigger[:-1]) | (text[1:] != text[:-1])
    first = np.flatnonzero(new)
    windows = np.diff(np.append(first, len(place)))
    start, trigger, text = place[first], trigger[first], text[first]
    common = hashed(trigger, trigger + span - scale.window + 1)
    phrase = hashed(start, start + windows - 1 + span)
    return text, start, windows, common, phrase


def symbols_of(texts: pa.Array, scale: Scale) -> tuple[np.ndarray, np.ndarray]:
    """(symbols of all texts, first of each text and the end): bytes, or hashes of words."""
    if scale.words:
        codes, words, offsets = word_codes(texts)
        return word_hashes(words)[codes], offsets
    offsets = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8)
    return np.frombuffer(texts.buffers()[2], np.uint8) if texts.buffers()[2] and texts.buffers()[2].size else np.empty(0, np.uint8), offsets


def pieces(symbols: np.ndarray, offsets: np.ndarray, span: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first text, offset in it, symbols, end of each text in them): some texts, or a part of a very long one."""
    a, n_texts = 0, len(offsets) - 1
    while a < n_texts:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + PIECE, side="right")) - 1)
        if b == a + 1 and offsets[b] - offsets[a] > PIECE:
            n = int(offsets[b] - offsets[a])
            for at in range(0, max(1, n - span + 1), PIECE):
                some = symbols[offsets[a] + at : offsets[a] + min(n, at + PIECE + span - 1)]
                yield a, at, some, np.array([len(some)])
        else:
            yield a, 0, symbols[offsets[a] : offsets[b]], offsets[a + 1 : b + 1] - offsets[a]
        a = b


PHRASE = ["scale", "__text_key", "__text_size", "start", "windows", "common", "phrase"]


def with_text_key(docs: DataFrame) -> DataFrame:
    text = F.coalesce("text", F.lit(""))
    return docs.withColumn("__text_key", F.xxhash64(text)).withColumn("__text_size", F.octet_length(text))


def parse(docs: DataFrame, scales: tuple[Scale, ...] = (BYTES,)) -> DataFrame:
    """The phrases of all texts. A text is named by its hash and size, so equal texts have equal rows; scale: place in `scales`."""
    shortest = min(2 * s.span - 1 if s.words else s.span for s in scales)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text", PIECE):
            key, size = part.column("__text_key").to_numpy(), part.column("__text_size").to_numpy()
            texts = texts_of(part)
            for k, scale in enumerate(scales):
                for first, at, symbols, ends in pieces(*symbols_of(texts, scale), scale.span):
                    text, start, windows, common, phrase = phrases(symbols, ends, scale)
                    begin = np.concatenate(([0], ends[:-1]))[text] - at
                    text = text + first
                    common = mixed64(common + np.uint64(k))
                    columns = (np.full(len(text), k), key[text], size[text], start - begin, windows, common.view(np.int64), phrase.view(np.int64))
                    kinds = (pa.int8(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(v.astype(t.to_pandas_dtype()), t) for v, t in zip(columns, kinds, strict=True)], PHRASE)

    texts = with_text_key(docs.where(F.octet_length("text") >= shortest)).select("__text_key", "__text_size", "text")
    return texts.mapInArrow(make, "scale byte, __text_key long, __text_size int, start int, windows int, common long, phrase long")


def _few(df: DataFrame) -> DataFrame:
    """Broadcast if it has few rows; df is settled, so counting it is cheap."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def ranks(symbols: np.ndarray, depth: int) -> np.ndarray:
    """Rank of each suffix in the order of suffixes cut at `depth` symbols, equal ones alike: by prefix doubling.

    Suffixes that end before `depth` come first; their ranks mean nothing else.
    """
    n, have = len(symbols), 1
    if symbols.dtype == np.uint8 and depth >= 8:
        padded = np.concatenate((symbols, np.zeros(7, np.uint8)))
        key, have = np.zeros(n, np.uint64), 8
        for k in range(8):
            key = (key << np.uint64(8)) | padded[k : n + k]
    else:
        key = symbols
    rank = np.unique(key, return_inverse=True)[1].astype(np.int64)
    while have < depth:
        ahead = have if 2 * have <= depth else depth - have
        later = np.zeros(n, np.int64)
        later[: max(0, n - ahead)] = rank[ahead:] + 1
        rank = np.unique(rank * (n + 1) + later, return_inverse=True)[1]
        have += ahead
    return rank


def repeated_suffixes(symbols: np.ndarray, sizes: np.ndarray, windows: np.ndarray, places: np.ndarray, owner: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(entry, first offset, last offset) of the dictionary's entries of one place that have suffixes repeated elsewhere.

    The entries' symbols lie side by side; the suffix array holds the first `windows` suffixes of each. A run of neighbours
    with `span` symbols in common repeats if it holds two owners, or an entry of more places.
    """
    entry = np.repeat(np.arange(len(sizes)), windows)
    offset = np.arange(len(entry)) - np.repeat(np.cumsum(windows) - windows, windows)
    rank = ranks(symbols, span)[(np.cumsum(sizes) - sizes)[entry] + offset]
    array = np.argsort(rank, kind="stable")
    first = np.flatnonzero(np.concatenate(([True], rank[array][1:] != rank[array][:-1])))
    of, own = places[entry[array]], owner[entry[array]]
    again = (np.maximum.reduceat(of, first) > 1) | (np.minimum.reduceat(own, first) != np.maximum.reduceat(own, first))
    hit = np.zeros(len(entry), bool)
    hit[array] = np.repeat(again, np.diff(np.append(first, len(array))))
    hit &= places[entry] == 1
    entry, offset = entry[hit], offset[hit]
    if not len(entry):
        return entry, offset, offset
    change = np.flatnonzero(np.concatenate(([True], entry[1:] != entry[:-1])))
    return entry[change], offset[change], offset[np.append(change[1:], len(entry)) - 1]


ENTRY = ["common", "scale", "phrase", "windows", "places", "owner", "symbols", "at", "suffix"]
HITS = "scale byte, common long, phrase long, windows int, low int, high int"


def _looked_up(texts: DataFrame, scales: tuple[Scale, ...]) -> DataFrame:
    """The dictionary's entries asked for: a row with the symbols, or for hot ones a row with the hash of each suffix."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held, n = [], 0
            for key, text, asked in zip(*(batch.column(k) for k in range(3)), strict=True):
                rows = asked.values
                which = rows.field(0).to_numpy(zero_copy_only=False)
                for k in np.unique(which):
                    scale, mine = scales[k], np.flatnonzero(which == k)
                    symbols = symbols_of(pa.array([text.as_py()], pa.large_string()), scale)[0]
                    start, windows, common, phrase, places, hot = (rows.field(f).to_numpy(zero_copy_only=False)[mine] for f in range(1, 7))
                    hashed = Hashed(symbols) if hot.any() else None
                    for row in zip(start.tolist(), windows.tolist(), common.tolist(), phrase.tolist(), places.tolist(), hot.tolist(), strict=True):
                        s, w, c, p, m, h = row
                        if h:
                            at = np.arange(s, s + w)
                            held += [(c, k, p, w, m, key.as_py(), None, i, x) for i, x in enumerate(hashed(at, at + scale.span).view(np.int64).tolist())]
                            n += 40 * w
                        else:
                            raw = symbols[s : s + w - 1 + scale.span].tobytes()
                            held.append((c, k, p, w, m, key.as_py(), raw, None, None))
                            n += len(raw)
                if n > SLICE:
                    yield _batch(held)
                    held, n = [], 0
            if held:
                yield _batch(held)

    return texts.mapInArrow(look, "common long, scale byte, phrase long, windows int, places int, owner long, symbols binary, at int, suffix long")


def _batch(held: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int8(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int32(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*held, strict=True), kinds, strict=True)], ENTRY)


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Entries that come sorted by their common part, put together to slices of whole groups."""
    held: list[pa.RecordBatch] = []
    size, last = 0, None
    for batch in batches:
        if not batch.num_rows:
            continue
        common = batch.column(0).to_numpy()
        raw = batch.column(ENTRY.index("symbols"))
        filled = np.concatenate(([0], np.cumsum(pc.binary_length(raw).to_numpy(zero_copy_only=False))))
        cuts = [0, *(np.flatnonzero(common[1:] != common[:-1]) + 1).tolist(), batch.num_rows]
        begin = 0
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            if size > SLICE and common[a] != last:
                yield pa.Table.from_batches([*held, *([batch.slice(begin, a - begin)] if a > begin else [])])
                held, size, begin = [], 0, a
            size += int(filled[b] - filled[a])
            last = common[a]
        held.append(batch.slice(begin))
    if held:
        yield pa.Table.from_batches(held)


def _sorted_hits(entries: DataFrame, scales: tuple[Scale, ...]) -> DataFrame:
    """Suffix arrays of slices of the dictionary: which suffixes of entries of one place are repeated."""

    def sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _slices(batches):
            which = part.column("scale").to_numpy()
            for k in np.unique(which):
                mine = part.take(pa.array(np.flatnonzero(which == k))) if (which != k).any() else part
                raw = mine.column("symbols").combine_chunks()
                sizes = pc.binary_length(raw).to_numpy() // (8 if scales[k].words else 1)
                symbols = np.frombuffer(b"".join(raw.to_pylist()), np.uint64 if scales[k].words else np.uint8)
                windows, places = mine.column("windows").to_numpy(), mine.column("places").to_numpy()
                owner = mine.column("owner").to_numpy() if scales[k].words else np.arange(len(sizes))
                entry, low, high = repeated_suffixes(symbols, sizes, windows, places, owner, scales[k].span)
                if len(entry):
                    named = mine.select(["scale", "common", "phrase", "windows"]).take(pa.array(entry)).combine_chunks().to_batches()[0]
                    yield pa.RecordBatch.from_arrays([*named.columns, pa.array(low.astype(np.int32)), pa.array(high.astype(np.int32))], ["scale", "common", "phrase", "windows", "low", "high"])

    dealt = entries.repartition(shuffle_width(entries.sparkSession), "common").sortWithinPartitions("common")
    return dealt.mapInArrow(sort, HITS)


def _hashed_hits(suffixes: DataFrame, scales: tuple[Scale, ...]) -> DataFrame:
    """The same for groups too large for a slice: equal suffixes are told by hashes, counted before they are shuffled."""
    words = F.array(*[F.lit(s.words) for s in scales])
    own = F.min("owner") != F.max("owner")
    again = F.when(F.get(words, F.first("scale").cast("int")), own).otherwise(F.count(F.lit(1)) > 1) | (F.max("places") > 1)
    twice = suffixes.groupBy("common", "suffix").agg(again.alias("again")).where("again").select("common", "suffix")
    hits = suffixes.where("places = 1").join(twice, ["common", "suffix"], "left_semi")
    return hits.groupBy("scale", "common", "phrase", "windows").agg(F.min("at").alias("low"), F.max("at").alias("high"))


def repeated_spans(docs: DataFrame, scales: tuple[Scale, ...] = (BYTES,)) -> DataFrame:
    """(scale, text_key, size, starts, ends) of the texts that have repeats: maximal runs in symbols, in order; settled.

    On a scale of bytes a string repeats if it also starts elsewhere, on one of words if another row has it too.
    """
    parsed = settle(parse(docs, scales), "phrases")
    again = settle(parsed.groupBy("common").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("common"), "common")
    rows = settle(parsed.join(_few(again), "common", "left_semi").groupBy(*PHRASE).agg(F.count(F.lit(1)).alias("k")), "parse", large=True)
    discard(parsed, again)
    words = F.get(F.array(*[F.lit(s.words) for s in scales]), F.col("scale").cast("int"))
    elsewhere = (F.min("__text_key") != F.max("__text_key")) | (F.max("k") > 1)
    dictionary = rows.groupBy("scale", "common", "phrase", "windows").agg(
        F.sum("k").alias("k"), F.when(elsewhere, 2).otherwise(1).alias("owners"), F.min(F.struct("__text_key", "__text_size", "start")).alias("at")
    )
    places = F.when(words, F.col("owners")).otherwise(F.least("k", F.lit(2))).cast("int")
    dictionary = settle(dictionary.select("scale", "common", "phrase", "windows", places.alias("places"), "at.*"), "dictionary")
    groups = dictionary.groupBy("common").agg(F.count(F.lit(1)).alias("m"), F.min("places").alias("least")).where("m > 1 and least = 1")
    groups = settle(groups.select("common", (F.col("m") > HOT).alias("hot")), "groups")

    asked = dictionary.join(_few(groups), "common")
    asked = asked.groupBy("__text_key", "__text_size").agg(F.collect_list(F.struct("scale", "start", "windows", "common", "phrase", "places", "hot")).alias("asked"))
    asked = settle(asked, "asked")
    texts = with_text_key(docs).select("__text_key", "__text_size", "text").join(_few(asked.select("__text_key", "__text_size")), ["__text_key", "__text_size"], "left_semi")
    texts = texts.groupBy("__text_key", "__text_size").agg(F.first("text").alias("text")).join(asked, ["__text_key", "__text_size"])
    entries = settle(_looked_up(texts.select("__text_key", "text", "asked"), scales), "entries", large=True)
    discard(groups, asked)
    hits = _sorted_hits(entries.where("symbols is not null"), scales)
    if entries.where("symbols is null").limit(1).count():
        hits = hits.union(_hashed_hits(entries.where("symbols is null"), scales))
    whole = dictionary.where("places > 1").select("scale", "common", "phrase", "windows", F.lit(0).alias("low"), (F.col("windows") - 1).alias("high"))
    repeated = settle(whole.union(hits), "repeated", large=True)
    discard(entries, dictionary)
    span = F.get(F.array(*[F.lit(s.span) for s in scales]), F.col("scale").cast("int"))
    # windows of one phrase lie within `span` of one another: what they cover has no gap
    spans = rows.join(repeated, ["scale", "common", "phrase", "windows"]).select("scale", "__text_key", "__text_size", (F.col("start") + F.col("low")).alias("start"), (F.col("start") + F.col("high") + span).alias("end"))
    spans = spans.groupBy("scale", "__text_key", "__text_size").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    made = settle(spans.mapInArrow(_merge, "scale byte, __text_key long, __text_size int, starts array<int>, ends array<int>"), "spans")
    discard(rows, repeated)
    return made


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        runs = [merged(*(s.values.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))) for s in batch.column(3)]
        lists = [pa.array([r[k] for r in runs], pa.list_(pa.int32())) for k in (0, 1)]
        yield pa.RecordBatch.from_arrays([*batch.columns[:3], *lists], ["scale", "__text_key", "__text_size", "starts", "ends"])


def merged(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of the spans."""
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate(end[order])
    new = np.ones(len(start), bool)
    new[1:] = start[1:] > end[:-1]
    return start[new], end[np.append(np.flatnonzero(new)[1:] - 1, len(end) - 1)] if len(end) else end


RESULTS = ("n_bytes", "n_removed", "n_spans", "kept", "kept_sha256", "n_passages", "n_passage_words")


def without_repeats(docs: DataFrame, repeats: Scale = BYTES, passages: Scale | None = WORDS, digest: bool = False) -> DataFrame:
    """Adds n_bytes, n_removed, n_spans and kept (binary) to docs; with digest kept_sha256 instead, and no text.

    With `passages` also n_passages and n_passage_words: the passages of at least that many words which another row has
    too, and the words in them. They are counted, not removed.
    """
    spans = repeated_spans(docs, (repeats, passages) if passages else (repeats,))
    of = lambda k, *what: spans.where(F.col("scale") == k).select("__text_key", "__text_size", *what)
    cuts, found = of(0, F.col("starts").alias("__starts"), F.col("ends").alias("__ends")), None
    total = cuts.agg(F.sum(F.size("__starts"))).first()[0] or 0
    keyed = with_text_key(docs.drop(*RESULTS)).join(F.broadcast(cuts) if total <= BROADCAST_ROWS else cuts, ["__text_key", "__text_size"], "left")
    extra: list[Column] = []
    if passages:
        length = F.aggregate(F.zip_with("ends", "starts", lambda e, s: e - s), F.lit(0).cast("long"), lambda a, x: a + x)
        found = of(1, F.size("starts").cast("long").alias("n_passages"), length.alias("n_passage_words"))
        keyed = keyed.join(_few(found), ["__text_key", "__text_size"], "left")
        extra = [F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_passages", "n_passage_words")]
    columns = [c for c in docs.columns if c not in RESULTS and not (digest and c == "text")]
    last = "kept_sha256 string" if digest else "kept binary"
    given = keyed.select(*columns, *extra, F.coalesce("text", F.lit("")).alias("__text"), "__starts", "__ends")
    names = given.columns[:-3]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = len(names)
            sizes, removed, runs, left = [], [], [], []
            for text, start, end in zip(*(batch.column(at + k) for k in range(3)), strict=True):
                data = text.as_py().encode()
                kept = data
                if start.is_valid:
                    edges = [0, *(x for pair in zip(start.as_py(), end.as_py(), strict=True) for x in pair), len(data)]
                    kept = b"".join(data[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True))
                runs.append(len(start.as_py()) if start.is_valid else 0)
                sizes.append(len(data))
                removed.append(len(data) - len(kept))
                left.append(hashlib.sha256(kept).hexdigest() if digest else kept)
            made = [pa.array(v, pa.int64()) for v in (sizes, removed, runs)] + [pa.array(left, pa.string() if digest else pa.binary())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:at], *made], [*names, "n_bytes", "n_removed", "n_spans", last.split()[0]])

    return given.mapInArrow(cut, extended(given.select(*names), f"n_bytes long, n_removed long, n_spans long, {last}"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = without_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), digest=True)
    return made.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passages", "n_passage_words")
