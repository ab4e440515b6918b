"""SentencePiece encoding and decoding by suffix-array matching.

A batch's text is cut into units, runs of spaces with what follows up to the next space; no piece crosses into the next
unit, so a unit's pieces depend on the unit alone, and each distinct unit of a batch is encoded once. The distinct units
are put together, their suffixes sorted as deep as the longest piece, and every piece is found by binary search: its
occurrences are a range of the suffix array. Each occurrence is an edge from its start to its end. Edges are sorted by
position in their unit and relaxed, all units side by side.

For a model of scores (unigram) an edge relaxes its end to the better sum. For a model of merges an end is reached by
exactly one edge: the one whose piece may stand behind the piece that ends where it starts. Two pieces may stand side by
side if merging their joint text gives the two again, which is decided from the merges that built them; a sequence is what
merging gives if and only if all neighbours in it may stand side by side.

Null and empty texts have no ids and decode to the empty text; characters without a piece become byte pieces; U+2581 is a
space, as in the library. Repeated rows give repeated results; further columns are kept.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import extended, gathered, mixed64, table, texts_of
from progmatch.llm.word_memo import WordMemo, spread

MARK = "▁"
START, FAR = -2, np.int64(2**40)
CACHE_BITS = 21
#: Characters of distinct units in one suffix array, bytes of text in one batch, ids decoded at once.
SLICE, BATCH_BYTES, DECODE_IDS = 150_000, 1 << 20, 250_000


def merge_all(text: str, rank: dict[str, int]) -> tuple[list[str], tuple[str, str] | None]:
    """(symbols after all merges, the last pair merged): the best-ranked neighbours first, the leftmost of equals."""
    symbols, last = list(text), None
    while len(symbols) > 1:
        at = min(range(len(symbols) - 1), key=lambda i: (rank.get(symbols[i] + symbols[i + 1], 1 << 60), i))
        if symbols[at] + symbols[at + 1] not in rank:
            break
        last = (symbols[at], symbols[at + 1])
        symbols[at : at + 2] = [symbols[at] + symbols[at + 1]]
    return symbols, last


@dataclass
class Pieces:
    """What a model says, as arrays that travel to executors: strings of ids, their scores, and which are ordinary pieces."""

    strings: list[str]
    scores: list[float]
    ordinary: list[bool]
    byte_id: list[int]  # of each byte value
    skipped: list[bool]  # control symbols: nothing is decoded from them
    merges: bool = True
    _state: dict = field(default_factory=dict, repr=False)

    @classmethod
    def load(cls, path: str, merges: bool = True) -> Pieces:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = model.vocab_size()
        probe = " A ﬁ  Ǻ "
        if model.decode(model.encode(probe)) != probe:
            raise ValueError("only models that leave the text as it is are supported")
        byte_id = [-1] * 256
        for i in range(n):
            if model.is_byte(i):
                byte_id[int(model.id_to_piece(i)[1:-1], 16)] = i
        if -1 in byte_id:
            raise ValueError("only models with a piece for each byte are supported")
        special = [model.is_control(i) or model.is_unknown(i) for i in range(n)]
        ordinary = [not (s or model.is_byte(i) or model.is_unused(i)) for i, s in enumerate(special)]
        return cls([model.id_to_piece(i) for i in range(n)], [model.get_score(i) for i in range(n)], ordinary, byte_id, special, merges)

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("_state", "tables", "decoder")} | {"_state": {}}

    @cached_property
    def tables(self) -> Tables:
        return Tables(self)

    def memo(self) -> WordMemo:
        """Of one task: what a worker keeps between tasks are the tables alone."""
        return WordMemo(self.tables.encode_units, 120_000)

    @cached_property
    def decoder(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(bytes of all ids, first byte of each id, number of bytes)."""
        value = {i: bytes([b]) for b, i in enumerate(self.byte_id)}
        made = [value.get(i, b"" if skip else s.replace(MARK, " ").encode()) for i, (s, skip) in enumerate(zip(self.strings, self.skipped, strict=True))]
        sizes = np.array([len(b) for b in made], np.int64)
        return np.frombuffer(b"".join(made), np.uint8), np.cumsum(sizes) - sizes, sizes


class Tables:
    """Search keys of the pieces, and for a model of merges which pieces may stand side by side."""

    def __init__(self, pieces: Pieces):
        self.merges = pieces.merges
        text = {s: i for i, s in enumerate(pieces.strings) if pieces.ordinary[i]}
        lone = sorted({c for s in text for c in s if c not in text})
        self.n_ids = len(pieces.strings)
        self.symbols = dict(text) | {c: self.n_ids + k for k, c in enumerate(lone)}  # characters that are only parts of pieces
        n = self.n_ids + len(lone)
        order = {s: r for r, s in enumerate(sorted(text, key=lambda s: (-pieces.scores[text[s]], text[s])))}
        self.score = np.full(n, min(pieces.scores) - 10.0)
        self.born = np.full(n, -1, np.int64)
        self.left, self.right = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
        usable = []
        for s, i in self.symbols.items():
            if i < self.n_ids:
                self.score[i] = pieces.scores[i]
            if len(s) > 1:
                if self.merges:
                    got, last = merge_all(s, order)
                    if got != [s]:
                        continue  # merging never gives this piece
                    self.born[i], self.left[i], self.right[i] = order[s], self.symbols[last[0]], self.symbols[last[1]]
            usable.append((s, i))
        if self.merges:
            made = np.flatnonzero(self.born >= 0)
            if (self.born[self.left[made]] >= self.born[made]).any() or (self.born[self.right[made]] >= self.born[made]).any():
                raise ValueError("a piece is merged before its parts")
            splits = {}
            for s in text:
                for k in range(1, len(s)):
                    a, b = self.symbols.get(s[:k]), self.symbols.get(s[k:])
                    if a is not None and b is not None:
                        splits[a * n + b] = order[s]
            keys = np.array(sorted(splits), np.int64)
            self.split_key, self.split_rank = keys, np.array([splits[k] for k in keys.tolist()], np.int64)
            self.cached_key = np.full(1 << CACHE_BITS, -1, np.int64)
            self.cached = np.zeros(1 << CACHE_BITS, bool)
        self.n = n
        self.ids = np.array([i for _, i in usable], np.int64)
        self.sizes = np.array([len(s) for s, _ in usable], np.int64)
        self.most = int(self.sizes.max()) if len(usable) else 1
        points = np.zeros((len(usable), self.most), np.uint32)
        for row, (s, _) in enumerate(usable):
            points[row, : len(s)] = [ord(c) for c in s]
        self.points = points
        self.chars = np.unique(points[points > 0])
        self.byte_id = np.array(pieces.byte_id, np.int64)
        self.single = {ord(s): i for s, i in usable if len(s) == 1 and i < self.n_ids}
        self.single_points = np.array(sorted(self.single), np.uint32)

    # --- which pieces may stand side by side

    def _decide(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Walks back through the merges on either side of the boundary, looking for one that would have crossed it."""
        good = np.ones(len(a), bool)
        at = np.arange(len(a))
        x, y = a.copy(), b.copy()
        end_x, end_y = np.full(len(a), FAR), np.full(len(a), FAR)
        while len(at):
            key = x * self.n + y
            place = np.minimum(np.searchsorted(self.split_key, key), len(self.split_key) - 1)
            rank = np.where(self.split_key[place] == key, self.split_rank[place], FAR)
            crossed = (rank < end_x) & (rank <= end_y) & (rank < FAR)
            good[at[crossed]] = False
            born_x, born_y = self.born[x], self.born[y]
            go = ~crossed & ((born_x >= 0) | (born_y >= 0))
            at, x, y, end_x, end_y, born_x, born_y = (v[go] for v in (at, x, y, end_x, end_y, born_x, born_y))
            undo_y = born_y >= born_x
            x, end_x = np.where(undo_y, x, self.right[x]), np.where(undo_y, end_x, born_x)
            y, end_y = np.where(undo_y, self.left[y], y), np.where(undo_y, born_y, end_y)
        return good

    def side_by_side(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """For arrays of symbols; a may be START or a character without a piece (-1), b the latter."""
        good = np.ones(len(a), bool)
        ask = np.flatnonzero((a >= 0) & (b >= 0))
        key = a[ask] * self.n + b[ask]
        slot = mixed_slot(key)
        hit = self.cached_key[slot] == key
        good[ask[hit]] = self.cached[slot[hit]]
        miss = ~hit
        if miss.any():
            new, back = np.unique(key[miss], return_inverse=True)
            found = self._decide(new // self.n, new % self.n)
            good[ask[miss]] = found[back]
            slot = mixed_slot(new)
            self.cached_key[slot], self.cached[slot] = new, found
        return good

    # --- encoding

    def edges(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(start, size, symbol) of every occurrence of every piece in the text; 0 separates units."""
        alphabet = np.intersect1d(np.unique(points), self.chars)
        bits = 8 if len(alphabet) < 254 else 16
        if len(alphabet) >= 65534:
            bits = 32
        per, n = 64 // bits, len(points)
        where = np.minimum(np.searchsorted(alphabet, points), max(len(alphabet) - 1, 0))
        codes = np.where(alphabet[where] == points, where + 2, 1).astype(np.uint64) if len(alphabet) else np.ones(n, np.uint64)
        codes[points == 0] = 0
        depth = -(-self.most // per)
        padded = np.concatenate((codes, np.zeros(depth * per, np.uint64)))
        key = np.zeros(n + (depth - 1) * per, np.uint64)
        for j in range(per):
            key = (key << np.uint64(bits)) | padded[j : j + len(key)]
        keys = [key[d * per : d * per + n] for d in range(depth)]
        suffixes = np.lexsort(keys[::-1])
        keys = [k[suffixes] for k in keys]

        place = np.minimum(np.searchsorted(alphabet, self.points), max(len(alphabet) - 1, 0))
        inside = np.arange(self.most)[None] < self.sizes[:, None]
        known = (alphabet[place] == self.points) if len(alphabet) else np.zeros_like(inside)
        some = np.flatnonzero((known | ~inside).all(1))
        piece = np.where(inside[some], place[some] + 2, 0).astype(np.uint64)
        filler = np.where(inside[some], 0, (1 << bits) - 1).astype(np.uint64)
        piece, filler = (np.pad(v, ((0, 0), (0, depth * per - self.most)), constant_values=c) for v, c in ((piece, 0), (filler, (1 << bits) - 1)))
        lows, highs = [], []
        for d in range(depth):
            low, high = np.zeros(len(some), np.uint64), np.zeros(len(some), np.uint64)
            for j in range(d * per, (d + 1) * per):
                low, high = (low << np.uint64(bits)) | piece[:, j], (high << np.uint64(bits)) | piece[:, j] | filler[:, j]
            lows.append(low)
            highs.append(high)
        first, last = np.searchsorted(keys[0], lows[0], "left"), np.searchsorted(keys[0], highs[0], "right")
        for d in range(1, depth):
            for r in np.flatnonzero((self.sizes[some] > d * per) & (last > first)):
                part = keys[d][first[r] : last[r]]
                first[r], last[r] = first[r] + np.searchsorted(part, lows[d][r], "left"), first[r] + np.searchsorted(part, highs[d][r], "right")
        times = last - first
        rows = np.repeat(np.arange(len(some)), times)
        ends = np.cumsum(times)
        start = suffixes[np.repeat(first - (ends - times), times) + np.arange(len(rows))]
        return start, self.sizes[some][rows], self.ids[some][rows]

    def encode_units(self, units: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all units, number of ids of each). Units are put together up to SLICE characters at a time, which bounds the edges held."""
        sizes = np.fromiter((len(u) for u in units), np.int64, len(units))
        cuts = [0, *(np.flatnonzero(np.diff(np.cumsum(sizes) // SLICE)) + 1).tolist(), len(units)]
        made = [self._encode(units[a:b], sizes[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True) if b > a]
        if not made:
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        return np.concatenate([m[0] for m in made]), np.concatenate([m[1] for m in made])

    def _encode(self, units: list[str], sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        points = np.frombuffer("".join(units).encode("utf-32-le"), np.uint32)
        unit_of = np.repeat(np.arange(len(units)), sizes)
        firsts = np.cumsum(sizes + 1) - sizes - 1
        spaced = np.zeros(int(sizes.sum()) + len(units), np.uint32)
        where = np.arange(len(points)) + unit_of
        own = points.copy()
        own[own == 0] = 0x10FFFF  # a NUL is a character without a piece, not the separator
        spaced[where] = own
        start, size, symbol = self.edges(spaced)
        lone = where[~np.isin(own, self.single_points)]  # characters without a piece of their own
        in_parts = {c: i for c, i in ((ord(s), i) for s, i in self.symbols.items() if len(s) == 1) if i >= self.n_ids}
        if in_parts:
            have = np.isin(start, lone) & (size == 1)
            start, size, symbol = start[~have], size[~have], symbol[~have]
        lone_symbol = np.array([in_parts.get(int(c), -1) for c in spaced[lone]], np.int64)
        start, size, symbol = np.concatenate((start, lone)), np.concatenate((size, np.ones(len(lone), np.int64))), np.concatenate((symbol, lone_symbol))
        first_at = np.zeros(len(spaced), np.int64)
        first_at[where] = firsts[unit_of]
        step = start - first_at[start]
        step = step.astype(np.uint16) if len(sizes) and sizes.max() < 65536 else step
        order = np.argsort(step, kind="stable")
        start, size, symbol, step = start[order], size[order], symbol[order], step[order]
        cuts = np.searchsorted(step, np.arange(int(sizes.max()) + 1 if len(sizes) else 1))
        last = np.full(len(spaced) + 1, -1, np.int64)
        width = np.zeros(len(spaced) + 1, np.int32)
        last[firsts] = START
        best = np.full(len(spaced) + 1, -np.inf) if not self.merges else None
        if best is not None:
            best[firsts] = 0.0
        for a, b in zip(cuts, [*cuts[1:], len(start)], strict=True):
            if a == b:
                continue
            s, e, x = start[a:b], start[a:b] + size[a:b], symbol[a:b]
            if best is None:
                good = self.side_by_side(last[s], x) & ((width[s] > 0) | (last[s] == START))
            else:
                gain = best[s] + np.where(x < 0, self.score.min(), self.score[x])
                good = gain > best[e]
                best[e[good]] = gain[good]
            last[e[good]], width[e[good]] = x[good], size[a:b][good]
        ends = firsts + sizes
        passed = np.zeros(len(spaced) + 1, bool)
        at, stop = ends[sizes > 0], firsts[sizes > 0]
        while len(at):
            passed[at] = True
            if (width[at] == 0).any():
                raise ValueError("a unit has no sequence of pieces")
            at = at - width[at]
            go = at > stop
            at, stop = at[go], stop[go]
        spots = np.flatnonzero(passed)
        ids = last[spots]
        unit = np.searchsorted(firsts, spots, "left") - 1
        few = np.flatnonzero((ids < 0) | (ids >= self.n_ids))
        if len(few):
            restored = np.zeros(len(spaced), np.uint32)
            restored[where] = points
            found = [self.byte_id[list(chr(c).encode("utf-8"))] for c in restored[spots[few] - 1]]
            times = np.ones(len(ids), np.int64)
            times[few] = [len(f) for f in found]
            ids, unit = np.repeat(ids, times), np.repeat(unit, times)
            at = np.cumsum(times) - times
            for k, f in zip(few, found, strict=True):
                ids[at[k] : at[k] + len(f)] = f
        return ids.astype(np.uint32), np.bincount(unit, minlength=len(units)).astype(np.int64)


def mixed_slot(key: np.ndarray) -> np.ndarray:
    return (mixed64(key.astype(np.uint64)) >> np.uint64(64 - CACHE_BITS)).astype(np.int64)


_BREAK = "\U0010fffe"


def units_of(texts: pa.Array) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """(code of each unit, distinct units with U+2581 for spaces, first unit of each text and the end)."""
    texts = pc.replace_substring(texts, MARK, " ")
    empty = pc.equal(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    if pc.any(pc.match_substring(texts, _BREAK)).as_py():
        lists = pa.array([_cut(" " + t) for t in texts.to_pylist()], pa.large_list(pa.large_string()))
    else:
        lead = pc.binary_join_element_wise(pa.scalar(" ", texts.type), texts, pa.scalar("", texts.type))
        lists = pc.split_pattern(pc.replace_substring_regex(lead, "([^ ]) ", rf"\1{_BREAK} "), _BREAK)
    offsets = lists.offsets.to_numpy().astype(np.int64)
    offsets = offsets - offsets[0]
    coded = lists.flatten().dictionary_encode()
    codes = coded.indices.to_numpy()
    if empty.any():  # an empty text has one unit of one space here, and none in truth
        keep = np.ones(len(codes), bool)
        keep[offsets[:-1][empty]] = False
        before = np.concatenate(([0], np.cumsum(keep)))
        codes, offsets = codes[keep], before[offsets]
    return codes, pc.replace_substring(coded.dictionary, " ", MARK), offsets


def _cut(text: str) -> list[str]:
    import re

    return re.findall(" +[^ ]*", text)


def encode_batch(pieces: Pieces, texts: pa.Array, memo: WordMemo | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all texts, first id of each and the end)."""
    codes, units, offsets = units_of(texts)
    ids, starts, lengths = (memo or pieces.memo())(units.to_pylist())
    out, ends = spread(ids, starts, lengths, codes.astype(np.int64))
    return out, np.concatenate(([0], ends))[offsets]


def decode_batch(pieces: Pieces, ids: np.ndarray, offsets: np.ndarray) -> list[str]:
    data, firsts, sizes = pieces.decoder
    raw, ends = spread(data, firsts, sizes, ids.astype(np.int64))
    cuts = np.concatenate(([0], ends))[offsets]
    whole = raw.tobytes()
    texts = (whole[a:b].decode("utf-8", "replace") for a, b in zip(cuts[:-1], cuts[1:], strict=True))
    return [t[1:] if t.startswith(" ") else t for t in texts]


def with_ids(docs: DataFrame, pieces: Pieces, text: str = "text", ids: str = "ids", decoded: str | None = None) -> DataFrame:
    """Adds the ids of a text column, and with `decoded` the text that these ids decode to; columns of those names are replaced."""
    docs = docs.drop(ids, *([decoded] if decoded else []))
    held = docs.sparkSession.sparkContext.broadcast(pieces)  # a vocabulary: it does not grow with the data
    fields = extended(docs, f"`{ids}` array<int>" + (f", `{decoded}` string" if decoded else ""))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = held.value.memo()
        for part in gathered(batches, text, BATCH_BYTES):
            found, offsets = encode_batch(held.value, texts_of(part, text), memo)
            made = part.append_column(ids, pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(found.astype(np.int32))))
            if decoded:
                made = made.append_column(decoded, pa.array(decode_batch(held.value, found, offsets), pa.string()))
            yield from made.to_batches()

    return docs.mapInArrow(encode, fields)


def with_text(docs: DataFrame, pieces: Pieces, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """Adds the text of a column of ids; null ids are none; a column of that name is replaced."""
    docs = docs.drop(text)
    held = docs.sparkSession.sparkContext.broadcast(pieces)
    fields = extended(docs, f"`{text}` string")

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(batch.schema.get_field_index(ids))
            sizes = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            offsets = np.concatenate(([0], np.cumsum(sizes)))
            cuts = [0, *(np.flatnonzero(np.diff(offsets[1:] // DECODE_IDS)) + 1).tolist(), len(sizes)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if b > a:
                    texts = decode_batch(held.value, flat[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                    yield pa.RecordBatch.from_arrays([*batch.slice(a, b - a).columns, pa.array(texts, pa.string())], [*batch.schema.names, text])

    return docs.mapInArrow(decode, fields)


def op1_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    pieces = Pieces.load(public_tokenizers.path("piece_bpe_32k.model"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    both = with_ids(docs, pieces, decoded="decoded")
    return both.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids", F.sha2("decoded", 256).alias("decoded_sha256"), (F.col("decoded") == F.coalesce("text", F.lit(""))).alias("round_trip"))
