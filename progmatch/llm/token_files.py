"""Token ids in files of directly addressable codes.

An id is cut into chunks of a few bits, the lowest first. Level k holds chunk k of every id that has one; a bitmap beside
it says whether the id goes on in level k + 1, and a directory holds the number of set bits before every 512th. The place
of an id's next chunk is the rank of its bit, so any id is read with one look into each of its levels: nothing before it is
decoded. The last level has no bitmap.

Documents are cut into ranges of doc_id, each range is put in order in one task and written as files of a bounded number of
ids; a table of the files lists their ranges, order, sizes and paths. Files that a lost or repeated task leaves are in no
row of that table and are never read. Documents without an id come first, equal ids follow one another by text hash; null
texts are empty and have only the end id; an empty table writes nothing.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from progmatch.llm.common import gathered, settle, shared_path, shuffle_width, table, texts_of, word_codes
from progmatch.llm.word_memo import WordMemo, spread

MAGIC, BITS, BLOCK, END_ID, FILE_IDS = b"DACF", 8, 512, 2, 4_000_000
FILES = "range int, number int, path string, n_docs long, n_tokens long"
#: Fixed value: a word apart that stands between words which are encoded together.
BETWEEN = "\x01"


# --- the format -----------------------------------------------------------------------------------------------------


def levels_of(ids: np.ndarray, bits: int = BITS) -> list[tuple[np.ndarray, np.ndarray | None]]:
    """(chunks, whether each goes on or None for the last) of each level."""
    if not 1 <= bits <= 8:
        raise ValueError(f"a chunk has 1 to 8 bits: {bits}")
    found, left = [], ids.astype(np.uint32)
    while True:
        chunk, left = (left & np.uint32((1 << bits) - 1)).astype(np.uint8), left >> np.uint32(bits)
        on = left > 0
        if not on.any():
            return [*found, (chunk, None)]
        found.append((chunk, on))
        left = left[on]


def packed(ids: np.ndarray, doc_ids: list[int | None], ends: np.ndarray, bits: int = BITS) -> bytes:
    """A file: ids of documents one after another; ends: the end of each document's."""
    levels = levels_of(ids, bits)
    parts = [MAGIC, struct.pack("<BBQQ", bits, len(levels), len(doc_ids), len(ids))]
    parts += [np.array([d is not None for d in doc_ids], np.uint8).tobytes(), np.array([d or 0 for d in doc_ids], "<i8").tobytes(), ends.astype("<u8").tobytes()]
    for chunk, on in levels:
        parts += [struct.pack("<Q", len(chunk)), chunk.tobytes()]
        if on is not None:
            before = np.concatenate(([0], np.cumsum(np.add.reduceat(on, np.arange(0, len(on), BLOCK), dtype=np.int64))))[:-1]
            parts += [np.packbits(on, bitorder="little").tobytes(), before.astype("<u4").tobytes()]
    body = b"".join(parts)
    return body + struct.pack("<I", zlib.crc32(body))


class TokenFile:
    """Reads a file's bytes. token(i) and document(k) look up only what they return; all_ids() decodes everything."""

    def __init__(self, data: bytes):
        if data[:4] != MAGIC or struct.unpack("<I", data[-4:])[0] != zlib.crc32(data[:-4]):
            raise ValueError("not a whole file of directly addressable codes")
        self.bits, n_levels, self.n_docs, self.n_tokens = struct.unpack_from("<BBQQ", data, 4)
        at = 4 + struct.calcsize("<BBQQ")

        def take(kind: str, n: int) -> np.ndarray:
            nonlocal at
            got = np.frombuffer(data, kind, n, at)
            at += got.nbytes
            return got

        given, ids, self.ends = take("u1", self.n_docs), take("<i8", self.n_docs), take("<u8", self.n_docs).astype(np.int64)
        self.doc_ids = [int(d) if g else None for g, d in zip(given, ids, strict=True)]
        self.levels = []
        for k in range(n_levels):
            n = int(take("<u8", 1)[0])
            chunk = take("u1", n)
            self.levels.append((chunk, *((take("u1", (n + 7) // 8), take("<u4", (n + BLOCK - 1) // BLOCK)) if k < n_levels - 1 else (None, None))))

    def token(self, i: int) -> int:
        if not 0 <= i < self.n_tokens:
            raise IndexError(i)
        value = 0
        for k, (chunk, on, before) in enumerate(self.levels):
            value |= int(chunk[i]) << (k * self.bits)
            if on is None or not on[i >> 3] >> (i & 7) & 1:
                return value
            start = i // BLOCK * BLOCK // 8
            bits = np.unpackbits(on[start : (i >> 3) + 1], bitorder="little")[: i - start * 8]
            i = int(before[i // BLOCK]) + int(bits.sum())
        return value

    def tokens(self, start: int, end: int) -> np.ndarray:
        """Ids from start to end: in each level they lie side by side."""
        out, where = np.zeros(end - start, np.uint32), np.arange(end - start)
        for k, (chunk, on, before) in enumerate(self.levels):
            if end <= start:
                break
            out[where] |= chunk[start:end].astype(np.uint32) << np.uint32(k * self.bits)
            if on is None:
                break
            first = start // BLOCK * BLOCK
            bits = np.unpackbits(on[first // 8 : (end + 7) // 8], bitorder="little")
            own = bits[start - first : end - first].astype(bool)
            start = int(before[start // BLOCK]) + int(bits[: start - first].sum())
            where, end = where[own], start + int(own.sum())
        return out

    def document(self, k: int) -> np.ndarray:
        return self.tokens(int(self.ends[k - 1]) if k else 0, int(self.ends[k]))

    def all_ids(self) -> np.ndarray:
        return self.tokens(0, self.n_tokens)


# --- encoding -------------------------------------------------------------------------------------------------------

_MEMOS: dict[str, WordMemo] = {}


def memo_for(path: str) -> WordMemo:
    if path not in _MEMOS:
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        mark = tokenizer.encode(BETWEEN, add_special_tokens=False).ids

        def ids_of(texts: list[str]) -> list[np.ndarray]:
            """Of each text; this call of the library's gives the same ids and leaves out where they lie, which costs it more."""
            return [np.array(x.ids, np.uint32) for x in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

        def encode(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
            ids, lengths = [], []
            for k in range(0, len(words), 4096):
                some = words[k : k + 4096]
                joined = f" {BETWEEN} ".join(some)
                if len(mark) != 1 or joined.count(BETWEEN) != len(some) - 1:
                    each = ids_of(some)
                    ids += each
                    lengths.append(np.array([len(x) for x in each], np.int64))
                    continue
                (got,) = ids_of([joined])
                apart = got == mark[0]
                lengths.append(np.diff(np.concatenate(([-1], np.flatnonzero(apart), [len(got)]))) - 1)
                ids.append(got[~apart])
                if len(lengths[-1]) != len(some):
                    raise ValueError("the tokenizer does not keep words apart")
            return np.concatenate(ids), np.concatenate(lengths)

        _MEMOS[path] = WordMemo(encode)
    return _MEMOS[path]


def encoded(texts: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all texts with the end id behind each, the end of each text's): white space never lies inside a token."""
    codes, words, offsets = word_codes(texts)
    ids, starts, lengths = memo_for(path)(words.to_pylist())
    stop = len(lengths)
    ids, starts, lengths = np.append(ids, np.uint32(END_ID)), np.append(starts, len(ids)), np.append(lengths, 1)
    codes = np.insert(codes.astype(np.int64), offsets[1:], stop)
    out, ends = spread(ids, starts, lengths, codes)
    return out, ends[offsets[1:] + np.arange(len(offsets) - 1)] if len(offsets) > 1 else np.empty(0, np.int64)


# --- files ----------------------------------------------------------------------------------------------------------


def open_store(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_files(docs: DataFrame, tokenizer: str, folder: str, file_ids: int = FILE_IDS) -> DataFrame:
    """Writes doc_id, text as files below `folder` (a URI that all executors share); returns the settled table of files."""
    spark = docs.sparkSession
    key = [F.col("doc_id").asc_nulls_first(), F.col("__h")]  # equal or missing ids can fill many ranges
    rows = docs.select("doc_id", "text", F.xxhash64("text").alias("__h")).repartitionByRange(shuffle_width(spark), *key).sortWithinPartitions(*key)
    rows = rows.select(F.spark_partition_id().alias("range"), "doc_id", "text")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = open_store(folder)
        store.create_dir(root, recursive=True)
        held: list = []
        state = {"range": None, "number": 0, "ids": 0}

        def flush() -> pa.RecordBatch:
            ids = np.concatenate([h[0] for h in held])
            lengths = np.concatenate([h[1] for h in held])
            doc_ids = [d for h in held for d in h[2]]
            name = f"{root}/{state['range'] + 1:08d}-{state['number']:06d}-{uuid.uuid4().hex}.dac"
            with store.open_output_stream(name) as f:
                f.write(packed(ids, doc_ids, np.cumsum(lengths)))
            row = pa.RecordBatch.from_pydict({"range": pa.array([state["range"]], pa.int32()), "number": pa.array([state["number"]], pa.int32()), "path": [name], "n_docs": pa.array([len(doc_ids)], pa.int64()), "n_tokens": pa.array([len(ids)], pa.int64())})
            held.clear()
            state.update(number=state["number"] + 1, ids=0)
            return row

        for part in gathered(batches, "text"):
            ids, ends = encoded(texts_of(part), tokenizer)
            lengths, ranges, doc_ids = np.diff(ends, prepend=0), part.column("range").to_numpy(), part.column("doc_id").to_pylist()
            cuts = [0, *(np.flatnonzero(np.diff(ranges)) + 1), len(ranges)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if state["range"] != ranges[a]:
                    if held:
                        yield flush()
                    state.update(range=int(ranges[a]), number=0)
                first = int(ends[a - 1]) if a else 0
                held.append((ids[first : int(ends[b - 1])], lengths[a:b], doc_ids[a:b]))
                state["ids"] += int(ends[b - 1]) - first
                if state["ids"] >= file_ids:
                    yield flush()
        if held:
            yield flush()

    return settle(rows.mapInArrow(write, FILES), "token-files")


def with_starts(files: DataFrame) -> DataFrame:
    """Adds start: ids in all files before. The ranges' sums, a row for each range, are added up in one task."""
    behind = lambda w: F.coalesce(F.sum("n_tokens").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranges = files.groupBy("range").agg(F.sum("n_tokens").alias("n_tokens")).select("range", behind(Window.orderBy("range")).alias("before"))
    inner = behind(Window.partitionBy("range").orderBy("number"))
    return files.withColumn("inner", inner).join(ranges, "range").withColumn("start", F.col("before") + F.col("inner")).drop("before", "inner")


def read_files(files: DataFrame, folder: str, digest: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids) of every document, from the files; with digest ids_crc32 instead of ids."""
    spark = files.sparkSession

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = open_store(folder)
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with store.open_input_stream(path) as f:
                    got = TokenFile(f.read())
                ids = got.all_ids().astype("<u4")
                firsts = np.concatenate(([0], got.ends[:-1]))
                if digest:
                    last = pa.array([zlib.crc32(ids[a:b].tobytes()) for a, b in zip(firsts, got.ends, strict=True)], pa.int64())
                else:
                    last = pa.ListArray.from_arrays(pa.array(np.append(firsts, len(ids)), pa.int32()), pa.array(ids.astype(np.int64)))
                arrays = [pa.array(got.doc_ids, pa.int64()), pa.array(firsts + start), pa.array(got.ends - firsts), last]
                yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "start", "n_tokens", "ids_crc32" if digest else "ids"])

    schema = f"doc_id long, start long, n_tokens long, {'ids_crc32 long' if digest else 'ids array<long>'}"
    dealt = with_starts(files).select("path", "start").repartition(shuffle_width(spark), "path")
    return dealt.mapInArrow(read, schema)


def op6_token_binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    folder = shared_path(spark, "ids")
    files = write_files(docs, public_tokenizers.path("word_bpe_49k.json"), folder)
    return read_files(files, folder, digest=True)
