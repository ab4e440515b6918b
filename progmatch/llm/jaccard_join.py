"""N-gram Jaccard join with Bayesian candidate pruning.

A text is the set of its five-word shingles (a text of one to four words is one shingle, an empty text the shingle of no
words). Texts with equal sets are one node; a node has a multiplicity. Nodes that agree on all hashes of a band of their
MinHash signatures meet in a bucket; buckets of the same members count once, in their first band. Inside a bucket, values
are compared a few at a time: a pair is dropped once the posterior probability that its similarity reaches the threshold,
given the agreements so far and a uniform prior, is below the tolerance. Pairs that survive are verified on their whole
shingle sets. A pair that meets in several buckets is handled in the first band it agrees on.

Links are never written out as pairs: a task adds up, for each node, the documents it is linked to, and gives spanning
links. Buckets beyond a block size are cut into blocks whose pairs are dealt to many tasks, so no bucket has to fit into
one. Classes are the connected components of links; a class's id is its least doc_id. A class without an id, or whose least
id is also that of another class (ids may be repeated), gets a negative number made from its least node instead.

With 32 bands of 4 hashes a pair at similarity 0.8 misses all bands with probability 5e-8, and pruning loses a pair with
probability of about the tolerance; both are the method's own errors, no pair is capped or sampled away. Null texts are
empty, all empty texts are copies of one another; rows with null doc_id take part, null sorting behind all ids.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import SHINGLE_WORDS, discard, extended, gathered, mixed64, settle, shuffle_width, table, texts_of, word_codes, word_hashes
from progmatch.llm.components import components

THRESHOLD, BANDS, ROWS, STEP, TOLERANCE, BLOCK = 0.8, 32, 4, 16, 1e-6, 512
HASHES = BANDS * ROWS
#: So many documents' ids at most are broadcast to pick their texts; more are joined by a shuffle.
BROADCAST_ROWS = 500_000


def shingles(texts: pa.Array, size: int = SHINGLE_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first of each text and the end): each distinct shingle hash of each text, ascending inside a text."""
    codes, words, offsets = word_codes(texts)
    h = word_hashes(words)[codes]
    n = len(offsets) - 1
    counts = np.diff(offsets)
    doc = np.repeat(np.arange(n), counts)
    runs = max(0, len(h) - size + 1)
    mixed = np.full(runs, size, np.uint64)
    for k in range(size):
        mixed = mixed * np.uint64(0x9E3779B97F4A7C15) + h[k : runs + k]
    whole = doc[:runs] == doc[size - 1 :] if runs else np.empty(0, bool)
    mixed, owner = mixed64(mixed[whole]), doc[:runs][whole]
    short = np.flatnonzero(counts < size)
    single = np.array([_of_few(h[offsets[i] : offsets[i + 1]]) for i in short], np.uint64)
    mixed, owner = np.concatenate((mixed, single)), np.concatenate((owner, short))
    order = np.lexsort((mixed, owner))
    mixed, owner = mixed[order], owner[order]
    first = np.ones(len(mixed), bool)
    first[1:] = (mixed[1:] != mixed[:-1]) | (owner[1:] != owner[:-1])
    return mixed[first], np.searchsorted(owner[first], np.arange(n + 1))


def _of_few(h: np.ndarray) -> int:
    value = len(h) + 1
    for x in h:
        value = (value * 0x9E3779B97F4A7C15 + int(x)) % 2**64
    return int(mixed64(np.array([value], np.uint64))[0])


_RNG = np.random.default_rng(20240501)
_XOR, _MULTIPLY = (_RNG.integers(1, 2**63, HASHES, dtype=np.uint64) for _ in range(2))


def signatures(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """MinHash values, a row for each text; every text has a shingle."""
    out = np.empty((len(starts) - 1, HASHES), np.uint32)
    for k in range(HASHES):
        v = (hashes ^ _XOR[k]) * (_MULTIPLY[k] | np.uint64(1))
        v ^= v >> np.uint64(31)
        out[:, k] = np.minimum.reduceat((v * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32), starts[:-1]).astype(np.uint32)
    return out


def least_agreements(threshold: float = THRESHOLD, tolerance: float = TOLERANCE, step: int = STEP) -> list[int]:
    """After step, 2 step, ... values: agreements below which P(similarity >= threshold | agreements) < tolerance."""
    found = []
    for n in range(step, HASHES + 1, step):
        for m in range(n + 1):
            reach = sum(comb(n + 1, j) * threshold**j * (1 - threshold) ** (n + 1 - j) for j in range(m + 1))
            if reach >= tolerance:
                break
        found.append(m)
    return found


def surviving(sig: np.ndarray, sizes: np.ndarray, band: int, blocks: np.ndarray, pair: tuple[int, int], threshold: float, least: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows of a bucket that pruning leaves: of the blocks in `pair`, first agreeing on `band`, sizes not too unequal."""
    rows = np.flatnonzero(blocks == pair[0])
    cols = rows if pair[0] == pair[1] else np.flatnonzero(blocks == pair[1])
    if not len(rows) or not len(cols):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    left, right = [], []
    slab = max(1, 1_000_000 // len(cols))
    for a in range(0, len(rows), slab):
        some = rows[a : a + slab]
        lo, hi = np.minimum(sizes[some][:, None], sizes[cols][None]), np.maximum(sizes[some][:, None], sizes[cols][None])
        open_pairs = lo >= threshold * hi - 1e-9
        if pair[0] == pair[1]:
            open_pairs &= some[:, None] < cols[None]
        i, j = np.nonzero(open_pairs)
        i, j = some[i], cols[j]
        for b in range(band):  # a pair belongs to the first band it agrees on
            if not len(i):
                break
            own = slice(b * ROWS, (b + 1) * ROWS)
            differ = (sig[i, own] != sig[j, own]).any(1)
            i, j = i[differ], j[differ]
        agree = np.zeros(len(i), np.int64)
        for t, bound in enumerate(least):
            if not len(i):
                break
            own = slice(t * STEP, (t + 1) * STEP)
            agree += (sig[i, own] == sig[j, own]).sum(1)
            keep = agree >= bound
            i, j, agree = i[keep], j[keep], agree[keep]
        left.append(i)
        right.append(j)
    return np.concatenate(left), np.concatenate(right)


def verified(sets: list[np.ndarray], i: np.ndarray, j: np.ndarray, threshold: float) -> np.ndarray:
    """Which of the pairs reach the threshold, by their whole sets."""
    sizes = np.array([len(s) for s in sets])
    if len(i) <= 4 * len(sets):
        both = np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i, j, strict=True)], np.int64)
    else:
        flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
        _, column, times = np.unique(flat, return_inverse=True, return_counts=True)
        shared = times[column] > 1
        shared_columns, column = np.unique(column[shared], return_inverse=True)
        owner = owner[shared]
        inter = np.zeros((len(sets), len(sets)), np.float32)
        order = np.argsort(column, kind="stable")
        column, owner = column[order], owner[order]
        width = max(1, 8_000_000 // len(sets))
        for c in range(0, len(shared_columns), width):
            a, b = np.searchsorted(column, (c, c + width))
            grid = np.zeros((len(sets), min(width, len(shared_columns) - c)), np.float32)
            grid[owner[a:b], column[a:b] - c] = 1
            inter += grid @ grid.T
        both = np.rint(inter[i, j]).astype(np.int64)
    return both >= threshold * (sizes[i] + sizes[j] - both) - 1e-9


def _cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of one cell at a time; they come sorted by bucket, part_a, part_b."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(3)]
        change = np.zeros(batch.num_rows - 1, bool)
        for k in keys:
            change |= k[1:] != k[:-1]
        cuts = [0, *(np.flatnonzero(change) + 1), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            key = tuple(int(k[a]) for k in keys)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def _matrix(part: pa.Table) -> np.ndarray:
    return np.frombuffer(b"".join(part.column("sig").to_pylist()), "<u4").reshape(-1, HASHES)


def nodes_of(docs: DataFrame) -> DataFrame:
    """(doc_id, node, n, sig) of every row, settled. node names the shingle set."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text"):
            hashes, starts = shingles(texts_of(part))
            sig = signatures(hashes, starts).astype("<u4")
            yield pa.RecordBatch.from_arrays([part.column("doc_id").combine_chunks(), pa.array(_names(hashes, starts), pa.string()), pa.array(np.diff(starts), pa.int64()), pa.array([r.tobytes() for r in sig], pa.binary())], ["doc_id", "node", "n", "sig"])

    return settle(docs.select("doc_id", "text").mapInArrow(make, "doc_id long, node string, n long, sig binary"), "shingle-nodes")


def _names(hashes: np.ndarray, starts: np.ndarray) -> list[str]:
    import xxhash

    raw = hashes.astype("<u8")
    return [xxhash.xxh3_128_hexdigest(raw[a:b]) for a, b in zip(starts[:-1], starts[1:], strict=True)]


def _band_keys(sig: DataFrame) -> DataFrame:
    """(bucket, band, node, n, sig is left out): the signature is cut natively, a key is the hash of its band and bytes."""
    width = ROWS * 4
    keys = F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda b: F.xxhash64(b, F.substring("sig", b * width + 1, F.lit(width))))
    return sig.select("node", F.posexplode(keys).alias("band", "bucket"))


def jaccard_classes(docs: DataFrame, threshold: float = THRESHOLD, tolerance: float = TOLERANCE, block: int = BLOCK) -> DataFrame:
    """(doc_id, class_id, n_links, node, chosen): a row for each row of docs (doc_id, text).

    chosen marks the rows of a class's least doc_id and its node: one of them stands for the class. n_links is the number of other rows at a Jaccard similarity of the threshold or more, exact copies included.
    """
    if threshold < THRESHOLD:
        raise ValueError(f"the bands are made for similarities of {THRESHOLD} or more: {threshold}")
    spark = docs.sparkSession
    least, width = least_agreements(threshold, tolerance), shuffle_width(spark)
    rows = nodes_of(docs)
    nodes = settle(rows.groupBy("node").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("times"), F.first("n").alias("n"), F.first("sig").alias("sig")), "nodes", large=True)

    keys = _band_keys(nodes)
    met = keys.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"), F.min("band").alias("band"), F.bit_xor(F.xxhash64("node")).alias("x"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("y")).where("m > 1")
    once = met.groupBy("m", "x", "y").agg(F.min(F.struct("band", "bucket")).alias("f")).select("f.bucket", "m")
    # a member of a bucket of several blocks goes to every pair of blocks that its own is in
    parts = F.ceil(F.col("m") / block).cast("int")
    members = keys.join(once, "bucket").withColumn("parts", parts).withColumn("part", F.pmod(F.xxhash64("node", F.lit(2)), F.col("parts")).cast("int"))
    others = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.struct(F.least(o, F.col("part")).alias("a"), F.greatest(o, F.col("part")).alias("b")))
    members = members.withColumn("cell", F.explode(others)).select("bucket", F.col("cell.a").alias("part_a"), F.col("cell.b").alias("part_b"), "band", "part", "node")
    cells = members.join(nodes.select("node", "n", "sig"), "node").select("bucket", "part_a", "part_b", "band", "part", "node", "n", "sig")

    def dealt(df: DataFrame) -> DataFrame:
        return df.repartition(width, "bucket", "part_a", "part_b").sortWithinPartitions("bucket", "part_a", "part_b")

    def pruned(part: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        head = part.slice(0, 1).to_pylist()[0]
        return surviving(_matrix(part), part.column("n").to_numpy(), head["band"], part.column("part").to_numpy(), (head["part_a"], head["part_b"]), threshold, least)

    def prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _cells(batches):
            i, j = pruned(part)
            if len(i):
                used = pa.array(np.unique(np.concatenate((i, j))))
                yield from part.select(["bucket", "part_a", "part_b", "band", "part", "node"]).take(used).to_batches()

    left = settle(dealt(cells).mapInArrow(prune, "bucket long, part_a int, part_b int, band int, part int, node string"), "pruned", large=True)
    needed = left.select("node").distinct().join(nodes.select("node", "first"), "node")
    needed = settle(needed.select("node", "first"), "needed")
    sets = _sets(docs, needed)
    full = left.join(sets, "node").join(nodes.select("node", "n", "sig", "times"), "node")
    full = full.select("bucket", "part_a", "part_b", "band", "part", "node", "n", "sig", "times", "shingles")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _cells(batches):
            i, j = pruned(part)
            found = [np.frombuffer(s, "<u8") for s in part.column("shingles").to_pylist()]
            good = verified(found, i, j, threshold)
            i, j = i[good], j[good]
            times, names = part.column("times").to_numpy(), part.column("node").to_pylist()
            linked = np.bincount(i, times[j], minlength=len(names)) + np.bincount(j, times[i], minlength=len(names))
            root = _spanning(len(names), i, j)
            some = np.flatnonzero(linked)
            if len(some):
                yield pa.RecordBatch.from_arrays([pa.array([names[k] for k in some]), pa.array([names[root[k]] for k in some]), pa.array(linked[some].astype(np.int64))], ["a", "b", "linked"])

    links = settle(dealt(full).mapInArrow(verify, "a string, b string, linked long"), "links", large=True)
    discard(left, needed)
    roots = components(links.select("a", "b"))
    linked = links.groupBy(F.col("a").alias("node")).agg(F.sum("linked").alias("linked"))
    named = nodes.select("node", "first", "times").join(roots, "node", "left").join(linked, "node", "left").withColumn("root", F.coalesce("root", "node"))
    picked = F.min(F.struct(F.col("first").isNull().alias("none"), "first", "node")).alias("p")
    named_classes = classes = settle(named.groupBy("root").agg(picked).select("root", F.col("p.first").alias("least"), F.col("p.node").alias("stands")), "classes")
    shared = classes.where("least is not null").groupBy("least").agg(F.count(F.lit(1)).alias("m"), F.min("root").alias("owner")).where("m > 1").select("least", "owner")
    made = -F.pmod(F.xxhash64("root"), F.lit(2**63 - 1)) - 1
    class_id = F.when(F.col("least").isNull() | (F.col("owner") != F.col("root")), made).otherwise(F.col("least"))
    classes = classes.join(shared, "least", "left").select("root", "least", "stands", class_id.alias("class_id"))
    linked = (F.col("times") - 1 + F.coalesce("linked", F.lit(0))).alias("n_links")
    placed = named.join(classes, "root").select("node", "class_id", linked, F.when(F.col("node") == F.col("stands"), F.col("least")).alias("least"), (F.col("node") == F.col("stands")).alias("stands"))
    placed = settle(placed, "placed")
    discard(nodes, links, named_classes)
    chosen = F.col("stands") & F.col("doc_id").eqNullSafe(F.col("least"))
    return rows.select("doc_id", "node").join(placed, "node").select("doc_id", "class_id", "n_links", "node", chosen.alias("chosen"))


def _spanning(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Least member of each row's component in a cell: labels fall until none moves."""
    root = np.arange(n)
    while True:
        new = root.copy()
        np.minimum.at(new, i, root[j])
        np.minimum.at(new, j, root[i])
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _sets(docs: DataFrame, needed: DataFrame) -> DataFrame:
    """(node, shingles) of the nodes needed, from one document of each."""
    by_id = needed.where("first is not null").select(F.col("first").alias("doc_id")).distinct()
    n = by_id.count()
    picked = docs.select("doc_id", "text").join(F.broadcast(by_id) if n <= BROADCAST_ROWS else by_id, "doc_id", "left_semi")
    if needed.where("first is null").limit(1).count():
        picked = picked.union(docs.select("doc_id", "text").where("doc_id is null"))

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text"):
            hashes, starts = shingles(texts_of(part))
            raw = hashes.astype("<u8")
            yield pa.RecordBatch.from_arrays([pa.array(_names(hashes, starts)), pa.array([raw[a:b].tobytes() for a, b in zip(starts[:-1], starts[1:], strict=True)], pa.binary())], ["node", "shingles"])

    made = picked.mapInArrow(make, "node string, shingles binary")
    return made.join(needed.select("node"), "node", "left_semi").dropDuplicates(["node"])


def _with_node(docs: DataFrame) -> DataFrame:
    """docs with `__node`, the name of each row's shingle set."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, "text"):
            yield from part.append_column("__node", pa.array(_names(*shingles(texts_of(part))), pa.string())).to_batches()

    return docs.mapInArrow(make, extended(docs, "__node string"))


def one_of_each(docs: DataFrame) -> DataFrame:
    """The documents without near duplicates: one row of each class, of its least doc_id.

    Where an id is null or repeated, it does not tell the rows of different classes apart: those rows are picked by id and
    shingle set.
    """
    classes = settle(jaccard_classes(docs).select("doc_id", "node", "chosen"), "kept")
    ids = settle(classes.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"), F.max("chosen").alias("chosen")).where("chosen").select(F.col("doc_id").alias("__kept"), "n"), "ids")
    plain, unclear = ids.where("n = 1 and __kept is not null").select("__kept"), ids.where("n > 1 or __kept is null").select("__kept")
    n = plain.count()
    rows = docs.join(F.broadcast(plain) if n <= BROADCAST_ROWS else plain, F.col("doc_id") == F.col("__kept"), "left_semi")
    if not unclear.limit(1).count():
        return rows
    picked = classes.where("chosen").join(unclear, F.col("doc_id").eqNullSafe(F.col("__kept")), "left_semi").select(F.col("doc_id").alias("__kept"), F.col("node").alias("__node")).distinct()
    named = _with_node(docs.join(unclear, F.col("doc_id").eqNullSafe(F.col("__kept")), "left_semi"))
    alike = F.col("doc_id").eqNullSafe(F.col("__kept")) & (named["__node"] == picked["__node"])
    return rows.unionByName(named.join(picked, alike, "left_semi").dropDuplicates(["doc_id", "__node"]).drop("__node"))


def op9_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "class_id", "n_links")
