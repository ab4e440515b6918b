"""The sorted list and its position pairs in packed form: few bytes for each pair go through the shuffle, and nothing else does.

The list is put in order once and kept as chunks of profile keys; a position is its place. A chunk, with the first keys of the
next, has the pairs that begin in it. Each task reads the whole list, takes the pairs that its profiles own and adds them up:
no pair is shuffled. What tasks read grows with the square of the list, so a list of over MOST_READ positions is read once, its
pairs dealt by their owner and packed as bytes. The sums go straight to their reader: pairs are not settled.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from progmatch.functions.text import words
from progmatch.operators.order import positioned
from progmatch.operators.schedule import SCHEDULERS
from progmatch.operators.sortedlist import SCOPES, SORTED_WEIGHTS
from progmatch.session import drop, release, settle, shuffle_width
from progmatch.sources.profiles import Task

CHUNK = 1 << 17
#: Positions dealt to ranges at once, and positions of a range, about.
DEALT_ROWS, RANGE_ROWS = 1 << 18, 1 << 21
#: Texts from which the ranges are told, and of their positions one in so many.
CUT_TEXTS, CUT_PART = 1000, 16
#: Owners are dealt into so many lots for each task of the session.
LOTS = 32
#: Numbers of positions are sent to every task up to so many profiles.
MOST_PROFILES = 4_000_000
LARGEST_ID = 1 << 57
#: Every task reads the list up to so many positions; beyond, pairs are shuffled.
MOST_READ = 1 << 28
#: Position pairs that a task of the list's readers holds at most, about.
TASK_PAIRS = 1 << 23
#: Tasks whose pairs are counted first, to tell about how far a budget reaches, and by how much more is given on at once.
TRIED, MARGIN = 6, 1.25


def packed_list(task: Task, seed: int = 0, chunk: int = CHUNK) -> DataFrame:
    """Settled (at, k, keys): chunk k of range `at`, keys in the list's order as 64-bit integers; linkage: 2 pid + (0 for L, 1 for R).

    Positions are dealt to ranges of tokens and ties as blobs, each with a dictionary of its tokens, and put in order as numbers.
    """
    spark = task.profiles.sparkSession
    key = 2 * F.col("pid") + F.when(F.col("source") == "L", 0).otherwise(1) if task.linkage else F.col("pid")
    tie = F.unhex(F.md5(F.concat("token", F.lit("|"), "source", F.lit(":"), F.col("pid").cast("string"), F.lit(f"|{seed}"))))

    def rows_of(profiles: DataFrame) -> DataFrame:
        rows = profiles.select(F.explode(F.array_distinct(words(F.col("text")))).alias("token"), "source", "pid")
        return rows.select("token", tie.alias("tie"), key.alias("key"))

    cuts = _cuts(task.profiles, rows_of)
    known = spark.sparkContext.broadcast(cuts)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= DEALT_ROWS:
                yield _dealt(pa.Table.from_batches(held).combine_chunks().to_batches()[0], *known.value)
                held, size = [], 0
        if size:
            yield _dealt(pa.Table.from_batches(held).combine_chunks().to_batches()[0], *known.value)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def out() -> Iterator[pa.RecordBatch]:
            keys = _sorted_keys(held)
            held.clear()
            for k in range(-(-len(keys) // chunk)):
                data = keys[k * chunk : (k + 1) * chunk].astype("<i8").tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([k], pa.int32()), pa.array([data], pa.binary())], ["at", "k", "keys"])

        for batch in batches:
            for at, *parts in zip(batch.column(0).to_pylist(), *(batch.column(c) for c in range(1, 5)), strict=True):
                if at != now and held:
                    yield from out()
                now = at
                tokens, codes, ties, keys = (x.as_py() for x in parts)
                n = len(ties) // 16
                held.append((tokens, _whole(codes, 0, n)[0], np.frombuffer(ties, "<u8"), _whole(keys, 0, n)[0]))
        if held:
            yield from out()

    kinds = "at int, tokens array<binary>, codes binary, ties binary, keys binary"
    dealt = rows_of(task.profiles).mapInArrow(deal, kinds).repartitionById(len(cuts[0]) + 1, "at").sortWithinPartitions("at")
    made = settle(dealt.mapInArrow(pack, "at int, k int, keys binary"), "packed-list", "zstd")
    release(made.sparkSession)
    return made


def _cuts(profiles: DataFrame, rows_of: Callable[[DataFrame], DataFrame]) -> tuple[list[bytes], np.ndarray]:
    """(tokens, upper halves of ties) where ranges of the list begin, from the positions of a sample: any cuts give the same list."""
    share = min(1.0, CUT_TEXTS / max(1, profiles.count()))
    some = profiles.where(F.pmod(F.xxhash64("pid", F.lit(5)), F.lit(1_000_000)) < int(share * 1_000_000) + 1)
    rows = rows_of(some).where(F.substring("tie", 1, 1) < F.lit(bytearray([256 // CUT_PART])))
    seen = rows.select(F.encode("token", "UTF-8").alias("token"), F.substring("tie", 1, 8).alias("tie")).toArrow()
    release(profiles.sparkSession)
    # the first byte of a tie is low in this sample; stretched, ties cover all of their range again
    points = sorted(zip(seen.column(0).to_pylist(), (int.from_bytes(x, "big") * CUT_PART for x in seen.column(1).to_pylist()), strict=True))
    ranges = max(shuffle_width(profiles.sparkSession), int(len(points) * CUT_PART / share) // RANGE_ROWS + 1)
    points = [points[len(points) * k // ranges] for k in range(1, ranges)] if points else []
    points = sorted(set(points))
    return [t for t, _ in points], np.array([x for _, x in points], np.uint64)


def _dealt(rows: pa.RecordBatch, tokens: list[bytes], ties: np.ndarray) -> pa.RecordBatch:
    """(at, tokens, codes, ties, keys) of each range that some of the rows (token, tie, key) lie in."""
    words_of = rows.column(0).dictionary_encode()
    names, code = [x.encode() for x in words_of.dictionary.to_pylist()], words_of.indices.to_numpy().astype(np.int64)
    tie = np.frombuffer(b"".join(rows.column(1).to_pylist()), ">u8").astype(np.uint64).reshape(-1, 2)
    key = rows.column(2).to_numpy()
    low, high = (np.array([side(tokens, x) for x in names], np.int64) for side in (bisect_left, bisect_right))
    at = low[code]
    cut = np.flatnonzero((low < high)[code])
    if len(cut):  # tokens that more than one range has
        order = cut[np.argsort(code[cut], kind="stable")]
        heads = np.flatnonzero(np.diff(code[order], prepend=-1))
        for a, b in zip(heads, [*heads[1:], len(order)], strict=True):
            own, c = order[a:b], code[order[a]]
            at[own] += np.searchsorted(ties[low[c] : high[c]], tie[own, 0], "right")
    order = np.argsort(at, kind="stable")
    ends = np.flatnonzero(np.diff(at[order], append=-1)) + 1
    made = []
    for a, b in zip([0, *ends[:-1]], ends, strict=True):
        own = order[a:b]
        used, codes = np.unique(code[own], return_inverse=True)
        made.append((int(at[own[0]]), [names[c] for c in used], _trimmed(codes), tie[own].astype("<u8").tobytes(), _trimmed(key[own])))
    types = (pa.int32(), pa.list_(pa.binary()), pa.binary(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*made, strict=True), types, strict=True)], ["at", "tokens", "codes", "ties", "keys"])


def _sorted_keys(parts: list[tuple[list[bytes], np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
    """Keys of a range's parts (tokens, codes, ties, keys) in the order of tokens and ties."""
    rank = {x: k for k, x in enumerate(sorted({x for p in parts for x in p[0]}))}
    token = np.concatenate([np.array([rank[x] for x in p[0]], np.uint64)[p[1]] for p in parts])
    tie, key = np.concatenate([p[2] for p in parts]).reshape(-1, 2), np.concatenate([p[3] for p in parts])
    bits = np.uint64(max(1, len(rank).bit_length()))
    near = token << (np.uint64(64) - bits) | tie[:, 0] >> bits
    order = np.argsort(near)
    near = near[order]
    if (near[1:] == near[:-1]).any():
        order = np.lexsort((tie[:, 1], tie[:, 0], token))
    return key[order]


def _following(packed: DataFrame, reach: int) -> dict[tuple[int, int], np.ndarray]:
    """The first `reach` keys behind each chunk: the driver sees so many keys of each."""
    rows = sorted((r["at"], r["k"], bytes(r["head"])) for r in packed.select("at", "k", F.substring("keys", 1, 8 * reach).alias("head")).collect())
    found, behind = {}, np.empty(0, np.int64)
    for at, k, head in reversed(rows):
        found[at, k] = behind
        behind = np.concatenate((np.frombuffer(head, "<i8"), behind))[:reach]
    return found


def _trimmed(x: np.ndarray) -> bytes:
    """As many bytes of each number as the largest needs, behind their count."""
    n = 8 if len(x) and x.min() < 0 else max(1, (int(x.max(initial=0)).bit_length() + 7) // 8)
    return bytes([n]) + np.ascontiguousarray(x.astype("<i8")[:, None].view(np.uint8)[:, :n]).tobytes()


def _whole(data: bytes, at: int, count: int) -> tuple[np.ndarray, int]:
    n = data[at]
    out = np.zeros((count, 8), np.uint8)
    out[:, :n] = np.frombuffer(data, np.uint8, count * n, at + 1).reshape(count, n)
    return out.view("<i8")[:, 0], at + 1 + count * n


def position_pairs(keys: np.ndarray, behind: np.ndarray, reach: int, linkage: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(l, r, d) of the pairs that begin at a key of the chunk."""
    every, parts = np.concatenate((keys, behind)), []
    for d in range(1, reach + 1):
        a = every[: min(len(keys), max(0, len(every) - d))]
        b = every[d : d + len(a)]
        use = (a ^ b) & 1 == 1 if linkage else a != b
        a, b = a[use], b[use]
        first = a & 1 == 0 if linkage else a < b
        l, r = np.where(first, a, b), np.where(first, b, a)  # noqa: E741
        parts.append((l >> 1, r >> 1, np.full(len(l), d)) if linkage else (l, r, np.full(len(l), d)))
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


Finish = Callable[[np.ndarray, np.ndarray, np.ndarray], list[np.ndarray]]  # (l, r, h of shape (pairs, reach)) -> columns


def owned_pairs(every: np.ndarray, n: int, at: np.ndarray, reach: int, linkage: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(l, r, d) of the pairs that begin at one of the first `n` keys and whose l stands at one of the places `at`."""
    steps = np.concatenate((np.arange(-reach, 0), np.arange(1, reach + 1)))
    there = at[:, None] + steps
    begin = np.minimum(at[:, None], there)
    use = (begin >= 0) & (begin < n) & (there < len(every))
    l, r = every[at], every[np.where(use, there, 0)]  # noqa: E741
    use &= r & 1 == 1 if linkage else r > l[:, None]
    row, step = np.nonzero(use)
    l, r, d = l[row], r[row, step], np.abs(steps)[step]  # noqa: E741
    return (l >> 1, r >> 1, d) if linkage else (l, r, d)


def _lots_of(l: np.ndarray, lots: int) -> np.ndarray:  # noqa: E741
    """The lot of each owner, 0 to lots - 1."""
    return ((l.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) * np.uint64(lots) >> np.uint64(32)).astype(np.int64)


def _as_one(l: np.ndarray, value: np.ndarray, bits: int) -> tuple[np.ndarray, ...]:  # noqa: E741
    """(l, value), or where ids are small enough one number for both: it takes half the room and sorts far faster."""
    room = (63 - bits) // 2
    fits = min(l.min(), value.min()) >= 0 and l.max() < 1 << room and value.max() < 1 << room + bits
    return (l << room + bits | value,) if fits else (l, value)


def _in_order(parts: list[tuple[np.ndarray, ...]], bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(l, value) of all parts, in this order."""
    low = (63 - bits) // 2 + bits
    apart = lambda both: (both >> low, both & ((1 << low) - 1))
    if all(len(p) == 1 for p in parts):
        both = np.concatenate([p[0] for p in parts])
        both.sort()
        return apart(both)
    l, value = (np.concatenate(c) for c in zip(*[apart(*p) if len(p) == 1 else p for p in parts], strict=True))  # noqa: E741
    order = np.lexsort((value, l))
    return l[order], value[order]


def _check_ids(*ids: np.ndarray) -> None:
    if max(abs(int(x)) for c in ids for x in (c.min(), c.max())) >= LARGEST_ID:
        raise ValueError("ids of 2^57 and more can't be packed")


def summed(packed: DataFrame, reach: int, linkage: bool, schema: str, finish: Finish, whole: bool = False, tried: bool = False) -> DataFrame:
    """(l, r, columns of `finish`) of every pair of profiles at most `reach` positions apart, each once; with `whole`, what finish
    makes of all pairs of some owners is the result: pairs of a call are in the order of l and r, and no other call has the same l.
    tried: of some owners only, where they are a small part; the result's `share` tells which part of all owners they are, about."""
    spark, bits = packed.sparkSession, reach.bit_length()
    behind = spark.sparkContext.broadcast(_following(packed, reach))
    names = [f.split(" ")[0] for f in schema.split(", ")]

    def added(parts: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        l, value = _in_order(parts, bits)  # noqa: E741
        r, d = value >> bits, value & ((1 << bits) - 1)
        new = np.ones(len(l), bool)
        new[1:] = (l[1:] != l[:-1]) | (r[1:] != r[:-1])
        pair = np.cumsum(new) - 1
        l, r, n = l[new], r[new], int(pair[-1]) + 1  # noqa: E741
        h = np.bincount((d - 1) * n + pair, minlength=n * reach).reshape(reach, n).T
        columns = finish(l, r, h) if whole else [l, r, *finish(l, r, h)]
        for a in range(0, len(columns[0]), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(c[a : a + (1 << 16)]) for c in columns], names)

    positions = packed.agg(F.coalesce(F.sum(F.length("keys")), F.lit(0))).first()[0] // 8
    if positions <= MOST_READ:
        return _summed_by_reading(packed, behind, reach, linkage, schema, added, positions, tried)
    made = _summed_by_dealing(packed, behind, reach, linkage, schema, added)
    made.share = 1.0
    return made


def _summed_by_reading(packed: DataFrame, behind, reach: int, linkage: bool, schema: str, added: Callable, positions: int, tried: bool) -> DataFrame:
    spark, bits = packed.sparkSession, reach.bit_length()
    tasks = max(2 * spark.sparkContext.defaultParallelism, -(-positions * reach // (2 * TASK_PAIRS if linkage else TASK_PAIRS)))
    some = min(tasks, TRIED) if tried else tasks

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in range(LOTS)]
        for batch in batches:
            for row in range(batch.num_rows):
                at, k, task = (batch.column(c)[row].as_py() for c in (0, 1, 3))
                keys = np.frombuffer(batch.column(2)[row].as_buffer(), "<i8")
                every = np.concatenate((keys, behind.value[at, k]))
                lot = _lots_of(every >> 1 if linkage else every, tasks * LOTS)
                mine = lot // LOTS == task
                l, r, d = owned_pairs(every, len(keys), np.flatnonzero(mine & (every & 1 == 0) if linkage else mine), reach, linkage)  # noqa: E741
                if not len(l):
                    continue
                _check_ids(l, r)
                lot, packed_pairs = _lots_of(l, tasks * LOTS) % LOTS, _as_one(l, r << bits | d, bits)
                for j in range(LOTS):
                    use = lot == j
                    if use.any():
                        held[j].append(tuple(c[use] for c in packed_pairs))
        for j in range(LOTS):
            if parts := held[j]:
                held[j] = []
                yield from added(parts)

    # one partition of the list meets each task: the task streams it
    ask = spark.range(0, some, 1, some).select(F.col("id").alias("task")).hint("shuffle_replicate_nl")
    made = packed.select("at", "k", "keys").coalesce(1).crossJoin(ask).mapInArrow(run, schema)
    made.share = some / tasks
    return made


def _summed_by_dealing(packed: DataFrame, behind, reach: int, linkage: bool, schema: str, added: Callable) -> DataFrame:
    spark, bits = packed.sparkSession, reach.bit_length()
    lots = LOTS * shuffle_width(spark)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, k, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                keys = np.frombuffer(data.as_buffer(), "<i8")
                l, r, d = position_pairs(keys, behind.value[at, k], reach, linkage)  # noqa: E741
                if not len(l):
                    continue
                _check_ids(l, r)
                lot = _lots_of(l, lots).astype(np.int32)
                order = np.lexsort((l, lot))
                l, value, lot = l[order], (r << bits | d)[order], lot[order]  # noqa: E741
                new = np.ones(len(l), bool)
                new[1:] = l[1:] != l[:-1]
                heads = np.flatnonzero(new)
                counts = np.diff(heads, append=len(l))
                cuts = np.flatnonzero(np.diff(lot, prepend=-1))
                ends = np.append(cuts[1:], len(l))
                own = np.searchsorted(heads, np.append(cuts, len(l)))
                blobs = []
                for j, (a, b) in enumerate(zip(cuts, ends, strict=True)):
                    o = slice(own[j], own[j + 1])
                    blobs.append(np.array([own[j + 1] - own[j], b - a], "<u4").tobytes() + _trimmed(l[heads[o]]) + _trimmed(counts[o]) + _trimmed(value[a:b]))
                yield pa.RecordBatch.from_arrays([pa.array(lot[cuts]), pa.array(blobs, pa.binary())], ["lot", "packed"])

    def unpacked(data: bytes) -> tuple[np.ndarray, np.ndarray]:
        n, m = (int(x) for x in np.frombuffer(data, "<u4", 2))
        owners, at = _whole(data, 8, n)
        counts, at = _whole(data, at, n)
        return np.repeat(owners, counts), _whole(data, at, m)[0]

    def add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, parts = None, []
        for batch in batches:
            for lot, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if parts and lot != now:
                    yield from added(parts)
                    parts = []
                now = lot
                parts.append(_as_one(*unpacked(data.as_buffer().to_pybytes()), bits))
        if parts:
            yield from added(parts)

    # chunks are far smaller than what comes of them: each range of the list has its own task
    dealt = packed.repartition(max(1, packed.count()), "at", "k").mapInArrow(deal, "lot int, packed binary")
    return dealt.repartition(shuffle_width(spark), "lot").sortWithinPartitions("lot").mapInArrow(add_up, schema)


def histograms(packed: DataFrame, window: int, linkage: bool) -> DataFrame:
    """(l, r, h1 .. h<window>): position pairs at each distance."""
    schema = "l long, r long, " + ", ".join(f"h{d} long" for d in range(1, window + 1))
    return summed(packed, window, linkage, schema, lambda l, r, h: [np.ascontiguousarray(h[:, d]) for d in range(window)])


def weights(h: np.ndarray, weight: str, scope: str, p: np.ndarray | None = None, q: np.ndarray | None = None) -> np.ndarray:
    """sortedlist.sorted_weight on arrays."""
    window = h.shape[1]
    times = [window - d if scope == "global" else 1 for d in range(window)]
    if weight in ("acf", "id"):
        return sum(h[:, d] * times[d] / (d + 1 if weight == "id" else 1) for d in range(window))
    acf = np.cumsum(h, axis=1).astype(np.float64)

    def norm(a: np.ndarray) -> np.ndarray:
        if weight == "dncf":
            return 2 * a / (p + q)
        if weight == "cncf":
            return a / np.sqrt(p * q)
        below = p + q - a
        return np.where(below > 0, a / np.where(below > 0, below, 1), a)

    return sum(norm(acf[:, d]) for d in range(window)) if scope == "global" else norm(acf[:, -1])


def position_counts(packed: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(keys ascending, positions of each)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0):
                keys, n = np.unique(np.frombuffer(data.as_buffer(), "<i8"), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(n.astype(np.int64))], ["key", "p"])

    sums = packed.select("keys").mapInArrow(count, "key long, p long").groupBy("key").agg(F.sum("p").alias("p"))
    sums = settle(sums, "positions")
    release(packed.sparkSession)
    if sums.count() > MOST_PROFILES:
        raise ValueError(f"more than {MOST_PROFILES} profiles: join their numbers of positions to the histogram instead (sortedlist.with_positions)")
    rows = sums.toPandas().sort_values("key")
    return rows["key"].to_numpy(np.int64), rows["p"].to_numpy(np.float64)


def _weigher(packed: DataFrame, weight: str, scope: str, linkage: bool) -> Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
    """(l, r, h) -> weights, not rounded."""
    if weight not in SORTED_WEIGHTS or scope not in SCOPES:
        raise ValueError(f"unknown weight or scope: {weight}, {scope}")
    if weight in ("acf", "id"):
        return lambda l, r, h: weights(h, weight, scope)
    known = packed.sparkSession.sparkContext.broadcast(position_counts(packed))

    def weigh(l: np.ndarray, r: np.ndarray, h: np.ndarray) -> np.ndarray:  # noqa: E741
        keys, p = known.value
        of = lambda x: p[np.searchsorted(keys, x)]
        return weights(h, weight, scope, of(2 * l if linkage else l), of(2 * r + 1 if linkage else r))

    return weigh


def packed_weights(packed: DataFrame, weight: str, scope: str, window: int, linkage: bool) -> DataFrame:
    """(l, r, w), rounded, of every pair inside the window."""
    weigh = _weigher(packed, weight, scope, linkage)
    made = summed(packed, window, linkage, "l long, r long, w double", lambda l, r, h: [weigh(l, r, h)])
    return made.withColumn("w", F.round("w", 9)).where("w > 0")


def _nine(x: np.ndarray) -> np.ndarray:
    return np.floor(x * 1e9 + 0.5) / 1e9


def _heaviest_first(node: np.ndarray, w: np.ndarray) -> np.ndarray:
    """The order by node, then falling w, then place, as one sort of numbers where they fit. Nodes ascend from 0."""
    levels = np.unique(w)
    places, steps = len(w).bit_length(), len(levels).bit_length()
    if not len(w) or int(node[-1]).bit_length() + steps + places > 63:
        return np.lexsort((-w, node))
    keys = (node << steps | (len(levels) - 1 - np.searchsorted(levels, w))) << places | np.arange(len(w))
    keys.sort()
    return keys & ((1 << places) - 1)


def _order_keys(kind: str, l: np.ndarray, r: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:  # noqa: E741
    """Four numbers that put a linkage's pairs in the scheduler's order, the left profile its node. All pairs of a node are there, by l and r."""
    zero = np.zeros(len(l), np.int64)
    if kind == "edge":
        return zero, -w, l, r
    node = np.cumsum(np.diff(l, prepend=l[:1]) != 0)
    first = np.searchsorted(node, np.arange(node[-1] + 1 if len(node) else 0))
    s = -_nine(np.bincount(node, w) / np.bincount(node))[node]
    order = _heaviest_first(node, w)
    t = np.empty(len(l), np.int64)
    t[order] = np.arange(len(l)) - first[node] + 1
    if kind == "depth":
        return zero, s, l, t
    if kind == "breadth":
        return t, s, l, zero
    best = t == 1
    return np.where(best, 1, 2), np.where(best, -w, s), l, np.where(best, r, t)


#: Steps in which the second key of an order is counted: as many as doubles have in their upper bits.
KEY_BITS = 24


def _steps(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Whole numbers that never fall where (first, second) rises."""
    bits = (second + 0.0).view(np.int64)
    rising = np.where(bits < 0, ~bits, bits | np.int64(-(1 << 63))).view(np.uint64) >> np.uint64(64 - KEY_BITS)
    return first << KEY_BITS | rising.astype(np.int64)


def _steps_of(kind: str, keys: tuple[np.ndarray, ...]) -> np.ndarray:
    """The steps of an order's keys. Breadth rises with the place in the node, at which each node has one pair at most: the driver sees
    no more steps than the largest node has pairs."""
    return keys[0] if kind == "breadth" else _steps(*keys[:2])


def packed_schedule(packed: DataFrame, weight: str, scope: str, window: int, kind: str, budget: int) -> DataFrame:
    """(pos, l, r, w): what schedule() gives for packed_weights() of a linkage, anchor left, without all pairs on disk.

    A node's pairs are all in one task, which knows their places in the order but for the number of pairs before. Pairs of some nodes
    are counted by steps of the order first, which tells about what step the budget reaches; all nodes then give on their pairs up to
    a step beyond. Should these be fewer than the budget, all pairs are counted, so the result never depends on the guess.
    """
    if kind not in SCHEDULERS:
        raise ValueError(f"unknown scheduler: {kind}")
    if budget < 0:
        raise ValueError(f"negative budget: {budget}")
    weigh = _weigher(packed, weight, scope, True)

    def keyed(l: np.ndarray, r: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, ...]:  # noqa: E741
        w = _nine(weigh(l, r, h))
        l, r, w = l[w > 0], r[w > 0], w[w > 0]  # noqa: E741
        return l, r, w, *_order_keys(kind, l, r, w)

    def count(l: np.ndarray, r: np.ndarray, h: np.ndarray) -> list[np.ndarray]:  # noqa: E741
        step, n = np.unique(_steps_of(kind, keyed(l, r, h)[3:]), return_counts=True)
        return [step, n.astype(np.int64)]

    def reached(tried: bool) -> tuple[int, bool]:
        """(the step that the budget reaches, or about, and whether the step is sure)"""
        made = summed(packed, window, True, "step long, n long", count, True, tried)
        share = made.share
        counts = made.groupBy("step").agg(F.sum("n").alias("n")).orderBy("step").toArrow()
        release(packed.sparkSession)
        most = budget if share == 1 else budget * share * MARGIN + 4 * (budget * share) ** 0.5 + 10
        found = counts.column("step").to_numpy()[np.cumsum(counts.column("n").to_numpy()) >= most]
        return int(found[0]) if len(found) else np.iinfo(np.int64).max, share == 1 or not len(found)

    def given(last: int) -> DataFrame:
        def give(l: np.ndarray, r: np.ndarray, h: np.ndarray) -> list[np.ndarray]:  # noqa: E741
            columns = keyed(l, r, h)
            use = _steps_of(kind, columns[3:]) <= last
            return [c[use] for c in columns]

        near = settle(summed(packed, window, True, "l long, r long, w double, o0 long, o1 double, o2 long, o3 long", give, True), "scheduled")
        release(packed.sparkSession)
        return near

    last, sure = reached(True)
    near = given(last)
    if not sure and near.count() < budget:
        drop(near)
        near = given(reached(False)[0])
    return positioned(near, ["o0", "o1", "o2", "o3", "l", "r"], limit=budget).select("pos", "l", "r", "w")
