"""Filters built from packed keys: sets of codes and places go through Spark by the array, not by the row.

Keys come as arrays (`binary` cells of 64-bit integers). A task maps an array to codes, sorts them and cuts them at the bounds
of shards; each piece is sent to its shard, less the shard's start, in four bytes a code where shards are narrow enough. A
shard is then sorted once more and freed of repeats, or becomes a stretch of a bitmap. What a task holds is an array and a
shard, so memory does not follow the number of keys. Codes lie from the first bound on; equal ones count once.
"""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangesieve.functions.hashing import mixed_values
from rangesieve.functions.ship import ship
from rangesieve.operators.bitmaps import learned

#: Keys of a cell, keys that a task deals together, codes of a shard in the mean, places of a stretch of a bitmap, most shards.
ARRAY, TOGETHER, SHARD, STRETCH, MOST_SHARDS = 2**15, 2**19, 2**20, 2**22, 2**12
#: Bytes of a bitmap that every task may hold.
HELD = 2**27
#: Keys that a function takes at once, so that its steps stay near the processor.
NEAR = 2**15
#: Functions of arrays of keys; each gives a code, or place, a key (or several, as rows of a table).
Codes = list[Callable[[np.ndarray], np.ndarray]]


def drawn(spark: SparkSession, n: int, bits: int, stream: int, tasks: int) -> DataFrame:
    """Arrays k of `hashing.mixed` of the numbers below n, below 2^bits."""
    ship(spark)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                yield _cells(mixed_values(np.arange(i * ARRAY, min(n, (i + 1) * ARRAY)), 2**bits, stream))

    return spark.range(0, -(-n // ARRAY), 1, max(1, min(tasks, -(-n // ARRAY)))).mapInArrow(make, "k binary")


def scattered(keys: DataFrame, bits: int, n: int, tasks: int) -> DataFrame:
    """Arrays k of the distinct ones among about n keys below 2^bits, in no order: they are sorted by a bijection."""
    mask, factor = 2**bits - 1, 0x9E3779B97F4A7C15 % 2**bits | 1
    back, starts = pow(factor, -1, 2**bits), even(0, mask, n, ARRAY)
    times = lambda k, by: ((k.astype(np.uint64) * np.uint64(by)) & np.uint64(mask)).astype(np.int64)
    return dealt(keys, [lambda k: times(k, factor)], starts, mask, tasks, lambda shard, z: _cells(times(z.astype(np.int64) + starts[shard], back)), "k binary")


def arrays(keys: DataFrame) -> DataFrame:
    """Arrays k of a frame of keys; null keys never enter."""
    ship(keys.sparkSession)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(batch.column(0).drop_null().to_numpy(zero_copy_only=False).astype(np.int64))
            size += len(held[-1])
            if size >= ARRAY:
                yield _cells(np.concatenate(held))
                held, size = [], 0
        if size:
            yield _cells(np.concatenate(held))

    return keys.select("k").mapInArrow(make, "k binary")


def _cells(k: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"k": pa.array([np.ascontiguousarray(k, np.int64).tobytes()], pa.binary())})


def each(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
    """The keys of some cells together."""
    held, size = [], 0
    for batch in batches:
        for cell in batch.column(0):
            held.append(np.frombuffer(cell.as_buffer(), np.int64).copy())
            size += len(held[-1])
            if size >= TOGETHER:
                yield np.concatenate(held)
                held, size = [], 0
    if size:
        yield np.concatenate(held)


def even(first: int, last: int, n: int, wide: int = SHARD) -> np.ndarray:
    """Starts of shards of equal width for about n codes from first to last that are spread evenly; enough of them for
    codes of four bytes, if that takes no more than MOST_SHARDS."""
    size = max(1, last - first + 1)
    narrow = -(-size // 2**32)
    count = min(max(-(-n // wide), narrow if narrow <= MOST_SHARDS else 1), MOST_SHARDS, size)
    return np.array([first + i * size // count for i in range(count)], np.int64)


def stretches(size: int) -> np.ndarray:
    """Starts of the stretches of a bitmap, at whole bytes."""
    wide = max(STRETCH, -(-size // MOST_SHARDS // 8) * 8)
    return np.arange(0, max(size, 1), wide, dtype=np.int64)


def _distinct(z: np.ndarray) -> np.ndarray:
    z.sort()
    return z[np.append(True, z[1:] != z[:-1])] if len(z) else z


def dealt(keys: DataFrame, codes: Codes, starts: np.ndarray, last: int, tasks: int, done, schema: str, alike: bool = True) -> DataFrame:
    """The rows of done(shard, offsets) for every shard with codes up to `last`. offsets: distinct and ascending where `alike`
    (codes that repeat are dropped in the arrays first), else as they come. tasks: those that deal and those that build."""
    ship(keys.sparkSession)
    small = max(np.diff(starts, append=last + 1).tolist()) <= 2**32
    dtype, width = (np.uint32, 4) if small else (np.int64, 8)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for k in each(batches):
            for code in codes:
                z = np.concatenate([code(k[i : i + NEAR]).ravel() for i in range(0, len(k), NEAR)])
                z = _distinct(z) if alike else _sorted(z)
                ends = np.append(0, np.append(np.searchsorted(z, starts[1:]), len(z)))
                count = np.diff(ends)
                some = np.flatnonzero(count)
                offsets = np.ascontiguousarray(z - np.repeat(starts, count), np.int64).astype(dtype)
                at = np.append(0, np.cumsum(count[some] * width)).astype(np.int32)
                bits = pa.Array.from_buffers(pa.binary(), len(some), [None, pa.py_buffer(at), pa.py_buffer(offsets)])
                yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), bits], ["shard", "bits"])

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, parts = -1, []
        for batch in batches:
            for i, cell in zip(batch.column(0).to_pylist(), batch.column(1)):
                if i != shard and parts:
                    yield done(shard, _whole(parts))
                    parts = []
                shard = i
                parts.append(np.frombuffer(cell.as_buffer(), dtype).copy())
        if parts:
            yield done(shard, _whole(parts))

    def _whole(parts: list[np.ndarray]) -> np.ndarray:
        z = np.concatenate(parts)
        return _distinct(z) if alike else z

    spread = keys.coalesce(tasks).mapInArrow(deal, "shard int, bits binary")
    # A partition is a shard; a task takes its partitions one after another.
    return spread.repartitionById(len(starts), F.col("shard")).coalesce(tasks).mapInArrow(build, schema)


def _sorted(z: np.ndarray) -> np.ndarray:
    z.sort()
    return z


def tidy(spark: SparkSession) -> None:
    """Let Spark drop the files of shuffles that nothing refers to any more, so that those of several builds don't add up."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


SET = "shard int, n long, bits binary"


def _row(shard: int, n: int, bits: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([n], pa.int64()), pa.array([bits.tobytes()], pa.binary())], ["shard", "n", "bits"])


def code_set(keys: DataFrame, codes: Codes, starts: np.ndarray, last: int, tasks: int) -> DataFrame:
    """(shard, n, bits): a shard's n distinct codes, ascending, less its start: in four or, where shards are wider, eight bytes."""
    return dealt(keys, codes, starts, last, tasks, lambda shard, z: _row(shard, len(z), z), SET)


def bitmap(keys: DataFrame, places: Codes, size: int, tasks: int) -> DataFrame:
    """(shard, n, bits): a stretch of the bitmap of all places below size, and how many are set; stretches without any are
    left out. A map of at most HELD bytes is made whole by every task and its stretches are put together; places of a larger
    one are dealt to their stretches."""
    starts = stretches(size)
    wide = np.diff(starts, append=size)

    def done(shard: int, offsets: np.ndarray) -> pa.RecordBatch:
        marks = np.zeros(int(wide[shard]), bool)
        marks[offsets] = True
        return _row(shard, int(marks.sum()), np.packbits(marks, bitorder="little"))

    if size > 8 * HELD:
        return dealt(keys, places, starts, size - 1, tasks, done, SET, False)

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine = np.zeros(-(-size // 8), np.uint8)
        for k in each(batches):
            for place in places:
                for i in range(0, len(k), NEAR):
                    z = place(k[i : i + NEAR]).ravel()
                    byte, bit = z >> 3, _ONE_BIT[z & 7]
                    while len(byte):  # of places in one byte the last is set; the others again, at most seven times
                        mine[byte] |= bit
                        left = mine[byte] & bit == 0
                        byte, bit = byte[left], bit[left]
        for shard, start in enumerate(starts):
            piece = mine[start // 8 : -(-(start + wide[shard]) // 8)]
            if piece.any():
                yield _row(shard, 0, piece)

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, whole = -1, None
        for batch in batches:
            for i, cell in zip(batch.column(0).to_pylist(), batch.column(2)):
                piece = np.frombuffer(cell.as_buffer(), np.uint8)
                if i == shard:
                    whole |= piece
                    continue
                if whole is not None:
                    yield _row(shard, int(np.bitwise_count(whole).sum()), whole)
                shard, whole = i, piece.copy()
        if whole is not None:
            yield _row(shard, int(np.bitwise_count(whole).sum()), whole)

    ship(keys.sparkSession)
    return keys.coalesce(tasks).mapInArrow(own, SET).repartitionById(len(starts), F.col("shard")).coalesce(tasks).mapInArrow(joined, SET)


_ONE_BIT = (1 << np.arange(8)).astype(np.uint8)


def unpacked(shards: DataFrame, starts: np.ndarray, last: int) -> np.ndarray:
    """All codes of a `code_set`, on the driver: for tests and small sets."""
    dtype = np.uint32 if max(np.diff(starts, append=last + 1).tolist()) <= 2**32 else np.int64
    found = sorted((r["shard"], bytes(r["bits"])) for r in shards.select("shard", "bits").collect())
    return np.concatenate([np.zeros(0, np.int64), *[np.frombuffer(b, dtype).astype(np.int64) + starts[i] for i, b in found]])


# --- keys in order ------------------------------------------------------------------------------------------------------


class Ordered:
    """Distinct keys in order: shards (shard, k), each an array, with what lies around a shard (a row each, on the driver).
    The frame is kept until `free`."""

    def __init__(self, keys: DataFrame, starts: np.ndarray, last: int, tasks: int):
        def done(shard: int, z: np.ndarray) -> pa.RecordBatch:
            k = z.astype(np.int64) + starts[shard]
            return pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([k.tobytes()], pa.binary()), pa.array([len(k)]), pa.array([int(k[0])]), pa.array([int(k[-1])])], ["shard", "k", "n", "least", "most"])

        self.starts = starts
        self.shards = dealt(keys, [lambda k: k], starts, last, tasks, done, "shard int, k binary, n long, least long, most long").cache()
        found = sorted(tuple(r) for r in self.shards.select("shard", "n", "least", "most").collect())
        self.n = sum(r[1] for r in found)
        before = np.cumsum([0, *[r[1] for r in found]])
        #: shard -> (keys before it, the last key before it, the first key behind it)
        self.around = {r[0]: (int(before[i]), found[i - 1][3] if i else None, found[i + 1][2] if i + 1 < len(found) else None) for i, r in enumerate(found)}

    def free(self) -> None:
        self.shards.unpersist()

    def map(self, run: Callable[[int, np.ndarray, tuple], pa.RecordBatch], schema: str) -> DataFrame:
        around = self.around

        def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i, cell in zip(batch.column(0).to_pylist(), batch.column(1)):
                    yield run(i, np.frombuffer(cell.as_buffer(), np.int64), around[i])

        return self.shards.select("shard", "k").mapInArrow(go, schema)


@contextmanager
def ordered(keys: DataFrame, starts: np.ndarray, last: int, tasks: int) -> Iterator[Ordered]:
    made = Ordered(keys, starts, last, tasks)
    try:
        yield made
    finally:
        made.free()


def digits(x: np.ndarray) -> np.ndarray:
    """Number of binary digits of each; 64 of a negative one."""
    high, low = x >> 32, x & (2**32 - 1)
    found = np.where(high > 0, 32 + np.frexp(high.astype(np.float64))[1], np.frexp(low.astype(np.float64))[1])
    return np.where(x < 0, 64, found).astype(np.int64)


def parting(k: np.ndarray, around: tuple) -> tuple[np.ndarray, np.ndarray]:
    """Bits in which each key of a shard parts from the key before and the key behind; 64 where there is none."""
    inner = digits(k[1:] ^ k[:-1])
    ends = [64 if x is None else int(digits(np.array([k[i] ^ x]))[0]) for i, x in ((0, around[1]), (-1, around[2]))]
    return np.append(ends[0], inner), np.append(inner, ends[1])


def parted(ordered: Ordered) -> dict[tuple[int, int], int]:
    """`filters.parted`."""

    def run(shard: int, k: np.ndarray, around: tuple) -> pa.RecordBatch:
        p, n = parting(k, around)
        found, c = np.unique(p * 65 + n, return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(found // 65), pa.array(found % 65), pa.array(c.astype(np.int64))], ["prev", "next", "c"])

    return {(r[0], r[1]): r[2] for r in ordered.map(run, "prev long, next long, c long").groupBy("prev", "next").agg(F.sum("c")).collect()}


def trie_leaves(ordered: Ordered, suffix_bits: int = 0) -> DataFrame:
    """(shard, n, bits): the starts of `filters.ttf_leaves`, then how many bits each leaf leaves open (a byte each)."""

    def run(shard: int, k: np.ndarray, around: tuple) -> pa.RecordBatch:
        s = np.maximum(np.minimum(np.minimum(*parting(k, around)) - 1, 62) - suffix_bits, 0)
        return _row(shard, len(k), np.concatenate([(k >> s << s).view(np.uint8), s.astype(np.uint8)]))

    return ordered.map(run, SET)


def learned_codes(ordered: Ordered, every: int, scale: int) -> DataFrame:
    """(shard, n, bits): distinct codes of `bitmaps.learned_codes`, ascending. A knot is every `every`-th key; a shard needs
    those inside it, the last before it and the first behind it."""

    def marks_of(k: np.ndarray, around: tuple) -> np.ndarray:
        return k[-around[0] % every :: every]

    def ends(shard: int, k: np.ndarray, around: tuple) -> pa.RecordBatch:
        marks = marks_of(k, around)
        marks = marks[[0, -1]] if len(marks) else marks
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(marks), shard, np.int32)), pa.array(marks)], ["shard", "k"])

    found = sorted((r[0], r[1]) for r in ordered.map(ends, "shard int, k long").collect())  # two rows a shard

    def run(shard: int, k: np.ndarray, around: tuple) -> pa.RecordBatch:
        before, behind = [x for i, x in found if i < shard][-1:], [x for i, x in found if i > shard][:1]
        marks = np.array([*before, *marks_of(k, around), *behind], np.int64)
        first = -(-around[0] // every) - len(before)  # number of the first of these knots
        z = _distinct(learned(marks, k, scale) + first * scale)
        if around[1] is not None and before and learned(marks, np.array([around[1]]), scale)[0] + first * scale == z[0]:
            z = z[1:]
        return _row(shard, len(z), z)

    return ordered.map(run, SET)


def nearest(ordered: Ordered, asked: DataFrame, ends: Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]) -> list[tuple[int, int, int]]:
    """`tuning.alike` of the empty ones among the ranges that `ends` draws from arrays of keys: (level, width, c)."""
    starts, around = ordered.starts, ordered.around
    filled = np.array(sorted(around), np.int64)
    spark = asked.sparkSession

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for k in each(batches):
            a, b = ends(k)
            # Below all filled shards a range is asked in the first one; in a shard without keys, in the one before.
            at = filled[np.maximum(np.searchsorted(starts[filled], a, "right") - 1, 0)]
            for shard in np.unique(at):
                mine = at == shard
                yield pa.RecordBatch.from_arrays([pa.array([int(shard)], pa.int32()), pa.array([np.concatenate([a[mine], b[mine]]).tobytes()], pa.binary())], ["shard", "asked"])

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        out = {"level": np.zeros(0, np.int64), "width": np.zeros(0, np.int64), "c": np.zeros(0, np.int64)}
        if right.num_rows and left.num_rows:
            k = np.frombuffer(left.column("k")[0].as_buffer(), np.int64)
            _, last, following = around[key[0].as_py()]
            both = [np.frombuffer(x.as_buffer(), np.int64).reshape(2, -1) for x in right.column("asked")]
            a, b = np.concatenate(both, axis=1)
            i, j = np.searchsorted(k, a, "right") - 1, np.searchsorted(k, b, "left")
            low = np.where(i >= 0, k[np.maximum(i, 0)], -1 if last is None else last)
            high = np.where(j < len(k), k[np.minimum(j, len(k) - 1)], -1 if following is None else following)
            no_low, no_high = (i < 0) & (last is None), (j >= len(k)) & (following is None)
            empty = (j <= i + 1) & (no_low | (low < a)) & (no_high | (high > b))
            level = np.minimum(np.where(no_low, 63, digits(a ^ low)), np.where(no_high, 63, digits(b ^ high)))
            found, c = np.unique((level * 65 + digits(b - a))[empty], return_counts=True)
            out = {"level": found // 65, "width": found % 65, "c": c.astype(np.int64)}
        return pa.table(out)

    ship(spark)
    questions = asked.mapInArrow(deal, "shard int, asked binary")
    made = ordered.shards.select("shard", "k").groupBy("shard").cogroup(questions.groupBy("shard")).applyInArrow(run, "level long, width long, c long")
    return sorted(tuple(r) for r in made.groupBy("level", "width").agg(F.sum("c")).collect())
