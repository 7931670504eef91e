"""Many filters of one key set asked together: each task holds the sorted keys and the bitmaps, makes the codes of every
filter for itself and counts the questions that are maybe. So a batch is read once, nothing is shuffled, and a filter more
costs no job. For key sets and bitmaps that may be sent to the tasks (`bitmaps.MOST_BYTES` each); the answers are those of `methods.hits`."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructField, StructType

from rangesieve.functions.hashing import HashParams, h_values
from rangesieve.functions.ship import ship
from rangesieve.operators.bitmaps import learned
from rangesieve.operators.dealt import _distinct, digits, parting

#: Bytes of sorted keys that are sent to the tasks at most, by experiments that gather them.
MOST_KEYS = 2**26
#: Keys, or questions, that a step takes at once, and questions that a task asks of one filter.
NEAR, TOGETHER = 2**16, 2**20
#: A filter: from sorted keys and what was sent for it (a bitmap, or None) to a test of ends (a, b).
Filter = Callable[[np.ndarray, object], Callable[[np.ndarray, np.ndarray], np.ndarray]]


def _any_in(codes: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    if not len(codes):
        return np.zeros(len(lo), bool)
    order = np.argsort(lo)  # codes are met in order, which is faster than at random
    at = np.empty(len(lo), np.int64)
    at[order] = np.searchsorted(codes, lo[order], "left")
    return (at < len(codes)) & (codes[np.minimum(at, len(codes) - 1)] <= hi)


def locality(p: HashParams) -> Filter:
    def make(keys, sent):
        codes = _distinct(np.concatenate([h_values(keys[i : i + NEAR], p) for i in range(0, max(len(keys), 1), NEAR)]))

        def half(a, b):
            x, y = h_values(a, p), h_values(b, p)
            if not len(codes):
                return np.zeros(len(a), bool)
            return np.where(x <= y, _any_in(codes, x, y), (codes[0] <= y) | (codes[-1] >= x))

        def test(a, b):
            cross = b // p.r - a // p.r
            out, inside, two = np.full(len(a), len(codes) > 0), cross == 0, cross == 1
            out[inside] = half(a[inside], b[inside])
            if two.any():
                x, y = a[two], b[two]
                edge = y - y % p.r
                out[two] = half(x, edge - 1) | half(edge, y)
            return out

        return test

    return make


def bucket(wide: int) -> Filter:
    """Codes are those of `filters.cbf_codes`, whose division drops the fraction."""
    div = lambda x: np.where(x < 0, -(-x // wide), x // wide)

    def make(keys, sent):
        codes = _distinct(div(keys))
        return lambda a, b: _any_in(codes, div(a), div(b))

    return make


def trie(suffix_bits: int) -> Filter:
    def make(keys, sent):
        if not len(keys):
            return lambda a, b: np.zeros(len(a), bool)
        s = np.maximum(np.minimum(np.minimum(*parting(keys, (0, None, None))) - 1, 62) - suffix_bits, 0)
        z = keys >> s << s
        ends = z + (np.int64(1) << s) - 1

        def test(a, b):
            i = np.searchsorted(z, b, "right") - 1
            return (i >= 0) & (ends[i] >= a)

        return test

    return make


def learned_map(every: int, scale: int) -> Filter:
    def make(keys, sent):
        marks = keys[::every]
        codes = _distinct(learned(marks, keys, scale))
        return lambda a, b: _any_in(codes, learned(marks, a, scale), learned(marks, b, scale))

    return make


def sent_bitmap(hit: Callable[..., np.ndarray]) -> Filter:
    return lambda keys, sent: lambda a, b: hit(sent, a, b)


def parted(keys: np.ndarray) -> dict[tuple[int, int], int]:
    """`filters.parted` of sorted keys."""
    if not len(keys):
        return {}
    before, behind = parting(keys, (0, None, None))
    found, c = np.unique(before * 65 + behind, return_counts=True)
    return {(int(x) // 65, int(x) % 65): int(n) for x, n in zip(found, c)}


def _ends(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ends a and b, and which rows ask something; the ends of others are 0."""
    a, b = (batch.column(c).cast(pa.int64()) for c in ("a", "b"))
    there = a.is_valid().to_numpy(zero_copy_only=False) & b.is_valid().to_numpy(zero_copy_only=False)
    a, b = (x.fill_null(0).to_numpy(zero_copy_only=False) for x in (a, b))
    there &= a <= b
    return np.where(there, a, 0), np.where(there, b, 0), there


def keep_empty(keys: Broadcast, ranges: DataFrame) -> DataFrame:
    """`order.keep_empty` by sorted keys that every task holds."""
    ship(ranges.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, there = _ends(batch)
            yield batch.filter(pa.array(there & ~_any_in(keys.value, a, b)))

    return ranges.mapInArrow(run, ranges.schema)


def alike(keys: Broadcast, sample: DataFrame) -> list[tuple[int, int, int]]:
    """`tuning.alike` by sorted keys that every task holds."""
    ship(sample.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k = keys.value
        for batch in batches:
            a, b, there = _ends(batch)
            a, b = a[there], b[there]
            if len(k):
                i, j = np.searchsorted(k, a, "right") - 1, np.searchsorted(k, b, "left")
                low = np.where(i < 0, 63, digits(a ^ k[np.maximum(i, 0)]))
                high = np.where(j == len(k), 63, digits(b ^ k[np.minimum(j, len(k) - 1)]))
            else:
                low = high = np.full(len(a), 63, np.int64)
            found, c = np.unique(np.minimum(low, high) * 65 + digits(b - a), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found // 65), pa.array(found % 65), pa.array(c.astype(np.int64))], ["level", "width", "c"])

    made = sample.select("a", "b").mapInArrow(run, "level long, width long, c long")
    return sorted(tuple(r) for r in made.groupBy("level", "width").agg(F.sum("c")).collect())


#: Places of a bitmap, and functions from keys to places (several, as rows of a table).
Places = tuple[int, list[Callable[[np.ndarray], np.ndarray]]]


def bitmap(keys: np.ndarray, made: Places) -> np.ndarray:
    size, places = made
    mine = np.zeros(-(-size // 8) * 8, bool)
    for start in range(0, len(keys), NEAR):
        for place in places:
            mine[place(keys[start : start + NEAR]).ravel()] = True
    return np.packbits(mine, bitorder="little")


def mapped(make: Filter, made: Places | None) -> Filter:
    """A filter whose bitmap is made where it is asked."""
    return make if made is None else lambda keys, sent: make(keys, bitmap(keys, made))


def bitmaps(spark: SparkSession, keys: Broadcast, made: list[Places]) -> list[np.ndarray]:
    """`bitmaps.bitmap_of` sorted keys that every task holds, a task a bitmap, on the driver."""
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                bits = bitmap(keys.value, made[i])
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int64()), pa.array([bits.tobytes()], pa.binary())], ["i", "bits"])

    if not made:
        return []
    rows = spark.range(0, len(made), 1, len(made)).mapInArrow(run, "i long, bits binary").toArrow()
    found = dict(zip(rows.column("i").to_pylist(), rows.column("bits")))
    return [np.frombuffer(found[i].as_buffer(), np.uint8) for i in range(len(made))]


def hits(keys: Broadcast, make: Filter, own, asked: DataFrame) -> DataFrame:
    """(q, hit): the questions (q, a, b) that are maybe."""
    spark = asked.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(own)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = make(keys.value, sent.value)
        for batch in batches:
            a, b, there = _ends(batch)
            found = pa.array(there & test(a, b))
            yield pa.RecordBatch.from_arrays([batch.column("q"), found], ["q", "hit"]).filter(found)

    return asked.select("q", "a", "b").mapInArrow(run, StructType([asked.schema["q"], StructField("hit", BooleanType())]))


def answers(keys: Broadcast, make: Filter, own, ranges: DataFrame) -> DataFrame:
    """Ranges with `maybe`, as `order.answered` gives it: null where an end is null or the ends are reversed."""
    spark = ranges.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(own)
    names = [c for c in ranges.columns if c != "maybe"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = make(keys.value, sent.value)
        for batch in batches:
            a, b, there = _ends(batch)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(test(a, b), mask=~there)], [*names, "maybe"])

    return ranges.select(*names).mapInArrow(run, StructType([*[ranges.schema[c] for c in names], StructField("maybe", BooleanType())]))


def positives(keys: np.ndarray | Broadcast, filters: dict[tuple, tuple[Filter, object]], asked: DataFrame, by: tuple[str, ...] = ("len",), total: int = 0, each=map) -> dict[tuple, int]:
    """(*filter, *by): how many questions (q, a, b) with those integers in q are maybe. filters: with what is sent for each.

    Keys that are sent here: one pass over the questions, dealt anew, for all filters. Keys that are sent already: a job a
    filter, run by `each`, in which a task asks TOGETHER of the `total` kept questions, so that few tasks make the filter."""
    spark = asked.sparkSession
    ship(spark)
    made = asked.select(*[F.col(f"q.{c}").cast("long").alias(c) for c in by], "a", "b")
    if isinstance(keys, Broadcast):
        few = made.coalesce(max(1, -(-total // TOGETHER)))
        return {k: c for found in each(lambda x: _counted(keys, dict([x]), few, by), filters.items()) for k, c in found.items()}
    sent = spark.sparkContext.broadcast(keys)
    out = _counted(sent, filters, made.repartition(2 * spark.sparkContext.defaultParallelism), by)
    sent.unpersist()
    return out


def _counted(keys: Broadcast, filters: dict[tuple, tuple[Filter, object]], made: DataFrame, by: tuple[str, ...]) -> dict[tuple, int]:
    names, makers = list(filters), [x for x, _ in filters.values()]
    sent = made.sparkSession.sparkContext.broadcast([x for _, x in filters.values()])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [([b.column(c).to_numpy() for c in by], b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches]
        if not held:
            return
        a, b = (np.concatenate([x[i] for x in held]) for i in (1, 2))
        number, cells = np.zeros(len(a), np.int64), [()]
        for i in range(len(by)):  # cells by their numbers, a column after the other
            values, at = np.unique(np.concatenate([x[0][i] for x in held]), return_inverse=True)
            number, cells = number * len(values) + at.ravel(), [(*x, int(v)) for x in cells for v in values]
        del held
        rows = []
        for i, (make, own) in enumerate(zip(makers, sent.value)):  # one filter at a time, so that only its codes are held
            test = make(keys.value, own)
            c = sum(np.bincount(number[j : j + NEAR][test(a[j : j + NEAR], b[j : j + NEAR])], minlength=len(cells)) for j in range(0, len(a), NEAR))
            rows += [(i, *cells[x], int(c[x])) for x in np.flatnonzero(c)]
        yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], pa.int64()) for j in range(len(by) + 2)], ["i", *by, "c"])

    found = made.mapInArrow(run, ", ".join(f"{c} long" for c in ("i", *by, "c")))
    out = {(*names[r[0]], *r[1:-1]): r[-1] for r in found.groupBy("i", *by).agg(F.sum("c")).collect()}
    sent.unpersist()
    return out
