"""Bit filters as packed bitmaps that every task holds: Bloom and tree filters are asked without a shuffle.

A filter of bits * n places is small beside its table (at 20 bits a key, 2.5 bytes a key), so its bitmap is sent to the tasks
once, and they look up all nodes of a question there, a batch at a time. A bitmap above MOST_BYTES is not sent: the callers
then keep to the joins of `filters`, which have the same answers. Questions are (q, a, b) as in `order.questions`, with any q;
the functions here return the q of those that are maybe, each once for every row asked.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import BooleanType, LongType, StructField, StructType

from rangesieve.functions.hashing import affine_of, affine_values, line_values, next_values
from rangesieve.functions.ship import ship
from rangesieve.operators.order import rank

#: Bytes of a bitmap, or of a list of prefixes, that are sent to the tasks at most.
MOST_BYTES = 2**25
#: Bytes of a piece of a bitmap on its way, and nodes that a task looks at together.
PIECE, TOGETHER = 2**17, 2**16


def draws(x: np.ndarray, modulus: int, stream: int) -> np.ndarray:
    """`hashing.draw` of an array."""
    return affine_values(x, *affine_of(stream), modulus)


def spread(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(i, v): every v from x[i] to y[i]; none where x > y."""
    count = np.maximum(y - x + 1, 0)
    i = np.repeat(np.arange(len(x)), count)
    return i, x[i] + np.arange(len(i)) - np.repeat(np.cumsum(count) - count, count)


def portions(weight: np.ndarray) -> Iterator[slice]:
    """Slices of consecutive rows that weigh TOGETHER at most, or hold one row."""
    ends, start = np.cumsum(weight), 0
    while start < len(weight):
        stop = max(start + 1, int(np.searchsorted(ends, (ends[start - 1] if start else 0) + TOGETHER, "right")))
        yield slice(start, stop)
        start = stop


def has(bitmap: np.ndarray, place: np.ndarray) -> np.ndarray:
    return (bitmap[place >> 3] >> (place & 7).astype(np.uint8)) & 1 != 0


def bitmap_of(keys: DataFrame, size: int, places: Callable[[np.ndarray], Iterator[np.ndarray]]) -> np.ndarray:
    """The bitmap of `size` places, on the driver. places: arrays of places of an array of keys. A task sets bits in a map of
    its own; pieces of the maps are put together by their number."""
    ship(keys.sparkSession)

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine, some = np.zeros(-(-size // 8) * 8, bool), False
        for batch in batches:
            k = batch.column(0).drop_null().to_numpy(zero_copy_only=False)
            some = some or len(k) > 0
            for place in places(k):
                mine[place] = True
        if some:
            packed = np.packbits(mine, bitorder="little")
            for i in range(0, len(packed), PIECE):
                piece = packed[i : i + PIECE]
                if piece.any():
                    yield pa.RecordBatch.from_pydict({"piece": pa.array([i // PIECE], pa.int32()), "bits": pa.array([piece.tobytes()], pa.binary())})

    def joined(pieces: pa.Table) -> pa.Table:
        whole = np.bitwise_or.reduce([np.frombuffer(bits.as_py(), np.uint8) for bits in pieces.column("bits")])
        return pa.table({"piece": pieces.column("piece").slice(0, 1), "bits": pa.array([whole.tobytes()], pa.binary())})

    made = keys.select("k").mapInArrow(own, "piece int, bits binary").groupBy("piece").applyInArrow(joined, "piece int, bits binary")
    out = np.zeros(-(-size // 8), np.uint8)
    for row in made.toLocalIterator():
        piece = np.frombuffer(bytes(row["bits"]), np.uint8)
        out[row["piece"] * PIECE : row["piece"] * PIECE + len(piece)] = piece
    return out


def maybe(asked: DataFrame, held, hit: Callable[..., np.ndarray]) -> DataFrame:
    """(q, hit): the questions for which hit(what was sent, a, b) is true."""
    spark = asked.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("a", "b"))
            found = pa.array(hit(sent.value, a, b), pa.bool_())
            rows = pa.RecordBatch.from_arrays([batch.column("q"), found], ["q", "hit"])
            yield rows.filter(found)

    made = StructType([asked.schema["q"], StructField("hit", BooleanType())])
    return asked.select("q", "a", "b").mapInArrow(run, made)


# --- Bloom filter of the nodes of all levels ----------------------------------------------------------------------------


def _level_value(node: np.ndarray, level: int) -> np.ndarray:
    return ((node & (2**58 - 1)) << 4) | level


def level_bitmap(keys: DataFrame, hashes: list[int], bits: int) -> np.ndarray:
    """The places of `filters.level_bits`."""

    return bitmap_of(keys, bits, lambda k: (place(k) for place in level_places(hashes, bits)))


def level_places(hashes: list[int], bits: int) -> list[Callable[[np.ndarray], np.ndarray]]:
    return [lambda k, level=level, j=j: draws(_level_value(k >> level, level), bits, 132 + j) for level, count in enumerate(hashes) for j in range(count)]


def level_hits(asked: DataFrame, bitmap: np.ndarray, hashes: list[int], bits: int) -> DataFrame:
    """Questions with a living leaf: the walk of `filters.level_descent`."""
    return maybe(asked, bitmap, level_hit(hashes, bits))


def level_hit(hashes: list[int], bits: int) -> Callable[..., np.ndarray]:
    top = len(hashes) - 1

    def hit(bitmap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.zeros(len(a), bool)
        for part in portions(np.maximum((b - a) >> top, 0) + 2 * top + 2):
            out[part] = walked(bitmap, a[part], b[part])
        return out

    def walked(bitmap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        i, node = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for level in range(top, -1, -1):
            x, y = (a + (1 << level) - 1) >> level, ((b + 1) >> level) - 1
            i, node = np.repeat(i, 2), np.repeat(node * 2, 2) + np.tile(np.array([0, 1]), len(node))
            if level == top:
                more = [spread(x, y)]
            else:
                left, right = np.flatnonzero((x <= y) & ((x & 1 == 1) | (x == y))), np.flatnonzero((x < y) & (y & 1 == 0))
                more = [(left, x[left]), (right, y[right])]
            i, node = np.concatenate([i, *[m[0] for m in more]]), np.concatenate([node, *[m[1] for m in more]])
            for j in range(hashes[level]):
                lives = has(bitmap, draws(_level_value(node, level), bits, 132 + j))
                i, node = i[lives], node[lives]
        out = np.zeros(len(a), bool)
        out[i] = True
        return out

    return hit


# --- small trees in hashed words ------------------------------------------------------------------------------------------


def _heap(node: np.ndarray, level: int, height: int) -> np.ndarray:
    return (1 << (height - level)) + (node & ((1 << (height - level)) - 1))


def tree_bitmap(keys: DataFrame, shift: int, height: int, words: int, hashes: int) -> np.ndarray:
    """The places of `filters.tree_bits`, those of each function behind those of the one before."""
    return bitmap_of(keys, hashes * words << (height + 1), lambda k: (p for place in tree_places(shift, height, words, hashes) for p in place(k)))


def tree_places(shift: int, height: int, words: int, hashes: int) -> list[Callable[[np.ndarray], np.ndarray]]:
    """A function of a word: the places of all levels in it, a row a level."""
    size = words << (height + 1)

    def places(k: np.ndarray, j: int) -> np.ndarray:
        word = j * size + (draws(k >> (shift + height), words, 300 + j) << (height + 1))
        return np.stack([word + _heap(k >> (shift + level), level, height) for level in range(height + 1)])

    return [lambda k, j=j: places(k, j) for j in range(hashes)]


def tree_hits(asked: DataFrame, bitmap: np.ndarray, shift: int, height: int, words: int, hashes: int) -> DataFrame:
    """Questions with a node of their cover set in all its words: `filters.ltb_probe`. The nodes are those of a dyadic cover
    whose top level holds all nodes inside."""
    return maybe(asked, bitmap, tree_hit(shift, height, words, hashes))


def tree_hit(shift: int, height: int, words: int, hashes: int) -> Callable[..., np.ndarray]:
    size = words << (height + 1)

    def hit(bitmap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        a, b = a >> shift, b >> shift
        out = np.zeros(len(a), bool)
        for part in portions(np.maximum((b - a) >> height, 0) + 2 * height + 2):
            out[part] = covered(bitmap, a[part], b[part])
        return out

    def covered(bitmap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.zeros(len(a), bool)
        for level in range(height + 1):
            x, y = (a + (1 << level) - 1) >> level, ((b + 1) >> level) - 1
            if level == height:
                sides = [spread(x, y)]
            else:
                left, right = np.flatnonzero((x <= y) & ((x & 1 == 1) | (x == y))), np.flatnonzero((x < y) & (y & 1 == 0))
                sides = [(left, x[left]), (right, y[right])]
            for i, node in sides:
                for j in range(hashes):
                    word = draws(node >> (height - level), words, 300 + j) << (height + 1)
                    lives = has(bitmap, j * size + word + _heap(node, level, height))
                    i, node = i[lives], node[lives]
                out[i] = True
        return out

    return hit


# --- exact prefixes and a Bloom filter of longer ones -----------------------------------------------------------------------


def prefix_bitmap(keys: DataFrame, shift: int, bits: int, hashes: int) -> np.ndarray:
    """The places of `filters.bloom_bits` with the stream of the prefix filter."""
    return bitmap_of(keys, bits, lambda k: (place(k) for place in prefix_places(shift, bits, hashes)))


def prefix_places(shift: int, bits: int, hashes: int) -> list[Callable[[np.ndarray], np.ndarray]]:
    return [lambda k, j=j: draws(k >> shift, bits, 148 + j) for j in range(hashes)]


class Ascending:
    """Ascending integers to be searched, in four bytes each where they lie close enough together."""

    def __init__(self, values: np.ndarray):
        # In four bytes the least is 1, and none is the greatest number there is: ends outside stay outside.
        self.base = int(values[0]) - 1 if len(values) and int(values[-1]) - int(values[0]) < 2**32 - 2 else None
        self.held = values if self.base is None else (values - self.base).astype(np.uint32)

    def search(self, x: np.ndarray, side: str) -> np.ndarray:
        return np.searchsorted(self.held, x if self.base is None else (np.clip(x, self.base, self.base + 2**32 - 1) - self.base).astype(np.uint32), side)

    def at(self, i: np.ndarray) -> np.ndarray:
        return self.held[i].astype(np.int64) + (self.base or 0)

    def all(self) -> np.ndarray:
        return self.at(np.arange(len(self.held)))


def prefix_bytes(count: int, shift: int, width: int) -> int:
    """Bytes that `prefixes` takes at most, of keys with so many digits."""
    return count * (4 if width - shift < 32 else 8)


def prefixes(keys: DataFrame, shift: int) -> Ascending:
    """The distinct prefixes above shift, on the driver."""
    found = keys.where("k is not null").selectExpr(f"shiftright(k, {shift}) AS t").distinct().toArrow().column("t").to_numpy()
    return Ascending(np.sort(found.astype(np.int64)))


def prefix_hits(asked: DataFrame, trie: Ascending, bloom: np.ndarray, shift1: int, shift2: int, bits: int, hashes: int, most: int) -> DataFrame:
    """Questions that meet a prefix, or are wider than `most` prefixes: `filters.tpb_probe`."""
    return maybe(asked, (trie, bloom), prefix_hit(shift1, shift2, bits, hashes, most))


def prefix_hit(shift1: int, shift2: int, bits: int, hashes: int, most: int) -> Callable[..., np.ndarray]:
    step, first_hash = shift1 - shift2, affine_of(148)
    steps = line_values(np.arange(most), first_hash[0], 0)

    def hit(sent: tuple, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        x, y = a >> shift2, b >> shift2
        out = y - x >= most
        for part in portions(np.where(out, 0, y - x + 1)):
            out[part] |= met(*sent, np.where(out[part], 1, x[part]), np.where(out[part], 0, y[part]))
        return out

    def met(trie: Ascending, bloom: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        # The trie first: a part of the range under a node without keys asks nothing more.
        first = trie.search(x >> step, "left")
        last = trie.search(y >> step, "right") - 1
        i, at = spread(first, np.where(x <= y, last, first - 1))
        node = trie.at(at)
        low = np.maximum(x[i], node << step)
        under, v = spread(low, np.minimum(y[i], ((node + 1) << step) - 1))
        # Most points end at the first hash, which is carried on from the start of their run.
        lives = has(bloom, next_values(line_values(low, *first_hash), under, v - low[under], steps, bits))
        i, v = i[under[lives]], v[lives]
        for j in range(1, hashes):
            lives = has(bloom, draws(v, bits, 148 + j))
            i, v = i[lives], v[lives]
        out = np.zeros(len(x), bool)
        out[i] = True
        return out

    return hit


# --- the learned map ----------------------------------------------------------------------------------------------------


def knots(keys: DataFrame, every: int, n: int) -> np.ndarray:
    """Every `every`-th key, ascending, on the driver: `filters.lbf_knots`."""
    found = rank(keys, "k", n=n).where(f"(i - 1) % {every} = 0").select("k").toArrow().column("k").to_numpy()
    return np.sort(found.astype(np.int64))


def learned(marks: np.ndarray, x: np.ndarray, scale: int) -> np.ndarray:
    """The map of `filters.lbf_map`: scale places a knot, a power of two; below all knots -1."""
    if not len(marks):
        return np.full(len(x), -1, np.int64)
    i = np.searchsorted(marks, x, "right") - 1
    at = np.maximum(i, 0)
    wide = np.append(np.diff(marks), 2**40)[at]
    t = x - marks[at]
    digits = scale.bit_length() - 1
    if not len(t) or int(t.max()) < 2 ** (62 - digits):
        step = (t << digits) // wide
    else:  # the product has more than 64 bits: a long division
        step = t // wide
        rest = t - step * wide
        for _ in range(digits):
            rest = rest * 2
            more = rest >= wide
            step, rest = step * 2 + more, np.where(more, rest - wide, rest)
    return np.where(i < 0, -1, i * scale + step)


def _mapped(df: DataFrame, sent_marks: np.ndarray, scale: int, ends: dict[str, str], keep: list[str]) -> DataFrame:
    """Columns `keep` and, for (new, old) of ends, the map of the old one."""
    spark = df.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(sent_marks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [pa.array(learned(sent.value, batch.column(old).to_numpy(zero_copy_only=False), scale)) for old in ends.values()]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], *made], [*keep, *ends])

    return df.select(*keep, *ends.values()).mapInArrow(run, StructType([*[df.schema[c] for c in keep], *[StructField(c, LongType()) for c in ends]]))


def learned_codes(keys: DataFrame, marks: np.ndarray, scale: int) -> DataFrame:
    return _mapped(keys.where("k is not null"), marks, scale, {"z": "k"}, [])


def learned_pieces(asked: DataFrame, marks: np.ndarray, scale: int) -> DataFrame:
    return _mapped(asked, marks, scale, {"lo": "a", "hi": "b"}, ["q"])
