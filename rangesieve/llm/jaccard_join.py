"""Self-join of word n-gram sets by Jaccard similarity: a chosen-path join.

Texts with one and the same shingle set form a class; only classes are joined. A class is embedded into 128 tokens
(position, least hash at that position); two sets of similarity s share a token with probability s. A run samples
tokens with the probability that lets a pair at the threshold expect one shared token, and splits the classes on
them. Small buckets are searched by brute force on the embedding. Runs repeat until the target recall.

A pair that shares a common passage with many other texts still shares rarer tokens, so classes with tokens in large
buckets get more runs, by the share of their tokens that are rare. Only classes with few rare tokens split further, on
freshly sampled tokens, level by level. There, the classes whose mean similarity to a large bucket is high (its core,
as in a group of near copies) would stay together in every split; they are compared with the bucket at once, in chunks
around pivots, and leave the recursion. At the last level all that is left counts as core.

Found pairs only have to connect: each connected candidate group is then compared exactly, once, inside one task (or
block by block where it is large), on the whole shingle sets. No pair is ever emitted as a row; a task emits for each
class its number of links and one root.

Defined cases: a text of one to four words has one shingle, all its words; null texts, empty ones and texts without
any letter or digit have no shingle, are linked with nothing and are classes of their own; repeated rows are
separate documents of one class (and so linked with each other); null ids are allowed and stay null; extra columns
are ignored by the join and carried along by keep_one_of_each.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import NEAR, SHINGLE_WORDS, WORD, carry, give_back, materialise, own, restore, ship_package, shuffle_width
from rangesieve.llm.components import connected_components

POSITIONS = 128
RECALL = 0.9999
BUCKET = 512  # classes that are compared with each other in one bucket
SHORT = 48  # classes of a bucket up to which all pairs are compared at once
LEVELS = 4
CHUNK = 1024  # classes of a dense bucket searched in one task
BLOCK, BLOCK_SHINGLES = 512, 2_000_000  # classes of a group compared exactly in one task, in pairs of blocks, and their shingles
#: Estimates from 128 positions deviate by up to 0.04 (one sigma) near 0.8; the slack is about four of them.
BUCKET_LINK = NEAR - 0.15
PIVOT_LINK, PIVOT_TAKE, PIVOT_PAIR = 0.45, 0.92, 0.28
#: Mean similarity to the bucket from which a class belongs to its core. A class near one of the core has a mean of
#: CORE - (1 - NEAR) at least; HALO leaves room for the estimates. Chunks of under FEW classes are all halo.
CORE, HALO, FEW = 0.5, 0.2, 32
#: Share of a class's sampled tokens in small buckets: from RARE on a few more runs do, below HALF it splits further.
RARE, HALF = 0.75, 0.5
_NOWHERE = 0x5CA1AB1E
HOT = 8  # buckets a shuffle partition that are listed by name

_rng = np.random.default_rng(20240229)
_XOR = _rng.integers(0, 2**32, POSITIONS, dtype=np.uint32)
_MUL = _rng.integers(0, 2**31, POSITIONS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_POW = _rng.integers(0, 2**62, SHINGLE_WORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


class _WordHash(dict):
    def __missing__(self, word: str) -> int:
        if len(self) > 500_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


_words = _WordHash()


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles."""
    words = WORD.findall(text.lower()) if text else []
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, len(words))
    with np.errstate(over="ignore"):
        k = min(len(h), SHINGLE_WORDS)
        s = np.full(len(h) - k + 1, k, np.uint64)
        for j in range(k):
            s += h[j : len(h) - k + 1 + j] * _POW[j]
            s ^= s >> np.uint64(29)
    return np.unique(s)


def embed(sets: list[np.ndarray]) -> np.ndarray:
    """The 128 least hashes of each nonempty set."""
    sizes = np.array([len(s) for s in sets])
    at = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    every = np.concatenate(sets)
    h = ((every ^ (every >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)).astype(np.uint32)
    out = np.empty((len(sets), POSITIONS), np.uint32)
    v = np.empty_like(h)
    for k in range(POSITIONS):
        np.multiply(np.bitwise_xor(h, _XOR[k], out=v), _MUL[k], out=v)
        out[:, k] = np.minimum.reduceat(v, at)
    return out


def _sliced(batch: pa.RecordBatch, chars: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """Slices with a bounded amount of text, one row at least."""
    lengths = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index("text"))), 0).to_pylist()
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if i > start and total + n > chars:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if start < batch.num_rows:
        yield batch.slice(start)


SKETCHED = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("set_key", T.BinaryType()), T.StructField("n", T.IntegerType()), T.StructField("sig", T.BinaryType()), T.StructField("low", T.BinaryType())])


def _key(s: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(s.tobytes())


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in _sliced(whole):
            sets = [shingle_set(t) for t in batch.column(1).to_pylist()]
            some = [s for s in sets if len(s)]
            sigs = embed(some) if some else np.empty((0, POSITIONS), np.uint32)
            whole_sig, low_sig = iter(sigs), iter(sigs.astype(np.uint8))
            yield pa.record_batch([batch.column(0).cast(pa.int64()), pa.array([_key(s) if len(s) else None for s in sets], pa.binary()), pa.array([len(s) for s in sets], pa.int32()), pa.array([next(whole_sig).tobytes() if len(s) else None for s in sets], pa.binary()), pa.array([next(low_sig).tobytes() if len(s) else None for s in sets], pa.binary())], names=SKETCHED.fieldNames())
    _words.clear()
    give_back()


def miss_rate(runs: int, rare: float = 1.0, splits: int = 1) -> float:
    """Probability that a pair at the threshold shares no bucket that is searched after so many splits in any run, if
    that share of its equal positions leads to such buckets.

    The pair's equal positions are binomial and the same in all runs; each split samples each of them on its own."""
    equal = np.arange(POSITIONS + 1)
    weight = np.array([math.comb(POSITIONS, k) * NEAR**k * (1 - NEAR) ** (POSITIONS - k) for k in equal])
    lost = np.zeros(POSITIONS + 1)
    for _ in range(splits):
        lost = (1 - (1 - lost) / (NEAR * POSITIONS)) ** (equal * rare)
    return float(weight @ lost**runs)


def runs_needed(rare: float = 1.0, splits: int = 1, recall: float = RECALL) -> int:
    """Runs after which such a pair is missed with half of what the target allows; the other half is for other pairs."""
    runs = 1
    while miss_rate(runs, rare, splits) > (1 - recall) / 2:
        runs += 1
    return runs


def shared_rare(rare: float) -> float:
    """Least share of rare tokens among those that a pair at the threshold shares, if one of the two has that share."""
    return (rare - (1 - NEAR)) / NEAR


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _sampled(path: np.ndarray) -> np.ndarray:
    """For each path hash, which positions are sampled below it: each with probability 1 / (threshold * positions)."""
    h = _mixed(path[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(1, POSITIONS + 1, dtype=np.uint64))
    return h < np.uint64(int(2**64 / (NEAR * POSITIONS)))


PATHS = "bucket long, cls long"


def _split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Children of (bucket, cls, sig) rows."""
    for batch in batches:
        if not batch.num_rows:
            continue
        path = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
        cls = batch.column(1).to_numpy(zero_copy_only=False)
        sig = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint32).reshape(-1, POSITIONS)
        rows, k = np.nonzero(_sampled(path))
        child = _mixed(_mixed(path[rows]) ^ (k.astype(np.uint64) << np.uint64(32) | sig[rows, k].astype(np.uint64)))
        yield pa.record_batch([pa.array(child.view(np.int64)), pa.array(cls[rows])], names=["bucket", "cls"])


def _roots(runs: int, done: int = 0) -> np.ndarray:
    return _mixed(np.arange(done + 1, runs + 1, dtype=np.uint64) * np.uint64(0xD1B54A32D192ED03))


def _start(runs: int, done: int = 0):
    """First split of the runs after those done, up to `runs`."""
    roots = _roots(runs, done)
    runs -= done

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if n:
                repeated = [pa.array(np.repeat(roots, n).view(np.int64)), pa.concat_arrays([batch.column(0)] * runs), pa.concat_arrays([batch.column(1)] * runs)]
                yield from _split([pa.record_batch(repeated, names=["bucket", "cls", "sig"])])

    return run


EDGES = "u long, v long"


def _signatures(pdf: pd.DataFrame) -> np.ndarray:
    return np.frombuffer(b"".join(pdf.sig), np.uint32).reshape(-1, POSITIONS)


def _agree(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    """Equal positions of rows, counted eight to a word: a row has at most 128, which fit the word's top byte."""
    words = (many == one).view(np.uint64).sum(axis=1, dtype=np.uint64)
    return (words * np.uint64(0x0101010101010101) >> np.uint64(56)).astype(np.int64)


def _estimates(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    return _agree(one, many) / POSITIONS


def _tree_pairs(sig: np.ndarray, link: float) -> np.ndarray:
    """Row pairs whose estimate reaches the link level, enough to connect all that such pairs connect: a row is compared
    with those only that nothing has reached yet."""
    out, left, found = [np.empty((0, 2), np.int64)], np.arange(len(sig)), []
    rest = sig
    while len(left):
        if not found:
            found, left, rest = [left[0]], left[1:], rest[1:]
            continue
        p = found.pop()
        near = _agree(sig[p], rest) >= link * POSITIONS
        if near.any():
            new = left[near]
            out.append(np.stack([np.full(len(new), p), new], axis=1))
            found.extend(new)
            left, rest = left[~near], rest[~near]
    return np.concatenate(out)


def _near_pairs(starts: np.ndarray, sizes: np.ndarray, sig: np.ndarray, link: float, most: int = 20_000) -> np.ndarray:
    """Row pairs inside runs (starts, sizes) whose estimate reaches the link level, or enough of them to connect the same
    rows; for all runs of a size at once where they are short."""
    out = [np.empty((0, 2), np.int64)]
    for start, size in zip(starts[sizes > SHORT], sizes[sizes > SHORT]):
        out.append(_tree_pairs(sig[start : start + size], link) + start)
    for size in np.unique(sizes[sizes <= SHORT]):
        i, j = np.triu_indices(size, 1)
        at = starts[sizes == size]
        step = max(1, most // len(i))
        for a in range(0, len(at), step):
            left, right = (at[a : a + step, None] + i).ravel(), (at[a : a + step, None] + j).ravel()
            for c in range(0, len(left), most):
                x, y = left[c : c + most], right[c : c + most]
                near = _agree(sig[x], sig[y]) >= link * POSITIONS
                out.append(np.stack([x[near], y[near]], axis=1))
    return np.concatenate(out)


def _search_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges inside small buckets, from (bucket, cls, low) rows in bucket order; low: the lowest byte of each position."""
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def search(rows, last: bool):
        bucket, cls, low = (np.concatenate([r[k] for r in rows]) for k in range(3))
        starts = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
        sizes = np.diff(np.append(starts, len(bucket)))
        done = len(starts) if last else len(starts) - 1
        end = len(bucket) if last else starts[-1]
        pairs = _near_pairs(starts[:done], sizes[:done], low, BUCKET_LINK)
        star = _forest(cls[pairs])
        return pa.record_batch([pa.array(star.u, pa.int64()), pa.array(star.v, pa.int64())], names=["u", "v"]), (bucket[end:], cls[end:], low[end:])

    for batch in batches:
        if not batch.num_rows:
            continue
        bucket, cls = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
        held.append((bucket, cls, np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint8).reshape(-1, POSITIONS)))
        if sum(len(h[0]) for h in held) >= 20_000:
            found, rest = search(held, False)
            held = [rest]
            yield found
    if held:
        yield search(held, True)[0]


def _forest(edges: np.ndarray) -> pd.DataFrame:
    """A star for each component of the edges: at most one row a class."""
    parent: dict[int, int] = {}

    def top(x):
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in edges.tolist():
        a, b = top(a), top(b)
        parent[max(a, b)] = min(a, b)
    rows = [(x, top(x)) for x in parent if top(x) != x]
    return pd.DataFrame(rows, columns=["u", "v"], dtype="int64")


STARS = "u long, v long, bucket long, sig binary, core boolean"


def _mean_similarity(sig: np.ndarray) -> np.ndarray:
    """Mean estimated similarity of each row to the others, from the frequencies of its tokens."""
    total = np.zeros(len(sig))
    for k in range(POSITIONS):
        _, at, n = np.unique(sig[:, k], return_inverse=True, return_counts=True)
        total += n[at] - 1
    return total / (POSITIONS * max(len(sig) - 1, 1))


def _search_chunk(last: bool):
    """Search a chunk of a large bucket. Its core, the classes like most of the bucket, is compared around pivots and
    goes no further; at the last level all classes count as core.

    Rows: edges (u, v); pivots (v null, sig) that stand for what they take, of the core and of its halo, which holds all
    classes that may be near a core class; and classes that go on (v and sig null)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        sig, cls, bucket = _signatures(pdf), pdf.cls.to_numpy(), int(pdf.bucket.iloc[0])
        mean = np.ones(len(cls)) if last else _mean_similarity(sig)
        core = mean >= CORE
        halo = (mean >= HALO) | (len(cls) < FEW)
        left = np.concatenate([np.flatnonzero(core), np.flatnonzero(~core)])  # all core pivots before the first other
        edges, pivots, cores = [np.empty((0, 2), np.int64)], [], []
        while len(left):
            p = left[0]
            if not core[p] and not halo[p]:
                left = left[1:]
                continue
            est = _estimates(sig[p], sig[left])
            if core[p]:
                near = left[(est >= PIVOT_LINK) & (left != p)]
                edges.append(np.stack([cls[near], np.full(len(near), cls[p])], axis=1))
            pivots.append(p)
            cores.append(bool(core[p]))
            left = left[(est < PIVOT_TAKE) & (left != p)]
        on = cls[~core]
        stars = _forest(np.concatenate(edges)).assign(bucket=bucket, sig=None, core=None)
        marks = pd.DataFrame({"u": cls[pivots], "v": pd.array([None] * len(pivots), "Int64"), "bucket": bucket, "sig": [sig[p].tobytes() for p in pivots], "core": cores})
        further = pd.DataFrame({"u": on, "v": pd.array([None] * len(on), "Int64"), "bucket": bucket, "sig": None, "core": None})
        return pd.concat([x for x in (stars, marks, further) if len(x)], ignore_index=True)

    return run


def _search_pivots(pdf: pd.DataFrame) -> pd.DataFrame:
    """Edges between the pivots of two blocks of a bucket, of which one at least is of the core."""
    pdf = pdf.sort_values("core", ascending=False, kind="stable")
    sig, cls = _signatures(pdf), pdf.cls.to_numpy()
    out = [np.empty((0, 2), np.int64)]
    for i in range(min(int(pdf.core.sum()), len(cls) - 1)):
        near = np.flatnonzero(_estimates(sig[i], sig[i + 1 :]) >= PIVOT_PAIR) + i + 1
        out.append(np.stack([np.full(len(near), cls[i]), cls[near]], axis=1))
    return _forest(np.concatenate(out))


def in_block_pairs(df: DataFrame, blocks: str, key: str) -> DataFrame:
    """Repeat each row for every pair of blocks that its own block is in: columns one <= two; `blocks` counts the blocks."""
    mine = F.pmod(F.xxhash64(key), F.col(blocks))
    pairs = F.transform(F.sequence(F.lit(0).cast("long"), F.col(blocks) - 1), lambda o: F.struct(F.least(o, F.col("_mine")).alias("one"), F.greatest(o, F.col("_mine")).alias("two")))
    return df.withColumn("_mine", mine.cast("long")).withColumn("_pair", F.explode(pairs)).select(*df.columns, F.col("_pair.one").alias("one"), F.col("_pair.two").alias("two"))


def candidate_edges(classes: DataFrame) -> DataFrame:
    """Edges between classes (cls, sig, low) that connect every pair at the threshold, but for the target's misses."""
    spark = classes.sparkSession
    lows = classes.select(F.col("cls").alias("c_"), "low")
    # What is searched at the end, all levels together, as each search takes several shuffles: no bucket is on two levels.
    small, stars = [], []

    def look(rows: DataFrame) -> DataFrame:
        """Set the small buckets aside; the rows (bucket, cls, size) of the large ones."""
        counts = rows.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1").withColumnRenamed("bucket", "b_")
        # At most HOT buckets a partition hold more rows than this: a bounded list, whose rows skip the join by bucket.
        most = max(BUCKET, rows.count() // (HOT * shuffle_width(spark)))
        # (A row that fits no bucket keeps the plan the same where there are none.)
        named = [(r.b_, r["size"]) for r in counts.where(F.col("size") > most).collect()]
        marked = spark.createDataFrame([*named, (_NOWHERE, 0)], "h_ long, size long")
        hot = rows.join(F.broadcast(marked), F.col("bucket") == F.col("h_")).select("bucket", "cls", "size")
        rest = rows.join(F.broadcast(marked), F.col("bucket") == F.col("h_"), "left_anti")
        shared = rest.join(counts, F.col("bucket") == F.col("b_")).select("bucket", "cls", "size")
        shared = materialise(shared, "buckets")
        small.append(shared.where(F.col("size") <= BUCKET).select("bucket", "cls"))
        return shared.where(F.col("size") > BUCKET).union(hot)

    def crowded(large: DataFrame, sigs: DataFrame, last: bool) -> DataFrame:
        """Set the edges round the core of the large buckets aside; the rows (bucket, cls) that go on."""
        chunk = F.pmod(F.xxhash64("cls", F.lit(1)), F.greatest(F.ceil(F.col("size") / CHUNK), F.lit(1)))
        dealt = large.join(sigs, F.col("cls") == F.col("c_")).select("bucket", "cls", "sig", chunk.alias("chunk"))
        stars.append(materialise(dealt.groupBy("bucket", "chunk").applyInPandas(_search_chunk(last), STARS), "stars"))
        return stars[-1].where("v is null and sig is null").select("bucket", F.col("u").alias("cls"))

    def searched() -> DataFrame:
        """The edges of all that was set aside."""
        rows = reduce(DataFrame.union, small).join(lows, F.col("cls") == F.col("c_")).select("bucket", "cls", "low")
        edges = rows.repartition(shuffle_width(spark), "bucket").sortWithinPartitions("bucket", "cls").mapInArrow(_search_buckets, EDGES)
        if not stars:
            return edges
        every = reduce(DataFrame.union, stars)
        pivots = every.where("v is null and sig is not null").select("bucket", F.col("u").alias("cls"), "sig", "core")
        many = pivots.groupBy("bucket").agg(F.ceil(F.count("*") / BUCKET).alias("blocks"), F.max("core").alias("some")).where("some").withColumnRenamed("bucket", "b_")
        paired = in_block_pairs(pivots.join(many, F.col("bucket") == F.col("b_")).select("bucket", "cls", "sig", "core", "blocks"), "blocks", "cls")
        return edges.union(every.where("v is not null").select("u", "v")).union(paired.groupBy("bucket", "one", "two").applyInPandas(_search_pivots, EDGES))

    def of(rows: DataFrame, some: DataFrame) -> DataFrame:
        return rows.join(some, F.col("cls") == F.col("c_"), "left_semi")

    first, some, many = runs_needed(1.0), runs_needed(shared_rare(RARE)), runs_needed(shared_rare(HALF))
    large = look(materialise(classes.select("cls", "sig").mapInArrow(_start(first), PATHS), "paths"))
    # Of the tokens that the first runs sampled (the same positions for all classes), the share in large buckets.
    tokens = int(_sampled(_roots(first)).sum())
    busy = large.groupBy("cls").agg((1 - F.count("*") / tokens).alias("rare"))
    sigs = materialise(classes.select("cls", "sig").join(busy.withColumnRenamed("cls", "c_"), F.col("cls") == F.col("c_")).select("c_", "sig", "rare"), "signatures")
    if sigs.isEmpty():
        return searched()
    # A pair that shares a sampled token is found unless all the tokens it shares are in large buckets. Classes with some
    # of those get further runs, in which small buckets are searched only, by how rare their tokens are.
    once = sigs.where(F.col("rare") >= RARE / 3).select("c_", "sig").mapInArrow(_start(some, first), PATHS)
    again = sigs.where((F.col("rare") >= RARE / 3) & (F.col("rare") < RARE)).select("c_", "sig").mapInArrow(_start(many, some), PATHS)
    look(materialise(once.union(again), "paths"))
    # Classes with few rare tokens split further; those that go on beyond the first bucket get the runs of the last level.
    sigs = materialise(sigs.where(F.col("rare") < HALF).select("c_", "sig"), "signatures")
    if sigs.isEmpty():
        return searched()
    large = of(large, sigs)
    for level in range(LEVELS + 1):
        rest = crowded(large, sigs, level == LEVELS)
        if level == 0:
            sigs = materialise(sigs.join(rest.select("cls").distinct(), F.col("cls") == F.col("c_"), "left_semi"), "signatures")
            if sigs.isEmpty():
                return searched()
            large = look(materialise(sigs.select("c_", "sig").mapInArrow(_start(runs_needed(1.0, LEVELS + 1), first), PATHS), "paths"))
            rest = rest.union(crowded(large, sigs, False))
        if level < LEVELS:
            rows = materialise(rest.join(sigs, F.col("cls") == F.col("c_")).select("bucket", "cls", "sig").mapInArrow(_split, PATHS), "paths")
            if rows.isEmpty():
                return searched()
            large = look(rows)
    return searched()


# --- exact comparison -----------------------------------------------------------------------------------------------


def _reshingle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, cls, set_key, ...) -> the class's whole shingle set, from the one text whose set has the class's key."""
    for whole in batches:
        for batch in _sliced(whole):
            columns = batch.to_pydict()
            keep, sets = [], []
            for i, text in enumerate(columns["text"]):
                s = shingle_set(text)
                if _key(s) == columns["set_key"][i]:
                    keep.append(i)
                    sets.append(s.tobytes())
            yield pa.record_batch([pa.array([columns["cls"][i] for i in keep], pa.int64()), pa.array([columns["root"][i] for i in keep], pa.int64()), pa.array([columns["copies"][i] for i in keep], pa.int64()), pa.array(sets, pa.binary())], names=["cls", "root", "copies", "shingles"])
    _words.clear()
    give_back()


def _intersections(sets: list[np.ndarray], rows: slice, columns: slice) -> np.ndarray:
    """Sizes of the intersections of sets[rows] with sets[columns], by slices of the shared shingles."""
    every = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    order = np.argsort(every, kind="stable")
    every, owner = every[order], owner[order]
    first = np.concatenate([[True], every[1:] != every[:-1]])
    number = np.cumsum(first) - 1
    shared = np.bincount(number)[number] > 1
    owner, number = owner[shared], number[shared]
    n = len(sets)
    out = np.zeros((len(range(*rows.indices(n))), len(range(*columns.indices(n)))), np.float32)
    if not len(number):
        return out
    # numbers ascend, so a slice of shingles is a slice of rows
    low = int(number[0])
    while low <= number[-1]:
        a, b = np.searchsorted(number, [low, low + 4096])
        if b > a:
            m = np.zeros((n, 4096), np.float32)
            m[owner[a:b], number[a:b] - low] = 1
            out += m[rows] @ m[columns].T
        low += 4096
    return out


LINKS = "cls long, linked long, root long"


def _compare(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
    """Links of each class inside a block, or between two blocks: weights are the classes' copies."""
    pdf = pdf.drop_duplicates("cls").sort_values(["mine", "cls"], kind="stable")
    sets = [np.frombuffer(x, np.uint64) for x in pdf.shingles]
    cls, copies, sizes = pdf.cls.to_numpy(), pdf.copies.to_numpy(), np.array([len(s) for s in sets])
    half = int((pdf.mine == key[1]).sum()) if key[1] != key[2] else len(cls)
    across = key[1] != key[2]
    rows, columns = (slice(0, half), slice(half, None)) if across else (slice(None), slice(None))
    inter = _intersections(sets, rows, columns)
    union = sizes[rows][:, None] + sizes[columns][None, :] - inter
    near = inter >= NEAR * union - 1e-6
    if not across:
        np.fill_diagonal(near, False)
    linked = np.zeros(len(cls), np.int64)
    linked[rows] += near @ copies[columns]
    if across:
        linked[columns] += near.T @ copies[rows]
    base = half if across else 0
    a, b = np.nonzero(near)
    star = _forest(np.stack([cls[a], cls[b + base]], axis=1))
    roots = dict(zip(star.u, star.v))
    return pd.DataFrame({"cls": cls, "linked": linked, "root": [roots.get(c, c) for c in cls]})


def link_classes(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """(cls, linked, root) of the classes that meet another class in a candidate group.

    classes: cls, doc_id, set_key, copies, n, sig, low, where doc_id names a document with that set.
    """
    groups = materialise(connected_components(candidate_edges(classes)), "groups")
    named = groups.join(classes, F.col("node") == F.col("cls"))
    sizes = named.groupBy("root").agg(F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_SHINGLES)).alias("blocks")).withColumnRenamed("root", "r_")
    members = named.select("cls", "root", "copies", "set_key", F.col("doc_id").alias("d_"))
    lost = F.lit(-(2**63))
    texts = own(docs, "doc_id", "text").withColumn("k_", F.coalesce(F.col("doc_id").cast("long"), lost))
    held = texts.join(members.hint("merge"), F.col("k_") == F.coalesce(F.col("d_"), lost)).select("text", "cls", "root", "copies", "set_key")
    sets = held.mapInArrow(_reshingle, "cls long, root long, copies long, shingles binary")
    placed = in_block_pairs(sets.join(sizes, F.col("root") == F.col("r_")).drop("r_"), "blocks", "cls").withColumn("mine", F.pmod(F.xxhash64("cls"), F.col("blocks")))
    parts = placed.groupBy("root", "one", "two").applyInPandas(_compare, LINKS)
    parts = materialise(parts, "links")
    linked = parts.groupBy("cls").agg(F.sum("linked").alias("linked"))
    roots = connected_components(parts.where("cls <> root").select(F.col("cls").alias("u"), F.col("root").alias("v")))
    return linked.join(roots, F.col("cls") == F.col("node"), "left").select("cls", "linked", F.coalesce("root", "cls").alias("root"))


def near_groups(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, class_id (least doc_id of its connected group), links (documents linked with it),
    set_copies (documents with its shingle set, itself included) and set_key."""
    ship_package(docs.sparkSession)
    sketched = materialise(own(docs, "doc_id", "text").mapInArrow(_sketch, SKETCHED).withColumn("row", F.monotonically_increasing_id()), "sketches")
    some = sketched.where("set_key is not null")
    first = some.groupBy("set_key").agg(F.min("row").alias("cls"), F.count("*").alias("copies"), F.min("doc_id").alias("least"))
    first = materialise(first, "classes")
    classes = some.join(first.select("cls", "copies"), F.col("row") == F.col("cls")).select("cls", "doc_id", "set_key", "copies", "n", "sig", "low")
    classes = materialise(classes, "signatures")
    links = materialise(link_classes(docs, classes), "linked")
    known = first.join(links.withColumnRenamed("cls", "l_"), F.col("cls") == F.col("l_"), "left").select("set_key", "copies", "least", F.coalesce("linked", F.lit(0)).alias("linked"), F.coalesce("root", "cls").alias("root"))
    group = known.groupBy("root").agg(F.min("least").alias("class_id")).withColumnRenamed("root", "r_")
    named = known.join(group, F.col("root") == F.col("r_")).select(F.col("set_key").alias("k_"), "class_id", "copies", "linked")
    joined = sketched.join(named, F.col("set_key") == F.col("k_"), "left")
    alone = F.col("set_key").isNull()
    return joined.select(
        "doc_id",
        F.when(alone, F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"),
        F.when(alone, F.lit(0)).otherwise(F.col("copies") - 1 + F.col("linked")).cast("long").alias("links"),
        F.when(alone, F.lit(1)).otherwise(F.col("copies")).cast("long").alias("set_copies"),
        F.lower(F.hex("set_key")).alias("set_key"),
    )


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """The documents of which one of each group stays, all columns: the one with the group's least doc_id.

    Rows that share an id count as one document and stay or go together; rows without id stay."""
    found = near_groups(docs)
    drop = found.where((F.col("links") > 0) & ~F.col("doc_id").eqNullSafe(F.col("class_id"))).select(F.col("doc_id").alias("_gone")).distinct()
    return restore(carry(docs, "doc_id").join(drop, F.col("doc_id") == F.col("_gone"), "left_anti"))


ORACLE = r"""
WITH RECURSIVE toks AS (
  SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM documents),
sh AS (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS s
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM toks WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
inter AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL),
near AS (
  SELECT x, y FROM inter JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 10 * c >= 8 * (p.n + q.n - c)),
reach AS (
  SELECT doc_id AS x, doc_id AS y FROM documents
  UNION
  SELECT r.x, near.y FROM reach r JOIN near ON r.y = near.x)
SELECT d.doc_id, (SELECT min(y) FROM reach WHERE reach.x = d.doc_id) AS class_id,
       (SELECT count(*) FROM near WHERE near.x = d.doc_id) AS links
FROM documents d
"""
