"""Packed form: Elias-Fano shards as binary columns, with rank, select and predecessor on the bits.

A shard holds up to CODES sorted codes of one range of code space. Low parts are stored in l bits each; high parts are
unary: bit (code >> l) + i is set for the i-th code. Both live in 64-bit words, with the ones counted before each word of
the high part; a predecessor takes two selects of zeros and a binary search among the low parts of one cell.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.functions.hashing import HashParams
from rangesieve.functions.ship import ship
from rangesieve.operators.order import SHARDS, grows, predecessor, shuffle_width, splitters, with_shard

CODES = 65_536
#: Points that one task asks of one copy of a blob.
ASKED = 100_000
_U = np.uint64


def _to_words(bits: np.ndarray) -> np.ndarray:
    """Bits, first one lowest, in 64-bit words."""
    return np.packbits(np.pad(bits.astype(np.uint8), (0, -len(bits) % 64)), bitorder="little").view(_U)


class EliasFano:
    """Sorted distinct non-negative integers in n * l + (top >> l) + n + 1 bits."""

    def __init__(self, n: int, l: int, length: int, high: np.ndarray, low: np.ndarray):
        self.n, self.l, self.length, self.high, self.low = n, l, length, high, np.append(low, _U(0))
        ones = np.bitwise_count(high).astype(np.int64)
        self.before = np.concatenate([[0], np.cumsum(ones)])  # ones before each word
        self.zeros_before = np.arange(len(high) + 1) * 64 - self.before

    @classmethod
    def encode(cls, z: np.ndarray, l: int) -> EliasFano:
        z = np.asarray(z, _U)
        high = np.zeros(int(z[-1] >> _U(l)) + len(z) + 1 if len(z) else 1, np.uint8)
        high[(z >> _U(l)).astype(np.int64) + np.arange(len(z))] = 1
        words = np.zeros((len(z) * l + 63) // 64, _U)
        if l and len(z):
            at = np.arange(len(z), dtype=np.int64) * l
            part = z & _U(2**l - 1)
            word, shift = at >> 6, (at & 63).astype(_U)
            np.bitwise_or.at(words, word, part << shift)
            over = (at & 63) + l > 64
            np.bitwise_or.at(words, word[over] + 1, part[over] >> (_U(64) - shift[over]))
        return cls(len(z), l, len(high), _to_words(high), words)

    def bits(self) -> int:
        return self.n * self.l + self.length

    def bit_string(self) -> str:
        return "".join(map(str, np.unpackbits(self.high.view(np.uint8), bitorder="little")[: self.length]))

    def selects(self, bit: int, ks: np.ndarray) -> np.ndarray:
        """1-based places of the k-th ones or zeros, counted from 1; 0 for k = 0."""
        ks = np.asarray(ks, np.int64)
        counts = self.before if bit else self.zeros_before
        word = np.clip(np.searchsorted(counts, ks, side="left") - 1, 0, len(self.high) - 1)
        held = self.high[word] if bit else ~self.high[word]
        rows = np.unpackbits(np.ascontiguousarray(held).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        inside = np.argmax(np.cumsum(rows, axis=1) >= (ks - counts[word])[:, None], axis=1)
        return np.where(ks > 0, word * 64 + inside + 1, 0)

    def select(self, bit: int, k: int) -> int:
        return int(self.selects(bit, np.array([k]))[0])

    def lows(self, i: np.ndarray) -> np.ndarray:
        """Low parts of the codes of ranks i (from 0)."""
        if not self.l:
            return np.zeros(len(i), _U)
        at = np.asarray(i, np.int64) * self.l
        shift = (at & 63).astype(_U)
        first = self.low[at >> 6] >> shift
        rest = np.where(shift > 0, self.low[np.minimum((at >> 6) + 1, len(self.low) - 1)] << ((_U(64) - shift) & _U(63)), _U(0))
        return (first | rest) & _U(2**self.l - 1)

    def access(self, i: np.ndarray) -> np.ndarray:
        """Codes of ranks i (from 0)."""
        high = self.selects(1, np.asarray(i) + 1) - 1 - np.asarray(i)
        return (high.astype(_U) << _U(self.l)) | self.lows(i)

    def decode(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.high.view(np.uint8), bitorder="little")[: self.length])
        return ((ones - np.arange(self.n)).astype(_U) << _U(self.l)) | self.lows(np.arange(self.n))

    def cells(self, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First and last rank (from 1) of the codes whose high part is that of y; empty if last < first."""
        p = np.asarray(y, np.int64) >> self.l
        beyond = p >= self.length - self.n
        p = np.where(beyond, 0, p)
        first, last = self.selects(0, p) - p + 1, self.selects(0, p + 1) - p - 1
        return np.where(beyond, self.n + 1, first), np.where(beyond, self.n, last)

    def cell(self, y: int) -> tuple[int, int]:
        first, last = self.cells(np.array([y]))
        return int(first[0]), int(last[0])

    def ranks(self, y: np.ndarray) -> np.ndarray:
        """Number of codes <= y, for each y (0 below 0)."""
        y = np.asarray(y, np.int64)
        if not self.n:
            return np.zeros(len(y), np.int64)
        low, high = self.cells(np.maximum(y, 0))
        low, wanted = low - 1, (y & (2**self.l - 1)).astype(_U)
        while (open_ := low < high).any():
            mid = (low + high) // 2
            under = open_ & (self.lows(np.clip(mid, 0, self.n - 1)) <= wanted)
            low, high = np.where(under, mid + 1, low), np.where(open_ & ~under, mid, high)
        return np.where(y < 0, 0, low)

    def predecessor(self, y: int) -> int | None:
        found = int(self.ranks(np.array([y]))[0])
        return int(self.access(np.array([found - 1]))[0]) if found else None

    def dump(self) -> tuple[bytes, bytes]:
        return self.high.tobytes(), self.low[:-1].tobytes()

    @classmethod
    def load(cls, n: int, l: int, length: int, high: bytes, low: bytes) -> EliasFano:
        return cls(n, l, length, np.frombuffer(high, _U), np.frombuffer(low, _U))


def open_shards(shards: list[tuple[list[int], int]]) -> list[EliasFano]:
    """Packed shards of a few sorted codes, (codes, low bits) each, on the driver."""
    return [EliasFano.encode(np.array(z), l) for z, l in shards]


SHARD_ROWS = "shard int, n long, l int, first long, last long, length long, high binary, low binary"


def pack(codes: DataFrame, l: int, n: int | None = None) -> DataFrame:
    """Rows of up to CODES codes, from distinct codes (z). Codes stream through a task in order, so its memory is bounded."""
    ship(codes.sparkSession)

    def encode(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shard, held = None, np.empty(0, np.int64)

        def row(z: np.ndarray) -> tuple:
            ef = EliasFano.encode(z - z[0], l)
            return (shard, len(z), l, z[0], z[-1], ef.length, *ef.dump())

        for pdf in batches:
            rows = []
            for s, part in pdf.groupby("shard", sort=False):
                if s != shard and len(held):
                    rows.append(row(held))
                    held = held[:0]
                shard, held = int(s), np.concatenate([held, part.z.to_numpy()])
                while len(held) >= CODES:
                    rows.append(row(held[:CODES]))
                    held = held[CODES:]
            if rows:
                yield pd.DataFrame(rows, columns=_NAMES)
        if len(held):
            yield pd.DataFrame([row(held)], columns=_NAMES)

    placed = with_shard(codes.where("z is not null"), "z", splitters(codes, "z", n), "shard")
    ordered = placed.repartition(SHARDS * shuffle_width(codes.sparkSession), "shard").sortWithinPartitions("shard", "z")
    return ordered.select("shard", "z").mapInPandas(encode, SHARD_ROWS)


_NAMES = [x.split()[0] for x in SHARD_ROWS.split(", ")]


def _load(row) -> EliasFano:
    return EliasFano.load(int(row.n), int(row.l), int(row.length), row.high, row.low)


def unpack(shards: DataFrame) -> DataFrame:
    ship(shards.sparkSession)

    def decode(batches):
        for pdf in batches:
            for row in pdf.itertuples():
                yield pd.DataFrame({"z": _load(row).decode().astype(np.int64) + row.first})

    return shards.mapInPandas(decode, "z long")


def beside(points: DataFrame, blobs: DataFrame, on: list[str], ask, schema: str) -> DataFrame:
    """ask(points, blob row) for the points and the one blob that share `on`. A blob that many points ask is copied to a
    task for every ASKED of them; it is never copied to rows. Points without blob give no row."""
    ship(points.sparkSession)
    many = points.groupBy(*on).agg(F.ceil(F.count("*") / ASKED).cast("int").alias("_parts")).withColumnsRenamed({c: f"m_{c}" for c in on})
    same = [F.col(c).eqNullSafe(F.col(f"m_{c}")) for c in on]
    gone = [f"m_{c}" for c in on] + ["_parts"]
    plain = [c for c in points.columns if "map<" not in dict(points.dtypes)[c]]
    asked = points.join(grows(many), same).withColumn("_part", F.pmod(F.xxhash64(*plain), F.col("_parts")).cast("int")).drop(*gone)
    held = blobs.join(grows(many), same).withColumn("_part", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))).drop(*gone)

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({x.split()[0]: [] for x in schema.split(", ")})
        return ask(left, next(right.itertuples()))

    return asked.groupBy(*on, "_part").cogroup(held.groupBy(*on, "_part")).applyInPandas(run, schema)


def find(shards: DataFrame, points: DataFrame, at: str) -> DataFrame:
    """Points (qid, `at`) with pred: the largest code <= at, null if none, from the packed bits alone."""
    placed = predecessor(shards.select(F.col("first").alias("z")), points.select("qid", at), at).select("qid", at, F.col("pred.z").alias("first"))

    def ask(left: pd.DataFrame, shard) -> pd.DataFrame:
        ef = _load(shard)
        found = ef.ranks(left[at].to_numpy() - shard.first)  # 1 at least: the first code lies at or below
        return pd.DataFrame({"qid": left.qid, at: left[at], "pred": ef.access(found - 1).astype(np.int64) + shard.first})

    held = beside(placed.where("first is not null"), shards, ["first"], ask, f"qid long, {at} long, pred long")
    return held.union(placed.where("first is null").select("qid", at, F.lit(None).cast("long").alias("pred")))


def shard_zeros(shards: DataFrame) -> DataFrame:
    """(cell, codes_below): for every occupied cell, the codes that lie below its end, from the place of the zero that
    closes it. A cell whose codes two shards share counts in the last of them."""
    ship(shards.sparkSession)

    def run(batches):
        for pdf in batches:
            for row in pdf.itertuples():
                ef = _load(row)
                z = ef.decode().astype(np.int64) + row.first
                top = np.unique(z >> row.l)
                # Cells of the whole are cut by the shard's first code: a border inside is a rank of the bits.
                below = ef.ranks(((top + 1) << row.l) - 1 - row.first)
                yield pd.DataFrame({"first": row.first, "cell": top, "inside": below})

    counted = shards.select("first", "n")
    before = counted.withColumn("start", F.coalesce(F.sum("n").over(Window.orderBy("first").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select(F.col("first").alias("f_"), "start")
    found = shards.mapInPandas(run, "first long, cell long, inside long").join(F.broadcast(before), F.col("first") == F.col("f_"))
    return found.groupBy("cell").agg(F.max(F.col("start") + F.col("inside")).alias("codes_below"))


def register_udfs(spark) -> None:
    """SQL functions over one packed filter: maybe_contains_code(n, l, first, length, high, low, lo, hi)."""
    ship(spark)

    def contains(n: pd.Series, l: pd.Series, first: pd.Series, length: pd.Series, high: pd.Series, low: pd.Series, lo: pd.Series, hi: pd.Series) -> pd.Series:
        df = pd.DataFrame({"n": n, "l": l, "first": first, "length": length, "high": high, "low": low, "lo": lo, "hi": hi})
        out = np.zeros(len(df), bool)
        run = (df.high.ne(df.high.shift()) | df.low.ne(df.low.shift()) | df["first"].ne(df["first"].shift())).cumsum().to_numpy()
        for g in np.unique(run):
            at = np.flatnonzero(run == g)
            part = df.iloc[at]
            ef, start = _load(part.iloc[0]), int(part["first"].iloc[0])
            out[at] = ef.ranks(part.hi.to_numpy() - start) > ef.ranks(part.lo.to_numpy() - start - 1)
        return pd.Series(out, dtype=bool)

    spark.udf.register("maybe_contains_code", F.pandas_udf(contains, T.BooleanType()))


def build_from_list(keys: list[int], p: HashParams, l: int) -> EliasFano:
    """Filter of a few keys on the driver, for worked examples."""
    from rangesieve.functions.hashing import h_value

    return EliasFano.encode(np.array(sorted({h_value(k, p) for k in keys})), l)
