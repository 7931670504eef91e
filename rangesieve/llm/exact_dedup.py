"""Exact dedup through minimal perfect hashes over historical digests.

The digests of the history (already accepted texts) are grouped, dealt into shards by their leading bits and each
shard becomes one row: a minimal perfect hash plus, at every slot, the full 32-byte digest, the winner's id and the
number of rows. New digests look their slot up, compare all 32 bytes, and either join that slot's group or, being
nonmembers, form a group of their own. A group's winner is its largest id.

Defined cases: null text counts as empty; two texts are equal if they are identical after lower-casing A-Z only; of
rows repeated with one id and text, exactly one is kept; a null id loses against any id; an empty table gives no
rows; extra columns are ignored by the digest query and carried along by keep_first_copies.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import carry, materialise, own, restore, ship_package

GAMMA = 1.6
SHARD_DIGESTS = 20_000


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def _places(words: np.ndarray, level: int, size: int) -> np.ndarray:
    """Place of each digest (four 64-bit words) at one level."""
    with np.errstate(over="ignore"):
        h = _mix(words[:, 0] + np.uint64(level * 0x9E3779B97F4A7C15 % 2**64))
        for k in (1, 2, 3):
            h = _mix(h ^ (words[:, k] + np.uint64(level + k)))
    return (h % np.uint64(size)).astype(np.int64)


class PerfectHash:
    """Levels of bit arrays: a digest alone at its place of a level sets that bit, the others go one level down."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels
        self.ranks = []
        before = 0
        for bits in levels:
            self.ranks.append(before + np.cumsum(bits) - bits)
            before += int(bits.sum())
        self.n = before

    @classmethod
    def build(cls, digests: np.ndarray) -> PerfectHash:
        """digests: distinct rows of 32 bytes."""
        left = digests.reshape(-1, 32).copy().view("<u8")
        levels = []
        while len(left):
            size = max(int(GAMMA * len(left)), 2)
            at = _places(left, len(levels), size)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(alone.astype(np.int64))
            left = left[~alone[at]]
        return cls(levels)

    def slots(self, digests: np.ndarray) -> np.ndarray:
        """A slot below n for every member; some slot or -1 for others."""
        words = digests.reshape(-1, 32).copy().view("<u8")
        out = np.full(len(words), -1, dtype=np.int64)
        todo = np.arange(len(words))
        for k, bits in enumerate(self.levels):
            if not len(todo):
                break
            at = _places(words[todo], k, len(bits))
            hit = bits[at] == 1
            out[todo[hit]] = self.ranks[k][at[hit]]
            todo = todo[~hit]
        return out

    def dump(self) -> tuple[list[int], bytes]:
        return [len(b) for b in self.levels], b"".join(np.packbits(b.astype(np.uint8)).tobytes() for b in self.levels)

    @classmethod
    def load(cls, sizes, blob: bytes) -> PerfectHash:
        levels, at = [], 0
        for size in sizes:
            width = -(-int(size) // 8)
            levels.append(np.unpackbits(np.frombuffer(blob, np.uint8, width, at))[: int(size)].astype(np.int64))
            at += width
        return cls(levels)


def _as_matrix(column) -> np.ndarray:
    return np.frombuffer(b"".join(column), np.uint8).reshape(-1, 32)


def _digests(texts: pa.Array) -> pa.Array:
    return pa.array([hashlib.sha256((b or b"").lower()).digest() for b in texts.cast(pa.binary()).to_pylist()], pa.binary())


def text_digest(column: str) -> Column:
    """SHA-256 of the UTF-8 text after lower-casing A-Z; null counts as empty."""
    return F.arrow_udf(_digests, T.BinaryType())(column)


INDEX = "shard int, sizes array<int>, bits binary, digests binary, winners binary, counts binary"


def _index_shard(pdf: pd.DataFrame) -> pd.DataFrame:
    digests = _as_matrix(pdf.digest)
    table = PerfectHash.build(digests)
    at = table.slots(digests)
    order = np.empty(table.n, dtype=np.int64)
    order[at] = np.arange(table.n)
    sizes, bits = table.dump()
    winners = pdf.winner.to_numpy(np.int64)[order]
    counts = pdf.n.to_numpy(np.int64)[order]
    return pd.DataFrame({"shard": [int(pdf.shard.iloc[0])], "sizes": [sizes], "bits": [bits], "digests": [digests[order].tobytes()], "winners": [winners.tobytes()], "counts": [counts.tobytes()]})


NO_ID = -(2**63)
GROUPS = "digest binary, winner long, n long, in_history boolean"


def _look_up(index: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
    """Groups of one shard: the history's slots, joined by the members found among the new digests, then the nonmembers."""
    parts = []
    own_new = np.ones(len(new), dtype=bool)
    digests = _as_matrix(new.digest) if len(new) else np.empty((0, 32), np.uint8)
    winner, n = new.winner.to_numpy(np.int64), new.n.to_numpy(np.int64)
    for row in index.itertuples():
        table = PerfectHash.load(row.sizes, row.bits)
        slots = np.frombuffer(row.digests, np.uint8).reshape(-1, 32)
        winners, counts = np.frombuffer(row.winners, np.int64).copy(), np.frombuffer(row.counts, np.int64).copy()
        if len(new):
            at = table.slots(digests)
            member = at >= 0
            member[member] = (slots[at[member]] == digests[member]).all(axis=1)
            np.maximum.at(winners, at[member], winner[member])
            np.add.at(counts, at[member], n[member])
            own_new &= ~member
        parts.append(pd.DataFrame({"digest": [x.tobytes() for x in slots], "winner": winners, "n": counts, "in_history": True}))
    parts.append(pd.DataFrame({"digest": new.digest[own_new].map(bytes), "winner": winner[own_new], "n": n[own_new], "in_history": False}))
    return pd.concat(parts, ignore_index=True)


def build_index(groups: DataFrame, shards: int) -> DataFrame:
    """Index rows (one per shard) over distinct digests (digest, winner, n)."""
    dealt = groups.withColumn("shard", _shard(shards))
    return dealt.groupBy("shard").applyInPandas(_index_shard, INDEX)


def _shard(shards: int):
    return F.pmod(F.xxhash64("digest"), F.lit(shards)).cast("int")


def digest_groups(history: DataFrame, new: DataFrame, shards: int) -> DataFrame:
    """One row per distinct digest of history and new rows (each: id long or null, digest): winner, n, in_history."""

    def grouped(df):
        return df.groupBy("digest").agg(F.max(F.coalesce("id", F.lit(NO_ID))).alias("winner"), F.count("*").alias("n"))

    index = build_index(grouped(history), shards)
    fresh = grouped(new).withColumn("shard", _shard(shards))
    return index.groupBy("shard").cogroup(fresh.groupBy("shard")).applyInPandas(_look_up, GROUPS)


def split_history(rows: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """The earlier half of the ids is the history of the later half; returns both and the shard count."""
    seen = rows.agg(F.count("*").alias("n"), F.percentile_approx("id", 0.5, 1000).alias("mid")).first()
    mid = seen.mid if seen.mid is not None else 0
    older = F.coalesce(F.col("id") <= mid, F.lit(False))
    return rows.where(older), rows.where(~older), max(1, -(-seen.n // SHARD_DIGESTS))


def find_copies(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, in_history."""
    ship_package(docs.sparkSession)
    rows = own(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("id"), text_digest("text").alias("digest"))
    rows = materialise(rows.groupBy("digest", "id").agg(F.count("*").alias("times")), "digests")
    each = rows.select("id", "digest", F.explode(F.expr("sequence(1, times)")).alias("copy"))
    history, new, shards = split_history(each)
    groups = digest_groups(history, new, shards)
    keep = F.when(F.col("winner") != NO_ID, F.col("winner"))
    return each.join(groups, "digest").select(
        F.col("id").alias("doc_id"),
        keep.alias("keep_id"),
        F.col("n").alias("group_size"),
        (F.coalesce("id", F.lit(NO_ID)).eqNullSafe(F.col("winner")) & (F.col("copy") == 1)).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
        "in_history",
    )


def keep_first_copies(docs: DataFrame) -> DataFrame:
    """The documents that stay, all their columns: of equal texts the row with the largest doc_id."""
    stays = find_copies(docs).where("kept").select(F.coalesce("doc_id", F.lit(NO_ID)).alias("_id"), F.unhex("text_sha256").alias("_stay"))
    keyed = carry(docs, "doc_id", "text").withColumn("_digest", text_digest("text")).withColumn("_key", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)))
    joined = keyed.join(stays, (F.col("_key") == F.col("_id")) & (F.col("_digest") == F.col("_stay")), "left_semi")
    # Rows repeated with one id and text differ at most in other columns; one of them stays.
    return restore(joined.dropDuplicates(["_key", "_digest"]))


ORACLE = """
SELECT doc_id,
       max(doc_id) OVER g AS keep_id,
       count(*) OVER g AS group_size,
       row_number() OVER (PARTITION BY norm ORDER BY doc_id DESC NULLS LAST) = 1 AS kept,
       sha256(norm) AS text_sha256
FROM (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm
      FROM documents)
WINDOW g AS (PARTITION BY norm)
"""
