"""Packing token sequences by minimum bin slack.

A document's ids (with its closing id) are cut into full windows and a remainder. Remainders are counted by length;
the counts have at most one entry a length, whatever the corpus, so the plan is made on the driver: the longest
remaining length opens a window, a bitset subset-sum over the other lengths finds the multiset that fills the window
closest to its capacity, backtracking gives how often each length occurs in it, and the pattern is repeated as often
as the counts allow. Lengths that no multiset fills within `max_slack` are laid end to end and cut at the windows'
ends; the last partial window is cut into powers of two, which need no padding.

Ranks of equal lengths come from running sums that spread a hot length over many tasks, so a document finds its window
by its length and rank alone.

Defined cases: null text counts as empty (its only id is the closing one); repeated rows are separate documents; an
empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
import struct
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import give_back, materialise, own, running_sum, ship_package

WINDOW = 2048
CLOSING_ID = 1
TOKENIZER = "word_bpe_49k.json"
MAX_SLACK = 2
CACHED_WORDS = 850_000
SLICE_CHARS = 2_000_000

_latin = [chr(i) for i in range(0x250)]
_letters = "".join(re.escape(c) for c in _latin if unicodedata.category(c)[0] == "L")
_numbers = "".join(re.escape(c) for c in _latin if unicodedata.category(c)[0] == "N")
#: The tokenizer's own split, over Latin letters; any other text goes through the library as a whole.
_SPLIT = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{_letters}]+|[{_numbers}]|[^\s{_letters}{_numbers}]+")
#: Texts with other characters, before or after lower-casing, go through the library.
_ODD = re.compile("[^\x00-\x1b\x20-ɏ]|[" + "".join(c for c in _latin if max(c.lower()) > "ɏ") + "]")


def _byte_letters() -> list[str]:
    """The byte-level alphabet: printable bytes stand for themselves, the others for the letters from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    others = iter(range(0x100, 0x200))
    return [chr(b if b in plain else next(others)) for b in range(256)]


_BYTES = _byte_letters()


class _Ids(dict):
    """Run without white space -> its ids as little-endian 32-bit bytes, worked out when it is first asked for.

    Words never merge over a space, so a run's ids are those of its words on end, and a word's are the model's merges.
    """

    def __init__(self, tokenizer):
        super().__init__()
        self.tokenizer, self.merges, self.most = tokenizer, tokenizer.model, CACHED_WORDS

    def __missing__(self, run: str) -> bytes:
        words = _SPLIT.findall(run)
        if len(words) > 1:
            found = b"".join([self[w] for w in words])
        else:
            letters = run if run.isascii() and run.isprintable() else "".join([_BYTES[b] for b in run.encode()])
            ids = [t.id for t in self.merges.tokenize(letters)]
            found = struct.pack(f"<{len(ids)}I", *ids)
        if len(self) >= self.most:
            self.clear()
        self[run] = found
        return found


_open: dict[str, _Ids] = {}


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encode_all(texts: list[str], path: str, cached_words: int = CACHED_WORDS) -> list[bytes]:
    """Ids of whole texts, little-endian unsigned 32-bit."""
    if path not in _open:
        from tokenizers import Tokenizer

        _open[path] = _Ids(Tokenizer.from_file(path))
    ids = _open[path]
    ids.most = cached_words
    by_library = lambda t: np.asarray(ids.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes()
    return [by_library(t) if "<|" in t or _ODD.search(t) else b"".join(map(ids.__getitem__, t.lower().split())) for t in texts]


def encode(text: str, path: str) -> bytes:
    return encode_all([text], path)[0]


def _slices(texts: list[str]) -> Iterator[list[str]]:
    """Runs of texts of a bounded length, one text at least."""
    now, total = [], 0
    for t in texts:
        if now and total + len(t) > SLICE_CHARS:
            yield now
            now, total = [], 0
        now.append(t)
        total += len(t)
    if now:
        yield now


CUT = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("doc_tokens", T.LongType()), T.StructField("crcs", T.ArrayType(T.LongType())), T.StructField("rest", T.IntegerType()), T.StructField("rest_crc", T.LongType()), T.StructField("rest_ids", T.BinaryType())])


def _tokenize(name: str | None, window: int, cached_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path = name if "/" in (name or "") else tokenizer_path(name or TOKENIZER)
        closing = np.asarray([CLOSING_ID], "<u4").tobytes()
        width = 4 * window
        for batch in batches:
            tokens, crcs, rests, rest_crcs, kept = [], [], [], [], []
            every = (ids + closing for part in _slices([t or "" for t in batch.column(1).to_pylist()]) for ids in encode_all(part, path, cached_words))
            for ids in every:
                full = len(ids) // width
                tokens.append(len(ids) // 4)
                crcs.append([zlib.crc32(ids[k * width : (k + 1) * width]) for k in range(full)])
                rest = ids[full * width :]
                rests.append(len(rest) // 4)
                rest_crcs.append(zlib.crc32(rest))
                kept.append(_narrow(rest))
            yield pa.record_batch([batch.column(0).cast(pa.int64()), pa.array(tokens, pa.int64()), pa.array(crcs, pa.list_(pa.int64())), pa.array(rests, pa.int32()), pa.array(rest_crcs, pa.int64()), pa.array(kept, pa.binary())], names=CUT.fieldNames())
        if cached_words < CACHED_WORDS:  # a small cache says that memory is short: nothing is kept for the next task
            _open[path].clear() if path in _open else None
            give_back()

    return run


def _narrow(ids: bytes) -> bytes:
    """Two bytes an id where all ids fit, behind a marker byte."""
    wide = np.frombuffer(ids, "<u4")
    return b"\x02" + wide.astype("<u2").tobytes() if not len(wide) or wide.max() < 65536 else b"\x04" + ids


def _widen(kept: bytes) -> bytes:
    return kept[1:] if kept[:1] == b"\x04" else np.frombuffer(kept, "<u2", offset=1).astype("<u4").tobytes()


# --- the plan -------------------------------------------------------------------------------------------------------


def closest_fill(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The multiset of lengths (within counts) whose sum comes closest to capacity from below, as length -> times.

    Bit s of a bitset says that the sum s can be reached; each step adds a length once, twice, four times, ... and is
    kept for backtracking. The search ends early when the capacity itself is reached.
    """
    if capacity <= 0:
        return {}
    mask = (1 << (capacity + 1)) - 1
    reach, steps = 1, []
    for length in sorted((x for x in counts if x <= capacity and counts[x] > 0), reverse=True):
        left, take = min(counts[length], capacity // length), 1
        while left > 0:
            take = min(take, left)
            more = (reach | reach << (take * length)) & mask
            if more != reach:
                steps.append((length, take, reach))
                reach = more
            left -= take
            take *= 2
        if reach >> capacity & 1:
            break
    at = reach.bit_length() - 1
    found: dict[int, int] = {}
    for length, take, before in reversed(steps):
        if not before >> at & 1:
            found[length] = found.get(length, 0) + take
            at -= take * length
    return found


def plan_windows(counts: dict[int, int], window: int = WINDOW, max_slack: int = MAX_SLACK) -> tuple[list[tuple[dict[int, int], int]], dict[int, int]]:
    """Patterns (length -> times, repeats) with slack up to max_slack, and what is left over, length -> count."""
    counts = {k: v for k, v in counts.items() if v > 0}
    patterns: list[tuple[dict[int, int], int]] = []
    over: dict[int, int] = {}
    while counts:
        longest = max(counts)
        counts[longest] -= 1
        fill = closest_fill(counts, window - longest)
        counts[longest] += 1
        fill[longest] = fill.get(longest, 0) + 1
        if window - sum(k * v for k, v in fill.items()) > max_slack:
            over[longest] = counts.pop(longest)
            continue
        repeats = min(counts[k] // v for k, v in fill.items())
        for k, v in fill.items():
            counts[k] -= repeats * v
            if not counts[k]:
                del counts[k]
        patterns.append((fill, repeats))
    return patterns, over


def _assignments(patterns, over, window: int):
    """Rows (rest, from_rank, to_rank, sequence, times, offset) of the patterns, the base of each leftover length, sequences used."""
    used: dict[int, int] = {}
    rows, sequence = [], 0
    for fill, repeats in patterns:
        offset = 0
        for length in sorted(fill, reverse=True):
            times, start = fill[length], used.get(length, 0)
            rows.append((length, start, start + times * repeats, sequence, times, offset))
            used[length] = start + times * repeats
            offset += times * length
        sequence += repeats
    bases, at = [], 0
    for length in sorted(over, reverse=True):
        bases.append((length, used.get(length, 0), at))
        at += over[length] * length
    return rows, bases, at, sequence


PIECES = T.StructType([T.StructField(n, T.LongType()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_length")])


def _cut_leftovers(window: int, total: int, first: int):
    """Pieces of leftover remainders, each at a known place of the laid-out line."""
    full_end = total - total % window
    ends, at = [], full_end
    for k in reversed(range(window.bit_length())):
        if total % window >> k & 1:
            ends.append((at, at + (1 << k)))
            at += 1 << k

    def place(at: int) -> tuple[int, int, int]:
        if at < full_end:
            return at // window * window, (at // window + 1) * window, first + at // window
        for k, (a, b) in enumerate(ends):
            if at < b:
                return a, b, first + full_end // window + k
        raise ValueError("beyond the line")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                ids = _widen(row["rest_ids"])
                done, n = 0, row["rest"]
                while done < n:
                    low, high, sequence = place(row["place"] + done)
                    take = min(n - done, high - row["place"] - done)
                    out.append((row["doc_id"], row["doc_tokens"] - n + done, take, zlib.crc32(ids[4 * done : 4 * (done + take)]), row["doc_tokens"], sequence, row["place"] + done - low, high - low))
                    done += take
            columns = list(zip(*out)) if out else [()] * len(PIECES)
            yield pa.record_batch([pa.array(c, pa.int64()) for c in columns], names=PIECES.fieldNames())

    return run


def pack_documents(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, max_slack: int = MAX_SLACK, cached_words: int = CACHED_WORDS) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, sequence_length (ids in it).

    cached_words bounds the memory of a Python worker (about 200 bytes a word) and changes no result."""
    spark = docs.sparkSession
    ship_package(spark)
    cut = materialise(own(docs, "doc_id", "text").mapInArrow(_tokenize(tokenizer, window, cached_words), CUT), "tokens")
    # At most one row a length, and the number of documents and full windows.
    counts = {r.rest: r.n for r in cut.where("rest > 0").groupBy("rest").agg(F.count("*").alias("n")).collect()}
    n_rows = cut.count()
    patterns, over = plan_windows(counts, window, max_slack)
    rows, bases, line, sequences = _assignments(patterns, over, window)
    partial = line % window
    after_line = sequences + line // window + bin(partial).count("1")

    spread = F.xxhash64("doc_id", "doc_tokens", "crcs")
    whole = cut.where(F.size("crcs") > 0).select("doc_id", "doc_tokens", "crcs", F.size("crcs").cast("long").alias("n_full"), F.lit(0).alias("all"))
    whole = running_sum(whole, ["all"], spread, "n_full", n_rows, "first")
    full = whole.select("doc_id", "doc_tokens", "first", F.posexplode("crcs").alias("k", "crc")).select(
        "doc_id", (F.col("k").cast("long") * window).alias("start"), F.lit(window).cast("long").alias("length"), F.col("crc").alias("ids_crc32"), "doc_tokens", (F.col("first") + F.col("k") + after_line).alias("sequence_id"), F.lit(0).cast("long").alias("offset"), F.lit(window).cast("long").alias("sequence_length")
    )

    ranked = cut.where("rest > 0").select("doc_id", "doc_tokens", "rest", F.lit(1).cast("long").alias("one"), "rest_crc", F.when(F.col("rest").isin(list(over)), F.col("rest_ids")).alias("rest_ids"))
    ranked = running_sum(ranked, ["rest"], F.xxhash64("doc_id", "doc_tokens", "rest_crc"), "one", n_rows, "rank")
    # Bounded by construction: at most window - 1 lengths, each closed by the pattern that uses it up.
    sums: dict[int, int] = {}
    for rest, _, _, seq, times, _ in rows:
        sums[seq] = sums.get(seq, 0) + rest * times
    slots = spark.createDataFrame([(*r, sums[r[3]]) for r in rows], "s_rest int, a long, b long, seq long, times long, off long, fill long")
    slots = slots.groupBy("s_rest").agg(F.array_sort(F.collect_list(F.struct("a", "b", "seq", "times", "off", "fill"))).alias("slots"))
    leftover = spark.createDataFrame(bases, "l_rest int, from_rank long, base long")
    placed = ranked.join(F.broadcast(slots), F.col("rest") == F.col("s_rest"), "left").join(F.broadcast(leftover), F.col("rest") == F.col("l_rest"), "left")
    placed = placed.withColumn("slot", F.expr("get(filter(slots, s -> rank >= s.a and rank < s.b), 0)"))
    fitted = placed.where("slot is not null").select(
        "doc_id",
        (F.col("doc_tokens") - F.col("rest")).alias("start"),
        F.col("rest").cast("long").alias("length"),
        F.col("rest_crc").alias("ids_crc32"),
        "doc_tokens",
        F.expr("slot.seq + (rank - slot.a) div slot.times").alias("sequence_id"),
        F.expr("slot.off + ((rank - slot.a) % slot.times) * rest").alias("offset"),
        F.col("slot.fill").alias("sequence_length"),
    )
    tail = placed.where("slot is null").select("doc_id", "doc_tokens", "rest", (F.col("base") + (F.col("rank") - F.col("from_rank")) * F.col("rest")).alias("place"), "rest_ids")
    cut_up = tail.mapInArrow(_cut_leftovers(window, line, sequences), PIECES)
    return full.unionByName(fitted).unionByName(cut_up)
