"""Language identification by cross-parsing.

For every language a suffix automaton of labelled text is built. A text is parsed against it from left to right into
the longest phrases that occur in that reference: the automaton is walked until it has no transition, which ends a
phrase. The language that needs the fewest phrases, each weighed with the bits that name a place in its reference,
wins. The walk runs over many texts in lockstep, cut into segments, so it is a handful of array operations a step.

The reference is a bounded sample of labelled rows: the distinct lettered texts of a language in the order of their hash,
whole, until it has REFERENCE characters (the text that reaches the bound ends there) or DOCUMENTS texts.

An automaton's moves are a table of its states by its own reference's letters, and sorted pairs (state, letter) where the
table would take more than TABLE cells, as with thousands of letters.

Defined cases: null text or text without any letter gives `und` with score 0; a letter that a reference
lacks opens a phrase there; ties go to the language first by name; without labelled documents every text is `und`; repeated rows
are predicted alike; extra columns are ignored. Texts are parsed whole, in segments of SEGMENT letters.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import fold, own, ship_package

REFERENCE, DOCUMENTS = 40_000, 400
TABLE = 8_000_000
SEGMENT = 1_024
BATCH_CHARS = 4_000_000
FOLDS = 5
UNKNOWN = "und"


class Moves:
    """Transitions of an automaton: from states by letters to states, 0 as target = none, state 0 is the root."""

    def __init__(self, rows: list[dict[int, int]]):
        used = sorted({c for row in rows for c in row})
        own = np.zeros(max(used, default=0) + 1, np.int64)  # its own numbers of letters, 0: not in this reference
        own[used] = np.arange(1, len(used) + 1)
        self.own, self.width = own, len(used) + 1
        pairs = sorted((s * self.width + int(own[c]), t) for s, row in enumerate(rows) for c, t in row.items())
        keys = np.fromiter((k for k, _ in pairs), np.int64, len(pairs))
        targets = np.fromiter((t for _, t in pairs), np.int32, len(pairs))
        self.dense = len(rows) * self.width <= TABLE
        if self.dense:
            self.table = np.zeros(len(rows) * self.width, np.int32)
            self.table[keys] = targets
        else:
            self.keys, self.targets = np.append(keys, 2**62), np.append(targets, 0)

    def letters(self, codes: np.ndarray) -> np.ndarray:
        """The reference's own numbers of a text's codes."""
        return np.where(codes < len(self.own), self.own[np.minimum(codes, len(self.own) - 1)], 0)

    def after(self, states: np.ndarray, letters: np.ndarray) -> np.ndarray:
        at = states.astype(np.int64) * self.width + letters
        if self.dense:
            return self.table[at]
        place = np.searchsorted(self.keys, at)
        return np.where(self.keys[place] == at, self.targets[place], 0).astype(np.int32)


def suffix_automaton(codes: list[int]) -> list[dict[int, int]]:
    """Transitions of the suffix automaton of a code sequence: a dict a state, state 0 is the root."""
    moves: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in codes:
        state = len(moves)
        moves.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in moves[p]:
            moves[p][c] = state
            p = link[p]
        if p >= 0:
            q = moves[p][c]
            if length[q] == length[p] + 1:
                link[state] = q
            else:
                clone = len(moves)
                moves.append(dict(moves[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and moves[p].get(c) == q:
                    moves[p][c] = clone
                    p = link[p]
                link[q] = link[state] = clone
        last = state
    return moves


class CrossParser:
    """Automata of several references over one alphabet. Code 0: a letter that no reference has; 1: no letter."""

    def __init__(self, references: dict[str, str]):
        self.languages = sorted(references)
        texts = {k: references[k].lower() for k in self.languages}
        letters = sorted({c for t in texts.values() for c in t if c.isalpha()})
        self.width = len(letters) + 2
        alpha = np.fromiter((chr(i).isalpha() if not 0xD800 <= i < 0xE000 else False for i in range(0x110000)), bool, 0x110000)
        self.codes = np.where(alpha, 0, 1).astype(np.int32)
        self.codes[[ord(c) for c in letters]] = np.arange(2, self.width)
        self.moves, self.bits = [], []
        for k in self.languages:
            codes = self.encode(texts[k])
            self.moves.append(Moves(suffix_automaton(codes.tolist())))
            self.bits.append(np.log2(max(len(codes), 2)))

    def encode(self, text: str) -> np.ndarray:
        """Codes of a lower-cased text: letters, and one separator for each run of anything else between letters."""
        c = self.codes[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
        keep = np.ones(len(c), bool)
        keep[1:] = (c[1:] != 1) | (c[:-1] != 1)
        return c[keep]

    def phrases(self, sequences: list[np.ndarray]) -> np.ndarray:
        """Phrases of each sequence (rows) against each reference (columns)."""
        owner, starts, lengths, at = [], [], [], 0
        for i, s in enumerate(sequences):
            for a in range(0, len(s), SEGMENT):
                owner.append(i)
                starts.append(at + a)
                lengths.append(min(SEGMENT, len(s) - a))
            at += len(s)
        out = np.zeros((len(sequences), len(self.languages)), np.int64)
        if not owner:
            return out
        every = np.concatenate(sequences)
        order = np.argsort(-np.array(lengths), kind="stable")
        starts, lengths, owner = np.array(starts)[order], np.array(lengths)[order], np.array(owner)[order]
        steps = int(lengths[0])
        active = np.searchsorted(-lengths, -np.arange(steps), side="left")
        for j, moves in enumerate(self.moves):
            letters = moves.letters(every)
            state, count = np.zeros(len(starts), np.int32), np.ones(len(starts), np.int64)
            for t in range(steps):
                n = active[t]
                c = letters[starts[:n] + t]
                to = moves.after(state[:n], c)
                stuck = np.flatnonzero(to == 0)
                if len(stuck):
                    if t:
                        count[stuck] += 1
                    to[stuck] = moves.after(np.zeros(len(stuck), np.int32), c[stuck])
                state[:n] = to
            out[:, j] = np.bincount(owner, weights=count, minlength=len(sequences)).astype(np.int64)
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        sequences = [self.encode(t.lower()) if t else np.empty(0, np.int32) for t in texts]
        lettered = np.array([bool((s != 1).any()) for s in sequences], bool)
        if not self.languages:
            return [UNKNOWN] * len(texts), [0.0] * len(texts)
        cost = self.phrases(sequences) * np.array(self.bits)
        best = cost.argmin(axis=1)
        if len(self.languages) > 1:
            two = np.sort(cost, axis=1)[:, :2]
            score = two[:, 1] / np.maximum(two.sum(axis=1), 1e-9)
        else:
            score = np.ones(len(texts))
        return [self.languages[b] if ok else UNKNOWN for b, ok in zip(best, lettered)], [float(x) if ok else 0.0 for x, ok in zip(score, lettered)]


_parsers: dict[tuple, CrossParser] = {}


def _parser(references: dict[str, str]) -> CrossParser:
    key = tuple(sorted(references.items()))
    if key not in _parsers:
        _parsers.clear()
        _parsers[key] = CrossParser(references)
    return _parsers[key]


def learn_references(docs: DataFrame) -> dict[str, str]:
    """Language -> reference text, from text and lang of the documents that are not held out."""
    rows = own(docs, "doc_id", "text", "lang").where(F.col("lang").isNotNull() & (fold(F.col("doc_id"), FOLDS) != 0))
    lettered = rows.where(F.col("text").rlike(r"\p{L}")).select("lang", F.xxhash64("text").alias("h"), "text")
    # Copies count once: they share the hash. What is gathered by language are hashes alone, cut to the first ones.
    order = Window.partitionBy("lang").orderBy("h")
    first = lettered.select("lang", "h").distinct().withColumn("k", F.row_number().over(order)).where(F.col("k") <= DOCUMENTS)
    chosen = F.broadcast(first.select(F.col("lang").alias("l_"), F.col("h").alias("h_"), "k"))  # DOCUMENTS a language
    # A text beyond the bound can't add more than the bound.
    texts = lettered.join(chosen, F.expr("lang = l_ AND h = h_")).groupBy("lang", "k").agg(F.min(F.substring("text", 1, REFERENCE)).alias("text"))
    earlier = Window.partitionBy("lang").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    taken = texts.withColumn("before", F.coalesce(F.sum(F.length("text") + 1).over(earlier), F.lit(0))).where(F.col("before") < REFERENCE)
    found: dict[str, str] = {}
    for r in taken.orderBy("lang", "k").select("lang", F.expr(f"substring(text, 1, {REFERENCE} - before)").alias("text")).collect():  # REFERENCE characters a language
        found[r.lang] = found.get(r.lang, "") + " " + r.text
    return {k: v for k, v in found.items() if any(c.isalpha() for c in v)}


PREDICTED = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])


def _predict(references: dict[str, str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parser = _parser(references)
        for batch in batches:
            ids, texts = batch.column(0).cast(pa.int64()), batch.column(1).to_pylist()
            start, total = 0, 0
            for i in range(len(texts) + 1):
                n = len(texts[i] or "") if i < len(texts) else 0
                if i == len(texts) or (i > start and total + n > BATCH_CHARS):
                    if i > start:
                        lang, score = parser.predict(texts[start:i])
                        yield pa.record_batch([ids.slice(start, i - start), pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=PREDICTED.fieldNames())
                    start, total = i, 0
                total += n

    return run


def identify_languages(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    ship_package(docs.sparkSession)
    found = own(docs, "doc_id", "text").mapInArrow(_predict(learn_references(docs)), PREDICTED)
    return found.select("doc_id", (fold(F.col("doc_id"), FOLDS) == 0).alias("held_out"), "lang_pred", "score")
