"""Toxicity by a subsequence string kernel, Nyström landmarks and a linear support vector machine.

The kernel compares tokens: a feature is three letters in order, with up to GAP other characters between neighbours,
and counts DECAY for every character skipped; so an insult with an inserted or a dropped character keeps most of its
features. A sentence is as toxic as its worst token, a document as its worst sentence. As only documents are
labelled, the machine learns which token makes a labelled text toxic: it starts with tokens that toxic texts share
and clean ones lack, and then alternates between fitting and choosing the worst token of each toxic text, with the
clean texts' nearest tokens as further negatives.

The machine's weights in the space of the landmarks are folded back into one weight per feature, so that scoring a
token is a sum over its features; every distinct token of a batch is scored once. Scores are calibrated to
probabilities on the training texts.

Fitting uses a bounded sample: SAMPLE labelled documents of each class, those with the smallest hash of the id.

Defined cases: null and empty texts and texts without any token of three characters get the score of the lowest
margin; without labelled texts of both classes every score is the share of label 1 (0 without any label), held below
the threshold; repeated rows score alike; extra columns are ignored. Runs of single characters are read as one more
token, and tokens above LONG characters in overlapping pieces.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import fold, own, ship_package
from rangesieve.llm.rule_quality import labelled_sample

SAMPLE = 2_000
FOLDS, HELD = 3, 1
THRESHOLD = 0.7
GAP, DECAY = 2, 0.5
LANDMARKS, ROUNDS, RIDGE = 96, 3, 1e-2
LONG, PIECE = 40, 24
LOWEST = -3.0
_SIDE = 64
_EDGES = ".,;:!?\"'()[]{}<>*#%&$|~^=+-_/\\…«»„“”‚‘’"
_SPACED = re.compile(r"(?:(?<=\s)|^)(?:\S[\s.,\-_*]+){2,}\S(?=\s|$)")


def _letter_codes() -> np.ndarray:
    """a-z: 1-26; other letters: 27-62; anything else: 63; 0 marks a word's two ends."""
    codes = np.full(0x110000, 63, np.int64)
    for i in range(0x3000):
        if chr(i).isalpha():
            codes[i] = 27 + i * 7 % 36
    codes[0x3000:] = 27 + np.arange(0x3000, 0x110000) * 7 % 36
    codes[ord("a") : ord("z") + 1] = np.arange(1, 27)
    codes[0] = 0
    return codes


_CODES = _letter_codes()


def tokens_of(text: str | None) -> set[str]:
    """Distinct raw tokens of a text, with joined runs of single characters."""
    if not text:
        return set()
    low = text.lower()
    found = set(low.split())
    if any(len(t.strip(_EDGES)) == 1 for t in found):
        found.update("".join(c for c in m if not c.isspace() and c not in _EDGES) for m in _SPACED.findall(low))
    return found


def features(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Kernel features of words: (word number, feature, weight) with one row a pair, and each word's norm."""
    words = [f"\0{w}\0" if w else "" for w in words]
    lengths = np.array([len(w) for w in words], np.int64)
    codes = _CODES[np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)]
    word = np.repeat(np.arange(len(words)), lengths)
    keys, weights = [], []
    for d in range(1, GAP + 2):
        for e in range(1, GAP + 2):
            m = len(codes) - d - e
            if m <= 0:
                continue
            ok = word[:m] == word[d + e :]
            key = ((word[:m] * _SIDE + codes[:m]) * _SIDE + codes[d : d + m]) * _SIDE + codes[d + e :]
            keys.append(key[ok])
            weights.append(np.full(int(ok.sum()), DECAY ** (d + e - 2)))
    norms = np.zeros(len(words))
    if not keys or not sum(map(len, keys)):
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0), norms
    key, weight = np.concatenate(keys), np.concatenate(weights)
    order = np.argsort(key, kind="stable")
    key, weight = key[order], weight[order]
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    weight, key = np.add.reduceat(weight, first), key[first]
    number = key // _SIDE**3
    norms = np.sqrt(np.bincount(number, weights=weight**2, minlength=len(words)))
    return number, key % _SIDE**3, weight, norms


class Space:
    """Normalised feature vectors of a few words as rows of a matrix over the features that they have."""

    def __init__(self, words: list[str]):
        number, feature, weight, norms = features(words)
        self.features = np.unique(feature)
        self.number_of = np.full(_SIDE**3, -1, np.int32)
        self.number_of[self.features] = np.arange(len(self.features))
        self.unit = np.zeros((len(words), len(self.features)), np.float32)
        self.unit[number, self.number_of[feature]] = weight / norms[number]

    def kernel(self, words: list[str]) -> np.ndarray:
        """Normalised kernel of words with the space's words, by columns."""
        out = np.zeros((len(words), len(self.unit)), np.float32)
        columns = np.ascontiguousarray(self.unit.T)
        for a in range(0, len(words), 500):
            number, feature, weight, norms = features(words[a : a + 500])
            at = self.number_of[feature] if len(feature) else np.empty(0, np.int32)
            some = at >= 0
            number, at, weight = number[some], at[some], weight[some]
            if not len(number):
                continue
            starts = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]]))
            out[a + number[starts]] = np.add.reduceat(columns[at] * (weight / norms[number])[:, None], starts).astype(np.float32)
        return out

    def spread(self, weights: np.ndarray) -> np.ndarray:
        """One weight per feature of the whole feature space."""
        out = np.zeros(_SIDE**3, np.float32)
        out[self.features] = weights @ self.unit
        return out


@dataclass
class Model:
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def margins(self, words: list[str]) -> np.ndarray:
        """Margin of each stripped word; LOWEST for words without features."""
        out = np.full(len(words), LOWEST)
        number, feature, weight, norms = features(words)
        some = norms > 0
        total = np.bincount(number, weights=weight * self.weights[feature], minlength=len(words))
        out[some] = total[some] / norms[some] + self.bias
        return np.maximum(out, LOWEST)

    def probability(self, margin: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * np.asarray(margin) + self.shift, -60, 60)))


def _pieces(token: str) -> list[str]:
    w = token.strip(_EDGES)
    return [w] if len(w) <= LONG else [w[i : i + PIECE] for i in range(0, len(w) - PIECE // 2, PIECE // 2)]


class TokenMargins(dict):
    """Raw token -> margin, filled for many tokens at once."""

    def __init__(self, model: Model, most: int = 600_000):
        super().__init__()
        self.model, self.most = model, most

    def learn(self, tokens: set[str]) -> None:
        fresh = [t for t in tokens if t not in self]
        if len(self) + len(fresh) > self.most:
            self.clear()
            fresh = list(tokens)
        for a in range(0, len(fresh), 4_000):
            part = fresh[a : a + 4_000]
            pieces = [_pieces(t) for t in part]
            flat = self.model.margins([p for ps in pieces for p in ps])
            at = np.concatenate([[0], np.cumsum([len(p) for p in pieces])[:-1]])
            self.update(zip(part, np.maximum.reduceat(flat, at).tolist()))


#: A token that shares nothing with any landmark is clean: its margin is this fixed bias.
BIAS = -1.0


def _svm(z: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float | None = None, steps: int = 600) -> np.ndarray:
    """Linear support vector machine with squared hinge loss and fixed bias, by accelerated gradient."""
    ridge = RIDGE if ridge is None else ridge
    z, weight = z.astype(np.float64), weight / weight.sum()
    step = 1 / (2 * np.linalg.eigvalsh((z * weight[:, None]).T @ z)[-1] + ridge)
    w = v = np.zeros(z.shape[1])
    for t in range(steps):
        slack = np.maximum(0, 1 - y * (z @ v + BIAS))
        u = v - step * (-2 * z.T @ (weight * y * slack) + ridge * v)
        v = u + t / (t + 3) * (u - w)
        w = u
    return w


def _choose_landmarks(words: list[str], most: int) -> list[str]:
    """In the given order, words that are not nearly the same as one chosen before."""
    words = [w for w in words[: 5 * most] if w]
    if not words:
        return []
    space = Space(words)
    chosen: list[int] = []
    for i, row in enumerate(space.unit):
        if row.any() and (not chosen or (space.unit[chosen] @ row).max() < 0.85):
            chosen.append(i)
            if len(chosen) >= most:
                break
    return [words[i] for i in chosen]


def fit(texts: list[str], labels: list[int], seed: int = 5) -> Model:
    """A model from labelled texts."""
    share = float(np.mean(labels)) if labels else 0.0
    flat = Model(np.zeros(_SIDE**3, np.float32), 0.0, 0.0, float(np.log(np.clip(share, 0.01, 0.6) / (1 - np.clip(share, 0.01, 0.6)))))
    if len(set(labels)) < 2:
        return flat
    toxic: list[set[str]] = []
    clean_words: Counter = Counter()
    toxic_words: Counter = Counter()
    seen: set[int] = set()
    for text, label in zip(texts, labels):
        if hash(text) in seen:  # copies say nothing new
            continue
        seen.add(hash(text))
        words = {p for t in tokens_of(text) for p in _pieces(t) if len(p) >= 3}
        (toxic_words if label else clean_words).update(words)
        if label:
            toxic.append(words)
    only = {w: n for w, n in toxic_words.items() if w not in clean_words}
    by_count = sorted(only, key=lambda w: (-only[w], w))
    least = max(2, round(0.004 * len(toxic)))
    good = {w for w in by_count if only[w] >= max(least, 3)}
    if len(good) < 5:
        good = set(by_count[:20])
    if not good or not clean_words:
        return flat
    rng = np.random.default_rng(seed)
    clean_list = sorted(clean_words, key=lambda w: (-clean_words[w], w))
    bad = set(clean_list[:1500]) | {clean_list[i] for i in rng.choice(len(clean_list), min(4_000, len(clean_list)), replace=False)}
    model, hard = flat, []
    for turn in range(ROUNDS):
        marks = _choose_landmarks(sorted(good, key=lambda w: (-only.get(w, 0), w)), LANDMARKS)
        marks += _choose_landmarks(hard + sorted(bad, key=lambda w: (-clean_words[w], w)), LANDMARKS)
        space = Space(marks)
        value, vector = np.linalg.eigh((space.unit @ space.unit.T).astype(np.float64))
        some = value > 1e-6 * value[-1]
        root = vector[:, some] / np.sqrt(value[some])
        words = sorted(good) + sorted(bad)
        z = space.kernel(words) @ root
        y = np.array([1.0] * len(good) + [-1.0] * len(bad))
        # Tokens weigh by how many texts share them, and the two classes alike.
        share = np.array([float(only.get(t, 1)) for t in sorted(good)] + [1 + np.log(clean_words[t]) for t in sorted(bad)])
        share[y > 0] *= share[y < 0].sum() / share[y > 0].sum()
        w = _svm(z, y, share)
        model = Model(space.spread(root @ w), BIAS, 1.0, 0.0)
        if turn == ROUNDS - 1:
            break
        margins = TokenMargins(model)
        margins.learn(set(clean_words))
        # The clean texts' worst tokens are further negatives.
        hard = sorted(clean_words, key=lambda t: (-margins[t], t))[:1_500]
        bad |= set(hard)
        # A toxic text that no shared token explains offers its worst token, if no clean text has that.
        margins.learn(set(only))
        new = set()
        for held in toxic:
            if not held & good:
                mine = [t for t in held if t in only]
                worst = max(mine, key=lambda t: (margins[t], only[t], t), default=None)
                if worst and margins[worst] > 0:
                    new.add(worst)
        good |= new
    margins = TokenMargins(model)
    tops = []
    for text in texts:
        found = tokens_of(text)
        margins.learn(found)
        tops.append(max((margins[t] for t in found), default=LOWEST))
    top, lab = np.array(tops), np.array(labels, float)
    # The cut that errs least on the training texts, in the middle of its gap; probability 1/2 there.
    order = np.argsort(top, kind="stable")
    v, l = top[order], lab[order]
    errors = np.concatenate([[0], np.cumsum(l)]) + (len(l) - l.sum()) - np.concatenate([[0], np.cumsum(1 - l)])
    edges = np.concatenate([[v[0] - 1], (v[1:] + v[:-1]) / 2, [v[-1] + 1]])
    valid = np.concatenate([[True], v[1:] > v[:-1], [True]])
    best = np.flatnonzero(valid & (errors == errors[valid].min()))
    gap = [abs((v[min(i, len(v) - 1)]) - v[max(i - 1, 0)]) for i in best]
    cut = float(edges[best[int(np.argmax(gap))]])
    slope = 6.0
    return Model(model.weights, model.bias, slope, float(-slope * cut + np.log(THRESHOLD / (1 - THRESHOLD))))


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> Model:
    parts = [labelled_sample(labels.where(F.col("toxic") == k), "toxic", FOLDS, HELD, most) for k in (0, 1)]
    sample = parts[0].union(parts[1])
    # Bounded by 2 * most rows of two numbers.
    rows = own(docs, "doc_id", "text").where("text is not null").join(F.broadcast(sample), F.col("doc_id") == F.col("label_id")).select("label_id", "text", "label")
    got = sorted((r.label_id, r.label, r.text) for r in rows.limit(4 * most).collect())
    return fit([t for _, _, t in got], [k for _, k, _ in got])


SCORED = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("score", T.DoubleType())])


def _score(held):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        margins = TokenMargins(model)
        for batch in batches:
            ids, texts = batch.column(0).cast(pa.int64()), batch.column(1).to_pylist()
            for a in range(0, len(texts), 200):
                found = [tokens_of(t) for t in texts[a : a + 200]]
                margins.learn(set().union(*found))
                top = [max(map(margins.__getitem__, f), default=LOWEST) for f in found]
                yield pa.record_batch([ids.slice(a, len(found)), pa.array(model.probability(np.array(top)), pa.float64())], names=SCORED.fieldNames())

    return run


def score_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    spark = docs.sparkSession
    ship_package(spark)
    model = spark.sparkContext.broadcast(train(docs, labels))  # one weight per feature: 1 MB
    scored = own(docs, "doc_id", "text").mapInArrow(_score(model), SCORED)
    return scored.select("doc_id", (fold(F.col("doc_id"), FOLDS) == HELD).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
