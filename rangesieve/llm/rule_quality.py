"""Quality by a sparse rule ensemble over text statistics.

Statistics are Spark columns. On a bounded sample of labelled documents, small boosted trees are grown; each path from
a root to a node is a conjunctive rule. A lasso logistic regression over the rules (and the clipped statistics) keeps
a few of them, and the result is compiled into one Spark column: scoring is a projection that follows the scan.

Defined cases: null text counts as empty and gets the score of all-zero statistics; without labelled documents of both
classes every score is the share of label 1 (0.5 without any label); documents without label are scored like others;
repeated rows are scored alike; extra columns are ignored.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rangesieve.llm.common import carry, fold, own, restore

#: Labelled documents used for fitting, at most: those with the smallest hash of the id.
SAMPLE = 6_000
TREES, DEPTH, LEAF, RATE, LASSO = 24, 3, 8, 0.3, 2e-3
THRESHOLD = 0.3
FOLDS = 5

_SYMBOLS = r"[*#$%&|!{}<>\\^~=+@_\[\]]"


def statistics(text: Column) -> dict[str, Column]:
    """Named statistics of a text; every one is 0 for the empty text."""
    t = F.coalesce(text, F.lit(""))
    chars = F.greatest(F.length(t), F.lit(1))
    return {"chars": F.length(t), "words": F.regexp_count(t, F.lit(r"\S+")), "symbols": F.regexp_count(t, F.lit(_SYMBOLS)) / chars, "capitals": F.regexp_count(t, F.lit(r"\p{Lu}")) / chars, "digits": F.regexp_count(t, F.lit("[0-9]")) / chars, "stops": F.regexp_count(t, F.lit("[.,;:?]")) / chars, "lines": F.regexp_count(t, F.lit("\n")), "distinct": F.size(F.array_distinct(F.split(F.lower(t), r"\s+"))), "bars": F.regexp_count(t, F.lit(r"\|")) / chars}


DERIVED = {
    "word_length": lambda c: c["chars"] / F.greatest(c["words"], F.lit(1)),
    # Log over log: the share of distinct words falls with length alone, this hardly does.
    "variety": lambda c: F.when(c["words"] > 0, F.log1p(c["distinct"]) / F.log1p(c["words"])).otherwise(F.lit(0)),
    "stops_a_word": lambda c: c["stops"] * c["chars"] / F.greatest(c["words"], F.lit(1)),
    "words_a_line": lambda c: c["words"] / (c["lines"] + 1),
    "symbols_a_word": lambda c: c["symbols"] * c["chars"] / F.greatest(c["words"], F.lit(1)),
    "capitals_a_word": lambda c: c["capitals"] * c["chars"] / F.greatest(c["words"], F.lit(1)),
}
NAMES = ["chars", "words", "symbols", "capitals", "digits", "stops", "lines", "bars", *DERIVED]


def with_statistics(df: DataFrame, text: str = "text") -> DataFrame:
    """Add one struct column `stats` of doubles."""
    base = statistics(F.col(text))
    first = df.withColumn("_base", F.struct(*[v.cast("double").alias(k) for k, v in base.items()]))
    held = {k: F.col(f"_base.{k}") for k in base}
    both = held | {k: f(held) for k, f in DERIVED.items()}
    return first.withColumn("stats", F.struct(*[both[k].cast("double").alias(k) for k in NAMES])).drop("_base")


@dataclass
class Model:
    """score = sigmoid(bias + sum of rule weights); a rule is a list of (statistic, '<=' or '>', threshold)."""

    bias: float = 0.0
    rules: list[tuple[list[tuple[str, str, float]], float]] = field(default_factory=list)
    linear: list[tuple[str, float, float, float]] = field(default_factory=list)  # statistic, low, high, weight

    def column(self, stats: str = "stats") -> Column:
        total = F.lit(float(self.bias))
        for conditions, weight in self.rules:
            test = F.lit(True)
            for name, op, at in conditions:
                c = F.col(f"{stats}.{name}")
                test = test & ((c <= at) if op == "<=" else (c > at))
            total = total + F.when(test, F.lit(float(weight))).otherwise(F.lit(0.0))
        for name, low, high, weight in self.linear:
            total = total + F.lit(float(weight)) * F.greatest(F.least(F.col(f"{stats}.{name}"), F.lit(float(high))), F.lit(float(low)))
        return 1 / (1 + F.exp(-total))

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.bias)
        for conditions, weight in self.rules:
            total += weight * _holds(conditions, x)
        for name, low, high, weight in self.linear:
            total += weight * np.clip(x[:, NAMES.index(name)], low, high)
        return 1 / (1 + np.exp(-np.clip(total, -500, 500)))

    def dump(self) -> str:
        return json.dumps([self.bias, self.rules, self.linear])


def _holds(conditions, x: np.ndarray) -> np.ndarray:
    test = np.ones(len(x), dtype=bool)
    for name, op, at in conditions:
        c = x[:, NAMES.index(name)]
        test &= (c <= at) if op == "<=" else (c > at)
    return test


def _best_split(x: np.ndarray, r: np.ndarray):
    """Statistic and threshold with the largest drop of squared error of the residual r."""
    n, total = len(r), r.sum()
    best = (1e-9, -1, 0.0)
    for j in range(x.shape[1]):
        order = np.argsort(x[:, j], kind="stable")
        v, s = x[order, j], np.cumsum(r[order])
        k = np.flatnonzero(v[1:] > v[:-1])
        k = k[(k >= LEAF - 1) & (k < n - LEAF)]
        if len(k):
            left = s[k]
            gain = left**2 / (k + 1) + (total - left) ** 2 / (n - k - 1) - total**2 / n
            i = int(gain.argmax())
            if gain[i] > best[0]:
                best = (float(gain[i]), j, float((v[k[i]] + v[k[i] + 1]) / 2))
    return best


def _grow(x, r, rows, path, depth, rules, fit):
    fit[rows] = r[rows].mean()
    if depth == 0 or len(rows) < 2 * LEAF:
        return
    _, j, at = _best_split(x[rows], r[rows])
    if j < 0:
        return
    low = x[rows, j] <= at
    for op, part in (("<=", rows[low]), (">", rows[~low])):
        own_path = [*path, (NAMES[j], op, at)]
        rules.append(own_path)
        _grow(x, r, part, own_path, depth - 1, rules, fit)


def _lasso(z: np.ndarray, y: np.ndarray, lasso: float, steps: int = 1500) -> tuple[np.ndarray, float]:
    """L1-penalised logistic regression by accelerated proximal gradient; the bias is free."""
    n, d = z.shape
    full = np.hstack([z, np.ones((n, 1))])
    step = 4 * n / max(np.linalg.norm(full, 2) ** 2, 1e-9)
    w = v = np.zeros(d + 1)
    t = 1.0
    for _ in range(steps):
        g = full.T @ (1 / (1 + np.exp(-np.clip(full @ v, -50, 50))) - y) / n
        u = v - step * g
        u[:-1] = np.sign(u[:-1]) * np.maximum(np.abs(u[:-1]) - step * lasso, 0)
        t_next = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v = u + (t - 1) / t_next * (u - w)
        if np.abs(u - w).max() < 1e-7:
            w = u
            break
        w, t = u, t_next
    return w[:-1], float(w[-1])


def fit(x: np.ndarray, y: np.ndarray, seed: int = 7) -> Model:
    """A model from statistics (rows of NAMES) and labels 0/1."""
    share = float(y.mean()) if len(y) else 0.5
    if len(set(y.tolist())) < 2:
        share = min(max(share, 0.01), 0.99)
        return Model(bias=float(np.log(share / (1 - share))))
    rng = np.random.default_rng(seed)
    score = np.full(len(y), np.log(share / (1 - share)))
    paths: list = []
    for _ in range(TREES):
        residual = y - 1 / (1 + np.exp(-score))
        rows = np.sort(rng.choice(len(y), size=max(2 * LEAF, len(y) // 2), replace=len(y) < 4 * LEAF))
        grown: list = []
        _grow(x, residual, rows, [], DEPTH, grown, np.zeros(len(y)))
        leaves = [p for p in grown if not any(q[: len(p)] == p and len(q) > len(p) for q in grown)]
        for p in leaves:
            held = _holds(p, x)
            score[held] += RATE * 4 * residual[held].mean()
        paths += grown
    unique: dict = {}
    for p in paths:
        held = _holds(p, x)
        if 0.005 < held.mean() < 0.995:
            unique.setdefault(held.tobytes(), (p, held))
    rules = list(unique.values())
    low, high = np.quantile(x, 0.02, axis=0), np.quantile(x, 0.98, axis=0)
    spread = np.maximum(high - low, 1e-12)
    linear = (np.clip(x, low, high) - low) / spread
    z = np.hstack([np.array([h for _, h in rules], dtype=float).reshape(len(rules), len(y)).T, linear])
    w, bias = _lasso(z, y.astype(float), LASSO)
    model = Model(bias=bias)
    model.rules = [(p, float(k)) for (p, _), k in zip(rules, w) if k]
    for j, k in enumerate(w[len(rules) :]):
        if k:
            model.linear.append((NAMES[j], float(low[j]), float(high[j]), float(k / spread[j])))
            model.bias -= float(k * low[j] / spread[j])
    return model


def labelled_sample(labels: DataFrame, label: str, parts: int, held: int, most: int) -> DataFrame:
    """At most `most` labelled ids outside the held-out fold, by the smallest hash of the id: (label_id, label)."""
    rows = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull() & (fold(F.col("doc_id"), parts) != held))
    return rows.select(F.col("doc_id").cast("long").alias("label_id"), F.col(label).cast("int").alias("label")).orderBy(F.xxhash64("label_id"), "label_id", "label").limit(most)


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> Model:
    sample = labelled_sample(labels, "quality", FOLDS, 0, most)
    # Bounded by `most` rows of two numbers.
    rows = own(docs, "doc_id", "text").join(F.broadcast(sample), F.col("doc_id") == F.col("label_id"))
    got = with_statistics(rows.select("label_id", "text", "label")).select("label_id", "stats", "label").toPandas().sort_values(["label_id", "label"])
    x = np.array([list(s.asDict().values()) if hasattr(s, "asDict") else list(s.values()) for s in got.stats], dtype=float).reshape(len(got), len(NAMES))
    return fit(x, got.label.to_numpy(int))


def score_quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    model = train(docs, labels)
    scored = with_statistics(own(docs, "doc_id", "text")).select("doc_id", (fold(F.col("doc_id"), FOLDS) == 0).alias("held_out"), model.column().alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that the classifier accepts, all their columns."""
    model = train(docs, labels)
    # A filter over plain columns is pushed below their projection, and each rule would compute its statistics anew;
    # it isn't pushed below a projection with a row number that it reads.
    scored = with_statistics(carry(docs, "text")).withColumn("_row", F.monotonically_increasing_id())
    return scored.where((model.column() >= THRESHOLD) & (F.col("_row") >= 0)).transform(restore)
