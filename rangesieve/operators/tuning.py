"""Tuning of the baselines on a sample of empty ranges. A sample is summed up by level and width, in at most 64 * 64 rows;
all else is arithmetic on the driver."""

from __future__ import annotations

from math import exp, log

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK
from rangesieve.functions.models import space_bucket
from rangesieve.operators.families import sample_gaps
from rangesieve.operators.filters import Parted, dyadic_cover, neighbours
from rangesieve.operators.order import questions

Alike = list[tuple[int, int, int]]


def alike(keys: DataFrame, sample: DataFrame, n: int | None = None) -> Alike:
    """(level, width, c): sample ranges by the level that tells them from keys and the digits of b - a."""
    gaps = sample_gaps(keys, sample.where("a <= b").select("a", "b"), n).groupBy("level", F.expr(SPARK.bit_length("b - a")).alias("width")).agg(F.count("*").alias("c"))
    return sorted((r.level, r.width, r.c) for r in gaps.collect())


def tpb_grid(ones: dict[int, int], sample: Alike, bits: float, u: int, step: int = 2) -> list[tuple[int, int, float]]:
    """(shift1, shift2, fpr): expected rate on the sample of every split of the budget between exact prefixes above
    shift1 and a Bloom filter of those above shift2. shift1 = log2 u is the Bloom filter alone, shift2 = shift1 the
    prefixes alone. ones: occupied prefixes by shift. A width counts as the largest of its digits."""
    w, n, rows = u.bit_length() - 1, ones.get(0, 0), []
    total = sum(c for _, _, c in sample) or 1
    for s1 in range(0, w + 1, step):
        trie = space_bucket(ones[s1], u, 2**s1) if s1 < w else 0.0
        for s2 in range(0, s1 + 1, step):
            left = bits * n - trie
            if left < 0 or s2 == w:
                continue
            p = 1.0 if s2 == s1 else exp(-left / max(ones[s2], 1) * log(2) ** 2)
            rate = sum(c * (1.0 if level <= s2 else 1 - (1 - p) ** ((2**width - 1 >> s2) + 1) if level <= s1 else 0.0) for level, width, c in sample)
            rows.append((s1, s2, rate / total))
    return rows or [(w, 0, 1.0)]


def tpb_tune(ones: dict[int, int], sample: Alike, bits: float, u: int, step: int = 2) -> tuple[int, int]:
    best = min(tpb_grid(ones, sample, bits, u, step), key=lambda r: (round(r[2], 9), r[0], r[1]))
    return best[0], best[1]


def ltb_tune(ones: dict[int, int], sample: Alike, words: int, height: int, hashes: int, u: int) -> int:
    """Start level of the local trees with the least expected rate on the sample: the sampled variant."""
    w, total = u.bit_length() - 1, sum(c for _, _, c in sample) or 1

    def expected(shift: int) -> float:
        nodes = sum(ones.get(min(shift + i, 62), 1) for i in range(height + 1))
        fill = 1 - exp(-nodes / (words * 2 ** (height + 1)))
        sure = sum(c for level, _, c in sample if level <= shift) / total
        return round(sure + (1 - sure) * min(1.0, 2 * height * fill**hashes), 9)

    return min(range(max(1, w - height)), key=lambda s: (expected(s), s))


def ltb_spaced(keys: DataFrame, height: int, n: int | None = None) -> int:
    """Start level from the keys alone, the spaced variant: the trees' roots lie where half of the neighbouring keys have
    parted, as the bits above that tell few keys apart."""
    parted = {r.bits: r.c for r in neighbours(keys, n).where("prev is not null").groupBy(F.expr(SPARK.bit_length("k ^ prev")).alias("bits")).agg(F.count("*").alias("c")).collect()}  # 63 rows
    seen, half = 0, sum(parted.values()) / 2
    for bits in sorted(parted):
        seen += parted[bits]
        if seen >= half:
            return max(0, bits - height)
    return 0


def spaced_of(found: Parted, height: int) -> int:
    """`ltb_spaced` from where keys part."""
    bits = sorted(p for p, _ in found if p < 64)
    seen, half = 0, sum(c for (p, _), c in found.items() if p < 64) / 2
    for p in dict.fromkeys(bits):
        seen += sum(c for (q, _), c in found.items() if q == p)
        if seen >= half:
            return max(0, p - height)
    return 0


def plb_tune(sample: DataFrame, top: int, hashes: int) -> list[int]:
    """Hash functions for each level, leaves first: levels down from the highest one that covers of the sample touch;
    one function each above the leaves, and the functions of levels never used go to the leaves."""
    used = {r.level for r in dyadic_cover(questions(sample), top).select("level").distinct().collect()}  # at most top + 1 rows
    high = max(used, default=0)
    return [hashes + (top - high)] + [1] * high
