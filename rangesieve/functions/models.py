"""Cost and accuracy models: space in bits, error bounds, crossovers, recommendations. Plain numbers."""

from __future__ import annotations

from math import log2


def error_bound(length: int, bits: float) -> float:
    """False positive bound of the locality-hash filter with a budget in bits per key."""
    return min(1.0, length / 2 ** (bits - 2))


def prefix_search_bound(length: int, bits: float) -> float:
    """The same for the heavier index, which spends one more bit per key."""
    return min(1.0, length / 2 ** (bits - 3))


def space_locality_hash(n, length, eps):
    return n * log2(length / eps) + 2 * n


def space_prefix_search(n, length, eps):
    return n * log2(length / eps) + 3 * n


def space_pointwise(n, length, eps):
    return n * log2(length / eps)


def space_per_level(n, length, eps):
    return 1.44 * n * log2(length / eps)


def space_bucket(t, u, s):
    return t * (log2(u / (t * s)) + 2) if t else 0.0


def space_truncated_trie(n, suffix_bits, inner_nodes):
    return (10 + suffix_bits) * n + 10 * inner_nodes


def space_learned_bitmap(n, k):
    return n * log2(k) + 2.4 * n


def space_lossless(n, u):
    return n * (log2(u / n) + 2)


def space_bound(n, length, eps):
    """Leading term of the lower bound."""
    return n * log2(length / eps)


def learned_bitmap_error(u, n, length, k):
    """For uniform keys and queries."""
    return (u / k) / (u - n * length)


def crossover_per_level() -> float:
    """L / eps below which the per-level Bloom filter is smaller than the locality-hash filter."""
    return 2 ** (2 / 0.44)


def net_cost(error_rate: float, probe_cost: float, access_cost: float) -> float:
    """Cost of a query on an empty range behind a filter."""
    return probe_cost + error_rate * access_cost


def break_even_access(fpr_a: float, probe_a: float, fpr_b: float, probe_b: float) -> float | None:
    """Access cost at which filters a and b cost the same; None if there is none."""
    return (probe_b - probe_a) / (fpr_a - fpr_b) if fpr_a != fpr_b else None


def recommend(guarantee: bool, correlated: bool, shifting: bool, costly_access: bool) -> str:
    """Which filter to take for a profile."""
    if guarantee or correlated or shifting:
        return "locality-hash"
    return "truncated-trie-or-bucket" if costly_access else "bucket"
