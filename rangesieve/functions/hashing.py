"""Integer arithmetic that Spark and an SQL oracle write alike: hashes, draws, bit lengths.

Functions of a `Dialect` return SQL text; the class hides the few words that differ. There, products modulo the prime
2^61 - 1 go through 38-digit decimals in Spark (128-bit integers elsewhere). Plans over frames use `with_affine`, which has
the same results and stays in 64-bit integers and short pieces of generated code.

Keys are any integers from -2^62 up to 2^62 - 1; blocks of negative keys are counted downwards, places in a block upwards.
"""

from __future__ import annotations

import random
from dataclasses import dataclass, replace
from math import sin

import numpy as np
from pyspark.sql import DataFrame

PRIME = 2**61 - 1


@dataclass(frozen=True)
class Dialect:
    name: str
    wide: str

    def div(self, a: str, b) -> str:
        return f"(({a}) div ({b}))" if self.name == "spark" else f"(({a}) // ({b}))"

    def floor_mod(self, x: str, r) -> str:
        return f"pmod({x}, {r})" if self.name == "spark" else f"((({x}) % ({r}) + ({r})) % ({r}))"

    def floor_div(self, x: str, r) -> str:
        return self.div(f"({x}) - {self.floor_mod(x, r)}", r)

    def affine(self, x: str, c1: int, c2: int, modulus) -> str:
        """(c1 x + c2) mod 2^61 - 1 mod the modulus."""
        return f"CAST((CAST({c1} AS {self.wide}) * CAST({self.floor_mod(x, PRIME)} AS {self.wide}) + CAST({c2} AS {self.wide})) % CAST({PRIME} AS {self.wide}) % CAST({modulus} AS {self.wide}) AS BIGINT)"

    def bit_length(self, x: str) -> str:
        """Number of binary digits of a non-negative integer; 0 for 0."""
        return f"(CASE WHEN ({x}) = 0 THEN 0 ELSE length(bin({x})) END)" if self.name == "spark" else f"(CASE WHEN ({x}) = 0 THEN 0 ELSE length(ltrim(bin({x}), '0')) END)"

    def xor(self, a: str, b: str) -> str:
        return f"(({a}) ^ ({b}))" if self.name == "spark" else f"xor({a}, {b})"

    def shift(self, x: str, by) -> str:
        return f"shiftright({x}, CAST({by} AS INT))" if self.name == "spark" else f"(({x}) >> CAST({by} AS INT))"

    def hex_to_int(self, text: str) -> str:
        return f"CAST(conv({text}, 16, 10) AS BIGINT)" if self.name == "spark" else f"CAST(concat('0x', {text}) AS BIGINT)"


SPARK = Dialect("spark", "DECIMAL(38,0)")
DUCK = Dialect("duck", "HUGEINT")


def with_affine(df: DataFrame, made: list[tuple[str, str, int, int, object]]) -> DataFrame:
    """Add columns (name, x, c1, c2, modulus): (c1 x + c2) mod 2^61 - 1 mod the modulus, x and modulus as SQL text, c1 and
    c2 as numbers or columns.

    Factors are cut into 31-bit parts: c1 x = top 2^62 + mid 2^31 + bottom, where 2^61 counts as 1. Each step is a
    projection of its own, as parts are used more than once and one long expression would leave compiled code."""
    base = [f"`{c}`" for c in df.columns]
    xs = list(dict.fromkeys(x for _, x, _, _, _ in made))
    half = 2**31 - 1
    y = df.selectExpr(*base, *[f"pmod(CAST({x} AS BIGINT), {PRIME}L) AS _y{i}" for i, x in enumerate(xs)])
    cut = y.selectExpr(*base, *[t for i in range(len(xs)) for t in (f"_y{i} & {half}L AS _l{i}", f"shiftright(_y{i}, 31) AS _h{i}")])
    parts = []
    for j, (_, x, c1, _, _) in enumerate(made):
        i = xs.index(x)
        high, low = (f"shiftright({c1}, 31)", f"({c1} & {half}L)") if isinstance(c1, str) else (f"{c1 >> 31}L", f"{c1 & half}L")
        parts += [f"2L * {high} * _h{i} AS _t{j}", f"{high} * _l{i} + {low} * _h{i} AS _m{j}", f"{low} * _l{i} % {PRIME}L AS _b{j}"]
    multiplied = cut.selectExpr(*base, *parts)
    done = [f"((_t{j} + shiftright(_m{j}, 30) + shiftleft(_m{j} & {2**30 - 1}L, 31) + _b{j}) % {PRIME}L + {c2 if isinstance(c2, str) else f'{c2}L'}) % {PRIME}L % ({m}) AS `{name}`" for j, (name, _, _, c2, m) in enumerate(made)]
    return multiplied.selectExpr(*base, *done)


def affine_of(stream: int) -> tuple[int, int]:
    rng = random.Random(1000 + stream)
    return rng.randrange(1, PRIME), rng.randrange(PRIME)


def with_draws(df: DataFrame, made: list[tuple[str, str, object, int]]) -> DataFrame:
    """Add columns (name, x, modulus, stream), each `draw` of x."""
    return with_affine(df, [(name, x, *affine_of(stream), m) for name, x, m, stream in made])


def with_local_hash(df: DataFrame, made: list[tuple[str, str]], p: HashParams, r=None, factors=None) -> DataFrame:
    """Add columns (name, x), each `local_hash` of x, which is SQL text. r, factors: columns of the frame instead of p's r,
    and its c1 and c2."""
    r = f"{p.r}L" if r is None else r
    c1, c2 = factors or (p.c1, p.c2)
    hashed = with_affine(df, [(f"_q{i}", SPARK.floor_div(x, r), c1, c2, r) for i, (_, x) in enumerate(made)])
    return hashed.selectExpr(*[f"`{c}`" for c in df.columns], *[f"(_q{i} + pmod({x}, {r})) % {r} AS `{name}`" for i, (name, x) in enumerate(made)])


def draw(d: Dialect, i: str, modulus, stream: int) -> str:
    """A repeatable affine hash of an integer below the modulus, for the places of Bloom filters and the like."""
    return d.affine(i, *affine_of(stream), modulus)


def mixed(d: Dialect, i: str, modulus, stream: int) -> str:
    """A repeatable draw below the modulus for a row: 62 bits of a mixing hash, so that draws are no lattice."""
    text = "STRING" if d.name == "spark" else "VARCHAR"
    h = f"md5(concat('{stream}:', CAST({i} AS {text})))"
    first, last = d.hex_to_int(f"substr({h}, 1, 15)"), d.hex_to_int(f"substr({h}, 16, 1)")
    return f"CAST(({first} + ({last} % 4) * {2**60}) % ({modulus}) AS BIGINT)"


@dataclass(frozen=True)
class HashParams:
    """Parameters of a locality hash into [0, r): block x div r is hashed, the place in the block is kept."""

    r: int
    c1: int
    c2: int
    n: int = 0
    u: int = 2**62

    @property
    def exact(self) -> bool:
        return self.r >= self.u


def seeded(r: int, seed: int, n: int = 0, u: int = 2**62) -> HashParams:
    rng = random.Random(seed)
    return HashParams(min(r, u), rng.randrange(1, PRIME), rng.randrange(PRIME), n, u)


def params_for_error(n: int, length: int, eps: float, u: int = 2**62, seed: int = 1) -> HashParams:
    """r = n L / eps, rounded up."""
    return seeded(max(1, -int(-(n * length) // eps)), seed, n, u)


def params_for_budget(n: int, bits: int, u: int = 2**62, seed: int = 1) -> HashParams:
    """eps = L / 2^(bits - 2), so that r = n 2^(bits - 2) for any L."""
    return seeded(max(1, n * 2 ** (bits - 2)), seed, n, u)


def power_of_two(p: HashParams) -> HashParams:
    """The same with r rounded up to a power of two."""
    return replace(p, r=1 << (p.r - 1).bit_length())


def block_hash(d: Dialect, block: str, p: HashParams, r=None) -> str:
    return d.affine(block, p.c1, p.c2, r if r is not None else p.r)


def local_hash(d: Dialect, x: str, p: HashParams, r=None) -> str:
    r = r if r is not None else p.r
    return f"(({block_hash(d, d.floor_div(x, r), p, r)} + {d.floor_mod(x, r)}) % {r})"


def local_hash_pow2(x: str, p: HashParams) -> str:
    """Spark form for r = 2^k: shift, add, mask."""
    k = p.r.bit_length() - 1
    return f"(({block_hash(SPARK, f'shiftright({x}, {k})', p)} + (({x}) & {p.r - 1})) & {p.r - 1})"


def local_hash_fast(x: str, p: HashParams, seed: int = 42) -> str:
    """Spark form with a practical hash of the block, as a string hash would be."""
    return f"((pmod(xxhash64({SPARK.floor_div(x, p.r)}, {seed}), {p.r}) + pmod({x}, {p.r})) % {p.r})"


def h_value(x: int, p: HashParams) -> int:
    """The hash on the driver, for worked examples and packed probes."""
    return ((p.c1 * (x // p.r) + p.c2) % PRIME % p.r + x % p.r) % p.r


def affine_values(x: np.ndarray, c1: int, c2: int, modulus: int) -> np.ndarray:
    """(c1 x + c2) mod 2^61 - 1 mod the modulus for an array of integers."""
    return _rest(line_values(x, c1, c2), modulus)


def line_values(x: np.ndarray, c1: int, c2: int) -> np.ndarray:
    """(c1 x + c2) mod 2^61 - 1 for an array of integers, by the parts that `with_affine` takes."""
    x, half = _folded(np.asarray(x, np.int64)), 2**31 - 1
    high, low = x >> 31, x & half
    top, mid, bottom = 2 * (c1 >> 31) * high, (c1 >> 31) * low + (c1 & half) * high, _folded((c1 & half) * low)
    total = _folded(_folded(top + (mid >> 30)) + ((mid & (2**30 - 1)) << 31) + bottom)
    return _folded(total + c2)


def next_values(start: np.ndarray, at: np.ndarray, further: np.ndarray, steps: np.ndarray, modulus: int) -> np.ndarray:
    """`affine_values` some places further than start[at], whose `line_values` are given; steps: c1 t mod 2^61 - 1 for each t."""
    total = start[at] + steps[further]
    return _rest(np.where(total >= PRIME, total - PRIME, total), modulus)


def _rest(x: np.ndarray, modulus: int) -> np.ndarray:
    return x - x // modulus * modulus  # faster than % on arrays


def _folded(x: np.ndarray) -> np.ndarray:
    """x mod 2^61 - 1: 2^61 counts as 1, below zero, too."""
    x = (x & PRIME) + (x >> 61)
    x += np.where(x < 0, PRIME, 0)
    return np.where(x >= PRIME, x - PRIME, x)


def h_values(x: np.ndarray, p: HashParams) -> np.ndarray:
    """`h_value` for an array of integers."""
    x = np.asarray(x, np.int64)
    place = np.mod(x, p.r)
    return (affine_values((x - place) // p.r, p.c1, p.c2, p.r) + place) % p.r


# --- mixing draws of arrays -------------------------------------------------------------------------------------------

_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_SINES = [np.uint32(int(abs(sin(i + 1)) * 2**32)) for i in range(64)]
_STARTS = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
#: Numbers whose sums are taken together, so that all words stay near the processor.
_TOGETHER = 2**14


def mixed_values(x: np.ndarray, modulus: int, stream: int) -> np.ndarray:
    """`mixed` of an array of integers above -2^63."""
    x, out = np.asarray(x, np.int64), np.empty(len(x), np.int64)
    for start in range(0, len(x), _TOGETHER):
        part = x[start : start + _TOGETHER]
        size = np.abs(part)
        digits = np.searchsorted(_TENS, size, "right") + 1
        kind = np.where(part < 0, -digits, digits)
        for one in np.unique(kind):
            at = np.flatnonzero(kind == one)
            out[start + at] = _first_62(size[at], f"{stream}:{'-' if one < 0 else ''}".encode(), abs(int(one)))
    return _rest(out, modulus)


_TENS = 10 ** np.arange(1, 19, dtype=np.int64)


def _first_62(size: np.ndarray, before: bytes, digits: int) -> np.ndarray:
    """The first 15 hexadecimal digits of md5 of a text and a number's digits, and two bits of the next, as in `mixed`."""
    block = np.zeros((64, len(size)), np.uint8)  # one block: a text of at most 55 bytes
    block[: len(before)] = np.frombuffer(before, np.uint8)[:, None]
    rest, length = size, len(before) + digits
    for i in range(length - 1, len(before) - 1, -1):
        shorter = rest // 10
        block[i] = 48 + (rest - shorter * 10)
        rest = shorter
    block[length] = 128
    words = [(block[i].astype(np.uint32) | block[i + 1].astype(np.uint32) << 8 | block[i + 2].astype(np.uint32) << 16 | block[i + 3].astype(np.uint32) << 24) if i <= length else None for i in range(0, 56, 4)] + [np.uint32(8 * length), None]
    a, b, c, d = (np.full(len(size), x, np.uint32) for x in _STARTS)
    for i in range(64):
        if i < 16:
            mix, at = d ^ (b & (c ^ d)), i
        elif i < 32:
            mix, at = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            mix, at = b ^ c ^ d, (3 * i + 5) % 16
        else:
            mix, at = c ^ (b | ~d), 7 * i % 16
        mix += a
        mix += _SINES[i]
        if words[at] is not None:
            mix += words[at]
        turn = _TURNS[i // 16][i % 4]
        turned = mix << np.uint32(turn)
        turned |= mix >> np.uint32(32 - turn)
        turned += b
        a, b, c, d = d, turned, b, c
    first, second = ((s + x).byteswap().astype(np.int64) for s, x in ((a, _STARTS[0]), (b, _STARTS[1])))
    return (first << 28 | second >> 4) + ((second & 3) << 60)
