"""All filters at one budget of bits a key, each as a Spark plan and as SQL over the CTEs keys(k) and ranges(qid, a, b, ...).

`answer(setup, name, bits, ranges)` adds `maybe`, `hits` has the questions (q, a, b) that are maybe; `hits_sql(name, bits, u)` is a list of CTEs that ends with the pairs of
ends that are maybe, `<tag>_hit(a, b)`. Sizes follow the number of keys, so a filter keeps its rate as tables grow.
"""

from __future__ import annotations

from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from rangesieve.functions import models
from rangesieve.functions.hashing import DUCK, SPARK, draw, local_hash, mixed, params_for_budget, seeded
from rangesieve.operators import asked as held
from rangesieve.operators import bitmaps as packed
from rangesieve.operators import filters as f
from rangesieve.operators import tuning
from rangesieve.operators.dealt import _distinct as distinct
from rangesieve.operators.order import answered, any_code_in, questions
from rangesieve.plans import workloads as w
from rangesieve.sources.keys import VIEWS, keys, keys_sql, universe

EVERY = 64
HASHES, TREE_HASHES, HEIGHT, TOP = 4, 2, 6, 10
SAMPLE = 10  # one question in so many tunes the tuned filters


class Setup:
    """Keys of a view and the counts that sizes follow; each count is taken once."""

    def __init__(self, spark: SparkSession, sf: str, view: str, k: DataFrame | None = None):
        self.k = keys(spark, sf, view) if k is None else k
        self.view, self.u, self.w = view, universe(view), VIEWS[view][2]
        self.known: np.ndarray | None = None

    def gather(self) -> Setup:
        """Bring the keys to the driver, in order, and from there to the tasks, where they take at most `asked.MOST_KEYS` bytes:
        counts, empty ranges, samples and filters then need no shuffle. More keys stay where they are."""
        if self.known is None and 8 * self.n <= held.MOST_KEYS:
            self.known = np.sort(self.k.select("k").toArrow().column("k").to_numpy().astype(np.int64))
            self.sent = self.k.sparkSession.sparkContext.broadcast(self.known)
        return self

    @cached_property
    def n(self) -> int:
        return self.k.count()

    @cached_property
    def ones(self) -> dict[int, int]:
        return f.ones_of(self.parted)

    @cached_property
    def parted(self) -> f.Parted:
        """Where neighbouring keys part, which the next three are counted from."""
        return f.parted(self.k, self.n) if self.known is None else held.parted(self.known)

    @cached_property
    def inner(self) -> int:
        return f.inner_nodes_of(self.parted, self.w)

    @cached_property
    def spaced(self) -> int:
        return tuning.spaced_of(self.parted, HEIGHT)

    def warm(self) -> Setup:
        """Take all counts now, before jobs run beside each other."""
        _ = (self.n, self.ones, self.inner, self.spaced)
        return self

    def ends(self, kind: str, length: int, degree: int = 8, cell: int = 0) -> DataFrame:
        """The batch of a workload: uncorrelated, correlated, nonempty, or its empty ranges with the prefix empty_."""
        made = w.ends(self.k, kind.removeprefix("empty_"), length, self.u, degree, cell)
        return self.keep_empty(made) if kind.startswith("empty_") else made

    def keep_empty(self, ranges: DataFrame) -> DataFrame:
        return w.keep_empty(self.k, ranges) if self.known is None else held.keep_empty(self.sent, ranges)

    def alike(self, sample: DataFrame) -> tuning.Alike:
        return tuning.alike(self.k, sample, self.n) if self.known is None else held.alike(self.sent, sample)

    def tuned_on(self, ranges: DataFrame) -> tuning.Alike:
        sample = ranges.where(f"{mixed(SPARK, 'qid', SAMPLE, 7)} = 0").select("a", "b").cache()  # read by several jobs
        try:
            return self.alike(sample)
        finally:
            sample.unpersist()

    def width(self, bits: float) -> int:
        """log2 of the narrowest bucket that the budget allows."""
        fits = [j for j, t in self.ones.items() if t and j <= self.w and models.space_bucket(t, self.u, 2**j) <= bits * self.n]
        return min(fits) if fits else self.w

    def suffix(self, bits: float) -> int:
        """Real suffix bits of the trie; a trie below its least size has none and takes more than the budget."""
        return max(0, int(bits - models.space_truncated_trie(self.n, 0, self.inner) / max(self.n, 1)))


def slots(bits: float) -> int:
    return 2 ** max(1, int(bits - 2.4))


def levels(bits: float) -> list[int]:
    """Hash functions of the per-level filter, leaves first."""
    return [max(1, round(bits / 1.44 - TOP))] + [1] * TOP


def _locality(s, bits, asked, sample):
    p = params_for_budget(s.n, bits, s.u)
    return f.lhf_hits(f.lhf_codes(s.k, p, False), asked, p)


def _bucket(s, bits, asked, sample):
    wide = 2 ** s.width(bits)
    return f.cbf_hits(f.cbf_codes(s.k, wide, False), asked, wide, s.n)


def _trie(s, bits, asked, sample):
    return f.ttf_hits(f.ttf_leaves(s.k, s.suffix(bits)), asked, s.n)


def _learned(s, bits, asked, sample):
    if _sent(64 * s.n // EVERY):
        marks = packed.knots(s.k, EVERY, s.n)
        return any_code_in(packed.learned_codes(s.k, marks, EVERY * slots(bits)), packed.learned_pieces(asked, marks, EVERY * slots(bits)), s.n)
    knots = f.lbf_knots(s.k, EVERY)
    return f.lbf_hits(f.lbf_codes(s.k, knots, EVERY, slots(bits)), knots, asked, EVERY, slots(bits), s.n)


def _sent(places: int) -> bool:
    """Whether a bitmap, or a list of so many bits, goes to the tasks; else places are joined."""
    return places <= 8 * packed.MOST_BYTES


def _prefix(s, bits, asked, sample):
    one, two = tuning.tpb_tune(s.ones, sample, bits, s.u)
    trie = models.space_bucket(s.ones[one], s.u, 2**one) if one < s.w else 0.0
    left = int(max(64, bits * s.n - trie))
    if _sent(left) and _sent(8 * packed.prefix_bytes(s.ones[one], one, s.w)):
        return packed.prefix_hits(asked, packed.prefixes(s.k, one), packed.prefix_bitmap(s.k, two, left, HASHES), one, two, left, HASHES, f.MOST)
    return f.tpb_hits(s.k, asked, one, two, left, HASHES)


def _per_level(s, bits, asked, sample):
    counts, size = levels(bits), max(64, bits * s.n)
    if _sent(size):
        return packed.level_hits(asked, packed.level_bitmap(s.k, counts, size), counts, size)
    return f.level_walk(f.level_bits(s.k, counts, size), asked, counts, size)[0]


def tree_words(n: int, bits: int) -> int:
    return max(1, bits * n // 2 ** (HEIGHT + 1))


def _tree_hits(s, bits, asked, shift):
    words = tree_words(s.n, bits)
    if _sent(words * TREE_HASHES << (HEIGHT + 1)):
        return packed.tree_hits(asked, packed.tree_bitmap(s.k, shift, HEIGHT, words, TREE_HASHES), shift, HEIGHT, words, TREE_HASHES)
    return f.ltb_hits(f.tree_bits(s.k, shift, HEIGHT, words, TREE_HASHES), asked, shift, HEIGHT, words, TREE_HASHES)


def _tree(s, bits, r, shift):
    return answered(r, _tree_hits(s, bits, questions(r), shift))


HITS = {
    "locality-hash": _locality,
    "bucket": _bucket,
    "truncated-trie": _trie,
    "learned-bitmap": _learned,
    "prefix-bloom": _prefix,
    "per-level": _per_level,
    "local-tree": lambda s, bits, asked, sample: _tree_hits(s, bits, asked, 0),
    "local-tree-sampled": lambda s, bits, asked, sample: _tree_hits(s, bits, asked, tuning.ltb_tune(s.ones, sample, tree_words(s.n, bits), HEIGHT, TREE_HASHES, s.u)),
    "local-tree-spaced": lambda s, bits, asked, sample: _tree_hits(s, bits, asked, s.spaced),
}
METHODS = tuple(HITS)
TUNED = ("prefix-bloom", "local-tree-sampled")
HEURISTIC = ("bucket", "truncated-trie", "learned-bitmap", "prefix-bloom", "local-tree-sampled", "local-tree-spaced")
ROBUST = ("locality-hash", "per-level", "local-tree")


def filter_of(s: Setup, name: str, bits: int, sample: tuning.Alike | None) -> tuple[held.Filter, held.Places | None]:
    """A filter that is made of sorted keys where it is asked, and the places of its bitmap, if it has one."""
    if name == "locality-hash":
        return held.locality(params_for_budget(s.n, bits, s.u)), None
    if name == "bucket":
        return held.bucket(2 ** s.width(bits)), None
    if name == "truncated-trie":
        return held.trie(s.suffix(bits)), None
    if name == "learned-bitmap":
        return held.learned_map(EVERY, EVERY * slots(bits)), None
    if name == "per-level":
        counts, size = levels(bits), max(64, bits * s.n)
        return held.sent_bitmap(packed.level_hit(counts, size)), (size, packed.level_places(counts, size))
    if name == "prefix-bloom":
        one, two = tuning.tpb_tune(s.ones, sample, bits, s.u)
        trie = models.space_bucket(s.ones[one], s.u, 2**one) if one < s.w else 0.0
        left = int(max(64, bits * s.n - trie))
        hit = packed.prefix_hit(one, two, left, HASHES, f.MOST)
        return (lambda keys, bloom: (lambda known: lambda a, b: hit((known, bloom), a, b))(packed.Ascending(distinct(keys >> one)))), (left, packed.prefix_places(two, left, HASHES))
    words = tree_words(s.n, bits)
    shift = {"local-tree": lambda: 0, "local-tree-sampled": lambda: tuning.ltb_tune(s.ones, sample, words, HEIGHT, TREE_HASHES, s.u), "local-tree-spaced": lambda: s.spaced}[name]()
    return held.sent_bitmap(packed.tree_hit(shift, HEIGHT, words, TREE_HASHES)), (TREE_HASHES * words << (HEIGHT + 1), packed.tree_places(shift, HEIGHT, words, TREE_HASHES))


def maps_of(s: Setup, made: list[held.Places | None], each=map) -> list[np.ndarray | None]:
    """The bitmaps, on the driver; each: a map that makes them beside each other where keys are not gathered."""
    if s.known is None:
        flat = lambda x: packed.bitmap_of(s.k, x[0], lambda k: (p for place in x[1] for p in np.atleast_2d(place(k))))
        return list(each(lambda x: None if x is None else flat(x), made))
    found = iter(held.bitmaps(s.k.sparkSession, s.sent, [x for x in made if x is not None]))
    return [None if x is None else next(found) for x in made]


def together(s: Setup, names: tuple[str, ...], budgets: list[int], sample: tuning.Alike | None, each=map) -> dict[tuple, tuple[held.Filter, object]] | None:
    """(name, bits): filters that are asked together, and what is sent for each; None if keys or maps are too large for it."""
    if s.known is None and 8 * s.n > packed.MOST_BYTES or not all(_sent(b * s.n * TREE_HASHES) for b in budgets):
        return None
    cells = [(name, bits) for bits in budgets for name in names]
    made = [filter_of(s, name, bits, sample) for name, bits in cells]
    if s.known is not None:  # a job asks one filter in few tasks: its bitmap is made there and needs no way over the driver
        return {cell: (held.mapped(*x), None) for cell, x in zip(cells, made)}
    maps = maps_of(s, [x for _, x in made], each)
    return {cell: (x[0], own) for cell, x, own in zip(cells, made, maps)}


def _own(s: Setup, name: str, bits: int, sample: tuning.Alike | None) -> tuple[held.Filter, object] | None:
    """A filter and what is sent for it, where keys are gathered and its bitmap may be sent."""
    if s.known is None or not _sent(bits * s.n * TREE_HASHES):
        return None
    make, places = filter_of(s, name, bits, sample)
    return make, maps_of(s, [places])[0]


def hits(s: Setup, name: str, bits: int, asked: DataFrame, sample: tuning.Alike | None = None) -> DataFrame:
    """(q, hit, ...) of questions (q, a, b): a question is maybe if one of its rows is a hit; those without may be left out."""
    own = _own(s, name, bits, sample)
    return HITS[name](s, bits, asked, sample) if own is None else held.hits(s.sent, *own, asked)


def answer(s: Setup, name: str, bits: int, ranges: DataFrame, sample: tuning.Alike | None = None) -> DataFrame:
    """Ranges with `maybe`. sample: what a tuned filter learns from, one range in SAMPLE of `ranges` itself if not given."""
    if name in TUNED and sample is None:
        sample = s.tuned_on(ranges)
    if (own := _own(s, name, bits, sample)) is not None:
        return held.answers(s.sent, *own, ranges)
    return answered(ranges, hits(s, name, bits, questions(ranges), sample))


# --- SQL --------------------------------------------------------------------------------------------------------------


def with_keys(view: str, rest: str) -> str:
    return f"WITH keys AS MATERIALIZED ({keys_sql(DUCK, view)}), {rest}"


def ends_sql(kind: str, u: int, length: int, degree: int = 8, cell: int = 0) -> str:
    made = f"SELECT qid, a, a + {length - 1} AS b FROM (SELECT k AS qid, {w.left_end(DUCK, kind.removeprefix('empty_'), length, u, degree, cell)} AS a FROM keys)"
    return w.empties_sql(made) if kind.startswith("empty_") else made


def counts_sql(u: int) -> str:
    """CTEs that sizes and tuning follow: nn, ones, nb, inner_nodes, and gaps of the sample."""
    width, digits = u.bit_length() - 1, DUCK.bit_length
    return f"""q AS MATERIALIZED (SELECT DISTINCT a, b FROM ranges WHERE a <= b),
nn AS (SELECT count(*) AS n FROM keys),
ones AS MATERIALIZED (SELECT j, count(DISTINCT k >> j) AS t FROM keys, (SELECT unnest(range(63))::INT AS j) GROUP BY j),
nb AS MATERIALIZED (SELECT k, {digits('xor(k, lag(k) OVER (ORDER BY k))')} AS p, {digits('xor(k, lead(k) OVER (ORDER BY k))')} AS n FROM keys),
inner_nodes AS (SELECT count(*) AS z FROM (SELECT DISTINCT level, k >> level FROM (SELECT k, unnest(range(greatest(least(coalesce(p, 64), coalesce(n, 64), 63) - 1, 0) + 1, {width + 1}))::INT AS level FROM nb))),
smp AS (SELECT a, b FROM ranges WHERE {mixed(DUCK, 'qid', SAMPLE, 7)} = 0 AND a <= b),
nx AS (SELECT s.a, s.b, c.k AS after FROM smp s ASOF LEFT JOIN keys c ON s.b <= c.k),
pv AS (SELECT x.a, x.b, x.after, c.k AS before FROM nx x ASOF LEFT JOIN keys c ON x.a >= c.k),
gaps AS MATERIALIZED (SELECT level, wide, count(*) AS c FROM (SELECT least(coalesce({digits('xor(a, before)')}, 63), coalesce({digits('xor(b, after)')}, 63)) AS level, {digits('b - a')} AS wide FROM pv) GROUP BY ALL)"""


def locality_sql(t: str, par: str, h=None) -> str:
    """CTEs from <t>_par(r) on."""
    h = h or (lambda x: local_hash(DUCK, x, seeded(2, 1), "r"))
    return f"""{t}_par AS MATERIALIZED ({par}), {t}_codes AS (SELECT DISTINCT {h('k')} AS z FROM keys, {t}_par),
{t}_cut AS MATERIALIZED (SELECT a, b, r, {DUCK.floor_div('b', 'r')} - {DUCK.floor_div('a', 'r')} AS spans FROM q, {t}_par),
{t}_halves AS (SELECT a, b, r, a AS x0, b AS y0 FROM {t}_cut WHERE spans = 0
  UNION ALL SELECT a, b, r, a, b - {DUCK.floor_mod('b', 'r')} - 1 FROM {t}_cut WHERE spans = 1
  UNION ALL SELECT a, b, r, b - {DUCK.floor_mod('b', 'r')}, b FROM {t}_cut WHERE spans = 1),
{t}_ends AS MATERIALIZED (SELECT a, b, r, {h('x0')} AS x, {h('y0')} AS y FROM {t}_halves),
{t}_pieces AS (SELECT a, b, x AS lo, y AS hi FROM {t}_ends WHERE x <= y
  UNION ALL SELECT a, b, 0, y FROM {t}_ends WHERE x > y
  UNION ALL SELECT a, b, x, r - 1 FROM {t}_ends WHERE x > y
  UNION ALL SELECT a, b, 0, r - 1 FROM {t}_cut WHERE spans > 1),
{t}_hit AS (SELECT DISTINCT p.a, p.b FROM {t}_pieces p ASOF JOIN {t}_codes c ON p.hi >= c.z WHERE c.z >= p.lo)"""


def budget_par(bits: int, u: int) -> str:
    return f"SELECT CAST(least(greatest(count(*) * CAST({2 ** (bits - 2)} AS HUGEINT), 1), {u}) AS BIGINT) AS r FROM keys"


def bucket_par(bits: int, u: int) -> str:
    return f"SELECT coalesce(min(CASE WHEN j <= {u.bit_length() - 1} AND t * (log2({u}::DOUBLE / (t::DOUBLE * pow(2, j))) + 2) <= {bits} * n THEN j END), {u.bit_length() - 1})::INT AS s FROM ones, nn"


def bucket_sql(t: str, par: str) -> str:
    return f"""{t}_par AS MATERIALIZED ({par}), {t}_codes AS (SELECT DISTINCT k >> s AS z FROM keys, {t}_par),
{t}_ends AS MATERIALIZED (SELECT a, b, a >> s AS lo, b >> s AS hi FROM q, {t}_par),
{t}_hit AS (SELECT DISTINCT p.a, p.b FROM {t}_ends p ASOF JOIN {t}_codes c ON p.hi >= c.z WHERE c.z >= p.lo)"""


def trie_leaves(t: str, suffix: str) -> str:
    """<t>_leaves(z, hi, k, s) with so many suffix bits (SQL text of one row, column m)."""
    return f"""{t}_sh AS (SELECT k, greatest(least(coalesce(p, 64), coalesce(n, 64), 63) - 1 - m, 0)::INT AS s FROM nb, ({suffix})),
{t}_leaves AS (SELECT (k >> s) << s AS z, ((k >> s) << s) + (1::BIGINT << s) - 1 AS hi, k, s FROM {t}_sh)"""


def trie_sql(t: str, suffix: str) -> str:
    return f"{trie_leaves(t, suffix)}, {t}_hit AS (SELECT DISTINCT p.a, p.b FROM q p ASOF JOIN {t}_leaves c ON p.b >= c.z WHERE c.hi >= p.a)"


def suffix_sql(bits: int) -> str:
    return f"SELECT greatest(0, trunc({bits} - (10.0 * n + 10 * z) / greatest(n, 1)))::INT AS m FROM nn, inner_nodes"


def _learned_at(x: str, k: int) -> str:
    return f"CASE WHEN z IS NULL THEN -1 ELSE i * {EVERY * k} + (({x} - z)::HUGEINT * {EVERY * k} // (coalesce(nxt, z + {2**40}) - z))::BIGINT END"


def learned_codes(t: str, k: int) -> str:
    return f"""{t}_knots AS MATERIALIZED (SELECT z, i, lead(z) OVER (ORDER BY z) AS nxt FROM (SELECT k AS z, (row_number() OVER (ORDER BY k) - 1) // {EVERY} AS i, (row_number() OVER (ORDER BY k) - 1) % {EVERY} AS rest FROM keys) WHERE rest = 0),
{t}_codes AS (SELECT DISTINCT {_learned_at('k', k)} AS z FROM keys ASOF LEFT JOIN {t}_knots ON k >= z)"""


def learned_sql(t: str, k: int) -> str:
    return f"""{learned_codes(t, k)},
{t}_lows AS (SELECT a, b, {_learned_at('a', k)} AS lo FROM q ASOF LEFT JOIN {t}_knots ON a >= z), {t}_ends AS MATERIALIZED (SELECT a, b, lo, {_learned_at('b', k)} AS hi FROM {t}_lows ASOF LEFT JOIN {t}_knots ON b >= z),
{t}_hit AS (SELECT DISTINCT p.a, p.b FROM {t}_ends p ASOF JOIN {t}_codes c ON p.hi >= c.z WHERE c.z >= p.lo)"""


def places(v: str, modulus: str, streams: list[int]) -> str:
    return "unnest([" + ", ".join(draw(DUCK, v, modulus, s) for s in streams) + "])"


BLOOM = [100 + 3 * 16 + j for j in range(HASHES)]


def prefix_grid(t: str, bits: int, u: int) -> str:
    """<t>_f(s1, s2, trie, fpr): expected rate of every split of the budget."""
    top = u.bit_length() - 1
    return f"""{t}_g AS (SELECT x.j AS s1, y.j AS s2, CASE WHEN x.j < {top} THEN x.t * (log2({u}::DOUBLE / (x.t::DOUBLE * pow(2, x.j))) + 2) ELSE 0.0 END AS trie, y.t AS t2 FROM ones x JOIN ones y ON y.j <= x.j WHERE x.j <= {top} AND x.j % 2 = 0 AND y.j % 2 = 0 AND y.j <> {top}),
{t}_h AS (SELECT s1, s2, trie, CASE WHEN s1 = s2 THEN 1.0 ELSE exp(-({bits} * n - trie) / greatest(t2, 1) * pow(ln(2), 2)) END AS p FROM {t}_g, nn WHERE {bits} * n - trie >= 0),
{t}_f AS (SELECT s1, s2, trie, sum(c * CASE WHEN level <= s2 THEN 1.0 WHEN level <= s1 THEN 1 - pow(1 - p, (((1::BIGINT << wide) - 1) >> s2) + 1) ELSE 0.0 END) / sum(c) AS fpr FROM {t}_h, gaps GROUP BY ALL)"""


def prefix_sql(t: str, par: str) -> str:
    """From <t>_par(s1, s2, m) on."""
    return f"""{t}_par AS MATERIALIZED ({par}), {t}_trie AS (SELECT DISTINCT k >> s1 AS t FROM keys, {t}_par),
{t}_bits AS MATERIALIZED (SELECT DISTINCT {places('v', 'm', BLOOM)} AS place FROM (SELECT DISTINCT k >> s2 AS v, m FROM keys, {t}_par)),
{t}_ends AS MATERIALIZED (SELECT a, b, a >> s2 AS x, b >> s2 AS y, s1 - s2 AS up, m FROM q, {t}_par),
{t}_asked AS (SELECT a, b, unnest(range(x, y + 1)) AS v, up, m FROM {t}_ends WHERE y - x < {f.MOST}),
{t}_live AS (SELECT a, b, v, {places('v', 'm', BLOOM)} AS place FROM {t}_asked WHERE v >> up IN (SELECT t FROM {t}_trie)),
{t}_hit AS (SELECT DISTINCT a, b FROM (SELECT a, b, v FROM {t}_live JOIN {t}_bits USING (place) GROUP BY ALL HAVING count(*) = {HASHES}) UNION SELECT a, b FROM {t}_ends WHERE y - x >= {f.MOST})"""


def cover_sql(source: str, top: int) -> str:
    return f"""SELECT DISTINCT a, b, level, unnest(CASE WHEN level = {top} THEN range(x, y + 1) ELSE list_concat(CASE WHEN x % 2 = 1 OR x = y THEN [x] ELSE [] END, CASE WHEN y % 2 = 0 OR x = y THEN [y] ELSE [] END) END) AS node
FROM (SELECT a, b, level, (lo + (1::BIGINT << level) - 1) >> level AS x, ((hi + 1) >> level) - 1 AS y FROM {source}, (SELECT unnest(range({top + 1}))::INT AS level)) WHERE x <= y"""


def per_level_sql(t: str, counts: list[int], m: str) -> str:
    """m: SQL of the number of bits over nn(n)."""
    top = len(counts) - 1
    v = lambda level: "(" + f.LEVEL_NODE.format(node="node", level=level) + ")"
    streams = lambda level: [132 + j for j in range(counts[level])]
    out = [f"{t}_par AS MATERIALIZED (SELECT {m} AS m FROM nn)", f"{t}_bits AS MATERIALIZED (SELECT DISTINCT place FROM (" + " UNION ALL ".join(f"SELECT {places(v(i), 'm', streams(i))} AS place FROM (SELECT DISTINCT k >> {i} AS node, m FROM keys, {t}_par)" for i in range(top + 1)) + "))", f"{t}_cover AS MATERIALIZED ({cover_sql('(SELECT a, b, a AS lo, b AS hi FROM q)', top)})"]
    for i in range(top, -1, -1):
        more = f" UNION ALL SELECT a, b, unnest([node * 2, node * 2 + 1]) FROM {t}_a{i + 1}" if i < top else ""
        out.append(f"{t}_n{i} AS MATERIALIZED (SELECT a, b, node FROM {t}_cover WHERE level = {i}{more})")
        out.append(f"{t}_a{i} AS MATERIALIZED (SELECT a, b, node FROM (SELECT a, b, node, {places(v(i), 'm', streams(i))} AS place FROM {t}_n{i}, {t}_par) JOIN {t}_bits USING (place) GROUP BY ALL HAVING count(*) = {counts[i]})")
    return ", ".join(out) + f", {t}_hit AS (SELECT DISTINCT a, b FROM {t}_a0)"


def tree_sql(t: str, shift: str, bits: int, height: int = HEIGHT) -> str:
    """shift: SQL of one row with a column s."""
    heap = f"((1::BIGINT << ({height} - level)) + node - (tree << ({height} - level)))"
    place = lambda j: f"{draw(DUCK, 'tree', 'words', 300 + j)} * {2 ** (height + 1)} + {heap}"
    both = lambda source: " UNION ALL ".join(f"SELECT *, {j} AS j, {place(j)} AS place FROM {source}" for j in range(TREE_HASHES))
    return f"""{t}_par AS MATERIALIZED (SELECT s, greatest(1, {bits} * n // {2 ** (height + 1)}) AS words FROM nn, ({shift})),
{t}_nodes AS (SELECT DISTINCT k >> (s + {height}) AS tree, level, k >> (s + level) AS node, words FROM keys, {t}_par, (SELECT unnest(range({height + 1}))::INT AS level)),
{t}_bits AS MATERIALIZED (SELECT DISTINCT j, place FROM ({both(f'{t}_nodes')})),
{t}_cover AS MATERIALIZED ({cover_sql(f'(SELECT a, b, a >> s AS lo, b >> s AS hi FROM q, {t}_par)', height)}),
{t}_asked AS (SELECT a, b, level, node, node >> ({height} - level) AS tree, words FROM {t}_cover, {t}_par),
{t}_hit AS (SELECT DISTINCT a, b FROM (SELECT a, b, level, node FROM ({both(f'{t}_asked')}) JOIN {t}_bits USING (j, place) GROUP BY ALL HAVING count(*) = {TREE_HASHES}))"""


def sampled_shift(bits: int, u: int) -> str:
    top = max(1, u.bit_length() - 1 - HEIGHT)
    return f"""SELECT s FROM (SELECT x.j AS s, (SELECT sum(t) FROM ones y WHERE y.j BETWEEN x.j AND x.j + {HEIGHT}) AS nodes, (SELECT sum(CASE WHEN level <= x.j THEN c ELSE 0 END) / sum(c) FROM gaps) AS sure, greatest(1, {bits} * n // {2 ** (HEIGHT + 1)}) AS words FROM ones x, nn WHERE x.j < {top})
ORDER BY round(sure + (1 - sure) * least(1.0, {2 * HEIGHT} * pow(1 - exp(-nodes / (words * {2 ** (HEIGHT + 1)})), {TREE_HASHES})), 9), s LIMIT 1"""


SPACED = f"SELECT greatest(0, quantile_disc(p, 0.5) - {HEIGHT})::INT AS s FROM nb WHERE p IS NOT NULL"


_TAGS = dict(zip(METHODS, ("lh", "bu", "tt", "lb", "pb", "pl", "lt", "se", "ss")))


def tag(name: str, bits: int) -> str:
    return f"{_TAGS[name]}{bits}"


def hits_sql(name: str, bits: int, u: int, sample: str = "") -> str:
    """CTEs of a method at a budget, the last one <tag>_hit(a, b); `counts_sql` goes before."""
    t = tag(name, bits) + sample
    if name == "locality-hash":
        return locality_sql(t, budget_par(bits, u))
    if name == "bucket":
        return bucket_sql(t, bucket_par(bits, u))
    if name == "truncated-trie":
        return trie_sql(t, suffix_sql(bits))
    if name == "learned-bitmap":
        return learned_sql(t, slots(bits))
    if name == "prefix-bloom":
        return f"{prefix_grid(t, bits, u)}, " + prefix_sql(t, f"SELECT s1, s2, CAST(floor(greatest(64, {bits} * n - trie)) AS BIGINT) AS m FROM {t}_f, nn ORDER BY round(fpr, 9), s1, s2 LIMIT 1")
    if name == "per-level":
        return per_level_sql(t, levels(bits), f"greatest(64, {bits} * n)")
    return tree_sql(t, {"local-tree": "SELECT 0 AS s", "local-tree-sampled": sampled_shift(bits, u), "local-tree-spaced": SPACED}[name], bits)


def answer_sql(name: str, bits: int, view: str, ranges: str, columns: str = "qid, a, b") -> str:
    u = universe(view)
    return with_keys(view, f"ranges AS MATERIALIZED ({ranges}), {counts_sql(u)}, {hits_sql(name, bits, u)} SELECT {columns}, (a, b) IN (SELECT (a, b) FROM {tag(name, bits)}_hit) AS maybe FROM ranges")
