"""More registered queries: the remaining families, tuned baselines, updates, and the experiments.

Experiments draw a question for each key (a repeatable tenth of them in the grids), so batches grow with the table. Each
method at each budget is one job that sends a few counts to the driver; the questions are kept for all of them.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions import models
from rangesieve.functions.hashing import DUCK, SPARK, HashParams, draw, h_values, local_hash, mixed, mixed_values, params_for_budget, seeded, with_local_hash
from rangesieve.operators import bitmaps as packed
from rangesieve.operators import dealt
from rangesieve.operators.asked import positives
from rangesieve.operators import families as fam
from rangesieve.operators import filters as f
from rangesieve.operators import tuning, updates
from rangesieve.operators.order import any_code_in, grows, keep_empty, predecessor, rank
from rangesieve.plans import measures
from rangesieve.plans import methods as m
from rangesieve.plans import workloads as w
from rangesieve.plans.methods import HASHES, Setup, answer_sql, counts_sql, ends_sql, hits_sql, tag, with_keys
from rangesieve.plans.queries import BUDGET, LENGTH, ORACLES, QUERIES, U, VIEW, _codes_sql, _on_batch, _par_sql, _R, batch_sql, counted_sql, heldout_keys, heldout_sql, register, sweep_drawn, sweep_ranges, sweep_sql
from rangesieve.sources import strings
from rangesieve.sources.keys import VIEWS, keys, keys_sql, read_table, universe
from rangesieve.streaming import windows

__all__ = ["ORACLES", "QUERIES"]
BUDGETS = (8, 12, 16, 20, 24, 28)

# --- packed access ----------------------------------------------------------------------------------------------------


def _ranked(spark, sf) -> tuple[Setup, DataFrame]:
    s = Setup(spark, sf, VIEW)
    return s, rank(f.lhf_codes(s.k, params_for_budget(s.n, BUDGET, s.u)), "z", n=s.n)


def ef_cells(spark, sf):
    """First and last rank of the codes of every occupied high part, and where select of zeros finds it."""
    parts = _ranked(spark, sf)[1].selectExpr("shiftright(z, 14) AS hi", "i")
    return parts.groupBy("hi").agg(F.min("i").alias("first"), F.max("i").alias("last")).selectExpr("hi", "first", "last", "hi + first - 1 AS select_zero")


register("ef_cells", ef_cells, with_keys(VIEW, f"{_par_sql(VIEW)}, {_codes_sql(seeded(2, 1))}, c AS (SELECT z >> 14 AS hi, z FROM codes), g AS (SELECT hi, count(*) AS c FROM c GROUP BY hi) SELECT hi, 1 + (coalesce(sum(c) OVER (ORDER BY hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS first, (sum(c) OVER (ORDER BY hi))::BIGINT AS last, (hi + coalesce(sum(c) OVER (ORDER BY hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS select_zero FROM g"))


def ef_access(spark, sf):
    """The nth code for drawn i."""
    s, codes = _ranked(spark, sf)
    asked = s.k.selectExpr("k AS qid", f"{mixed(SPARK, 'k', s.n, 11)} + 1 AS nth")
    return asked.join(codes, F.col("nth") == F.col("i"), "left").select("qid", "nth", F.coalesce("z", F.lit(-1)).alias("z"))


register("ef_access", ef_access, with_keys(VIEW, f"{_par_sql(VIEW)}, {_codes_sql(seeded(2, 1))}, n AS (SELECT row_number() OVER (ORDER BY z) AS i, z FROM codes) SELECT qid, nth, coalesce(z, -1) AS z FROM (SELECT k AS qid, {mixed(DUCK, 'k', '(SELECT count(*) FROM keys)', 11)} + 1 AS nth FROM keys) LEFT JOIN n ON nth = i"))


def ef_select(spark, sf):
    """Places of the k-th zero of each packed shard, by select on its bits: one for every cell border."""
    from rangesieve.functions.packed import pack, shard_zeros

    s = Setup(spark, sf, VIEW)
    return shard_zeros(pack(f.lhf_codes(s.k, params_for_budget(s.n, BUDGET, s.u)), BUDGET - 2, s.n)).select("cell", "codes_below")


# Bits before a zero are zeros of lower cells and ones of lower codes; so the codes below the end of a cell.
register("lhf_select_zero", ef_select, with_keys(VIEW, f"{_par_sql(VIEW)}, {_codes_sql(seeded(2, 1))}, c AS (SELECT DISTINCT (z >> 14) AS cell FROM codes), t AS (SELECT z, row_number() OVER (ORDER BY z) AS i FROM codes) SELECT cell, i AS codes_below FROM c ASOF JOIN t ON ((cell + 1) << 14) > z"))

# --- families ---------------------------------------------------------------------------------------------------------


def psh_probe(spark, sf):
    s = Setup(spark, sf, VIEW)
    p = params_for_budget(s.n, BUDGET, s.u)
    return fam.psh_probe(f.lhf_codes(s.k, p, False), s.ends("correlated", LENGTH), p)


register("psh_probe", psh_probe, ORACLES["lhf_probe_correlated"])

LAYERS, DELTA = 5, 6


def _phb_place(v: str, layer: str) -> str:
    return f"({draw(DUCK, f'((({v}) >> {DELTA}) * 64 + {layer})', 'words', 400)} * {2**DELTA} + (({v}) & {2**DELTA - 1}))"


def _phb(s: Setup, r: DataFrame) -> DataFrame:
    words = max(1, BUDGET * s.n // 2**DELTA)
    return fam.phb_probe(fam.phb_bits(s.k, LAYERS, DELTA, words), r, LAYERS, DELTA, words)


register("phb_probe", _on_batch("correlated", LENGTH, _phb), batch_sql("correlated", LENGTH, f"""wd AS (SELECT greatest(1, {BUDGET} * n // {2**DELTA}) AS words FROM nn),
bits AS (SELECT DISTINCT {_phb_place(f'k >> (layer * {DELTA})', 'layer')} AS place FROM keys, wd, (SELECT unnest(range({LAYERS}))::INT AS layer)),
pts AS (SELECT a, b, unnest(range(a, b + 1)) AS x FROM q),
lifted AS (SELECT a, b, x, max(j) AS j FROM (SELECT a, b, x, unnest(range({LAYERS}))::INT AS j FROM pts) WHERE ((x >> (j * {DELTA})) << (j * {DELTA})) >= a AND ((x >> (j * {DELTA})) << (j * {DELTA})) + (1::BIGINT << (j * {DELTA})) - 1 <= b GROUP BY ALL),
nodes AS (SELECT DISTINCT a, b, j, x >> (j * {DELTA}) AS v FROM lifted),
path AS (SELECT a, b, j, v, words, unnest(range(j, {LAYERS}))::INT AS layer FROM nodes, wd),
live AS (SELECT a, b FROM path WHERE {_phb_place(f'v >> ((layer - j) * {DELTA})', 'layer')} IN (SELECT place FROM bits) GROUP BY a, b, j, v HAVING count(*) = {LAYERS} - j)""", "live"))

LEVELS = [HASHES + 2, 1, 1, 1, 1, 1]


def _descent(spark, sf, levels=None):
    """Answers and work of the per-level filter on correlated ranges; levels None: tuned on an uncorrelated sample."""
    s = Setup(spark, sf, VIEW)
    if levels is None:
        levels = tuning.plb_tune(_sample(s), 5, HASHES)
    return fam.level_descent(fam.level_bits(s.k, levels, BUDGET * s.n), s.ends("correlated", LENGTH), levels, BUDGET * s.n)


def _sample(s: Setup, degree: int | None = None, length: int = LENGTH) -> DataFrame:
    """n/10 empty ranges; uncorrelated unless a degree (10 D) is given."""
    tenth = w.share(s.k, 10)
    return keep_empty(s.k, w.ends(tenth, "uncorrelated", length, s.u, 8, 50) if degree is None else w.ends(tenth, "correlated", length, s.u, degree, 50))


def _sample_sql(degree: int | None = None, length: int = LENGTH) -> str:
    """The same over keys."""
    made = ends_sql("uncorrelated", U, length, 8, 50) if degree is None else ends_sql("correlated", U, length, degree, 50)
    return w.empties_sql(f"SELECT * FROM ({made}) WHERE {mixed(DUCK, 'qid', 10, 6)} = 0")


def _level_work(levels: list[int]) -> str:
    return with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql('correlated', U, LENGTH)}), {counts_sql(U)}, {m.per_level_sql('p', levels, f'({BUDGET} * n)')} " + " UNION ALL ".join(f"SELECT {i} AS level, count(*) AS nodes, count(*) * {c} AS places FROM p_n{i}" for i, c in enumerate(levels)))


register("plb_levels_probe", lambda spark, sf: _descent(spark, sf, LEVELS)[0], batch_sql("correlated", LENGTH, m.per_level_sql("p", LEVELS, f"({BUDGET} * n)"), "p_hit"))
register("plb_probe_count", lambda spark, sf: _descent(spark, sf, LEVELS)[1](), _level_work(LEVELS))
register("plb_tuned_probe", lambda spark, sf: _descent(spark, sf)[0], batch_sql("correlated", LENGTH, m.per_level_sql("p", [HASHES] + [1] * 5, f"({BUDGET} * n)"), "p_hit"))


def plb_bits(spark, sf):
    """Set bits of the per-level filter at each budget, and the share of all."""
    s, rows = Setup(spark, sf, VIEW), []
    for bits in BUDGETS:
        rows.append((bits, f.level_bits(s.k, m.levels(bits), bits * s.n).count()))
    return spark.createDataFrame(rows, "bits int, ones long").withColumn("fill", F.round(F.col("ones") / (F.col("bits") * s.n), 6))


register("plb_bits", plb_bits, with_keys(VIEW, f"ranges AS (SELECT 0 AS qid, 0 AS a, 0 AS b), {counts_sql(U)}, " + ", ".join(m.per_level_sql(f"p{b}", m.levels(b), f"({b} * n)") for b in BUDGETS) + " " + " UNION ALL ".join(f"SELECT {b} AS bits, count(*) AS ones, round(count(*) / ({b} * (SELECT n FROM nn)), 6) AS fill FROM p{b}_bits" for b in BUDGETS)))

# --- tuning -----------------------------------------------------------------------------------------------------------


def tpb_grid(spark, sf):
    s = Setup(spark, sf, VIEW)
    rows = tuning.tpb_grid(s.ones, tuning.alike(s.k, _sample(s), s.n), BUDGET, s.u)
    return spark.createDataFrame(rows, "shift1 int, shift2 int, fpr double").withColumn("fpr", F.round("fpr", 6))


def _own_sample(text: str) -> str:
    """counts_sql whose sample is the CTE `tuner` instead of a tenth of the ranges."""
    found = counts_sql(U)
    return found.replace(f"SELECT a, b FROM ranges WHERE {mixed(DUCK, 'qid', m.SAMPLE, 7)} = 0 AND a <= b", text)


register("tpb_grid", tpb_grid, with_keys(VIEW, f"ranges AS (SELECT 0 AS qid, 0 AS a, 0 AS b), {_own_sample(f'SELECT a, b FROM ({_sample_sql()})')}, {m.prefix_grid('g', BUDGET, U)} SELECT s1 AS shift1, s2 AS shift2, round(fpr, 6) AS fpr FROM g_f"))

SHIFTED = ("locality-hash", "prefix-bloom", "local-tree-sampled")


def workload_shift(spark, sf):
    """Tuned baselines: sample from one degree of correlation, questions from another; the locality hash beside them."""
    rows = []
    with gathered(Setup(spark, sf, VIEW, dealt_out(keys(spark, sf, VIEW)))) as s:
        samples = {d: s.alike(_sample(s, d)) for d in (0, 8)}
        s.ones
        for asked in (0, 8):
            with held_empty(s, s.ends("correlated", LENGTH, asked)) as made:
                r = Batch(made)
                # A method that learns nothing from a sample is asked once for all of them.
                found = every([cells((name, tuned, asked), s, name, BUDGET, r, samples[tuned]) for name in SHIFTED for tuned in (samples if name in m.TUNED else [0])])
                rows += [(name, other, *rest) for name, tuned, *rest in found for other in ([tuned] if name in m.TUNED else samples)]
    return rated(spark, rows, "method string, tuned_d int, asked_d int")


@contextmanager
def held(ranges: DataFrame):
    """Questions kept while several filters are asked; lost blocks are made again."""
    kept = ranges.cache()
    try:
        yield kept
    finally:
        kept.unpersist()


def dealt_out(k: DataFrame) -> DataFrame:
    """Keys in partitions enough for all cores, however few they are: what is drawn from them is work for all."""
    return k.repartition(2 * k.sparkSession.sparkContext.defaultParallelism)


@contextmanager
def gathered(s: Setup):
    """A setup whose keys are kept, and gathered where they may be."""
    with held(s.k):
        try:
            yield s.gather()
        finally:
            if s.known is not None:
                s.sent.unpersist()


@contextmanager
def held_empty(s: Setup, drawn: DataFrame):
    """The empty ones of drawn questions, kept; what was drawn is kept until they are found, as several jobs read it."""
    if s.known is not None:
        with held(s.keep_empty(drawn)) as empty:
            yield empty
        return
    with held(drawn):
        empty = keep_empty(s.k, drawn).cache()
        empty.count()
    try:
        yield empty
    finally:
        empty.unpersist()


def counted(answers: DataFrame, *by: str) -> list[tuple]:
    """(*by, n_ranges, positives) on the driver: as many rows as an experiment has cells."""
    return [tuple(r) for r in answers.groupBy(*by).agg(F.count("*").alias("n_ranges"), F.sum(F.col("maybe").cast("long")).alias("positives")).collect()]


#: Jobs of one experiment that are planned and run beside each other.
BESIDE = 6


def every(jobs: list[Callable[[], list[tuple]]]) -> list[tuple]:
    """Rows of all jobs, in order."""
    with ThreadPoolExecutor(BESIDE) as pool:
        return [row for rows in pool.map(lambda job: job(), jobs) for row in rows]


def cells(fixed: tuple, s: Setup, name: str, bits: int, r: Batch, sample=None) -> Callable[[], list[tuple]]:
    return lambda: [(*fixed, *x) for x in r.counted(m.hits(s, name, bits, r.asked, sample))]


class Batch:
    """Questions of an experiment, for filters of which only counts are wanted. Rows are told apart by qid and the columns
    `by`, which the experiments draw so that none repeats; so neither questions nor answers are joined with the rows."""

    def __init__(self, ranges: DataFrame, *by: str):
        self.ranges, self.by = ranges, by
        self.asked = ranges.select(F.struct("qid", *by).alias("q"), "a", "b")
        self.n = {tuple(r[:-1]): r[-1] for r in ranges.groupBy(*by).agg(F.count("*")).collect()}  # a row a cell

    def counted(self, hits: DataFrame) -> list[tuple]:
        """(*by, n_ranges, positives) on the driver: as many rows as an experiment has cells."""
        found = hits.where("hit").select("q").distinct().groupBy(*[F.col(f"q.{c}").alias(c) for c in self.by]).agg(F.count("*"))
        positives = {tuple(r[:-1]): r[-1] for r in found.collect()}
        return [(*cell, n, positives.get(cell, 0)) for cell, n in self.n.items()]


_seen: dict[tuple, list] = {}


def once(spark, sf: str, name: str, make: Callable[[], list[tuple]]) -> list[tuple]:
    """Rows of an experiment, which several queries read; made once for an application and a folder."""
    key = (spark.sparkContext.applicationId, sf, name)
    if key not in _seen:
        _seen[key] = make()
    return _seen[key]


def rated(spark, rows: list[tuple], schema: str) -> DataFrame:
    return measures.with_limits(spark.createDataFrame(rows, f"{schema}, n_ranges long, positives long"))


def rated_sql(parts: list[str]) -> str:
    """Rates from selects of (..., n_ranges, positives)."""
    return f"SELECT *, {measures.LIMITS_SQL} FROM (" + " UNION ALL ".join(parts) + ")"


def _count_of(name: str, bits: int, fixed: str, by: str = "", suffix: str = "") -> str:
    group = f" GROUP BY {by}" if by else ""
    columns = "".join(f", {x}" for x in by.split(", ") if x)
    return f"SELECT {fixed}{columns}, count(*) AS n_ranges, coalesce(sum(((a, b) IN (SELECT (a, b) FROM {tag(name, bits)}{suffix}_hit))::INT), 0)::BIGINT AS positives FROM ranges{group}"


_SHIFT = []
for _asked in (0, 8):
    for _tuned in (0, 8):
        _ctes = with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql('empty_correlated', U, LENGTH, _asked)}), {_own_sample(f'SELECT a, b FROM ({_sample_sql(_tuned)})')}, " + ", ".join(hits_sql(x, BUDGET, U) for x in SHIFTED))
        _SHIFT.append(f"SELECT * FROM ({_ctes} " + " UNION ALL ".join(_count_of(x, BUDGET, f"'{x}' AS method, {_tuned} AS tuned_d, {_asked} AS asked_d") for x in SHIFTED) + ")")
register("workload_shift", workload_shift, rated_sql(_SHIFT))


def ltb_tuned_probe(spark, sf):
    """Start level from a correlated sample, asked for correlated ranges."""
    s = Setup(spark, sf, VIEW)
    return m.answer(s, "local-tree-sampled", BUDGET, s.ends("correlated", LENGTH), tuning.alike(s.k, _sample(s, 8), s.n))


register("ltb_tuned_probe", ltb_tuned_probe, with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql('correlated', U, LENGTH)}), {_own_sample(f'SELECT a, b FROM ({_sample_sql(8)})')}, {hits_sql('local-tree-sampled', BUDGET, U)} SELECT qid, a, b, (a, b) IN (SELECT (a, b) FROM {tag('local-tree-sampled', BUDGET)}_hit) AS maybe FROM ranges"))

for _name, _shift in (("ltb_wide_probe", 5), ("ltb_spacing_probe", 18)):
    register(_name, _on_batch("correlated", LENGTH, lambda s, r, x=_shift: m._tree(s, BUDGET, r, x)), batch_sql("correlated", LENGTH, m.tree_sql("w", f"SELECT {_shift} AS s", BUDGET), "w_hit"))

COARSE, HOT = 30, 10


def atf_probe(spark, sf):
    """Buckets split where a first batch of empty ranges met false positives; then the same batch again."""
    s = Setup(spark, sf, VIEW)
    seen = s.ends("empty_correlated", LENGTH)
    return fam.leaves_probe(fam.region_leaves(s.k, fam.adapted_regions(s.k, seen, COARSE), COARSE, COARSE), seen)


_SEEN = f"ranges AS MATERIALIZED ({ends_sql('empty_correlated', U, LENGTH)})"
_GAPS = f"""{_SEEN}, nxt AS (SELECT r.qid, r.a, r.b, k.k AS after FROM ranges r ASOF LEFT JOIN keys k ON r.b <= k.k), prv AS (SELECT x.*, k.k AS before FROM nxt x ASOF LEFT JOIN keys k ON x.a >= k.k),
gaps AS (SELECT qid, a, b, least(coalesce({DUCK.bit_length('xor(a, before)')}, 63), coalesce({DUCK.bit_length('xor(b, after)')}, 63)) AS level FROM prv)"""
register("sample_gaps", _on_batch("empty_correlated", LENGTH, lambda s, r: fam.sample_gaps(s.k, r, s.n)), with_keys(VIEW, _GAPS + " SELECT qid, a, b, level FROM gaps"))
_LEAF = "SELECT DISTINCT (k >> s) << s AS z, ((k >> s) << s) + (1::BIGINT << s) - 1 AS hi FROM (SELECT k, least(coalesce(s, {cold}), {shift})::INT AS s FROM keys LEFT JOIN regions ON k >> {shift} = region)"
_IN_LEAF = "SELECT qid, a, b, coalesce(hi >= a, false) AS maybe FROM ranges ASOF LEFT JOIN leaves ON b >= z"
register("atf_probe", atf_probe, with_keys(VIEW, f"""{_GAPS}, regions AS (SELECT region, greatest(min(level) - 1, 0) AS s FROM (SELECT level, unnest([a >> {COARSE}, b >> {COARSE}]) AS region FROM gaps WHERE level <= {COARSE}) GROUP BY region),
leaves AS ({_LEAF.format(cold=COARSE, shift=COARSE)}) {_IN_LEAF}"""))


def cbf_weighted(spark, sf):
    """Narrow buckets where queries are frequent, wide ones elsewhere."""
    s = Setup(spark, sf, VIEW)
    seen = s.ends("empty_correlated", LENGTH)
    return fam.leaves_probe(fam.region_leaves(s.k, fam.weighted_regions(seen, COARSE, HOT), COARSE, 22), seen)


register("cbf_weighted", cbf_weighted, with_keys(VIEW, f"""{_SEEN}, mass AS (SELECT a >> {COARSE} AS region, count(*) AS c FROM ranges GROUP BY 1), regions AS (SELECT region, {HOT} AS s FROM mass WHERE c >= (SELECT avg(c) FROM mass)),
leaves AS ({_LEAF.format(cold=22, shift=COARSE)}) {_IN_LEAF}"""))
# --- updates, shards, strings -----------------------------------------------------------------------------------------


def lhf_insert(spark, sf):
    s = Setup(spark, sf, VIEW)
    base = s.k.where("k % 10 <> 0")
    p = params_for_budget(base.count(), BUDGET, s.u)
    return updates.lhf_insert(f.lhf_codes(base, p), s.k.where("k % 10 = 0"), p)


register("lhf_insert", lhf_insert, with_keys(VIEW, f"par AS ({m.budget_par(BUDGET, U)} WHERE k % 10 <> 0), {_codes_sql(seeded(2, 1))} SELECT z FROM codes"))


def lhf_compact(spark, sf):
    s = Setup(spark, sf, VIEW)
    return updates.lhf_compact(s.k, s.n, BUDGET, s.u)[0]


register("lhf_compact", lhf_compact, ORACLES[f"lhf_codes_{VIEW}"])

PARTS = 64


def lhf_sharded_probe(spark, sf):
    """Shards of equal width in key space, each with its own parameters."""
    s = Setup(spark, sf, VIEW)
    return updates.sharded_probe(s.k, s.ends("correlated", LENGTH), BUDGET, [i * s.u // PARTS for i in range(1, PARTS)])


def _sharded_sql() -> str:
    wide = U // PARTS
    h = lambda x: local_hash(DUCK, f"({x} - first)", updates.ANY, "r")
    return with_keys(VIEW, f"""ranges AS MATERIALIZED ({ends_sql('correlated', U, LENGTH)}), q AS (SELECT DISTINCT a, b FROM ranges),
t0 AS (SELECT k // {wide} AS shard, count(*) * {2 ** (BUDGET - 2)} AS r, min(k) AS first, max(k) AS last FROM keys GROUP BY 1),
t AS (SELECT *, coalesce(sum(r) OVER (ORDER BY shard ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM t0),
codes AS (SELECT DISTINCT start + {h('k')} AS z FROM keys JOIN t ON k // {wide} = shard),
met AS (SELECT a, b, greatest(a, first) AS x, least(b, last) AS y, first, r, start FROM (SELECT a, b, unnest(list_distinct([least(a // {wide}, {PARTS - 1}), least(b // {wide}, {PARTS - 1})])) AS s FROM q) JOIN t ON s = shard WHERE greatest(a, first) <= least(b, last)),
cut AS (SELECT *, (y - first) // r - (x - first) // r AS spans FROM met),
halves AS (SELECT a, b, x, y, first, r, start FROM cut WHERE spans = 0 UNION ALL SELECT a, b, x, y - (y - first) % r - 1, first, r, start FROM cut WHERE spans = 1 UNION ALL SELECT a, b, y - (y - first) % r, y, first, r, start FROM cut WHERE spans = 1),
ends AS (SELECT a, b, {h('x')} AS lo, {h('y')} AS hi, r, start FROM halves),
pieces AS (SELECT a, b, start + lo AS lo, start + hi AS hi FROM ends WHERE lo <= hi UNION ALL SELECT a, b, start, start + hi FROM ends WHERE lo > hi UNION ALL SELECT a, b, start + lo, start + r - 1 FROM ends WHERE lo > hi UNION ALL SELECT a, b, start, start + r - 1 FROM cut WHERE spans > 1),
hit AS (SELECT DISTINCT p.a, p.b FROM pieces p ASOF JOIN codes c ON p.hi >= c.z WHERE c.z >= p.lo)
SELECT qid, a, b, (a, b) IN (SELECT (a, b) FROM hit) AS maybe FROM ranges""")


register("lhf_sharded_probe", lhf_sharded_probe, _sharded_sql())


def _url_sql(width: str) -> str:
    h = lambda x: strings.string_hash(DUCK, x, width)
    return f"""WITH s AS (SELECT page_id, regexp_replace(url, '^[a-z]+://', '') AS s FROM pages WHERE url IS NOT NULL), wd AS (SELECT max(octet_length(encode(s))) AS width FROM s), codes AS (SELECT DISTINCT {h('s')} AS z FROM s),
ranges AS (SELECT page_id AS qid, concat(substr(s, 1, length(s) - 1), '0') AS a, concat(substr(s, 1, length(s) - 1), '~') AS b FROM s),
ends AS (SELECT qid, {strings.head(DUCK, 'a', width)} = {strings.head(DUCK, 'b', width)} AS same, {h('a')} AS x, {h('b')} AS y FROM ranges),
pieces AS (SELECT qid, x AS lo, y AS hi FROM ends WHERE same AND x <= y UNION ALL SELECT qid, 0, y FROM ends WHERE same AND x > y UNION ALL SELECT qid, x, {strings.SPACE - 1} FROM ends WHERE same AND x > y),
hit AS (SELECT qid FROM ends WHERE NOT same UNION SELECT qid FROM pieces p WHERE EXISTS (SELECT 1 FROM codes WHERE z BETWEEN p.lo AND p.hi))
"""


def url_keys(spark, sf):
    """Ranges of URLs that differ in their last character."""
    s = read_table(spark, sf, "pages").where("url is not null").selectExpr("page_id", "regexp_replace(url, '^[a-z]+://', '') AS s")
    width = s.agg(F.max(F.octet_length("s"))).first()[0] or 8
    ranges = s.selectExpr("page_id AS qid", "concat(substr(s, 1, length(s) - 1), '0') AS a", "concat(substr(s, 1, length(s) - 1), '~') AS b")
    return strings.string_probe(SPARK, strings.string_codes(SPARK, s, "s", width), ranges, width)


register("url_keys", url_keys, _url_sql("(SELECT width FROM wd)") + "SELECT qid, a, b, qid IN (SELECT qid FROM hit) AS maybe FROM ranges")


# --- robustness -------------------------------------------------------------------------------------------------------

SWEEP_BITS = 20


def robustness_sweep(spark, sf):
    """False positive rates of all methods over D and length at 20 bits a key, with 95 % limits; a trie below its least
    size takes more. Tuned methods learn from a tenth of all the sweep's questions."""


    def make() -> list[tuple]:
        with gathered(Setup(spark, sf, VIEW, dealt_out(keys(spark, sf, VIEW)))) as s, held_empty(s, sweep_drawn(s)) as made:
            r, sample = Batch(made, "d", "len"), s.warm().tuned_on(made)
            return [(name, *rest) for name, _, *rest in all_budgets(s, m.METHODS, [SWEEP_BITS], r, sample)]

    return rated(spark, once(spark, sf, "sweep", make), "method string, d int, len int")


_SWEPT = with_keys(VIEW, f"{sweep_sql()}, ranges AS MATERIALIZED (SELECT * FROM swept), {counts_sql(U)}, ")
_SWEEP = _SWEPT + ", ".join(hits_sql(x, SWEEP_BITS, U) for x in m.METHODS) + " " + rated_sql([_count_of(x, SWEEP_BITS, f"'{x}' AS method", "d, len") for x in m.METHODS])
register("robustness_sweep", robustness_sweep, _SWEEP)


def robustness_summary(spark, sf):
    """Extremes over the degree of correlation and where each method is lost."""
    return measures.robustness(QUERIES["robustness_sweep"](spark, sf), "method", "len")


register("robustness_summary", robustness_summary, f"SELECT method, len, max(fpr) AS worst, min(fpr) AS best, coalesce(min(CASE WHEN fpr > 0.5 THEN d END), -1) AS lost_at FROM ({_SWEEP}) GROUP BY ALL")


def effectiveness_gap(spark, sf):
    """Orders of magnitude between the locality hash's rate and each other method's, by degree and length. Rates count half
    a positive more, so none is zero; `seen` says whether both had positives, else the gap is an estimate from below."""
    return measures.gaps(QUERIES["robustness_sweep"](spark, sf), "locality-hash", "d", "len")


register("effectiveness_gap", effectiveness_gap, measures.gaps_sql(_SWEEP, "locality-hash", "d, len"))
register("predictability", lambda spark, sf: measures.predictability(QUERIES["robustness_sweep"](spark, sf), "method", "len"), f"SELECT method, len, round(max(fpr) - min(fpr), 6) AS spread, round(stddev_pop(fpr), 6) AS deviation FROM ({_SWEEP}) GROUP BY ALL")


def lhf_sweep(spark, sf):
    """Rates of the locality hash alone over D and length at 12 bits a key. A plan, so that each query over it reads its keys."""
    s = Setup(spark, sf, VIEW)
    found = m.answer(s, "locality-hash", 12, sweep_ranges(s)).groupBy("d", "len").agg(F.count("*").alias("n_ranges"), F.sum(F.col("maybe").cast("long")).alias("positives"))
    return measures.with_limits(found)


_LHF_SWEEP = _SWEPT + hits_sql("locality-hash", 12, U) + " " + rated_sql([_count_of("locality-hash", 12, "d, len", "").replace("FROM ranges", "FROM ranges GROUP BY d, len")])
register("lhf_sweep", lhf_sweep, _LHF_SWEEP)



def _totals(grouped) -> DataFrame:
    found = grouped.agg(F.sum("n_ranges").alias("n_ranges"), F.max("fpr").alias("worst"))
    return found.withColumns({c: F.coalesce(c, F.lit(-1)) for c in ("d", "len")})


register("grid_cube", lambda spark, sf: _totals(lhf_sweep(spark, sf).cube("d", "len")), f"SELECT coalesce(d, -1) AS d, coalesce(len, -1) AS len, sum(n_ranges)::BIGINT AS n_ranges, max(fpr) AS worst FROM ({_LHF_SWEEP}) GROUP BY CUBE (d, len)")
register("grid_rollup", lambda spark, sf: _totals(lhf_sweep(spark, sf).rollup("d", "len")), ORACLES["grid_cube"].replace("CUBE (d, len)", "ROLLUP (d, len)"))


def grid_sets(spark, sf):
    return _totals(lhf_sweep(spark, sf).groupingSets([["d"], ["len"], []], "d", "len"))


register("grid_sets", grid_sets, ORACLES["grid_cube"].replace("CUBE (d, len)", "GROUPING SETS ((d), (len), ())"))

SEEDS = 40


def bound_vs_rate(spark, sf):
    """Mean rate over 40 hash draws against the bound, by budget and length, with its standard error. All draws are asked
    in one pass a budget: each has a code space of its own."""
    s = Setup(spark, sf, VIEW)
    asked = None
    for cell, length in enumerate(w.LENGTHS):
        one = w.ends(w.share(s.k, 10), "correlated", length, s.u, 8, cell).withColumn("len", F.lit(length))
        asked = one if asked is None else asked.union(one)
    empty = keep_empty(s.k, asked).select("a", "b", "len")
    drawn = [(i, p.c1, p.c2) for i, p in enumerate(seeded(2, seed) for seed in range(SEEDS))]
    seeds = F.broadcast(spark.createDataFrame(drawn, "seed long, c1 long, c2 long"))
    out = None
    for bits in (12, 16):
        p = params_for_budget(s.n, bits, s.u)
        hashed = lambda df, made: with_local_hash(df, made, p, factors=("c1", "c2"))  # noqa: B023, E731
        codes = hashed(s.k.crossJoin(seeds), [("z", "k")]).selectExpr(f"seed * {p.r}L + z AS z")
        each = empty.crossJoin(seeds).select(F.struct("a", "b", "len", "seed", "c1", "c2").alias("q"), "a", "b")
        pieces = f.lhf_pieces(each, p, lambda df: hashed(df.select("*", "q.c1", "q.c2"), [("x", "a"), ("y", "b")]))
        placed = pieces.selectExpr("q", f"q.seed * {p.r}L + lo AS lo", f"q.seed * {p.r}L + hi AS hi")
        hits = any_code_in(codes, placed, SEEDS * s.n).groupBy("q.len", "q.seed", "q.a").agg(F.max(F.col("hit").cast("long")).alias("hit"))
        one = hits.groupBy("len", "seed").agg(F.count("*").alias("n_ranges"), F.sum("hit").alias("positives")).withColumn("bits", F.lit(bits))
        out = one if out is None else out.union(one)
    return measures.against_bound(out)


def _bound_sql(length: int, cell: int, bits: int) -> str:
    """(bits, len, n_ranges, positives) of each hash draw."""
    h = lambda x: local_hash(DUCK, x, HashParams(2, "c1", "c2"), "r")
    made = f"SELECT * FROM ({ends_sql('correlated', U, length, 8, cell)}) WHERE {mixed(DUCK, 'qid', 10, 6)} = 0"
    seeds = ", ".join(f"({i}, {p.c1}, {p.c2})" for i, p in enumerate(seeded(2, seed) for seed in range(SEEDS)))
    return with_keys(VIEW, f"""seeds(seed, c1, c2) AS (VALUES {seeds}), q AS MATERIALIZED (SELECT DISTINCT a, b FROM ({w.empties_sql(made)})), par AS ({m.budget_par(bits, U)}),
codes AS (SELECT DISTINCT seed, {h('k')} AS z FROM keys, par, seeds),
cut AS (SELECT a, b, r, seed, c1, c2, b // r - a // r AS spans FROM q, par, seeds),
halves AS (SELECT a, b, r, seed, c1, c2, a AS x0, b AS y0 FROM cut WHERE spans = 0 UNION ALL SELECT a, b, r, seed, c1, c2, a, b - b % r - 1 FROM cut WHERE spans = 1 UNION ALL SELECT a, b, r, seed, c1, c2, b - b % r, b FROM cut WHERE spans = 1),
ends AS (SELECT a, b, r, seed, {h('x0')} AS x, {h('y0')} AS y FROM halves),
pieces AS (SELECT a, b, seed, x AS lo, y AS hi FROM ends WHERE x <= y UNION ALL SELECT a, b, seed, 0, y FROM ends WHERE x > y UNION ALL SELECT a, b, seed, x, r - 1 FROM ends WHERE x > y UNION ALL SELECT a, b, seed, 0, r - 1 FROM cut WHERE spans > 1),
hit AS (SELECT DISTINCT p.a, p.b, p.seed FROM pieces p ASOF JOIN codes c ON p.seed = c.seed AND p.hi >= c.z WHERE c.z >= p.lo)
SELECT {bits} AS bits, {length} AS len, (SELECT count(*) FROM q) AS n_ranges, (SELECT count(*) FROM hit WHERE hit.seed = seeds.seed) AS positives FROM seeds""")


register("bound_vs_rate", bound_vs_rate, "WITH e AS (" + " UNION ALL ".join(f"SELECT * FROM ({_bound_sql(x, c, bits)})" for c, x in enumerate(w.LENGTHS) for bits in (12, 16)) + ") SELECT bits, len, round(avg(positives / n_ranges), 6) AS fpr, round(stddev_samp(positives / n_ranges) / sqrt(count(*)), 6) AS error, round(least(1.0, len / pow(2.0, bits - 2)), 6) AS bound FROM e GROUP BY bits, len")

# --- grids ------------------------------------------------------------------------------------------------------------

#: (row, view, workload): the uniform view with both synthetic families, and two clustered views with withheld keys.
ROWS = (("uniform", "md5_60", "correlated"), ("uniform", "md5_60", "uncorrelated"), ("prices", "part_price", "heldout"), ("places", "user_time", "heldout"))
TENTH = 10


def grid_setup(spark, sf, view: str, kind: str, k: DataFrame | None = None) -> tuple[Setup, DataFrame]:
    """Keys of a grid's row (k: the view's, where they are kept) and the questions of all lengths, of which empty ones are asked (qid, a, b, len): from a tenth of the keys, which are
    withheld where the workload says so."""
    s, out = Setup(spark, sf, view, k), None
    if kind == "heldout":
        kept, asked = w.hold_out(s.k)
        s = Setup(spark, sf, view, kept)
    else:
        asked = w.share(s.k, TENTH)
    for cell, length in enumerate(w.LENGTHS):
        one = w.heldout(asked, length) if kind == "heldout" else w.ends(asked, kind, length, s.u, 8, cell)
        one = one.withColumn("len", F.lit(length))
        out = one if out is None else out.union(one)
    return s, out


def grid_sql(view: str, kind: str) -> str:
    """CTEs keys and ranges(qid, a, b, len) of a grid's row."""
    u, parts = universe(view), []
    for cell, length in enumerate(w.LENGTHS):
        made = heldout_sql(length) if kind == "heldout" else f"SELECT * FROM ({ends_sql(kind, u, length, 8, cell)}) WHERE {mixed(DUCK, 'qid', TENTH, 6)} = 0"
        parts.append(f"SELECT *, {length} AS len FROM ({made})")
    text = with_keys(view, f"ranges AS MATERIALIZED ({w.empties_sql(' UNION ALL '.join(parts))}), {counts_sql(u)}")
    return heldout_keys(view, text) if kind == "heldout" else text


def admissible(bits: int, n: int, u: int) -> bool:
    """Whether a budget stays below the cost of a lossless encoding, beyond which a filter has no use."""
    return bits * n <= models.space_lossless(n, u)


def all_budgets(s: Setup, names: tuple[str, ...], budgets: list[int], r: Batch, sample) -> list[tuple]:
    """(name, bits, len, n_ranges, positives): all filters in one pass over the questions where they can be sent."""
    with ThreadPoolExecutor(BESIDE) as pool:
        filters = m.together(s, names, budgets, sample, pool.map)
    if filters is None:
        return every([cells((name, bits), s, name, bits, r, sample) for bits in budgets for name in names])
    keys = packed.prefixes(s.k, 0).all() if s.known is None else s.sent
    with ThreadPoolExecutor(BESIDE) as pool:
        found = positives(keys, filters, r.asked, r.by, sum(r.n.values()), pool.map)
    return [(*cell, *q, n, found.get((*cell, *q), 0)) for cell in filters for q, n in r.n.items()]


def _grid(names: tuple[str, ...]):
    def run(spark, sf):
        rows = []
        for row, view, kind in ROWS:
            with held(dealt_out(keys(spark, sf, view))) as k:
                s, drawn = grid_setup(spark, sf, view, kind, k)
                with gathered(s), held_empty(s, drawn) as made:
                    _ = s.n if set(names) <= set(m.ROBUST) else s.warm()
                    r, sample = Batch(made, "len"), s.tuned_on(made) if set(names) & set(m.TUNED) else None
                    rows += [(row, kind, *x) for x in all_budgets(s, names, [b for b in BUDGETS if admissible(b, s.n, s.u)], r, sample)]
        return rated(spark, rows, "data string, workload string, method string, bits int, len int")

    parts = []
    for row, view, kind in ROWS:
        u = universe(view)
        counts = [f"SELECT c.* FROM ({_count_of(x, b, f'{chr(39)}{row}{chr(39)} AS data, {chr(39)}{kind}{chr(39)} AS workload, {chr(39)}{x}{chr(39)} AS method, {b} AS bits', 'len')}) c, nn WHERE {b} * n <= n * (log2({u}::DOUBLE / n) + 2)" for b in BUDGETS for x in names]
        parts.append(f"SELECT * FROM ({grid_sql(view, kind)}, " + ", ".join(hits_sql(x, b, u) for b in BUDGETS for x in names) + " " + " UNION ALL ".join(counts) + ")")
    return run, rated_sql(parts)


register("heuristic_grid", *_grid(m.HEURISTIC))
register("robust_grid", *_grid(m.ROBUST))


def nonempty_grid(spark, sf):
    """False negatives of every method over ranges with keys, at 16 bits a key."""
    s = Setup(spark, sf, VIEW)
    with held(s.k), held(s.ends("nonempty", LENGTH)) as made:
        r, sample = Batch(made), s.warm().tuned_on(s.ends("empty_correlated", LENGTH))
        found = every([cells((name,), s, name, BUDGET, r, sample) for name in m.METHODS])
    rows = [(name, n, n - hits) for name, n, hits in found]
    return spark.createDataFrame(rows, "method string, n_ranges long, false_negatives long")


register("nonempty_grid", nonempty_grid, with_keys(VIEW, "m AS (SELECT unnest([" + ", ".join(f"'{x}'" for x in m.METHODS) + "]) AS method) SELECT method, (SELECT count(*) FROM keys) AS n_ranges, 0::BIGINT AS false_negatives FROM m"))


def count_grid(spark, sf):
    """Mean error of counts, raw and corrected, for ranges with keys of several lengths and budgets."""
    s, rows = Setup(spark, sf, VIEW), []
    for cell, length in enumerate(COUNTED):
        with held(s.k), held(s.ends("nonempty", length, 8, cell)) as r:
            made = f.lhf_count(s.k.select(F.col("k").alias("z")), r, HashParams(s.u, 1, 0, s.n)).selectExpr("qid AS q_", "est AS exact")
            with held(made) as exact:
                for bits in (12, 20):
                    p = params_for_budget(s.n, bits, s.u)
                    both = f.correct_count(f.lhf_count(f.lhf_codes(s.k, p), r, p), p).join(grows(exact), F.expr("qid = q_"))
                    rows.append((bits, length, *both.agg(F.round(F.avg(F.expr("est - exact")), 4), F.round(F.avg(F.expr("corrected - exact")), 4)).first()))
    return spark.createDataFrame(rows, "bits int, len long, mean_raw double, mean_corrected double")


COUNTED = (2**10, 2**20, 2**30)
register("count_grid", count_grid, " UNION ALL ".join(f"SELECT * FROM ({counted_sql(x, b, c)} SELECT {b} AS bits, {x}::BIGINT AS len, round(avg(est - exact), 4) AS mean_raw, round(avg(corrected - exact), 4) AS mean_corrected FROM done JOIN ex ON qid = q_)" for c, x in enumerate(COUNTED) for b in (12, 20)))


def adversary(spark, sf):
    """Questions right next to a known hundredth of the keys, to all methods."""
    s = Setup(spark, sf, VIEW).warm()
    near = w.keep_empty(s.k, w.share(s.k, 100).selectExpr("k AS qid", "k + 1 AS a", f"k + {LENGTH} AS b"))
    with held(near) as made:
        r, sample = Batch(made), s.tuned_on(s.ends("empty_uncorrelated", LENGTH))
        rows = every([cells((name,), s, name, SWEEP_BITS, r, sample) for name in m.METHODS])
    return rated(spark, rows, "method string")


_NEAR = f"SELECT k AS qid, k + 1 AS a, k + {LENGTH} AS b FROM keys WHERE {mixed(DUCK, 'k', 100, 6)} = 0"
_BEFORE = f"SELECT a, b FROM ({ends_sql('empty_uncorrelated', U, LENGTH)}) WHERE {mixed(DUCK, 'qid', m.SAMPLE, 7)} = 0"
register("adversary", adversary, with_keys(VIEW, f"ranges AS MATERIALIZED ({w.empties_sql(_NEAR)}), {_own_sample(_BEFORE)}, " + ", ".join(hits_sql(x, SWEEP_BITS, U) for x in m.METHODS) + " " + rated_sql([_count_of(x, SWEEP_BITS, f"'{x}' AS method") for x in m.METHODS])))

_NORMAL = (("normal", "uncorrelated"), ("normal", "correlated"), ("md5_60", "normal"))


def normal_keys(spark, sf):
    """Normal keys with both query families, and uniform keys with queries at normal places."""
    rows = []
    # A normal key takes thirteen md5 sums, so keys are made once.
    with held(keys(spark, sf, "normal")) as normal, held(keys(spark, sf, "md5_60")) as uniform:
        for view, kind in _NORMAL:
            s = Setup(spark, sf, view, normal if view == "normal" else uniform)
            r = w.keep_empty(s.k, normal.selectExpr("k AS qid", "k div 4 AS a", f"k div 4 + {LENGTH - 1} AS b")) if kind == "normal" else s.ends(f"empty_{kind}", LENGTH)
            with held(r) as made:
                kept, _ = Batch(made), (s.n, s.ones)  # before jobs run beside each other
                rows += every([cells((view, kind, name), s, name, 14, kept) for name in ("locality-hash", "bucket")])
    return rated(spark, rows, "view string, workload string, method string")


def _normal_sql(view: str, kind: str) -> str:
    u = universe(view)
    made = w.empties_sql(f"SELECT k AS qid, k // 4 AS a, k // 4 + {LENGTH - 1} AS b FROM ({keys_sql(DUCK, 'normal')})") if kind == "normal" else ends_sql(f"empty_{kind}", u, LENGTH)
    return f"SELECT * FROM ({with_keys(view, f'ranges AS MATERIALIZED ({made}), {counts_sql(u)}, ')}" + ", ".join(hits_sql(x, 14, u) for x in ("locality-hash", "bucket")) + " " + " UNION ALL ".join(_count_of(x, 14, f"'{view}' AS view, '{kind}' AS workload, '{x}' AS method") for x in ("locality-hash", "bucket")) + ")"


register("normal_keys", normal_keys, rated_sql([_normal_sql(*x) for x in _NORMAL]))

OUTLIERS = 21


def outlier_ids(spark, sf):
    """Low-magnitude ids with 21 far outliers at 12 bits a key: the bulk lies in one block and is told apart without error,
    while a lossless encoding needs far more bits because of the outliers."""
    bulk = keys(spark, sf, "order_total")
    far = spark.range(OUTLIERS).selectExpr(f"{2**44} + id * {7919 * 2**30} AS k")
    s, rows = Setup(spark, sf, "type_time", bulk.union(far).distinct()), []
    for cell, length in enumerate(w.LENGTHS):
        with held(w.keep_empty(s.k, w.ends(bulk, "uncorrelated", length, universe("order_total"), 8, cell))) as made:
            r = Batch(made)
            rows += every([cells((name, length), s, name, 12, r) for name in ("locality-hash", "bucket", "per-level")])
    return rated(spark, rows, "method string, len int")


def _outliers_sql() -> str:
    u, parts = universe("type_time"), []
    for cell, length in enumerate(w.LENGTHS):
        made = f"SELECT qid, a, a + {length - 1} AS b FROM (SELECT k AS qid, {w.left_end(DUCK, 'uncorrelated', length, universe('order_total'), 8, cell)} AS a FROM bulk)"
        ctes = f"WITH bulk AS MATERIALIZED ({keys_sql(DUCK, 'order_total')}), keys AS MATERIALIZED (SELECT k FROM bulk UNION SELECT {2**44} + id * {7919 * 2**30} FROM range({OUTLIERS}) t(id)), ranges AS MATERIALIZED ({w.empties_sql(made)}), {counts_sql(u)}, " + ", ".join(hits_sql(x, 12, u) for x in ("locality-hash", "bucket", "per-level"))
        parts.append(f"SELECT * FROM ({ctes} " + " UNION ALL ".join(_count_of(x, 12, f"'{x}' AS method, {length} AS len") for x in ("locality-hash", "bucket", "per-level")) + ")")
    return rated_sql(parts)


register("outlier_ids", outlier_ids, _outliers_sql())


def theory_table(spark, sf):
    """Bits per key of every design with a closed form, by L and eps, and the budget below which the per-level design is
    smaller. Buckets are as narrow as the budget allows; their number and the trie's inner nodes are counted."""
    rows = []
    for view in ("event_us", "md5_60", "part_price"):
        s = Setup(spark, sf, view)
        n, u, wide = s.n, s.u, s.width(BUDGET)
        counted_ = (("bucket", models.space_bucket(s.ones[wide], u, 2**wide)), ("truncated-trie", models.space_truncated_trie(n, 0, s.inner)), ("learned-bitmap", models.space_learned_bitmap(n, 100)), ("lossless", models.space_lossless(n, u)))
        rows += [(view, name, 0, 0, round(bits / n, 4)) for name, bits in counted_]
        for length in w.LENGTHS:
            for one_in in (10, 100, 1000):
                closed = (("locality-hash", models.space_locality_hash), ("prefix-search", models.space_prefix_search), ("per-level", models.space_per_level), ("pointwise", models.space_pointwise), ("bound", models.space_bound))
                rows += [(view, name, length, one_in, round(space(n, length, 1 / one_in) / n, 4)) for name, space in closed]
    return spark.createDataFrame(rows, "view string, method string, len int, one_in int, bits_per_key double")


def _theory_sql(view: str) -> str:
    u = universe(view)
    closed = {"locality-hash": "log2(x) + 2", "prefix-search": "log2(x) + 3", "per-level": "1.44 * log2(x)", "pointwise": "log2(x)", "bound": "log2(x)"}
    cells = "(SELECT l AS len, e AS one_in, (l * e)::DOUBLE AS x FROM (SELECT unnest([1, 32, 1024]) AS l), (SELECT unnest([10, 100, 1000]) AS e))"
    return f"SELECT * FROM ({with_keys(view, f'ranges AS (SELECT 0 AS qid, 0 AS a, 0 AS b), {counts_sql(u)}, wd AS ({m.bucket_par(BUDGET, u)})')} SELECT '{view}' AS view, 'bucket' AS method, 0 AS len, 0 AS one_in, round(t * (log2({u}::DOUBLE / (t::DOUBLE * pow(2, j))) + 2) / n, 4) AS bits_per_key FROM ones JOIN wd ON j = s, nn UNION ALL SELECT '{view}', 'truncated-trie', 0, 0, round((10.0 * n + 10 * z) / n, 4) FROM nn, inner_nodes UNION ALL SELECT '{view}', 'learned-bitmap', 0, 0, round(log2(100) + 2.4, 4) UNION ALL SELECT '{view}', 'lossless', 0, 0, round(log2({u}::DOUBLE / n) + 2, 4) FROM nn" + "".join(f" UNION ALL SELECT '{view}', '{k}', len, one_in, round({v}, 4) FROM {cells}" for k, v in closed.items()) + ")"


register("theory_table", theory_table, " UNION ALL ".join(_theory_sql(v) for v in ("event_us", "md5_60", "part_price")))


def worst_regions(spark, sf):
    s = Setup(spark, sf, VIEW)
    return measures.worst_regions(f.cbf_probe(f.cbf_codes(s.k, 2**20, False), s.ends("empty_correlated", LENGTH), 2**20, s.n), 34, 10)


register("worst_regions_topk", worst_regions, with_keys(VIEW, f"{_SEEN}, q AS (SELECT DISTINCT a, b FROM ranges), {m.bucket_sql('c', 'SELECT 20 AS s')} SELECT a >> 34 AS region, count(*) AS false_positives FROM ranges WHERE (a, b) IN (SELECT (a, b) FROM c_hit) GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10"))

# --- operators around the filters -------------------------------------------------------------------------------------


def range_join_binned(spark, sf):
    """Keys in ranges, exactly: bins of 2^20, ranges once a bin, equality join, then the condition."""
    s = Setup(spark, sf, VIEW)
    r = s.ends("nonempty", 10**6).select("qid", "a", "b", F.explode(F.expr("sequence(shiftright(a, 20), shiftright(b, 20))")).alias("bin"))
    return r.join(s.k.selectExpr("k", "shiftright(k, 20) AS kb"), F.expr("bin = kb AND k BETWEEN a AND b")).groupBy("qid").agg(F.count("*").alias("n"))


register("range_join_binned", range_join_binned, with_keys(VIEW, f"r AS ({ends_sql('nonempty', U, 10**6)}), kr AS (SELECT k, row_number() OVER (ORDER BY k) AS i FROM keys), h AS (SELECT r.*, i AS upto FROM r ASOF JOIN kr ON b >= k) SELECT qid, upto - coalesce(i, 0) AS n FROM h ASOF LEFT JOIN kr ON a > k"))


def asof_successor(spark, sf):
    s = Setup(spark, sf, VIEW)
    points = s.ends("uncorrelated", LENGTH).selectExpr("qid", "a", "-a AS m")
    return predecessor(s.k.selectExpr("-k AS z"), points, "m", n=s.n).selectExpr("qid", "a", "coalesce(-pred.z, -1) AS succ")


register("asof_successor", asof_successor, with_keys(VIEW, f"ranges AS ({ends_sql('uncorrelated', U, LENGTH)}) SELECT qid, a, coalesce(k, -1) AS succ FROM ranges ASOF LEFT JOIN keys ON a <= k"))


def codes_setops(spark, sf):
    """Sizes of union, intersection and difference of the codes of two halves of the keys."""
    s = Setup(spark, sf, VIEW)
    p = params_for_budget(s.n, 8, s.u)
    one, two = f.lhf_codes(s.k.where("k % 2 = 0"), p), f.lhf_codes(s.k.where("k % 2 = 1"), p)
    named = lambda name, df: df.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
    return named("union", f.lhf_merge(one, two)).union(named("intersect", one.intersect(two))).union(named("except", one.subtract(two)))


_HALVES = f"{_par_sql(VIEW, 8)}, one AS (SELECT DISTINCT {local_hash(DUCK, 'k', seeded(2, 1), _R)} AS z FROM keys WHERE k % 2 = 0), two AS (SELECT DISTINCT {local_hash(DUCK, 'k', seeded(2, 1), _R)} AS z FROM keys WHERE k % 2 = 1)"
register("codes_setops", codes_setops, with_keys(VIEW, _HALVES + " SELECT 'union' AS op, count(*) AS n FROM (SELECT z FROM one UNION SELECT z FROM two) UNION ALL SELECT 'intersect', count(*) FROM (SELECT z FROM one INTERSECT SELECT z FROM two) UNION ALL SELECT 'except', count(*) FROM (SELECT z FROM one EXCEPT SELECT z FROM two)"))


def semi_join_prefilter(spark, sf):
    """Customers with an order whose total lies in a band round their balance: the filter first, the exact join on the rest."""
    s = Setup(spark, sf, "order_total")
    asked = read_table(spark, sf, "customer").where("c_acctbal is not null").selectExpr("c_custkey AS qid", "CAST(round(c_acctbal * 100) AS BIGINT) * 40 + 4000000 AS a").selectExpr("qid", "a", "a + 4999 AS b")
    left = m.answer(s, "locality-hash", 12, asked).where("maybe").drop("maybe")
    return any_code_in(s.k.selectExpr("k AS z"), left.selectExpr("*", "a AS lo", "b AS hi"), s.n).where("hit").select("qid")


register("semi_join_prefilter", semi_join_prefilter, with_keys("order_total", "asked AS (SELECT c_custkey AS qid, CAST(round(c_acctbal * 100) AS BIGINT) * 40 + 4000000 AS a FROM customer) SELECT qid FROM asked WHERE EXISTS (SELECT 1 FROM keys WHERE k BETWEEN a AND a + 4999)"))

register("window_filters_sliding", lambda spark, sf: windows.window_filters(read_table(spark, sf, "events"), "2 days", "1 day", "1 hour", 3600).selectExpr("CAST(start AS STRING) AS start", "n", "CAST(size(codes) AS BIGINT) AS codes"), "WITH e AS (SELECT ts, user_id * 1048576 + hour(ts) AS z, unnest([0, 1]) AS back FROM events), d AS (SELECT ts, z, epoch_us(ts) // 86400000000 - back AS day FROM e) SELECT strftime(make_timestamp(day * 86400000000), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, count(DISTINCT z) AS codes FROM d GROUP BY day")
register("window_filters_session", lambda spark, sf: windows.session_counts(read_table(spark, sf, "events"), "6 hours", "1 hour").selectExpr("user_id", "CAST(start AS STRING) AS start", "n"))


ORACLES["window_filters_session"] = "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, CAST(min(ts) AS VARCHAR) AS start, count(*) AS n FROM s GROUP BY user_id, g"

# --- times ------------------------------------------------------------------------------------------------------------


def timed(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - began, 4)


def construction_times(spark, sf):
    """Seconds to build each filter of a tenth, once and ten times as many uniform keys as there are line items, averaged
    over budgets; for the tuned one, the seconds of tuning on n/10 small uncorrelated ranges apart. Keys are kept, in no
    order, before a clock runs; every build sorts for itself."""
    rows, base = [], read_table(spark, sf, "lineitem").count()
    for n in (base // 10, base, 10 * base):
        if n:
            rows += constructed(spark, n, spark.sparkContext.defaultParallelism)
    return spark.createDataFrame(rows, "method string, n long, seconds double, tuning_seconds double")


def constructed(spark, n: int, tasks: int) -> list[tuple]:
    """(method, n, seconds, tuning_seconds) for n draws."""
    u, spent = universe("md5_60"), {}
    with held(dealt.scattered(dealt.drawn(spark, n, 60, 12, 4 * tasks), 60, n, tasks)) as made:
        made.count()
        starts = dealt.even(0, u - 1, n)
        began = time.perf_counter()
        with dealt.ordered(made, starts, u - 1, tasks) as inside:
            ones = f.ones_of(dealt.parted(inside))
            sample = dealt.nearest(inside, made, _small_ranges(u))
            n_keys = inside.n
        tuning_seconds = round(time.perf_counter() - began, 4)
        for bits in (12, 20):
            for method, build in builds(made, n, n_keys, bits, ones, sample, starts, u, tasks).items():
                began = time.perf_counter()
                build()
                spent[method] = spent.get(method, 0.0) + (time.perf_counter() - began) / 2
                dealt.tidy(spark)
    return [(x, n, round(t, 4), tuning_seconds if x in ("prefix-bloom",) else 0.0) for x, t in spent.items()]


def _small_ranges(u: int):
    """Ends of `workloads.ends` for a tenth of an array of keys: uncorrelated, of LENGTH."""

    def ends(k):
        k = k[mixed_values(k, 10, 6) == 0]
        a = mixed_values(k, u - LENGTH, 150)
        return a, a + LENGTH - 1

    return ends


def builds(made: DataFrame, n: int, n_keys: int, bits: int, ones: dict[int, int], sample: tuning.Alike, starts, u: int, tasks: int) -> dict[str, Callable[[], object]]:
    """Jobs that build each filter of arrays of keys at a budget; ones, sample: what sizes and the tuned filter follow."""
    w_, p = u.bit_length() - 1, params_for_budget(n, bits, u)
    wide = min((j for j, t in ones.items() if t and j <= w_ and models.space_bucket(t, u, 2**j) <= bits * n_keys), default=w_)
    one, two = tuning.tpb_tune(ones, sample, bits, u)
    size, words = max(64, bits * n), m.tree_words(n, bits)

    def in_order(build):
        with dealt.ordered(made, starts, u - 1, tasks) as inside:
            timed(build(inside))

    def shifted(by: int):
        last = (u - 1) >> by
        return dealt.code_set(made, [lambda k: k >> by], dealt.even(0, last, n), last, tasks)

    return {
        "locality-hash": lambda: timed(dealt.code_set(made, [lambda k: h_values(k, p)], dealt.even(0, p.r - 1, n), p.r - 1, tasks)),
        "bucket": lambda: timed(shifted(wide)),
        "truncated-trie": lambda: in_order(dealt.trie_leaves),
        "learned-bitmap": lambda: in_order(lambda inside: dealt.learned_codes(inside, m.EVERY, m.EVERY * m.slots(bits))),
        "prefix-bloom": lambda: (timed(shifted(one)), timed(dealt.bitmap(made, packed.prefix_places(two, size, HASHES), size, tasks))),
        "per-level": lambda: timed(dealt.bitmap(made, packed.level_places(m.levels(bits), bits * n), bits * n, tasks)),
        "local-tree": lambda: timed(dealt.bitmap(made, packed.tree_places(0, m.HEIGHT, words, m.TREE_HASHES), (words * m.TREE_HASHES) << (m.HEIGHT + 1), tasks)),
    }


def probed(spark, sf, kinds: tuple[str, ...], lengths: tuple[int, ...]) -> list[tuple]:
    """(method, workload, len, n_ranges, micros) at 16 bits a key. Keys and questions are kept before a clock runs."""
    rows = []
    with gathered(Setup(spark, sf, VIEW, dealt_out(keys(spark, sf, VIEW)))) as s:
        s.warm()
        for length in lengths:
            with held_empty(s, s.ends("correlated", length)) as empty, held(s.ends("nonempty", length)) as met:
                sample = s.tuned_on(empty)
                for kind in kinds:
                    r = empty if kind == "empty_correlated" else met
                    n = r.count()
                    rows += [(name, kind, length, n, round(timed(m.answer(s, name, BUDGET, r, sample)) / max(n, 1) * 1e6, 3)) for name in m.METHODS]
    return rows


PROBED = ("empty_correlated", "nonempty")


def probe_times(spark, sf):
    """Microseconds a query in batches at 16 bits a key, over empty correlated ranges and ranges with keys, by length."""
    rows = once(spark, sf, "probe_times", lambda: probed(spark, sf, PROBED, w.LENGTHS))
    return spark.createDataFrame(rows, "method string, workload string, len int, n_ranges long, micros double")


register("construction_times", construction_times)
register("probe_times", probe_times)
