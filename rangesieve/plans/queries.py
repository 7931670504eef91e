"""Registered queries: methods, baselines, measures and experiments on the given tables, each with SQL where it can."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangesieve.functions import models
from rangesieve.functions.hashing import DUCK, SPARK, HashParams, draw, h_value, local_hash, local_hash_fast, local_hash_pow2, mixed, params_for_budget, params_for_error, power_of_two, seeded
from rangesieve.functions.packed import EliasFano, find, pack, unpack
from rangesieve.functions.ship import ship
from rangesieve.operators import filters as f
from rangesieve.operators.order import any_code_in, exact_nonempty, keep_empty, predecessor, questions, rank
from rangesieve.plans import methods as m
from rangesieve.plans import workloads as w
from rangesieve.plans.methods import EVERY, HASHES, Setup, answer_sql, counts_sql, ends_sql, hits_sql, places, tag, with_keys
from rangesieve.sources.keys import VIEWS, keys, keys_sql, read_table, universe, with_outliers
from rangesieve.streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

BUDGET, LENGTH = 16, 32
VIEW = "event_us"
U = universe(VIEW)


def register(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


# --- locality hash ----------------------------------------------------------------------------------------------------


def _params(k: DataFrame, view: str, bits: int = BUDGET, seed: int = 1) -> HashParams:
    return params_for_budget(k.count(), bits, universe(view), seed)


def _par_sql(view: str, bits: int = BUDGET) -> str:
    return f"par AS ({m.budget_par(bits, universe(view))})"


_R = "(SELECT r FROM par)"


def _codes_sql(p: HashParams) -> str:
    return f"codes AS (SELECT DISTINCT {local_hash(DUCK, 'k', p, 'r')} AS z FROM keys, par)"


def _codes(view: str) -> Query:
    def run(spark, sf):
        k = keys(spark, sf, view)
        return f.lhf_codes(k, _params(k, view))

    return run


for _view in ("event_us", "md5_60", "mixed62", "part_price", "user_time", "normal"):
    register(f"lhf_codes_{_view}", _codes(_view), with_keys(_view, f"{_par_sql(_view)}, {_codes_sql(seeded(2, 1))} SELECT z FROM codes"))


def lhf_codes_pow2(spark, sf):
    k = keys(spark, sf, "order_total")
    p = power_of_two(_params(k, "order_total", 12))
    return k.select(F.expr(local_hash_pow2("k", p)).alias("z")).distinct()


def _pow2_sql() -> str:
    p = seeded(2, 1)
    return with_keys("order_total", f"par AS (SELECT CAST(2 ** ceil(log2(least(count(*) * {2 ** 10}, {universe('order_total')}))) AS BIGINT) AS r FROM keys), {_codes_sql(p)} SELECT z FROM codes")


register("lhf_codes_pow2", lhf_codes_pow2, _pow2_sql())


def lhf_codes_fast(spark, sf):
    """With the practical hash, places in a block are kept (neighbours stay neighbours), and few codes meet."""
    k = keys(spark, sf, VIEW)
    p = _params(k, VIEW)
    codes = k.selectExpr(f"{local_hash_fast('k', p)} AS z", f"{local_hash_fast('k + 1', p)} AS next", f"pmod(k + 1, {p.r}) > 0 AS same")
    torn = F.sum(F.expr(f"CAST(same AND next <> (z + 1) % {p.r} AS BIGINT)"))
    return codes.agg(torn.alias("torn"), (F.count("*") - F.count_distinct("z") <= 10 + F.count("*") / 2 ** (BUDGET - 2)).alias("few_meet"))


register("lhf_codes_fast", lhf_codes_fast, "SELECT 0::BIGINT AS torn, true AS few_meet")


def _probe(view: str, kind: str, length: int, bits: int, degree: int = 8) -> Query:
    def run(spark, sf):
        s = Setup(spark, sf, view)
        return m.answer(s, "locality-hash", bits, s.ends(kind, length, degree))

    return run


for _name, _view, _kind, _length, _bits, _degree in (
    ("lhf_probe_uncorrelated", "event_us", "uncorrelated", 1024, 12, 8),
    ("lhf_probe_correlated", "event_us", "correlated", 32, 16, 8),
    ("lhf_probe_nonempty", "event_us", "nonempty", 32, 16, 8),
    ("lhf_probe_points", "event_us", "correlated", 1, 12, 8),
    ("lhf_probe_wide_universe", "md5_60", "correlated", 1024, 16, 8),
    ("lhf_probe_multiblock", "price_cents", "uncorrelated", 1024, 8, 8),
    ("lhf_probe_clustered", "user_time", "correlated", 32, 16, 8),
    ("lhf_probe_low_budget", "part_price", "uncorrelated", 1024, 8, 8),
    ("time_windows", "type_time", "correlated", 1_000_000, 24, 2),
):
    register(_name, _probe(_view, _kind, _length, _bits, _degree), answer_sql("locality-hash", _bits, _view, ends_sql(_kind, universe(_view), _length, _degree)))


def _pieces(view: str, length: int, bits: int, spans: int) -> tuple[Query, str]:
    """Pieces in code space of the questions that cross so many block borders, and the answers to those."""

    def run(spark, sf):
        s = Setup(spark, sf, view)
        p = params_for_budget(s.n, bits, s.u)
        r = s.ends("uncorrelated", length).where(f"b div {p.r} - a div {p.r} = {spans}")
        wraps = f.lhf_pieces(questions(r), p).groupBy("q").agg(F.count("*").alias("pieces")).selectExpr("q.a AS x_", "q.b AS y_", "pieces")
        return m.answer(s, "locality-hash", bits, r).join(wraps, F.expr("a = x_ AND b = y_")).select("qid", "a", "b", "pieces", "maybe")

    u = universe(view)
    text = answer_sql("locality-hash", bits, view, f"SELECT e.* FROM ({ends_sql('uncorrelated', u, length)}) e, ({m.budget_par(bits, u)}) WHERE b // r - a // r = {spans}", f"qid, a, b, (SELECT count(*) FROM {tag('locality-hash', bits)}_pieces p WHERE p.a = ranges.a AND p.b = ranges.b) AS pieces")
    return run, text


register("lhf_probe_wrapped", *_pieces("event_us", 2**16, 10, 0))
register("lhf_probe_boundary", *_pieces("event_us", 2**16, 10, 1))


def lhf_probe_heldout(spark, sf):
    kept, gone = w.hold_out(keys(spark, sf, "part_price"))
    return m.answer(Setup(spark, sf, "part_price", kept), "locality-hash", 12, w.heldout(gone, LENGTH))


def heldout_keys(view: str, text: str) -> str:
    """SQL over all keys of a view, made to read nine tenths as keys; the CTE `every` has all."""
    base = f"({keys_sql(DUCK, view)})"
    return text.replace(f"WITH keys AS MATERIALIZED {base}", f"WITH every AS MATERIALIZED {base}, keys AS MATERIALIZED (SELECT k FROM every WHERE {mixed(DUCK, 'k', 10, 5)} <> 0)", 1)


def heldout_sql(length: int) -> str:
    return f"SELECT k AS qid, k AS a, k + {length - 1} AS b FROM every WHERE {mixed(DUCK, 'k', 10, 5)} = 0"


register("lhf_probe_heldout", lhf_probe_heldout, heldout_keys("part_price", answer_sql("locality-hash", 12, "part_price", heldout_sql(LENGTH))))


def lhf_probe_fast(spark, sf):
    """False negatives and rate with the practical hash, on questions at keys and on empty ones."""
    s = Setup(spark, sf, VIEW)
    p = params_for_budget(s.n, 12, s.u)
    missed = f.lhf_probe_fast(s.k, s.ends("nonempty", LENGTH), p).agg(F.sum(F.expr("CAST(NOT maybe AS BIGINT)")).alias("false_negatives"))
    rate = f.lhf_probe_fast(s.k, s.ends("empty_correlated", LENGTH), p).agg((F.avg(F.col("maybe").cast("int")) <= 1.5 * models.error_bound(LENGTH, 12)).alias("near_bound"))
    return missed.crossJoin(rate)


register("lhf_probe_fast", lhf_probe_fast, "SELECT 0::BIGINT AS false_negatives, true AS near_bound")

_ODD_RANGES = [(1, 5, 20), (1, 400, 401), (None, 9, 11), (None, 30, 31), (2, None, 11), (3, 9, None), (4, None, None), (5, 11, 9), (6, -3, -1), (7, -60, -50), (7, -4, 100), (8, 0, 0), (9, 10, 10), (9, 10, 10), (10, -(2**62), 2**62 - 1)]
_ODD_KEYS = [10, 10, 20, -2, None, 2**40, -(2**50)]


def odd_frames(spark) -> tuple[DataFrame, DataFrame]:
    """Keys with repeats, a null and negatives; questions with null, reversed and repeated ends, null and shared ids, and
    extra columns whose names working columns have, too."""
    k = spark.createDataFrame([(x,) for x in _ODD_KEYS], "k long")
    return k, spark.createDataFrame([(*r, i, "x", 0, 0, 0) for i, r in enumerate(_ODD_RANGES)], "qid long, a long, b long, row long, _m string, pred long, lo long, hi long")


#: Minutes of the events, shifted to lie on both sides of 0: many repeat, one in seven is null.
_ODD_KEY = "if(event_id % 7 = 0, NULL, {micros} div 60000000 - 20000)"
#: Ends of an event's question by event_id % 9, from its minute x: near, open, reversed, single, wide, negative.
_ODD_ENDS = [("x - 5", "x + 5"), ("NULL", "x"), ("x", "NULL"), ("NULL", "NULL"), ("x + 1", "x - 1"), ("x", "x"), ("x + 1", "x + 3"), (f"{-(2**62)}", f"{2**62 - 1}"), ("-x - 60000", "-x - 59990")]


def odd_tables(spark, sf) -> tuple[DataFrame, DataFrame]:
    """The same oddities as in `odd_frames`, made of the events: an event each has a key and a question."""
    events = read_table(spark, sf, "events").where("event_id is not null and ts is not null")
    minute = _ODD_KEY.format(micros=VIEWS[VIEW][1](SPARK))
    side = lambda i: f"CASE event_id % 9 {' '.join(f'WHEN {j} THEN CAST({e[i]} AS BIGINT)' for j, e in enumerate(_ODD_ENDS))} END"
    asked = events.selectExpr("event_id", f"{minute.replace('NULL', '0')} AS x")
    return events.selectExpr(f"CAST({minute} AS BIGINT) AS k"), asked.selectExpr("if(event_id % 5 = 0, NULL, event_id div 2) AS qid", f"{side(0)} AS a", f"{side(1)} AS b", "event_id AS row", "'x' AS _m", "0L AS pred", "0L AS lo", "0L AS hi")


def lhf_probe_odd(spark, sf):
    """No wrong "empty" on any frame: each odd question is answered true, false or null by rule. Lossless parameters."""
    k, r = odd_tables(spark, sf)
    p = HashParams(2**62, 1, 0, k.count())
    return f.lhf_probe(f.lhf_codes(k, p), r, p).select("row", "maybe")


def _odd_sql() -> str:
    minute = f"{VIEWS[VIEW][1](DUCK)} // 60000000 - 20000"
    side = lambda i: f"CASE event_id % 9 {' '.join(f'WHEN {j} THEN CAST({e[i]} AS BIGINT)' for j, e in enumerate(_ODD_ENDS))} END"
    return f"""WITH e AS (SELECT event_id, CASE WHEN event_id % 7 = 0 THEN 0 ELSE {minute} END AS x FROM events WHERE event_id IS NOT NULL AND ts IS NOT NULL), keys AS (SELECT DISTINCT x AS k FROM e WHERE event_id % 7 <> 0),
r AS (SELECT event_id AS row, {side(0)} AS a, {side(1)} AS b FROM e) SELECT row, CASE WHEN a <= b THEN coalesce(k >= a, false) END AS maybe FROM r ASOF LEFT JOIN keys ON r.b >= keys.k"""


register("lhf_probe_odd", lhf_probe_odd, _odd_sql())


def lhf_collisions(spark, sf):
    k = keys(spark, sf, "md5_60")
    p = _params(k, "md5_60", 12)
    return f.lhf_codes(k, p).agg((F.lit(p.n) - F.count("*")).alias("duplicates")).withColumn("expected", F.lit(round((p.n - 1) / 2 / 2**10, 6)))


register("lhf_collisions", lhf_collisions, with_keys("md5_60", f"{_par_sql('md5_60', 12)}, {_codes_sql(seeded(2, 1))} SELECT (SELECT count(*) FROM keys) - (SELECT count(*) FROM codes) AS duplicates, round(((SELECT count(*) FROM keys) - 1) / 2 / 1024.0, 6) AS expected"))


def ef_parts(spark, sf):
    """Rank, high part, low part and position of the high bit of each code."""
    k = keys(spark, sf, VIEW)
    codes = rank(f.lhf_codes(k, _params(k, VIEW)), "z")
    return codes.selectExpr("i", "z", "shiftright(z, 13) AS hi", "z & 8191 AS lo", "shiftright(z, 13) + i AS pos")


register("ef_parts", ef_parts, with_keys(VIEW, f"{_par_sql(VIEW)}, {_codes_sql(seeded(2, 1))} SELECT row_number() OVER (ORDER BY z) AS i, z, z >> 13 AS hi, z & 8191 AS lo, (z >> 13) + row_number() OVER (ORDER BY z) AS pos FROM codes"))


def ef_roundtrip(spark, sf):
    k = keys(spark, sf, VIEW)
    return unpack(pack(f.lhf_codes(k, _params(k, VIEW)), 13))


register("ef_roundtrip", ef_roundtrip, ORACLES[f"lhf_codes_{VIEW}"])


def ef_bits_per_key(spark, sf):
    """Bits of the packed form for each key, low and high parts, at several budgets; a shard has a code in each."""
    s, out = Setup(spark, sf, VIEW), None
    for bits in (8, 12, 16, 20, 24, 28):
        parts = rank(f.lhf_codes(s.k, params_for_budget(s.n, bits, s.u)), "z", n=s.n).selectExpr(f"shiftright(z, {bits - 2}) + i AS pos")
        one = parts.agg(F.lit(bits).alias("bits"), F.count("*").alias("codes"), F.round((F.count("*") * (bits - 2) + F.max("pos") + 1) / s.n, 3).alias("bits_per_key"))
        out = one if out is None else out.union(one)
    return out


register("ef_bits_per_key", ef_bits_per_key, with_keys(VIEW, ", ".join(f"p{b} AS ({m.budget_par(b, U)}), c{b} AS (SELECT DISTINCT {local_hash(DUCK, 'k', seeded(2, 1), 'r')} AS z FROM keys, p{b})" for b in (8, 12, 16, 20, 24, 28)) + " " + " UNION ALL ".join(f"SELECT {b} AS bits, count(*) AS codes, round((count(*) * {b - 2} + (max(z) >> {b - 2}) + count(*) + 1) / (SELECT count(*) FROM keys), 3) AS bits_per_key FROM c{b}" for b in (8, 12, 16, 20, 24, 28))))


def _points(s: Setup, below: int, stream: int) -> DataFrame:
    return s.k.selectExpr("k AS qid", f"{mixed(SPARK, 'k', below, stream)} AS y")


def ef_predecessor(spark, sf):
    s = Setup(spark, sf, VIEW)
    p = params_for_budget(s.n, BUDGET, s.u)
    return predecessor(f.lhf_codes(s.k, p), _points(s, p.r, 9), "y", n=s.n).select("qid", "y", F.col("pred.z").alias("pred"))


def ef_predecessor_packed(spark, sf):
    """The same on the packed bits: two selects of zeros give a cell, whose low parts are searched."""
    s = Setup(spark, sf, VIEW)
    p = params_for_budget(s.n, BUDGET, s.u)
    return find(pack(f.lhf_codes(s.k, p), BUDGET - 2, s.n), _points(s, p.r, 9), "y").select("qid", "y", "pred")


_PRED = with_keys(VIEW, f"{_par_sql(VIEW)}, {_codes_sql(seeded(2, 1))}, pts AS (SELECT k AS qid, {mixed(DUCK, 'k', _R, 9)} AS y FROM keys) SELECT qid, y, z AS pred FROM pts ASOF LEFT JOIN codes ON y >= z")
register("ef_predecessor", ef_predecessor, _PRED)
register("ef_predecessor_packed", ef_predecessor_packed, _PRED)

# The worked example: ten keys, L = 4, eps = 0.4. Fixed values.
EXAMPLE_KEYS = [9, 48, 50, 191, 226, 269, 335, 446, 487, 511]
EXAMPLE = HashParams(100, 10, 5, 10, 512)
EXAMPLE_PRIME = 2**31 - 1


#: A customer's orders are the keys of a small example each: cents of the total, cut to the example's universe.
_EXAMPLE_KEY = "CAST(round(o_totalprice * 100) AS BIGINT) % 512"


def example_codes(k: DataFrame) -> DataFrame:
    """k with its code under the example's hash."""
    return k.withColumn("z", F.expr(local_hash(SPARK, "k", EXAMPLE)))


def lhf_worked_example(spark, sf):
    """Each order's key under the example's hash."""
    return example_codes(read_table(spark, sf, "orders").selectExpr("o_orderkey", f"{_EXAMPLE_KEY} AS k").where("k is not null"))


register("lhf_worked_example", lhf_worked_example, f"SELECT o_orderkey, k, (10 * (k // 100) + 5 + k % 100) % 100 AS z FROM (SELECT o_orderkey, {_EXAMPLE_KEY} AS k FROM orders) WHERE k IS NOT NULL")


ASKED = (44, 47)


def example_answer(codes: list[int]) -> tuple:
    """The question ASKED to the packed codes of a few keys: hashed ends, their cell by select of zeros (0 beyond the
    last zero), predecessor (-1 if there is none), answer."""
    ef = EliasFano.encode(np.array(sorted(codes)), 3)
    lo, hi = h_value(ASKED[0], EXAMPLE), h_value(ASKED[1], EXAMPLE)
    zero = lambda i: ef.select(0, i) if i <= ef.length - ef.n else 0
    found = ef.predecessor(hi)
    return lo, hi, zero(hi >> 3), zero((hi >> 3) + 1), *ef.cell(hi), -1 if found is None else found, found is not None and found >= lo


def worked_question(spark, sf):
    """The worked example's question [44, 47], asked of the keys of every customer's orders."""
    ship(spark)
    k = read_table(spark, sf, "orders").selectExpr("o_custkey", f"{_EXAMPLE_KEY} AS k").where("o_custkey is not null and k is not null")
    held = example_codes(k).groupBy("o_custkey").agg(F.collect_set("z").alias("codes"))

    def run(batches):
        for pdf in batches:
            rows = [(key, *example_answer(codes)) for key, codes in zip(pdf.o_custkey, pdf.codes)]
            yield pd.DataFrame(rows, columns=["o_custkey", "lo", "hi", "zero_p", "zero_next", "first", "last", "pred", "maybe"])

    return held.mapInPandas(run, "o_custkey long, lo long, hi long, zero_p long, zero_next long, first long, last long, pred long, maybe boolean")


# The ends 44 and 47 have the codes 49 and 52, in cell 6: a zero comes after all codes of its cell and of those before.
register("worked_question", worked_question, f"""WITH c AS (SELECT DISTINCT o_custkey, (10 * (k // 100) + 5 + k % 100) % 100 AS z FROM (SELECT o_custkey, {_EXAMPLE_KEY} AS k FROM orders) WHERE o_custkey IS NOT NULL AND k IS NOT NULL),
g AS (SELECT o_custkey, count(*) AS n, max(z // 8) + 1 AS zeros, count(*) FILTER (z // 8 < 6) AS below, count(*) FILTER (z // 8 < 7) AS upto, max(z) FILTER (z <= 52) AS pred FROM c GROUP BY o_custkey)
SELECT o_custkey, 49 AS lo, 52 AS hi, CASE WHEN zeros >= 6 THEN 6 + below ELSE 0 END AS zero_p, CASE WHEN zeros >= 7 THEN 7 + upto ELSE 0 END AS zero_next, CASE WHEN zeros > 6 THEN below + 1 ELSE n + 1 END AS first, CASE WHEN zeros > 6 THEN upto ELSE n END AS last, coalesce(pred, -1) AS pred, coalesce(pred >= 49, false) AS maybe FROM g""")

COUNTED = 10**6


def _counted(s: Setup) -> DataFrame:
    p = params_for_budget(s.n, BUDGET, s.u)
    return f.correct_count(f.lhf_count(f.lhf_codes(s.k, p), s.ends("nonempty", COUNTED), p), p)


def lhf_count(spark, sf):
    return _counted(Setup(spark, sf, VIEW)).select("qid", "a", "b", "est", F.round("corrected", 6).alias("corrected"))


def lhf_count_error(spark, sf):
    s = Setup(spark, sf, VIEW)
    exact = f.lhf_count(s.k.select(F.col("k").alias("z")), s.ends("nonempty", COUNTED), HashParams(s.u, 1, 0, s.n)).selectExpr("qid AS q_", "est AS exact")
    both = _counted(s).join(exact, F.col("qid") == F.col("q_"))
    return both.agg(F.round(F.avg(F.col("est") - F.col("exact")), 4).alias("mean_raw"), F.round(F.avg(F.col("corrected") - F.col("exact")), 4).alias("mean_corrected"), F.max(F.abs(F.col("est") - F.col("exact"))).alias("worst"))


def counted_sql(length: int, bits: int, cell: int = 0) -> str:
    """CTEs up to done(qid, a, b, est, corrected) and ex(q_, exact)."""
    t = tag("locality-hash", bits)
    return with_keys(VIEW, f"""ranges AS MATERIALIZED ({ends_sql('nonempty', U, length, 8, cell)}), {counts_sql(U)}, {hits_sql('locality-hash', bits, U)},
ranked AS (SELECT z, row_number() OVER (ORDER BY z) AS i FROM {t}_codes), highs AS (SELECT p.*, coalesce(i, 0) AS upto FROM {t}_pieces p ASOF LEFT JOIN ranked c ON p.hi >= c.z),
both_ends AS (SELECT p.*, coalesce(i, 0) AS below FROM highs p ASOF LEFT JOIN ranked c ON p.lo > c.z),
est AS (SELECT a, b, sum(upto - below)::BIGINT AS est FROM both_ends GROUP BY ALL),
kr AS (SELECT k, row_number() OVER (ORDER BY k) AS i FROM keys), eh AS (SELECT g.*, coalesce(i, 0) AS upto FROM ranges g ASOF LEFT JOIN kr c ON g.b >= c.k), ex AS (SELECT g.qid AS q_, g.upto - coalesce(i, 0) AS exact FROM eh g ASOF LEFT JOIN kr c ON g.a > c.k),
done AS (SELECT qid, a, b, est, greatest(0.0, est::DOUBLE * (1 + (n - 1) / (2.0 * r)) - n::DOUBLE * (b - a + 1) / r::DOUBLE) AS corrected FROM ranges JOIN est USING (a, b), nn, {t}_par)
""")


_EST = counted_sql(COUNTED, BUDGET)
register("lhf_count", lhf_count, _EST + "SELECT qid, a, b, est, round(corrected, 6) AS corrected FROM done")
register("lhf_count_raw", lambda spark, sf: lhf_count(spark, sf).select("qid", "est"), _EST + "SELECT qid, est FROM done")
register("lhf_count_error", lhf_count_error, _EST + "SELECT round(avg(est - exact), 4) AS mean_raw, round(avg(corrected - exact), 4) AS mean_corrected, max(abs(est - exact)) AS worst FROM done JOIN ex ON qid = q_")


def lhf_params_table(spark, sf):
    """Parameters from (n, L, eps): r, low bits, bits a key, and the budget with the same bound."""
    n = keys(spark, sf, VIEW).count()
    rows = []
    for length in w.LENGTHS:
        for denominator in (10, 100, 1000):
            p = params_for_error(n, length, 1 / denominator, U)
            rows.append((length, denominator, p.r, max(0, (p.r // n).bit_length() - 1), round(models.space_locality_hash(n, length, 1 / denominator) / n, 6)))
    return spark.createDataFrame(rows, "len long, one_in long, r long, low_bits long, bits_per_key double")


register("lhf_params_table", lhf_params_table, with_keys(VIEW, f"nn AS (SELECT count(*) AS n FROM keys), c AS (SELECT len::BIGINT AS len, one_in::BIGINT AS one_in, least(n * len * one_in, {U})::BIGINT AS r, n FROM nn, (SELECT unnest([1, 32, 1024]) AS len), (SELECT unnest([10, 100, 1000]) AS one_in)) SELECT len, one_in, r, floor(log2(r // n))::BIGINT AS low_bits, round(log2(len * one_in) + 2, 6) AS bits_per_key FROM c"))


def lhf_merge(spark, sf):
    k = keys(spark, sf, VIEW)
    p = _params(k, VIEW)
    return f.lhf_merge(f.lhf_codes(k.where("k % 2 = 0"), p), f.lhf_codes(k.where("k % 2 = 1"), p))


register("lhf_merge", lhf_merge, ORACLES[f"lhf_codes_{VIEW}"])

# --- buckets ----------------------------------------------------------------------------------------------------------


def _cbf_sql(kind: str, shift: int, columns: str = "qid, a, b") -> str:
    return with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql(kind, U, LENGTH)}), q AS (SELECT DISTINCT a, b FROM ranges), {m.bucket_sql('c', f'SELECT {shift} AS s')} SELECT {columns}, (a, b) IN (SELECT (a, b) FROM c_hit) AS maybe FROM ranges")


def _cbf(kind: str, s: int) -> Query:
    def run(spark, sf):
        k = Setup(spark, sf, VIEW)
        return f.cbf_probe(f.cbf_codes(k.k, s, False), k.ends(kind, LENGTH), s, k.n)

    return run


for _kind in ("uncorrelated", "correlated", "nonempty"):
    register(f"cbf_probe_{_kind}", _cbf(_kind, 2**14), _cbf_sql(_kind, 14))
register("cbf_lossless", _cbf("correlated", 1), _cbf_sql("correlated", 0))
register("cbf_one_bucket", _cbf("correlated", 2**42), _cbf_sql("correlated", 42))

for _view in ("event_us", "md5_60", "part_price"):
    register(f"cbf_ones_{_view}", lambda spark, sf, v=_view: f.cbf_ones_by_width(keys(spark, sf, v)), with_keys(_view, "js AS (SELECT unnest(range(63))::INT AS j) SELECT j, count(DISTINCT k >> j) AS t FROM js, keys GROUP BY j"))


def cbf_choice(spark, sf):
    """Width that a budget allows, and the space it takes, for each budget."""
    rows = []
    for view in ("event_us", "md5_60", "part_price"):
        k = keys(spark, sf, view)
        n, u = k.count(), universe(view)
        ones = {r.j: r.t for r in f.cbf_ones_by_width(k).collect()}
        for bits in (8, 12, 16, 20, 24, 28):
            fits = [j for j, t in ones.items() if 2**j <= u and models.space_bucket(t, u, 2**j) <= bits * n]
            rows.append((view, bits, min(fits) if fits else None))
    return spark.createDataFrame(rows, "view string, bits int, log_width int")


_CHOICES = " UNION ALL ".join(f"SELECT '{v}' AS view, {universe(v)} AS u, j, t FROM ({ORACLES[f'cbf_ones_{v}']})" for v in ("event_us", "md5_60", "part_price"))
register("cbf_choice", cbf_choice, f"WITH o AS ({_CHOICES}), n AS (SELECT view AS nv, t AS n FROM o WHERE j = 0), b AS (SELECT unnest([8, 12, 16, 20, 24, 28]) AS bits) SELECT view, bits, min(CASE WHEN pow(2, j) <= u AND t * (log2(u::DOUBLE / (t::DOUBLE * pow(2, j))) + 2) <= bits * n THEN j END) AS log_width FROM o JOIN n ON view = nv, b GROUP BY view, bits")


def cbf_fp_cause(spark, sf):
    """For false positives: whether a key left of a lies in a's bucket, or one right of b in b's."""
    s = 2**22
    k = Setup(spark, sf, VIEW)
    z = k.k.select(F.col("k").alias("z"))
    positive = f.cbf_probe(f.cbf_codes(k.k, s, False), k.ends("empty_correlated", LENGTH), s, k.n).where("maybe").drop("maybe")
    left = any_code_in(z, positive.selectExpr("qid", "a", "b", f"a div {s} * {s} AS lo", "a - 1 AS hi"), k.n).selectExpr("qid", "a", "b", "hit AS from_left")
    right = any_code_in(z, left.selectExpr("*", "b + 1 AS lo", f"b div {s} * {s} + {s - 1} AS hi"), k.n)
    return right.selectExpr("qid", "from_left", "hit AS from_right")


register("cbf_fp_cause", cbf_fp_cause, f"WITH pos AS ({_cbf_sql('empty_correlated', 22)}), keys AS MATERIALIZED ({keys_sql(DUCK, VIEW)}), l AS (SELECT p.*, coalesce(k >= a >> 22 << 22, false) AS from_left FROM (SELECT * FROM pos WHERE maybe) p ASOF LEFT JOIN keys ON a > k) SELECT qid, from_left, coalesce(k <= (b >> 22 << 22) + {2**22 - 1}, false) AS from_right FROM l ASOF LEFT JOIN keys ON b < k")


def cbf_bitmap_count(spark, sf):
    """Dense form: bits set per 32,768 buckets of width 2^10 prices."""
    k = keys(spark, sf, "price_cents").selectExpr("k div 1024 AS z")
    return k.groupBy(F.bitmap_bucket_number("z").alias("part")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("z"))).alias("t"))


register("cbf_bitmap_count", cbf_bitmap_count, with_keys("price_cents", "z AS (SELECT DISTINCT k // 1024 AS z FROM keys) SELECT CASE WHEN z > 0 THEN 1 + (z - 1) // 32768 ELSE z // 32768 END AS part, count(*) AS t FROM z GROUP BY part"))


def cbf_and_lhf(spark, sf):
    """Both filters, each with half the budget; maybe only if both say so."""
    s = Setup(spark, sf, VIEW)
    one = m.answer(s, "bucket", 12, s.ends("empty_correlated", LENGTH)).withColumnRenamed("maybe", "m1")
    return m.answer(s, "locality-hash", 12, one).selectExpr("qid", "m1", "maybe AS m2", "m1 AND maybe AS maybe")


register("cbf_and_lhf", cbf_and_lhf, with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql('empty_correlated', U, LENGTH)}), {counts_sql(U)}, {hits_sql('bucket', 12, U)}, {hits_sql('locality-hash', 12, U)}, both_of AS (SELECT qid, (a, b) IN (SELECT (a, b) FROM {tag('bucket', 12)}_hit) AS m1, (a, b) IN (SELECT (a, b) FROM {tag('locality-hash', 12)}_hit) AS m2 FROM ranges) SELECT qid, m1, m2, m1 AND m2 AS maybe FROM both_of"))

# --- baselines, all at the same budget --------------------------------------------------------------------------------


def _on_batch(kind: str, length: int, made) -> Query:
    def run(spark, sf):
        s = Setup(spark, sf, VIEW)
        return made(s, s.ends(kind, length))

    return run


def batch_sql(kind: str, length: int, ctes: str, hit: str) -> str:
    """Answers from CTEs that define the pairs of ends `hit`, over nn(n), nb and q."""
    return with_keys(VIEW, f"ranges AS MATERIALIZED ({ends_sql(kind, U, length)}), {counts_sql(U)}, {ctes} SELECT qid, a, b, (a, b) IN (SELECT (a, b) FROM {hit}) AS maybe FROM ranges")


for _name, _method in (("ttf_probe_real", "truncated-trie"), ("lbf_probe", "learned-bitmap"), ("tpb_probe", "prefix-bloom"), ("plb_probe", "per-level"), ("ltb_probe", "local-tree"), ("ltb_se_probe", "local-tree-sampled"), ("ltb_ss_probe", "local-tree-spaced"), ("cbf_probe_budget", "bucket")):
    register(_name, _on_batch("correlated", LENGTH, lambda s, r, x=_method: m.answer(s, x, BUDGET, r)), answer_sql(_method, BUDGET, VIEW, ends_sql("correlated", U, LENGTH)))

register("exact_nonempty", _on_batch("correlated", LENGTH, lambda s, r: exact_nonempty(s.k, r)), with_keys(VIEW, f"ranges AS ({ends_sql('correlated', U, LENGTH)}) SELECT qid, a, b, coalesce(k >= a, false) AS truth FROM ranges ASOF LEFT JOIN keys ON b >= k"))
register("keep_empty", _on_batch("empty_correlated", LENGTH, lambda s, r: r), with_keys(VIEW, f"ranges AS ({ends_sql('empty_correlated', U, LENGTH)}) SELECT qid, a, b FROM ranges"))
register("minmax_probe", _on_batch("uncorrelated", LENGTH, lambda s, r: f.minmax_probe(s.k, r)), with_keys(VIEW, f"ranges AS ({ends_sql('uncorrelated', U, LENGTH)}) SELECT qid, a, b, b >= (SELECT min(k) FROM keys) AND a <= (SELECT max(k) FROM keys) AS maybe FROM ranges"))

_POINTS = [100 + j for j in range(HASHES)]


def _pointwise_sql(length: int) -> str:
    return batch_sql("correlated", length, f"""bits AS (SELECT DISTINCT {places('k', f'({BUDGET} * n)', _POINTS)} AS place FROM keys, nn),
pts AS (SELECT a, b, unnest(range(a, b + 1)) AS x FROM q), asked AS (SELECT a, b, x, {places('x', f'({BUDGET} * n)', _POINTS)} AS place FROM pts, nn),
live AS (SELECT a, b, x FROM asked JOIN bits USING (place) GROUP BY ALL HAVING count(*) = {HASHES})""", "live")


for _name, _length in (("pointwise_probe", LENGTH), ("bloom_points", 1)):
    register(_name, _on_batch("correlated", _length, lambda s, r: f.pointwise_probe(s.k, r, BUDGET * s.n, HASHES)), _pointwise_sql(_length))

register("ttf_leaves", lambda spark, sf: f.ttf_leaves(keys(spark, sf, VIEW)), with_keys(VIEW, f"ranges AS (SELECT 0 AS qid, 0 AS a, 0 AS b), {counts_sql(U)}, {m.trie_leaves('t', 'SELECT 0 AS m')} SELECT z, hi, k, s FROM t_leaves"))
register("ttf_probe_hash", _on_batch("correlated", 1, lambda s, r: f.ttf_probe_points(f.ttf_leaves(s.k), r, 6, s.n)), batch_sql("correlated", 1, f"{m.trie_leaves('t', 'SELECT 0 AS m')}, tagged AS (SELECT z, hi, {draw(DUCK, 'k', 64, 77)} AS tag FROM t_leaves), hit AS (SELECT q.a, q.b FROM q ASOF JOIN tagged c ON q.b >= c.z WHERE c.hi >= q.a AND c.tag = {draw(DUCK, 'q.a', 64, 77)})", "hit"))


def ttf_space(spark, sf):
    """Inner nodes of the truncated trie (distinct proper prefixes on the way to the leaves) and bits per key."""
    s = Setup(spark, sf, VIEW)
    return spark.createDataFrame([(s.inner, round(models.space_truncated_trie(s.n, 0, s.inner) / max(s.n, 1), 6))], "inner_nodes long, bits_per_key double")


register("ttf_space", ttf_space, with_keys(VIEW, f"ranges AS (SELECT 0 AS qid, 0 AS a, 0 AS b), {counts_sql(U)} SELECT z AS inner_nodes, round((10.0 * n + 10 * z) / n, 6) AS bits_per_key FROM inner_nodes, nn"))
register("lbf_codes", lambda spark, sf: (lambda k: f.lbf_codes(k, f.lbf_knots(k, EVERY), EVERY, m.slots(BUDGET)))(keys(spark, sf, VIEW)), with_keys(VIEW, m.learned_codes("l", m.slots(BUDGET)) + " SELECT z FROM l_codes"))
register("dyadic_cover", _on_batch("correlated", LENGTH, lambda s, r: f.dyadic_cover(r, 5, q="qid")), with_keys(VIEW, f"r AS ({ends_sql('correlated', U, LENGTH)}), c AS ({m.cover_sql('(SELECT qid AS a, qid AS b, a AS lo, b AS hi FROM r)', 5)}) SELECT a AS qid, level, node FROM c"))

# --- experiments ------------------------------------------------------------------------------------------------------

DEGREES = range(0, 11)
_GRID = [(i, d, length, w.width(d)) for i, (d, length) in enumerate((d, length) for d in DEGREES for length in w.LENGTHS)]


_CELL = "concat(g, ':', k)"


SWEPT = 4  # one key in so many has a question a cell


def sweep_sql() -> str:
    """CTEs grid and swept(qid, a, b, d, len), the empty ranges of the sweep."""
    rows = ", ".join(map(str, _GRID))
    return f"grid(g, d, len, w) AS (VALUES {rows}), drawn AS (SELECT k AS qid, k + {mixed(DUCK, _CELL, 'w', 900)} AS a, d, len FROM keys, grid WHERE {mixed(DUCK, 'k', SWEPT, 6)} = 0), swept AS ({w.empties_sql('SELECT qid, a, a + len - 1 AS b, d, len FROM drawn')})"


def sweep_ranges(s: Setup) -> DataFrame:
    return keep_empty(s.k, sweep_drawn(s))


def sweep_drawn(s: Setup) -> DataFrame:
    """Ranges, of which the sweep asks the empty ones, for every degree of correlation (10 D) and length, one drawn for each key in SWEPT: qid, a, b, d, len."""
    grid = s.k.sparkSession.createDataFrame(_GRID, "g int, d int, len int, w long")
    placed = w.share(s.k, SWEPT).crossJoin(F.broadcast(grid)).selectExpr("k AS qid", f"k + {mixed(SPARK, _CELL, 'w', 900)} AS a", "d", "len")
    return placed.selectExpr("qid", "a", "a + len - 1 AS b", "d", "len")


def length_shift(spark, sf):
    """A filter for L = 32 asked with other lengths."""
    s, out = Setup(spark, sf, VIEW), None
    for cell, length in enumerate((1, 8, 32, 128, 1024)):
        one = m.answer(s, "locality-hash", BUDGET, s.ends("empty_correlated", length, 8, cell)).select(F.lit(length).alias("len"), "maybe")
        out = one if out is None else out.union(one)
    return out.groupBy("len").agg(F.count("*").alias("n_ranges"), F.round(F.avg(F.col("maybe").cast("int")), 6).alias("fpr"))


register("length_shift", length_shift, "SELECT len, count(*) AS n_ranges, round(avg(maybe::INT), 6) AS fpr FROM (" + " UNION ALL ".join(f"SELECT {x} AS len, maybe FROM ({answer_sql('locality-hash', BUDGET, VIEW, ends_sql('empty_correlated', U, x, 8, c))})" for c, x in enumerate((1, 8, 32, 128, 1024))) + ") GROUP BY len")


def keys_summary(spark, sf):
    out = None
    for view in VIEWS:
        one = keys(spark, sf, view).agg(F.lit(view).alias("view"), F.count("*").alias("n"), F.min("k").alias("least"), F.max("k").alias("greatest"))
        out = one if out is None else out.union(one)
    return out


register("keys_summary", keys_summary, " UNION ALL ".join(f"SELECT '{v}' AS view, count(*) AS n, min(k) AS least, max(k) AS greatest FROM ({keys_sql(DUCK, v)})" for v in VIEWS))


def recommend_rules(spark, sf):
    """The rule table over what every customer's orders show: each profile met, its choice, and its customers."""
    kinds = (False, True)
    rows = [(g, c, x, a, models.recommend(g, c, x, a)) for g in kinds for c in kinds for x in kinds for a in kinds]
    rules = spark.createDataFrame(rows, "g boolean, c boolean, x boolean, a boolean, choice string")
    seen = read_table(spark, sf, "orders").groupBy("o_custkey").agg(F.expr("bool_and(o_orderpriority <> '5-LOW')").alias("guarantee"), F.expr("count(distinct date_trunc('month', o_orderdate)) < count(o_orderdate)").alias("correlated"), F.expr("year(max(o_orderdate)) - year(min(o_orderdate)) >= 6").alias("shifting"), F.expr("sum(CAST(round(o_totalprice * 100) AS BIGINT)) > 25000000 * count(o_totalprice)").alias("costly_access"))
    # What a customer's orders don't show (nulls only) doesn't hold.
    names = ("guarantee", "correlated", "shifting", "costly_access")
    profiles = seen.select(*[F.coalesce(c, F.lit(False)).alias(c) for c in names]).groupBy(*names).agg(F.count("*").alias("customers"))
    return profiles.join(F.broadcast(rules), F.expr("guarantee = g AND correlated = c AND shifting = x AND costly_access = a")).select(*names, "choice", "customers")


register("recommend_rules", recommend_rules, """WITH seen AS (SELECT o_custkey, coalesce(bool_and(o_orderpriority <> '5-LOW'), false) AS guarantee, count(DISTINCT date_trunc('month', o_orderdate)) < count(o_orderdate) AS correlated, coalesce(year(max(o_orderdate)) - year(min(o_orderdate)) >= 6, false) AS shifting, coalesce(sum(CAST(round(o_totalprice * 100) AS BIGINT)) > 25000000 * count(o_totalprice), false) AS costly_access FROM orders GROUP BY o_custkey)
SELECT guarantee, correlated, shifting, costly_access, CASE WHEN guarantee OR correlated OR shifting THEN 'locality-hash' WHEN costly_access THEN 'truncated-trie-or-bucket' ELSE 'bucket' END AS choice, count(*) AS customers FROM seen GROUP BY ALL""")


def window_counts(spark, sf):
    e = read_table(spark, sf, "events")
    return windows.window_filters(e, "1 day", None, "1 hour", 60).selectExpr("CAST(start AS STRING) AS start", "n", "CAST(size(codes) AS BIGINT) AS codes")


register("window_filters", window_counts, "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, count(DISTINCT user_id * 1048576 + (hour(ts) * 3600 + minute(ts) * 60 + second(ts)) // 60) AS codes FROM events GROUP BY 1")


def json_keys(spark, sf):
    """Keys from a JSON property, read with an explicit schema."""
    e = read_table(spark, sf, "events")
    return e.select(F.from_json("props", "k INT")["k"].cast("long").alias("k")).where("k is not null").groupBy("k").agg(F.count("*").alias("n"))


register("json_keys", json_keys, "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY 1")
