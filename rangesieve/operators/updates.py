"""Filters that grow or are kept in parts: inserts, compaction, shards of key space, segments."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangesieve.functions.hashing import HashParams, params_for_budget, with_local_hash
from rangesieve.operators.filters import lhf_codes, lhf_merge
from rangesieve.operators.order import answered, any_code_in, questions, splitters, with_shard


def lhf_insert(codes: DataFrame, added: DataFrame, p: HashParams) -> DataFrame:
    """Codes after an insert under the filter's own parameters. The bound grows with the keys: m added keys on n make
    it (1 + m/n) times as large until the filter is compacted."""
    return lhf_merge(codes, lhf_codes(added, p))


def needs_compaction(n: int, added: int, fraction: float = 0.25) -> bool:
    return added > fraction * n


def lhf_compact(keys: DataFrame, n: int, bits: int, u: int, seed: int = 1) -> tuple[DataFrame, HashParams]:
    """Rebuild from the keys with parameters for their number now."""
    p = params_for_budget(n, bits, u, seed)
    return lhf_codes(keys, p), p


ANY = HashParams(2, 2**60 + 33, 2**59 + 7)


def shard_table(keys: DataFrame, bounds: list[int], bits: int) -> DataFrame:
    """One row a shard of key space with keys: its first key, its own r, and where its codes start."""
    found = with_shard(keys, "k", bounds, "shard").groupBy("shard").agg(F.count_distinct("k").alias("n_s"), F.min("k").alias("first"), F.max("k").alias("last"))
    r = (F.col("n_s") * 2 ** (bits - 2)).alias("r")
    sized = found.select("shard", "first", "last", r)
    start = F.coalesce(F.sum("r").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("long")
    return sized.withColumn("start", start)


def sharded_probe(keys: DataFrame, ranges: DataFrame, bits: int, bounds: list[int] | None = None) -> DataFrame:
    """One locality-hash filter a shard, each with its own block length, so that no parameter grows with the whole key
    set. A range is cut at shards; lengths of the cuts add up to its own, and so does the bound. The shard table has as
    many rows as there are bounds, and a range that reaches over more than two shards holds a key of those between."""
    some = keys.where("k is not null")
    bounds = splitters(some, "k") if bounds is None else bounds
    table = shard_table(some, bounds, bits)
    placed = with_shard(some, "k", bounds, "_s").join(F.broadcast(table), F.expr("_s = shard"))
    codes = with_local_hash(placed, [("z", "k - first")], ANY, "r").selectExpr("start + z AS z")
    reach = with_shard(with_shard(questions(ranges), "a", bounds, "x"), "b", bounds, "y")
    met = reach.select("q", "a", "b", F.explode(F.expr("if(x = y, array(x), array(x, y))")).alias("_s")).join(F.broadcast(table), F.expr("_s = shard"))
    between = reach.where("y > x + 1").join(F.broadcast(table.select("shard")), F.expr("shard > x and shard < y"), "left_semi").selectExpr("q", "true AS hit")
    cut = met.selectExpr("q", "greatest(a, first) AS a", "least(b, last) AS b", "first", "r", "start").where("a <= b")
    spans = cut.withColumn("spans", F.expr("(b - first) div r - (a - first) div r"))
    border = "(b - (b - first) % r)"
    halves = spans.where("spans < 2").select("q", "first", "r", "start", F.inline(F.expr(f"if(spans = 0, array(struct(a, b)), array(struct(a, {border} - 1 AS b), struct({border} AS a, b)))")))
    ends = with_local_hash(halves, [("x", "a - first"), ("y", "b - first")], ANY, "r")
    parts = ends.select("q", F.inline(F.expr("if(x <= y, array(struct(start + x AS lo, start + y AS hi)), array(struct(start AS lo, start + y AS hi), struct(start + x AS lo, start + r - 1 AS hi)))")))
    whole = spans.where("spans >= 2").selectExpr("q", "start AS lo", "start + r - 1 AS hi")
    return answered(ranges, any_code_in(codes, parts.union(whole)).select("q", "hit").union(between))
