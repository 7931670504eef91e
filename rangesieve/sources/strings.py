"""String keys: bytes padded or cut to a width; the head is hashed, the last six bytes keep their order."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions.hashing import Dialect
from rangesieve.operators.order import any_code_in

SPACE = 2**48


def _digits(d: Dialect, x: str, width: str) -> str:
    return f"rpad(hex({x}), 2 * {width}, '0')" if d.name == "spark" else f"rpad(hex(encode({x})), (2 * {width})::INT, '0')"


def head(d: Dialect, x: str, width: str) -> str:
    return f"substr({_digits(d, x, width)}, 1, CAST(2 * {width} - 12 AS INT))"


def string_hash(d: Dialect, x: str, width: str) -> str:
    tail = d.hex_to_int(f"substr({_digits(d, x, width)}, CAST(2 * {width} - 11 AS INT), 12)")
    return f"(({d.hex_to_int(f'substr(md5({head(d, x, width)}), 1, 12)')} + {tail}) % {SPACE})"


def string_codes(d, strings: DataFrame, column: str, width: int) -> DataFrame:
    """Codes z of a column of strings; nulls never enter. Longer strings are cut, which keeps their order."""
    return strings.where(F.col(column).isNotNull()).select(F.expr(string_hash(d, column, str(width))).alias("z")).distinct()


def string_probe(d, codes: DataFrame, ranges: DataFrame, width: int) -> DataFrame:
    """Ranges (a, b, ...) of strings with `maybe`: filtered if both ends share their head, else answered maybe; null where
    an end is null or a > b. Ends that repeat are asked once."""
    asked = ranges.select("a", "b").where("a <= b").distinct().select(F.struct("a", "b").alias("q"), "a", "b")
    ends = asked.select("q", F.expr(f"{head(d, 'a', str(width))} = {head(d, 'b', str(width))}").alias("same"), F.expr(string_hash(d, "a", str(width))).alias("x"), F.expr(string_hash(d, "b", str(width))).alias("y"))
    parts = ends.where("same").select("q", F.inline(F.expr(f"if(x <= y, array(struct(x AS lo, y AS hi)), array(struct(0L AS lo, y AS hi), struct(x AS lo, {SPACE - 1}L AS hi)))")))
    hits = any_code_in(codes, parts).select("q", "hit").union(ends.where("not same").select("q", F.lit(True).alias("hit")))
    found = hits.where("hit").select(F.col("q.a").alias("x_"), F.col("q.b").alias("y_")).distinct()
    met = ranges.join(found, (F.col("a") == F.col("x_")) & (F.col("b") == F.col("y_")), "left")
    return met.select(*ranges.columns, F.when(F.col("a") <= F.col("b"), F.col("x_").isNotNull()).alias("maybe"))
