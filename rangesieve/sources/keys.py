"""Key views: integer keys derived from the tables, as SQL text in either dialect."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK, Dialect


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _micros(d: Dialect, ts: str) -> str:
    """Microseconds since 2024-01-01, from the fields of a timestamp without zone."""
    if d.name == "duck":
        return f"(epoch_us({ts}) - epoch_us(TIMESTAMP '2024-01-01'))"
    return f"(CAST(datediff(CAST({ts} AS DATE), DATE '2024-01-01') AS BIGINT) * 86400000000 + CAST(hour({ts}) AS BIGINT) * 3600000000 + CAST(minute({ts}) AS BIGINT) * 60000000 + CAST(extract(SECOND FROM {ts}) * 1000000 AS BIGINT))"


def _cents(x: str) -> str:
    return f"CAST(round({x} * 100) AS BIGINT)"


def _line() -> str:
    return "concat(CAST(l_orderkey AS STRING), '-', CAST(l_linenumber AS STRING))"


def _mixed(d: Dialect) -> str:
    i = "(8 * l_orderkey + l_linenumber + 1)"
    return f"(({i} * 48271) % 2147483647) * 2147483648 + ({i} * (69621 * CAST(16807 AS BIGINT) % 2147483647)) % 2147483647"


def _normal(d: Dialect) -> str:
    draws = [f"substr(md5(concat('{c}', {_line()})), {at}, 7)" for c in "abc" for at in (1, 8, 15, 22)]
    total = " + ".join(d.hex_to_int(x) for x in draws)
    last = d.hex_to_int(f"substr(md5(concat('d', {_line()})), 1, 7)")
    return f"{2**61} + ({total} - {6 * 2**28}) * 1717986918 + {last}"


def _interleave(d: Dialect) -> str:
    dims = ["CAST(floor((CAST(embedding[{}] AS DOUBLE) + 1) * 524288) AS BIGINT)".format(i if d.name == "spark" else i + 1) for i in (0, 1)]
    return " + ".join(f"({d.shift(x, b)} % 2) * {2 ** (2 * b + k)}" for k, x in enumerate(dims) for b in range(20))


#: view -> (table, expression, log2 of the universe)
VIEWS = {
    "event_us": ("events", lambda d: _micros(d, "ts"), 42),
    "user_time": ("events", lambda d: f"user_id * {2**42} + {_micros(d, 'ts')}", 52),
    "type_time": ("events", lambda d: f"{d.hex_to_int('substr(md5(event_type), 1, 2)')} * {2**42} + {_micros(d, 'ts')}", 50),
    "md5_60": ("lineitem", lambda d: d.hex_to_int(f"substr(md5({_line()}), 1, 15)"), 60),
    "mixed62": ("lineitem", _mixed, 62),
    "part_price": ("lineitem", lambda d: f"l_partkey * {2**24} + {_cents('l_extendedprice')}", 40),
    "price_cents": ("lineitem", lambda d: _cents("l_extendedprice"), 24),
    "order_total": ("orders", lambda d: _cents("o_totalprice"), 26),
    "acctbal": ("customer", lambda d: f"{_cents('c_acctbal')} + 100000", 21),
    "order_line": ("lineitem", lambda d: "8 * l_orderkey + l_linenumber", 22),
    "order_key": ("orders", lambda d: "o_orderkey", 20),
    "normal": ("lineitem", _normal, 62),
    "point_zorder": ("embeddings", _interleave, 40),
}


def universe(view: str) -> int:
    return 2 ** VIEWS[view][2]


def keys(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    """Distinct keys k of a view; nulls never enter. Only the columns of the expression are read."""
    table, expression, _ = VIEWS[view]
    return read_table(spark, sf_dir, table).select(F.expr(expression(SPARK)).cast("long").alias("k")).where("k is not null").distinct()


def keys_sql(d: Dialect, view: str) -> str:
    table, expression, _ = VIEWS[view]
    text = expression(d).replace("AS STRING", "AS VARCHAR") if d.name == "duck" else expression(d)
    return f"SELECT DISTINCT CAST({text} AS BIGINT) AS k FROM {table}"


def with_outliers(keys_: DataFrame, count: int = 21) -> DataFrame:
    """Low-magnitude ids and a few far outliers."""
    far = keys_.sparkSession.range(count).select((F.lit(2**40) + F.col("id") * 7919 * 2**30).alias("k"))
    return keys_.union(far).distinct()
