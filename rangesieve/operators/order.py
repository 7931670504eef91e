"""Order operators without a single-partition window: ranks, predecessors, emptiness.

Values are dealt into shards between bounds, which are values themselves, taken from a hash sample; their number follows
the shuffle width. Work inside a shard is a window, and what crosses shards is one row a shard. A shard that many points
ask is dealt to several tasks, each with a copy of its values (at most one more copy of all values in the mean).

Nulls among values or points have no place in an order: values that are null don't count, a null point has no predecessor.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Shards a shuffle partition, and sampled values a shard.
SHARDS, SAMPLED = 2, 32
_TOP = 2**63 - 1


def grows(df: DataFrame) -> DataFrame:
    """Mark a side of a join that grows with the data. Spark takes the size of exploded rows for that of the file they come
    from, so without the mark it may send them all through the driver as a broadcast."""
    return df.hint("merge")


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def splitters(df: DataFrame, value: str, n: int | None = None) -> list[int]:
    """Ascending bounds, all of them values of the column. n: about how many values there are (counted if not given).

    What reaches the driver is about SHARDS * SAMPLED values a shuffle partition."""
    parts = SHARDS * shuffle_width(df.sparkSession)
    n = df.count() if n is None else n
    every = max(1, n // (parts * SAMPLED))
    # Not a filter: one would be pushed down through the expressions that made the values, and repeat them.
    chosen = F.expr(f"if(v is not null and pmod(xxhash64(v), {every}) = 0, array(v), array())")
    found = sorted(r.v for r in df.select(F.col(value).cast("long").alias("v")).select(F.explode(chosen).alias("v")).distinct().collect())
    return sorted({found[i * len(found) // parts] for i in range(1, parts)}) if found else []


def with_shard(df: DataFrame, value: str, bounds: list[int], name: str) -> DataFrame:
    """Add the number of bounds at or below a column: a binary search in a constant array, a projection a step. So it
    stays in generated code, however many bounds there are."""
    if not bounds:
        return df.withColumn(name, F.lit(0))
    size = 2 ** len(bounds).bit_length()
    table = f"array({', '.join(f'{b}L' for b in bounds + [_TOP] * (size - 1 - len(bounds)))})"
    out = df.withColumn(name, F.lit(0))
    while size > 1:
        size //= 2
        out = out.withColumn(name, F.expr(f"`{name}` + if(`{value}` >= {table}[`{name}` + {size - 1}], {size}, 0)"))
    return out


def rank(df: DataFrame, value: str, name: str = "i", n: int | None = None) -> DataFrame:
    """Distinct values with their rank from 1."""
    placed = with_shard(df.select(F.col(value)), value, splitters(df, value, n), "_s")
    counts = placed.groupBy("_s").agg(F.count("*").alias("_n"))
    before = counts.select(F.col("_s").alias("_t"), F.coalesce(F.sum("_n").over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    inner = F.row_number().over(Window.partitionBy("_s").orderBy(value))
    return placed.withColumn("_r", inner).join(F.broadcast(before), F.col("_s") == F.col("_t")).select(value, (F.col("_b") + F.col("_r")).cast("long").alias(name))


def _copies(placed: DataFrame, shards: int) -> list[int]:
    """How many tasks each shard's points are dealt to, from the number of points in each (a row a shard)."""
    asked = {r["_s"]: r.n for r in placed.groupBy("_s").agg(F.count("*").alias("n")).collect() if r["_s"] >= 0}
    share = max(1, -(-2 * sum(asked.values()) // shards))
    return [max(1, -(-asked.get(s, 0) // share)) for s in range(shards)]


def _dealt(values: DataFrame, points: DataFrame, copies: list[int], spread: Column) -> tuple[DataFrame, DataFrame]:
    """Values in each copy of their shard, points in one copy: both with `_part`."""
    if max(copies) == 1:
        return values.withColumn("_part", F.lit(0)), points.withColumn("_part", F.lit(0))
    table = f"array({', '.join(map(str, copies))})"
    many = F.expr(f"{table}[greatest(_s, 0)]")
    return values.withColumn("_part", F.explode(F.sequence(F.lit(0), many - 1))), points.withColumn("_part", F.pmod(spread, many).cast("int"))


def predecessor(codes: DataFrame, points: DataFrame, at: str, payload: list[str] | None = None, n: int | None = None) -> DataFrame:
    """Points with `pred`: a struct of the largest code z <= at and its payload; null if there is none."""
    payload = payload or []
    bounds = splitters(codes, "z", n)
    item = F.struct("z", *payload)
    whole = F.struct(*[F.col(f"`{c}`") for c in points.columns])
    # Codes repeat at will; of equal ones with different payloads the greatest counts, as in the window below.
    stored = with_shard(codes.where("z is not null").select(F.col("z").cast("long").alias("_v"), item.alias("_code")), "_v", bounds, "_s")
    asked = with_shard(points.select(F.col(at).cast("long").alias("_v"), whole.alias("_row")), "_v", bounds, "_s")
    tops = stored.groupBy("_s").agg(F.max("_code").alias("_top"))
    last = F.max("_top").over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, -1))
    shards = codes.sparkSession.range(len(bounds) + 1).select(F.col("id").cast("int").alias("_s"))
    # One row a shard: the last code before it.
    carry = shards.join(tops, "_s", "left").select(F.col("_s").alias("_t"), last.alias("_carry"))
    # Equal points of different rows spread, too; a map can't be hashed.
    plain = [f"_row.`{f.name}`" for f in points.schema.fields if "map<" not in f.dataType.simpleString()]
    spread = F.xxhash64("_v", *plain)
    values, places = _dealt(stored, asked, _copies(asked, len(bounds) + 1), spread)
    kind = lambda x: F.lit(x).alias("_kind")
    left = values.select("_v", "_s", "_part", kind(0), "_code", F.lit(None).cast(asked.schema["_row"].dataType).alias("_row"))
    right = places.select("_v", "_s", "_part", kind(1), F.lit(None).cast(stored.schema["_code"].dataType).alias("_code"), "_row")
    inside = F.max("_code").over(Window.partitionBy("_s", "_part").orderBy("_v", "_kind").rowsBetween(Window.unboundedPreceding, 0))
    found = left.unionByName(right).withColumn("_pred", inside).where("_kind = 1").join(F.broadcast(carry), F.col("_s") == F.col("_t"))
    pred = F.when(F.col("_v").isNotNull(), F.coalesce("_pred", "_carry"))
    return found.select("_row.*", pred.alias("pred"))


def any_code_in(codes: DataFrame, pieces: DataFrame, n: int | None = None) -> DataFrame:
    """Pieces (lo, hi, ...) with `hit`: whether any code z lies in [lo, hi]. Codes may repeat.

    Bounds are codes, so a piece that reaches over one is hit; any other lies in one shard with all codes it may hold.
    One shuffle for the codes, one for the pieces."""
    spark = codes.sparkSession
    bounds = splitters(codes, "z", n)
    placed = with_shard(pieces, "hi", bounds, "_s")
    if bounds:
        # Shard -1 holds the pieces that are hit already.
        table = f"array({', '.join(f'{b}L' for b in bounds)})"
        placed = placed.withColumn("_s", F.expr(f"if(_s > 0 and lo < {table}[greatest(_s, 1) - 1], -1, _s)"))
    stored = with_shard(codes.select(F.col("z").cast("long").alias("hi")), "hi", bounds, "_s")
    copies = _copies(placed, len(bounds) + 1)
    values, asked = _dealt(stored, placed, copies, F.xxhash64("lo", "hi"))
    asked = asked.withColumn("_part", F.expr(f"if(_s < 0, CAST(pmod(xxhash64(lo, hi), {SHARDS * shuffle_width(spark)}) AS INT), _part)"))
    whole = F.struct(*[F.col(f"`{c}`") for c in pieces.columns])
    right = asked.select("hi", "_s", "_part", F.lit(1).alias("_kind"), whole.alias("_row"))
    left = values.select("hi", "_s", "_part", F.lit(0).alias("_kind"), F.lit(None).cast(right.schema["_row"].dataType).alias("_row"))
    inside = F.max(F.when(F.col("_kind") == 0, F.col("hi"))).over(Window.partitionBy("_s", "_part").orderBy("hi", "_kind").rowsBetween(Window.unboundedPreceding, 0))
    found = left.unionByName(right).withColumn("_last", inside).where("_kind = 1")
    return found.select("_row.*", F.expr("_s < 0 or coalesce(_last >= _row.lo, false)").alias("hit"))


def count_codes_upto(codes: DataFrame, points: DataFrame, at: str, name: str, n: int | None = None) -> DataFrame:
    """Points with the number of codes <= at (codes distinct)."""
    found = predecessor(rank(codes, "z", n=n).select("z", "i"), points, at, ["i"], n)
    return found.select(*points.columns, F.coalesce("pred.i", F.lit(0)).cast("long").alias(name))


# --- questions and answers --------------------------------------------------------------------------------------------


def _place(df: DataFrame, name: str) -> int:
    return df.columns.index(name)


def _numbered(df: DataFrame) -> DataFrame:
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def questions(ranges: DataFrame) -> DataFrame:
    """(q, a, b): each pair of ends once, with q = (a, b); null and reversed ones ask nothing."""
    a, b = F.col(f"c{_place(ranges, 'a')}"), F.col(f"c{_place(ranges, 'b')}")
    ends = _numbered(ranges).select(a.cast("long").alias("a"), b.cast("long").alias("b")).distinct()
    # Not a filter: one would be pushed down through the expressions that made the ends, and repeat them.
    return ends.select(F.inline(F.expr("if(a <= b, array(struct(struct(a, b) AS q, a AS a, b AS b)), array())")))


def answered(ranges: DataFrame, hits: DataFrame, name: str = "maybe") -> DataFrame:
    """All rows and columns of ranges with the answer: true if (q, hit) has a true hit of its ends, null if an end is
    null or the ends are reversed. Rows that repeat or share an id keep an answer each; a column of that name is replaced."""
    found = hits.where("hit").select(F.col("q.a").alias("x_"), F.col("q.b").alias("y_")).distinct()
    rows, a, b = _numbered(ranges), F.col(f"c{_place(ranges, 'a')}").cast("long"), F.col(f"c{_place(ranges, 'b')}").cast("long")
    met = rows.join(grows(found), (a == F.col("x_")) & (b == F.col("y_")), "left")
    kept = [F.col(f"c{i}").alias(c) for i, c in enumerate(ranges.columns) if c != name]
    return met.select(*kept, F.when(a <= b, F.col("x_").isNotNull()).alias(name))


def exact_nonempty(keys: DataFrame, ranges: DataFrame) -> DataFrame:
    """Ground truth: ranges with `truth` (null as in `answered`)."""
    pieces = questions(ranges).selectExpr("q", "a AS lo", "b AS hi")
    return answered(ranges, any_code_in(keys.select(F.col("k").alias("z")), pieces), "truth")


def keep_empty(keys: DataFrame, ranges: DataFrame) -> DataFrame:
    """The ranges without key; those without a truth are left out. Each row is asked by itself: one shuffle, no join back."""
    names, rows = ranges.columns, _numbered(ranges)
    # A generator, so that the expressions that made the rows are not repeated by what follows.
    rows = rows.select(F.inline(F.array(F.struct(*rows.columns))))
    ends = [F.col(f"c{_place(ranges, c)}").cast("long").alias(to) for c, to in (("a", "lo"), ("b", "hi"))]
    found = any_code_in(keys.select(F.col("k").alias("z")), rows.select(F.struct(*rows.columns).alias("row"), *ends))
    return found.where("lo <= hi and not hit").select(*[F.col(f"row.c{i}").alias(c) for i, c in enumerate(names)])
