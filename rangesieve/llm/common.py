"""Shared plumbing of the corpus operators: inputs, scratch tables, folds, word lists, code shipping."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile
import zlib
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A word of the shingling operators: a run of letters and digits, after lower-casing.
WORD = re.compile(r"[^\W_]+")
#: Shingle length in words and the similarity from which two texts count as near copies.
SHINGLE_WORDS = 5
NEAR = 0.8


BATCH_ROWS = 1_000


def give_back() -> None:
    """At the end of a task: return freed memory to the system, as Python workers outlive their stage."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # not every C library can
        pass


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors once per context, so that Arrow functions can be unpickled anywhere."""
    # Batches of texts, which may be long: a thousand rows each keep a worker's memory small.
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    sc = spark.sparkContext
    if getattr(sc, "_rangesieve_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    folder = os.path.realpath(tempfile.mkdtemp(prefix="rangesieve_zip_"))
    target = os.path.join(folder, "rangesieve_code.zip")
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    sc.addPyFile(target)
    sc._rangesieve_shipped = True


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir; a folder of our own only where that is unset and all runs on one
    machine, as in tests. A cluster must name one."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = getattr(sc, "_rangesieve_scratch", None)
        if not found:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            found = "file://" + tempfile.mkdtemp(prefix="rangesieve_scratch_")
            sc._rangesieve_scratch = found
    return found.rstrip("/")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write a frame to the shared scratch folder and read it back: cuts lineage and survives lost executors."""
    path = f"{scratch_dir(df.sparkSession)}/rangesieve/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def id_crc(col: Column) -> Column:
    """crc32 of an id written as decimal text (null counts as the empty text)."""
    return F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary"))


def fold(col: Column, parts: int) -> Column:
    """The fold of an id: crc32 of its text modulo the number of parts."""
    return F.pmod(id_crc(col), F.lit(parts))


def fold_of(doc_id: int, parts: int) -> int:
    """The same fold on the driver, for tests."""
    return zlib.crc32(str(doc_id).encode()) % parts


def own(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, so that extra columns of the input can't clash with working columns.

    A name that differs from an extra column's only by case is resolved by position, exact spelling first.
    """
    by_exact = {c: i for i, c in reversed(list(enumerate(df.columns)))}
    if len(set(map(str.lower, df.columns))) == len(df.columns):
        return df.select(*names)
    renamed = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return renamed.select(*[F.col(f"c{by_exact[n]}").alias(n) for n in names])


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


def sized_partitions(spark: SparkSession, rows: int, per_task: int) -> int:
    """Partitions so that a task gets about per_task rows, at least the session's shuffle width."""
    return max(shuffle_width(spark), -(-rows // per_task))


#: Rows that one task orders in a running sum.
CUT_ROWS = 5_000


def running_sum(df: DataFrame, keys: list[str], spread: Column, value: str, n_rows: int, name: str) -> DataFrame:
    """Add `name`: the sum of `value` over the rows of the same keys that come before, in the order of `spread`.

    A hot key spreads over many tasks: rows are cut by the spread hash, cuts are summed, the sums run over the cuts of
    a key, and only the rows of one cut are ordered together. Rows with equal spread are in any order.
    """
    cuts = max(1, -(-n_rows // CUT_ROWS))
    cut = df.withColumn("_h", spread).withColumn("_cut", F.pmod("_h", F.lit(cuts)))
    sums = cut.groupBy(*keys, "_cut").agg(F.sum(value).alias("_words"))
    earlier = Window.partitionBy(*keys).orderBy("_cut").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(*keys, "_cut", F.coalesce(F.sum("_words").over(earlier), F.lit(0)).alias("_offset"))
    inner = Window.partitionBy(*keys, "_cut").orderBy("_h").rowsBetween(Window.unboundedPreceding, -1)
    placed = cut.withColumn("_inside", F.coalesce(F.sum(value).over(inner), F.lit(0)))
    return placed.join(offsets, [*keys, "_cut"]).select(*df.columns, (F.col("_offset") + F.col("_inside")).alias(name))


def carry(docs: DataFrame, *names: str) -> DataFrame:
    """The named columns and the whole row as `_all`: an operator's working columns can't clash with others' names."""
    renamed = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])
    at = {c: i for i, c in reversed(list(enumerate(docs.columns)))}
    whole = F.struct(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)]).alias("_all")
    return renamed.select(*[F.col(f"c{at[n]}").alias(n) for n in names], whole)


def restore(df: DataFrame) -> DataFrame:
    return df.select("_all.*")
