"""Segments behind filters: a catalog with one packed filter a segment, and a source that reads only the segments a
predicate may meet.

A segment is a Parquet file of bounded size. The catalog is a Parquet table (path, kmin, kmax, n, r, l, first, length,
high, low); it is never broadcast. A scan reads the rows of it whose [kmin, kmax] meets the predicate, then asks their
filters, then opens what is left. Nulls of the key never enter; a segment without keys has no row and is never read by
a scan with a predicate.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from rangesieve.functions.hashing import HashParams, h_value, h_values, seeded
from rangesieve.functions.packed import EliasFano
from rangesieve.functions.ship import ship

CATALOG = "path string, kmin long, kmax long, n long, r long, l int, first long, length long, high binary, low binary"


def _params(r: int) -> HashParams:
    return seeded(int(r), 1)


def build_catalog(segments: DataFrame, key: str, bits: int) -> DataFrame:
    """Catalog of a frame read from the segment files; only the key column is read. One group is one file."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        ks = np.unique(pdf["k"].to_numpy())
        p = _params(len(ks) * 2 ** (bits - 2))
        z = np.unique(h_values(ks, p))
        ef = EliasFano.encode(z - z[0], bits - 2)
        high, low = ef.dump()
        return pd.DataFrame({"path": [pdf["path"].iloc[0]], "kmin": [ks[0]], "kmax": [ks[-1]], "n": [len(z)], "r": [p.r], "l": [bits - 2], "first": [z[0]], "length": [ef.length], "high": [high], "low": [low]})

    ship(segments.sparkSession)
    named = segments.select(F.input_file_name().alias("path"), F.col(key).cast("long").alias("k")).where("k is not null")
    return named.distinct().groupBy("path").applyInPandas(build, CATALOG)


def save_catalog(catalog: DataFrame, path: str) -> None:
    catalog.write.mode("overwrite").parquet(path)


def load_catalog(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CATALOG).parquet(path)


def maybe_in_segment(row, a: int, b: int) -> bool:
    """Whether a segment's filter says that a key may lie in [a, b]."""
    p, first = _params(row["r"]), int(row["first"])
    a, b = max(a, int(row["kmin"])), min(b, int(row["kmax"]))
    if a > b:
        return False
    crossed = b // p.r - a // p.r
    if crossed >= 2:
        return True
    ef = EliasFano.load(int(row["n"]), int(row["l"]), int(row["length"]), row["high"], row["low"])

    def any_between(lo: int, hi: int) -> bool:
        below = ef.predecessor(hi - first)
        return below is not None and below + first >= lo

    edge = b - b % p.r
    for x, y in [(a, b)] if crossed == 0 else [(a, edge - 1), (edge, b)]:
        x, y = h_value(x, p), h_value(y, p)
        if any_between(x, y) if x <= y else (any_between(0, y) or any_between(x, p.r - 1)):
            return True
    return False


def _dataset(path: str) -> ds.Dataset:
    fs, inner = pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (None, path)
    return ds.dataset(inner, format="parquet", filesystem=fs)


def segments_to_read(catalog: str, a: int | None, b: int | None) -> list[str]:
    """Paths a predicate [a, b] must read (None: open end). Rows of the catalog stream by in batches."""
    lo, hi = -(2**63) if a is None else a, 2**63 - 1 if b is None else b
    met = (ds.field("kmin") <= hi) & (ds.field("kmax") >= lo)
    out = []
    for batch in _dataset(catalog).to_batches(filter=met, batch_size=64):
        out += [r["path"] for r in batch.to_pylist() if maybe_in_segment(r, lo, hi)]
    return sorted(out)


class _Segment(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class _Reader(DataSourceReader):
    def __init__(self, schema: StructType, options: dict):
        self.schema, self.catalog, self.key = schema, options["path"], options["key"]
        self.lo: int | None = None
        self.hi: int | None = None

    def pushFilters(self, filters):
        """Bounds on the key choose segments; every predicate is still applied by Spark."""
        for f in filters:
            if getattr(f, "attribute", None) == (self.key,) and isinstance(getattr(f, "value", None), int):
                if isinstance(f, (EqualTo, GreaterThanOrEqual, GreaterThan)):
                    low = f.value + isinstance(f, GreaterThan)
                    self.lo = low if self.lo is None else max(self.lo, low)
                if isinstance(f, (EqualTo, LessThanOrEqual, LessThan)):
                    high = f.value - isinstance(f, LessThan)
                    self.hi = high if self.hi is None else min(self.hi, high)
            yield f

    def partitions(self):
        if self.lo is None and self.hi is None:
            return [_Segment(p) for batch in _dataset(self.catalog).to_batches(columns=["path"]) for p in batch.column(0).to_pylist()]
        return [_Segment(p) for p in segments_to_read(self.catalog, self.lo, self.hi)]

    def read(self, partition):
        if partition is None:  # what Spark passes when no segment is left
            return
        names = [f.name for f in self.schema.fields]
        for batch in _dataset(partition.value).to_batches(columns=names, batch_size=8192):
            yield pa.RecordBatch.from_arrays(batch.columns, names=names)


class SegmentSource(DataSource):
    """spark.read.format("range_segments").schema(...).option("key", ...).load(catalog). Needs
    spark.sql.python.filterPushdown.enabled."""

    @classmethod
    def name(cls) -> str:
        return "range_segments"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(schema, self.options)


def guarded_scan(spark: SparkSession, catalog: str, key: str, a: int, b: int) -> DataFrame:
    """Rows with a <= key <= b, by Spark's own Parquet reader over the segments the filters leave; an empty frame of
    the key alone if they leave none."""
    from pyspark.sql.types import LongType, StructField

    paths = segments_to_read(catalog, a, b)
    if not paths:
        return spark.createDataFrame([], StructType([StructField(key, LongType())]))
    return spark.read.parquet(*paths).where(F.col(key).between(a, b))
