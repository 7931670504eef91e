"""Filters over streams whose late events aren't lost: a base filter a window, and a delta filter for what comes late.

Every micro-batch writes its codes under its own batch number, so a batch that is run again after a failure replaces
what it wrote before. An event is late if its window had closed, by the greatest event time of earlier batches less the
allowed delay. Base and delta have the same codes' space: a question is maybe if either says so, and compaction is their
union. Events without time or user are left out; repeated events change nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

CODES = "start timestamp, z long, late boolean, batch long"
TOPS = "top timestamp, batch long"


def unique_events(events: DataFrame, keys: list[str], watermark: str) -> DataFrame:
    """The first event of each key: within the watermark on a stream, over all rows on a table."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys) if events.isStreaming else timed.dropDuplicates(keys)


def _read(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """A table written by batches; no rows before the first one."""
    jvm = spark.sparkContext._jvm
    folder = jvm.org.apache.hadoop.fs.Path(path)
    exists = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder)
    return spark.read.schema(schema).parquet(path) if exists else spark.createDataFrame([], schema)


def codes_of(events: DataFrame, width: str, s: int) -> DataFrame:
    """(start, end, ts, z): window of each event and its code, user_id * 2^20 + bucket of s seconds in the day."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).where("ts is not null and user_id is not null")
    z = F.expr(f"user_id * {2**20} + (hour(ts) * 3600 + minute(ts) * 60 + second(ts)) div {s}")
    return timed.select(F.window("ts", width).alias("w"), "ts", z.alias("z")).select("w.start", "w.end", "ts", "z")


def add_batch(batch: DataFrame, number: int, out: str, width: str, delay: str, s: int) -> None:
    """Write the codes of one micro-batch, marked as late or not, and its greatest event time."""
    spark = batch.sparkSession
    coded = codes_of(batch, width, s)
    # One row: the greatest event time of the batches before this one.
    top = _read(spark, f"{out}/tops", TOPS).where(F.col("batch") < number).agg(F.max("top").alias("top"))
    late = F.coalesce(F.col("end") <= F.col("top") - F.expr(f"INTERVAL {delay}"), F.lit(False))
    marked = coded.join(F.broadcast(top)).select("start", "z", late.alias("late")).distinct()
    marked.write.mode("overwrite").parquet(f"{out}/codes/batch={number}")
    coded.agg(F.max("ts").alias("top")).write.mode("overwrite").parquet(f"{out}/tops/batch={number}")


def start(events: DataFrame, out: str, checkpoint: str, width: str, delay: str, s: int) -> StreamingQuery:
    """Run over all that is there, then stop; start again to go on."""
    run = lambda batch, number: add_batch(batch, number, out, width, delay, s)
    return events.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def load(spark: SparkSession, out: str, part: str = "both") -> DataFrame:
    """(start, z) of the base filters, the delta filters, or both together (compacted)."""
    codes = _read(spark, f"{out}/codes", CODES)
    kept = {"base": codes.where("not late"), "delta": codes.where("late"), "both": codes}[part]
    return kept.select("start", "z").distinct()


def probe(asked: DataFrame, codes: DataFrame) -> DataFrame:
    """Questions (qid, start, lo, hi), on a table or a stream, against stored codes: those that are maybe."""
    stored = codes.groupBy("start").agg(F.array_sort(F.collect_set("z")).alias("codes"))
    return asked.join(stored, "start").where(F.exists("codes", lambda z: (z >= F.col("lo")) & (z <= F.col("hi")))).select("qid", "start", "lo", "hi")
