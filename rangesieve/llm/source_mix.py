"""Mixing sources to target weights by weighted fair queueing.

Every source is a queue. Its documents stand in a shuffled order; the j-th copy pass over the queue continues the
count of words, and a copy's virtual finish time is the source's words up to and with it, divided by the source's
target. Serving copies in order of finish time and stopping at the total budget gives every source its target.

Targets share the budget (all words) by weight. A target stops at three times its source's words; the excess is
shared again by weight among the others, which is the level of water-filling: sources are taken in order of
words / weight, and each is capped as long as the level reached so far lies above its cap.

Defined cases: null text has size 0; null source is a source of its own, last in order; documents without words are
taken with 0 words; an empty table gives no rows; ties in the shuffle are broken by doc_id, then size; repeated rows
are separate documents; extra columns are carried by mix_documents and ignored by the query.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangesieve.llm.common import carry, materialise, own, restore, shuffle_width

WEIGHTS = (5, 2, 1)
MOST_TIMES = 3
WORD_RUN = r"[^\x20\x09-\x0D]+"
QUEUE_ROWS = 1_000
SEED = "mix"


def source_targets(sized: DataFrame, weights=WEIGHTS, most: int = MOST_TIMES) -> DataFrame:
    """source, source_rank, source_size, target of every source, from rows (source, size)."""
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    scale = 1
    for w in weights:
        scale *= w
    ranked = sums.withColumn("source_rank", F.row_number().over(by_name) - 1).withColumn(
        "weight", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("source_rank") % len(weights) + 1).cast("int"))
    )
    by_fill = Window.orderBy(F.col("source_size") * F.expr(f"{scale} div weight"), "source_rank")
    before = by_fill.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    big = "decimal(38,0)"
    room = ranked.select(
        "*",
        (F.sum("source_size").over(everything) - F.coalesce(F.sum(F.col("source_size") * most).over(before), F.lit(0))).alias("left_words"),
        (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))).alias("left_weight"),
    ).withColumn("capped", (F.col("source_size") * most).cast(big) * F.col("left_weight") <= F.col("left_words").cast(big) * F.col("weight"))
    level = F.max(F.when(~F.col("capped"), F.struct("left_weight", "left_words"))).over(everything)
    return room.withColumn("level", level).select(
        "source",
        "source_rank",
        "source_size",
        F.when(F.col("capped"), (F.col("source_size") * most).cast("double")).otherwise(F.col("level.left_words").cast("double") / F.col("level.left_weight") * F.col("weight")).alias("target"),
    )


def queue_positions(sized: DataFrame, n_rows: int) -> DataFrame:
    """Add `upto`: words of the row's source up to and with the row, in shuffled order.

    Queues are cut by the leading bits of the shuffle key, so that a hot source spreads over many tasks: sums per cut,
    a running sum over the cuts of a source, and a running sum within a cut.
    """
    cuts = max(1, -(-n_rows // QUEUE_ROWS))
    keyed = sized.withColumn("key", F.md5(F.concat(F.lit(SEED), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))))
    keyed = keyed.withColumn("cut", F.expr(f"cast(conv(substr(key, 1, 8), 16, 10) as bigint) * {cuts} div 4294967296"))
    sums = keyed.groupBy("source", "cut").agg(F.sum("size").alias("words"))
    earlier = Window.partitionBy("source").orderBy("cut").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(F.col("source").alias("s_"), F.col("cut").alias("c_"), F.coalesce(F.sum("words").over(earlier), F.lit(0)).alias("offset"))
    inner = Window.partitionBy("source", "cut").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    placed = keyed.withColumn("inside", F.sum("size").over(inner))
    return placed.join(offsets, placed["source"].eqNullSafe(offsets["s_"]) & (placed["cut"] == offsets["c_"])).select(*sized.columns, (F.col("offset") + F.col("inside")).alias("upto"))


def plan_mix(sized: DataFrame) -> DataFrame:
    """Rows of `sized` (doc_id, source, size and any others) with source_size, target and takes: words of each copy.

    takes is an array over the copies 1..most in serving order; its sum is what the mix takes of the row.
    """
    seen = sized.agg(F.count("*").alias("n"), F.coalesce(F.sum("size"), F.lit(0)).alias("words")).first()
    n_rows, budget = seen.n, seen.words
    targets = source_targets(sized.select("source", "size"))
    placed = queue_positions(sized, n_rows)
    t = targets.select(F.col("source").alias("t_"), "source_rank", "source_size", "target")
    queued = placed.join(t, placed["source"].eqNullSafe(t["t_"])).drop("t_")
    queued = materialise(queued, "queues")
    finish = "transform(sequence(1, {m}), e -> struct(if(target > 0, cast((e - 1) * source_size + upto as double) / target, 0d) as finish, source_rank as rank, upto as upto, e as copy))"
    copies = queued.withColumn("copies", F.expr(finish.format(m=MOST_TIMES)))
    # Global order by ranges of the finish time: the words up to any finish time f are about f times the budget.
    slots = max(shuffle_width(sized.sparkSession) * 16, -(-n_rows // QUEUE_ROWS))
    served = copies.where("size > 0").select("size", F.explode("copies").alias("c")).where("c.finish < 2")
    ranged = served.withColumn("slot", F.floor(F.col("c.finish") * slots))
    per_slot = ranged.groupBy("slot").agg(F.sum("size").alias("words"))
    order = Window.orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    ends = per_slot.withColumn("before", F.coalesce(F.sum("words").over(order), F.lit(0))).where(F.col("before") < budget)
    last = ends.orderBy(F.col("slot").desc()).first()
    if last is None:
        stop = None
    else:
        inner = Window.partitionBy("slot").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
        tail = ranged.where(F.col("slot") == last.slot).withColumn("before", F.coalesce(F.sum("size").over(inner), F.lit(0)) + last["before"])
        stop = tail.where(F.col("before") < budget).orderBy(F.col("c").desc()).select("c", "before").first()
    if stop is None:
        takes = F.expr("transform(copies, c -> 0L)")
    else:
        edge = F.struct(F.lit(stop.c.finish).alias("finish"), F.lit(stop.c.rank).alias("rank"), F.lit(stop.c.upto).cast("long").alias("upto"), F.lit(stop.c.copy).alias("copy"))
        rest = F.least("size", F.lit(budget - stop.before).cast("long"))
        takes = F.transform("copies", lambda c: F.when(c < edge, F.col("size")).when(c == edge, rest).otherwise(F.lit(0).cast("long")))
    return copies.withColumn("takes", takes).drop("copies")


def sized_documents(docs: DataFrame) -> DataFrame:
    """doc_id, source and size (number of word runs) of every row, written once: the text is read a single time."""
    rows = own(docs, "doc_id", "source", "text")
    return materialise(rows.select("doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORD_RUN)), F.lit(0)).cast("long").alias("size")), "sizes")


def mix_sources(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken and copies (how many copies the mix takes, the last may be cut)."""
    plan = plan_mix(sized_documents(docs))
    return plan.select(
        "doc_id",
        "size",
        "source_size",
        "target",
        F.aggregate("takes", F.lit(0).cast("long"), lambda a, x: a + x).alias("taken"),
        F.size(F.filter("takes", lambda x: x > 0)).cast("long").alias("copies"),
    )


def mix_documents(docs: DataFrame) -> DataFrame:
    """The mix itself: rows of docs, repeated once for every copy of which the mix takes any word (a cut copy stays whole).

    Documents without words are kept once.
    """
    rows = carry(docs, "doc_id", "source", "text").withColumn("_row", F.xxhash64("_all"))
    sized = materialise(rows.select(F.col("doc_id"), F.col("source"), F.coalesce(F.regexp_count("text", F.lit(WORD_RUN)), F.lit(0)).cast("long").alias("size"), "_row"), "sizes")
    plan = plan_mix(sized)
    times = plan.groupBy("doc_id", "_row").agg(
        F.sum(F.when(F.col("size") == 0, F.lit(1)).otherwise(F.size(F.filter("takes", lambda x: x > 0)))).alias("_times"), F.count("*").alias("_same")
    )
    # Rows that are repeated as a whole are one group of copies: each of them gets the group's copies, evenly.
    first = times.select(F.coalesce("doc_id", F.lit(-(2**63))).alias("_id"), F.col("_row").alias("_r"), F.expr("cast(ceil(_times / _same) as int)").alias("_times"))
    # The same plan at every size: the rows are shuffled.
    joined = rows.withColumn("_key", F.coalesce("doc_id", F.lit(-(2**63)))).join(first.hint("merge"), (F.col("_key") == F.col("_id")) & (F.col("_row") == F.col("_r")))
    return joined.where("_times > 0").withColumn("_copy", F.explode(F.expr("sequence(1, _times)"))).transform(restore)


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         md5(concat('mix', coalesce(doc_id::VARCHAR, ''))) AS key
  FROM documents),
src AS (
  SELECT source, sum(size)::HUGEINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS source_rank
  FROM sized GROUP BY source),
weighed AS (SELECT *, [5, 2, 1][(source_rank % 3 + 1)::INT]::HUGEINT AS weight FROM src),
room AS (
  SELECT *, sum(source_size) OVER () - coalesce(sum(3 * source_size) OVER f, 0) AS left_words,
         sum(weight) OVER () - coalesce(sum(weight) OVER f, 0) AS left_weight
  FROM weighed WINDOW f AS (ORDER BY source_size * (10 // weight), source_rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
caps AS (SELECT *, 3 * source_size * left_weight <= left_words * weight AS capped FROM room),
lvl AS (SELECT arg_max(left_words, left_weight) AS w, max(left_weight) AS g FROM caps WHERE NOT capped),
tgt AS (
  SELECT source, source_rank, source_size,
         CASE WHEN capped THEN (3 * source_size)::DOUBLE ELSE w::DOUBLE / g::DOUBLE * weight::DOUBLE END AS target
  FROM caps LEFT JOIN lvl ON TRUE),
queued AS (
  SELECT s.*, t.source_rank, t.source_size, t.target,
         sum(size) OVER (PARTITION BY t.source_rank ORDER BY key, s.doc_id, size ROWS UNBOUNDED PRECEDING) AS upto
  FROM sized s JOIN tgt t ON s.source IS NOT DISTINCT FROM t.source),
copies AS (
  SELECT q.*, e, ((e - 1) * source_size + upto)::DOUBLE / target AS finish, row_number() OVER () AS rid
  FROM queued q, (SELECT unnest([1, 2, 3]) AS e) WHERE size > 0),
served AS (
  SELECT *, sum(size) OVER (ORDER BY finish, source_rank, upto, e ROWS UNBOUNDED PRECEDING) - size AS before FROM copies),
got AS (
  SELECT doc_id, source, size, upto, sum(greatest(0, least(size, (SELECT sum(size) FROM sized) - before)))::BIGINT AS taken,
         count(*) FILTER (before < (SELECT sum(size) FROM sized)) AS copies
  FROM served GROUP BY ALL)
SELECT q.doc_id, q.size, q.source_size::BIGINT AS source_size, q.target, coalesce(g.taken, 0)::BIGINT AS taken, coalesce(g.copies, 0)::BIGINT AS copies
FROM queued q LEFT JOIN got g ON q.size > 0 AND g.doc_id IS NOT DISTINCT FROM q.doc_id AND g.source IS NOT DISTINCT FROM q.source AND g.upto = q.upto
"""
