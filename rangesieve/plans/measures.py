"""Accuracy and cost measures over frames of answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fpr(answers: DataFrame, *by: str) -> DataFrame:
    """Rate of "maybe" over a batch of empty ranges."""
    return answers.groupBy(*by).agg(F.count("*").alias("n_ranges"), F.round(F.avg(F.col("maybe").cast("int")), 6).alias("fpr"))


def false_negatives(answers: DataFrame, *by: str) -> DataFrame:
    """Number of "empty" over a batch of ranges with keys."""
    return answers.groupBy(*by).agg(F.count("*").alias("n_ranges"), F.sum((~F.col("maybe")).cast("long")).alias("false_negatives"))


#: Upper 95 % limit of a rate by the score interval, as SQL over (n_ranges, positives): not 0 where no positive was seen.
_Z = 1.96
_UPPER = f"(positives + {_Z**2 / 2} + {_Z} * sqrt(positives * (n_ranges - positives) / CAST(n_ranges AS DOUBLE) + {_Z**2 / 4})) / (n_ranges + {_Z**2})"
LIMITS_SQL = f"round(positives / CAST(n_ranges AS DOUBLE), 6) AS fpr, round({_UPPER}, 9) AS fpr_high"


def with_limits(counts: DataFrame) -> DataFrame:
    """Rates and their upper 95 % limits from (n_ranges, positives)."""
    return counts.selectExpr("*", *LIMITS_SQL.replace(", round", "\n round").split("\n"))


def gaps(rates: DataFrame, one: str, *by: str) -> DataFrame:
    """(*by, other, orders, seen): log10 of each other method's rate over that of `one`, with half a positive more each."""
    half = F.expr("(positives + 0.5) / (n_ranges + 1)")
    base = rates.where(F.col("method") == one).select(*[F.col(c).alias(f"{c}_") for c in by], half.alias("x_"), F.col("positives").alias("p_"))
    both = rates.where(F.col("method") != one).join(base, [F.col(c) == F.col(f"{c}_") for c in by])
    return both.select(*by, F.col("method").alias("other"), F.round(F.log10(half / F.col("x_")), 4).alias("orders"), ((F.col("positives") > 0) & (F.col("p_") > 0)).alias("seen"))


def gaps_sql(rates: str, one: str, by: str) -> str:
    return f"WITH rates AS MATERIALIZED ({rates}) SELECT {by}, o.method AS other, round(log10(((o.positives + 0.5) / (o.n_ranges + 1)) / ((x.positives + 0.5) / (x.n_ranges + 1))), 4) AS orders, o.positives > 0 AND x.positives > 0 AS seen FROM (SELECT * FROM rates WHERE method <> '{one}') o JOIN (SELECT * FROM rates WHERE method = '{one}') x USING ({by})"


def against_bound(each: DataFrame) -> DataFrame:
    """(bits, len, fpr, error, bound) from a row a hash draw (bits, len, n_ranges, positives): mean and standard error."""
    rate = F.col("positives") / F.col("n_ranges")
    found = each.groupBy("bits", "len").agg(F.round(F.avg(rate), 6).alias("fpr"), F.round(F.stddev_samp(rate) / F.sqrt(F.count("*")), 6).alias("error"))
    return found.withColumn("bound", F.expr("round(least(1.0D, len / pow(2.0D, bits - 2)), 6)"))


def robustness(rates: DataFrame, *by: str) -> DataFrame:
    """From rates (d, fpr): extremes over d, and the least d with a rate above one half (-1 if none)."""
    return rates.groupBy(*by).agg(F.max("fpr").alias("worst"), F.min("fpr").alias("best"), F.coalesce(F.min(F.when(F.col("fpr") > 0.5, F.col("d"))), F.lit(-1)).alias("lost_at"))


def predictability(rates: DataFrame, *by: str) -> DataFrame:
    """Spread of the rate over views and workloads."""
    return rates.groupBy(*by).agg(F.round(F.max("fpr") - F.min("fpr"), 6).alias("spread"), F.round(F.stddev_pop("fpr"), 6).alias("deviation"))


def worst_regions(answers: DataFrame, shift: int, k: int) -> DataFrame:
    """The k regions of width 2^shift with the most false positives (ties: lower region first)."""
    return answers.where("maybe").groupBy(F.expr(f"shiftright(a, {shift})").alias("region")).agg(F.count("*").alias("false_positives")).orderBy(F.desc("false_positives"), "region").limit(k)
