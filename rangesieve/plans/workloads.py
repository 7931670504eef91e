"""Query batches: one question for each key (or each key of a repeatable share), so a batch grows with the table. Ends
are drawn by a mixing hash of the key, so that any engine makes the same ranges and they are no lattice."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK, Dialect, mixed
from rangesieve.operators.order import keep_empty

LENGTHS = (1, 32, 1024)
__all__ = ["LENGTHS", "ends", "heldout", "hold_out", "keep_empty", "share"]


def width(degree: int) -> int:
    """Places from a key on where a correlated range may start; degree is 10 D."""
    return 2 ** (3 * (10 - degree)) + 1


def left_end(d: Dialect, kind: str, length, u: int, degree: int = 8, cell: int = 0) -> str:
    """SQL text of the left end of key k's question. Each cell of an experiment draws on its own."""
    if kind == "uncorrelated":
        return mixed(d, "k", u - length, 100 + cell)
    if kind == "correlated":
        return f"(k + {mixed(d, 'k', width(degree), 200 + cell)})"
    if kind == "nonempty":
        return f"greatest(0, k - {mixed(d, 'k', length, 300 + cell)})"
    raise ValueError(kind)


def ends(keys: DataFrame, kind: str, length: int, u: int, degree: int = 8, cell: int = 0) -> DataFrame:
    """(qid, a, b): the question of every key; qid is the key."""
    return keys.selectExpr("k AS qid", f"{left_end(SPARK, kind, length, u, degree, cell)} AS a").selectExpr("qid", "a", f"a + {length - 1} AS b")


def share(keys: DataFrame, one_in: int) -> DataFrame:
    """One key in `one_in`, by a draw on the key itself."""
    return keys.where(f"{mixed(SPARK, 'k', one_in, 6)} = 0") if one_in > 1 else keys


def hold_out(keys: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(kept, withheld): a tenth of the keys, by a draw on the key itself."""
    tagged = keys.withColumn("_t", F.expr(mixed(SPARK, "k", 10, 5)))
    return tagged.where("_t <> 0").select("k"), tagged.where("_t = 0").select("k")


def heldout(withheld: DataFrame, length: int) -> DataFrame:
    return withheld.selectExpr("k AS qid", "k AS a", f"k + {length - 1} AS b")


# --- the same as SQL over a CTE keys(k) -------------------------------------------------------------------------------


def empties_sql(ranges: str) -> str:
    return f"SELECT w.* FROM ({ranges}) w ASOF LEFT JOIN keys ON w.b >= keys.k WHERE keys.k IS NULL OR keys.k < w.a"
