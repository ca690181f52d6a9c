"""The last row before a position, and the rows inside an interval, without pairing each question with all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def last_before(asked: DataFrame, rows: DataFrame, value: Column, by: list[str], at: str = "fix_seq", inclusive: bool = False) -> DataFrame:
    """``asked`` with ``met``: ``value`` (a struct) of the last of ``rows`` of the same ``by`` whose seq is below ``at``, or equal if ``inclusive``.

    Questions and rows stand in one order per key and a window carries the latest row on; of rows at one position the
    greatest value counts.  Questions without any row go.
    """
    questions = asked.select(*by, F.col(at).alias("__pos"), F.lit(1).alias("__kind"), F.struct(*asked.columns).alias("__row"), F.lit(None).alias("__met"))
    shown = rows.select(*by, F.col("seq").alias("__pos"), F.lit(0 if inclusive else 2).alias("__kind"), F.lit(None).alias("__row"), value.alias("__met"))
    order = W.partitionBy(*by).orderBy("__pos", "__kind", "__met").rowsBetween(W.unboundedPreceding, W.currentRow)
    met = shown.unionByName(questions).withColumn("met", F.last("__met", ignorenulls=True).over(order))
    return met.where("__row is not null and met is not null").select("__row.*", "met")


def inside(asked: DataFrame, rows: DataFrame, by: list[str], after: str, until: str, at: str, width: int = 256) -> DataFrame:
    """``asked`` joined to the ``rows`` of the same ``by`` whose ``at`` lies in (after, until], by pieces of ``width`` positions."""
    piece = lambda c: F.floor(F.col(c) / width).cast("long")
    spread = asked.where(F.col(after) < F.col(until)).withColumn("__piece", F.explode(F.sequence(piece(after), piece(until))))
    met = spread.join(rows.withColumn("__piece", piece(at)), [*by, "__piece"])
    return met.where((F.col(at) > F.col(after)) & (F.col(at) <= F.col(until))).drop("__piece")
