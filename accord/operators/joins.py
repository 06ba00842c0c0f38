"""Joins that Spark has no operator for, from those that it has."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with value: that of the latest right row of the key at or before left's time. One sort of both sides, no pairs."""
    names = left.columns
    l_ = left.select(*names, F.lit(None).cast(right.schema[value].dataType).alias("asof_value"), F.lit(1).alias("asof_side"))
    r_ = right.select(*[F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], F.col(value).alias("asof_value"), F.lit(0).alias("asof_side"))
    w = W.partitionBy(key).orderBy(at, "asof_side").rowsBetween(W.unboundedPreceding, 0)
    both = l_.unionByName(r_).withColumn("asof_found", F.last("asof_value", ignorenulls=True).over(w))
    return both.where("asof_side = 1").select(*names, F.col("asof_found").alias(value))


def within(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs of a left row and a right row of its key that lies at most `seconds` before it, columns prefixed left_ and right_.

    Time is cut into cells as long as the interval; a left row meets right rows of its own cell and the one before, so a hot key is spread over its cells.
    """
    cell = lambda c: F.floor(F.unix_timestamp(c.cast("timestamp")) / seconds)
    l_ = left.select(*[F.col(c).alias(f"left_{c}") for c in left.columns]).withColumn("cell", F.explode(F.array(cell(F.col(f"left_{at}")), cell(F.col(f"left_{at}")) - 1)))
    r_ = right.select(*[F.col(c).alias(f"right_{c}") for c in right.columns]).withColumn("right_cell", cell(F.col(f"right_{at}")))
    near = (F.col(f"right_{at}") <= F.col(f"left_{at}")) & (F.col(f"right_{at}") >= F.col(f"left_{at}") - F.expr(f"INTERVAL '{seconds}' SECOND"))
    return l_.join(r_, (F.col(f"left_{key}") == F.col(f"right_{key}")) & (F.col("cell") == F.col("right_cell")) & near).drop("cell", "right_cell")
