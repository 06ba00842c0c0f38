"""What the operators share: table access, shared scratch space (from the library), and column helpers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from accord.scratch import dropped, few_files, scratch_dir, written

__all__ = ["WORD", "dropped", "few_files", "let", "scratch_dir", "spare", "table", "written"]

#: A word is a run of characters other than the space and U+0009 to U+000D.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def let(value: Column, use) -> Column:
    """Evaluates value once for each row and hands it to use as a variable, which the optimiser can't copy into loops."""
    return F.transform(F.array(value), use)[0]


def spare(name: str, taken) -> str:
    """name, with underscores after it until it is none of the names taken (compared as Spark does, without case)."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name += "_"
    return name

