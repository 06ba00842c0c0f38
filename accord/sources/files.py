"""Readers and writers: table files in several formats, image folders, layouts by source and grade, and an idempotent sink for streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None) -> DataFrame:
    """kind: parquet, orc, json, csv (with a header) or frames, a folder of image files as bytes. Text formats need a schema: none is inferred."""
    if kind == "frames":
        return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    reader = spark.read
    if kind in ("json", "csv"):
        if schema is None:
            raise ValueError(f"{kind} needs a schema")
        reader = reader.schema(schema)
    if kind == "csv":
        reader = reader.option("header", "true")
    return reader.format(kind).load(path)


def require(df: DataFrame, schema: StructType | str) -> DataFrame:
    """df, if it has the columns of schema with their types."""
    want = schema if isinstance(schema, StructType) else StructType.fromDDL(schema)
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    bad = [f"{f.name}: {have.get(f.name)} for {f.dataType.simpleString()}" for f in want if have.get(f.name) != f.dataType.simpleString()]
    if bad:
        raise ValueError("; ".join(bad))
    return df


def write(df: DataFrame, path: str, kind: str = "parquet", by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    """Partition columns are low in number: source and grade, not videos."""
    w = df.write.mode(mode).format(kind)
    if kind == "csv":
        w = w.option("header", "true")
    (w.partitionBy(*by) if by else w).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "video_id") -> None:
    """A table bucketed and sorted by video: pairing, choosing and building by video then need no exchange. Rows are dealt first, so each bucket is one file."""
    df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def upsert_batches(path: str, keys: list[str]):
    """A function for foreachBatch: a batch written again replaces itself, and latest() shows each key once."""

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.withColumn("batch_id", F.lit(batch_id)).write.mode("overwrite").parquet(f"{path}/batch={batch_id:012d}")

    return put


def latest(spark: SparkSession, path: str, keys: list[str]) -> DataFrame:
    """Of each key the row of the last batch."""
    rows = spark.read.option("recursiveFileLookup", "true").parquet(path)
    rest = [c for c in rows.columns if c not in (*keys, "batch_id")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch_id").alias("r")).select(*keys, "r.*")
