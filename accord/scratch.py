"""Tables in the folder that all executors share: they cut lineage, survive lost executors and can be read as often as needed."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Files of a table that is written, at most: so many for each core, or a part of the shuffle partitions where those are more.
FILES_PER_CORE, PARTITIONS_PER_FILE = 8, 4
_MADE: set[str] = set()


def scratch_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir; where that is unset, one in the warehouse, or on a single machine a temporary one."""
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    master = spark.sparkContext.master
    if not at and (not master.startswith("local") or master.startswith("local-cluster")):
        at = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/scratch"
    if not at:
        at = getattr(scratch_dir, "own", None)
        if at is None:
            at = scratch_dir.own = tempfile.mkdtemp(prefix="accord-")
            atexit.register(shutil.rmtree, at, ignore_errors=True)
        at = f"file://{at}"
    return at


def few_files(df: DataFrame) -> DataFrame:
    """df in fewer partitions, without another shuffle, where a plan ends in very many: what is written from it has so many files. Their number
    follows the cores and the shuffle partitions, so a task never takes more than PARTITIONS_PER_FILE of those once there are many."""
    spark = df.sparkSession
    return df.coalesce(max(FILES_PER_CORE * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")) // PARTITIONS_PER_FILE))


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows as a table in the shared folder, in as many files as few_files() allows: cuts lineage, survives lost executors, and is read as often as needed."""
    path = f"{scratch_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df = few_files(df)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    _MADE.add(path)
    return out


def dropped(df: DataFrame) -> None:
    """Removes a table of written() that no later plan reads."""
    _remove(df.sparkSession, df.scratch_path)


def clear(spark: SparkSession) -> None:
    """Removes all tables that written() has made in this process and that are still there: for when the results that read them have been stored."""
    for path in list(_MADE):
        _remove(spark, path)


def _remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _MADE.discard(path)
