"""Shared-folder tables: what cuts lineage and survives the loss of an executor."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of (long, long, long) that may be broadcast, about 24 MB; beyond it operators shuffle.
BROADCAST_ROWS = 1_000_000


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one where a session within one process names none."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir names no folder that driver and executors share")
        folder = tempfile.mkdtemp(prefix="poolcurator-")
        spark.sparkContext.setCheckpointDir(folder)
        folder = spark.sparkContext.getCheckpointDir()
    return folder.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def write_table(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """Writes df to the shared folder as Parquet; the table read back, and its path."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def drop_path(spark: SparkSession, path: str) -> None:
    """Removes a table that no later step reads."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def small_side(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if its counted rows are within the limit, else as it is."""
    return F.broadcast(df) if rows <= limit else df


def pick(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, so that extra columns never clash."""
    return df.select(*[F.col(f"`{n}`") for n in names])


def attach_by_group(rows: DataFrame, groups: DataFrame, keys: list[str], size: str, total: int, cells: int = 4096) -> DataFrame:
    """rows joined with groups on keys, where a group may hold a large share of all rows.

    groups has one row per key with the number of its rows in column `size`; the sizes add up
    to `total`, so fewer than `cells` groups are larger than total/cells. Those few are
    broadcast; what is left has no key above that size and is joined by a shuffle.
    Duplicated keys in groups are not allowed; rows without a group are dropped.
    """
    limit = max(1, total // cells)
    hot = F.broadcast(groups.where(F.col(size) > limit))
    cold = groups.where(F.col(size) <= limit)
    return rows.join(hot, keys).unionByName(rows.join(hot.select(*keys), keys, "left_anti").join(cold, keys))
