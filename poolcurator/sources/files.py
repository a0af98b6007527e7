"""File sources and sinks: formats, broken lines, idempotent stage outputs, a replay data source."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; only a session within one process may do without naming one."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir names no folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="poolcurator-"))
        folder = spark.sparkContext.getCheckpointDir()
    return folder.rstrip("/")


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


#: Lets shuffles of a finished write go at once; else they stay until the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_cleaning: dict[str, object] = {"lock": Lock(), "writes": 0, "before": None}


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """What is run inside leaves no shuffle files; the session has its own setting again after the last of several writes at once."""
    with _cleaning["lock"]:
        if not _cleaning["writes"]:
            _cleaning["before"] = spark.conf.get(CLEANUP, None)
            spark.conf.set(CLEANUP, "true")
        _cleaning["writes"] += 1
    try:
        yield
    finally:
        with _cleaning["lock"]:
            _cleaning["writes"] -= 1
            if not _cleaning["writes"]:
                spark.conf.unset(CLEANUP) if _cleaning["before"] is None else spark.conf.set(CLEANUP, _cleaning["before"])


def durable(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read back: later plans start from the table, also after an executor is lost.

    The write's shuffle files are dropped with it.
    """
    path = scratch(df.sparkSession, name)
    with shuffles_dropped(df.sparkSession):
        df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_durable(df: DataFrame) -> None:
    """Removes the files of a table that `durable` returned."""
    spark = df.sparkSession
    shared = shared_folder(spark).split("://")[-1]
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if shared in folder:  # never a table of the caller's
            drop_folder(spark, folder)


def drop_folder(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> DataFrame:
    """df as a table bucketed and sorted by key: joins and aggregates of such tables on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return df.sparkSession.table(table)


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """df written in a format and read back with its schema."""
    spark = df.sparkSession
    path = scratch(spark, fmt)
    options = {"header": "true", "escape": '"'} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(path)
    return spark.read.format(fmt).options(**options).schema(df.schema).load(path)


def parse_jsonl(lines: DataFrame, ddl: str) -> DataFrame:
    """Lines of JSON (column value) as columns; _corrupt has the lines that do not parse."""
    p = F.from_json("value", f"{ddl}, _corrupt string", {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_corrupt"})
    return lines.select(p.alias("p")).select("p.*")


def write_selection(pool: DataFrame, selected: DataFrame, path: str, fmt: str = "parquet", key: str = "sample_id") -> None:
    """The selected samples in training layout; ids are few and broadcast only if their count says so."""
    from poolcurator.operators.topk import rehydrate

    rehydrate(pool, selected, key).select(key, "instruction", "input", "output").write.mode("overwrite").format(fmt).save(path)


def write_stage(df: DataFrame, path: str, run_id: str, bucket: str) -> None:
    """Idempotent sink: the (run, bucket) partition is replaced as a whole, so a repeated task or run adds nothing twice."""
    df.withColumns({"run_id": F.lit(run_id), "bucket": F.lit(bucket)}).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id", "bucket").parquet(path)


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _ReplayReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.parts, self.every = int(options.get("rows", 10)), int(options.get("partitions", 2)), int(options.get("broken_every", 0))

    def partitions(self) -> list[InputPartition]:
        step = max(1, -(-self.n // self.parts))
        return [_Range(i, min(self.n, i + step)) for i in range(0, self.n, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        import json

        for i in range(partition.lo, partition.hi):
            good = json.dumps([{"sample_id": i, "scores": {"clean": i % 5 + 1}, "reasoning": "", "flagged": False}])
            yield i, [i], good[:7] if self.every and i % self.every == self.every - 1 else good


class ReplayVerdicts(DataSource):
    """Made-up judge replies (batch_id, members, raw), for tests and load trials; options rows, partitions, broken_every."""

    @classmethod
    def name(cls) -> str:
        return "replay_verdicts"

    def schema(self) -> str:
        return "batch_id long, members array<long>, raw string"

    def reader(self, schema) -> DataSourceReader:
        return _ReplayReader(self.options)
