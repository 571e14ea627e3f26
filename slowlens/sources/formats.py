"""Readers and writers: Parquet, CSV, JSON, ORC, text logs, day partitions, buckets, results, and a Python data source."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_local_base: str | None = None


def work_path(spark: SparkSession, name: str) -> str:
    """A new path in the cluster's shared folder, or in a folder of our own where no cluster names one."""
    global _local_base
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        _local_base = _local_base or f"file://{tempfile.mkdtemp(prefix='slowlens-')}"
        base = _local_base
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    """Write in a format and read it again with the same schema."""
    path = work_path(df.sparkSession, fmt)
    df.write.format(fmt).save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).load(path)


def write_text_log(log: DataFrame) -> str:
    """A statement log as plain lines: oid|server|time."""
    path = work_path(log.sparkSession, "log")
    log.select(F.concat_ws("|", F.col("oid").cast("string"), F.col("server").cast("string"), F.col("time_s").cast("string"))).write.text(path)
    return path


def text_log(spark: SparkSession, path: str) -> DataFrame:
    """Plain log lines as columns; lines of another form are left out."""
    pattern = r"^(\d+)\|(\d+)\|([0-9.]+)$"
    part = lambda i: F.regexp_extract("value", pattern, i)
    return spark.read.text(path).where(F.col("value").rlike(pattern)).select(part(1).cast("bigint").alias("oid"), part(2).cast("bigint").alias("server"), part(3).cast("decimal(18,2)").alias("time_s"))


def record_threshold(log: DataFrame, seconds: float = 5.0) -> DataFrame:
    """Statements slower than the threshold of the recorder."""
    return log.where(F.col("time_s") > seconds)


def by_day(events: DataFrame, ts: str = "ts") -> DataFrame:
    """The same rows from files by day: a filter on `day` reads its files only."""
    path = work_path(events.sparkSession, "days")
    events.withColumn("day", F.col(ts).cast("date")).write.partitionBy("day").parquet(path)
    return events.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by key: joins and groups on the key need no exchange."""
    name = f"slowlens_{uuid.uuid4().hex}"
    path = work_path(df.sparkSession, name)
    df.write.bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
    return df.sparkSession.table(name)


def save_result(result: DataFrame, path: str) -> None:
    """A result both as Parquet and as JSON lines of its patterns."""
    result.write.parquet(f"{path}/parquet")
    result.write.json(f"{path}/json")


class _LogReader(DataSourceReader):
    def __init__(self, path: str, names: list[str]):
        self.path, self.names = path, names

    def partitions(self):
        return [InputPartition(n) for n in self.names]

    def read(self, partition):
        import pyarrow.fs as fs

        store, where = fs.FileSystem.from_uri(partition.value)
        with store.open_input_stream(where) as f:
            for line in f.read().decode().splitlines():
                oid, server, time_s = line.split("|")
                yield int(oid), int(server), float(time_s)


class LogSource(DataSource):
    """A directory of log files, one partition a file."""

    @classmethod
    def name(cls) -> str:
        return "slowlens_log"

    def schema(self) -> str:
        return "oid bigint, server bigint, time_s double"

    def reader(self, schema) -> DataSourceReader:
        import pyarrow.fs as fs

        path = self.options["path"]
        store, where = fs.FileSystem.from_uri(path)
        scheme = path.split("://")[0] + "://" if "://" in path else "file://"
        found = [x.path for x in store.get_file_info(fs.FileSelector(where)) if x.base_name.startswith("part-")]
        return _LogReader(path, [scheme + p for p in sorted(found)])


def register_log_source(spark: SparkSession) -> None:
    spark.dataSource.register(LogSource)
