"""Continuous supervision: the log as a stream, waits and alerts in windows, watched patterns, periodic mining."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slowlens.functions import exact
from slowlens.operators import selectors
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.lattice import describe, to_column
from slowlens.operators.selectors import Selector
from slowlens.plans import search
from slowlens.sources.formats import work_path

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])
DELAY = "1 hour"


def read_stream(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """A directory of log files as a stream. Watermarks need a time zone, so ts becomes a timestamp."""
    reader = spark.readStream.schema(EVENTS)
    reader = reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def run_available(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there, into files, and read the result; for tests and catching up."""
    spark = stream.sparkSession
    out, mark = work_path(spark, "stream"), checkpoint or work_path(spark, "offsets")
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out).outputMode("append")
    else:
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(out))
    handle = writer.option("checkpointLocation", mark).trigger(availableNow=True).start()
    handle.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling_waits(events: DataFrame, width: str = "1 day") -> DataFrame:
    """Sessions by class and window; state of a window goes once the watermark passes it."""
    return events.withWatermark("ts", DELAY).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding_alerts(events: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    """Alert rate in overlapping windows."""
    w = F.window("ts", width, slide).alias("w")
    return events.withWatermark("ts", DELAY).groupBy(w).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("errors")).select(F.col("w.start").alias("start"), "n", "errors")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Activity of a server between pauses."""
    return events.withWatermark("ts", DELAY).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def with_environment(events: DataFrame, env: DataFrame) -> DataFrame:
    """Stream to static; env has columns server and properties."""
    return events.join(env, events["user_id"] == env["server"], "left").drop("server")


def runs_with_alerts(runs: DataFrame, alerts: DataFrame, hours: int = 48) -> DataFrame:
    """Stream to stream: runs and the alerts of their server in the hours before; both sides keep state that long."""
    r = runs.withWatermark("ts", DELAY).select(F.col("event_id").alias("oid"), "user_id", F.col("ts").alias("run_ts"))
    a = alerts.withWatermark("ts", DELAY).where("event_type = 'error'").select(F.col("event_id").alias("alert"), F.col("user_id").alias("alert_user"), F.col("ts").alias("alert_ts"))
    on = (F.col("user_id") == F.col("alert_user")) & (F.col("run_ts") > F.col("alert_ts")) & (F.col("run_ts") <= F.col("alert_ts") + F.expr(f"INTERVAL {hours} HOURS"))
    return r.join(a, on).select("oid", "alert")


def deduplicated(events: DataFrame) -> DataFrame:
    """Each event once, ids remembered as long as late rows may come."""
    return events.withWatermark("ts", DELAY).dropDuplicatesWithinWatermark(["event_id"])


class Watch:
    """Watched patterns: running count, sum and sum of squares of the target, merged batch by batch into a small table.

    Each batch leaves a new version of the table under `path`, named by the batch, so a replayed batch changes nothing, and
    a watch that is made anew on the same path goes on from the last whole version. The offsets of the stream stand beside
    it, as both must go on together. Rows with a null target count nowhere. Sums are exact unless the target is floating.
    """

    def __init__(self, spark: SparkSession, patterns: list[tuple[Selector, ...]], target: str = "t", level: float | None = None, path: str | None = None):
        self.spark, self.patterns, self.target, self.level = spark, patterns, target, level
        self.root = path or work_path(spark, f"watch-{uuid.uuid4().hex}")
        self.version = max(self._versions(), default=-1)

    def _place(self, name: str):
        """A file or folder under the root, and its file system."""
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}" if name else self.root)
        return at.getFileSystem(self.spark._jsc.hadoopConfiguration()), at

    def _versions(self) -> list[int]:
        """Versions written to their end."""
        fs, root = self._place("")
        found = [s.getPath().getName() for s in fs.listStatus(root)] if fs.exists(root) else []
        return sorted(int(n) for n in found if n.isdigit() and fs.exists(self._place(f"{n}/_SUCCESS")[1]))

    @property
    def path(self) -> str | None:
        return f"{self.root}/{self.version}" if self.version >= 0 else None

    def update(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.version:
            return
        kind, t = batch.schema[self.target].dataType, F.col(self.target)
        total = "double" if exact.is_floating(kind) else f"decimal(38,{kind.scale if isinstance(kind, T.DecimalType) else 0})"
        flags = F.filter(F.array(*[F.when(to_column(p), F.lit(describe(p))) for p in self.patterns], F.lit("all")), lambda x: x.isNotNull())
        rows = batch.where(t.isNotNull()).select(F.explode(flags).alias("description"), exact.summand(t, kind).alias("s1"), (t.cast("double") * t.cast("double")).alias("s2"), F.lit(1).cast("bigint").alias("n"))
        merge = lambda df: df.groupBy("description").agg(F.sum("n").alias("n"), F.sum("s1").cast(total).alias("s1"), F.sum("s2").alias("s2"))
        new = merge(rows)
        if self.path:
            new = merge(new.unionByName(self.spark.read.parquet(self.path)))
        new.write.mode("overwrite").parquet(f"{self.root}/{batch_id}")
        old = [v for v in self._versions() if v < self.version]  # the version before stays for those who read it now
        self.version = batch_id
        for v in old:
            fs, at = self._place(str(v))
            fs.delete(at, True)

    def table(self) -> DataFrame:
        """description, n, mean, and `crossed` where the mean is above the level."""
        if self.path is None:
            return self.spark.createDataFrame([], "description string, n bigint, mean double, crossed boolean")
        mean = F.col("s1").cast("double") / F.col("n")
        return self.spark.read.parquet(self.path).select("description", "n", F.round(mean, 6).alias("mean"), (mean > (self.level if self.level is not None else float("inf"))).alias("crossed"))

    def start(self, stream: DataFrame, checkpoint: str | None = None):
        return stream.writeStream.foreachBatch(self.update).option("checkpointLocation", checkpoint or f"{self.root}/offsets").trigger(availableNow=True).start()


def remine(stream: DataFrame, build: Callable[[DataFrame], SubgroupDataset], nominal: list[str], keep: list[DataFrame], measure: str = "wracc", k: int = 5, depth: int = 2):
    """Search each batch anew; results go to `keep`."""

    def mine(batch: DataFrame, batch_id: int) -> None:
        ds = build(batch)
        session = search.Session(ds, selectors.nominal(ds, nominal), search.get(measure).needs == "median")
        keep.append(search.beam(session, measure, k, depth).frame(batch.sparkSession))
        session.close()

    return stream.writeStream.foreachBatch(mine).option("checkpointLocation", work_path(stream.sparkSession, "offsets")).trigger(availableNow=True).start()
