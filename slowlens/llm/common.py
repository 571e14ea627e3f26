"""What the corpus operators share: table access, shared scratch space, row numbering and components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_local_base: str | None = None
_open: list[Scratch] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_base(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; one of our own only where none is set."""
    global _local_base
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if _local_base is None:
        _local_base = tempfile.mkdtemp(prefix="slowlens-")
    return f"file://{_local_base}"


class Scratch:
    """Tables written to the shared folder: they cut lineage and survive the loss of executors."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_base(spark)}/{label}-{uuid.uuid4().hex}"
        self.count = 0
        _open.append(self)

    def settle(self, df: DataFrame, name: str) -> DataFrame:
        self.count += 1
        path = f"{self.root}/{self.count:03d}-{name}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def clear(self) -> None:
        """Delete every table of this scratch; only once nothing that reads them is still to run."""
        where = self.spark._jvm.org.apache.hadoop.fs.Path(self.root)
        where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)

    def drop(self, *frames: DataFrame | None) -> None:
        """Delete settled tables that no later plan reads."""
        for df in frames:
            path = getattr(df, "_scratch_path", None)
            if path:
                jvm = self.spark._jvm
                where = jvm.org.apache.hadoop.fs.Path(path)
                where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)


def clear_since(mark: int) -> None:
    """Delete the scratch tables opened since there were `mark` of them."""
    while len(_open) > mark:
        _open.pop().clear()


def opened() -> int:
    return len(_open)


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The same rows in short batches, so that a Python worker holds few texts as strings at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def numbered(df: DataFrame, key: str, order: list, spread, buckets: int, scratch: Scratch, out: str) -> DataFrame:
    """Number the rows of each key from 0 without gaps, no task holding a whole key.

    Rows of a key are dealt into `buckets` by `spread` (an integer column that is even over rows); a small table of
    counts by (key, bucket) gives each bucket its offset. The counts are summed map-side, and the running sum runs over
    keys x buckets rows only.
    """
    return _numbered(df.withColumn("_slw_b", F.pmod(spread, F.lit(buckets)).cast("int")), key, order, scratch, out)


def placed_rows(df: DataFrame, stretch: int = 4096) -> DataFrame:
    """Add _slw_part and _slw_row: the place of every row in the order of df, in stretches of so many rows.

    Of tables in files that is the order of file names (longer ones last, as Spark counts its part files), then of rows
    in a file; of other frames the order of partitions, then of rows.
    """
    try:
        placed = df.withColumn("_slw_file", F.col("_metadata.file_name")).withColumn("_slw_row", F.col("_metadata.row_index"))
        placed.schema  # noqa: B018  # analysed here
    except AnalysisException:
        placed = df.withColumn("_slw_file", F.lit("")).withColumn("_slw_row", F.monotonically_increasing_id())
    name = F.concat(F.lpad(F.length("_slw_file").cast("string"), 4, "0"), "_slw_file", F.lpad(F.floor(F.col("_slw_row") / stretch).cast("string"), 19, "0"))
    return placed.withColumn("_slw_part", name).drop("_slw_file")


def numbered_in_place(df: DataFrame, key: str, scratch: Scratch, out: str) -> DataFrame:
    """Number the rows of each key from 0 without gaps, in the order that placed_rows() noted."""
    return _numbered(df.withColumnRenamed("_slw_part", "_slw_b"), key, ["_slw_row"], scratch, out).drop("_slw_row")


def _numbered(dealt: DataFrame, key: str, order: list, scratch: Scratch, out: str) -> DataFrame:
    """Numbers by bucket (_slw_b), in a bucket by `order`."""
    counts = dealt.groupBy(key, "_slw_b").agg(F.count("*").alias("_slw_n"))
    before = Window.partitionBy(key).orderBy("_slw_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(F.col(key).alias("_slw_k"), F.col("_slw_b").alias("_slw_ob"), F.coalesce(F.sum("_slw_n").over(before), F.lit(0)).alias("_slw_off"))
    offsets = scratch.settle(offsets, "offsets")
    within = Window.partitionBy(key, "_slw_b").orderBy(*order)
    return (
        dealt.withColumn("_slw_rn", F.row_number().over(within))
        .join(offsets, F.col(key).eqNullSafe(F.col("_slw_k")) & (F.col("_slw_b") == F.col("_slw_ob")))
        .withColumn(out, F.col("_slw_off") + F.col("_slw_rn") - 1)
        .drop("_slw_b", "_slw_rn", "_slw_k", "_slw_ob", "_slw_off")
    )


def hot_keys(counts: DataFrame, key: str, n: str, parts: int = 500, total: int | None = None) -> list:
    """The keys that hold 1/parts of all rows or more; `counts` has a row for each key and its number of rows.

    At most `parts` keys reach the driver, by arithmetic. Where `total` is given, it is that many rows of which a key has
    to hold a part.
    """
    if total is None:
        total = counts.agg(F.sum(n)).first()[0] or 0
    least = max(2, -(-total // parts))
    return [r[0] for r in counts.where(F.col(n) >= least).select(key).collect()] if total > parts else []


def salted_join(left: DataFrame, right: DataFrame, left_on: list[str], right_on: list[str], left_key: str, right_key: str, hot: list, spread, how: str = "inner", salts: int = 128) -> DataFrame:
    """left join right, the rows of hot keys dealt over `salts` tasks.

    `right` has few rows for each key. Rows of left with a hot key go by key and a share of `spread`; the hot rows of right,
    few as there are few hot keys, are repeated once for each share. Other rows join as ever.
    """
    on = [F.col(a) == F.col(b) for a, b in zip(left_on, right_on, strict=True)]
    if hot:
        left = left.withColumn("_slw_salt", F.when(F.col(left_key).isin(hot), F.pmod(spread, F.lit(salts))).otherwise(0).cast("int"))
        shares = F.when(F.col(right_key).isin(hot), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
        right = right.withColumn("_slw_share", F.explode(shares))
        on.append(F.col("_slw_salt") == F.col("_slw_share"))
    condition = on[0]
    for c in on[1:]:
        condition = condition & c
    return left.join(right, condition, how).drop("_slw_salt", "_slw_share")


def components(links: DataFrame, scratch: Scratch, rounds: int = 60) -> DataFrame:
    """Connected components of links (a, b): one row (node, comp) per linked node, comp being the smallest node.

    Labels spread to neighbours and then jump to the label of their label, so chains shrink geometrically; each round is
    an aggregation and two joins on tables in the shared folder, and nothing is gathered on the driver but a count.
    """
    both = scratch.settle(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    hubs = hot_keys(both.groupBy("b").agg(F.count("*").alias("n")), "b", "n")  # leaders of groups of copies
    labels = scratch.settle(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("comp")), "labels")
    for _ in range(rounds):
        near = salted_join(both, labels, ["b"], ["node"], "b", "node", hubs, F.xxhash64("a")).groupBy("a").agg(F.min("comp").alias("m"))
        step = labels.join(near, labels.node == near.a).select("node", F.least("comp", "m").alias("comp"), F.col("comp").alias("old"))
        step = scratch.settle(step, "step")
        far = step.select(F.col("node").alias("far"), F.col("comp").alias("_c"))
        # a component is named by one of its nodes, most often the hub of a star
        large = hot_keys(step.groupBy("comp").agg(F.count("*").alias("n")), "comp", "n") if hubs else []
        new = scratch.settle(salted_join(step, far, ["comp"], ["far"], "comp", "far", large, F.xxhash64("node")).select("node", F.least("comp", "_c").alias("comp"), "old"), "labels")
        scratch.drop(labels, step)
        labels = new
        if labels.where("comp <> old").limit(1).count() == 0:
            return labels.select("node", "comp")
    raise RuntimeError("components did not settle; raise `rounds`")
