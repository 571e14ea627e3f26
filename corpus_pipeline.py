"""From raw documents to balanced shards: quality, near duplicates, benchmark leaks, mixing, sharding.

Each stage works on all that its predecessor kept; run() writes every stage's result to the shared folder, reads it
again for the next, and deletes what a stage wrote for itself. The mixed order lives in the order of the mixing stage's
files and rows; the last stage reads it from there and numbers the slots of each shard by it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm import decontaminate, minhash, mixing, quality, sharding
from slowlens.llm.common import Scratch, clear_since, opened, table

WEIGHTS: dict[str, float] | None = None  # target weights of sources; None: roots of their sizes


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier doesn't reject."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    scored = quality.score_documents(docs, model, docs.columns, "_slw_score")
    return scored.where(F.col("_slw_score") >= quality.ACCEPT).select(*docs.columns)


def keep_first_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies."""
    return minhash.drop_near_duplicates(docs, Scratch(spark, "near"))


def keep_unleaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"), Scratch(spark, "leaks"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, range-partitioned and sorted into the mixed order."""
    mixed = mixing.mix(docs, Scratch(spark, "mix"), WEIGHTS)
    return mixed.orderBy("_slw_slot", "_slw_in_block").select(*docs.columns)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard of all documents; slots of a shard follow the mixed order."""
    return sharding.shard_layout(docs, Scratch(spark, "shards"), in_place=True)


STAGES = [("quality", keep_good), ("near_duplicates", keep_first_copies), ("decontamination", keep_unleaked), ("mixing", mix_sources), ("sharding", shard)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        before, mark = docs, opened()
        docs = scratch.settle(stage(spark, docs, sf_dir), name)
        scratch.drop(before)
        clear_since(mark)  # what the stage wrote for itself
    return docs
