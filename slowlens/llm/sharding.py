"""Sharding by longest processing time first: groups of equal texts go, largest first, to the least loaded shard.

Groups of one size are alike, so the heap is asked by size: how many of the groups of that size each shard takes. The
driver holds a count for each distinct size only. There are at most 2 x the root of all bytes of those (sizes up to the
root, and at most root-many groups beyond it): 350,000 at 30 GB, 20 million pairs of numbers at 100 TB. Groups of a size
are numbered where they lie and find their shard by their number. Shard sizes differ by no more than the last group that
the fullest shard took; only a group heavier than a shard's fair part can make that much, as it must not be split.

Cases: a null text weighs and groups as an empty one; repeated doc_ids keep one row each; an empty table gives no rows.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, hot_keys, numbered, numbered_in_place, placed_rows, salted_join, table

SHARDS, SLOT_BUCKETS, GROUP_BUCKETS, BROADCAST_ROWS = 8, 512, 64, 1_000_000


def _hash(text: Column, lane: int) -> Column:
    return F.xxhash64(F.lit(f"lane{lane}"), text)


def longest_first(sizes: np.ndarray, counts: np.ndarray, shards: int) -> np.ndarray:
    """How many groups of each size every shard takes; sizes fall, ties in load go to the lower shard.

    counts[i] groups of sizes[i] go one by one to the least loaded shard. As they are alike, that is the same as taking
    the counts[i] least of the loads that the shards have and would have after one, two, ... of them.
    """
    load = [0] * shards
    out = np.zeros((len(sizes), shards), np.int64)
    heap = [(0, s) for s in range(shards)]
    for i, (size, n) in enumerate(zip(sizes.tolist(), counts.tolist(), strict=True)):
        if n <= 4 * shards:
            for _ in range(n):
                at, s = heapq.heappop(heap)
                out[i, s] += 1
                load[s] = at + size
                heapq.heappush(heap, (load[s], s))
            continue
        low, high = min(load), max(load) + size * (n + 1)  # the greatest level with no more than n loads under it
        while high - low > 1:
            level = (low + high) // 2
            if sum(max(0, -(-(level - x) // size)) for x in load) <= n:
                low = level
            else:
                high = level
        took = [max(0, -(-(low - x) // size)) for x in load]
        left = n - sum(took)
        for s in range(shards):
            if left and load[s] + took[s] * size == low:
                took[s] += 1
                left -= 1
        out[i] = took
        load = [x + k * size for x, k in zip(load, took, strict=True)]
        heap = [(x, s) for s, x in enumerate(load)]
        heapq.heapify(heap)
    return out


def assign_shards(docs: DataFrame, scratch: Scratch, shards: int = SHARDS, text: str = "text") -> DataFrame:
    """Add `size` and `shard` to docs; equal texts share a shard."""
    body = F.coalesce(F.col(text), F.lit(""))
    keyed = docs.withColumn("size", (F.octet_length(body) + 1).cast("bigint")).withColumn("_slw_h1", _hash(body, 1)).withColumn("_slw_h2", _hash(body, 2))
    keyed = scratch.settle(keyed.drop(text), "keyed")
    groups = keyed.groupBy("_slw_h1", "_slw_h2").agg(F.sum("size").alias("_slw_bytes"), F.count("*").alias("_slw_n"))
    groups = scratch.settle(groups, "groups")
    sizes = groups.groupBy("_slw_bytes").agg(F.count("*").alias("n")).toArrow()  # a row for each distinct size
    order = np.argsort(-sizes["_slw_bytes"].to_numpy(), kind="stable")
    size, count = sizes["_slw_bytes"].to_numpy()[order], sizes["n"].to_numpy()[order]
    upto = np.cumsum(longest_first(size, count, shards), axis=1)
    spark = docs.sparkSession
    dealt = pa.table({"_slw_size": size, "_slw_upto": pa.ListArray.from_arrays(pa.array(np.arange(0, len(size) * shards + 1, shards, dtype=np.int32)), pa.array(upto.ravel()))})
    ends = spark.createDataFrame(dealt)
    nth = numbered(groups, "_slw_bytes", ["_slw_h1", "_slw_h2"], F.col("_slw_h1"), GROUP_BUCKETS, scratch, "_slw_nth")
    if len(size) <= BROADCAST_ROWS:
        nth = nth.join(F.broadcast(ends), F.col("_slw_bytes") == F.col("_slw_size"))
    else:
        usual = hot_keys(spark.createDataFrame(pa.table({"size": size, "n": count})), "size", "n")
        nth = salted_join(nth, ends, ["_slw_bytes"], ["_slw_size"], "_slw_bytes", "_slw_size", usual, F.col("_slw_h1"))
    shard = F.size(F.filter("_slw_upto", lambda u: u <= F.col("_slw_nth")))
    placed = scratch.settle(nth.select(F.col("_slw_h1").alias("_slw_g1"), F.col("_slw_h2").alias("_slw_g2"), "_slw_n", shard.alias("shard")), "shards")
    hot = hot_keys(placed, "_slw_g1", "_slw_n")
    out = salted_join(keyed, placed.drop("_slw_n"), ["_slw_h1", "_slw_h2"], ["_slw_g1", "_slw_g2"], "_slw_h1", "_slw_g1", hot, F.xxhash64("doc_id"))
    return out.drop("_slw_h1", "_slw_h2", "_slw_g1", "_slw_g2")


def shard_layout(docs: DataFrame, scratch: Scratch, shards: int = SHARDS, buckets: int = SLOT_BUCKETS, in_place: bool = False) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard; slots of a shard run from 0 without gaps. With `in_place`
    they follow the order of docs."""
    known = placed_rows(docs) if in_place else docs
    crc = F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32")
    known = known.select("doc_id", "text", crc, *["_slw_part", "_slw_row"] * in_place)
    narrow = assign_shards(known, scratch, shards)
    narrow = scratch.settle(narrow, "placed")
    if in_place:
        slots = numbered_in_place(narrow, "shard", scratch, "slot")
    else:
        slots = numbered(narrow, "shard", ["doc_id", "text_crc32", "size"], F.xxhash64("doc_id", "text_crc32"), buckets, scratch, "slot")
    return slots.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_layout(table(spark, sf_dir, "documents"), Scratch(spark, "op6"))
