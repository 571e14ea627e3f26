"""Mixing sources to target weights by Pfair scheduling, in DataFrame expressions only.

A source with target weight w owns block i (from 1) in the window from floor((i - 1) / w) to ceil(i / w); among the
released blocks the one with the earliest deadline takes the next slot. Target weights are fractions with one denominator,
the period: the least period up to `slots` in which every asked weight is a whole number of slots, else one of about
`slots`, in which each asked weight is rounded to a whole number, at least one. The schedule repeats after a period, so
one is laid out once, in a fold over its slots, and block i of any source finds its slot by division, whatever the size of
the corpus. Sources of equal weight have equal windows and are one class in the fold, so its state grows with the root of
the period and not with the number of sources. Up to the slot where the first source runs out, the blocks that a source
has had never differ from weight x slots by a whole block; later its slots stay empty and the others keep their order. No
row is dropped or repeated, and every source is a stream of its own.

Cases: a null source is a source of its own; a source of weight 0, or without one where weights are given, follows after
all others, block by block; repeated rows keep one position each; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, numbered, table

SLOTS, BLOCK, BUCKETS, CHUNK, BROADCAST_ROWS, DIGITS = 8192, 16, 1024, 64, 1_000_000, 1e-9


def stream_shares(docs: DataFrame, scratch: Scratch, power: float = 0.5, weights: dict[str, float] | None = None, slots: int = SLOTS) -> DataFrame:
    """(source, n, stream, share, class, member): each source's rows, its number from 0, its slots in a period, and its
    place among the sources of equal share. A row for each source.

    Target weights are given, or else go as the number of rows to `power`.
    """
    size = docs.groupBy("source").agg(F.count("*").alias("n"))
    if weights:
        given = F.create_map(*[F.lit(x) for kv in weights.items() for x in kv])
        want = F.coalesce(F.try_element_at(given, F.coalesce("source", F.lit(""))).cast("double"), F.lit(0.0))
    else:
        want = F.pow(F.col("n").cast("double"), F.lit(power))
    asked = scratch.settle(size.withColumn("want", F.greatest(want, F.lit(0.0))), "sizes")
    count, total = asked.where("want > 0").agg(F.count("*"), F.sum("want")).first()
    base = max(slots, 4 * count)
    if 0 < count <= slots:
        ratios = asked.where("want > 0").agg(F.collect_set(F.col("want") / total).alias("r"))  # distinct weights, at most `slots`
        near = lambda q: F.forall("r", lambda r: (F.round(r * q) >= 1) & (F.abs(r * q - F.round(r * q)) < DIGITS * q))
        base = ratios.select(F.try_element_at(F.filter(F.sequence(F.lit(1), F.lit(slots)), near), F.lit(1))).first()[0] or base
    share = F.when(F.col("want") > 0, F.greatest(F.lit(1), F.round(F.col("want") / F.lit(total or 1.0) * base))).otherwise(0).cast("bigint")
    by_share = Window.partitionBy("share").orderBy(F.asc_nulls_first("source"))
    order = Window.orderBy(F.desc("share"), F.asc_nulls_first("source"))  # a row for each source
    shared = asked.withColumn("share", share).withColumn("member", F.row_number().over(by_share) - 1).withColumn("class", F.dense_rank().over(Window.orderBy(F.desc("share"))) - 1)
    return shared.select("source", "n", (F.row_number().over(order) - 1).alias("stream"), "share", "class", "member")


def period(shares: DataFrame, slots: int, chunk: int = CHUNK) -> DataFrame:
    """(stream, nth, place): where the nth block (from 0) of each stream stands in a period of `slots`, the sum of shares."""
    classes = shares.where("share > 0").groupBy("class").agg(F.first("share").alias("share"), F.count("*").alias("members"))
    row = classes.agg(F.array_sort(F.collect_list(F.struct("class", "share", "members"))).alias("s"))  # distinct shares of one period

    def place(state: Column, t: Column) -> Column:
        """Give slot t to the released block with the earliest deadline; ties go to the greater share."""

        def next_block(x: Column, i: Column) -> Column:
            taken = F.get(state["done"], i)
            n = F.floor(taken / x["members"])  # its members take turns at the nth block
            ready = (n < x["share"]) & (F.floor(n * slots / x["share"]) <= t)
            return F.struct(F.when(ready, F.ceil((n + 1) * slots / x["share"])).otherwise(F.lit(4 * slots)).cast("bigint").alias("due"), i.cast("int").alias("at"), taken.alias("taken"))

        def apply(pick: Column) -> Column:
            done = F.transform(state["done"], lambda n, i: F.when(i == pick["at"], n + 1).otherwise(n))
            return F.struct(done.alias("done"), F.concat(state["out"], F.array(F.struct(pick["at"].alias("class"), pick["taken"].alias("taken"), t.cast("bigint").alias("place")))).alias("out"))

        return F.element_at(F.transform(F.array(F.array_min(F.transform("s", next_block))), apply), 1)

    kind = "array<struct<class:int,taken:bigint,place:bigint>>"

    def step(state: Column, first: Column) -> Column:
        """A chunk of slots, so that a long list isn't copied at every slot."""
        start = F.struct(state["done"].alias("done"), F.array().cast(kind).alias("out"))
        laid = F.aggregate(F.sequence(first, F.least(first + chunk, F.lit(slots)) - 1), start, place)
        return F.element_at(F.transform(F.array(laid), lambda y: F.struct(y["done"].alias("done"), F.concat(state["out"], F.array(y["out"])).alias("out"))), 1)

    zero = F.struct(F.transform("s", lambda x: F.lit(0).cast("bigint")).alias("done"), F.array().cast(f"array<{kind}>").alias("out"))
    firsts = F.sequence(F.lit(0), F.lit(max(slots - 1, 0)), F.lit(chunk))
    laid = row.where(F.size("s") > 0).select(F.explode(F.flatten(F.aggregate(firsts, zero, step, lambda st: st["out"]))).alias("p")).select("p.*")
    own = shares.where("share > 0").join(classes.select(F.col("class").alias("_c"), "members"), F.col("class") == F.col("_c")).select(F.col("class").alias("_class"), "member", "members", "stream")
    taken_by = (F.col("class") == F.col("_class")) & (F.col("taken") % F.col("members") == F.col("member"))
    return laid.join(own, taken_by).select("stream", F.floor(F.col("taken") / F.col("members")).alias("nth"), "place")


def mix(docs: DataFrame, scratch: Scratch, weights: dict[str, float] | None = None, power: float = 0.5, block: int = BLOCK, slots: int = SLOTS) -> DataFrame:
    """Add _slw_stream, _slw_block, _slw_slot and _slw_in_block to docs. Reading by slot, then place in the block, gives the mixed order."""
    shares = scratch.settle(stream_shares(docs, scratch, power, weights, slots), "shares")
    sources, whole = shares.agg(F.count("*"), F.coalesce(F.sum("share"), F.lit(0))).first()
    plan = scratch.settle(period(shares, whole), "period")
    small = F.broadcast if max(sources, whole) <= BROADCAST_ROWS else lambda df: df
    blocks = F.ceil(F.col("n") / block)
    last = shares.where("share > 0").withColumn("last", blocks - 1)
    ends = last.join(plan.select(F.col("stream").alias("_s"), "nth", "place"), (F.col("stream") == F.col("_s")) & (F.col("last") % F.col("share") == F.col("nth")))
    end = ends.agg(F.coalesce(F.max(F.floor(F.col("last") / F.col("share")) * whole + F.col("place") + 1), F.lit(0))).first()[0]
    before = Window.partitionBy(F.col("share") > 0).orderBy("stream").rowsBetween(Window.unboundedPreceding, -1)  # a row for each source
    tail = F.when(F.col("share") == 0, F.lit(end) + F.coalesce(F.sum(blocks).over(before), F.lit(0)))
    own = shares.select(F.col("source").alias("_slw_src"), F.col("stream").alias("_slw_stream"), F.col("share").alias("_slw_share"), tail.alias("_slw_tail"))
    streamed = docs.join(small(own), docs["source"].eqNullSafe(F.col("_slw_src"))).drop("_slw_src")
    placed = numbered(streamed, "_slw_stream", ["doc_id"], F.xxhash64("doc_id"), BUCKETS, scratch, "_slw_at")
    placed = placed.withColumn("_slw_block", F.floor(F.col("_slw_at") / block)).withColumn("_slw_in_block", (F.col("_slw_at") % block).cast("int"))
    nth = F.when(F.col("_slw_share") > 0, F.col("_slw_block") % F.col("_slw_share"))
    at = plan.select(F.col("stream").alias("_slw_ps"), F.col("nth").alias("_slw_nth"), F.col("place").alias("_slw_place"))
    placed = placed.join(small(at), (F.col("_slw_stream") == F.col("_slw_ps")) & (nth == F.col("_slw_nth")), "left")
    slot = F.coalesce(F.floor(F.try_divide(F.col("_slw_block"), F.col("_slw_share"))) * whole + F.col("_slw_place"), F.col("_slw_tail") + F.col("_slw_block"))
    return placed.withColumn("_slw_slot", slot.cast("bigint")).drop("_slw_at", "_slw_share", "_slw_tail", "_slw_ps", "_slw_nth", "_slw_place")


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, source, stream, block, slot, in_block of every document, mixed to weights by the root of source sizes."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    mixed = mix(docs, Scratch(spark, "op4"))
    return mixed.select("doc_id", "source", F.col("_slw_stream").alias("stream"), F.col("_slw_block").alias("block"), F.col("_slw_slot").alias("slot"), F.col("_slw_in_block").alias("in_block"))
