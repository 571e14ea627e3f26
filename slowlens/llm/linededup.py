"""Repeated runs of lines by a suffix array over line ids.

Only lines that occur twice or more can be in a repeated run, and a run worth deleting has MIN_WORDS words, so what
enters is the stretches of consecutive repeated lines with that many words. Over them a suffix array is built by prefix
doubling: rank_0 orders line ids, rank_(j+1) orders the pairs (rank_j here, rank_j 2^j lines on); a round ranks the
distinct pairs by a range sort and a small table of partition offsets, and suffixes that stand alone leave. A rank is the
place of the first suffix of its bucket, so every bucket is an interval of the array with a common prefix of 2^j lines.

The intervals' full common prefixes follow by going down from the longest: the members of an interval that go on alike
for 2^j more lines become an interval inside it, of which one member, the earliest in the corpus, stays behind to stand
for it. At the end each other suffix stands in the interval of the longest run that it shares with an earlier place;
these runs are deleted where they have MIN_WORDS words. The first copy of every run stays. "Earlier" goes by doc_id,
then by place in the text.

Cases: lines end at newlines and compare whole; null text has no lines; blank lines have no words; a run may repeat
within one text; rows that share a doc_id are separate texts in file order; an empty table gives no rows; further
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, hot_keys, salted_join, table

MIN_WORDS = 50


def ranked(keys: DataFrame, cols: list[str], scratch: Scratch) -> DataFrame:
    """Distinct `cols` with count `n`, and `rank`: how many rows sort before them. Range-partitioned, no single task."""
    counted = keys.groupBy(*cols).agg(F.count("*").alias("n"))
    parts = scratch.settle(counted.repartitionByRange(*cols).withColumn("_p", F.spark_partition_id()), "sorted")
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    sums = parts.groupBy("_p").agg(F.sum("n").alias("_s"))  # a row for each partition
    offsets = sums.select(F.col("_p").alias("_q"), F.coalesce(F.sum("_s").over(before), F.lit(0)).alias("_off"))
    within = Window.partitionBy("_p").orderBy(*cols).rowsBetween(Window.unboundedPreceding, -1)
    out = parts.join(F.broadcast(offsets), F.col("_p") == F.col("_q"))
    return out.select(*cols, "n", (F.col("_off") + F.coalesce(F.sum("n").over(within), F.lit(0))).alias("rank"))


def line_table(docs: DataFrame) -> DataFrame:
    """uid (a number for the row), doc_id, n_lines, pos, two hashes of the line, words."""
    rows = docs.select("doc_id", F.split("text", "\n", -1).alias("l")).where("l is not null").withColumn("uid", F.monotonically_increasing_id())
    one = lambda x: F.struct(F.xxhash64(F.lit(1), x).alias("h1"), F.xxhash64(F.lit(2), x).alias("h2"), F.regexp_count(x, F.lit(r"\S+")).alias("words"))
    rows = rows.select("uid", "doc_id", F.size("l").alias("n_lines"), F.posexplode("l").alias("pos", "x"))
    return rows.select("uid", "doc_id", "n_lines", "pos", one(F.col("x")).alias("s")).select("uid", "doc_id", "n_lines", "pos", "s.*")


def stretches(lines: DataFrame, scratch: Scratch, min_words: int) -> DataFrame:
    """The repeated lines that stand in stretches of min_words words or more; `upto` sums words within a text."""
    twice = lines.groupBy("h1", "h2").agg(F.count("*").alias("_n")).where("_n > 1").select(F.col("h1").alias("_h1"), F.col("h2").alias("_h2"), "_n")
    twice = scratch.settle(twice, "twice")
    hot = hot_keys(twice, "_h1", "_n")  # blank lines, say, and boilerplate
    met = salted_join(lines, twice, ["h1", "h2"], ["_h1", "_h2"], "h1", "_h1", hot, F.xxhash64("uid", "pos"))
    again = scratch.settle(met.select("uid", "doc_id", "pos", "h1", "h2", "words"), "again")
    by_text = Window.partitionBy("uid").orderBy("pos")
    run = again.withColumn("stretch", F.col("pos") - F.row_number().over(by_text)).withColumn("upto", F.sum("words").over(by_text))
    sums = run.groupBy("uid", "stretch").agg(F.sum("words").alias("_w")).where(F.col("_w") >= min_words).select(F.col("uid").alias("_u"), F.col("stretch").alias("_s"))
    return run.join(sums, (F.col("uid") == F.col("_u")) & (F.col("stretch") == F.col("_s"))).drop("_u", "_s", "stretch")


def with_kin(named: DataFrame, spread, total: int) -> DataFrame:
    """Add `n` and `first`, the number and the earliest of the members of an interval that go on by the same name.

    Rows of frequent names are dealt over many tasks; rows without a name have n = 0 and are kept apart from the join.
    """
    place = F.struct("doc_id", "uid", "pos")
    open_, rest = named.where("name is not null"), named.where("name is null")
    kin = open_.groupBy("interval", "name").agg(F.count("*").alias("n"), F.min(place).alias("first")).where("n > 1")
    kin = kin.select(F.col("interval").alias("_i"), F.col("name").alias("_n"), "n", "first").withColumn("_key", F.xxhash64("_i", "_n"))
    hot = hot_keys(kin, "_key", "n", total=total)
    joined = salted_join(open_.withColumn("_of", F.xxhash64("interval", "name")), kin, ["interval", "name"], ["_i", "_n"], "_of", "_key", hot, spread, "left")
    joined = joined.withColumn("n", F.coalesce("n", F.lit(0))).select(*named.columns, "n", "first")
    return joined.unionByName(rest.withColumn("n", F.lit(0)), allowMissingColumns=True)


def repeated_runs(lines: DataFrame, scratch: Scratch, min_words: int = MIN_WORDS, levels: int = 40) -> DataFrame:
    """(uid, start, length): for each place the longest run that occurs earlier, if it has min_words words."""
    base = scratch.settle(stretches(lines, scratch, min_words), "stretches")
    spread = F.xxhash64("uid", "pos")
    order = ranked(base.select("h1", "h2"), ["h1", "h2"], scratch).where("n > 1").select(F.col("h1").alias("_h1"), F.col("h2").alias("_h2"), "n", "rank")
    total = base.count()
    hot = hot_keys(order, "_h1", "n", total=total)
    crowded = [bool(hot)]  # by level; no run is more frequent than a shorter one that it begins with
    first = salted_join(base, order, ["h1", "h2"], ["_h1", "_h2"], "h1", "_h1", hot, spread).select("uid", "pos", "rank")
    ranks = [scratch.settle(first, "rank0")]
    for j in range(levels):
        here = ranks[-1]
        on = here.select(F.col("uid").alias("_u"), (F.col("pos") - (1 << j)).alias("_p"), F.col("rank").alias("then"))
        pairs = scratch.settle(here.join(on, (F.col("uid") == F.col("_u")) & (F.col("pos") == F.col("_p"))).select("uid", "pos", "rank", "then"), "pairs")
        order = ranked(pairs.select(F.col("rank").alias("here"), "then"), ["here", "then"], scratch).where("n > 1").select("here", F.col("then").alias("_t"), "n", F.col("rank").alias("new"))
        order, pairs_of = order.withColumn("_key", F.xxhash64("here", "_t")), pairs.withColumn("_of", F.xxhash64("rank", "then"))
        hot = hot_keys(order, "_key", "n", total=total) if crowded[-1] else []
        crowded.append(bool(hot))
        step = salted_join(pairs_of, order, ["rank", "then"], ["here", "_t"], "_of", "_key", hot, spread).select("uid", "pos", F.col("new").alias("rank"))
        step = scratch.settle(step, f"rank{j + 1}")
        scratch.drop(pairs)
        if step.isEmpty():
            break
        ranks.append(step)

    inside = scratch.settle(base.select("uid", "doc_id", "pos", F.lit(0).cast("bigint").alias("interval"), F.lit(0).alias("length")), "intervals")
    place = F.struct("doc_id", "uid", "pos")
    for j in range(len(ranks) - 1, -1, -1):
        names = ranks[j].select(F.col("uid").alias("_u"), F.col("pos").alias("_p"), F.col("rank").alias("name"))
        named = inside.join(names, (F.col("uid") == F.col("_u")) & (F.col("pos") + F.col("length") == F.col("_p")), "left").drop("_u", "_p")
        if crowded[j]:
            named = scratch.settle(named, "named")
            joined = with_kin(named, spread, total)
        else:  # a name has less than 1/500 of the rows here, so a window over them is no large task
            kin = Window.partitionBy("interval", F.coalesce("name", -1 - F.pmod(spread, F.lit(1 << 40))))  # rows without a name go apart
            joined = named.withColumn("n", F.count("name").over(kin)).withColumn("first", F.min(place).over(kin))
        is_first = (F.col("uid") == F.col("first.uid")) & (F.col("pos") == F.col("first.pos"))
        deeper = F.struct(F.xxhash64("interval", "name", F.lit(j)).alias("interval"), (F.col("length") + (1 << j)).alias("length"))
        stay = F.struct(F.col("interval").alias("interval"), F.col("length").alias("length"))
        go = F.when(F.col("n") < 2, F.array(stay)).when(is_first, F.array(stay, deeper)).otherwise(F.array(deeper))
        new = joined.select("uid", "doc_id", "pos", F.explode(go).alias("s")).select("uid", "doc_id", "pos", "s.*")
        new = scratch.settle(new, "intervals")
        scratch.drop(inside, named)
        inside = new
    firsts = inside.where("length > 0").groupBy("interval").agg(F.min(place).alias("first"), F.count("*").alias("n")).select(F.col("interval").alias("_i"), "first", "n")
    hot = hot_keys(firsts, "_i", "n", total=total) if crowded[0] else []
    later = salted_join(inside.where("length > 0"), firsts, ["interval"], ["_i"], "interval", "_i", hot, spread).where(place > F.col("first")).select("uid", F.col("pos").alias("start"), "length")
    at = base.select(F.col("uid").alias("_u"), F.col("pos").alias("_p"), "upto", "words")
    sized = later.join(at, (F.col("uid") == F.col("_u")) & (F.col("start") == F.col("_p"))).withColumn("until", F.col("upto") - F.col("words")).drop("_u", "_p", "upto", "words")
    sized = sized.join(at, (F.col("uid") == F.col("_u")) & (F.col("start") + F.col("length") - 1 == F.col("_p")))
    return sized.where(F.col("upto") - F.col("until") >= min_words).select("uid", "start", "length")


def line_decisions(docs: DataFrame, scratch: Scratch, min_words: int = MIN_WORDS) -> DataFrame:
    """doc_id, n_lines, n_removed and removed (array of first and last line, from 0) of every document."""
    lines = scratch.settle(line_table(docs), "lines")
    runs = repeated_runs(lines, scratch, min_words)

    # stretches of one text that touch or overlap are one
    by_text = Window.partitionBy("uid").orderBy("start", "length")
    ended = runs.withColumn("stop", F.col("start") + F.col("length") - 1).withColumn("before", F.max("stop").over(by_text.rowsBetween(Window.unboundedPreceding, -1)))
    group = F.sum((F.col("before").isNull() | (F.col("start") > F.col("before") + 1)).cast("int")).over(by_text.rowsBetween(Window.unboundedPreceding, 0))
    whole = ended.withColumn("g", group).groupBy("uid", "g").agg(F.min("start").alias("first"), F.max("stop").alias("last"))
    removed = whole.groupBy("uid").agg(F.array_sort(F.collect_list(F.struct("first", "last"))).alias("removed"), F.sum(F.col("last") - F.col("first") + 1).alias("n_removed"))
    removed = removed.select(F.col("uid").alias("_u"), "removed", "n_removed")
    texts = lines.where("pos = 0").select("uid", "doc_id", "n_lines").join(removed, F.col("uid") == F.col("_u"), "left")
    none = docs.where("text is null").select("doc_id", F.lit(0).alias("n_lines"))
    every = texts.select("doc_id", "n_lines", F.coalesce("n_removed", F.lit(0)).cast("int").alias("n_removed"), "removed").unionByName(none, allowMissingColumns=True)
    return every.select("doc_id", "n_lines", F.coalesce("n_removed", F.lit(0)).alias("n_removed"), F.coalesce("removed", F.array().cast("array<struct<first:int,last:int>>")).alias("removed"))


def without_repeats(docs: DataFrame, scratch: Scratch, min_words: int = MIN_WORDS) -> DataFrame:
    """docs with the later copies of repeated runs cut from the text; doc_ids must be unique here."""
    cuts = line_decisions(docs, scratch, min_words).where("n_removed > 0").select(F.col("doc_id").alias("_slw_id"), F.col("removed").alias("_slw_removed"))
    kept = F.filter(F.split("text", "\n", -1), lambda x, i: ~F.exists("_slw_removed", lambda r: (r["first"] <= i) & (i <= r["last"])))
    text = F.when(F.col("_slw_removed").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))
    return docs.join(cuts, F.col("doc_id") == F.col("_slw_id"), "left").withColumn("text", text).select(*docs.columns)


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, lines, lines removed and their ranges ("first-last", from 0) of every document."""
    found = line_decisions(table(spark, sf_dir, "documents"), Scratch(spark, "op2"))
    ranges = F.transform("removed", lambda r: F.concat_ws("-", r["first"].cast("string"), r["last"].cast("string")))
    return found.select("doc_id", "n_lines", "n_removed", F.array_join(ranges, ",").alias("removed"))
