"""Benchmark decontamination on templates: numbers, names and units become typed placeholders.

A text is read as a sequence of words, lower-cased. A number is a whole number with its decimals and thousands marks, a
unit is a known unit word right after a number, a name is a run of capitalised words that don't start a sentence; each is
one placeholder. Windows of WINDOW template words (whole items, if they have MIN_ITEM to WINDOW - 1 words) of the
benchmark and of all documents are hash-joined, and so are windows of the plain words, in which nothing is replaced, so
that a copy in other capitals or without marks is found as well. Hits of one document, item and alignment are judged
together: their placeholders must map item values to document values one to one (a re-parameterised question does), else
only windows with the same values count. The windows that count, over all alignments of an item, are put together: a
document is contaminated by an item if they cover COVERAGE of its words or RUN of them in a row.

A Bloom filter over the benchmark's windows, BITS_A_WINDOW bits for each, keeps all other windows from being shuffled; it
stops growing at MOST_BITS (256 MB), beyond which more windows pass it; the join decides in any case.

Cases: null text counts as empty; items under MIN_ITEM words match nothing; windows with fewer than half literal words
count only with equal values; rows that share a doc_id are judged together; an empty table gives no rows (an empty
benchmark: no contamination); further columns are ignored.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, hot_keys, salted_join, slices, table

WINDOW, MIN_ITEM, COVERAGE, RUN, BROADCAST_ROWS = 8, 5, 0.5, 13, 1_000_000
BITS_A_WINDOW, LEAST_BITS, MOST_BITS = 32, 1 << 20, 1 << 31
UNITS = frozenset("mm cm m km in ft yd mi mg g kg t lb lbs oz ml l cl gal ms s sec secs min mins h hr hrs hour hours minute minutes second seconds day days week weeks month months year years percent pct kb mb gb tb hz khz mhz ghz w kw kwh v mv a ma k c f j kj cal kcal usd eur gbp dollar dollars euro euros pound pounds cent cents mph kph".split())
_token = re.compile(r"\d[\d.,]*\d\w*|\w+|[.!?\n]")
_LITERAL, _NUMBER, _UNIT, _NAME, _MARK = range(5)
_TYPED = np.array([[0, 0], *([xxhash.xxh3_64_intdigest(f"placeholder {k}", seed) for seed in (1, 2)] for k in (_NUMBER, _UNIT, _NAME)), [0, 0]], np.uint64)
_STEP = np.array([0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93], np.uint64)


class _Words(dict):
    """Number of each word in the columns `kind` and `lanes`; kept from batch to batch up to a size."""

    def __init__(self) -> None:
        self.kind, self.lanes = array("b"), (array("Q"), array("Q"))

    def __missing__(self, w: str) -> int:
        self[w] = n = len(self.kind)
        low = w.lower()
        self.kind.append(_MARK if w in ".!?\n" else _NUMBER if w[0].isdigit() else _UNIT if low in UNITS else _NAME if w[0].isupper() and not w[1:].isupper() else _LITERAL)
        for seed, lane in enumerate(self.lanes, 1):
            lane.append(xxhash.xxh3_64_intdigest(low, seed))
        return n

    def rest(self, most: int = 300_000) -> None:
        if len(self) > most:
            self.clear()
            self.__init__()


class _Windows:
    """The windows of a list of texts, over template words or (`plain`) over the words as they are."""

    def __init__(self, words: _Read, plain: bool):
        self.read, n = words, len(words.kind)
        if plain:
            self.first_word, self.kind, self.lanes = np.arange(n), np.full(n, _LITERAL, np.int8), words.lanes
        else:
            again = np.r_[False, (words.kind[1:] == _NAME) & (words.kind[:-1] == _NAME) & (words.doc[1:] == words.doc[:-1])] if n else np.zeros(0, bool)
            self.first_word = np.flatnonzero(~again)  # of each template word; a run of names is one
            self.kind = words.kind[self.first_word]
            typed = np.flatnonzero(self.kind != _LITERAL)
            self.lanes = []
            for lane, h in enumerate(words.lanes):
                own = h[self.first_word]
                own[typed] = _TYPED[self.kind[typed], lane]
                self.lanes.append(own)
        self.doc = words.doc[self.first_word]
        self.last_word = np.r_[self.first_word[1:], n]
        self.total = np.bincount(self.doc, minlength=words.texts)
        self.first = np.searchsorted(self.doc, np.arange(words.texts))

    def starts(self, size: int) -> np.ndarray:
        """Where a window of this size lies within one text."""
        last = len(self.doc) - size + 1
        return np.flatnonzero(self.doc[:last] == self.doc[size - 1 :]) if last > 0 else np.zeros(0, np.int64)

    def hashes(self, at: np.ndarray, size: int, lane: int) -> np.ndarray:
        """Polynomial hashes, built from those of windows half as long."""
        if not len(at):
            return np.zeros(0, np.uint64)
        step = int(_STEP[lane])
        out, done, part, length = np.zeros(len(at), np.uint64), 0, self.lanes[lane], 1
        with np.errstate(over="ignore"):
            for bit in range(size.bit_length()):
                if size >> bit & 1:
                    out = out * np.uint64(pow(step, length, 1 << 64)) + part[at + done]
                    done += length
                if size >> bit > 1:
                    longer = part[: len(part) - length] * np.uint64(pow(step, length, 1 << 64)) + part[length:]
                    part, length = longer, 2 * length
            out = out + np.uint64(size)
        return out ^ (out >> np.uint64(31))

    def slots(self, at: int, size: int) -> list[str]:
        """Kind and lower-cased value of each placeholder of a window, in order."""
        r = self.read
        return [f"{self.kind[i]}:{' '.join(r.tokens[r.word[j]].lower() for j in range(self.first_word[i], self.last_word[i]) if r.doc[j] == self.doc[i])}" for i in range(at, at + size) if self.kind[i] != _LITERAL]


class _Read:
    """The words of a list of texts, with their kinds and hashes in two lanes."""

    def __init__(self, texts: list[str], seen: _Words):
        found = [_token.findall(t) for t in texts]
        sizes = np.array([len(f) for f in found], np.int64)
        self.texts = len(texts)
        self.tokens = [w for f in found for w in f]
        number = np.fromiter(map(seen.__getitem__, self.tokens), np.int64, len(self.tokens))
        kind = np.frombuffer(seen.kind, np.int8)[number] if len(number) else np.zeros(0, np.int8)
        doc = np.repeat(np.arange(len(texts)), sizes)
        fresh = np.r_[True, (kind[:-1] == _MARK) | (doc[1:] != doc[:-1])] if len(kind) else np.zeros(0, bool)  # starts a sentence
        self.word = np.flatnonzero(kind != _MARK)
        fresh, self.kind, self.doc = fresh[self.word], kind[self.word], doc[self.word]
        self.kind[(self.kind == _NAME) & fresh] = _LITERAL
        after = np.r_[False, (self.kind[:-1] == _NUMBER) & (self.doc[1:] == self.doc[:-1])] if len(self.kind) else np.zeros(0, bool)
        self.kind[(self.kind == _UNIT) & ~after] = _LITERAL
        self.lanes = [np.frombuffer(column, np.uint64)[number[self.word]] if len(self.word) else np.zeros(0, np.uint64) for column in seen.lanes]


_ROW = "key bigint, plain boolean, h1 bigint, h2 bigint, place int, size int, slots array<string>, total int"
_KINDS = [pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.string()), pa.int32()]


def _hit(h: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Whether a hash may be one of the benchmark's."""
    b = h & np.uint64(len(bits) * 64 - 1)
    return (bits[b >> np.uint64(6)] >> (b & np.uint64(63))) & np.uint64(1) != 0


def _emit(batches: Iterator[pa.RecordBatch], key: str, lengths: dict[bool, list[int]] | None, bits: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """Windows of texts. Of documents, those of the given lengths that pass the filter; of items (lengths None), all of
    WINDOW words, or the whole of a shorter item."""
    seen = _Words()
    for batch in slices(batches):
        ids, texts = batch.column(key).to_pylist(), batch.column("text").to_pylist()
        start = 0
        while start < len(texts):
            end, chars = start, 0
            while end < len(texts) and (end == start or chars + len(texts[end] or "") <= 2_000_000):
                chars += len(texts[end] or "")
                end += 1
            own = ids[start:end]
            read = _Read([t or "" for t in texts[start:end]], seen)
            start = end
            seen.rest()
            out: list[tuple] = []
            for plain in (False, True):
                w = _Windows(read, plain)
                for size in lengths[plain] if lengths is not None else range(MIN_ITEM, WINDOW + 1):
                    at = w.starts(size)
                    if lengths is None and size < WINDOW:
                        at = at[w.total[w.doc[at]] == size]
                    lanes = []
                    for lane in (0, 1):
                        h = w.hashes(at, size, lane)
                        if bits is not None:
                            keep = _hit(h, bits)
                            at, h, lanes = at[keep], h[keep], [x[keep] for x in lanes]
                        lanes.append(h)
                    for i, h1, h2 in zip(at.tolist(), lanes[0].view(np.int64).tolist(), lanes[1].view(np.int64).tolist(), strict=True):
                        d = w.doc[i]
                        out.append((own[d], plain, h1, h2, int(i - w.first[d]), size, w.slots(i, size), int(w.total[d])))
            cols = list(zip(*out, strict=True)) if out else [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, _KINDS, strict=True)], names=["key", "plain", "h1", "h2", "place", "size", "slots", "total"])


def filter_bits(items: DataFrame, n: int) -> np.ndarray:
    """The Bloom filter over the two hashes of n windows."""
    size = LEAST_BITS
    while size < min(n * BITS_A_WINDOW, MOST_BITS):
        size *= 2
    bit = F.explode(F.transform(F.array("h1", "h2"), lambda h: h.bitwiseAND(size - 1)))
    words = items.select(bit.alias("b")).groupBy(F.shiftright("b", 6).cast("int").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(b & 63 as int))")).alias("v")).toArrow()  # at most size / 64 rows
    bits = np.zeros(size // 64, np.uint64)
    bits[words["w"].to_numpy()] = words["v"].to_numpy().view(np.uint64)
    return bits


def contamination(docs: DataFrame, benchmark: DataFrame, scratch: Scratch) -> DataFrame:
    """(doc_id, items): the contaminated documents and the sorted ids of the items found in each."""
    items = scratch.settle(benchmark.select("item_id", "text").mapInArrow(lambda it: _emit(it, "item_id", None, None), _ROW), "items")
    sizes = items.groupBy("plain", "size").agg(F.count("*").alias("n")).collect()  # at most 2 (WINDOW - MIN_ITEM + 1) rows
    n = sum(r["n"] for r in sizes)
    lengths = {p: sorted(r["size"] for r in sizes if r["plain"] == p) for p in (False, True)}
    shared = docs.sparkSession.sparkContext.broadcast(filter_bits(items, n))
    hits = docs.select("doc_id", "text").mapInArrow(lambda it: _emit(it, "doc_id", lengths, shared.value), _ROW)
    hits = scratch.settle(hits.select("key", "plain", "h1", "h2", "place", "slots"), "hits")
    asked = items.select(F.col("key").alias("item_id"), F.col("h1").alias("_h1"), F.col("h2").alias("_h2"), F.col("plain").alias("_plain"), F.col("place").alias("at"), "size", F.col("slots").alias("own"), "total")
    if n <= BROADCAST_ROWS:
        met = hits.join(F.broadcast(asked), (F.col("h1") == F.col("_h1")) & (F.col("h2") == F.col("_h2")) & (F.col("plain") == F.col("_plain")))
    else:
        hot = hot_keys(hits.groupBy("h1").agg(F.count("*").alias("n")), "h1", "n")
        met = salted_join(hits, asked, ["h1", "h2", "plain"], ["_h1", "_h2", "_plain"], "h1", "_h1", hot, F.xxhash64("key", "place"))
    exact, open_ = F.col("own") == F.col("slots"), F.size("slots") * 2 <= F.col("size")
    met = met.where(exact | open_).select(F.col("key").alias("doc_id"), "item_id", "plain", (F.col("place") - F.col("at")).alias("shift"), "at", "size", "total", exact.alias("exact"), F.arrays_zip(F.col("own").alias("i"), F.col("slots").alias("d")).alias("pairs"))
    # one alignment has at most one row for each window of the item
    lined = met.groupBy("doc_id", "item_id", "plain", "shift").agg(
        F.collect_set("at").alias("every"), F.collect_set(F.when(F.col("exact"), F.col("at"))).alias("same"),
        F.array_distinct(F.flatten(F.collect_list("pairs"))).alias("pairs"), F.first("size").alias("size"), F.first("total").alias("total"),
    )
    one = (F.size(F.array_distinct(F.transform("pairs", lambda p: p["i"]))) == F.size("pairs")) & (F.size(F.array_distinct(F.transform("pairs", lambda p: p["d"]))) == F.size("pairs"))
    counted = lined.select("doc_id", "item_id", "plain", "size", "total", F.explode(F.when(one, F.col("every")).otherwise(F.col("same"))).alias("at"))
    # over all alignments: at most one row for each window of the item
    lined = counted.groupBy("doc_id", "item_id", "plain").agg(F.array_sort(F.collect_set("at")).alias("at"), F.first("size").alias("size"), F.first("total").alias("total"))

    def grow(s, p):
        gap = p - s["end"]  # words between the last window and this one
        more = F.when(gap >= 0, F.col("size")).otherwise(F.col("size") + gap)
        run = F.when(gap > 0, F.col("size")).otherwise(s["run"] + more)
        return F.struct((s["covered"] + more).alias("covered"), run.alias("run"), F.greatest(s["longest"], run).alias("longest"), (p + F.col("size")).alias("end"))

    zero = F.struct(*[F.lit(v).cast("int").alias(k) for k, v in (("covered", 0), ("run", 0), ("longest", 0), ("end", -1_000_000))])
    judged = lined.withColumn("s", F.aggregate("at", zero, grow))
    found = judged.where((F.col("s.covered") >= COVERAGE * F.col("total")) | (F.col("s.longest") >= RUN))
    return found.groupBy("doc_id").agg(F.array_sort(F.collect_set("item_id")).alias("items"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, scratch: Scratch) -> DataFrame:
    found = scratch.settle(contamination(docs, benchmark, scratch).select(F.col("doc_id").alias("_slw_id")), "found")
    few = found.count() <= BROADCAST_ROWS
    return docs.join(F.broadcast(found) if few else found, F.col("doc_id").eqNullSafe(F.col("_slw_id")), "left_anti")


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, contaminated and the items found, of every document."""
    docs = table(spark, sf_dir, "documents")
    scratch = Scratch(spark, "op10")
    found = scratch.settle(contamination(docs, table(spark, sf_dir, "benchmark"), scratch).withColumnRenamed("doc_id", "_id"), "found")
    every = docs.select("doc_id").join(found, F.col("doc_id").eqNullSafe(F.col("_id")), "left")
    return every.select("doc_id", F.col("_id").isNotNull().alias("contaminated"), F.coalesce(F.array_join(F.col("items").cast("array<string>"), ","), F.lit("")).alias("items"))
