"""Near duplicates by ProbMinHash signatures, banding and exact verification.

A document is a weighted set of its five-word shingles. For each shingle a Poisson process drops arrivals into REGISTERS
registers; a register keeps the shingle of its earliest arrival, and a process ends once its time passes the document's
latest register. The rate is the shingle's weight, and two registers agree with the probability Jaccard of the weights.
Bands of ROWS registers propose pairs; the exact value of what the registers estimate, SIMILARITY or more, links them.
With `weighted` a shingle weighs 1 + ln(count). Without, as in the queries, every weight is one: probability Jaccard is
then the plain Jaccard of shingle sets, the usual likeness of near copies, however often a shingle is repeated.

Equal token sequences are one node from the start. Within a bucket of a band each node is first compared with one
leader, the node that meets the most others over all its bands (the original of a group of copies agrees with all of
them); linked nodes are joined to components. Only then are nodes of one bucket compared whose components still differ,
on their signatures, in chunks of bounded size, and those above PROBABLE are verified. So no link between components is
lost but by the chance of banding (0.8^4 per band, 32 bands: under 1e-7) or of the signature's error (4 sigma).
A node with many probable partners in one component is verified against blocks of that component's members, the block's
sets side by side in one task's memory, so that rows grow with nodes and blocks and not with pairs of copies. Buckets,
leaders and exact copies that hold a large share of all rows are dealt over many tasks.

Cases: words are split at white space and lower-cased; a text of under five words has one shingle, all of it; null,
empty and blank texts are copies of one another; rows that share a doc_id count as one document; an empty table gives no
rows; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, components, hot_keys, salted_join, slices, table

WORDS, SIMILARITY, REGISTERS, ROWS, PROBABLE = 5, 0.8, 128, 4, 0.66
CHUNK, MEMBERS, FEW, BROADCAST_IDS = 2048, 256, 8, 1_000_000
_MIX, _STEP, _BASE = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


class _Words(dict):
    """Hash of each word, remembered for the frequent ones."""

    def __missing__(self, word: str) -> int:
        if len(self) > 250_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def _scatter(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * _MIX
    x = x ^ (x >> np.uint64(29))
    x = x * _BASE
    return x ^ (x >> np.uint64(32))


def shingle_sets(texts: list[str | None], seen: _Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document number, shingle hash, count) of the distinct shingles of a list of texts, by document and hash."""
    tokens = [(t or "").lower().split() for t in texts]
    sizes = np.array([len(t) for t in tokens], np.int64)
    words = np.fromiter((seen[w] for t in tokens for w in t), np.uint64, int(sizes.sum()))
    doc = np.repeat(np.arange(len(texts)), sizes)
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(words))  # words from here to the end of the text
    with np.errstate(over="ignore"):
        h = np.zeros(len(words), np.uint64)
        for k in range(WORDS):
            part = np.zeros(len(words), np.uint64)
            part[: max(0, len(words) - k)] = words[k:]
            h = h * _STEP + np.where(left > k, part, np.uint64(k))
        first = np.r_[True, doc[1:] != doc[:-1]] if len(doc) else np.zeros(0, bool)
        keep = (left >= WORDS) | first
        doc, h = doc[keep], _scatter(h[keep])
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.r_[True, (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])] if len(doc) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    return doc[at], h[at], np.diff(np.r_[at, len(doc)])


def weights(count: np.ndarray, weighted: bool) -> np.ndarray:
    return 1 + np.log(count) if weighted else np.ones(len(count))


def probability_jaccard(a: np.ndarray, x: np.ndarray, b: np.ndarray, y: np.ndarray) -> float:
    """Of two weighted sets, ids sorted: the sum over common ids i of 1 / sum over all j of max(x_j / x_i, y_j / y_i)."""
    common, i, j = np.intersect1d(a, b, assume_unique=True, return_indices=True)
    if not len(common):
        return float(len(a) == len(b) == 0)
    u, v = x[i], y[j]
    order = np.argsort(u / v, kind="stable")
    u, v = u[order], v[order]
    only_x, only_y = x.sum() - u.sum(), y.sum() - v.sum()
    above = np.cumsum(u[::-1])[::-1] + only_x  # weight in x of ids with this ratio x / y or a greater one
    below = np.r_[0.0, np.cumsum(v)[:-1]] + only_y
    return float((1 / (above / u + below / v)).sum())


def signatures(doc: np.ndarray, h: np.ndarray, weight: np.ndarray, n: int) -> np.ndarray:
    """n x REGISTERS: the low 32 bits of the shingle that each register keeps."""
    due = np.full(n * REGISTERS, np.inf)
    kept = np.zeros(n * REGISTERS, np.uint32)
    rate, time, live, turn = weight, np.zeros(len(h)), np.arange(len(h)), np.uint64(0)
    with np.errstate(over="ignore"):
        while len(live):
            turn += np.uint64(1)
            r = _scatter(h[live] + turn * _STEP)
            time[live] -= np.log(((r >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53) / rate[live]
            cell = doc[live] * REGISTERS + (_scatter(r) & np.uint64(REGISTERS - 1)).astype(np.int64)
            np.minimum.at(due, cell, time[live])
            won = due[cell] == time[live]
            kept[cell[won]] = h[live[won]].astype(np.uint32)
            latest = due.reshape(n, REGISTERS).max(axis=1)
            live = live[time[live] < latest[doc[live]]]
    return kept.reshape(n, REGISTERS)


def _parts(texts: list[str | None], most: int = 1_500_000, rows: int = 256) -> Iterator[tuple[int, int]]:
    """Runs of texts of bounded number and length; a longer text goes alone."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        n = len(t or "")
        if i > start and (size + n > most or i - start >= rows):
            yield start, i
            start, size = i, 0
        size += n
    if start < len(texts):
        yield start, len(texts)


def _sketch(batches: Iterator[pa.RecordBatch], weighted: bool) -> Iterator[pa.RecordBatch]:
    seen = _Words()
    for batch in slices(batches):
        texts, ids = batch.column("text").to_pylist(), batch.column("doc_id")
        for a, b in _parts(texts):
            part = texts[a:b]
            doc, h, count = shingle_sets(part, seen)
            sig = signatures(doc, h, weights(count, weighted), len(part))
            whole = [xxhash.xxh3_128_digest(" ".join((t or "").lower().split())) for t in part]
            yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(whole, pa.binary()), pa.array([s.tobytes() for s in sig], pa.binary())], names=["doc_id", "whole", "sig"])


def _sets(batches: Iterator[pa.RecordBatch], weighted: bool) -> Iterator[pa.RecordBatch]:
    seen = _Words()
    for batch in slices(batches):
        texts, ids = batch.column("text").to_pylist(), batch.column("doc_id")
        for a, b in _parts(texts):
            doc, h, count = shingle_sets(texts[a:b], seen)
            ends = pa.array(np.searchsorted(doc, np.arange(b - a + 1)).astype(np.int32))
            cols = [ids.slice(a, b - a), pa.ListArray.from_arrays(ends, pa.array(h.view(np.int64)))]
            if weighted:
                cols.append(pa.ListArray.from_arrays(ends, pa.array(weights(count, True))))
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "shingles", *["weights"] * weighted])


def _alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose signatures agree in PROBABLE of their registers or more."""
    for batch in batches:
        if batch.num_rows:
            left, right = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint32).reshape(-1, REGISTERS) for c in ("sa", "sb"))
            keep = pa.array((left == right).mean(axis=1) >= PROBABLE)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], names=["a", "b"])


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by group: pairs of different components and probable likeness, each in its first common band,
    as a node and its partners in one block of a component."""
    held: list[pa.RecordBatch] = []

    def pairs(group: pa.Table) -> Iterator[tuple[int, int, list[int]]]:
        """(node, block, partners in it), the node being of the smaller component."""
        node, comp, size, block, side, band = (np.asarray(group.column(c).combine_chunks()) for c in ("node", "comp", "size", "block", "side", "band"))
        sig = np.frombuffer(b"".join(group.column("sig").to_pylist()), np.uint32).reshape(-1, REGISTERS)
        both = group.column("two_sides")[0].as_py()
        met: dict[tuple[int, int], list[int]] = {}
        for i in range(len(node) - 1):
            js = np.flatnonzero((comp[i + 1 :] != comp[i]) & ((side[i + 1 :] != side[i]) | (not both))) + i + 1
            if len(js):
                same = sig[js] == sig[i]
                probable = same.mean(axis=1) >= PROBABLE
                if probable.any():
                    js, same = js[probable], same[probable]
                    common = same.reshape(len(js), -1, ROWS).all(axis=2)
                    for j in js[common.any(axis=1) & (common.argmax(axis=1) == band[i])]:
                        x, y = (i, j) if (size[i], node[i]) < (size[j], node[j]) else (j, i)
                        met.setdefault((int(node[x]), int(block[y])), []).append(int(node[y]))
        for (x, blk), ys in met.items():
            yield x, blk, ys

    def emit(last: bool) -> pa.RecordBatch | None:
        nonlocal held
        whole = pa.Table.from_batches(held)
        keys = np.asarray(whole.column("grp").combine_chunks())
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        done = cuts if last else cuts[:-1]
        rows = [r for x, y in zip(done, done[1:], strict=False) if y - x > 1 for r in pairs(whole.slice(x, y - x))]
        held = [] if last else whole.slice(done[-1]).combine_chunks().to_batches()
        cols = list(zip(*rows, strict=True)) if rows else [[], [], []]
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.list_(pa.int64()))], names=["node", "block", "partners"])

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            yield emit(False)
    if held:
        yield emit(True)


def _alike_sets(a: np.ndarray, x: np.ndarray | None, b: np.ndarray, y: np.ndarray | None) -> bool:
    if x is not None:
        at, to = np.argsort(a), np.argsort(b)
        return probability_jaccard(a[at], x[at], b[to], y[to]) >= SIMILARITY
    common = len(np.intersect1d(a, b, assume_unique=True))
    return common >= SIMILARITY * (len(a) + len(b) - common)


def _in_block(batches: Iterator[pa.RecordBatch], weighted: bool) -> Iterator[pa.RecordBatch]:
    """Rows sorted by block, members before askers: one link from each asker to the first member that verifies."""
    now, members = None, {}
    for batch in batches:
        a, b = [], []
        cols = [batch.column(c) for c in ("block", "asks", "doc_id", "shingles", "partners")]
        for i in range(batch.num_rows):
            block, asks, node = (c[i].as_py() for c in cols[:3])
            if block != now:
                now, members = block, {}
            own = np.asarray(cols[3][i].values), np.asarray(batch.column("weights")[i].values) if weighted else None
            if not asks:
                members[node] = own
                continue
            for other in cols[4][i].as_py():
                if _alike_sets(*own, *members[other]):
                    a.append(min(node, other))
                    b.append(max(node, other))
                    break
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def _weighed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose weighted sets are alike."""
    for batch in batches:
        side = lambda i, c: np.asarray(batch.column(c)[i].values)  # noqa: B023, E731
        keep = pa.array([_alike_sets(side(i, "x"), side(i, "wx"), side(i, "y"), side(i, "wy")) for i in range(batch.num_rows)], pa.bool_())
        yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], names=["a", "b"])


def _shingles_of(docs: DataFrame, ids: DataFrame, scratch: Scratch, weighted: bool) -> DataFrame:
    """(doc_id, shingles and, if weighted, weights) of the documents in ids (_id)."""
    ids = scratch.settle(ids.distinct(), "ids")
    few = ids.count() <= BROADCAST_IDS
    chosen = docs.select("doc_id", "text").join(F.broadcast(ids) if few else ids, F.col("doc_id") == F.col("_id"), "left_semi")
    schema = "doc_id bigint, shingles array<bigint>" + ", weights array<double>" * weighted
    return scratch.settle(chosen.mapInArrow(lambda it: _sets(it, weighted), schema).dropDuplicates(["doc_id"]), "sets")


def _verified_blocks(docs: DataFrame, asked: DataFrame, placed: DataFrame, scratch: Scratch, weighted: bool) -> DataFrame:
    """Links among (node, block, partners); the partners of a row are members of one component. `placed` has the block
    of every node that may be a partner."""
    lists = scratch.settle(asked.groupBy("node", "block").agg(F.array_distinct(F.flatten(F.collect_list("partners"))).alias("partners")), "lists")
    # short lists as pairs, long ones against their block
    short = lists.where(F.size("partners") < FEW).select("node", F.explode("partners").alias("other"))
    pairs = scratch.settle(short.select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct(), "pairs")
    long = lists.where(F.size("partners") >= FEW)
    blocks = long.select(F.col("block").alias("_block")).distinct()
    wanted = scratch.settle(placed.join(blocks, F.col("block") == F.col("_block"), "left_semi").select("node", "block").distinct(), "wanted")
    ids = pairs.select(F.col("a").alias("_id")).union(pairs.select("b")).union(long.select("node")).union(wanted.select("node"))
    sets = _shingles_of(docs, ids, scratch, weighted)
    nothing = F.lit(None).cast("array<bigint>")
    own = ["shingles", *["weights"] * weighted]
    members = wanted.join(sets, F.col("node") == F.col("doc_id")).select("block", F.lit(0).alias("asks"), "doc_id", *own, nothing.alias("partners"))
    askers = long.join(sets, F.col("node") == F.col("doc_id")).select("block", F.lit(1).alias("asks"), "doc_id", *own, "partners")
    met = members.unionByName(askers).repartition("block").sortWithinPartitions("block", "asks").mapInArrow(lambda it: _in_block(it, weighted), "a bigint, b bigint")
    return scratch.settle(_similar(pairs, sets, weighted).unionByName(met), "links")


def _verified(docs: DataFrame, pairs: DataFrame, scratch: Scratch, weighted: bool) -> DataFrame:
    """Those of pairs (a, b) whose shingle sets have SIMILARITY or more."""
    sets = _shingles_of(docs, pairs.select(F.explode(F.array("a", "b")).alias("_id")), scratch, weighted)
    out = scratch.settle(_similar(pairs, sets, weighted), "links")
    scratch.drop(sets)
    return out


def _similar(pairs: DataFrame, sets: DataFrame, weighted: bool) -> DataFrame:
    both = pairs
    for key, other, name in (("a", "b", "x"), ("b", "a", "y")):
        own = sets.select(F.col("doc_id").alias(f"_{key}"), F.col("shingles").alias(name), *[F.col("weights").alias(f"w{name}")] * weighted)
        hot = hot_keys(pairs.groupBy(key).agg(F.count("*").alias("n")), key, "n")  # leaders
        both = salted_join(both, own, [key], [f"_{key}"], key, f"_{key}", hot, F.xxhash64(other))
    if weighted:
        return both.select("a", "b", "x", "wx", "y", "wy").mapInArrow(_weighed, "a bigint, b bigint")
    common = F.size(F.array_intersect("x", "y"))
    return both.where(common >= SIMILARITY * (F.size("x") + F.size("y") - common)).select("a", "b")


def near_duplicate_classes(docs: DataFrame, scratch: Scratch, weighted: bool = False) -> DataFrame:
    """doc_id and class_id of every document; class_id is the smallest doc_id of the class."""
    known = docs.select("doc_id", "text").where(F.col("doc_id").isNotNull())
    sketch = scratch.settle(known.mapInArrow(lambda it: _sketch(it, weighted), "doc_id bigint, whole binary, sig binary"), "sketch")
    equal = sketch.groupBy("whole").agg(F.min(F.struct("doc_id", "sig")).alias("m"), F.count("*").alias("copies"))
    nodes = scratch.settle(equal.select("whole", "copies", F.col("m.doc_id").alias("node"), F.col("m.sig").alias("sig")), "nodes")
    bands = REGISTERS // ROWS
    banded = nodes.select("node", F.explode(F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.struct(i.alias("band"), F.xxhash64(i, F.substring("sig", i * 4 * ROWS + 1, F.lit(4 * ROWS))).alias("bucket")))).alias("e")).select("node", "e.band", "e.bucket")
    shared = scratch.settle(banded.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1"), "shared")
    hot = hot_keys(shared, "bucket", "n")

    def by_bucket(left: DataFrame, right: DataFrame) -> DataFrame:
        return salted_join(left, right.withColumnRenamed("bucket", "_bucket"), ["bucket"], ["_bucket"], "bucket", "_bucket", hot, F.xxhash64("node")).drop("_bucket")

    met = scratch.settle(by_bucket(banded, shared), "met")
    rank = met.groupBy("node").agg(F.sum("n").alias("score"))
    led = met.join(rank, "node").groupBy("bucket").agg(F.max(F.struct("score", (-F.col("node")).alias("minus"))).alias("m")).select("bucket", (-F.col("m.minus")).alias("leader"))
    first = scratch.settle(by_bucket(met.select("node", "bucket"), led).where("node <> leader").select("node", "leader").distinct(), "first")
    leaders = hot_keys(first.groupBy("leader").agg(F.count("*").alias("n")), "leader", "n")
    sig_a, sig_b = nodes.select(F.col("node").alias("_a"), F.col("sig").alias("sa")), nodes.select(F.col("node").alias("_b"), F.col("sig").alias("sb"))
    signed = salted_join(first.join(sig_a, F.col("node") == F.col("_a")), sig_b, ["leader"], ["_b"], "leader", "_b", leaders, F.xxhash64("node"))
    signed = signed.select(F.least("node", "leader").alias("a"), F.greatest("node", "leader").alias("b"), "sa", "sb")
    likely = scratch.settle(signed.mapInArrow(_alike, "a bigint, b bigint").distinct(), "likely")
    links = _verified(known, likely, scratch, weighted)
    comps = scratch.settle(components(links, scratch), "comps")

    sizes = scratch.settle(comps.groupBy("comp").agg(F.count("*").alias("size")).withColumnRenamed("comp", "_comp"), "sizes")
    sized = scratch.settle(salted_join(comps, sizes, ["comp"], ["_comp"], "comp", "_comp", hot_keys(sizes, "_comp", "size"), F.xxhash64("node")).select(F.col("node").alias("_node"), "comp", "size"), "sized")
    named = met.where("n > 2").join(sized, F.col("node") == F.col("_node"), "left").select("node", "band", "bucket", F.coalesce("comp", "node").alias("comp"), F.coalesce("size", F.lit(1)).alias("size"))
    named = named.withColumn("block", F.xxhash64("comp", F.pmod(F.xxhash64("node"), F.ceil(F.col("size") / MEMBERS))))
    open_buckets = named.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("_n")).where("lo < hi").select("bucket", F.ceil(F.col("_n") / CHUNK).alias("chunks"))
    rows = by_bucket(named, open_buckets)
    own = F.pmod(F.xxhash64("node"), F.col("chunks"))
    rows = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("chunks") - 1)))
    grp = F.xxhash64("bucket", F.least("own", "other"), F.greatest("own", "other"))
    rows = rows.select("node", "comp", "size", "block", "band", grp.alias("grp"), F.col("own").alias("side"), (F.col("own") != F.col("other")).alias("two_sides"))
    rows = rows.join(nodes.select(F.col("node").alias("_node"), "sig"), F.col("node") == F.col("_node")).drop("_node")
    cross = rows.repartition("grp").sortWithinPartitions("grp", "node").mapInArrow(_across, "node bigint, block bigint, partners array<bigint>")
    more = _verified_blocks(known, scratch.settle(cross, "cross"), named.select("node", "block"), scratch, weighted)
    comps = components(links.union(more), scratch)
    key = F.xxhash64("whole").alias("_key")
    classes = nodes.select("whole", "node", "copies", key).join(comps.withColumnRenamed("node", "_node"), F.col("node") == F.col("_node"), "left")
    classes = classes.select(F.col("whole").alias("_whole"), F.col("_key").alias("_of"), F.coalesce("comp", "node").alias("class_id"))
    copied = hot_keys(nodes.select(key, "copies"), "_key", "copies")
    return salted_join(sketch.select("doc_id", "whole", key), classes, ["whole"], ["_whole"], "_key", "_of", copied, F.xxhash64("doc_id")).select("doc_id", "class_id")


def drop_near_duplicates(docs: DataFrame, scratch: Scratch) -> DataFrame:
    """docs without the rows of which an earlier one of the class stays."""
    classes = scratch.settle(near_duplicate_classes(docs, scratch), "classes")
    copies = classes.where("doc_id <> class_id").select(F.col("doc_id").alias("_slw_id")).distinct()
    few = copies.count() <= BROADCAST_IDS
    kept = docs.join(F.broadcast(copies) if few else copies, F.col("doc_id") == F.col("_slw_id"), "left_anti")
    repeated = classes.groupBy("doc_id").count().where("count > 1").limit(1).count()
    return kept.dropDuplicates(["doc_id"]) if repeated else kept


def op7_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    classes = near_duplicate_classes(table(spark, sf_dir, "documents"), Scratch(spark, "op7"))
    return classes.withColumn("kept", F.col("doc_id") == F.col("class_id"))
