"""Nearest neighbours by multi-index hashing over learned rotated binary codes.

A rotation is learned on a bounded sample (principal axes, then alternating between codes and the closest rotation);
signs along it and along a second random turn of it are a vector's code. Rows are dealt into blocks; in each block every
16-bit substring of the codes has its own table. Among m substrings a code within Hamming radius r = a m + b of a query
agrees with it up to a flips in one of the first b + 1, or up to a - 1 flips in one of the others (else their flips would
sum to more than r), so probing those entries finds every code within r. Entries are probed by the flips of the query's
substring while those are fewer than the table's entries, else by a walk over the entries. Hits within r are reranked by
exact inner products in double precision. A query starts at the smallest radius that reaches RECALL on pairs of the
sample, and its radius grows in a block until it has k hits there or the block is used up.

How many rows are probed depends on the data: few where neighbours are close, most where they are hardly closer than
chance (see probed_share).

Every row is indexed, each dimension on its own. Cases: vectors that are null, zero, or hold null or non-finite components
take no part; ties go to the smaller vec_id; with too few candidates all are returned; an empty table gives no rows; rows
that share a vec_id count as one, the least vector.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import Scratch, table

SAMPLE, BLOCK_ROWS, QUERY_EVERY, K, RECALL, SEED, TURNS = 4000, 8192, 20, 20, 0.97, 11, 2
WORD = 16  # bits of a substring


def flips(most: int) -> np.ndarray:
    """All masks of a substring with at most so many bits."""
    return np.array([sum(1 << b for b in c) for k in range(most + 1) for c in combinations(range(WORD), k)], np.uint16)


def allowed(radius: int, tables: int) -> list[int]:
    """Flips to probe in each table, so that every code within the radius is met; -1: none."""
    whole, rest = divmod(min(radius, WORD * tables), tables)
    return [whole if t <= rest else whole - 1 for t in range(tables)]


class Codes:
    """A learned rotation, its codes, and the radius that reaches the wanted recall."""

    def __init__(self, x: np.ndarray, k: int = K, recall: float = RECALL, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.dim = x.shape[1]
        self.centre = x.mean(axis=0)
        unit = self._unit(x)
        axes = np.linalg.eigh(unit.T @ unit)[1][:, ::-1]
        turns = []
        for _ in range(TURNS):
            turn = np.linalg.qr(rng.normal(size=(self.dim, self.dim)))[0]
            for _ in range(20):  # codes for the rotation, then the rotation closest to the codes
                u, _, v = np.linalg.svd(np.sign(unit @ axes @ turn).T @ (unit @ axes))
                turn = (u @ v).T
            turns.append(axes @ turn)
        self.rotation = np.concatenate(turns, axis=1)
        self.tables = -(-self.rotation.shape[1] // 64) * 4
        code = self.code(x)
        asked = rng.choice(len(x), min(len(x), 200), replace=False)
        far = np.bitwise_count(code[asked][:, None, :].view(np.uint64) ^ code[None].view(np.uint64)).sum(axis=2)
        near = x[asked] @ x.T
        near[np.arange(len(asked)), asked] = -np.inf
        top = np.argsort(-near, axis=1)[:, : min(k, len(x) - 1)]
        reach = np.sort(np.take_along_axis(far, top, axis=1).ravel())
        # a larger table than the sample has closer neighbours, which the radius covers as well
        self.radius = int(reach[min(len(reach) - 1, int(recall * len(reach)))]) if len(reach) else 0

    def _unit(self, x: np.ndarray) -> np.ndarray:
        y = x - self.centre
        return y / np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-12)

    def code(self, x: np.ndarray) -> np.ndarray:
        """Rows of substrings."""
        bits = np.packbits(self._unit(x) @ self.rotation > 0, axis=1)
        return np.ascontiguousarray(np.pad(bits, ((0, 0), (0, 2 * self.tables - bits.shape[1])))).view(np.uint16)


class Block:
    """The rows of one block, with a table for each substring of the codes: its entries and the rows of each."""

    def __init__(self, codes: Codes, ids: np.ndarray, x: np.ndarray):
        self.codes, self.ids, self.x, self.code = codes, ids, x, codes.code(x)
        self.words = self.code.view(np.uint64)
        self.entries, self.order, self.starts, self.entry = [], [], [], []
        for column in self.code.T:
            order = np.argsort(column, kind="stable")
            entries, entry = np.unique(column, return_inverse=True)
            starts = np.searchsorted(column[order], entries)
            self.entry.append(entry.astype(np.int32))
            self.entries.append(entries)
            self.order.append(order)
            self.starts.append(np.r_[starts, len(order)])

    def probe(self, code: np.ndarray, radius: int) -> np.ndarray:
        """Which rows stand in a probed entry of some table."""
        marked = np.zeros(len(self.ids), bool)
        for t, most in enumerate(allowed(radius, self.codes.tables)):
            if most < 0:
                continue
            entries, starts = self.entries[t], self.starts[t]
            if most <= 2 and len(entries) > 200:
                wanted = code[t] ^ flips(most)
                at = np.searchsorted(entries, wanted)
                at = at[(at < len(entries)) & (entries[np.minimum(at, len(entries) - 1)] == wanted)]
                for i in at:
                    marked[self.order[t][starts[i] : starts[i + 1]]] = True
            else:
                marked |= (np.bitwise_count(entries ^ code[t]) <= most)[self.entry[t]]
        return marked

    def search(self, vec_id: int, q: np.ndarray, code: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        radius, bits = self.codes.radius, WORD * self.codes.tables
        while True:
            rows = np.flatnonzero(self.probe(code, radius))
            rows = rows[np.bitwise_count(self.words[rows] ^ code.view(np.uint64)).sum(axis=1) <= radius]
            rows = rows[self.ids[rows] != vec_id]
            if len(rows) >= k or radius >= bits:
                break
            radius = min(bits, radius + max(1, self.codes.tables // 2))
        score = (self.x[rows] * q).sum(axis=1)  # row by row, so that equal vectors score alike to the last bit
        if len(rows) > 4 * k:
            near = np.flatnonzero(score >= np.partition(score, len(score) - k)[len(score) - k])
            rows, score = rows[near], score[near]
        best = np.lexsort((self.ids[rows], -score))[:k]
        return self.ids[rows[best]], score[best]


def probed_share(x: np.ndarray, queries: int = 100, k: int = K) -> tuple[float, float]:
    """Of a block of vectors, the share of rows that a query's probes meet, and that of rows within its radius."""
    codes = Codes(x[:SAMPLE], k)
    block = Block(codes, np.arange(len(x)), x)
    met = [block.probe(c, codes.radius).mean() for c in block.code[:queries]]
    within = [(np.bitwise_count(block.words ^ c.view(np.uint64)).sum(axis=1) <= codes.radius).mean() for c in block.code[:queries]]
    return float(np.mean(met)), float(np.mean(within))


def usable(vectors: DataFrame) -> DataFrame:
    """Vectors as arrays of doubles, without those that take no part."""
    v = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("v")).where("vec_id is not null and v is not null and size(v) > 0")
    sound = F.forall("v", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("v", lambda c: c != 0)
    return v.where(sound)


def nearest(vectors: DataFrame, scratch: Scratch, k: int = K, every: int = QUERY_EVERY, sample: int = SAMPLE, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest rows of each query, a row whose vec_id is divisible by `every`."""
    rows = scratch.settle(usable(vectors), "vectors")
    if rows.groupBy("vec_id").count().where("count > 1").limit(1).count():
        rows = scratch.settle(rows.groupBy("vec_id").agg(F.min("v").alias("v")), "unique")
    dims = sorted((r["d"], r["n"]) for r in rows.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n")).collect())  # a row for each dimension
    parts = [_of_dimension(rows.where(F.size("v") == d), n, d, k, every, sample, block_rows) for d, n in dims]
    if not parts:
        return vectors.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    found = reduce(DataFrame.unionAll, parts)
    best = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("minus"), "vec_id"))), 1, k)  # at most k from each block
    return found.groupBy("query_id").agg(best.alias("b")).select("query_id", F.posexplode("b").alias("p", "n")).select("query_id", (F.col("p") + 1).alias("rank"), "n.vec_id", (-F.col("n.minus")).alias("score"))


def _of_dimension(rows: DataFrame, n: int, dim: int, k: int, every: int, sample: int, block_rows: int) -> DataFrame:
    """(query_id, vec_id, score): each query's nearest in every block of the n rows of one dimension."""
    taken = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).collect()  # at most `sample` rows
    codes = Codes(np.array([r["v"] for r in taken]), k)
    blocks = -(-n // block_rows)
    index = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"), F.lit(0).alias("asks"), "vec_id", "v")
    asked = rows.where(F.col("vec_id") % every == 0)
    # each query goes to every block: the stated query set against all rows, in blocks
    asked = asked.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.lit(1).alias("asks"), "vec_id", "v")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, xs, block = None, [], [], None
        for batch in batches:
            keys = np.asarray(batch.column("block"))
            asks, vec_id = np.asarray(batch.column("asks")), np.asarray(batch.column("vec_id"))
            x = np.asarray(batch.column("v").flatten()).reshape(-1, dim) if batch.num_rows else np.zeros((0, dim))
            out: list[tuple] = []
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]) | (asks[1:] != asks[:-1])) + 1).tolist(), len(keys)] if len(keys) else [0]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if keys[a] != key:
                    key, ids, xs, block = keys[a], [], [], None
                if not asks[a]:
                    ids.append(vec_id[a:b])
                    xs.append(x[a:b])
                    block = None
                elif ids:
                    block = block or Block(codes, np.concatenate(ids), np.concatenate(xs))
                    for q, v, c in zip(vec_id[a:b], x[a:b], codes.code(x[a:b]), strict=True):
                        found, score = block.search(int(q), v, c, k)
                        out += [(int(q), int(i), float(s)) for i, s in zip(found, score, strict=True)]
            cols = list(zip(*out, strict=True)) if out else [[], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64())], names=["query_id", "vec_id", "score"])

    together = index.unionByName(asked).repartitionById(blocks, "block").sortWithinPartitions("block", "asks")  # a block a task
    return together.mapInArrow(search, "query_id bigint, vec_id bigint, score double")


def op8_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), Scratch(spark, "op8"))
