"""Quality scores: ridge regression on random Fourier features of document statistics, then isotonic calibration.

A document is described by STATS statistics of its whole text. Random Fourier features approximate a Gaussian kernel on
them; each partition of the training sample sums its part of the normal equations, the driver adds the FIT_PARTS parts
and solves. Isotonic regression on rows kept from the fit turns ridge scores into probabilities.

Training sample: at most SAMPLE labelled rows, those with the smallest hash of doc_id, none of them held out
(crc32 of the doc_id as text, mod 5, is 0). The bound is the only one; every document is scored on its whole text.

Cases: null text counts as empty; all statistics of an empty text are 0 and it is scored by the same model; with no
usable label every score is 0.5; repeated rows are each scored; an empty table gives no rows; further columns stay out.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import slices, table

SAMPLE, FIT_PARTS, WAVES, RIDGE, BANDWIDTH, SEED = 20_000, 8, 256, 1e-3, 4.0, 20240607
ACCEPT = 0.3
_CLASSES = {"upper": range(65, 91), "lower": range(97, 123), "digit": range(48, 58), "high": range(128, 256), "stop": b".,;:?'\"-()", "odd": b"!#$%&*+/<=>@[\\]^_`{|}~", "bang": b"!", "pipe": b"|"}
STATS = ["log_words", "log_lines", "word_length", "log_word_length", *_CLASSES, "space", "distinct", "top_word", "adjacent", "line_words", "distinct_lines", "open_end", "distinct_pairs"]


def _class_rows() -> np.ndarray:
    rows = np.zeros((len(_CLASSES), 256))
    for i, members in enumerate(_CLASSES.values()):
        rows[i, list(members)] = 1
    return rows


_ROWS = _class_rows()


def statistics(text: str | None) -> list[float]:
    """The statistics of one whole text, in the order of STATS."""
    if not text:
        return [0.0] * len(STATS)
    words = text.split()
    lines = text.split("\n")
    counts = np.bincount(np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8), minlength=256)
    size, n = int(counts.sum()), max(1, len(words))
    shares = (_ROWS @ counts) / size
    seen = Counter(words)
    top = seen.most_common(1)[0][1] if seen else 0
    follow = words[1:]
    mean = (len(text) - len(words)) / n
    return [
        math.log1p(len(words)), math.log1p(len(lines)), min(mean, 50.0), math.log1p(mean), *shares.tolist(), (int(counts[32]) + int(counts[10])) / size,
        len(seen) / n, top / n, sum(map(eq, words, follow)) / n, math.log1p(n / len(lines)), len(set(lines)) / len(lines),
        float(text[-1] not in ".!?\"'"), len(set(zip(words, follow, strict=False))) / n,
    ]


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators; returns the pooled blocks' mean x and mean y, both ascending."""
    order = np.argsort(x, kind="stable")
    blocks: list[list[float]] = []  # sum of x, sum of y, rows
    for a, b in zip(x[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([a, b, 1.0])
        while len(blocks) > 1 and blocks[-2][1] / blocks[-2][2] >= blocks[-1][1] / blocks[-1][2]:
            last = blocks.pop()
            blocks[-1] = [p + q for p, q in zip(blocks[-1], last, strict=True)]
    return np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks])


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    waves: np.ndarray
    phase: np.ndarray
    weights: np.ndarray | None
    knots: tuple[np.ndarray, np.ndarray] | None = None

    def expand(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.scale, -6, 6)
        return np.concatenate([np.cos(z @ self.waves + self.phase) * math.sqrt(2 / self.waves.shape[1]), np.ones((len(z), 1))], axis=1)

    def score(self, stats: np.ndarray) -> np.ndarray:
        if self.weights is None:
            return np.full(len(stats), 0.5)
        raw = self.expand(stats) @ self.weights
        return np.clip(np.interp(raw, *self.knots), 0, 1) if self.knots is not None and len(self.knots[0]) else np.clip(raw, 0, 1)


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def _described(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        stats = [statistics(t) for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("part"), batch.column("y"), pa.array(stats, pa.list_(pa.float64()))], names=["part", "y", "stats"])


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, waves: int = WAVES, seed: int = SEED) -> QualityModel:
    rng = np.random.default_rng(seed)
    w = rng.normal(0, 1 / BANDWIDTH, (len(STATS), waves))
    phase = rng.uniform(0, 2 * math.pi, waves)
    usable = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).select(F.col("doc_id").alias("_id"), F.col("quality").cast("double").alias("y"))
    chosen = usable.orderBy(F.xxhash64("_id"), "_id", "y").limit(sample)
    part = F.pmod(F.xxhash64(F.lit("part"), "_id"), F.lit(FIT_PARTS)).cast("int")
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))  # at most `sample` rows
    stats = rows.select(part.alias("part"), "y", "text").mapInArrow(_described, "part int, y double, stats array<double>").repartition(FIT_PARTS, "part").persist()
    try:
        cells = [F.struct(F.avg(F.col("stats")[i]).alias("m"), F.stddev_pop(F.col("stats")[i]).alias("s")) for i in range(len(STATS))]
        n, moments = stats.agg(F.count("*"), F.array(*cells)).first()
        if not n:
            return QualityModel(np.zeros(len(STATS)), np.ones(len(STATS)), w, phase, None)
        model = QualityModel(np.array([m["m"] for m in moments]), np.array([max(m["s"], 1e-6) for m in moments]), w, phase, None)

        def equations(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            left, right, used = np.zeros((waves + 1, waves + 1)), np.zeros(waves + 1), 0
            for batch in batches:
                keep = np.asarray(batch.column("part")) % 4 != 3  # a quarter is kept for the calibration
                if keep.any():
                    x = model.expand(np.array(batch.column("stats").to_pylist())[keep])
                    left += x.T @ x
                    right += x.T @ np.asarray(batch.column("y"))[keep]
                    used += int(keep.sum())
            if used:  # FIT_PARTS keys fill at most FIT_PARTS partitions, however many there are
                yield pa.RecordBatch.from_arrays([pa.array([left.tobytes()], pa.binary()), pa.array([right.tobytes()], pa.binary())], names=["xx", "xy"])

        parts = stats.mapInArrow(equations, "xx binary, xy binary").collect()  # at most FIT_PARTS rows
        total = lambda c, shape: sum((np.frombuffer(bytes(r[c])).reshape(shape) for r in parts), np.zeros(shape))
        xx, xy = total("xx", (waves + 1, waves + 1)), total("xy", (waves + 1,))
        model.weights = np.linalg.solve(xx + RIDGE * n * np.eye(waves + 1) / waves, xy)
        kept = stats.where("part % 4 = 3").select("y", "stats").collect() or stats.select("y", "stats").collect()  # at most `sample` rows
        raw = model.expand(np.array([r["stats"] for r in kept])) @ model.weights
        model.knots = isotonic(raw, np.array([r["y"] for r in kept]))
        return model
    finally:
        stats.unpersist()


def score_documents(docs: DataFrame, model: QualityModel, keep: list[str], column: str = "score") -> DataFrame:
    """The columns `keep` and the score under the name `column`."""
    types = {f.name: f.dataType.simpleString() for f in docs.schema.fields}
    source = docs.select(*keep, F.col("text").alias("_slw_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            stats = np.array([statistics(t) for t in batch.column("_slw_text").to_pylist()]).reshape(-1, len(STATS))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(model.score(stats), pa.float64())], names=[*keep, column])

    return source.mapInArrow(run, ", ".join([*(f"`{c}` {types[c]}" for c in keep), f"`{column}` double"]))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    scored = score_documents(docs, model, ["doc_id"])
    return scored.select("doc_id", held_out(F.coalesce("doc_id", F.lit(-1))).alias("held_out"), "score", (F.col("score") >= ACCEPT).cast("int").alias("predicted"))
