"""Quality scores: random Fourier features over document statistics, ridge regression, isotonic calibration."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, id_remainder, id_text, table, text_hash, word_blocks

#: At most about this many labelled rows are fitted; beyond it, rows are chosen by a hash of their id.
FIT_ROWS = 200_000
#: Fourier features, the ridge penalty, the seed of the random directions, bins of the calibration.
FEATURES, PENALTY, SEED, BINS = 384, 1e-3, 7, 2048
THRESHOLD = 0.7

STATISTICS = (
    "log_words", "log_octets", "word_octets", "upper", "lower", "digit", "space", "newline", "stop", "comma", "bang", "bar", "sign", "other_mark", "high",
    "entropy", "distinct_words", "same_as_before", "seen_two_before", "end_mark", "log_lines", "line_words", "distinct_lines", "capital_words",
)
_GROUPS = {"upper": range(65, 91), "lower": range(97, 123), "digit": range(48, 58), "space": b" \t", "newline": b"\r\n", "stop": b".?;:", "comma": b",", "bang": b"!", "bar": b"|", "sign": b"#$%&*+=<>@^~\\/_{}[]", "other_mark": b"\"'()-`", "high": range(128, 256)}
_MEMBER = np.zeros((256, len(_GROUPS)))
for _k, _of in enumerate(_GROUPS.values()):
    _MEMBER[list(_of), _k] = 1


def statistics(data: bytes) -> list[float]:
    """The STATISTICS of one whole text; long texts are taken a block of words at a time."""
    counts = np.bincount(np.frombuffer(data, np.uint8), minlength=256).astype(float)
    n = max(1.0, counts.sum())
    shares = counts / n
    groups = dict(zip(_GROUPS, shares @ _MEMBER))
    some = shares[shares > 0]
    words = distinct = again = second = marks = capitals = 0
    for block in word_blocks(data):
        words += len(block)
        distinct += len(set(block))
        again += sum(map(bytes.__eq__, block, block[1:]))
        second += sum(map(bytes.__eq__, block, block[2:]))
        marks += sum(not x[-1:].isalnum() and x[-1] < 128 for x in block)
        capitals += sum(x[:1].isupper() for x in block)
    lines = different = 0
    for start in range(0, len(data), 1 << 20):
        part = data[start : start + (1 << 20)].split(b"\n")
        lines += len(part)
        different += len(set(part))
    w = max(1, words)
    return [
        math.log1p(words), math.log1p(len(data)), min(40.0, len(data) / w), *(float(groups[k]) for k in _GROUPS), float(-(some * np.log2(some)).sum()) if len(some) else 0.0,
        distinct / w, again / w, second / w, marks / w, math.log1p(lines), math.log1p(words / max(1, lines)), different / max(1, lines), capitals / w,
    ]


def document_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, stats (array of double in the order of STATISTICS), th (text hash). Null texts are empty texts."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [statistics(x.as_buffer().to_pybytes()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64())), batch.column(2)], names=["doc_id", "stats", "th"])

    return id_text(docs, id_col, text_col).withColumn("th", text_hash()).mapInArrow(work, "doc_id long, stats array<double>, th long")


class Model:
    """Standardisation, Fourier directions, ridge weights and the calibration's steps."""

    def __init__(self, mean: np.ndarray, scale: np.ndarray, features: int = FEATURES, seed: int = SEED):
        rng = np.random.default_rng(seed)
        d = len(mean)
        self.mean, self.scale = mean, scale
        self.directions = rng.normal(size=(d, features)) / math.sqrt(d)  # a Gaussian kernel whose width is the usual distance
        self.phases = rng.uniform(0, 2 * math.pi, features)
        self.weights = np.zeros(features + d + 1)
        self.steps, self.values = np.array([0.0]), np.array([0.5])

    def design(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.scale, -6, 6)
        return np.hstack([np.cos(z @ self.directions + self.phases) * math.sqrt(2 / len(self.phases)), z / 10, np.ones((len(z), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return self.design(stats) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        return np.interp(self.raw(stats), self.steps, self.values)


def _stats_of(batch: pa.RecordBatch, column: int) -> np.ndarray:
    return batch.column(column).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)


def pool_adjacent(weight: np.ndarray, total: np.ndarray) -> np.ndarray:
    """The non-decreasing means nearest to total/weight, by pooling adjacent violators."""
    pools: list[list[float]] = []
    for w, t in zip(weight.tolist(), total.tolist()):
        pools.append([w, t, 1])
        while len(pools) > 1 and pools[-2][1] * pools[-1][0] >= pools[-1][1] * pools[-2][0]:
            w2, t2, k2 = pools.pop()
            pools[-1] = [pools[-1][0] + w2, pools[-1][1] + t2, pools[-1][2] + k2]
    return np.concatenate([np.full(int(k), t / w) for w, t, k in pools]) if pools else np.zeros(0)


def fit(rows: DataFrame, features: int = FEATURES, penalty: float = PENALTY, fit_rows: int = FIT_ROWS) -> Model:
    """A model from ``rows``: doc_id, stats, label (0 or 1).

    A third of the rows (by a hash of the id) calibrate, the others are fitted. Each partition sums its own part
    of the normal equations; the driver adds and solves them: it sees features squared numbers, never rows.
    Without rows of both labels the model scores the mean label, and one half where there are no rows.
    """
    told = rows.agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("ones"), *(F.avg(F.col("stats")[k]).alias(f"m{k}") for k in range(len(STATISTICS))), *(F.stddev_pop(F.col("stats")[k]).alias(f"s{k}") for k in range(len(STATISTICS)))).first()
    n, k = told["n"], len(STATISTICS)
    model = Model(np.array([told[f"m{i}"] or 0.0 for i in range(k)]), np.array([max(told[f"s{i}"] or 0.0, 1e-6) for i in range(k)]), features)
    if not n or told["ones"] in (0, n):
        model.values = np.array([told["ones"] / n if n else 0.5])
        return model
    chosen = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < min(1.0, fit_rows / n) * (1 << 20)) if n > fit_rows else rows
    fold = F.pmod(F.crc32(F.concat(F.lit("fold"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))), F.lit(3)) == 0
    width = len(model.weights)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gram = np.zeros((width, width + 1))
        for batch in batches:
            x = model.design(_stats_of(batch, 0))
            y = batch.column(1).to_numpy(zero_copy_only=False).astype(float)
            gram += x.T @ np.hstack([x, y[:, None]])
        yield pa.RecordBatch.from_arrays([pa.array([0]), pa.array([gram.tobytes()], pa.binary())], names=["k", "gram"])

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(width * (width + 1))
        for batch in batches:
            for x in batch.column(1):
                total += np.frombuffer(x.as_buffer())
        yield pa.RecordBatch.from_arrays([pa.array([0]), pa.array([total.tobytes()], pa.binary())], names=["k", "gram"])

    # Partial sums meet in few tasks first, so that the driver gets at most 16 matrices whatever the size.
    partial = chosen.where(~fold).select("stats", F.col("label").cast("double").alias("label")).mapInArrow(sums, "k long, gram binary")
    parts = partial.repartition(16).mapInArrow(added, "k long, gram binary").collect()
    total = sum(np.frombuffer(bytes(p["gram"])).reshape(width, width + 1) for p in parts)
    rows_fitted = max(1.0, total[width - 1, width - 1])
    gram, right = total[:, :width] / rows_fitted, total[:, width] / rows_fitted
    model.weights = np.linalg.solve(gram + penalty * np.eye(width), right)

    def binned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            b = np.clip(np.floor((model.raw(_stats_of(batch, 0)) + 1) / 3 * BINS), 0, BINS - 1).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(b), batch.column(1)], names=["bin", "label"])

    held = chosen.where(fold).select("stats", F.col("label").cast("double").alias("label")).mapInArrow(binned, "bin long, label double")
    table_ = sorted(tuple(r) for r in held.groupBy("bin").agg(F.count(F.lit(1)), F.sum("label")).collect())  # BINS rows at most
    if table_:
        bins, weight, ones = (np.array(x, float) for x in zip(*table_))
        model.steps, model.values = (bins + 0.5) / BINS * 3 - 1, pool_adjacent(weight, ones)
    return model


def score(stats: DataFrame, model: Model) -> DataFrame:
    """doc_id, score (0 to 1), th, for every row of document_statistics()."""
    shared = stats.sparkSession.sparkContext.broadcast(model)  # features x statistics numbers: a fixed size

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = np.clip(shared.value.score(_stats_of(batch, 1)), 0, 1) if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got), batch.column(2)], names=["doc_id", "score", "th"])

    return stats.select("doc_id", "stats", "th").mapInArrow(work, "doc_id long, score double, th long")


def labelled(stats: DataFrame, labels: DataFrame) -> DataFrame:
    """Statistics with the label of their document. Several labels of one document: the majority, a tie counts as 0."""
    one = labels.where("doc_id is not null and quality in (0, 1)").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg((F.avg("quality") > 0.5).cast("int").alias("label"))
    return stats.select("doc_id", "stats").join(one, "doc_id")


def quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", fit_rows: int = FIT_ROWS) -> DataFrame:
    """Per row of ``docs``: doc_id, held_out, score, predicted, th (text hash).

    Labels of documents whose crc32(doc_id as text) mod 4 is 2 are never learnt from. Nothing but the text enters
    a score. Null and empty texts get the score of a text without words. Only whole texts' statistics are kept
    between the two passes; texts are read once.
    """
    ws = Workspace(docs.sparkSession, "quality")
    stats = ws.save(document_statistics(docs, id_col, text_col), "statistics")
    held = id_remainder(F.col("doc_id"), 4) == 2
    train = ws.save(labelled(stats, labels.where(id_remainder(F.col("doc_id"), 4) != 2)), "labelled")
    out = score(stats, fit(train, fit_rows=fit_rows))
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "th")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """quality() of all ``documents``, learnt from ``labels``."""
    return quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("th")
