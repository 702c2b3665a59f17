"""Quality classifier: ridge regression on random Fourier features, then isotonic calibration.

Document statistics (computed inside Spark) are standardised and mapped by random cosines that approximate a Gaussian
kernel.  Each partition sums its part of the normal equations, parts are summed in a tree, and the driver solves one
system of fixed size.  A second fold of labelled rows calibrates: outcomes are averaged over fixed bins of the raw
output and made monotone by pooling adjacent violators.  All labelled rows outside the held-out third are used.

A score needs the text only.  A null or empty text has zero statistics and gets a score like any other.  Without
labelled rows every score is 0.5.  Rows without a label or with a null one train nothing; documents that repeat are
scored one by one.  Further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import only, read_table, staged
from walkengine.llm.quality_rules import measured, ratios

#: Random features, ridge penalty a row, kernel width in standard deviations, seed, bins for calibration.
FEATURES, PENALTY, WIDTH, SEED, BINS = 128, 1e-3, 4.0, 5, 1024
STATISTICS = (
    "log_words log_chars log_lines mean_word_chars symbols_per_word stop_word_ratio upper_word_ratio "
    "dup_line_ratio bullet_line_ratio ellipsis_line_ratio repeat_ratio distinct_ratio mark_ratio bar_ratio digit_ratio "
    "upper_ratio sentence_words"
).split()


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id and the statistics of every whole text, as one array of doubles."""
    text = F.col("text")
    gone = lambda chars: F.length(text) - F.length(F.translate(text, chars, ""))
    own = {
        "n_chars": F.length(text),
        "n_distinct": F.size(F.array_distinct("words")),
        "n_marks": gone("!?"),
        "n_bars": gone("|"),
        "n_digits": gone("0123456789"),
        "n_capitals": F.length(F.regexp_replace(text, r"\P{Lu}+", "")),
        "n_ends": gone(".!?"),
    }
    over = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    named = ratios() | {
        "log_words": F.log1p("n_words"),
        "log_chars": F.log1p("n_chars"),
        "log_lines": F.log1p("n_lines"),
        "repeat_ratio": over("n_repeat_words", "n_words"),
        "distinct_ratio": over("n_distinct", "n_words"),
        "mark_ratio": over("n_marks", "n_words"),
        "bar_ratio": over("n_bars", "n_words"),
        "digit_ratio": over("n_digits", "n_chars"),
        "upper_ratio": over("n_capitals", "n_chars"),
        "sentence_words": F.log1p(F.col("n_words") / (F.col("n_ends") + 1)),
    }
    return (
        measured(only(docs, "doc_id", "text"), more=own)
        .select("doc_id", F.array(*(named[n].cast("double") for n in STATISTICS)).alias("stats"))
    )


class Model:
    """Standardisation, random features, ridge weights and calibration; as large for any input."""

    def __init__(self, mean: np.ndarray, spread: np.ndarray):
        draw = np.random.default_rng(SEED)
        self.mean, self.spread = mean, spread
        self.directions = draw.standard_normal((len(mean), FEATURES)) / WIDTH
        self.phases = draw.uniform(0, 2 * np.pi, FEATURES)
        self.weights = np.zeros(FEATURES + 1)
        self.knots, self.levels = np.array([0.0]), np.array([0.5])

    def features(self, stats: np.ndarray) -> np.ndarray:
        x = np.clip((stats - self.mean) / self.spread, -6, 6)
        z = np.sqrt(2 / FEATURES) * np.cos(x @ self.directions + self.phases)
        return np.hstack([z, np.ones((len(z), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return self.features(stats) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        """Calibrated, with a hundredth of the raw output so that order is kept within a pooled block."""
        raw = self.raw(stats)
        return np.clip(0.99 * np.interp(raw, self.knots, self.levels) + 0.01 * np.clip(raw, 0, 1), 0, 1)


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(len(column), -1)


def normal_equations(rows: DataFrame, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """Sums of z z' and z y over rows (stats, y): one part a partition, then a tree of sums."""
    low = np.tril_indices(FEATURES + 1)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        square, side, seen = np.zeros((FEATURES + 1,) * 2), np.zeros(FEATURES + 1), False
        for batch in batches:
            if batch.num_rows:
                z, seen = model.features(_matrix(batch["stats"])), True
                square += z.T @ z
                side += z.T @ np.asarray(batch["y"], np.float64)
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([square[low], side]).tobytes()])], names=["part"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            for x in batch["part"].to_pylist():
                total = np.frombuffer(x) if total is None else total + np.frombuffer(x)
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], names=["part"])

    parts = rows.select("stats", "y").mapInArrow(part, "part binary")
    width = parts.rdd.getNumPartitions()
    while width > 32:  # each round leaves about a sixteenth of the parts
        width = -(-width // 16)
        parts = parts.repartition(width).mapInArrow(add, "part binary")
    sums = [np.frombuffer(r.part) for r in parts.collect()]  # at most 32 parts of a fixed size
    total = np.sum(sums, axis=0) if sums else np.zeros(len(low[0]) + FEATURES + 1)
    square = np.zeros((FEATURES + 1,) * 2)
    square[low] = total[: len(low[0])]
    return square + np.tril(square, -1).T, total[len(low[0]) :]


def isotonic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pools adjacent violators; (mean x, mean y) of the blocks in ascending x."""
    blocks: list[list[float]] = []
    for a, b, w in zip(x, y, weight):
        blocks.append([a * w, b * w, w])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][2] >= blocks[-1][1] * blocks[-2][2]:
            last = blocks.pop()
            blocks[-1] = [p + q for p, q in zip(blocks[-1], last)]
    sums = np.array(blocks)
    return sums[:, 0] / sums[:, 2], sums[:, 1] / sums[:, 2]


def fit(rows: DataFrame) -> Model:
    """``rows``: stats, y (0 or 1), calibrate (whether the row is kept for calibration)."""
    n = len(STATISTICS)
    moments = rows.where("NOT calibrate").agg(
        F.count("*").alias("n"),
        *(F.avg(F.col("stats")[i]).alias(f"m{i}") for i in range(n)),
        *(F.stddev_pop(F.col("stats")[i]).alias(f"s{i}") for i in range(n)),
    ).first()
    if not moments.n:
        return Model(np.zeros(n), np.ones(n))
    spread = np.array([moments[f"s{i}"] for i in range(n)])
    model = Model(np.array([moments[f"m{i}"] for i in range(n)]), np.where(spread > 1e-9, spread, 1.0))
    square, side = normal_equations(rows.where("NOT calibrate"), model)
    model.weights = np.linalg.solve(square + PENALTY * moments.n * np.eye(len(side)) / FEATURES, side)

    def raw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                bins = np.clip((model.raw(_matrix(batch["stats"])) + 0.5) / 2 * BINS, 0, BINS - 1).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(bins), batch["y"].cast(pa.float64())], names=["bin", "y"])

    by_bin = (
        rows.where("calibrate").select("stats", "y").mapInArrow(raw, "bin long, y double")
        .groupBy("bin").agg(F.avg("y").alias("y"), F.count("*").alias("n")).orderBy("bin").collect()
    )
    if by_bin:
        x = (np.array([r.bin for r in by_bin]) + 0.5) / BINS * 2 - 0.5
        model.knots, model.levels = isotonic(x, np.array([r.y for r in by_bin]), np.array([r.n for r in by_bin]))
    else:
        model.knots, model.levels = np.array([0.0, 1.0]), np.array([0.0, 1.0])
    return model


def fold() -> F.Column:
    """crc32 of doc_id as text, mod 3; -1 for a null doc_id."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3, F.lit(-1))


def apply(stats: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                score = model.score(_matrix(batch["stats"]))
                columns = [batch["doc_id"].cast(pa.int64()), batch["held_out"], pa.array(score), pa.array((score >= 0.5).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "held_out", "score", "predicted"])

    rows = stats.select("doc_id", (fold() == 1).alias("held_out"), "stats")
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    stats = staged(statistics(docs), "statistics")
    marked = only(labels, "doc_id", "quality").where("quality IS NOT NULL AND doc_id IS NOT NULL")
    rows = staged(
        stats.join(marked, "doc_id")
        .where(fold().isin(0, 2))
        .select("stats", F.col("quality").cast("double").alias("y"), (fold() == 2).alias("calibrate")),
        "training",
    )
    return apply(stats, fit(rows))


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


QUERIES = {"op1_quality_classifier": op1_quality_classifier}
ORACLES: dict[str, str] = {}
