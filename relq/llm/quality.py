"""Quality scores: random Fourier features of document statistics, ridge by summed normal equations, isotonic calibration.

Statistics of every text are measured once and kept as a narrow table. The
normal equations are summed in each partition and then over partitions as
fixed-point numbers, so the fit does not depend on the order of rows; all
labelled rows take part. One fold of the labelled rows calibrates.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labels import residue, training_labels
from .workers import tidy
from .workspace import Workspace

FEATURES, WIDTH, RIDGE, BINS, SEED = 160, 3.0, 1e-3, 400, 77
FIXED_POINT = 1 << 30
STATISTICS = (
    "log_chars", "log_words", "word_length", "letters", "digits", "marks", "odd_marks", "capitals", "distinct_words", "top_word",
    "distinct_lines", "short_words", "stops", "line_length", "distinct_triples", "spaces",
)
_SETS = {name: np.frombuffer(chars, np.uint8) for name, chars in {
    "digits": b"0123456789", "marks": b".,;:!?'\"()-", "odd_marks": b"#$%&*|@<>[]{}=+~^_\\/`", "capitals": bytes(range(65, 91)), "stops": b".!?", "spaces": b" \t\n\r",
}.items()}


def statistics(text: str | None) -> list[float]:
    """The 16 statistics of a whole text; an empty one gives zeros."""
    raw = (text or "").encode("utf-8", "replace")
    words = raw.split()
    if not words:
        return [0.0] * len(STATISTICS)
    counts = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    share = {k: counts[v].sum() / len(raw) for k, v in _SETS.items()}
    letters = (counts[65:91].sum() + counts[97:123].sum() + counts[192:].sum()) / len(raw)
    n, lines, often = len(words), [x for x in raw.split(b"\n") if x.strip()], Counter(words)
    triples = max(1, n - 2)
    return [
        np.log1p(len(raw)) / 10, np.log1p(n) / 8, min(3.0, len(raw) / n / 10), letters, share["digits"], share["marks"], share["odd_marks"],
        share["capitals"], len(often) / n, often.most_common(1)[0][1] / n, len(set(lines)) / len(lines), sum(c for w, c in often.items() if len(w) <= 3) / n,
        min(3.0, share["stops"] * len(raw) / n), np.log1p(len(raw) / len(lines)) / 10, len(set(zip(words, words[1:], words[2:], strict=False))) / triples if n > 2 else 1.0, share["spaces"],
    ]


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, x)``: the statistics of every row."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = np.array([statistics(t.as_py()) for t in batch.column(1)], float).reshape(-1)
            ends = pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * len(STATISTICS))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(ends, pa.array(rows))], ["doc_id", "x"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), f"doc_id {kind}, x array<double>")


class FourierFeatures:
    """cos(W z + b), scaled, with W normal: products approximate a Gaussian kernel of standardised statistics."""

    def __init__(self, mean: np.ndarray, spread: np.ndarray, count: int = FEATURES, width: float = WIDTH):
        rng = np.random.default_rng(SEED)
        self.mean, self.spread = mean, np.where(spread > 1e-9, spread, 1.0)
        self.w = rng.standard_normal((len(mean), count)) / width
        self.b = rng.uniform(0, 2 * np.pi, count)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.spread, -5, 5)
        return np.column_stack([np.cos(z @ self.w + self.b) * np.sqrt(2 / len(self.b)), np.ones(len(x))])


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def normal_equations(rows: DataFrame, features: FourierFeatures) -> tuple[np.ndarray, np.ndarray, int]:
    """Z'Z, Z'y and the row count over ``(x, label)``: a sum per task and cell, then one per cell."""
    d = FEATURES + 1
    upper = np.triu_indices(d)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gram, target, n = np.zeros((d, d)), np.zeros(d), 0
        for batch in batches:
            if batch.num_rows:
                z, y = features(_matrix(batch.column(0))), batch.column(1).to_numpy(zero_copy_only=False)
                gram += z.T @ z
                target += z.T @ y
                n += len(y)
        if n:
            values = np.rint(np.concatenate([gram[upper], target, [n]]) * FIXED_POINT)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(values), dtype=np.int32)), pa.array(values.astype(np.int64))], ["cell", "value"])

    sums = rows.select("x", "label").mapInArrow(tidy(run), "cell int, value long").groupBy("cell").agg(F.sum(F.col("value").cast("decimal(38,0)")).alias("value"))
    cells = np.zeros(len(upper[0]) + d + 1)
    for r in sums.collect():  # a fixed number of cells
        cells[r["cell"]] = float(r["value"]) / FIXED_POINT
    gram = np.zeros((d, d))
    gram[upper] = cells[: len(upper[0])]
    return gram + np.triu(gram, 1).T, cells[len(upper[0]) : -1], round(cells[-1])


def isotonic(counts: np.ndarray, sums: np.ndarray) -> np.ndarray:
    """Non-decreasing means of the bins, by pooling adjacent violators; empty bins take what lies below."""
    blocks: list[list[float]] = []  # sum, count, bins
    for n, s in zip(counts, sums, strict=True):
        blocks.append([float(s), float(n), 1])
        while len(blocks) > 1 and (blocks[-1][1] == 0 or blocks[-2][1] == 0 or blocks[-2][0] / blocks[-2][1] >= blocks[-1][0] / blocks[-1][1]):
            last = blocks.pop()
            blocks[-1] = [a + b for a, b in zip(blocks[-1], last, strict=True)]
    return np.concatenate([np.full(int(k), s / n if n else 0.5) for s, n, k in blocks])


class QualityModel:
    """Features, ridge coefficients and calibrated levels."""

    def __init__(self, features: FourierFeatures, beta: np.ndarray, levels: np.ndarray):
        self.features, self.beta, self.levels = features, beta, levels

    def bins(self, x: np.ndarray) -> np.ndarray:
        raw = np.clip((self.features(x) @ self.beta + 0.5) / 2, 0, 1 - 1e-9)  # from [-0.5, 1.5)
        return (raw * BINS).astype(np.int64)

    def scores(self, x: np.ndarray) -> np.ndarray:
        return self.levels[self.bins(x)]


def train(measured: DataFrame, labels: DataFrame, label_col: str = "quality", held_out: tuple[int, int] = (5, 0), calibration: int = 1) -> QualityModel:
    """Fits on every labelled row outside the held-out residue; residue ``calibration`` is kept for calibrating.

    With labels of no row the score is 0.5 everywhere.
    """
    known = training_labels(labels, label_col)
    fold = residue(F.col("doc_id"), held_out[0])
    rows = measured.join(known, "doc_id").where(fold != held_out[1]).withColumn("fold", fold)
    d = len(STATISTICS)
    first = rows.agg(*[F.avg(F.get("x", F.lit(k))) for k in range(d)], *[F.stddev_pop(F.get("x", F.lit(k))) for k in range(d)]).first()
    found = np.round(np.array([v or 0.0 for v in first], float), 6)
    features = FourierFeatures(found[:d], found[d:])
    gram, target, n = normal_equations(rows.where(F.col("fold") != calibration), features)
    if not n:
        return QualityModel(features, np.zeros(FEATURES + 1), np.full(BINS, 0.5))
    beta = np.round(np.linalg.solve(gram + RIDGE * n * np.diag([1.0] * FEATURES + [1e-9]) / FEATURES, target), 9)
    draft = QualityModel(features, beta, np.zeros(BINS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(draft.bins(_matrix(batch.column(0))) if batch.num_rows else np.zeros(0, np.int64)), batch.column(1)], ["bin", "label"])

    tallies = rows.where(F.col("fold") == calibration).select("x", "label").mapInArrow(tidy(run), "bin long, label int").groupBy("bin").agg(F.count("*").alias("n"), F.sum("label").alias("s"))
    counts, sums = np.zeros(BINS), np.zeros(BINS)
    for r in tallies.collect():  # 400 bins at most
        counts[r["bin"]], sums[r["bin"]] = r["n"], r["s"]
    return QualityModel(features, beta, isotonic(counts, sums) if counts.sum() else np.linspace(0, 1, BINS))


def score_documents(measured: DataFrame, model: QualityModel) -> DataFrame:
    """``(doc_id, score)`` from measured statistics."""
    shared = measured.sparkSession.sparkContext.broadcast(model)
    kind = dict(measured.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(shared.value.scores(_matrix(batch.column(1))))], ["doc_id", "score"])

    return measured.select("doc_id", "x").mapInArrow(tidy(run), f"doc_id {kind}, score double")


def quality_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> DataFrame:
    """``(doc_id, score)``, one row per input row; null and blank texts have statistics of zero.

    Very long texts are measured whole; repeated rows are repeated and, if
    labelled, count as often in the fit. Empty tables give no rows.
    """
    measured = Workspace(docs.sparkSession, "quality").save(measure(docs, id_col, text_col), "statistics")
    return score_documents(measured, train(measured, labels, label_col))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its quality score and the decision at 0.3."""
    scored = quality_scores(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return scored.select("doc_id", (residue(F.col("doc_id"), 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
