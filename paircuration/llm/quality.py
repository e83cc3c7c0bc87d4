"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each class has a mean and a covariance, shrunk towards the pooled covariance and then towards a scaled identity.  A
score is the logistic of the difference of the two Gaussian log densities plus the log prior ratio, tempered by the fixed
slope SLOPE; Mahalanobis distances use Cholesky factors computed once and sent with the model.

The sufficient statistics (counts, sums, cross products) are aggregated over every labelled row outside the held-out
fold, so what is collected is one small matrix per class.  Defined results: null counts as empty; an empty text has
fixed statistics and is scored like any other; repeated rows are scored alike; a class with fewer than two rows takes
the pooled covariance, and without both classes every score is the labelled share of good rows (1.0 with no labels);
extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import fold_of, settle, sigmoid

NAMES = ("length", "word", "symbol", "digit", "upper", "punct", "blank", "pipe", "distinct", "top", "line", "lines", "repeat")
_CLASS = np.zeros(256, dtype=np.uint8)  # 1 upper, 2 digit, 3 sentence marks, 4 other symbols, 5 white space, 6 letters and bytes of others
_CLASS[65:91], _CLASS[97:123], _CLASS[128:], _CLASS[48:58] = 1, 6, 6, 2
_CLASS[[33, 35, 36, 37, 38, 42, 43, 47, 60, 61, 62, 64, 91, 92, 93, 94, 95, 96, 123, 124, 125, 126]] = 4
_CLASS[[34, 39, 40, 41, 44, 45, 46, 58, 59, 63]] = 3
_CLASS[[9, 10, 11, 12, 13, 32]] = 5
_FLOOR = 0.002
SLOPE = 0.5  # the statistics overlap in what they measure, so plain Gaussian log ratios are too sure of themselves


def statistics(text: bytes) -> list[float]:
    """Transformed statistics of a whole text: shares as log(share + floor), sizes as log(1 + size)."""
    data = np.frombuffer(text, dtype=np.uint8)
    n = max(1, len(data))
    kinds = np.bincount(_CLASS[data], minlength=7)
    words, lines = text.lower().split(), text.split(b"\n")
    m = max(1, len(words))
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    share = lambda k: np.log(k / n + _FLOOR)
    twins = sum(a == b for a, b in zip(words, words[1:]))
    return [
        np.log1p(len(data)), len(data) / m if words else 0.0, share(kinds[4]), share(kinds[2]), share(kinds[1]), share(kinds[3]), share(kinds[5]),
        np.log(text.count(b"|") / m + _FLOOR), np.log(len(counts) / m + _FLOOR) + 0.12 * np.log(m), np.log(max(counts.values(), default=0) / m + _FLOOR),
        np.log1p(n / len(lines)), np.log(1 - len(set(lines)) / len(lines) + _FLOOR), np.log(twins / m + _FLOOR),
    ]


def _statistic_batches(batches):
    for batch in batches:
        texts = pc.fill_null(batch.column(1), "").cast(pa.large_binary())
        rows = np.array([statistics(t.as_py()) for t in texts], dtype=np.float64).reshape(len(texts), len(NAMES))
        rows[:, 1] = np.log1p(rows[:, 1])
        yield pa.record_batch([batch.column(0)] + [pa.array(rows[:, i]) for i in range(len(NAMES))], names=["row_key", *NAMES])


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body")).mapInArrow(
        _statistic_batches, f"row_key {kind}, " + ", ".join(f"{n} double" for n in NAMES))


class Discriminant:
    """Two Gaussians with cached Cholesky factors."""

    def __init__(self, means, covariances, priors, slope: float = 1.0, shift: float = 0.0):
        self.means, self.slope, self.shift = means, slope, shift
        self.factors = [np.linalg.cholesky(c) for c in covariances]
        self.solvers = [np.linalg.inv(f) for f in self.factors]
        self.offsets = [np.log(p) - np.log(np.diag(f)).sum() for p, f in zip(priors, self.factors)]

    def log_ratio(self, x: np.ndarray) -> np.ndarray:
        """log density of class 1 minus that of class 0, priors included."""
        side = [o - 0.5 * (((x - m) @ s.T) ** 2).sum(axis=1) for m, s, o in zip(self.means, self.solvers, self.offsets)]
        return side[1] - side[0]

    def scores(self, x: np.ndarray) -> np.ndarray:
        return sigmoid(self.slope * self.log_ratio(x) + self.shift)


def moments(rows: DataFrame) -> dict[int, tuple[float, np.ndarray, np.ndarray]]:
    """Count, mean and covariance by label, from one aggregation."""
    d = len(NAMES)
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    sums = rows.groupBy("label").agg(
        F.count(F.lit(1)).alias("n"), *[F.sum(n).alias(f"s{i}") for i, n in enumerate(NAMES)],
        *[F.sum(F.col(NAMES[i]) * F.col(NAMES[j])).alias(f"p{i}_{j}") for i, j in pairs]).collect()
    out = {}
    for r in sums:
        mean = np.array([r[f"s{i}"] for i in range(d)]) / r["n"]
        cov = np.zeros((d, d))
        for i, j in pairs:
            cov[i, j] = cov[j, i] = r[f"p{i}_{j}"] / r["n"] - mean[i] * mean[j]
        out[r["label"]] = (r["n"], mean, cov)
    return out


def fit(rows: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", shrink: float = 0.1, ridge: float = 0.01) -> Discriminant | float:
    """Fit on all labelled rows outside the held-out fold; a float is the constant score of a one-class table."""
    marked = labels.select(F.col(id_col).alias("row_key"), F.col(label_col).cast("int").alias("label")).filter(
        "row_key IS NOT NULL AND label IN (0, 1)").filter(fold_of(F.col("row_key")) != 1)
    joined = rows.join(marked, "row_key")
    by = moments(joined)
    total = sum(v[0] for v in by.values())
    if len(by) < 2:
        return by.get(1, (0,))[0] / total if total else 1.0
    pooled = sum(by[k][0] * by[k][2] for k in by) / total
    level = np.trace(pooled) / len(pooled)
    covs = []
    for k in (0, 1):
        own = by[k][2] if by[k][0] > 1 else pooled
        mixed = (1 - shrink) * own + shrink * pooled
        covs.append((1 - ridge) * mixed + ridge * level * np.eye(len(mixed)))
    return Discriminant([by[k][1] for k in (0, 1)], covs, [by[k][0] / total for k in (0, 1)], slope=SLOPE)


def score(rows: DataFrame, model: Discriminant | float, id_col: str = "doc_id") -> DataFrame:
    """(id, score) from the statistics of `measured`."""
    kind = rows.schema["row_key"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            x = np.stack([batch.column(i + 1).to_numpy(zero_copy_only=False) for i in range(len(NAMES))], axis=1)
            s = np.full(len(x), model) if isinstance(model, float) else model.scores(x)
            yield pa.record_batch([batch.column(0), pa.array(s)], names=["row_key", "score"])

    return rows.select("row_key", *NAMES).mapInArrow(run, f"row_key {kind}, score double").withColumnRenamed("row_key", id_col)


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = settle(measured(spark.read.parquet(f"{sf_dir}/documents.parquet")), "statistics")
    found = score(rows, fit(rows, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return found.select("doc_id", (fold_of(F.col("doc_id")) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
