"""Quality classifier: regularised quadratic discriminant analysis of document statistics.

Statistics of the whole text are put on log scales. Per class, counts, sums and products of
the labelled training rows are aggregated in Spark; mean and covariance follow on the driver
(a few hundred numbers, whatever the corpus). Each covariance is shrunk towards the pooled one
(``pool``) and towards its own diagonal (``ridge``), then factored once by Cholesky; the
factors travel with the scoring tasks. The score is a logistic map of the Mahalanobis
log-density difference, its two constants fitted on a histogram of training differences.

No sample is taken: every labelled training row counts. Defined cases: null or empty text has
the statistics of no words; rows with a null label or null doc_id don't train; several labels
of a document each count; without two classes the score is the training share of label 1 (one half without labels);
repeated rows each get a score; an empty table gives no row; further columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD_RE, documents, id_mod, settled, sliced
from .quality_rules import count_text

FEATURES = ("log_words", "word_length", "symbols", "dup_lines", "repeats", "line_words", "upper", "marks", "stutters", "stops", "distinct", "digits")
BIN = 0.5


def features(text: str) -> list[float]:
    n, chars, symbols, dup, repeats, lines, upper, marks, stutters = count_text(text)
    words = WORD_RE.findall(text)
    share = lambda a, b: math.log((a + 0.5) / (b + 1.0))
    digits = sum(map(text.count, "0123456789"))
    return [
        math.log1p(n), math.log1p(chars / max(n, 1)), share(symbols, chars), share(dup, lines), share(repeats, n), math.log1p(n / max(lines, 1)), share(upper, chars),
        share(marks, chars), share(stutters, n), share(text.count(".") + text.count(","), n), math.log((len(set(words)) + 1.0) / (n + 1.0)) / (1.0 + math.log1p(n)), share(digits, chars),
    ]


def featurize(docs: DataFrame) -> DataFrame:
    """doc_id and x, the features of each row's whole text."""

    def run(batches):
        for b in sliced(batches):
            x = np.array([features(t or "") for t in b.column(1).to_pylist()], float).reshape(-1, len(FEATURES))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, len(FEATURES), dtype=np.int32)), pa.array(x.ravel()))], names=["doc_id", "x"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, x array<double>")


def _matrix(b: pa.RecordBatch) -> np.ndarray:
    return b.column(b.schema.get_field_index("x")).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)


@dataclass
class Discriminant:
    """means[k], factors[k] (lower Cholesky), log_det[k], prior of class 1, and the logistic constants."""

    means: list[np.ndarray]
    factors: list[np.ndarray]
    log_det: list[float]
    share: float
    slope: float = 1.0
    shift: float = 0.0

    def difference(self, x: np.ndarray) -> np.ndarray:
        """Log density of class 1 less that of class 0."""
        if not self.factors:
            return np.zeros(len(x))
        dens = []
        for m, low, det in zip(self.means, self.factors, self.log_det):
            z = np.linalg.solve(low, (x - m).T)
            dens.append(-0.5 * ((z * z).sum(0) + det))
        return dens[1] - dens[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        if not self.factors:
            return np.full(len(x), self.share)
        return 1 / (1 + np.exp(-np.clip(self.slope * np.arcsinh(self.difference(x) / 2) + self.shift, -60, 60)))


def moments(labelled: DataFrame) -> dict[int, tuple[float, np.ndarray, np.ndarray]]:
    """label -> (rows, sum x, sum x xT), added up in tasks, then in Spark by matrix cell."""
    d = len(FEATURES)

    def run(batches):
        total = {k: np.zeros((d + 1, d + 1)) for k in (0, 1)}
        for b in batches:
            y = b.column(b.schema.get_field_index("label")).to_numpy(zero_copy_only=False)
            x = np.column_stack([np.ones(b.num_rows), _matrix(b)])
            for k in (0, 1):
                total[k] += x[y == k].T @ x[y == k]
        k, i, j = np.meshgrid([0, 1], range(d + 1), range(d + 1), indexing="ij")
        yield pa.RecordBatch.from_arrays([pa.array(v.ravel().astype(np.int32)) for v in (k, i, j)] + [pa.array(np.stack([total[0], total[1]]).ravel())], names=["label", "i", "j", "v"])

    cells = labelled.mapInArrow(run, "label int, i int, j int, v double").groupBy("label", "i", "j").agg(F.sum("v").alias("v"))
    full = {k: np.zeros((d + 1, d + 1)) for k in (0, 1)}
    for r in cells.collect():  # 2 (d + 1)^2 cells
        full[r.label][r.i, r.j] = r.v
    return {k: (m[0, 0], m[0, 1:], m[1:, 1:]) for k, m in full.items()}


def fit(labelled: DataFrame, pool: float = 0.05, ridge: float = 0.02) -> Discriminant:
    """labelled: x and label (0 or 1)."""
    by = moments(labelled)
    n0, n1 = by[0][0], by[1][0]
    if min(n0, n1) < 2:
        return Discriminant([], [], [], n1 / (n0 + n1) if n0 + n1 else 0.5)
    means = [by[k][1] / by[k][0] for k in (0, 1)]
    own = [by[k][2] / by[k][0] - np.outer(means[k], means[k]) for k in (0, 1)]
    pooled = (n0 * own[0] + n1 * own[1]) / (n0 + n1)
    factors, dets = [], []
    for s in own:
        s = (1 - pool) * s + pool * pooled
        s = (1 - ridge) * s + ridge * np.diag(np.diag(s)) + 1e-4 * np.eye(len(s))
        factors.append(np.linalg.cholesky(s))
        dets.append(2 * float(np.log(np.diag(factors[-1])).sum()))
    model = Discriminant(means, factors, dets, n1 / (n0 + n1))
    model.slope, model.shift = _logistic(labelled, model)
    return model


def _logistic(labelled: DataFrame, model: Discriminant) -> tuple[float, float]:
    """Constants of the logistic map by Newton steps over a histogram of arcsinh(difference / 2)."""

    def run(batches):
        for b in batches:
            t = np.clip(np.arcsinh(model.difference(_matrix(b)) / 2), -50, 50)
            yield pa.RecordBatch.from_arrays([pa.array(np.round(t / BIN).astype(np.int32)), b.column(b.schema.get_field_index("label")).cast(pa.int32())], names=["bin", "label"])

    rows = labelled.mapInArrow(run, "bin int, label int").groupBy("bin", "label").count().collect()  # at most 2 * 201 cells
    t, y, n = (np.array(v, float) for v in zip(*[(r.bin * BIN, r.label, r["count"]) for r in rows]))
    a = np.array([1.0, 0.0])
    x = np.column_stack([t, np.ones_like(t)])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ a, -50, 50)))
        grad = x.T @ (n * (y - p)) - 0.1 * (a - [1, 0])
        step = np.linalg.solve((x * (n * p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(2), grad)
        a = a + np.clip(step, -2, 2)
        if abs(step).max() < 1e-9:
            break
    return float(max(a[0], 1e-3)), float(a[1])


def score(features_df: DataFrame, model: Discriminant) -> DataFrame:
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("doc_id")), pa.array(model.score(_matrix(b)))], names=["doc_id", "score"])

    return features_df.mapInArrow(run, f"doc_id {features_df.schema['doc_id'].dataType.simpleString()}, score double")


def train_rows(features_df: DataFrame, labels: DataFrame, held_out=None) -> DataFrame:
    known = labels.filter("quality in (0, 1)").select("doc_id", F.col("quality").cast("int").alias("label"))
    rows = features_df if held_out is None else features_df.filter(~held_out)
    return rows.join(known, "doc_id").select("x", "label")


def op7(spark, sf_dir) -> DataFrame:
    held = id_mod("doc_id", 4) == 2
    found = settled(featurize(documents(spark, sf_dir)), "quality-features")
    train = settled(train_rows(found, spark.read.parquet(f"{sf_dir}/labels.parquet"), held), "quality-train", found.count())
    scored = score(found, fit(train))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
