"""Quality by a regularised quadratic discriminant over document statistics.

Every whole text gives a vector of transformed statistics. Each class has a mean and a covariance, shrunk towards a multiple of the identity; the score is the logistic of the
difference of the two log densities (by Mahalanobis distances through Cholesky factors, computed once) and of the log prior, through a slope and an offset that fit the training rows.

The fit reads at most TRAIN_ROWS labelled rows, those with the least hash of their id, never the held-out ones. Labels, language, source and id are no inputs of a score.

Defined results: a null text counts as empty; with no rows of one class the score is the share of label 1 (0.5 without rows); null labels are not used; repeated rows score alike; an empty table gives an empty table.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import id_and_text, per_batch, read

TRAIN_ROWS, FOLDS, HELD_OUT, CUT, SHRINK, CLIP = 20_000, 5, 0, 0.3, 0.05, 40.0

#: Frequent function words of English, German, French and Spanish.
COMMON = frozenset(b"the of and to in a is that for it was on are with as be by at from this der die und das ist ein eine nicht mit den von zu le la les et de des un une est que pour dans en qui sur el los las y del se por con su".split())
_LETTER = np.array([chr(i).isalpha() and i < 128 or i >= 128 for i in range(256)])
_UPPER = np.array([65 <= i <= 90 for i in range(256)])
_DIGIT = np.array([48 <= i <= 57 for i in range(256)])
_STOP = np.array([chr(i) in ".,;:!?'\"-()" for i in range(256)])
_BLANK = np.array([i == 32 or 9 <= i <= 13 for i in range(256)])
_SYMBOL = ~(_LETTER | _DIGIT | _STOP | _BLANK)
CHUNK = 1 << 20


def statistics(text: str) -> list[float]:
    """Transformed statistics of one text: lengths as logs, shares as square roots."""
    data = text.encode()
    n = max(1, len(data))
    hist = np.zeros(256)
    for at in range(0, len(data), CHUNK):
        hist += np.bincount(np.frombuffer(data, np.uint8, min(CHUNK, len(data) - at), at), minlength=256)
    words, lines = data.split(), data.split(b"\n")
    w = max(1, len(words))
    p = hist[hist > 0] / n
    share = lambda mask: float(np.sqrt(hist[mask].sum() / n))
    return [
        float(np.log1p(len(data))),
        float(np.log1p((n - hist[_BLANK].sum()) / w)),
        share(_UPPER),
        share(_DIGIT),
        share(_STOP),
        share(_SYMBOL),
        float(np.sqrt(len(set(words)) / w)),
        float(np.sqrt(sum(map(COMMON.__contains__, words)) / w)),
        float(np.log1p(len(data) / len(lines))),
        float(np.sqrt(1 - len(set(lines)) / len(lines))),
        float(np.sqrt(hist[46] / w)),
        float(-(p * np.log(p)).sum()) if len(data) else 0.0,
    ]


@dataclass
class Discriminant:
    """Means, inverse Cholesky factors and log determinants of both classes, the prior's log odds, and the logistic over margins."""

    centre: np.ndarray
    scale: np.ndarray
    means: list[np.ndarray]
    factors: list[np.ndarray]
    log_dets: list[float]
    prior: float
    slope: float = 1.0
    offset: float = 0.0
    constant: float | None = None

    def margin(self, x: np.ndarray) -> np.ndarray:
        z = (x - self.centre) / self.scale
        density = [-0.5 * ((z - m) @ f.T).__pow__(2).sum(1) - 0.5 * d for m, f, d in zip(self.means, self.factors, self.log_dets, strict=True)]
        return density[1] - density[0] + self.prior

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        return 1 / (1 + np.exp(-(self.slope * np.clip(self.margin(x), -CLIP, CLIP) + self.offset)))


def fit(x: np.ndarray, y: np.ndarray, shrink: float = SHRINK) -> Discriminant:
    """A discriminant from rows of statistics and 0/1 labels."""
    d = x.shape[1] if x.ndim == 2 else 1
    if min((y == 0).sum(), (y == 1).sum()) < 2:
        share = float(y.mean()) if len(y) else 0.5
        return Discriminant(np.zeros(d), np.ones(d), [], [], [], 0.0, constant=share)
    centre, scale = x.mean(0), x.std(0) + 1e-6
    z = (x - centre) / scale
    means, factors, dets = [], [], []
    for label in (0, 1):
        rows = z[y == label]
        means.append(rows.mean(0))
        cov = np.cov(rows.T, bias=True).reshape(d, d)
        cov = (1 - shrink) * cov + shrink * max(np.trace(cov) / d, 1e-3) * np.eye(d)
        low = np.linalg.cholesky(cov)
        factors.append(np.linalg.inv(low))
        dets.append(2 * float(np.log(np.diag(low)).sum()))
    model = Discriminant(centre, scale, means, factors, dets, float(np.log((y == 1).sum() / (y == 0).sum())))
    model.slope, model.offset = calibrated(model.margin(x), y)
    return model


def calibrated(margin: np.ndarray, y: np.ndarray, ridge: float = 1e-4) -> tuple[float, float]:
    """Slope and offset of the logistic that fits clipped margins to labels, by Newton steps; both classes weigh the same."""
    x = np.stack([np.clip(margin, -CLIP, CLIP), np.ones(len(y))], 1)
    weight, theta = np.where(y == 1, 0.5 / (y == 1).sum(), 0.5 / (y == 0).sum()), np.array([0.1, 0.0])
    loss = lambda t: (weight * np.logaddexp(0, np.where(y == 1, -1, 1) * (x @ t))).sum() + ridge / 2 * t @ t
    for _ in range(100):
        p = 1 / (1 + np.exp(-(x @ theta)))
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + ridge * np.eye(2), x.T @ (weight * (p - y)) + ridge * theta)
        size = next((2.0**-k for k in range(30) if loss(theta - 2.0**-k * step) <= loss(theta)), 0)
        theta = theta - size * step
        if np.abs(size * step).max() < 1e-9:
            break
    return float(theta[0]), float(theta[1])


def held_out(folds: int = FOLDS, left: int = HELD_OUT) -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds == left


def labelled(docs: DataFrame, labels: DataFrame, label: str, folds: int, left: int, rows: int) -> DataFrame:
    """(text, label): at most `rows` labelled texts outside the held-out fold, those with the least hash of their id."""
    some = labels.filter(F.col(label).isin(0, 1) & ~held_out(folds, left)).select(F.col("doc_id").alias("key"), F.col(label).cast("int").alias("label"))
    some = some.orderBy(F.xxhash64("key"), "label").limit(rows)
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(some), F.col("doc_id") == F.col("key")).select("doc_id", "text", "label")


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> Discriminant:
    """Fits on the labelled rows; their statistics, not their texts, come to the driver."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = pa.array([statistics(t) for t in batch["text"].to_pylist()], pa.list_(pa.float64()))
        return pa.RecordBatch.from_arrays([batch["doc_id"], x, batch["label"]], ["doc_id", "x", "label"])

    some = labelled(docs.withColumn("doc_id", F.col("doc_id").cast("long")), labels, "quality", FOLDS, HELD_OUT, rows)
    got = sorted(per_batch(some, make, "doc_id long, x array<double>, label int").limit(rows).collect())  # sorted: the same sums each time
    return fit(np.array([r.x for r in got]), np.array([r.label for r in got]))


def scores(docs: DataFrame, model: Discriminant, cut: float = CUT) -> DataFrame:
    """(doc_id, score, predicted) of every whole text."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        s = model.score(np.array([statistics(t) for t in batch["text"].to_pylist()]))
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(s, pa.float64()), pa.array((s >= cut).astype(np.int32))], ["doc_id", "score", "predicted"])

    return per_batch(id_and_text(docs), make, "doc_id long, score double, predicted int")


def accepted(docs: DataFrame, model: Discriminant, cut: float = CUT) -> DataFrame:
    """The documents that the classifier keeps, with all their columns."""

    @F.pandas_udf("double")
    def score(text):  # noqa: ANN001, ANN202
        import pandas as pd

        return pd.Series(model.score(np.array([statistics(t or "") for t in text]).reshape(len(text), -1)))

    return docs.filter(score(F.col("text")) >= cut)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    out = scores(docs, train(docs, read(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out().alias("held_out"), "score", "predicted")
