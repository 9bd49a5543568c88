r"""Quality scores by a regularised quadratic discriminant over transformed document statistics.

A scan turns each whole text into a dozen statistics (lengths, shares of kinds of characters and words, repetition,
compressibility), log- or logit-transformed so that they are near to normal. Both classes get a mean and a covariance that
is shrunk towards the pooled covariance and the identity; the Cholesky factors are computed once and kept, so a score is
two triangular products per row. The difference of the Mahalanobis log densities is calibrated to a probability on the
training rows.

The fit uses at most `max_fit` labelled rows, those with the least id hash (a documented bound; every row is scored). Results for odd input: null text counts as empty and gets
the score of the empty text; rows without labels are scored like any other; repeated rows are scored row by row; labels
that are null are not used; an empty document table gives no rows; without labels of both
classes every score is 0.5 and no row is predicted good, but reject_low_quality, which has nothing to go by then, keeps all rows.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Stored, slices, without

#: Largest number of labelled rows that the fit sees.
MAX_FIT = 200_000
#: Shrinkage towards the pooled covariance and towards the identity; the score from which a row counts as good.
POOL, RIDGE, CUT = 0.15, 0.05, 0.7
#: Words of a text whose statistics count half in square.
SHORT = 60.0

_UPPER, _DIGIT = bytes(range(65, 91)), bytes(range(48, 58))
_ODD = b"#$%&*|!<>{}[]=_~^@\\/+"
_POINT = b".,;:?'\"()-"
NAMES = ("words", "word_length", "variety", "upper", "digit", "odd", "point", "beyond_ascii", "breaks", "repeated_lines", "top_word", "odd_words", "packed", "stops", "one_length", "repeated_pairs")


def _odds(part: float, whole: float) -> float:
    return float(np.log((part + 0.5) / (max(whole - part, 0) + 0.5)))


def statistics(text: bytes) -> list[float]:
    """Transformed statistics of one whole text, in the order of NAMES."""
    n, words = len(text), text.split()
    w = len(words)
    counts = Counter(words)
    lines = text.split(b"\n")
    upper, digit, odd, point = (n - len(text.translate(None, s)) for s in (_UPPER, _DIGIT, _ODD, _POINT))
    letters = sum(map(len, words))
    odd_words = sum(c for x, c in counts.items() if x[-1] in _ODD)
    stops = text.count(b". ") + text.count(b".\n") + text.endswith(b".")
    pairs = len(set(zip(words, words[1:], strict=False)))
    lengths = Counter(map(len, words))
    return [
        float(np.log1p(w)),
        float(np.log((letters + 1) / (w + 1))),
        float(np.log((len(counts) + 1) / (w + 1) ** 0.75)),
        _odds(upper, letters),
        _odds(digit, letters),
        _odds(odd, letters),
        _odds(point, letters),
        _odds(sum(map(text.count, (b"\xc3", b"\xc2", b"\xe2"))), letters),
        _odds(len(lines) - 1, w),
        _odds(len(lines) - len(set(lines)), len(lines)),
        _odds(max(counts.values(), default=0), w),
        _odds(odd_words, w),
        float(np.log((len(zlib.compress(text, 1)) + 8) / (n + 8))),
        _odds(stops, w),
        _odds(max(lengths.values(), default=0), w),
        _odds(max(w - 1, 0) - pairs, max(w - 1, 0)),
    ]


def features(docs: DataFrame, *keys: str) -> DataFrame:
    """doc_id, the key columns asked for, x (array of len(NAMES) doubles)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows = [statistics(t or b"") for t in b.column(1).cast(pa.binary()).to_pylist()]
            own = [b.column(0), *b.columns[2:]]
            yield pa.RecordBatch.from_arrays([*own, pa.array(rows, pa.list_(pa.float64()))], names=["doc_id", *keys, "x"])

    return docs.select("doc_id", "text", *keys).mapInArrow(run, T.StructType([docs.schema["doc_id"], *(docs.schema[k] for k in keys), T.StructField("x", T.ArrayType(T.DoubleType()))]))


def standard(x: np.ndarray, centre: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Standardised statistics; those of short texts, which vary most, are drawn towards the centre."""
    words = np.expm1(x[:, :1])
    return np.clip((x - centre) / scale, -12, 12) * (words / (words + SHORT)) ** 0.5


@dataclass
class Discriminant:
    """Two Gaussians over standardised statistics with cached factors, and the calibration of their log ratio."""

    centre: np.ndarray
    scale: np.ndarray
    means: list[np.ndarray]
    whiten: list[np.ndarray]
    log_det: list[float]
    slope: float = 1.0
    offset: float = 0.0

    def log_ratio(self, x: np.ndarray) -> np.ndarray:
        z = standard(x, self.centre, self.scale)
        dens = [-0.5 * (((z - m) @ w) ** 2).sum(axis=1) - 0.5 * d for m, w, d in zip(self.means, self.whiten, self.log_det, strict=True)]
        return dens[1] - dens[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.log_ratio(x) + self.offset, -40, 40)))


def fit(x: np.ndarray, y: np.ndarray, pool: float = POOL, ridge: float = RIDGE) -> Discriminant | None:
    """None unless both classes have rows."""
    if len(np.unique(y)) < 2:
        return None
    centre, scale = x.mean(axis=0), x.std(axis=0) + 1e-6
    z = standard(x, centre, scale)
    parts = [z[y == c] for c in (0, 1)]
    means = [p.mean(axis=0) for p in parts]
    scatter = [(p - m).T @ (p - m) for p, m in zip(parts, means, strict=True)]
    pooled = sum(scatter) / len(z)
    whiten, log_det = [], []
    for p, s in zip(parts, scatter, strict=True):
        cov = (1 - pool) * s / len(p) + pool * pooled
        cov = (1 - ridge) * cov + ridge * np.trace(cov) / len(cov) * np.eye(len(cov))
        low = np.linalg.cholesky(cov)
        whiten.append(np.linalg.inv(low).T)
        log_det.append(float(2 * np.log(np.diag(low)).sum()))
    out = Discriminant(centre, scale, means, whiten, log_det)
    r = np.clip(out.log_ratio(x), -60, 60)
    a, b = 0.3, 0.0  # calibration: two-parameter logistic regression by damped Newton steps
    for _ in range(50):
        p = 1 / (1 + np.exp(-(a * r + b)))
        v = p * (1 - p) + 1e-9
        g = np.array([((y - p) * r).sum() - 1e-3 * a, (y - p).sum()])
        hess = np.array([[(v * r * r).sum() + 1e-3, (v * r).sum()], [(v * r).sum(), v.sum() + 1e-6]])
        step = np.linalg.solve(hess, g)
        a, b = a + float(np.clip(step[0], -0.5, 0.5)), b + float(np.clip(step[1], -2, 2))
        if np.abs(step).max() < 1e-8:
            break
    out.slope, out.offset = max(a, 1e-3), b
    return out


def held_out() -> Column:
    """Rows that the fit never sees: those whose id's CRC has remainder 2 by 4."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def train(stats: DataFrame, labels: DataFrame, max_fit: int = MAX_FIT) -> Discriminant | None:
    """Fit on the labelled rows of stats (doc_id, x) that aren't held out."""
    good = labels.where(F.col("quality").isin(0, 1)).groupBy("doc_id").agg(F.max("quality").alias("y"))
    known = stats.where(~held_out()).join(good, "doc_id")
    known = Stored(known.withColumn("o", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20))), "known").df
    n = known.count()
    if n > max_fit:
        known = known.where(F.col("o") < int((1 << 20) * max_fit / n))
    rows = known.select("x", "y").toPandas()
    if rows.empty:
        return None
    return fit(np.array(rows["x"].tolist()), rows["y"].to_numpy())


def _scorer(spark: SparkSession, model: Discriminant | None):  # noqa: ANN202
    held = spark.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def score(x: pa.Array) -> pa.Array:
        if held.value is None or not len(x):
            return pa.array(np.full(len(x), 0.5))
        return pa.array(held.value.score(np.asarray(x.flatten()).reshape(len(x), -1)))

    return score


def quality_scores(docs: DataFrame, labels: DataFrame, max_fit: int = MAX_FIT) -> DataFrame:
    """doc_id, held_out, score, predicted: a row per input row."""
    stats = Stored(features(docs), "stats").df
    score = _scorer(docs.sparkSession, train(stats, labels, max_fit))
    out = stats.select("doc_id", held_out().alias("held_out"), score("x").alias("score"))
    return out.withColumn("predicted", (F.col("score") >= CUT).cast("int"))


def reject_low_quality(docs: DataFrame, labels: DataFrame, max_fit: int = MAX_FIT) -> DataFrame:
    """The rows of docs whose score reaches CUT, all columns: only texts that may be rejected are exchanged. Without labels of both
    classes there is no model, and nothing is rejected."""
    keyed = docs.select("doc_id", "text", F.xxhash64("text").alias("th"))
    stats = Stored(features(keyed, "th"), "stats").df
    model = train(stats, labels, max_fit)
    if model is None:
        return docs
    score = _scorer(docs.sparkSession, model)
    return without(docs, Stored(stats.where(score("x") < CUT).select("doc_id", "th").distinct(), "rejected").df)
