"""Quality classifier: regularised quadratic discriminant over document statistics.

Each class has a Gaussian over transformed statistics of a text.  A class's
covariance is shrunk towards its diagonal and towards the pooled covariance;
the inverse of its Cholesky factor is kept with the model, so a score costs one
product with a triangular matrix a class.  The score is the logistic of the Mahalanobis log-density
difference plus the log prior odds.

Fitting reads every labelled training row: each task adds up counts, sums and
products of its rows, a few hundred numbers a class, so the fit has no sample
and no bound.  Labels, language, source and id are never inputs of a score.

Null and empty texts have defined statistics (all zero counts) and are scored
like others; rows with equal text get equal scores; labels that are null or
neither 0 nor 1 are passed over, and a repeated label row counts again; without
rows of both classes the score is the share of label 1 (0.5 if none); an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import fold_of, free_name, named, release, text_bytes
from rowsketch.shared import materialise

FOLDS = 3
HELD_OUT = 1
THRESHOLD = 0.5
#: Weight of the diagonal, and of the pooled covariance, in a class's covariance.
SHRINK_DIAGONAL = 0.1
SHRINK_POOLED = 0.1
#: Least variance of a statistic.
FLOOR = 0.05

_UPPER = bytes(range(65, 91))
_DIGIT = bytes(range(48, 58))
_SYMBOL = b"#*$%&<>@^~_=+\\{}[]"
_LOWER = bytes(range(97, 123))
_HIGH = bytes(range(128, 256))
STATISTICS = ("log_words", "word_bytes", "symbols", "capitals", "digits", "exclamations", "bars", "stops", "high_bytes", "distinct_words", "repeated_lines", "line_words", "repeated_pairs")


def statistics(text: bytes) -> list[float]:
    """Transformed statistics of one UTF-8 text, in the order of ``STATISTICS``."""
    words = text.split()
    n = len(words)
    size = len(text)
    kept = lambda drop: size - len(text.translate(None, drop))
    letters = kept(_LOWER) + (upper := kept(_UPPER)) + (high := kept(_HIGH))
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    rate = lambda count, of: float(np.log((count + 0.5) / (of + 1.0)))
    pairs = len(set(zip(words, words[1:])))
    return [
        float(np.log1p(n)),
        float(np.log1p(sum(map(len, words)) / n)) if n else 0.0,
        rate(kept(_SYMBOL), n),
        rate(upper, letters),
        rate(kept(_DIGIT), size),
        rate(text.count(b"!"), n),
        rate(text.count(b"|"), n),
        rate(text.count(b".") + text.count(b","), n),
        rate(high, letters),
        rate(n - len(set(words)), n),
        rate(len(lines) - len(set(lines)), len(lines)),
        float(np.log1p(n / max(1, len(lines)))),
        rate(max(0, n - 1 - pairs), n),
    ]


def features(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, x): the statistics of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            x = [statistics(t.as_buffer().to_pybytes()) for t in rb.column(1)]
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(x, pa.list_(pa.float64()))], ["doc_id", "x"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_bytes(text).alias("text")).mapInArrow(run, "doc_id long, x array<double>")


@dataclass
class Discriminant:
    """Means, Cholesky factors of the covariances and log priors of classes 0 and 1."""

    means: list[np.ndarray]
    factors: list[np.ndarray]
    log_priors: list[float]
    share: float
    inverses: list[np.ndarray] = field(init=False)

    def __post_init__(self) -> None:
        self.inverses = [np.linalg.inv(c) for c in self.factors]

    def score(self, x: np.ndarray) -> np.ndarray:
        if not self.means:
            return np.full(len(x), self.share)
        logs = []
        for m, c, inverse, p in zip(self.means, self.factors, self.inverses, self.log_priors):
            z = inverse @ (x - m).T  # Mahalanobis distance through the cached factor
            logs.append(p - np.log(np.diag(c)).sum() - 0.5 * (z * z).sum(axis=0))
        return 1.0 / (1.0 + np.exp(np.clip(logs[0] - logs[1], -500, 500)))


def fit_from_sums(n: np.ndarray, sums: np.ndarray, products: np.ndarray, shrink_diagonal: float = SHRINK_DIAGONAL, shrink_pooled: float = SHRINK_POOLED, floor: float = FLOOR) -> Discriminant:
    """n (2,), sums (2, d) and products (2, d, d) of the classes' rows."""
    share = float(n[1] / n.sum()) if n.sum() else 0.5
    if (n < 2).any():
        return Discriminant([], [], [], share)
    means = [sums[k] / n[k] for k in (0, 1)]
    own = [products[k] / n[k] - np.outer(means[k], means[k]) for k in (0, 1)]
    pooled = (n[0] * own[0] + n[1] * own[1]) / n.sum()
    factors = []
    for c in own:
        c = (1 - shrink_pooled) * c + shrink_pooled * pooled
        c = (1 - shrink_diagonal) * c + shrink_diagonal * np.diag(np.diag(c))
        factors.append(np.linalg.cholesky(c + floor * np.eye(len(c))))
    return Discriminant(means, factors, [float(np.log(v / n.sum())) for v in n], share)


def fit(rows: DataFrame, labels: DataFrame, *, label: str = "quality", folds: int = FOLDS, held_out: int = HELD_OUT) -> Discriminant:
    """Fits on all labelled rows of :func:`features` outside the held-out fold."""
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("y in (0, 1)").where(fold_of(F.col("doc_id"), folds) != held_out)
    d = len(STATISTICS)

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, p = np.zeros(2), np.zeros((2, d)), np.zeros((2, d, d))
        for rb in batches:
            if not rb.num_rows:
                continue
            y = rb.column(0).to_numpy()
            x = rb.column(1).flatten().to_numpy().reshape(-1, d)
            for k in (0, 1):
                own = x[y == k]
                n[k] += len(own)
                s[k] += own.sum(axis=0)
                p[k] += own.T @ own
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([n, s.ravel(), p.ravel()]).tolist()], pa.list_(pa.float64()))], ["sums"])

    parts = rows.join(marks, "doc_id").select("y", "x").mapInArrow(add, "sums array<double>")
    # a row of fixed length for each task, added up by position
    total = parts.select(F.posexplode("sums")).groupBy("pos").agg(F.sum("col").alias("v")).orderBy("pos").collect()
    v = np.array([r["v"] for r in total]) if total else np.zeros(2 + 2 * d + 2 * d * d)
    return fit_from_sums(v[:2], v[2 : 2 + 2 * d].reshape(2, d), v[2 + 2 * d :].reshape(2, d, d))


def score(docs: DataFrame, labels: DataFrame, *, label: str = "quality", folds: int = FOLDS, held_out: int = HELD_OUT, threshold: float = THRESHOLD, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) for every document."""
    rows = materialise(features(docs, doc_id=doc_id, text=text), "statistics")
    model = fit(rows, labels, label=label, folds=folds, held_out=held_out)
    return _apply(rows, model, folds, held_out, threshold)


def _apply(rows: DataFrame, model: Discriminant, folds: int, held_out: int, threshold: float) -> DataFrame:
    d = len(STATISTICS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            x = rb.column(1).flatten().to_numpy().reshape(-1, d)
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(model.score(x))], ["doc_id", "score"])

    scored = rows.select("doc_id", "x").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", (fold_of(F.col("doc_id"), folds) == held_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, *, label: str = "quality", folds: int = FOLDS, held_out: int = HELD_OUT, threshold: float = THRESHOLD, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents, whole and unchanged, that the classifier does not reject.

    The statistics are computed once and written beside the documents; Python
    sees texts, and later statistics, but no other column.
    """
    mark = free_name(docs.columns, "statistics")

    @F.arrow_udf("array<double>")
    def measured(texts: pa.Array) -> pa.Array:
        out = pa.array([statistics(t.as_buffer().to_pybytes()) for t in texts], pa.list_(pa.float64()))
        release()
        return out

    marked = materialise(docs.select(*[named(c) for c in docs.columns], measured(text_bytes(text)).alias(mark)), "measured")
    model = fit(marked.select(named(doc_id).cast("long").alias("doc_id"), named(mark).alias("x")), labels, label=label, folds=folds, held_out=held_out)

    @F.arrow_udf("boolean")
    def good(x: pa.Array) -> pa.Array:
        return pa.array(model.score(x.flatten().to_numpy().reshape(len(x), -1)) >= threshold)

    return marked.where(good(named(mark))).select(*[named(c) for c in docs.columns])
