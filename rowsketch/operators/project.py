"""Low-rank projection of a view on a sketch's directions, and what is built on it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowsketch.functions.vectors import vec_norm2
from rowsketch.operators.dist import sketch, vectors
from rowsketch.operators.sketch import Sketch
from rowsketch.sources import view


def project(df: DataFrame, sk: Sketch, k: int, output: str = "coords", path: str = "arrow") -> DataFrame:
    """(row_id, coords) or (row_id, approx): rows on the leading k directions.

    The directions are d x k numbers in the task's closure.
    """
    v = sk.directions(k)
    keep = [c for c in df.columns if c != "vec"]
    if path == "sql":
        coords = F.array(*[_dot(v[:, c]) for c in range(v.shape[1])])
        return df.select(*keep, coords.alias("coords"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            x = vectors(rb.column(rb.num_columns - 1), len(v))
            y = x @ v if output == "coords" else (x @ v) @ v.T
            yield pa.RecordBatch.from_arrays([*rb.columns[:-1], pa.array(list(y), pa.list_(pa.float64()))], [*keep, output])

    from pyspark.sql import types as T

    schema = T.StructType([df.schema[c] for c in keep] + [T.StructField(output, T.ArrayType(T.DoubleType()))])
    return df.select(*keep, "vec").mapInArrow(run, schema)


def _dot(direction: np.ndarray) -> Column:
    fixed = F.array(*[F.lit(float(x)) for x in direction])
    return F.aggregate(F.zip_with("vec", fixed, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def residuals(df: DataFrame, sk: Sketch, k: int) -> DataFrame:
    """(row_id, norm2, residual): what the projection leaves of each row."""
    kept = [c for c in df.columns if c != "vec"]
    both = project(df.select(*kept, "vec", F.col("vec").alias("v0")).select(*kept, "v0", "vec"), sk, k)
    return both.select(*kept, vec_norm2("v0").alias("norm2"), F.greatest(F.lit(0.0), vec_norm2("v0") - vec_norm2("coords")).alias("residual"))


def residual_norm_udf(sk: Sketch, k: int):
    """The residual as a scalar pandas function."""
    v = sk.directions(k)

    @F.pandas_udf("double")
    def residual_norm(col: pd.Series) -> pd.Series:
        x = np.stack(col.to_numpy())
        y = x @ v
        return pd.Series(np.sqrt(np.maximum((x * x).sum(1) - (y * y).sum(1), 0)))

    return residual_norm


def pca(df: DataFrame, k: int, d: int, ell: int | None = None) -> tuple[Sketch, DataFrame]:
    """Principal components by sketching the centred view; the sketch and (row_id, coords)."""
    centred = view.center(df, d)
    sk = Sketch.from_df(sketch(centred, ell or max(2 * k, k + 10), d=d))
    return sk, project(centred, sk, k)


#: Queries that one pass over the documents answers.
QUERIES = 10_000


def lsi(documents: DataFrame, queries: DataFrame, *, dim: int = 256, ell: int = 64, k: int = 20, top: int = 5, block: int = QUERIES) -> DataFrame:
    """(query_id, row_id, rank, score): nearest documents in the space of the sketched, tf-idf weighted words.

    ``queries`` (item_id, text) go through the documents ``block`` at a time; a
    task keeps the best of each query only, so no pair beyond these leaves it.
    """
    docs = view.tfidf(view.from_text(documents, "doc_id", "text", dim), dim)
    docs = view.l2(docs)
    sk = Sketch.from_df(sketch(docs, ell, d=dim))
    asked = project(view.from_text(queries, "item_id", "text", dim, "l2"), sk, k)
    coords = project(docs, sk, k)
    best = None
    held: list = []
    for r in asked.toLocalIterator():
        held.append(r)
        if len(held) == block:
            part = _nearest(coords, held, top)
            best, held = part if best is None else best.unionByName(part), []
    if held or best is None:
        part = _nearest(coords, held, top)
        best = part if best is None else best.unionByName(part)
    from pyspark.sql import Window

    ranked = best.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "row_id")))
    return ranked.where(F.col("rank") <= top)


def _nearest(coords: DataFrame, asked: list, top: int) -> DataFrame:
    """(query_id, row_id, score): each task's best rows for each query."""
    ids = np.array([r["row_id"] for r in asked], np.int64)
    q = np.array([r["coords"] for r in asked], np.float64).reshape(len(ids), -1 if len(ids) else 0)
    q = q / np.maximum(np.sqrt(np.einsum("ij,ij->i", q, q)), 1e-300)[:, None]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, score = np.zeros((len(ids), 0), np.int64), np.zeros((len(ids), 0))
        for rb in batches:
            for at in range(0, rb.num_rows if len(ids) else 0, 1024):
                part = rb.slice(at, 1024)
                x = vectors(part.column(1), q.shape[1])
                s = q @ (x / np.maximum(np.sqrt(np.einsum("ij,ij->i", x, x)), 1e-300)[:, None]).T
                score = np.concatenate([score, s], axis=1)
                rows = np.concatenate([rows, np.broadcast_to(part.column(0).to_numpy(), s.shape)], axis=1)
                order = np.lexsort((rows, -score), axis=1)[:, :top]
                score, rows = np.take_along_axis(score, order, 1), np.take_along_axis(rows, order, 1)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, rows.shape[1])), pa.array(rows.ravel()), pa.array(score.ravel())], ["query_id", "row_id", "score"])

    return coords.select("row_id", "coords").mapInArrow(run, "query_id long, row_id long, score double")


def kmeans(coords: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """(row_id, cluster) of projected rows."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = coords.select("row_id", array_to_vector("coords").alias("features"))
    model = KMeans(k=k, seed=seed, maxIter=20).fit(rows)
    return model.transform(rows).select("row_id", F.col("prediction").alias("cluster"))
