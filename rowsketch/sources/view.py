"""Builders of matrix views (row_id, vec) from tables.  Filters belong before them."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowsketch.functions.vectors import vec_normalise

TOKEN = "[a-z]+"
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
#: Tags counted for the page view, in the order of its columns.
TAGS = ("p", "a", "li", "div", "span", "script", "style", "h1", "h2", "h3", "img", "td", "tr", "ul", "br")


def _id(row_id: Column | str) -> Column:
    return (F.col(row_id) if isinstance(row_id, str) else row_id).cast("long").alias("row_id")


def from_columns(df: DataFrame, row_id, cols: list[str], keys: list[str] = ()) -> DataFrame:
    """Numeric columns side by side; nulls become zero."""
    return df.select(*keys, _id(row_id), F.array(*[F.coalesce(F.col(c).cast("double"), F.lit(0.0)) for c in cols]).alias("vec"))


def from_array(df: DataFrame, row_id, col: str, keys: list[str] = ()) -> DataFrame:
    kind = df.schema[col].dataType.typeName()
    vec = F.col(col).cast("array<double>")
    if kind == "vectorudt" or kind == "udt":
        from pyspark.ml.functions import vector_to_array

        vec = vector_to_array(F.col(col))
    return df.select(*keys, _id(row_id), vec.alias("vec"))


def token_bucket(token: Column, dim: int) -> Column:
    """First 8 hexadecimal digits of md5, modulo dim."""
    return F.pmod(F.conv(F.substring(F.md5(token.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(dim)).cast("int")


def tokens(df: DataFrame, row_id, col: str, keys: list[str] = ()) -> DataFrame:
    """(keys, row_id, token), a row for each occurrence of a run of letters a-z in the lower-cased text."""
    return df.select(*keys, _id(row_id), F.explode(F.regexp_extract_all(F.lower(F.col(col)), F.lit(TOKEN), F.lit(0))).alias("token"))


def from_text(df: DataFrame, row_id, col: str, dim: int = 256, norm: str = "raw", keys: list[str] = ()) -> DataFrame:
    """Hashed bag of words, counted inside each row, so that nothing is shuffled.

    A row of the table is a row of the view; texts without a token have none.
    """
    keys = list(keys)
    schema = T.StructType([*[df.schema[k] for k in keys], T.StructField("row_id", T.LongType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buckets = _Buckets(dim)
        for rb in batches:
            for at in range(0, rb.num_rows, 1024):
                part = rb.slice(at, 1024)
                dense = np.stack([buckets.count(t) for t in part.column(part.num_columns - 1).to_pylist()])
                has = dense.any(axis=1)
                dense = dense[has]
                if norm == "l2":
                    dense = dense / np.sqrt(np.einsum("ij,ij->i", dense, dense))[:, None]
                vec = pa.ListArray.from_arrays(pa.array(np.arange(0, (len(dense) + 1) * dim, dim, dtype=np.int32)), pa.array(dense.ravel()))
                yield pa.RecordBatch.from_arrays([*[c.filter(pa.array(has)) for c in part.columns[:-1]], vec], [*keys, "row_id", "vec"])

    return df.select(*keys, _id(row_id), F.col(col).cast("string").alias("_text")).mapInArrow(run, schema)


class _Buckets:
    """Words to buckets as :func:`token_bucket` has them, each word hashed once a worker."""

    MOST = 1_000_000

    def __init__(self, dim: int):
        self.dim, self.known = dim, {}
        self.find = re.compile(TOKEN).findall

    def count(self, text: str | None) -> np.ndarray:
        words = self.find((text or "").lower())
        known = self.known
        if len(known) > self.MOST:
            known.clear()
        for w in set(words).difference(known):
            known[w] = int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % self.dim
        return np.bincount(np.fromiter(map(known.__getitem__, words), np.int64, len(words)), minlength=self.dim).astype(np.float64)


def from_coo(df: DataFrame, row: str, col: str, val: str, dim: int, keys: list[str] = ()) -> DataFrame:
    """Coordinate triples, one for each cell at most, as dense rows.

    A row travels as its (at most ``dim``) entries and is spread out batch by
    batch in the kernel's own format.
    """
    packed = df.groupBy(*keys, F.col(row).cast("long").alias("row_id")).agg(F.collect_list(F.struct(F.col(col).cast("int").alias("i"), F.col(val).cast("double").alias("x"))).alias("cells"))
    return _spread(packed.select(*keys, "row_id", F.col("cells.i").alias("i"), F.col("cells.x").alias("x")), dim, list(keys))


def _spread(df: DataFrame, dim: int, keys: list[str]) -> DataFrame:
    """(keys, row_id, i array, x array) to (keys, row_id, vec); positions outside the width are left out."""
    schema = T.StructType([*[df.schema[k] for k in keys], T.StructField("row_id", T.LongType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            for at in range(0, rb.num_rows, 1024):
                part = rb.slice(at, 1024)
                i, x = part.column(part.num_columns - 2), part.column(part.num_columns - 1)
                n = part.num_rows
                rows = np.repeat(np.arange(n), i.value_lengths().to_numpy())
                place, value = i.flatten().to_numpy(), x.flatten().to_numpy()
                inside = (place >= 0) & (place < dim)
                dense = np.zeros((n, dim))
                dense[rows[inside], place[inside]] = value[inside]
                vec = pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * dim, dim, dtype=np.int32)), pa.array(dense.ravel()))
                yield pa.RecordBatch.from_arrays([*part.columns[:-2], vec], [*keys, "row_id", "vec"])

    return df.mapInArrow(run, schema)


def vocabulary(df: DataFrame, item: str) -> DataFrame:
    """(item, idx): places by item order; distinct items pass through one sorted window each partition of a range."""
    distinct = df.select(F.col(item).cast("string").alias("item")).where("item is not null").distinct()
    ranged = distinct.repartitionByRange("item").sortWithinPartitions("item").select("item", F.spark_partition_id().alias("p"), F.monotonically_increasing_id().alias("m"))
    sizes = ranged.groupBy("p").agg(F.count("*").alias("n"), F.min("m").alias("first"))
    from pyspark.sql import Window

    offsets = sizes.select("p", "first", (F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("p")) - F.col("n")).alias("offset"))
    return ranged.join(F.broadcast(offsets), "p").select("item", (F.col("offset") + F.col("m") - F.col("first")).cast("int").alias("idx"))


def from_items(df: DataFrame, row_id, item: str, places: dict[str, int]) -> DataFrame:
    """Indicator rows over a small, given vocabulary; other items are left out."""
    mapping = F.create_map(*[x for k, v in places.items() for x in (F.lit(k), F.lit(v))])
    rows = df.select(_id(row_id), F.try_element_at(mapping, F.col(item).cast("string")).alias("idx")).where("idx is not null")
    return rows.select("row_id", F.transform(F.sequence(F.lit(0), F.lit(len(places) - 1)), lambda i: F.when(i == F.col("idx"), 1.0).otherwise(0.0)).alias("vec"))


def from_pivot(df: DataFrame, row_id, column: str, values: tuple, amount: str) -> DataFrame:
    """Sums of ``amount`` by the given values of ``column``."""
    wide = df.groupBy(_id(row_id)).pivot(column, list(values)).agg(F.sum(F.col(amount).cast("double")))
    return wide.select("row_id", F.array(*[F.coalesce(F.col(f"`{v}`"), F.lit(0.0)) for v in values]).alias("vec"))


def from_sparse(df: DataFrame, row_id, idx: str, val: str, dim: int) -> DataFrame:
    """(idx array<int>, val array<double>) rows as dense rows."""
    return _spread(df.select(_id(row_id), F.col(idx).cast("array<int>").alias("i"), F.col(val).cast("array<double>").alias("x")), dim, [])


def moments(view: DataFrame, d: int) -> DataFrame:
    """One row: n, and arrays of the columns' means and (population) deviations."""
    aggs = [F.count("*").alias("n")]
    aggs += [F.avg(F.col("vec")[i]).alias(f"m{i}") for i in range(d)] + [F.stddev_pop(F.col("vec")[i]).alias(f"s{i}") for i in range(d)]
    one = view.agg(*aggs)
    return one.select("n", F.array(*[f"m{i}" for i in range(d)]).alias("means"), F.array(*[f"s{i}" for i in range(d)]).alias("deviations"))


def standardise(view: DataFrame, d: int) -> DataFrame:
    """Zero mean and unit deviation; constant columns become zero. The moments are one row and are broadcast."""
    m = moments(view, d)
    keep = [c for c in view.columns if c != "vec"]
    scaled = F.transform("vec", lambda x, i: F.when(F.col("deviations")[i] > 0, (x - F.col("means")[i]) / F.col("deviations")[i]).otherwise(0.0))
    return view.crossJoin(F.broadcast(m)).select(*keep, scaled.alias("vec"))


def center(view: DataFrame, d: int) -> DataFrame:
    m = moments(view, d)
    keep = [c for c in view.columns if c != "vec"]
    return view.crossJoin(F.broadcast(m)).select(*keep, F.zip_with("vec", "means", lambda x, y: x - y).alias("vec"))


def l2(view: DataFrame) -> DataFrame:
    keep = [c for c in view.columns if c != "vec"]
    return view.select(*keep, vec_normalise("vec").alias("vec"))


def tfidf(view: DataFrame, d: int) -> DataFrame:
    """Counts weighted by ln((1 + n) / (1 + rows with the entry)) + 1; the weights are one row."""
    weights = view.agg(F.count("*").alias("n"), *[F.sum((F.col("vec")[i] > 0).cast("double")).alias(f"c{i}") for i in range(d)])
    weights = weights.select(F.array(*[F.log((1 + F.col("n")) / (1 + F.col(f"c{i}"))) + 1 for i in range(d)]).alias("w"))
    keep = [c for c in view.columns if c != "vec"]
    return view.crossJoin(F.broadcast(weights)).select(*keep, F.zip_with("vec", "w", lambda x, w: x * w).alias("vec"))


def clean(view: DataFrame, how: str = "skip") -> DataFrame:
    """Null and not finite entries in the JVM: 'skip' drops such rows, 'zero' fills them."""
    if how == "skip":
        return view.where("vec is not null and forall(vec, x -> x is not null and not isnan(x) and abs(x) < double('infinity'))")
    fixed = F.transform("vec", lambda x: F.when(x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")), 0.0).otherwise(x))
    return view.where("vec is not null").select(*[c for c in view.columns if c != "vec"], fixed.alias("vec"))


# the views of the given tables


def emb(embeddings: DataFrame, keys: list[str] = ()) -> DataFrame:
    return from_array(embeddings, "vec_id", "embedding", keys)


NUMBERS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def num(lineitem: DataFrame, keys: list[str] = ()) -> DataFrame:
    """Raw numeric columns; lineitem has no key, so the id is a hash and may repeat."""
    return from_columns(lineitem, F.xxhash64(*lineitem.columns), NUMBERS, keys)


def evt(events: DataFrame, keys: list[str] = ()) -> DataFrame:
    """The value in the slot of its event type."""
    slots = [F.when(F.col("event_type") == t, F.coalesce(F.col("value"), F.lit(0.0))).otherwise(0.0) for t in EVENT_TYPES]
    return events.select(*keys, _id("event_id"), F.array(*slots).alias("vec"))


def cust(orders: DataFrame) -> DataFrame:
    return from_pivot(orders, "o_custkey", "o_orderpriority", PRIORITIES, "o_totalprice")


def brands() -> tuple[str, ...]:
    return tuple(f"Brand#{a}{b}" for a in range(1, 6) for b in range(1, 6))


def pivot(lineitem: DataFrame, part: DataFrame) -> DataFrame:
    joined = lineitem.join(part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return from_pivot(joined, "l_suppkey", "p_brand", brands(), "l_quantity")


def doc(documents: DataFrame, dim: int = 256, norm: str = "l2") -> DataFrame:
    return from_text(documents, "doc_id", "text", dim, norm)


def conv(conversations: DataFrame, dim: int = 64) -> DataFrame:
    rows = conversations.withColumn("_row", F.xxhash64("conv_id", "turn"))
    return from_text(rows, "_row", "text", dim, "raw", ["role"])


def page(pages: DataFrame) -> DataFrame:
    counts = [F.regexp_count(F.lower("html"), F.lit(f"<{t}[ >/]")).cast("double") for t in TAGS]
    return pages.select(_id("page_id"), F.array(*counts, F.length("html").cast("double")).alias("vec"))
