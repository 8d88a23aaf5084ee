"""Vector helpers as Column expressions over arrays; they run in the JVM."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _col(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def vec_dot(a, b) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm2(a) -> Column:
    """Squared length."""
    return F.aggregate(_col(a), F.lit(0.0), lambda s, x: s + x * x)


def vec_scale(a, c) -> Column:
    c = _col(c) if isinstance(c, (str, Column)) else F.lit(float(c))
    return F.transform(_col(a), lambda x: x * c)


def vec_add(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def vec_normalise(a) -> Column:
    n = F.sqrt(vec_norm2(a))
    return F.when(n > 0, F.transform(_col(a), lambda x: x / n)).otherwise(_col(a))


def cosine(a, b) -> Column:
    n = F.sqrt(vec_norm2(a) * vec_norm2(b))
    return F.when(n > 0, vec_dot(a, b) / n)


def register(spark: SparkSession) -> None:
    """SQL names for the helpers, as SQL functions, and the sketch table functions."""
    from rowsketch.functions.udtf import ShrinkSketchTable, SketchRows
    from pyspark.sql.functions import udtf

    for name, args, body in (
        ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
        ("vec_norm2", "a ARRAY<DOUBLE>", "aggregate(a, 0D, (s, x) -> s + x * x)"),
        ("quad_lo", "rows ARRAY<ARRAY<DOUBLE>>, x ARRAY<DOUBLE>", "aggregate(transform(rows, r -> aggregate(zip_with(r, x, (p, q) -> p * q), 0D, (s, y) -> s + y)), 0D, (s, y) -> s + y * y)"),
        ("quad_hi", "rows ARRAY<ARRAY<DOUBLE>>, x ARRAY<DOUBLE>, shed DOUBLE", "aggregate(transform(rows, r -> aggregate(zip_with(r, x, (p, q) -> p * q), 0D, (s, y) -> s + y)), 0D, (s, y) -> s + y * y) + shed"),
    ):
        kind = "DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("sketch_rows", udtf(SketchRows, returnType="row_no int, sigma double, vec array<double>"))
    spark.udtf.register("shrink_sketch", udtf(ShrinkSketchTable, returnType="key string, row_no int, sigma double, shed double, n_rows long, vec array<double>"))
