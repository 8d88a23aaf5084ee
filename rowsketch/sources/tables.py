"""Tables by name, in several file formats, whole or as a stream of files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A table; formats without a schema of their own need one (nothing is inferred)."""
    if fmt == "parquet":
        return spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(f"{sf_dir}/{name}.{fmt}")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Registers tables as temporary views."""
    for name in names or NAMES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def file_stream(spark: SparkSession, path: str, schema: T.StructType, files_per_trigger: int = 1, fmt: str = "parquet") -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).format(fmt).load(path)


def rate_stream(spark: SparkSession, rows_per_second: int = 100, partitions: int = 1) -> DataFrame:
    """Row numbers as a stream, for tests: (timestamp, value)."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).option("numPartitions", partitions).load()


def noop(df: DataFrame) -> None:
    """Runs a plan to its end and keeps nothing."""
    df.write.format("noop").mode("overwrite").save()


def memory_sink(df: DataFrame, name: str, mode: str = "append"):
    """Starts a stream into an in-memory table, for tests; stop the query that comes back."""
    return df.writeStream.format("memory").queryName(name).outputMode(mode).start()
