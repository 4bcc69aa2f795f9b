"""Readers with fixed schemas and idempotent sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The recorded channels, by name.
TRACE = T.StructType([
    T.StructField("field_id", T.IntegerType()), T.StructField("session", T.IntegerType()), T.StructField("cart_id", T.LongType()), T.StructField("t_us", T.LongType()),
    T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType()), T.StructField("w", T.DoubleType()), T.StructField("ax", T.DoubleType()),
    T.StructField("ay", T.DoubleType()), T.StructField("az", T.DoubleType()), T.StructField("state", T.StringType()), T.StructField("src_id", T.LongType()),
])


def conform(df: DataFrame, schema: T.StructType) -> DataFrame:
    """Columns of the schema, cast; missing ones are an error, others are dropped."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    return df.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in schema])


def read_traces(spark: SparkSession, path: str, fmt: str = "parquet", fields=None, sessions=None, schema: T.StructType = TRACE) -> DataFrame:
    """Traces of some fields and sessions (partition columns when the folder is laid out by them)."""
    df = spark.read.format(fmt).schema(schema).option("header", "true").load(path)
    if fields is not None:
        df = df.where(F.col("field_id").isin(list(fields)))
    if sessions is not None:
        df = df.where(F.col("session").isin(list(sessions)))
    return df


def write_traces(df: DataFrame, path: str, per_file: int = 4_000_000) -> None:
    """By field and session, samples of a cart together; a re-run replaces only the partitions it brings."""
    (
        df.repartition("field_id", "session", "cart_id").sortWithinPartitions("field_id", "session", "cart_id", "t_us")
        .write.mode("overwrite").option("partitionOverwriteMode", "dynamic").option("maxRecordsPerFile", per_file).partitionBy("field_id", "session").parquet(path)
    )


def write_bucketed(df: DataFrame, name: str, buckets: int, by: str = "cart_id") -> None:
    """A table whose joins and windows on the cart need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def write_map(cells: DataFrame, path: str, fmt: str = "csv") -> None:
    cells.write.mode("overwrite").option("header", "true").format(fmt).save(path)
