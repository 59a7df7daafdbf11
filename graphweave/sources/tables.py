"""Typed scans of the given tables, other formats, and edge lists with a policy for bad rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

EDGE_SCHEMA = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def scan(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One table; the columns named reach the Parquet scan."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def round_trip(df: DataFrame, path: str, fmt: str) -> DataFrame:
    """df written in another format and read back with its own schema."""
    df.write.format(fmt).mode("overwrite").save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).load(path)


def edge_list(spark: SparkSession, path: str, separator: str = ",", bad_rows: str = "_bad") -> tuple[DataFrame, DataFrame]:
    """(edges, rows that do not parse) of delimited text with an explicit schema."""
    schema = T.StructType([*EDGE_SCHEMA.fields, T.StructField(bad_rows, T.StringType())])
    rows = spark.read.schema(schema).option("sep", separator).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", bad_rows).csv(path)
    fine = f"{bad_rows} is null and src is not null and dst is not null"
    return rows.where(fine).select("src", "dst"), rows.where(f"not ({fine})").select(bad_rows)


def write_partitioned(edges: DataFrame, path: str) -> DataFrame:
    """Edges stored by partition, so a reader of some partitions prunes the others."""
    edges.repartition("part").write.mode("overwrite").partitionBy("part").parquet(path)
    return edges.sparkSession.read.parquet(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int, key: str = "dst") -> DataFrame:
    """Edges stored in buckets of a key, so later joins and aggregations on it need no exchange."""
    edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return edges.sparkSession.table(table)
