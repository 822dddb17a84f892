"""Readers and writers around the method."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A table in parquet, orc, csv, json or text; csv and json want a schema, so that no pass infers one."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema is not None else r).load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, lower: int, upper: int, partitions: int, **properties) -> DataFrame:
    """A database table, read in ranges of a column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=lower, upperBound=upper, numPartitions=partitions, properties=properties)


def with_props(events: DataFrame, schema: str = "k int") -> DataFrame:
    """The JSON attribute of events as columns."""
    return events.withColumn("p", F.from_json("props", schema)).select(*events.columns, "p.*")


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> None:
    """A table bucketed and sorted on its join keys, so that joins of equal bucketing need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).format("parquet").saveAsTable(name)


def write_artefacts(path: str, run_id: str, **tables: DataFrame) -> None:
    """Components, cells, centroids and metrics of a run, each in its folder and partition."""
    for name, df in tables.items():
        df.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(f"{path}/{name}")


def read_artefact(spark: SparkSession, path: str, name: str, run_id: str) -> DataFrame:
    """One artefact of a run; the filter prunes to the run's partition."""
    return spark.read.parquet(f"{path}/{name}").where(F.col("run_id") == run_id).drop("run_id")


def discard(df: DataFrame) -> None:
    """Runs df and writes nowhere, for timing."""
    df.write.format("noop").mode("overwrite").save()
