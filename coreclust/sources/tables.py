"""Readers and writers: tables by folder, partitioned coresets, saved models."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

READERS = {"parquet": {}, "orc": {}, "csv": {"header": "true"}, "json": {}}


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


#: Bytes below which a table in fewer files than cores is worth dealing out.
SMALL = 1 << 30


def spread(df: DataFrame) -> DataFrame:
    """A small table in a few files, dealt over all cores; a file of one row group is one task otherwise.  Larger tables stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    small = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) < SMALL
    return df.repartition(cores) if small and len(df.inputFiles()) < cores else df


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A source with only the columns and rows asked for; text formats need their schema stated."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"state the schema of {fmt} input")
    reader = spark.read.format(fmt).options(**READERS[fmt])
    df = (reader.schema(schema) if schema else reader).load(path)
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def write_coreset(rows: DataFrame, path: str) -> None:
    rows.write.mode("overwrite").partitionBy("part").parquet(path)


def save_model(centers: DataFrame, params: dict, path: str) -> None:
    """Centers as Parquet and parameters as one row beside them, through Spark alone."""
    centers.write.mode("overwrite").parquet(f"{path}/centers")
    centers.sparkSession.createDataFrame([(json.dumps(params, sort_keys=True),)], "params string").coalesce(1).write.mode("overwrite").parquet(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/centers"), json.loads(spark.read.parquet(f"{path}/params").first()["params"])


def stream(spark: SparkSession, folder: str, name: str, files_per_trigger: int | None = None) -> DataFrame:
    """A table's files as a stream; its schema is read from the files once, and only its files are taken."""
    schema = spark.read.parquet(f"{folder}/{name}.parquet").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet")
    reader = reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader
    return reader.parquet(folder)


def with_event_time(df: DataFrame, column: str = "ts") -> DataFrame:
    """Timestamps without zone as instants, which watermarks need."""
    return df.withColumn(column, F.col(column).cast("timestamp"))
