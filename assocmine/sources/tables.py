"""Readers and writers of other formats and of generated rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, columns: list[str] | None = None) -> DataFrame:
    """parquet, orc, csv (with header) or json; text formats need a schema, so that no pass is spent on guessing."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.schema(schema) if schema else spark.read
    df = reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)
    return df.select(*columns) if columns else df


def read_stream(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def write_result(result: DataFrame, path: str) -> None:
    """Results by order and metric."""
    result.withColumn("ord", F.size("members")).write.mode("overwrite").partitionBy("ord", "metric").parquet(path)


def generated(spark: SparkSession, n: int, attributes: int, states: int = 3, tag: str = "gen") -> DataFrame:
    """Independent attributes from md5 uniforms of row numbers."""
    from assocmine.functions.expressions import uniform

    return spark.range(n).select(F.col("id").alias("key"), *[F.floor(states * uniform(f"{tag}{i}", F.lit(0), F.col("id"))).cast("int").alias(f"a{i}") for i in range(1, attributes + 1)])
