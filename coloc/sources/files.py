"""Files in and out: formats with explicit schemas, partitioned and bucketed sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.sources.staging import shared_folder


def read(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str, mode: str = "overwrite") -> None:
    writer = df.write.mode(mode)
    (writer.option("header", "true") if fmt == "csv" else writer).format(fmt).save(path)


def roundtrip(df: DataFrame, formats: tuple[str, ...] = ("csv", "json", "orc", "parquet")) -> DataFrame:
    """format, n, amount of df written in each format and read back."""
    spark = df.sparkSession
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    out = None
    for fmt in formats:
        path = f"{shared_folder(spark)}/roundtrip-{uuid.uuid4().hex}"
        write(df, path, fmt)
        one = read(spark, path, fmt, schema).agg(F.lit(fmt).alias("format"), F.count(F.lit(1)).alias("n"), F.round(F.sum("amount"), 3).alias("amount"))
        out = one if out is None else out.unionByName(one)
    return out


def partitioned(df: DataFrame, *by: str) -> DataFrame:
    """df written in folders by column and read back: later reads of one value skip the others."""
    path = f"{shared_folder(df.sparkSession)}/partitioned-{uuid.uuid4().hex}"
    df.repartition(*by).write.partitionBy(*by).parquet(path)
    return df.sparkSession.read.parquet(path).withColumns({c: F.col(c).cast(df.schema[c].dataType) for c in by})


def save_results(rules: DataFrame, path: str, run_id: str) -> None:
    """The rules table under a run's name: a run that is repeated replaces its own rows and no others."""
    named = rules.drop("run_id").withColumn("run_id", F.lit(run_id))
    named.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id").parquet(path)


def results(spark: SparkSession, path: str) -> DataFrame:
    rows = spark.read.parquet(path)
    return rows.withColumn("run_id", F.col("run_id").cast("string"))
