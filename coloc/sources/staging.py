"""Tables written once and read back, in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder only where that is unset and Spark is local."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="coloc-stage-"))
        base = sc.getCheckpointDir()
    return base.rstrip("/")


def _folder(spark: SparkSession, path: str) -> tuple:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def dropped(spark: SparkSession, path: str) -> None:
    fs, at = _folder(spark, path)
    fs.delete(at, True)


def staged(df: DataFrame, name: str = "stage", paths: list[str] | None = None) -> DataFrame:
    """Cuts the lineage: df written as Parquet in the shared folder and read back. The folder goes when the application ends; its
    path is added to `paths` for whoever drops it sooner."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    fs, at = _folder(spark, path)
    fs.deleteOnExit(at)
    if paths is not None:
        paths.append(path)
    return spark.read.schema(df.schema).parquet(path)
