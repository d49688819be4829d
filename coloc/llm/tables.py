"""Input and staging helpers that the text operators share."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, DataType

#: Texts can be long, and both the JVM and the worker hold a whole Arrow batch of them.
BATCH_ROWS = 2_000
#: A key is hot if it has more than this part of all rows; there are fewer such keys than this.
HOT_SHARE = 2_000
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def narrow(df: DataFrame, **wanted: str) -> DataFrame:
    """Columns out=source, found by position, so that other columns whose names clash (also by case) do no harm."""
    names = df.columns
    spare = df.toDF(*[f"_in{i}" for i in range(len(names))])
    return spare.select(*[F.col(f"_in{names.index(src)}").alias(out) for out, src in wanted.items()])


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; a temporary one only where that is unset."""
    sc = spark.sparkContext
    known = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not known:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="coloc-shared-"))
        known = sc.getCheckpointDir()
    return known.rstrip("/")


def staged(df: DataFrame, name: str, scratch: Scratch | None = None) -> DataFrame:
    """df written once as Parquet in the shared folder and read back: cuts the lineage and outlives lost executors.

    The folder goes when the application ends, or with the scratch that it belongs to.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _folder(spark, path)[0].deleteOnExit(_folder(spark, path)[1])
    if scratch is not None:
        scratch.paths.append(path)
    return spark.read.schema(df.schema).parquet(path)


def _folder(spark: SparkSession, path: str) -> tuple:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


class Scratch:
    """The staged folders of one job, deleted when it is over and its result no longer reads them."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def __enter__(self) -> Scratch:
        return self

    def __exit__(self, *failure) -> None:
        for path in self.paths:
            fs, at = _folder(self.spark, path)
            fs.delete(at, True)
        self.paths.clear()


def joined_by_hot_key(rows: DataFrame, facts: DataFrame, key: str, spread: str, counts: DataFrame | None = None, share: int = HOT_SHARE) -> DataFrame:
    """rows left joined with facts, a table of one row for each key. counts, or facts itself, is staged and has in n the number of rows of each key.

    Keys with more than a share-th of the counted rows are fewer than `share`, so their facts are sent to all executors; what has one of them, or a null
    key, is dealt out by its column `spread` among the others, where it meets nothing. No task gets a hot key's rows.
    """
    more = [c for c in facts.columns if c not in (key, "n")]
    counted = facts if counts is None else counts
    total = counted.agg(F.sum("n")).first()[0] or 0
    hot = facts.join(F.broadcast(counted.where(F.col("n") > total // share).select(key)), key, "left_semi")
    hot = hot.select(F.col(key).alias("_hot"), F.struct(*more).alias("_of_hot"))
    cold = facts.select(F.col(key).alias("_cold"), F.struct(*more).alias("_of_cold"))
    met = rows.join(F.broadcast(hot), F.col(key) == F.col("_hot"), "left")
    met = met.withColumn("_free", F.col("_hot").isNotNull() | F.col(key).isNull()).drop("_hot")
    met = met.withColumn("_own", F.when(F.col("_free"), _surrogate(F.xxhash64(spread, F.lit("~")), facts.schema[key].dataType)).otherwise(F.col(key)))
    out = met.join(cold, (F.col("_own") == F.col("_cold")) & ~F.col("_free"), "left")
    return out.select(*rows.columns, *[F.coalesce(F.col(f"_of_hot.{c}"), F.col(f"_of_cold.{c}")).alias(c) for c in more])


def _surrogate(number: Column, kind: DataType) -> Column:
    """A number as a value of a key's type."""
    if isinstance(kind, ArrayType):
        return F.array(_surrogate(number, kind.elementType))
    return number.cast("string").cast("binary") if isinstance(kind, BinaryType) else number.cast(kind)


def ship(spark: SparkSession) -> None:
    """Gives the executors' Python workers this package, once for each application, and no more than BATCH_ROWS rows at once."""
    if not 0 < int(spark.conf.get(_BATCH)) <= BATCH_ROWS:
        spark.conf.set(_BATCH, str(BATCH_ROWS))
    sc = spark.sparkContext
    if getattr(sc, "_coloc_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = os.path.join(tempfile.mkdtemp(prefix="coloc-ship-"), "coloc_llm_code.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in [root / "__init__.py", *sorted((root / "llm").glob("*.py"))]:
            z.write(p, str(p.relative_to(root.parent)))
    sc.addPyFile(target)
    sc._coloc_shipped = True
