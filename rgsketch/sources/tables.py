"""Reading and writing tables and sketches."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; a temporary one only for a local master without the setting."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="rgsketch-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def materialize(df: DataFrame, fmt: str = "parquet") -> DataFrame:
    """A written copy of ``df`` in the shared folder: lineage is cut and lost executors cost nothing of it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/rgsketch/{uuid.uuid4().hex}"
    df.write.format(fmt).save(path)
    return spark.read.schema(df.schema).format(fmt).load(path)


def drop_written(spark: SparkSession) -> None:
    """Delete what ``materialize`` and the round trips have written in the shared folder. For the end of a job: results that
    weren't stored elsewhere are read from it."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/rgsketch")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def write_sketch(df: DataFrame, path: str, partition_by: str | None = "layout_id") -> None:
    """Sketches as Parquet; those of one layout lie together, as only they compare."""
    writer = df.write.mode("overwrite")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, *keys: str) -> None:
    """A bucketed table, so that later joins on the keys need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
