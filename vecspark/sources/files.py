"""Sinks and round trips: the shared folder, partitioned and bucketed tables, text formats."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_path(spark: SparkSession, what: str) -> str:
    """A new path in the folder that the session names for checkpoints; a folder is set only where there is none."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not current.isDefined():
            spark.sparkContext.setCheckpointDir("/tmp/vecspark-checkpoints")
            current = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = current.get()
    return f"{folder.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def settle(df: DataFrame, what: str) -> DataFrame:
    """Written once as Parquet and read back: loops scan it and their plans stay short."""
    path = shared_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes the files that a settled table was read from, once nothing reads it any more."""
    spark = df.sparkSession
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)


def round_trip(df: DataFrame, kind: str, **options) -> DataFrame:
    """Through csv, json, orc, parquet or text, with the schema given and not inferred."""
    path = shared_path(df.sparkSession, kind)
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.format(kind).schema(df.schema).options(**options).load(path)


def write_partitioned(df: DataFrame, column: str) -> DataFrame:
    path = shared_path(df.sparkSession, "partitioned")
    df.write.partitionBy(column).parquet(path)
    return df.sparkSession.read.parquet(path)


def write_bucketed(df: DataFrame, column: str, buckets: int, name: str | None = None) -> DataFrame:
    """A table bucketed and sorted by the column; two such tables join on it without an exchange."""
    name = name or f"vecspark_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, column).sortBy(column).option("path", shared_path(df.sparkSession, "bucketed")).saveAsTable(name)
    return df.sparkSession.table(name)
