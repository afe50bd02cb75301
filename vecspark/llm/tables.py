"""How the operators of this subpackage read tables, sample labelled rows and set down intermediate tables."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; one is set only where there is none, as in tests."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            return current.get()
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("name a shared folder in spark.checkpoint.dir")
        folder = "/tmp/vecspark-checkpoints"
        spark.sparkContext.setCheckpointDir(folder)
        return spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return folder


def new_path(spark: SparkSession, what: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def settle(df: DataFrame, what: str) -> DataFrame:
    """The rows written to the shared folder and read back: a lineage cut that survives lost executors."""
    path = new_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes a settled table once nothing reads it any more."""
    jvm = df.sparkSession.sparkContext._jvm
    conf = df.sparkSession.sparkContext._jsc.hadoopConfiguration()
    for file in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(file)
        path.getFileSystem(conf).delete(path, True)


def stretch(text: Column, key: Column, chars: int) -> Column:
    """The whole text up to `chars` characters; of a longer one that many, from a place that a hash of the key draws."""
    start = F.pmod(F.xxhash64(key), F.greatest(F.length(text) - chars, F.lit(0)) + 1).cast("int") + 1
    return F.when(F.length(text) <= chars, text).otherwise(F.substring(text, start, F.lit(chars)))


def labelled_sample(documents: DataFrame, labels: DataFrame, label: str, rows: int, max_chars: int, where=None) -> list:
    """At most `rows` rows (doc_id, text, y), in the order of a hash of the id; of a text over `max_chars` a stretch of it.

    The bounds serve classifier fitting alone.  A label or text that is null is left out; where an id stands
    more than once the smallest text and the largest label stand for it.
    """
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("doc_id is not null and y is not null")
    if where is not None:
        marks = marks.where(where(F.col("doc_id")))
    ids = marks.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    found = texts.join(F.broadcast(ids), "doc_id").withColumn("text", stretch(F.col("text"), F.col("doc_id"), max_chars)).groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y"))
    return sorted(found.collect())
