"""Structured Streaming: windows over late data, de-duplication, state, live assignment and centroid updates.

Every query here replays a table with the availableNow trigger into the shared folder and returns what the stream
has written, so that a stream can be held against its batch counterpart.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.operators.assign import Kernel, run_kernel
from vecspark.operators.clustering import MiniBatchKMeans
from vecspark.operators.rotation import random_rotation
from vecspark.operators.seeding import start_matrix
from vecspark.plans.vector_queries import A0, centroid_rows, minibatch_sql
from vecspark.sources.files import shared_path
from vecspark.sources.vectors import embeddings, read_table

QUERIES: dict = {}
ORACLES: dict = {}


def keep(name: str, sql: str | None = None):
    def to(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return to


def stream_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table's files as a stream, with the schema of the table."""
    schema = read_table(spark, sf_dir, name).schema
    source = spark.readStream.schema(schema).format("parquet")
    return source.option("pathGlobFilter", f"{name}.parquet").load(sf_dir) if not _is_folder(spark, f"{sf_dir}/{name}.parquet") else source.load(f"{sf_dir}/{name}.parquet")


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over all that is there; its rows from a checkpointed file sink (complete mode: of the last batch)."""
    spark = stream.sparkSession
    out, state = shared_path(spark, "stream-out"), shared_path(spark, "stream-state")
    schema = stream.schema
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out)
    else:
        writer = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out))
    run = writer.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(schema).parquet(out)


def events(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    return stream_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


@keep("stream_tumbling", "SELECT CAST(epoch(time_bucket(INTERVAL '1 hour', ts)) AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    counted = events(spark, sf_dir).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drain(counted.select(F.unix_timestamp("window.start").alias("hour"), "event_type", "n"), "complete")


@keep("stream_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([epoch(time_bucket(INTERVAL '30 minutes', ts))::BIGINT, epoch(time_bucket(INTERVAL '30 minutes', ts))::BIGINT - 1800]) AS s FROM events) GROUP BY 1")
def _(spark, sf_dir):
    counted = events(spark, sf_dir).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return drain(counted.select(F.unix_timestamp("window.start").alias("start"), "n"), "complete")


# a session takes in an event that comes just as its gap ends
@keep("stream_session", """WITH e AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER w <= INTERVAL '6 hours' THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM e)
SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, session""")
def _(spark, sf_dir):
    """Every session, those still open at the end too: no watermark closes one, and the last batch is complete."""
    stream = stream_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    counted = stream.groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drain(counted.select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n"), "complete")


@keep("stream_dedup", "SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")
def _(spark, sf_dir):
    return drain(stream_table(spark, sf_dir, "events").select("user_id", "event_type").dropDuplicates()).agg(F.count(F.lit(1)).alias("n"))


@keep("stream_dedup_watermark")
def _(spark, sf_dir):
    return drain(events(spark, sf_dir).dropDuplicatesWithinWatermark(["user_id"]).select("user_id", "event_type"))


@keep("stream_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def _(spark, sf_dir):
    a = events(spark, sf_dir).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.col("event_id").alias("a"))
    b = events(spark, sf_dir).where("event_type = 'purchase'").select(F.col("user_id").alias("w"), F.col("ts").alias("tb"), F.col("event_id").alias("b"))
    return drain(a.join(b, F.expr("u = w AND tb BETWEEN ta AND ta + INTERVAL 1 HOUR")).select("a", "b"))


def running_totals(stream: DataFrame) -> DataFrame:
    """Count and sum of each user's values so far, kept in state."""

    def add(key, parts, state):
        n, total = state.get if state.exists else (0, 0.0)
        for part in parts:
            n, total = n + len(part), total + float(part["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [round(total, 4)]})

    return stream.select("user_id", "value").groupBy("user_id").applyInPandasWithState(add, "user_id long, n long, total double", "n long, total double", "update", "NoTimeout")


@keep("stream_running_totals", "SELECT user_id, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    out = shared_path(spark, "totals")
    run = running_totals(stream_table(spark, sf_dir, "events")).writeStream.foreachBatch(lambda df, i: df.withColumn("batch", F.lit(i)).write.mode("append").parquet(out)).outputMode("update").option("checkpointLocation", shared_path(spark, "totals-state")).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(out).groupBy("user_id").agg(F.max("n").alias("n"))


def assign_stream(vectors: DataFrame, centroids: np.ndarray) -> DataFrame:
    """Each arriving vector's centroid: the same kernel as in batch, on a stream."""
    return run_kernel(vectors, Kernel(centroids, True, max(1, centroids.shape[1] // 8), 8, np.inf, dtype=np.float64))


@keep("stream_assign", A0)
def _(spark, sf_dir):
    y = start_matrix(embeddings(spark, sf_dir), 22, 0)
    return drain(assign_stream(stream_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec")), y)).select("vec_id", "cid", F.round("dist", 6).alias("dist"))


@keep("stream_static_join", "SELECT label, count(*) AS n FROM embeddings WHERE label < 5 GROUP BY 1")
def _(spark, sf_dir):
    wanted = F.broadcast(spark.range(5).select(F.col("id").cast("int").alias("label")))
    return drain(stream_table(spark, sf_dir, "embeddings").select("vec_id", "label").join(wanted, "label")).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@keep("stream_minibatch", minibatch_sql(1, None))
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    y, counts = start_matrix(v, 22, 0), np.zeros(22, np.int64)
    rotation = random_rotation(y.shape[1], 0)
    stream = stream_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec"))

    def update(batch: DataFrame, number: int) -> None:
        MiniBatchKMeans.update(batch, y, counts, rotation, np.inf)

    run = stream.writeStream.foreachBatch(update).option("checkpointLocation", shared_path(spark, "minibatch")).trigger(availableNow=True).start()
    run.awaitTermination()
    return centroid_rows(spark, y, counts)
