"""Codes behind a coarse index: product quantisation of residuals, and the quantile-grid coding it is compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecspark.sources.files import settle

from .assign import Kernel
from .clustering import LloydKMeans, PhasedKMeans
from .model import Model, matrix, vector_rows


def coarse_then_codes(vectors: DataFrame, k: int, parts: int = 8, codes: int = 256, iterations: int = 5, seed: int = 0) -> tuple[Model, DataFrame, list[np.ndarray]]:
    """(coarse model, (vec_id, cid, code), books): residuals cut into `parts`, each coded by its nearest of `codes` means."""
    method = PhasedKMeans(k=k, max_iter=iterations, seed=seed)
    model = method.fit(vectors)
    d = model.centroids.shape[1]
    width = d // parts
    if width * parts != d:
        raise ValueError("the dimensions must divide by the number of parts")
    coarse = Kernel(model.centroids)
    shipped = vectors.sparkSession.sparkContext.broadcast((coarse, model.centroids.astype(np.float32)))

    def residual(batches):
        kernel, y = shipped.value
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(1))
                cid, _ = kernel(x)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cid.astype(np.int32)), vector_rows(x - y[cid])], names=["vec_id", "cid", "vec"])

    left = settle(vectors.select("vec_id", "vec").mapInArrow(residual, "vec_id long, cid int, vec array<float>"), "residuals")
    books = [LloydKMeans(k=codes, max_iter=iterations, seed=seed).fit(left.select("vec_id", F.slice("vec", p * width + 1, width).alias("vec"))).centroids for p in range(parts)]
    sent = vectors.sparkSession.sparkContext.broadcast([Kernel(b) for b in books])

    def encode(batches):
        own = sent.value
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(2))
                code = np.stack([kernel(np.ascontiguousarray(x[:, p * width : (p + 1) * width]))[0] for p, kernel in enumerate(own)], 1)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), vector_rows(code.astype(np.int32))], names=["vec_id", "cid", "code"])

    return model, left.mapInArrow(encode, "vec_id long, cid int, code array<int>"), books


def tile_assign(vectors: DataFrame, dims: int, tiles: int) -> DataFrame:
    """(vec_id, tile): equal-count tiles of the first `dims` dimensions, by exact ranks with ties in the order of vec_id.

    Each dimension is dealt out by ranges of (value, vec_id); a row's rank is its rank in its range and the rows of
    the ranges before, so no task sees all rows.
    """
    spark = vectors.sparkSession
    ranges = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = vectors.select("vec_id", *(F.col("vec")[i].alias(f"x{i}") for i in range(dims)))
    for i in range(dims):
        dealt = settle(rows.repartitionByRange(ranges, f"x{i}", "vec_id").withColumn("range", F.spark_partition_id()), "ranges")
        counts = sorted((r[0], r[1]) for r in dealt.groupBy("range").agg(F.count(F.lit(1))).collect())  # one row a range
        before = np.cumsum([0, *(n for _, n in counts)])
        base, more = divmod(int(before[-1]), tiles)  # the first `more` tiles have one row more
        first = F.broadcast(spark.createDataFrame([(p, int(b)) for (p, _), b in zip(counts, before)], "range int, first long"))
        rank = F.row_number().over(Window.partitionBy("range").orderBy(f"x{i}", "vec_id")) - 1
        ranked = dealt.withColumn("rank", rank).join(first, "range").withColumn("rank", F.col("rank") + F.col("first"))
        wide = more * (base + 1)
        tile = F.when(F.col("rank") < wide, F.floor(F.col("rank") / (base + 1))).otherwise(more + F.floor((F.col("rank") - wide) / max(base, 1)))
        rows = ranked.withColumn(f"t{i}", tile.cast("int")).drop("range", "rank", "first")
    return rows.select("vec_id", F.concat_ws("_", *(f"t{i}" for i in range(dims))).alias("tile"))
