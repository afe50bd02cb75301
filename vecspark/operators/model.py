"""Centroids between driver, tasks and disk; Arrow batches as matrices."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Centroids beyond this many bytes are not broadcast in one piece; assignments then run over slices of them.
BROADCAST_BYTES = 1 << 30


def matrix(column: pa.Array, dtype=np.float32) -> np.ndarray:
    """A list column as rows of a matrix, without a copy where the type is the same."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, -1).astype(dtype, copy=False) if n else np.zeros((0, 0), dtype)


def vector_rows(rows: np.ndarray, kind=None) -> pa.ListArray:
    n, d = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * d + 1, max(d, 1))[: n + 1], pa.int32()), pa.array(np.ascontiguousarray(rows).ravel(), kind))


@dataclass
class Model:
    """Centroids in the data's own space, counts, and the history of the fit."""

    centroids: np.ndarray
    counts: np.ndarray
    history: list[dict] = field(default_factory=list)
    rotation: np.ndarray | None = None
    d1: int = 0
    params: dict = field(default_factory=dict)

    @property
    def k(self) -> int:
        return len(self.centroids)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(i, [float(v) for v in c], int(n)) for i, (c, n) in enumerate(zip(self.centroids, self.counts, strict=True))]
        return spark.createDataFrame(rows, "cid int, centroid array<float>, n long")

    def history_frame(self, spark: SparkSession) -> DataFrame:
        schema = "iter int, d1 int, prune_rate double, mul_adds long, wcss double, shift double, changed long, empty int, recall double, explored double, secs double"
        names = [c.split()[0] for c in schema.split(", ")]
        return spark.createDataFrame([tuple(h.get(c) for c in names) for h in self.history], schema)

    def save(self, spark: SparkSession, path: str) -> None:
        self.frame(spark).write.mode("overwrite").parquet(f"{path}/centroids")
        meta = json.dumps({"params": self.params, "history": self.history, "d1": self.d1}, default=float)
        spark.createDataFrame([(meta,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Model:
        rows = spark.read.parquet(f"{path}/centroids").orderBy("cid").collect()
        meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
        return cls(np.array([r["centroid"] for r in rows], np.float32), np.array([r["n"] for r in rows]), meta["history"], None, meta["d1"], meta["params"])


def collect_centroids(frame: DataFrame) -> np.ndarray:
    """A centroid table as a matrix by cid; its size is checked first."""
    stats = frame.agg(F.count(F.lit(1)).alias("k"), F.max(F.size("centroid")).alias("d")).first()
    if (stats["k"] or 0) * (stats["d"] or 0) * 4 > 4 * BROADCAST_BYTES:
        raise ValueError("the centroid table is too large for the driver; use two levels")
    return np.array([r[0] for r in frame.orderBy("cid").select("centroid").collect()], np.float64)
