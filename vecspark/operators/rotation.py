"""Random orthogonal rotation, there and back."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import matrix, vector_rows


def random_rotation(d: int, seed: int = 0) -> np.ndarray:
    """A d x d orthogonal matrix, uniformly distributed (QR of a normal matrix with the signs of R's diagonal)."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, d)))
    return q * np.sign(np.diag(r))


def rotate(vectors: DataFrame, rotation: np.ndarray, dtype=np.float32) -> DataFrame:
    """vec times the rotation, by batches; the matrix is d x d and so of bounded size."""
    shipped = vectors.sparkSession.sparkContext.broadcast(rotation.astype(dtype))
    kind = "float" if dtype == np.float32 else "double"
    at = vectors.columns.index("vec")

    def turn(batches):
        for batch in batches:
            if batch.num_rows:
                columns = list(batch.columns)
                columns[at] = vector_rows(matrix(batch.column(at), dtype) @ shipped.value)
                yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names)

    schema = ", ".join(f"`{f.name}` {'array<' + kind + '>' if f.name == 'vec' else f.dataType.simpleString()}" for f in vectors.schema)
    return vectors.mapInArrow(turn, schema)


def unrotate(centroids: np.ndarray, rotation: np.ndarray) -> np.ndarray:
    return centroids @ rotation.T


def rotate_sql(vectors: DataFrame, rotation: np.ndarray) -> DataFrame:
    """The same in DataFrame functions: rows of the matrix are joined to the vectors' entries and summed by column."""
    spark = vectors.sparkSession
    d = len(rotation)
    cells = spark.createDataFrame([(i, j, float(rotation[i, j])) for i in range(d) for j in range(d)], "i int, j int, r double")
    entries = vectors.select("vec_id", F.posexplode("vec").alias("i", "v"))
    summed = entries.join(F.broadcast(cells), "i").groupBy("vec_id", "j").agg(F.sum(F.col("v").cast("double") * F.col("r")).alias("v"))
    return summed.groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("vec"))
