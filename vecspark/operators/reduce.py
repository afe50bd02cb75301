"""Fewer dimensions before clustering: a prefix of rotated dimensions, or principal components."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .rotation import random_rotation, rotate


def reduce_dimensions(vectors: DataFrame, n: int, kind: str = "prefix", seed: int = 0) -> DataFrame:
    """(vec_id, vec) with n dimensions.

    "prefix": the first n after a random rotation, scaled so that squared distances keep their mean; one pass and
    nothing to learn.  "pca": the platform's principal components, whose d x d covariance meets on the driver.
    """
    if kind == "prefix":
        first = vectors.limit(1).collect()
        d = len(first[0]["vec"]) if first else n
        cut = rotate(vectors.select("vec_id", "vec"), random_rotation(d, seed), np.float32)
        return cut.select("vec_id", F.transform(F.slice("vec", 1, n), lambda v: (v * F.lit(float(np.sqrt(d / n)))).cast("float")).alias("vec"))
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    ml = vectors.select("vec_id", array_to_vector("vec").alias("x"))
    return PCA(k=n, inputCol="x", outputCol="y").fit(ml).transform(ml).select("vec_id", vector_to_array("y", "float32").alias("vec"))
