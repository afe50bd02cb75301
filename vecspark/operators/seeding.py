"""Where clustering starts: random rows, k-means++, given centroids; and samples of the data."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecspark.sources.files import discard, settle

from .assign import Kernel, run_kernel


def default_k(n: int, c: float = 4.0) -> int:
    return int(math.floor(c * math.sqrt(n)))


def hash_order(seed: int, key: str = "vec_id") -> list[Column]:
    """An order of rows that any engine with md5 reproduces."""
    return [F.md5(F.concat(F.col(key).cast("string"), F.lit(f":{seed}"))), F.col(key)]


def init_random(vectors: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """k random rows (cid, vec_id, centroid): a top-k, not a sort."""
    rows = vectors.orderBy(*hash_order(seed)).limit(k).collect()
    schema = "cid int, vec_id long, centroid array<double>"
    return vectors.sparkSession.createDataFrame([(i, r["vec_id"], [float(v) for v in r["vec"]]) for i, r in enumerate(rows)], schema)


def start_matrix(vectors: DataFrame, k: int, seed: int) -> np.ndarray:
    return np.array([r["vec"] for r in vectors.select("vec_id", "vec").orderBy(*hash_order(seed)).limit(k).collect()], np.float64)


NEAR_ROUNDS = 32  #: seeding rounds between two writings of the nearest distances


def init_kmeanspp(vectors: DataFrame, k: int, seed: int = 0, power: float = 2.0, greedy_far: bool = False) -> np.ndarray:
    """D^power-weighted sequential seeding: one scan and one chosen row for each centroid.

    The weighted draw is the row of least -log(u) / weight with u hashed from the row and the round, so it is a
    top-1 by scan and does not depend on partitioning.  `greedy_far` takes the farthest row instead.  The nearest
    distance so far travels with the rows and is written down every few rounds, so a round computes the distances to
    the last few centroids alone.
    """
    chosen = start_matrix(vectors, 1, seed)
    rows = vectors.select("vec_id", "vec")
    known, near = 0, rows.withColumn("near", F.lit(float("inf")))
    while len(chosen) < k:
        fresh = run_kernel(near, Kernel(chosen[known:], dtype=np.float64), carry=("vec_id", "vec", "near"))
        now = fresh.select("vec_id", "vec", F.least("near", "dist").alias("near"))
        if len(chosen) - known == NEAR_ROUNDS:
            old, now = near, settle(now, "near")
            if known:
                discard(old)
            near, known = now, len(chosen)
        u = (F.conv(F.substring(F.md5(F.concat_ws(":", "vec_id", F.lit(seed), F.lit(len(chosen)))), 1, 12), 16, 10).cast("double") + 1) / float(2**48 + 1)
        weight = F.pow(F.sqrt("near"), F.lit(power))
        key = F.desc("near") if greedy_far else F.asc(F.when(weight > 0, -F.log(u) / weight).otherwise(float("inf")))
        found = now.orderBy(key, "vec_id").limit(1).collect()
        if not found:
            break
        chosen = np.concatenate([chosen, [found[0]["vec"]]])
    if known:
        discard(near)
    return chosen


def sample_rows(vectors: DataFrame, frac: float | None = None, max_per_centroid: int | None = None, k: int | None = None, seed: int = 0, n: int | None = None) -> DataFrame:
    """A hashed share of the rows, or the share that leaves about max_per_centroid * k of them."""
    if frac is None:
        n = vectors.count() if n is None else n
        frac = min(1.0, max_per_centroid * k / max(1, n))
    u = F.conv(F.substring(F.md5(F.concat(F.col("vec_id").cast("string"), F.lit(f":{seed}"))), 1, 8), 16, 10).cast("double") / float(2**32)
    return vectors if frac >= 1 else vectors.where(u < frac)


def sample_queries(vectors: DataFrame, n: int = 1000, seed: int = 1) -> DataFrame:
    """(qid, qvec): rows of the data themselves, by hash order."""
    return vectors.orderBy(*hash_order(seed)).limit(n).select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))


def every_20th(vectors: DataFrame) -> DataFrame:
    """(qid, qvec): the rows whose id is divisible by 20, the query set of the searches."""
    return vectors.where("vec_id % 20 = 0").select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
