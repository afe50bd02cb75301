"""Vector tables: `vec_id long, vec array<float>`, checked on the way in."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec"))


def flaw(d: int):
    """Why a row is no vector of d finite numbers; null if it is one."""
    bad = F.exists("vec", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == F.lit(float("inf"))))
    return F.when(F.col("vec").isNull(), "null").when(F.size("vec") != d, "length").when(bad, "not finite")


def validate(vectors: DataFrame, d: int, policy: str = "fail") -> DataFrame:
    """policy: "fail" raises when a bad row is read, "drop" leaves it out, "quarantine" keeps it with a column `flaw`."""
    if policy == "quarantine":
        return vectors.withColumn("flaw", flaw(d))
    if policy == "drop":
        return vectors.where(flaw(d).isNull())
    why = F.concat(F.lit("bad vector "), F.coalesce(F.col("vec_id").cast("string"), F.lit("null")), F.lit(": "), flaw(d))
    return vectors.where(F.when(flaw(d).isNull(), True).otherwise(F.raise_error(why).cast("boolean")))


def normalise(vectors: DataFrame, policy: str = "drop") -> DataFrame:
    """Unit vectors for cosine work; all-zero vectors have no direction and are dropped, or kept as they are."""
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, v: s + v.cast("double") * v.cast("double")))
    out = vectors.withColumn("norm", norm)
    if policy == "drop":
        out = out.where("norm > 0")
    return out.withColumn("vec", F.transform("vec", lambda v: F.when(F.col("norm") > 0, v / F.col("norm")).otherwise(v).cast("float"))).drop("norm")
