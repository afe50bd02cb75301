"""Mixing sources to target weights by Poisson replication, in DataFrame functions alone.

Each source has a mean repetition rate, its target share of all characters over what it holds.  A document's
number of copies is the Poisson quantile, at that mean, of a number in [0, 1) hashed from its id and the seed;
copies are exploded and dealt out in the order of another hash, which is a global shuffle.  Means above
`CHUNK` are sums of equal independent parts, so that no quantile table grows past a fixed length.

Defined results: a null source is the source of the empty name; a source without characters keeps the rate 1;
rows of equal id get equal numbers of copies; an empty table gives an empty one.  The added column is
`copy_no`, from 1; a column of that name in the input is replaced.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import settle, table

CHUNK = 128
BROADCAST_SOURCES = 2_000  #: up to so many sources, of at most 300 numbers each, the rates are broadcast


@dataclass(frozen=True)
class MixParams:
    weights: dict[str, float] = field(default_factory=dict)  #: target shares; empty: size ** alpha
    alpha: float = 0.5
    scale: float = 1.0  #: characters out, as a multiple of characters in
    seed: int = 17


def unit(key: Column, salt: Column) -> Column:
    """A number in [0, 1) with 52 random bits, the same in any SQL engine that has md5."""
    digits = F.substring(F.md5(F.concat_ws(":", key, salt)), 1, 13)
    return F.conv(digits, 16, 10).cast("double") / F.lit(float(2**52))


def rates(documents: DataFrame, params: MixParams) -> DataFrame:
    """source_key, rate, parts, cdf: one row a source."""
    sizes = settle(documents.groupBy(F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source_key")).agg(F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("size")), "mix-sizes")
    if params.weights:
        pairs = [x for k, v in params.weights.items() for x in (F.lit(k), F.lit(float(v)))]
        wanted = F.coalesce(F.create_map(*pairs)[F.col("source_key")], F.lit(0.0))
    else:
        wanted = F.pow(F.col("size").cast("double"), F.lit(params.alpha))
    total = sizes.agg(F.sum("size").alias("size"), F.sum(F.when(F.col("size") > 0, wanted)).alias("wanted")).first()
    size, weight = float(total["size"] or 0), float(total["wanted"] or 0) or 1.0
    rate = F.when(F.col("size") > 0, wanted / F.lit(weight) * F.lit(size * params.scale) / F.col("size")).otherwise(F.lit(1.0))
    out = sizes.select("source_key", rate.alias("rate")).withColumn("parts", F.greatest(F.lit(1), F.ceil(F.col("rate") / CHUNK)).cast("int"))
    part = F.col("rate") / F.col("parts")
    steps = F.sequence(F.lit(1), (part + 12 * F.sqrt(part) + 24).cast("int"))
    zero = F.exp(-part)

    def longer(acc, k):
        p = acc["p"] * part / k
        return F.struct(p.alias("p"), (acc["c"] + p).alias("c"), F.concat(acc["cdf"], F.array(acc["c"] + p)).alias("cdf"))

    start = F.struct(zero.alias("p"), zero.alias("c"), F.array(zero).alias("cdf"))
    return out.withColumn("cdf", F.aggregate(steps, start, longer, lambda acc: acc["cdf"]))


def mix_sources(documents: DataFrame, params: MixParams = MixParams()) -> DataFrame:
    """Every document as often as its Poisson draw says, with copy_no, in a hashed global order."""
    by_source = settle(rates(documents, params), "mix-rates")
    few = by_source.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    columns = [c for c in documents.columns if c != "copy_no"]
    side = by_source.select(F.col("source_key").alias("__mix_source"), F.col("parts").alias("__mix_parts"), F.col("cdf").alias("__mix_cdf"))
    joined = documents.withColumn("__mix_source", F.coalesce(F.col("source").cast("string"), F.lit(""))).join(F.broadcast(side) if few else side, "__mix_source")
    key = F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(str(params.seed)))
    draw = F.aggregate(
        F.sequence(F.lit(1), F.col("__mix_parts")),
        F.lit(0),
        lambda n, j: n + F.size(F.filter(F.col("__mix_cdf"), lambda c: c <= unit(key, j.cast("string")))),
    )
    copies = joined.withColumn("__mix_n", draw).where("__mix_n > 0").withColumn("copy_no", F.explode(F.sequence(F.lit(1), F.col("__mix_n"))))
    place = F.xxhash64(F.lit(params.seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.col("copy_no"))
    return copies.select(*columns, "copy_no", place.alias("__mix_place")).repartition("__mix_place").sortWithinPartitions("__mix_place").drop("__mix_place")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"))


OP9_SQL = """
WITH RECURSIVE sizes AS (
  SELECT coalesce(source, '') AS source_key, CAST(coalesce(sum(length(text)), 0) AS BIGINT) AS size FROM documents GROUP BY 1
), total AS (
  SELECT CAST(sum(size) AS DOUBLE) AS size, sum(pow(CAST(size AS DOUBLE), 0.5::DOUBLE)) FILTER (size > 0) AS wanted FROM sizes
), rate AS (
  SELECT s.source_key, CASE WHEN s.size > 0 THEN pow(CAST(s.size AS DOUBLE), 0.5::DOUBLE) / t.wanted * t.size / s.size ELSE 1.0::DOUBLE END AS lam
  FROM sizes s, total t
), cdf AS (
  SELECT source_key, lam, 0 AS k, exp(-lam) AS p, exp(-lam) AS c FROM rate
  UNION ALL
  SELECT source_key, lam, k + 1, p * lam / (k + 1), c + p * lam / (k + 1) FROM cdf WHERE k < CAST(floor(lam + 12 * sqrt(lam) + 24) AS INTEGER)
), steps AS (
  SELECT source_key, list(c ORDER BY k) AS cdf FROM cdf GROUP BY 1
), drawn AS (
  SELECT d.*, len(list_filter(s.cdf, lambda c: c <= CAST(('0x' || substr(md5(CAST(d.doc_id AS VARCHAR) || ':17:1'), 1, 13)) AS BIGINT)::DOUBLE / 4503599627370496.0::DOUBLE)) AS n
  FROM documents d JOIN steps s ON s.source_key = coalesce(d.source, '')
)
SELECT doc_id, text, lang, source, n_chars, CAST(copy_no AS INTEGER) AS copy_no
FROM (SELECT * EXCLUDE (n), unnest(range(1, n + 1)) AS copy_no FROM drawn WHERE n > 0)
"""
