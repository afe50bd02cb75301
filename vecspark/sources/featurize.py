"""Vectors from other tables: DataFrame functions alone, but for the character grams of texts, which are counted in Arrow batches."""

from __future__ import annotations

from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.operators.model import vector_rows

from .vectors import read_table

EVENT_TYPES = 5
BLOCK_CHARS = 1 << 20  #: characters of text that a task counts at once
BLOCK_ROWS = 1024
PIECES = 1 << 23  #: more pieces than a text can have at 256 characters or more each
NO_CHAR = 0x1FFFFF  #: what a gram of a text of under three characters holds in the missing places


def blocks(batches):
    """(keys, texts) of at most BLOCK_ROWS rows and about BLOCK_CHARS characters, or one row."""
    for batch in batches:
        sizes = np.cumsum(pc.binary_length(batch.column(1)).to_numpy(zero_copy_only=False))
        at = 0
        while at < batch.num_rows:
            before = sizes[at - 1] if at else 0
            to = min(at + BLOCK_ROWS, max(at + 1, int(np.searchsorted(sizes, before + BLOCK_CHARS, "right"))))
            yield batch.column(0).slice(at, to - at), batch.column(1).slice(at, to - at).to_pylist()
            at = to


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(text, gram) of every character trigram; a gram is its three code points in one number."""
    size = np.array([len(t) for t in texts], np.int64)
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    points = np.concatenate([points, np.full(2, NO_CHAR, np.uint64)])
    count = np.maximum(size - 2, np.minimum(size, 1))
    first = np.cumsum(size) - size
    row = np.repeat(np.arange(len(texts)), count)
    at = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(first, count)
    key = points[at] << np.uint64(42)
    for i in (1, 2):
        inside = np.repeat(size > i, count)
        key |= np.where(inside, points[np.minimum(at + i, len(points) - 1)], NO_CHAR).astype(np.uint64) << np.uint64(42 - 21 * i)
    return row, key


class GramHash:
    """(dim, sign) of distinct grams by md5; texts repeat few grams, so each is hashed once a task."""

    def __init__(self, d: int):
        self.d, self.known = d, {}

    def __call__(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        dim, sign = np.empty(len(keys), np.int64), np.empty(len(keys), np.int64)
        for i, key in enumerate(keys.tolist()):
            found = self.known.get(key)
            if found is None:
                text = "".join(chr(c) for c in (key >> 42, key >> 21 & NO_CHAR, key & NO_CHAR) if c != NO_CHAR)
                h = int.from_bytes(md5(text.encode("utf-8", "replace"), usedforsecurity=False).digest()[:4], "big")
                found = self.known[key] = (h % self.d, 1 if h >> 20 & 1 else -1)
                if len(self.known) > 1_000_000:
                    self.known.clear()
            dim[i], sign[i] = found
        return dim, sign


def counts_by_dim(texts: list[str], hashed: GramHash) -> np.ndarray:
    row, key = grams(texts)
    kinds, place = np.unique(key, return_inverse=True)
    dim, sign = hashed(kinds)
    return np.bincount(row * hashed.d + dim[place], sign[place], len(texts) * hashed.d).reshape(len(texts), hashed.d)


def spelt(texts: DataFrame, key: str) -> DataFrame:
    """(key, lower-cased text) of rows that have text; lower case is the JVM's."""
    return texts.select(F.col(key).cast("long").alias("key"), F.lower("text").alias("t")).where("length(t) > 0")


def trigram_cells(texts: DataFrame, key: str, d: int) -> DataFrame:
    """(key, dim, n): signed counts of hashed character trigrams of each row's whole lower-cased text, in one scan."""

    def count(batches):
        hashed = GramHash(d)
        for keys, own in blocks(batches):
            n = counts_by_dim(own, hashed)
            r, c = np.nonzero(n)
            yield pa.RecordBatch.from_arrays([keys.take(pa.array(r)), pa.array(c.astype(np.int32)), pa.array(n[r, c].astype(np.int64))], names=["key", "dim", "n"])

    return spelt(texts, key).mapInArrow(count, "key long, dim int, n long").withColumnRenamed("key", key)


def text_vectors(texts: DataFrame, key: str, d: int = 512) -> DataFrame:
    """(vec_id, vec): roots of the signed counts, at unit length; one vector for each row, in one scan without a shuffle."""

    def vectors(batches):
        hashed = GramHash(d)
        for keys, own in blocks(batches):
            n = counts_by_dim(own, hashed)
            norm = np.sqrt(np.abs(n).sum(1, keepdims=True))
            x = np.sign(n) * np.sqrt(np.abs(n)) / np.where(norm > 0, norm, 1)
            yield pa.RecordBatch.from_arrays([keys, vector_rows(x.astype(np.float32))], names=["vec_id", "vec"])

    return spelt(texts, key).mapInArrow(vectors, "vec_id long, vec array<float>")


def dense(cells: DataFrame, key: str, value: Column, d: int) -> DataFrame:
    """(vec_id, vec) from (key, dim, value); absent dims are 0."""
    held = cells.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("dim", value.alias("v")))).alias("m"))
    return held.select(F.col(key).alias("vec_id"), F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0)).cast("float")).alias("vec"))


def document_vectors(spark: SparkSession, sf_dir: str, d: int = 512) -> DataFrame:
    return text_vectors(read_table(spark, sf_dir, "documents"), "doc_id", d)


def chunks(documents: DataFrame, size: int = 400) -> DataFrame:
    """(piece_id, text): texts cut every `size` characters; piece_id is doc_id * PIECES plus the piece's place."""
    if size < 256:
        raise ValueError("pieces have 256 characters or more, so that their ids cannot clash")

    def cut(batches):
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                starts = range(0, len(text), size)
                for at in range(0, len(starts), BLOCK_ROWS):
                    own = starts[at : at + BLOCK_ROWS]
                    ids = [doc * PIECES + i // size for i in own]
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([text[i : i + size] for i in own], pa.string())], names=["piece_id", "text"])

    rows = documents.where("doc_id is not null and length(text) > 0").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(cut, "piece_id long, text string")


def chunk_vectors(spark: SparkSession, sf_dir: str, d: int = 256, size: int = 400) -> DataFrame:
    return text_vectors(chunks(read_table(spark, sf_dir, "documents"), size), "piece_id", d)


def order_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row of numbers for each order."""
    li = read_table(spark, sf_dir, "lineitem")
    numbers = [("l_quantity", "q"), ("l_extendedprice", "p"), ("l_discount", "d"), ("l_tax", "t")]
    aggs = [f(c).cast("double").alias(f"{n}_{s}") for c, s in numbers for f, n in ((F.sum, "sum"), (F.avg, "avg"), (F.min, "min"), (F.max, "max"))]
    flags = [F.avg((F.col("l_returnflag") == v).cast("double")).alias(f"flag_{v.lower()}") for v in "ANR"] + [F.avg((F.col("l_linestatus") == v).cast("double")).alias(f"status_{v.lower()}") for v in "FO"]
    angle = F.dayofyear("l_shipdate") * F.lit(6.283185307179586 / 365.25)
    return li.groupBy(F.col("l_orderkey").alias("vec_id")).agg(F.count(F.lit(1)).cast("double").alias("lines"), *aggs, *flags, F.avg(F.sin(angle)).alias("ship_sin"), F.avg(F.cos(angle)).alias("ship_cos"))


def z_scored(features: DataFrame) -> DataFrame:
    """(vec_id, vec): every feature less its mean over its deviation; one row of statistics is broadcast."""
    names = [c for c in features.columns if c != "vec_id"]
    stats = features.agg(*(F.avg(c).alias(f"m_{c}") for c in names), *(F.stddev_pop(c).alias(f"s_{c}") for c in names))
    score = [F.when(F.col(f"s_{c}") > 0, (F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}")).otherwise(0.0).cast("float") for c in names]
    return features.join(F.broadcast(stats)).select("vec_id", F.array(*score).alias("vec"))


def order_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return z_scored(order_features(spark, sf_dir))


def part_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    part, li = read_table(spark, sf_dir, "part"), read_table(spark, sf_dir, "lineitem")
    sold = li.groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.sum("l_quantity").alias("sold"), F.avg("l_extendedprice").alias("price"), F.count(F.lit(1)).cast("double").alias("lines"))
    brands = sorted(r[0] for r in part.select("p_brand").distinct().limit(64).collect())
    types = sorted(r[0] for r in part.select("p_type").distinct().limit(64).collect())
    hot = [(F.col("p_brand") == b).cast("double").alias(f"brand_{i}") for i, b in enumerate(brands)] + [(F.col("p_type") == t).cast("double").alias(f"type_{i}") for i, t in enumerate(types)]
    both = part.join(sold, "p_partkey", "left").fillna(0.0, ["sold", "price", "lines"])
    return z_scored(both.select(F.col("p_partkey").alias("vec_id"), F.col("p_retailprice").alias("retail"), F.col("p_size").cast("double").alias("size"), "sold", "price", "lines", *hot))


def user_day_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, dim, n): events by user and day; dim = hour * 5 + the type's place in the alphabet."""
    ev = read_table(spark, sf_dir, "events")
    kinds = sorted(r[0] for r in ev.select("event_type").distinct().limit(EVENT_TYPES).collect())
    place = F.array_position(F.array(*map(F.lit, kinds)), F.col("event_type")) - 1
    return ev.select((F.col("user_id") * 1000 + F.dayofyear("ts")).alias("vec_id"), (F.hour("ts") * EVENT_TYPES + place).cast("int").alias("dim")).groupBy("vec_id", "dim").agg(F.count(F.lit(1)).alias("n"))


def user_day_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dense(user_day_cells(spark, sf_dir), "vec_id", F.col("n").cast("double"), 24 * EVENT_TYPES)
