"""An index that queries build: exact search at first, lists of the regions that are asked for as they are asked for."""

from __future__ import annotations

from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .assign import assign_full
from .index import exact_knn, index_search, route, top_rank, write_lists
from .seeding import start_matrix


class ProgressiveIndex:
    """Query-driven indexing without a clustering up front.

    Cells lie around random rows.  A query whose `nprobe` nearest cells all have lists is answered from them; every other
    one scans all vectors.  After each batch of queries the cells that have been asked for `heat` times get their lists,
    in one scan that writes those vectors alone, so cold regions are never written.  `centroids` may also come from a
    fitted model once an index is worth its cost.
    """

    def __init__(self, vectors: DataFrame, k: int, path: str, nprobe: int = 4, heat: int = 8, seed: int = 0, centroids: np.ndarray | None = None, cid_buckets: int = 64):
        self.vectors, self.path, self.nprobe, self.heat, self.cid_buckets = vectors.select("vec_id", "vec"), path, nprobe, heat, cid_buckets
        self.centroids = start_matrix(self.vectors, k, seed) if centroids is None else np.asarray(centroids, np.float64)
        self.nprobe = min(nprobe, len(self.centroids))
        self.asked: Counter[int] = Counter()
        self.built: set[int] = set()  # at most k numbers
        self.parts: list[DataFrame] = []

    def lists(self) -> DataFrame:
        out = self.parts[0]
        for part in self.parts[1:]:
            out = out.unionByName(part)
        return out

    def search(self, queries: DataFrame, topk: int = 10, exclude_self: bool = True) -> DataFrame:
        """(qid, rank, vec_id, dist); what the queries ask for is counted, and `crack` builds the lists that are due."""
        spark = self.vectors.sparkSession
        probes = route(spark, queries, self.centroids, self.nprobe).select("qid", "cid")
        for r in probes.groupBy("cid").count().collect():  # at most k rows
            self.asked[r["cid"]] += r["count"]
        if not self.built:
            return exact_knn(queries, self.vectors, topk, exclude_self=exclude_self)
        ready = spark.createDataFrame([(c,) for c in sorted(self.built)], "cid int")
        served = probes.join(F.broadcast(ready), "cid", "left_semi").groupBy("qid").count().where(F.col("count") == self.nprobe).select("qid")
        warm, cold = queries.join(served, "qid", "left_semi"), queries.join(served, "qid", "left_anti")
        found = index_search(warm, self.lists(), self.centroids, topk, self.nprobe, exclude_self)
        rest = exact_knn(cold, self.vectors, topk, exclude_self=exclude_self)
        return top_rank(found.drop("rank").unionByName(rest.drop("rank")), topk)

    def crack(self) -> list[int]:
        """Writes the lists of the cells that have become hot since the last time, and says which."""
        due = sorted(c for c, n in self.asked.items() if n >= self.heat and c not in self.built)
        if due:
            placed = assign_full(self.vectors, self.centroids, dtype=np.float64, carry=("vec_id", "vec")).where(F.col("cid").isin(due)).drop("dist")
            self.parts.append(write_lists(placed, f"{self.path}/{len(self.parts)}", self.cid_buckets))
            self.built |= set(due)
        return due
