"""Assignment of vectors to centroids: full products, pruned, in SQL functions; and the sums for an update."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions import kernels
from vecspark.functions.kernels import BatchPlan, CentroidBlocks, Work

from .model import BROADCAST_BYTES, matrix, vector_rows

SUMS = "cid int, n long, wcss double, total array<double>, rows long, head_mul_adds long, tail_mul_adds long, tested long, rejected long, block_tested array<long>, block_rejected array<long>, secs array<double>"
DENSE_BYTES = 256 << 20


def slices(centroids: np.ndarray, limit: int = BROADCAST_BYTES) -> list[tuple[int, np.ndarray]]:
    """(first cid, centroids) in pieces that may each be broadcast."""
    rows = max(1, limit // max(1, centroids.shape[1] * centroids.itemsize))
    return [(at, centroids[at : at + rows]) for at in range(0, len(centroids), rows)]


class Kernel:
    """How a batch is assigned: everything that a task needs, of the size of the centroids.

    With a `rotation` the centroids are rotated ones and the batch is rotated on the way in, so that data in its own
    space needs no pass of its own.
    """

    def __init__(self, centroids: np.ndarray, pruned: bool = False, d1: int = 0, step: int = 64, epsilon0: float = 2.1, progressive: bool = True, layout: str = "blocks", seed_mode: str = "head_nearest", plan: BatchPlan = BatchPlan(), dtype=np.float32, refinement: str = "auto", rotation: np.ndarray | None = None):
        self.blocks = CentroidBlocks(np.ascontiguousarray(centroids, dtype), d1 if pruned else centroids.shape[1], step, layout)
        self.pruned, self.epsilon0, self.progressive, self.seed_mode, self.plan, self.dtype, self.refinement = pruned, epsilon0, progressive, seed_mode, plan, dtype, refinement
        self.rotation = None if rotation is None else rotation.astype(dtype)

    def __call__(self, x: np.ndarray, prev=None, work: Work | None = None):
        if self.rotation is not None:
            x = x @ self.rotation
        if not self.pruned:
            return kernels.assign_full(x, self.blocks, self.plan, work)
        return kernels.assign_pruned(x, self.blocks, prev, self.epsilon0, self.progressive, self.seed_mode, self.plan, work, refinement=self.refinement)


def default_step(d: int) -> int:
    return min(64, max(8, d // 8))


def run_kernel(vectors: DataFrame, kernel: Kernel, first: int = 0, carry: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """The columns `carry`, cid and dist (squared).

    A column `prev`, where there is one, seeds the thresholds.  Columns `cid` and `dist`, where there are, hold the best of
    the centroids before `first` and stay where no nearer one is found, so slices follow each other without a shuffle.
    """
    shipped = vectors.sparkSession.sparkContext.broadcast(kernel)
    extra = ["prev"] if "prev" in vectors.columns else []
    best = ["cid", "dist"] if first else []
    columns = ["vec", *extra, *best, *carry]
    kinds = {f.name: f.dataType.simpleString() for f in vectors.schema}
    skip = 1 + len(extra) + len(best)

    def assign(batches):
        own = shipped.value
        for batch in batches:
            if batch.num_rows:
                prev = batch.column(1).to_numpy(zero_copy_only=False) if extra else None
                cid, dist = own(matrix(batch.column(0), own.dtype), prev)
                cid, dist = (cid + first).astype(np.int32), dist.astype(np.float64)
                if best:
                    old = batch.column(skip - 1).to_numpy()
                    nearer = dist < old
                    cid, dist = np.where(nearer, cid, batch.column(skip - 2).to_numpy()), np.where(nearer, dist, old)
                yield pa.RecordBatch.from_arrays([*batch.columns[skip:], pa.array(cid), pa.array(dist)], names=[*carry, "cid", "dist"])

    schema = ", ".join([*(f"`{c}` {kinds[c]}" for c in carry), "cid int", "dist double"])
    return vectors.select(*columns).mapInArrow(assign, schema)


def in_slices(vectors: DataFrame, centroids: np.ndarray, limit: int, carry: tuple[str, ...], kernel) -> DataFrame:
    """Slices of the centroids one after the other in one stage, each broadcast within the limit."""
    parts = slices(centroids, limit)
    whole = tuple(dict.fromkeys((*carry, "vec")))
    found = vectors
    for at, piece in parts:
        last = at == parts[-1][0]
        found = run_kernel(found, kernel(piece), at, carry if last else whole)
    return found


def assign_full(vectors: DataFrame, centroids: np.ndarray, plan: BatchPlan = BatchPlan(), dtype=np.float32, limit: int = BROADCAST_BYTES, carry: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """Nearest centroid by full products; over slices of the centroids where they are too large for one broadcast."""
    return in_slices(vectors, centroids, limit, carry, lambda piece: Kernel(piece, plan=plan, dtype=dtype))


def assign_pruned(vectors: DataFrame, centroids: np.ndarray, d1: int | None = None, step: int | None = None, epsilon0: float = 2.1, prev: DataFrame | None = None, limit: int = BROADCAST_BYTES, carry: tuple[str, ...] = ("vec_id",), **options) -> DataFrame:
    """Nearest centroid by head product and pruning.  Vectors and centroids are rotated already, or `rotation` is given
    for vectors that are not.

    With `prev` (vec_id, cid) the first threshold is the distance to that centroid; a vector without one, and
    every vector where `prev` is not given, takes a threshold that needs no state.
    """
    d = centroids.shape[1]
    options = {"d1": d1 or max(1, d // 8), "step": step or default_step(d), "epsilon0": epsilon0} | options
    if prev is not None and len(centroids) * d * 4 <= limit:
        both = vectors.join(prev.select("vec_id", F.col("cid").alias("prev")), "vec_id", "left").withColumn("prev", F.coalesce("prev", F.lit(0)))
        return run_kernel(both, Kernel(centroids, True, **(options | {"seed_mode": "previous"})), carry=carry)
    return in_slices(vectors, centroids, limit, carry, lambda piece: Kernel(piece, True, **options))


def assign_sql(vectors: DataFrame, centroids: DataFrame) -> DataFrame:
    """The same in DataFrame functions: one broadcast row of all centroids and a row-local minimum, no shuffle."""
    every = centroids.agg(F.array_sort(F.collect_list(F.struct("cid", F.col("centroid").cast("array<double>").alias("y")))).alias("every"))
    dist = lambda y: F.aggregate(F.zip_with("vec", y, lambda a, b: (a.cast("double") - b) * (a.cast("double") - b)), F.lit(0.0), lambda s, v: s + v)
    near = F.array_min(F.transform("every", lambda c: F.struct(F.round(dist(c["y"]), 9).alias("at_nine"), c["cid"].alias("cid"), dist(c["y"]).alias("dist"))))
    return vectors.join(F.broadcast(every)).select("vec_id", near.alias("near")).select("vec_id", "near.cid", "near.dist")


class Sums:
    """A task's sums by centroid: held densely up to DENSE_BYTES, else given out batch by batch."""

    def __init__(self, k: int, d: int):
        self.k, self.dense = k, k * d * 8 <= DENSE_BYTES
        self.total, self.count, self.wcss = (np.zeros((k, d)) if self.dense else None), np.zeros(k, np.int64), np.zeros(k)

    def add(self, x: np.ndarray, cid: np.ndarray, dist: np.ndarray):
        present, n, sums = kernels.centroid_sums(x, cid, self.k)
        cost = np.bincount(cid, dist, self.k)
        if not self.dense:
            yield sum_rows(present, n, cost[present], sums)
            return
        self.total[present] += sums
        self.count[present] += n
        self.wcss += cost

    def rest(self):
        present = np.flatnonzero(self.count)
        for at in range(0, len(present), 4096):
            own = present[at : at + 4096]
            yield sum_rows(own, self.count[own], self.wcss[own], self.total[own])


def sum_rows(cids, n, wcss, sums, stats=None) -> pa.RecordBatch:
    m = len(cids)
    zero = pa.array(np.zeros(m, np.int64))
    lists = pa.array([[]] * m, pa.list_(pa.int64()))
    extra = [zero] * 5 + [lists, lists, pa.array([[]] * m, pa.list_(pa.float64()))]
    if stats is not None:
        extra = [pa.array([v], pa.int64()) for v in stats[:5]] + [pa.array([v.tolist()], pa.list_(pa.int64())) for v in stats[5:7]] + [pa.array([stats[7].tolist()], pa.list_(pa.float64()))]
    total = vector_rows(np.asarray(sums, np.float64)) if m and np.size(sums) else pa.array([[]] * m, pa.list_(pa.float64()))
    columns = [pa.array(np.asarray(cids, np.int32)), pa.array(np.asarray(n, np.int64)), pa.array(np.asarray(wcss, np.float64)), total, *extra]
    return pa.RecordBatch.from_arrays(columns, names=[c.split()[0] for c in SUMS.split(", ")])


def work_row(work: Work) -> pa.RecordBatch:
    stats = [work.rows, work.head_mul_adds, work.tail_mul_adds, work.tested, work.rejected_head, work.block_tested, work.block_rejected, work.secs]
    return sum_rows([-1], [0], [0.0], np.zeros((1, 0)), stats)


def iteration_sums(vectors: DataFrame, kernel: Kernel) -> DataFrame:
    """One scan: each task's sums and counts by centroid, and its work as rows of cid -1.

    Work travels as rows and not in accumulators, since a task that runs twice would count twice there.
    """
    shipped = vectors.sparkSession.sparkContext.broadcast(kernel)

    def scan(batches):
        own, work = shipped.value, Work()
        sums = Sums(own.blocks.k, own.blocks.d)
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(0), own.dtype)
                cid, dist = own(x, None, work)
                work.lap()
                yield from sums.add(x, cid, dist)
                work.lap("sums")
        yield from sums.rest()
        yield work_row(work)

    return vectors.select("vec").mapInArrow(scan, SUMS)


def labelled_sums(labelled: DataFrame, k: int, d: int) -> DataFrame:
    """Each task's sums and counts by centroid of rows (vec, cid, dist) that have their labels already."""

    def scan(batches):
        sums = Sums(k, d)
        for batch in batches:
            if batch.num_rows:
                yield from sums.add(matrix(batch.column(0), np.float64), batch.column(1).to_numpy(), batch.column(2).to_numpy())
        yield from sums.rest()

    return labelled.select("vec", "cid", "dist").mapInArrow(scan, SUMS)


#: Partial sums that one task of the merge may hold of a centroid.
MERGED_AT_ONCE = 64


def merge_sums(sums: DataFrame, tasks: int | None = None) -> DataFrame:
    """One row for each centroid, and one of cid -1 with the work of all tasks.

    One shuffle by centroid; from many tasks the sums meet in two steps, so that no group has more than about the root
    of the number of tasks.
    """

    def longest(column: pa.ChunkedArray) -> list:
        lists = column.to_pylist()
        width, kind = max(map(len, lists)), column.type.value_type.to_pandas_dtype()
        return np.sum([np.pad(np.array(x, kind), (0, width - len(x))) for x in lists], axis=0).tolist()

    def add(group: pa.Table) -> pa.Table:
        out = {"cid": group["cid"].slice(0, 1)}
        for c in ("n", "wcss"):
            out[c] = pa.array([sum(group[c].to_pylist())])
        out["total"] = vector_rows(matrix(group["total"], np.float64).sum(0, keepdims=True)) if group["cid"][0].as_py() >= 0 else pa.array([[]], pa.list_(pa.float64()))
        for c in ("rows", "head_mul_adds", "tail_mul_adds", "tested", "rejected"):
            out[c] = pa.array([sum(group[c].to_pylist())], pa.int64())
        for c in ("block_tested", "block_rejected"):
            out[c] = pa.array([longest(group[c])], pa.list_(pa.int64()))
        out["secs"] = pa.array([longest(group["secs"])], pa.list_(pa.float64()))
        return pa.table(out)

    tasks = tasks or sums._jdf.queryExecution().toRdd().getNumPartitions()
    if tasks > MERGED_AT_ONCE:
        part = F.pmod(F.spark_partition_id(), F.lit(math.isqrt(tasks)))
        sums = sums.withColumn("part", part).groupBy("cid", "part").applyInArrow(lambda group: add(group.drop_columns("part")), SUMS)
    return sums.groupBy("cid").applyInArrow(add, SUMS)


def collect_sums(sums: DataFrame) -> tuple[dict[int, tuple[int, float, np.ndarray]], dict]:
    """cid -> (n, wcss, sum), and the work; one job, whose k rows reach the driver."""
    out, work = {}, {c: 0 for c in ("rows", "head_mul_adds", "tail_mul_adds", "tested", "rejected")} | {"block_tested": [], "block_rejected": [], "secs": []}
    for r in merge_sums(sums).collect():
        if r["cid"] < 0:
            work = {c: r[c] for c in work}
        else:
            out[r["cid"]] = (r["n"], r["wcss"], np.array(r["total"]))
    return out, work


def update_centroids_sql(vectors: DataFrame, assignment: DataFrame, centroids: DataFrame) -> DataFrame:
    """Means by cluster in DataFrame functions; an empty cluster keeps its centroid."""
    entries = vectors.join(assignment.select("vec_id", "cid"), "vec_id").select("cid", F.posexplode("vec").alias("pos", "v"))
    means = entries.groupBy("cid", "pos").agg(F.avg(F.col("v").cast("double")).alias("m"), F.count(F.lit(1)).alias("n"))
    new = means.groupBy("cid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda s: s["m"]).alias("mean"), F.max("n").alias("n"))
    old = centroids.select("cid", F.col("centroid").cast("array<double>").alias("old"))
    return old.join(new, "cid", "left").select("cid", F.coalesce("mean", "old").alias("centroid"), F.coalesce("n", F.lit(0)).alias("n"))
