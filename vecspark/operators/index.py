"""The inverted-file index: build, route, search; exact search; recall and work of a search."""

from __future__ import annotations

from functools import reduce
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vecspark.functions.kernels import sq_dists, sq_norms

from .assign import assign_full, assign_pruned
from .model import Model, matrix

QUERY_BLOCK = 20_000  #: queries broadcast at once
PAIRS_AT_ONCE = 2_000_000  #: distances that a task holds


def query_matrix(queries: DataFrame, limit: int = QUERY_BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """(qid, vectors) of a query set within the bound; larger sets go block by block."""
    rows = queries.select("qid", "qvec").orderBy("qid").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"more than {limit} queries at once; pass them in blocks")
    return stacked(rows)


def stacked(rows: list) -> tuple[np.ndarray, np.ndarray]:
    return np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.float64).reshape(len(rows), -1 if rows else 0)


def query_blocks(queries: DataFrame, limit: int | None = None):
    """(qid, vectors) of every `limit` queries in the order of qid; a set within the bound, and an empty one, is one block."""
    limit = limit or QUERY_BLOCK
    ordered = queries.select("qid", "qvec").orderBy("qid")
    rows = ordered.limit(limit + 1).collect()
    if len(rows) <= limit:
        yield stacked(rows)
        return
    rows = ordered.toLocalIterator()
    while block := list(islice(rows, limit)):
        yield stacked(block)


def scores(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """What is least for the best match: squared distance, negative inner product, or one less the cosine."""
    if metric == "l2":
        return sq_dists(q, x)
    if metric == "ip":
        return -(q @ x.T)
    norm = np.sqrt(sq_norms(q))[:, None] * np.sqrt(sq_norms(x))[None, :]
    return 1 - (q @ x.T) / np.where(norm > 0, norm, 1)


def exact_knn(queries: DataFrame, vectors: DataFrame, topk: int = 10, metric: str = "l2", exclude_self: bool = True) -> DataFrame:
    """(qid, rank, vec_id, dist): each task keeps its own best topk of a query, and a window ranks those of all tasks.

    The vectors are scanned once for each block of queries.
    """
    found = [block_knn(ids, q, vectors, topk, metric, exclude_self) for ids, q in query_blocks(queries)]
    return top_rank(reduce(DataFrame.union, found), topk)


def block_knn(ids: np.ndarray, q: np.ndarray, vectors: DataFrame, topk: int, metric: str, exclude_self: bool) -> DataFrame:
    shipped = vectors.sparkSession.sparkContext.broadcast((ids, q))

    def search(batches):
        own, qm = shipped.value
        best_id, best_d = np.zeros((len(own), topk), np.int64), np.full((len(own), topk), np.inf)
        for batch in batches:
            if not batch.num_rows or not len(own):
                continue
            vid, x = batch.column(0).to_numpy(), matrix(batch.column(1), np.float64)
            few = max(1, PAIRS_AT_ONCE // batch.num_rows)
            for at in range(0, len(own), few):
                part = slice(at, at + few)
                d = np.round(scores(qm[part], x, metric), 9)
                if exclude_self:
                    d[own[part, None] == vid[None, :]] = np.inf
                v = np.concatenate([best_id[part], np.broadcast_to(vid, d.shape)], 1)
                d = np.concatenate([best_d[part], d], 1)
                order = np.lexsort((v, d), axis=1)[:, :topk]
                best_d[part], best_id[part] = np.take_along_axis(d, order, 1), np.take_along_axis(v, order, 1)
        r, c = np.nonzero(np.isfinite(best_d))
        yield pa.RecordBatch.from_arrays([pa.array(own[r]), pa.array(best_id[r, c]), pa.array(best_d[r, c])], names=["qid", "vec_id", "dist"])

    return vectors.select("vec_id", "vec").mapInArrow(search, "qid long, vec_id long, dist double")


def top_rank(found: DataFrame, topk: int) -> DataFrame:
    order = Window.partitionBy("qid").orderBy("dist", "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= topk).select("qid", "rank", "vec_id", "dist")


def exact_knn_sql(queries: DataFrame, vectors: DataFrame, topk: int = 10, exclude_self: bool = True) -> DataFrame:
    """The same with every pair as a row: distances by products of matrices, ranks by a window over all pairs."""
    found = pair_scores(queries, vectors, sq_dists, "dist", 9).where("dist is not null")
    return top_rank(found.where("qid <> vec_id") if exclude_self else found, topk)


PAIRS_A_BATCH = 1 << 18  #: rows of an Arrow batch of pairs


def pair_scores(queries: DataFrame, vectors: DataFrame, score, name: str, digits: int = 6) -> DataFrame:
    """(qid, vec_id, name): `score(q, x)` of every query and every vector, one product of matrices for each batch.

    The vectors are scanned once for each block of queries; a vector that is null or of another length has a null score.
    """
    spark = vectors.sparkSession

    def of_block(ids, q):
        shipped = spark.sparkContext.broadcast((ids, q))

        def pairs(batches):
            own, qm = shipped.value
            for batch in batches:
                if not batch.num_rows or not len(own):
                    continue
                vid, vec = batch.column(0), batch.column(1)
                fits = pa.compute.fill_null(pa.compute.equal(pa.compute.list_value_length(vec), qm.shape[1]), False)
                x = matrix(vec.filter(fits), np.float64)
                fits, few = fits.to_numpy(zero_copy_only=False), max(1, PAIRS_A_BATCH // batch.num_rows)
                for at in range(0, len(own), few):
                    part = own[at : at + few]
                    s = np.full((len(part), batch.num_rows), np.nan)
                    if len(x):
                        s[:, fits] = np.round(score(qm[at : at + few], x), digits) + 0.0
                    at_rows = pa.array(np.tile(np.arange(batch.num_rows), len(part)))
                    values = pa.array(s.ravel(), mask=np.tile(~fits, len(part)))
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(part, batch.num_rows)), vid.take(at_rows), values], names=["qid", "vec_id", name])

        return vectors.select("vec_id", "vec").mapInArrow(pairs, f"qid long, vec_id long, {name} double")

    return reduce(DataFrame.union, [of_block(ids, q) for ids, q in query_blocks(queries)])


def build_index(vectors: DataFrame, model: Model, path: str, cid_buckets: int = 4096, pruned: bool = True) -> DataFrame:
    """Lists as Parquet by cid_bucket, sorted by cid inside, so a search prunes folders and row groups.

    A vector and its list number come from one scan; nothing is joined.
    """
    carry = tuple(vectors.columns)
    if pruned and model.rotation is not None:
        placed = assign_pruned(vectors, model.centroids @ model.rotation, model.d1 or None, rotation=model.rotation, carry=carry)
    else:
        placed = assign_full(vectors, model.centroids, carry=carry)
    return write_lists(placed.drop("dist"), path, cid_buckets)


BUCKETS = "cid_buckets"  #: the key under which the column cid remembers the number of folders


def write_lists(placed: DataFrame, path: str, cid_buckets: int) -> DataFrame:
    """`placed` has cid beside the vectors' columns."""
    marked = placed.withColumn("cid", F.col("cid").alias("cid", metadata={BUCKETS: cid_buckets}))
    lists = marked.withColumn("cid_bucket", F.pmod("cid", F.lit(cid_buckets)))
    # a large cluster may hold a large share of the rows, so a list is spread over files by a salt of the id
    salt = F.pmod(F.xxhash64("vec_id"), F.lit(8))
    lists.repartition("cid_bucket", salt).sortWithinPartitions("cid_bucket", "cid").write.mode("overwrite").partitionBy("cid_bucket").parquet(path)
    return placed.sparkSession.read.parquet(path)


def only_lists(lists: DataFrame, cids: list[int]) -> DataFrame:
    """The wanted lists: folders are pruned by cid_bucket, row groups by cid."""
    if "cid_bucket" in lists.columns and (n := lists.schema["cid"].metadata.get(BUCKETS)):
        folders = sorted({c % n for c in cids})
        if len(folders) < n:
            lists = lists.where(F.col("cid_bucket").isin(folders))
    return lists.where(F.col("cid").isin(cids)) if len(cids) <= 10_000 else lists


def route(spark: SparkSession, queries: DataFrame, centroids: np.ndarray, nprobe: int) -> DataFrame:
    """(qid, cid, probe, dist): the nprobe nearest centroids of each query."""
    shipped = spark.sparkContext.broadcast(centroids)

    def near(batches):
        y = shipped.value
        for batch in batches:
            if batch.num_rows:
                d = np.round(sq_dists(matrix(batch.column(1), np.float64), y), 9)
                order = np.argsort(d, axis=1, kind="stable")[:, :nprobe]
                n, m = order.shape
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), m)), pa.array(order.ravel().astype(np.int32)), pa.array(np.tile(np.arange(1, m + 1, dtype=np.int32), n)), pa.array(np.take_along_axis(d, order, 1).ravel())], names=["qid", "cid", "probe", "dist"])

    return queries.select("qid", "qvec").mapInArrow(near, "qid long, cid int, probe int, dist double")


def index_search(queries: DataFrame, lists: DataFrame, centroids: np.ndarray, topk: int = 10, nprobe: int = 1, exclude_self: bool = True) -> DataFrame:
    """(qid, rank, vec_id, dist) from the lists of the nprobe nearest centroids; the lists are read once for each block of queries."""
    found = [block_search(ids, q, lists, centroids, topk, nprobe, exclude_self) for ids, q in query_blocks(queries)]
    return top_rank(reduce(DataFrame.union, found), topk)


def block_search(ids: np.ndarray, q: np.ndarray, lists: DataFrame, centroids: np.ndarray, topk: int, nprobe: int, exclude_self: bool) -> DataFrame:
    spark = lists.sparkSession
    d = np.round(sq_dists(q, centroids.astype(np.float64)), 9)
    probes = np.argsort(d, axis=1, kind="stable")[:, :nprobe]
    asking: dict[int, list[int]] = {}
    for i, row in enumerate(probes):
        for c in row:
            asking.setdefault(int(c), []).append(i)
    shipped = spark.sparkContext.broadcast((ids, q, {c: np.array(v) for c, v in asking.items()}))
    wanted = only_lists(lists, sorted(asking))

    def search(batches):
        own, qm, by_cid = shipped.value
        for batch in batches:
            if not batch.num_rows:
                continue
            cid, vid, x = batch.column(0).to_numpy(), batch.column(1).to_numpy(), matrix(batch.column(2), np.float64)
            out = []
            for c in np.unique(cid):
                asked = by_cid.get(int(c))
                if asked is None:
                    continue
                rows = np.flatnonzero(cid == c)
                few = max(1, PAIRS_AT_ONCE // len(rows))
                for at in range(0, len(asked), few):
                    qs = asked[at : at + few]
                    dist = np.round(sq_dists(qm[qs], x[rows]), 9)
                    if exclude_self:
                        dist[own[qs][:, None] == vid[rows][None, :]] = np.inf
                    keep = np.lexsort((np.broadcast_to(vid[rows], dist.shape), dist), axis=1)[:, :topk]
                    d_top = np.take_along_axis(dist, keep, 1)
                    r, k = np.nonzero(np.isfinite(d_top))
                    out.append((own[qs][r], vid[rows][keep[r, k]], d_top[r, k]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[i] for o in out])) for i in range(3)], names=["qid", "vec_id", "dist"])

    return wanted.select("cid", "vec_id", "vec").mapInArrow(search, "qid long, vec_id long, dist double")


def recall_at(found: DataFrame, truth: DataFrame, k: int, per_query: bool = False) -> DataFrame:
    """Mean share of a query's true top k that was found; a query that found nothing counts as 0."""
    wanted = truth.where(F.col("rank") <= k).select("qid", "vec_id")
    hits = wanted.join(found.where(F.col("rank") <= k).select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    each = wanted.select("qid").distinct().join(hits, "qid", "left").select("qid", (F.coalesce("hits", F.lit(0)) / F.lit(k)).alias("recall"))
    return each if per_query else each.agg(F.avg("recall").alias("recall"))


def membership_recall(assignment: DataFrame, probes: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Recall without searching: ranking inside probed lists is exact, so a true neighbour is found if its list is probed."""
    wanted = truth.where(F.col("rank") <= k).select("qid", "vec_id")
    located = assignment.select("vec_id", "cid").join(F.broadcast(wanted), "vec_id")
    hits = located.join(probes.select("qid", "cid"), ["qid", "cid"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    return wanted.select("qid").distinct().join(hits, "qid", "left").agg(F.avg(F.coalesce("hits", F.lit(0)) / F.lit(k)).alias("recall"))


def vectors_explored(probes: DataFrame, sizes: DataFrame, n: int) -> DataFrame:
    """Mean number of vectors in a query's probed lists, and its share of all."""
    each = probes.join(sizes.select("cid", "n"), "cid", "left").groupBy("qid").agg(F.sum(F.coalesce("n", F.lit(0))).alias("explored"))
    return each.agg(F.avg("explored").alias("explored"), (F.avg("explored") / F.lit(n)).alias("share"))


def probe_curve(queries: DataFrame, assignment: DataFrame, centroids: np.ndarray, truth: DataFrame, k: int, nprobes: list[int]) -> DataFrame:
    """(nprobe, recall, explored) from one routing at the largest nprobe."""
    spark = queries.sparkSession
    routed = route(spark, queries, centroids, max(nprobes))
    sizes = assignment.groupBy("cid").agg(F.count(F.lit(1)).alias("n"))
    wanted = truth.where(F.col("rank") <= k).select("qid", "vec_id")
    at = assignment.select("vec_id", "cid").join(F.broadcast(wanted), "vec_id").join(routed.select("qid", "cid", "probe"), ["qid", "cid"]).select("qid", "probe")
    levels = spark.createDataFrame([(int(p),) for p in nprobes], "nprobe int")
    queries_n = wanted.select("qid").distinct().agg(F.count(F.lit(1)).alias("nq"))
    hits = levels.join(F.broadcast(at.groupBy("probe").agg(F.count(F.lit(1)).alias("h"))), F.col("probe") <= F.col("nprobe"), "left").groupBy("nprobe").agg(F.coalesce(F.sum("h"), F.lit(0)).alias("hits"))
    work = routed.join(sizes, "cid", "left").groupBy("probe").agg(F.sum(F.coalesce("n", F.lit(0))).alias("w"))
    explored = levels.join(F.broadcast(work), F.col("probe") <= F.col("nprobe"), "left").groupBy("nprobe").agg(F.sum("w").alias("total"))
    return hits.join(explored, "nprobe").join(F.broadcast(queries_n)).select("nprobe", (F.col("hits") / (F.col("nq") * k)).alias("recall"), (F.col("total") / F.col("nq")).alias("explored"))


def least_nprobe(queries: DataFrame, assignment: DataFrame, centroids: np.ndarray, truth: DataFrame, k: int, recall: float = 0.9) -> tuple[int, float, float]:
    """(nprobe, recall, explored): the least level whose measured recall is enough; routing goes only as far as it must.

    Up to 64 lists every level is tried, beyond that levels an eighth apart; all lists together find everything.
    """
    lists, cap = len(centroids), 8
    while True:
        cap = min(cap, lists)
        levels = [1]
        while levels[-1] < cap:
            levels.append(min(cap, levels[-1] + max(1, levels[-1] // 8 if levels[-1] >= 64 else 1)))
        enough = probe_curve(queries, assignment, centroids, truth, k, levels).where(F.col("recall") >= recall).orderBy("nprobe").first()
        if enough or cap == lists:
            return (enough["nprobe"], enough["recall"], enough["explored"]) if enough else (lists, 1.0, float(assignment.count()))
        cap *= 4


def match_explored(curve: DataFrame, explored: float) -> DataFrame:
    """The least nprobe of a curve that explores as much as is asked for (its largest, if none does)."""
    enough = F.col("explored") >= F.lit(explored)
    return curve.orderBy(F.desc(enough.cast("int")), F.when(enough, F.col("nprobe")).otherwise(-F.col("nprobe"))).limit(1)
