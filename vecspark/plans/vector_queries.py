"""Queries of the vector methods on the given tables, each with the SQL that gives the same rows where SQL can."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.functions import columns as vc
from vecspark.functions import kernels, udx
from vecspark.functions.kernels import BatchPlan
from vecspark.operators import assign, measures
from vecspark.operators.clustering import BoundedKMeans, LloydKMeans, MiniBatchKMeans, PhasedKMeans, PivotKMeans, TwoLevelKMeans, adjust_head, repair_empty, share_k
from vecspark.operators.index import build_index, exact_knn, exact_knn_sql, index_search, least_nprobe, match_explored, membership_recall, pair_scores, probe_curve, recall_at, route, vectors_explored, write_lists
from vecspark.operators.model import Model
from vecspark.operators.rotation import random_rotation, rotate, rotate_sql
from vecspark.operators.seeding import default_k, every_20th, init_kmeanspp, init_random, sample_rows, start_matrix
from vecspark.operators.stopping import Convergence, RecallPlateau, plateaus
from vecspark.sources import featurize
from vecspark.sources.files import settle, shared_path
from vecspark.sources.vectors import embeddings, normalise, read_table, validate

K, SEED, D, D1, STEP, NQ, TOPK = 22, 0, 64, 8, 8, 100, 10
PROBES = 18  #: lists of the K around random rows that a search probes; tests measure its recall, 0.9 or more

QUERIES: dict = {}
ORACLES: dict = {}

V = "v AS (SELECT vec_id, embedding::DOUBLE[] AS v, label FROM embeddings)"


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql() if callable(sql) else sql
        return f

    return keep


def start_sql(k: int = K, seed: int = SEED) -> str:
    return f"c0 AS (SELECT CAST(row_number() OVER (ORDER BY md5(vec_id || ':{seed}'), vec_id) - 1 AS INTEGER) AS cid, v AS y FROM v QUALIFY row_number() OVER (ORDER BY md5(vec_id || ':{seed}'), vec_id) <= {k})"


def assign_cte(i: int) -> str:
    return f"a{i} AS (SELECT vec_id, v, label, cid, d FROM (SELECT v.vec_id, v.v, v.label, c.cid, pow(list_distance(v.v, c.y), 2) AS d FROM v, c{i} c) QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY round(d, 9), cid) = 1)"


def update_cte(i: int) -> str:
    return f"""m{i} AS (SELECT cid, list(m ORDER BY pos) AS y FROM (SELECT cid, pos, avg(x) AS m FROM (SELECT cid, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM a{i}) GROUP BY 1, 2) GROUP BY 1),
c{i + 1} AS (SELECT c.cid, coalesce(m.y, c.y) AS y FROM c{i} c LEFT JOIN m{i} m USING (cid))"""


def lloyd_sql(steps: int, tail: str, k: int = K, seed: int = SEED) -> str:
    parts = [V, start_sql(k, seed)]
    for i in range(steps):
        parts += [assign_cte(i), update_cte(i)]
    parts.append(assign_cte(steps))
    return "WITH " + ",\n".join(parts) + "\n" + tail


SIZES = f"sz AS (SELECT c.cid, count(a.vec_id) AS n FROM c0 c LEFT JOIN a0 a USING (cid) GROUP BY 1)"


def sizes_sql(tail: str) -> str:
    return f"WITH {V}, {start_sql()}, {assign_cte(0)}, {SIZES} {tail}"


ASSIGNED = "SELECT vec_id, cid, round(d, 6) AS dist FROM a{0}"


def rounded(assignment: DataFrame) -> DataFrame:
    return assignment.select("vec_id", "cid", F.round("dist", 6).alias("dist"))


def begin(spark, sf_dir, k: int = K):
    v = embeddings(spark, sf_dir)
    return v, start_matrix(v, k, SEED)


def lloyd(spark, sf_dir, steps: int) -> tuple[DataFrame, np.ndarray]:
    v, y = begin(spark, sf_dir)
    if not steps:
        return v, y
    return v, LloydKMeans(k=K, max_iter=steps, empty="keep", dtype=np.float64, seed=SEED).fit(v, y).centroids


# ---- vector columns ---------------------------------------------------------------------------------------------

@query("vec_norms", f"WITH {V} SELECT vec_id, round(list_inner_product(v, v), 6) AS sq FROM v")
def _(spark, sf_dir):
    return embeddings(spark, sf_dir).select("vec_id", F.round(vc.sq_norm("vec"), 6).alias("sq"))


@query("partial_norms", f"WITH {V} SELECT vec_id, round(list_inner_product(v[:8], v[:8]), 6) AS head_sq, round(list_inner_product(v[9:], v[9:]), 6) AS tail_sq FROM v")
def _(spark, sf_dir):
    return embeddings(spark, sf_dir).select("vec_id", F.round(vc.sq_norm(vc.head("vec", 8)), 6).alias("head_sq"), F.round(vc.sq_norm(vc.tail("vec", 8, D)), 6).alias("tail_sq"))


@query("prefix_norms", f"WITH {V} SELECT vec_id, CAST(n AS INTEGER) AS n, round(list_inner_product(v[:n], v[:n]), 6) AS sq FROM v, range(8, 65, 8) t(n)")
def _(spark, sf_dir):
    return embeddings(spark, sf_dir).select("vec_id", F.posexplode(vc.prefix_sq("vec", 8, D)).alias("i", "s")).select("vec_id", ((F.col("i") + 1) * 8).cast("int").alias("n"), F.round("s", 6).alias("sq"))


PAIRS = f"WITH {V}, q AS (SELECT vec_id AS qid, v AS qv FROM v WHERE vec_id % 20 = 0)"
ASKED_AT_ONCE = 1000  #: queries in one broadcast row


def asked(v):
    """The query rows in blocks, each one row to broadcast."""
    held = v.where("vec_id % 20 = 0").groupBy(F.floor(F.col("vec_id") / (20 * ASKED_AT_ONCE)).alias("block")).agg(F.collect_list(F.struct(F.col("vec_id").alias("qid"), F.col("vec").alias("qv"))).alias("qs"))
    return F.broadcast(held.select("qs"))


def query_pairs(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    return v.join(asked(v)).select("vec_id", "vec", F.explode("qs").alias("q")).select("vec_id", "vec", "q.qid", "q.qv")


def scored_pairs(v, score, name: str):
    """The same pairs with a score that matrix products give, norms taken once a row."""
    return pair_scores(every_20th(v), v, score, name)


def pair_query(name: str, tail: str):
    """A query of the rows whose id is divisible by 20 against all rows."""
    return query(name, PAIRS + tail)


@pair_query("l2_array", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return query_pairs(spark, sf_dir).select("qid", "vec_id", F.round(vc.l2("vec", "qv"), 6).alias("d"))


@pair_query("l2_by_inner_product", " SELECT qid, vec_id, round(greatest(list_inner_product(v, v) + list_inner_product(qv, qv) - 2 * list_inner_product(v, qv), 0), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return scored_pairs(embeddings(spark, sf_dir), kernels.sq_dists, "d")


@pair_query("head_plus_tail", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return scored_pairs(embeddings(spark, sf_dir), lambda q, x: kernels.sq_dists(q[:, :8], x[:, :8]) + kernels.sq_dists(q[:, 8:], x[:, 8:]), "d")


@pair_query("partial_l2_d1", " SELECT qid, vec_id, round(pow(list_distance(v[:8], qv[:8]), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return query_pairs(spark, sf_dir).select("qid", "vec_id", F.round(vc.l2(vc.head("vec", 8), vc.head("qv", 8)), 6).alias("d"))


@pair_query("dot_array", " SELECT qid, vec_id, round(list_inner_product(v, qv), 6) AS s FROM v, q")
def _(spark, sf_dir):
    return query_pairs(spark, sf_dir).select("qid", "vec_id", F.round(vc.dot("vec", "qv"), 6).alias("s"))


@pair_query("cosine_array", " SELECT qid, vec_id, round(list_cosine_similarity(v, qv), 6) AS s FROM v, q")
def _(spark, sf_dir):
    return scored_pairs(embeddings(spark, sf_dir), kernels.cosines, "s")


@pair_query("udf_distance", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return query_pairs(spark, sf_dir).select("qid", "vec_id", F.round(udx.vec_l2("vec", "qv"), 6).alias("d"))


@query("blocks_of_vector", f"WITH {V} SELECT vec_id, CAST(b AS INTEGER) AS blk, len(v[8 + b * 16 + 1 : least(64, 8 + b * 16 + 16)]) AS n, round(list_sum(v[8 + b * 16 + 1 : least(64, 8 + b * 16 + 16)]), 6) AS s FROM v, range(4) t(b)")
def _(spark, sf_dir):
    each = embeddings(spark, sf_dir).select("vec_id", F.explode(vc.blocks("vec", 8, D, 16)).alias("b"))
    return each.select("vec_id", "b.blk", F.size("b.vals").cast("long").alias("n"), F.round(vc.total(F.col("b.vals").cast("array<double>")), 6).alias("s"))


@query("udtf_blocks", f"WITH {V} SELECT vec_id, CAST(b AS INTEGER) AS blk, len(v[8 + b * 16 + 1 : least(64, 8 + b * 16 + 16)]) AS n FROM v, range(4) t(b)")
def _(spark, sf_dir):
    udx.register(spark)
    embeddings(spark, sf_dir).createOrReplaceTempView("vecspark_vectors")
    return spark.sql("SELECT vec_id, blk, CAST(size(vals) AS BIGINT) AS n FROM vecspark_vectors, LATERAL dimension_blocks(vec, 8, 16)")


@query("theta_table", lambda: lloyd_sql(0, "SELECT vec_id, CAST(b AS INTEGER) AS b, round(CASE WHEN b >= 64 THEN d ELSE d * (b / 64.0::DOUBLE) * pow(1 + 2.1::DOUBLE / sqrt(b), 2) END, 6) AS theta FROM a0, range(8, 65, 8) t(b)"))
def _(spark, sf_dir):
    """The test's limits on a row's partial distances, where its threshold is the distance to the nearest start."""
    v, y = begin(spark, sf_dir)
    each = assign.assign_full(v, y, dtype=np.float64).select("vec_id", "dist", F.explode(F.sequence(F.lit(8), F.lit(D), F.lit(8))).alias("b"))
    return each.select("vec_id", "b", F.round(vc.limit(F.col("b").cast("double"), D, F.col("dist"), 2.1), 6).alias("theta"))


@query("space_model_table", "SELECT label, n, d, k, 2 * n * d + k * d + 3 * n + k AS numbers FROM (SELECT label, count(*) AS n, CAST(max(len(embedding)) AS BIGINT) AS d, CAST(floor(4 * sqrt(count(*))) AS BIGINT) AS k FROM embeddings GROUP BY 1)")
def _(spark, sf_dir):
    t = read_table(spark, sf_dir, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.max(F.size("embedding")).cast("long").alias("d"))
    t = t.withColumn("k", F.floor(4 * F.sqrt("n")))
    return t.select("label", "n", "d", "k", measures.space_model(F.col("n"), F.col("d"), F.col("k")).alias("numbers"))


@query("default_k_table", "SELECT l_suppkey, count(*) AS n, CAST(floor(4 * sqrt(count(*))) AS BIGINT) AS k FROM lineitem GROUP BY 1")
def _(spark, sf_dir):
    t = read_table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    return t.select("l_suppkey", "n", F.udf(lambda n: default_k(n), "long")("n").alias("k"))


@query("default_k", "SELECT count(*) AS n, CAST(floor(4 * sqrt(count(*))) AS BIGINT) AS k FROM embeddings")
def _(spark, sf_dir):
    return embeddings(spark, sf_dir).agg(F.count(F.lit(1)).alias("n")).select("n", F.floor(4 * F.sqrt("n")).alias("k"))


@query("validate_vectors", "SELECT vec_id, CAST(NULL AS VARCHAR) AS flaw FROM embeddings")
def _(spark, sf_dir):
    return validate(embeddings(spark, sf_dir), D, "quarantine").select("vec_id", "flaw")


@query("normalise_vectors", f"WITH {V} SELECT vec_id, round(list_inner_product(v, v), 4) AS sq FROM v")
def _(spark, sf_dir):
    return normalise(embeddings(spark, sf_dir)).select("vec_id", F.round(vc.sq_norm("vec"), 4).alias("sq"))


# ---- rotation, seeding ------------------------------------------------------------------------------------------

def _pair_dists(v):
    return v.join(asked(v)).select("vec_id", "vec", F.explode("qs").alias("q")).select(F.col("q.qid").alias("qid"), "vec_id", F.round(vc.l2("vec", "q.qv"), 6).alias("d"))


@pair_query("rotation_preserves_l2", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return scored_pairs(rotate(embeddings(spark, sf_dir), random_rotation(D, 3), np.float64), kernels.sq_dists, "d")


@pair_query("rotate_sql", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q")
def _(spark, sf_dir):
    return _pair_dists(rotate_sql(embeddings(spark, sf_dir), random_rotation(D, 3)))


@query("init_random_md5", f"WITH {V}, {start_sql()} SELECT cid, round(list_sum(y), 6) AS s FROM c0")
def _(spark, sf_dir):
    return init_random(embeddings(spark, sf_dir), K, SEED).select("cid", F.round(vc.total(F.col("centroid")), 6).alias("s"))


U = "((CAST('0x' || substr(md5(a.vec_id || ':0:' || r.i), 1, 12) AS BIGINT) + 1)::DOUBLE / 281474976710657.0::DOUBLE)"


@query("kmeanspp", f"""WITH RECURSIVE {V}, r AS (
  SELECT 1 AS i, [vec_id] AS ids FROM (SELECT vec_id FROM v ORDER BY md5(vec_id || ':0'), vec_id LIMIT 1)
  UNION ALL
  SELECT i + 1, list_append(ids, (SELECT vec_id FROM (SELECT a.vec_id, min(pow(list_distance(a.v, b.v), 2)) AS d, any_value({U}) AS u FROM v a, v b WHERE list_contains(r.ids, b.vec_id) GROUP BY 1) ORDER BY CASE WHEN d > 1e-12 THEN -ln(u) / d ELSE 'inf'::DOUBLE END, vec_id LIMIT 1)) FROM r WHERE i < 8
) SELECT CAST(pos - 1 AS INTEGER) AS cid, round(list_sum(v.v), 6) AS s FROM (SELECT unnest(ids) AS vec_id, generate_subscripts(ids, 1) AS pos FROM r WHERE i = 8) JOIN v USING (vec_id)""")
def _(spark, sf_dir):
    y = init_kmeanspp(embeddings(spark, sf_dir), 8, SEED)
    return spark.createDataFrame([(i, round(float(c.sum()), 6)) for i, c in enumerate(y)], "cid int, s double")


@query("kmeanspp_farthest", f"""WITH RECURSIVE {V}, r AS (
  SELECT 1 AS i, [vec_id] AS ids FROM (SELECT vec_id FROM v ORDER BY md5(vec_id || ':0'), vec_id LIMIT 1)
  UNION ALL
  SELECT i + 1, list_append(ids, (SELECT vec_id FROM (SELECT a.vec_id, min(pow(list_distance(a.v, b.v), 2)) AS d FROM v a, v b WHERE list_contains(r.ids, b.vec_id) GROUP BY 1) ORDER BY round(d, 9) DESC, vec_id LIMIT 1)) FROM r WHERE i < 4
) SELECT CAST(pos - 1 AS INTEGER) AS cid, round(list_sum(v.v), 6) AS s FROM (SELECT unnest(ids) AS vec_id, generate_subscripts(ids, 1) AS pos FROM r WHERE i = 4) JOIN v USING (vec_id)""")
def _(spark, sf_dir):
    y = init_kmeanspp(embeddings(spark, sf_dir), 4, SEED, greedy_far=True)
    return spark.createDataFrame([(i, round(float(c.sum()), 6)) for i, c in enumerate(y)], "cid int, s double")


@query("sample_md5", "SELECT vec_id FROM embeddings WHERE CAST('0x' || substr(md5(vec_id || ':0'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE < 0.3")
def _(spark, sf_dir):
    return sample_rows(embeddings(spark, sf_dir), 0.3).select("vec_id")


@query("sample_cap_256k", "SELECT vec_id FROM embeddings WHERE CAST('0x' || substr(md5(vec_id || ':0'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE < least(1.0, 256.0 / (SELECT count(*) FROM embeddings))")
def _(spark, sf_dir):
    return sample_rows(embeddings(spark, sf_dir), max_per_centroid=256, k=1).select("vec_id")


# ---- assignment -------------------------------------------------------------------------------------------------

A0 = lloyd_sql(0, ASSIGNED.format(0))


@query("assign_full", A0)
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return rounded(assign.assign_full(v, y, dtype=np.float64))


@query("assign_sliced", A0)
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return rounded(assign.assign_full(v, y, dtype=np.float64, limit=5 * D * 8))


@query("assign_small_batches", A0)
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return rounded(assign.assign_full(v, y, BatchPlan(37, 5), np.float64))


@query("assign_sql", A0)
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    return rounded(assign.assign_sql(v, init_random(v, K, SEED)))


def _rotated(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    r = random_rotation(D, 3)
    return rotate(v, r, np.float64), y @ r


@query("assign_rotated", A0)
def _(spark, sf_dir):
    return rounded(assign.assign_full(*_rotated(spark, sf_dir), dtype=np.float64))


def pruned(name: str, **options):
    @query(name, A0)
    def _(spark, sf_dir):
        v, y = _rotated(spark, sf_dir)
        return rounded(assign.assign_pruned(v, y, D1, STEP, np.inf, dtype=np.float64, **options))


pruned("assign_pruned_exact_head_nearest_seed")
pruned("assign_pruned_exact_pairs", refinement="pairs")
pruned("assign_pruned_exact_progressive_off", refinement="pairs", progressive=False)
pruned("assign_pruned_exact_rows_layout", refinement="pairs", layout="rows")
pruned("assign_pruned_exact_first_batch_seed", seed_mode="first_batch", plan=BatchPlan(4096, 7))
pruned("assign_pruned_exact_sliced", limit=5 * D * 4)


@query("assign_pruned_exact", A0)
def _(spark, sf_dir):
    v, y = _rotated(spark, sf_dir)
    prev = assign.assign_full(v, y[: K // 2], dtype=np.float64)
    return rounded(assign.assign_pruned(v, y, D1, STEP, np.inf, prev=prev, dtype=np.float64))


@query("assign_pruned_default")
def _(spark, sf_dir):
    return rounded(assign.assign_pruned(*_rotated(spark, sf_dir), D1, STEP))


@query("assign_pruned_disagreement")
def _(spark, sf_dir):
    v, y = _rotated(spark, sf_dir)
    return measures.assignment_diff(assign.assign_full(v, y), assign.assign_pruned(v, y, D1, STEP))


QUERY_CTE = "qs AS (SELECT vec_id AS qid, v AS qv FROM v WHERE vec_id % 20 = 0)"


def knn_cte(score: str) -> str:
    return f"tr AS (SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) AS INTEGER) AS rank, vec_id, s FROM (SELECT q.qid, v.vec_id, round({score}, 9) AS s FROM v, qs q WHERE v.vec_id <> q.qid) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) <= {TOPK})"


L2 = "pow(list_distance(v.v, q.qv), 2)"


# ---- iterations -------------------------------------------------------------------------------------------------

for steps in (1, 2, 3):

    @query(f"lloyd_{steps}", lloyd_sql(steps, ASSIGNED.format(steps)))
    def _(spark, sf_dir, steps=steps):
        return rounded(assign.assign_full(*lloyd(spark, sf_dir, steps), dtype=np.float64))


@query("phased_3_exact", lloyd_sql(3, ASSIGNED.format(3)))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    method = PhasedKMeans(k=K, max_iter=3, empty="keep", epsilon0=np.inf, dtype=np.float64, seed=SEED)
    return rounded(method.transform(v, method.fit(v, y)))


for variant in ("elkan", "hamerly"):

    @query(f"{variant}_3", lloyd_sql(3, ASSIGNED.format(3)))
    def _(spark, sf_dir, variant=variant):
        v = embeddings(spark, sf_dir)
        return rounded(assign.assign_full(v, BoundedKMeans(K, 3, variant, SEED).fit(v).centroids, dtype=np.float64))


for variant in ("each", "all"):

    @query(f"pivot_{variant}_2", lloyd_sql(2, ASSIGNED.format(2)))
    def _(spark, sf_dir, variant=variant):
        v, y = begin(spark, sf_dir)
        return rounded(assign.assign_full(v, PivotKMeans(K, 2, empty="keep", variant=variant).fit(v, y).centroids, dtype=np.float64))


@query("phased_3_previous", lloyd_sql(3, ASSIGNED.format(3)))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    method = PhasedKMeans(k=K, max_iter=3, empty="keep", epsilon0=np.inf, dtype=np.float64, seed=SEED, seed_mode="previous")
    return rounded(method.transform(v, method.fit(v, y)))


@query("changed_labels", lloyd_sql(2, """SELECT CAST(i AS INTEGER) AS iter, CASE i WHEN 2 THEN (SELECT count(*) FROM a0 JOIN a1 USING (vec_id) WHERE a0.cid <> a1.cid) WHEN 3 THEN (SELECT count(*) FROM a1 JOIN a2 USING (vec_id) WHERE a1.cid <> a2.cid) END AS changed FROM range(1, 4) t(i)"""))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    model = LloydKMeans(k=K, max_iter=3, empty="keep", dtype=np.float64, stop=[Convergence(None, -1)]).fit(v, y)
    return model.history_frame(spark).select("iter", "changed")


def recall_sql(i: int) -> str:
    near = f"SELECT qid, cid FROM (SELECT q.qid, c.cid, round(pow(list_distance(c.y, q.qv), 2), 9) AS s FROM c{i + 1} c, qs q) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, cid) <= 3"
    return f"SELECT CAST({i + 1} AS INTEGER) AS iter, round((SELECT count(*) FROM tr JOIN a{i} USING (vec_id) JOIN ({near}) p ON p.qid = tr.qid AND p.cid = a{i}.cid) / (10.0::DOUBLE * (SELECT count(*) FROM qs)), 9) AS recall"


@query("recall_stop_supplied", lambda: lloyd_sql(3, "").rstrip() + f",\n{QUERY_CTE}, {knn_cte(L2)} " + " UNION ALL ".join(recall_sql(i) for i in range(3)))
def _(spark, sf_dir):
    """Supplied queries and truth; the series of the phased method is that of plain iterations."""
    v, y = begin(spark, sf_dir)
    queries = every_20th(v)
    rule = RecallPlateau(-1.0, topk=TOPK, probe_frac=0.1, queries=queries, truth=exact_knn(queries, v, TOPK))
    model = PhasedKMeans(k=K, max_iter=3, empty="keep", epsilon0=np.inf, dtype=np.float64, stop=[rule]).fit(v, y)
    return model.history_frame(spark).select("iter", F.round("recall", 9).alias("recall"))


@query("centroid_update_sql", lloyd_sql(1, "SELECT c1.cid, coalesce(t.n, 0) AS n, round(list_sum(c1.y), 6) AS s, round(c1.y[1], 6) AS first FROM c1 LEFT JOIN (SELECT cid, count(*) AS n FROM a0 GROUP BY 1) t USING (cid)"))
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    start = init_random(v, K, SEED)
    new = assign.update_centroids_sql(v, assign.assign_sql(v, start), start)
    return new.select("cid", "n", F.round(vc.total(F.col("centroid")), 6).alias("s"), F.round(F.col("centroid")[0], 6).alias("first"))


@query("phased_default")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    method = PhasedKMeans(max_iter=5, seed=SEED)
    return method.transform(v, method.fit(v))


@query("phased_history")
def _(spark, sf_dir):
    return PhasedKMeans(k=K, max_iter=6, seed=SEED, stop=[RecallPlateau(topk=TOPK, n_queries=NQ, probe_frac=0.1)]).fit(embeddings(spark, sf_dir)).history_frame(spark)


@query("two_level")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    method = TwoLevelKMeans(k=48)
    return method.transform(v, method.fit(v))


@query("refine")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    method = TwoLevelKMeans(k=48, refine_iter=2)
    return method.transform(v, method.fit(v))


def batch_sql(i: int, share: float | None) -> str:
    """One mini-batch step: rows of hash share `share` (all, if None) move the centroids c{i} to c{i + 1}, with their counts."""
    rows = "v" if share is None else f"(SELECT * FROM v WHERE CAST('0x' || substr(md5(vec_id || ':{i + 1}'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE < {share})"
    return f"""b{i} AS (SELECT vec_id, v, cid FROM (SELECT v.vec_id, v.v, c.cid, pow(list_distance(v.v, c.y), 2) AS d FROM {rows} v, c{i} c) QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY round(d, 9), cid) = 1),
m{i} AS (SELECT cid, any_value(n) AS n, list(m ORDER BY pos) AS y FROM (SELECT cid, pos, avg(x) AS m, count(*) AS n FROM (SELECT cid, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM b{i}) GROUP BY 1, 2) GROUP BY 1),
c{i + 1} AS (SELECT c.cid, c.n + coalesce(m.n, 0) AS n, CASE WHEN m.n IS NULL THEN c.y ELSE list_transform(list_zip(c.y, m.y), lambda p: p[1] + (p[2] - p[1]) * m.n / (c.n + m.n)::DOUBLE) END AS y FROM c{i} c LEFT JOIN m{i} m USING (cid))"""


def minibatch_sql(steps: int, share: float | None) -> str:
    start = start_sql().replace("c0 AS (SELECT", "c0 AS (SELECT 0::BIGINT AS n,", 1)
    return "WITH " + ",\n".join([V, start, *(batch_sql(i, share) for i in range(steps))]) + f" SELECT cid, n, round(list_sum(y), 5) AS s FROM c{steps}"


def centroid_rows(spark, y, counts) -> DataFrame:
    return spark.createDataFrame([(i, int(n), round(float(c.sum()), 5)) for i, (c, n) in enumerate(zip(y, counts, strict=True))], "cid int, n long, s double")


@query("minibatch", minibatch_sql(3, 0.4))
def _(spark, sf_dir):
    model = MiniBatchKMeans(K, batches=3, batch_frac=0.4, epsilon0=np.inf).fit(embeddings(spark, sf_dir))
    return centroid_rows(spark, model.centroids, model.counts)


@query("ml_kmeans")
def _(spark, sf_dir):
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = embeddings(spark, sf_dir).select("vec_id", array_to_vector("vec").alias("features"))
    return KMeans(k=K, maxIter=5, initMode="random", seed=1).fit(v).transform(v).select("vec_id", F.col("prediction").alias("cid"))


def series(spark, sf_dir, x) -> DataFrame:
    """(user_id, x): a number of each event of a user, in the order of time."""
    rows = F.sort_array(F.collect_list(F.struct("ts", "event_id", x.alias("x"))))
    return read_table(spark, sf_dir, "events").groupBy("user_id").agg(rows.alias("rows")).select("user_id", F.col("rows.x").alias("x"))


NEXT_D1 = "least(512, greatest(8, CASE WHEN {r} < 0.95::DOUBLE THEN ceil({d} * 1.2::DOUBLE) WHEN {r} > 0.97::DOUBLE THEN floor({d} * 0.8::DOUBLE) ELSE {d} END))"


@query("controller_trace", f"""WITH s AS (SELECT user_id, list(1 - value / 1000 ORDER BY ts, event_id) AS rates FROM events GROUP BY 1),
w AS (SELECT user_id, rates, list_reduce(list_prepend([64::DOUBLE], list_transform(rates, lambda r: [r])), lambda acc, x: list_append(acc, {NEXT_D1.format(r="x[1]", d="acc[-1]")})) AS widths FROM s)
SELECT user_id, CAST(i AS INTEGER) AS step, rates[i] AS rate, CAST(widths[i] AS INTEGER) AS d1, CAST(widths[i + 1] AS INTEGER) AS next_d1 FROM (SELECT *, unnest(range(1, len(rates) + 1)) AS i FROM w)""")
def _(spark, sf_dir):
    """A user's events as a series of pruning rates, and the head widths that the controller goes through."""

    def trace(rates):
        widths = [64]
        for rate in rates:
            widths.append(adjust_head(widths[-1], rate, 512))
        return widths

    t = series(spark, sf_dir, 1 - F.col("value") / 1000).withColumn("widths", F.udf(trace, "array<int>")("x"))
    each = t.select("user_id", F.posexplode(F.arrays_zip("x", F.slice("widths", 1, F.size("x")).alias("d1"), F.slice("widths", 2, F.size("x")).alias("next_d1"))).alias("i", "r"))
    return each.select("user_id", (F.col("i") + 1).alias("step"), F.col("r.x").alias("rate"), "r.d1", "r.next_d1")


@query("patience_trace", """WITH r AS (SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS INTEGER) AS i, value / 1000 AS recall FROM events),
g AS (SELECT user_id, i, recall, recall - max(recall) OVER (PARTITION BY user_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS gain, recall - lag(recall, 2) OVER (PARTITION BY user_id ORDER BY i) AS gain2 FROM r)
SELECT user_id, i, recall, coalesce(gain <= .005::DOUBLE AND lag(gain) OVER (PARTITION BY user_id ORDER BY i) <= .005::DOUBLE, false) AS stop_patience, coalesce(gain2 <= .005::DOUBLE, false) AS stop_window FROM g""")
def _(spark, sf_dir):
    """A user's events as a series of recalls, and where either rule would stop."""

    stops = F.udf(lambda x: [*zip(plateaus(x, 0.005), plateaus(x, 0.005, rule="window"), strict=True)], "array<struct<patience: boolean, window: boolean>>")
    t = series(spark, sf_dir, F.col("value") / 1000).withColumn("stop", stops("x"))
    each = t.select("user_id", F.posexplode(F.arrays_zip("x", "stop")).alias("i", "r"))
    return each.select("user_id", (F.col("i") + 1).alias("i"), F.col("r.x").alias("recall"), F.col("r.stop.patience").alias("stop_patience"), F.col("r.stop.window").alias("stop_window"))


@query("farthest_points", lloyd_sql(0, "SELECT CAST(20 + row_number() OVER (ORDER BY round(d, 9) DESC, vec_id) - 1 AS INTEGER) AS cid, round(list_sum(v), 6) AS s FROM a0 ORDER BY round(d, 9) DESC, vec_id LIMIT 2").replace(f"<= {K})", "<= 20)"))
def _(spark, sf_dir):
    """Two clusters that nothing is near to take the rows that are farthest from their centroids."""
    v, y = begin(spark, sf_dir)
    y[20:] = 1e6
    new = LloydKMeans(k=K, max_iter=1, empty="farthest", dtype=np.float64).fit(v, y).centroids[20:]
    return spark.createDataFrame([(20 + i, round(float(c.sum()), 6)) for i, c in enumerate(new)], "cid int, s double")


@query("split_empty", f"""WITH {V}, n AS (SELECT label, count(*) AS n FROM v GROUP BY 1),
m AS (SELECT label, pos, avg(x) AS x, CASE WHEN pos % 2 = 1 THEN 1 ELSE -1 END AS sign FROM (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM v) GROUP BY 1, 2),
y AS (SELECT label, cid, pos, x + (2 * cid - 1) * sign * CASE WHEN x <> 0 THEN abs(x) ELSE 1e-6::DOUBLE END / 1024 AS x FROM m JOIN n USING (label), (VALUES (0), (1)) t(cid) WHERE n.n > 1)
SELECT label, CAST(cid AS INTEGER) AS cid, CAST(CASE cid WHEN 1 THEN n // 2 ELSE n - n // 2 END AS BIGINT) AS n, round(sum(y.x), 6) AS s, round(max(CASE WHEN pos = 1 THEN y.x END), 6) AS first FROM y JOIN n USING (label) GROUP BY label, cid, n""")
def _(spark, sf_dir):
    """One cluster a label of more than one row, and beside it an empty one, which takes half of it, a perturbation of 1/1024 apart."""
    cells = read_table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("pos", "x")).groupBy("label", "pos").agg(F.avg(F.col("x").cast("double")).alias("x"), F.count(F.lit(1)).alias("n"))
    out = []
    for r in cells.groupBy("label").agg(F.max("n").alias("n"), F.array_sort(F.collect_list(F.struct("pos", "x"))).alias("y")).where("n > 1").collect():
        mean = np.array([c["x"] for c in r["y"]])
        y, n = repair_empty(np.stack([mean, np.zeros_like(mean)]), np.array([r["n"], 0]), seed=1)
        out += [(r["label"], i, int(m), round(float(c.sum()), 6), round(float(c[0]), 6)) for i, (c, m) in enumerate(zip(y, n, strict=True))]
    return spark.createDataFrame(out, "label int, cid int, n long, s double, first double")


SHARED = 100  #: fine clusters that the coarse ones share


@query("two_level_shares", lambda: sizes_sql(f""", live AS (SELECT cid, n, {SHARED} * n / sum(n) OVER ()::DOUBLE AS exact FROM sz WHERE n > 0), o AS (SELECT *, least(n, greatest(1, floor(exact))) AS o FROM live),
p AS (SELECT *, {SHARED} - sum(o) OVER () AS to_give, row_number() OVER (PARTITION BY o < n ORDER BY exact - o DESC, cid) AS more, row_number() OVER (PARTITION BY o > 1 ORDER BY exact - o, cid) AS less FROM o)
SELECT 'proportional' AS rule, cid AS meso, CAST(o + CASE WHEN to_give > 0 AND o < n AND more <= to_give THEN 1 WHEN to_give < 0 AND o > 1 AND less <= -to_give THEN -1 ELSE 0 END AS INTEGER) AS k FROM p
UNION ALL SELECT 'sqrt', cid, CAST(greatest(1, floor(sqrt(n))) AS INTEGER) FROM live"""))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    sizes = {r["cid"]: r["n"] for r in measures.cluster_sizes(assign.assign_full(v, y, dtype=np.float64), K).collect()}
    return spark.createDataFrame([(rule, m, k) for rule in ("proportional", "sqrt") for m, k in share_k(sizes, SHARED, rule).items()], "rule string, meso int, k int")


@query("coarse_then_codes")
def _(spark, sf_dir):
    from vecspark.operators.quantise import coarse_then_codes

    return coarse_then_codes(embeddings(spark, sf_dir), k=16, parts=4, codes=16, iterations=3)[1]


@query("tile_grid", f"""WITH {V}, t AS (SELECT vec_id, ntile(4) OVER (ORDER BY v[1], vec_id) - 1 AS a, ntile(4) OVER (ORDER BY v[2], vec_id) - 1 AS b FROM v) SELECT vec_id, a || '_' || b AS tile FROM t""")
def _(spark, sf_dir):
    from vecspark.operators.quantise import tile_assign

    return tile_assign(embeddings(spark, sf_dir), dims=2, tiles=4)


for kind in ("prefix", "pca"):

    @query(f"reduced_{kind}_clusters")
    def _(spark, sf_dir, kind=kind):
        from vecspark.operators.reduce import reduce_dimensions

        low = reduce_dimensions(embeddings(spark, sf_dir), 16, kind)
        method = PhasedKMeans(k=K, max_iter=3, seed=SEED)
        return method.transform(low, method.fit(low))


# ---- search and measures ----------------------------------------------------------------------------------------

def knn_query(name: str, metric: str, score: str):
    @query(name, f"WITH {V}, {QUERY_CTE}, {knn_cte(score)} SELECT qid, rank, vec_id, round(s, 6) AS dist FROM tr")
    def _(spark, sf_dir):
        v = embeddings(spark, sf_dir)
        return exact_knn(every_20th(v), v, TOPK, metric).withColumn("dist", F.round("dist", 6))


knn_query("exact_knn_10", "l2", L2)
knn_query("exact_knn_ip", "ip", "-list_inner_product(v.v, q.qv)")
knn_query("exact_knn_cosine", "cosine", "1 - list_cosine_similarity(v.v, q.qv)")


@query("exact_knn_sql", f"WITH {V}, {QUERY_CTE}, {knn_cte(L2)} SELECT qid, rank, vec_id, round(s, 6) AS dist FROM tr")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    return exact_knn_sql(every_20th(v), v, TOPK).withColumn("dist", F.round("dist", 6))


def probe_cte(nprobe: int) -> str:
    return f"pr AS (SELECT qid, cid, CAST(row_number() OVER (PARTITION BY qid ORDER BY s, cid) AS INTEGER) AS probe, s FROM (SELECT q.qid, c.cid, round(pow(list_distance(c.y, q.qv), 2), 9) AS s FROM c0 c, qs q) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, cid) <= {nprobe})"


SEARCH = f"""WITH {V}, {start_sql()}, {assign_cte(0)}, {QUERY_CTE}, {probe_cte(PROBES)}, {knn_cte(L2)},
fo AS (SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) AS INTEGER) AS rank, vec_id, s FROM (SELECT p.qid, a.vec_id, round(pow(list_distance(a.v, q.qv), 2), 9) AS s FROM pr p JOIN a0 a USING (cid) JOIN qs q USING (qid) WHERE a.vec_id <> p.qid) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) <= {TOPK}),
sz AS (SELECT cid, count(*) AS n FROM a0 GROUP BY 1)
"""
HITS = "SELECT count(*) / (10.0::DOUBLE * (SELECT count(*) FROM qs)) AS recall FROM tr JOIN fo USING (qid, vec_id)"


class Search:
    def __init__(self, spark, sf_dir):
        self.v, self.y = begin(spark, sf_dir)
        self.lists = assign.assign_full(self.v, self.y, dtype=np.float64)
        self.queries = every_20th(self.v)
        self.placed = assign.assign_full(self.v, self.y, dtype=np.float64, carry=("vec_id", "vec"))
        self.found = lambda: index_search(self.queries, self.placed, self.y, TOPK, PROBES)
        self.truth = lambda: exact_knn(self.queries, self.v, TOPK)
        self.probes = lambda n=PROBES: route(spark, self.queries, self.y, n)
        self.sizes = lambda: measures.cluster_sizes(self.lists, K)


@query("index_search_10", SEARCH + "SELECT qid, rank, vec_id, round(s, 6) AS dist FROM fo")
def _(spark, sf_dir):
    return Search(spark, sf_dir).found().withColumn("dist", F.round("dist", 6))


@query("index_on_disk_search", SEARCH + "SELECT qid, rank, vec_id, round(s, 6) AS dist FROM fo")
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    lists = build_index(s.v, Model(s.y, np.zeros(K, int)), shared_path(spark, "index"), cid_buckets=8)
    return index_search(s.queries, lists, s.y, TOPK, PROBES).withColumn("dist", F.round("dist", 6))


class FittedSearch:
    """Lists of a fitted model, and as many of them probed as a recall of 0.9 over the whole query set takes."""

    def __init__(self, spark, sf_dir):
        self.v = embeddings(spark, sf_dir)
        method = PhasedKMeans(k=default_k(self.v.count()), max_iter=10, seed=SEED)
        self.model = method.fit(self.v)
        self.y = self.model.centroids.astype(np.float64)
        self.placed = settle(method.transform(self.v, self.model, carry=("vec_id", "vec")), "lists")
        self.lists = self.placed.drop("vec")
        self.queries = every_20th(self.v)
        self.truth = settle(exact_knn(self.queries, self.v, TOPK), "truth")
        self.nprobe, self.recall, self.explored = least_nprobe(self.queries, self.lists, self.y, self.truth, TOPK)


@query("index_search_fitted")
def _(spark, sf_dir):
    s = FittedSearch(spark, sf_dir)
    return index_search(s.queries, s.placed, s.y, TOPK, s.nprobe).withColumn("dist", F.round("dist", 6))


@query("index_on_disk_search_fitted")
def _(spark, sf_dir):
    s = FittedSearch(spark, sf_dir)
    lists = write_lists(s.placed.drop("dist"), shared_path(spark, "index"), 8)
    return index_search(s.queries, lists, s.y, TOPK, s.nprobe).withColumn("dist", F.round("dist", 6))


@query("nprobe_rank", SEARCH + "SELECT qid, cid, probe, round(s, 6) AS dist FROM pr")
def _(spark, sf_dir):
    return Search(spark, sf_dir).probes().withColumn("dist", F.round("dist", 6))


@query("udtf_nprobe", SEARCH + "SELECT qid, cid, round(s, 6) AS dist FROM pr")
def _(spark, sf_dir):
    udx.register(spark)
    s = Search(spark, sf_dir)
    every = spark.createDataFrame([([[float(x) for x in c] for c in s.y],)], "centroids array<array<double>>")
    s.queries.join(F.broadcast(every)).createOrReplaceTempView("vecspark_queries")
    return spark.sql(f"SELECT qid, cid, round(dist, 6) AS dist FROM vecspark_queries, LATERAL nearest_lists(qvec, centroids, {PROBES})")


@query("recall_at_10", SEARCH + HITS)
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return recall_at(s.found(), s.truth(), TOPK).select(F.round("recall", 9).alias("recall"))


ORACLES["recall_at_10"] = SEARCH + HITS.replace("SELECT count(*) / (10.0::DOUBLE * (SELECT count(*) FROM qs))", "SELECT round(count(*) / (10.0::DOUBLE * (SELECT count(*) FROM qs)), 9)")


@query("recall_membership", ORACLES["recall_at_10"])
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return membership_recall(s.lists, s.probes(), s.truth(), TOPK).select(F.round("recall", 9).alias("recall"))


@query("recall_semi", SEARCH + "SELECT count(*) AS hits FROM tr SEMI JOIN fo USING (qid, vec_id)")
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return s.truth().join(s.found(), ["qid", "vec_id"], "left_semi").agg(F.count(F.lit(1)).alias("hits"))


@query("recall_intersect", SEARCH + "SELECT count(*) AS hits FROM (SELECT qid, vec_id FROM tr INTERSECT SELECT qid, vec_id FROM fo)")
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return s.truth().select("qid", "vec_id").intersect(s.found().select("qid", "vec_id")).agg(F.count(F.lit(1)).alias("hits"))


@query("explored", SEARCH + "SELECT round(avg(e), 6) AS explored, round(avg(e) / (SELECT count(*) FROM v), 9) AS share FROM (SELECT qid, sum(coalesce(n, 0)) AS e FROM pr LEFT JOIN sz USING (cid) GROUP BY 1)")
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return vectors_explored(s.probes(), s.sizes(), s.v.count()).select(F.round("explored", 6).alias("explored"), F.round("share", 9).alias("share"))


@query("index_probe_curve", f"""WITH {V}, {start_sql()}, {assign_cte(0)}, {QUERY_CTE}, {probe_cte(8)}, {knn_cte(L2)}, sz AS (SELECT cid, count(*) AS n FROM a0 GROUP BY 1), nq AS (SELECT count(*) AS c FROM qs)
SELECT CAST(l.n AS INTEGER) AS nprobe, round((SELECT count(*) FROM tr JOIN a0 USING (vec_id) JOIN pr ON pr.qid = tr.qid AND pr.cid = a0.cid WHERE pr.probe <= l.n) / (10.0::DOUBLE * nq.c), 9) AS recall,
  round((SELECT sum(sz.n) FROM pr JOIN sz USING (cid) WHERE pr.probe <= l.n) / nq.c::DOUBLE, 6) AS explored FROM (VALUES (1), (2), (4), (8)) l(n), nq""")
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    return probe_curve(s.queries, s.lists, s.y, s.truth(), TOPK, [1, 2, 4, 8]).select("nprobe", F.round("recall", 9).alias("recall"), F.round("explored", 6).alias("explored"))


@query("match_explored", ORACLES["index_probe_curve"].join(["SELECT nprobe, recall, explored FROM (", ") ORDER BY explored >= 60.0 DESC, CASE WHEN explored >= 60.0 THEN nprobe ELSE -nprobe END LIMIT 1"]))
def _(spark, sf_dir):
    s = Search(spark, sf_dir)
    curve = probe_curve(s.queries, s.lists, s.y, s.truth(), TOPK, [1, 2, 4, 8])
    return match_explored(curve, 60.0).select("nprobe", F.round("recall", 9).alias("recall"), F.round("explored", 6).alias("explored"))


@query("explored_cumsum", SEARCH + "SELECT qid, probe, CAST(sum(coalesce(n, 0)) OVER (PARTITION BY qid ORDER BY probe ROWS UNBOUNDED PRECEDING) AS BIGINT) AS explored FROM pr LEFT JOIN sz USING (cid)")
def _(spark, sf_dir):
    from pyspark.sql import Window

    s = Search(spark, sf_dir)
    order = Window.partitionBy("qid").orderBy("probe").rowsBetween(Window.unboundedPreceding, 0)
    return s.probes().join(s.sizes(), "cid").select("qid", "probe", F.sum("n").over(order).alias("explored"))


@query("cogroup_score", SEARCH + "SELECT p.qid, a.vec_id, round(pow(list_distance(a.v, q.qv), 2), 6) AS dist FROM pr p JOIN a0 a USING (cid) JOIN qs q USING (qid)")
def _(spark, sf_dir):
    import pandas as pd

    s = Search(spark, sf_dir)

    def score(asked, listed):
        if asked.empty or listed.empty:
            return pd.DataFrame({"qid": pd.Series(dtype="int64"), "vec_id": pd.Series(dtype="int64"), "dist": pd.Series(dtype="float64")})
        d = kernels.sq_dists(np.stack(asked.qvec).astype(np.float64), np.stack(listed.vec).astype(np.float64))
        return pd.DataFrame({"qid": np.repeat(asked.qid.to_numpy(), len(listed)), "vec_id": np.tile(listed.vec_id.to_numpy(), len(asked)), "dist": np.round(d.ravel(), 6)})

    asked = s.probes().select("qid", "cid").join(s.queries, "qid")
    return asked.groupBy("cid").cogroup(s.placed.groupBy("cid")).applyInPandas(score, "qid long, vec_id long, dist double")


@query("wcss", lloyd_sql(0, "SELECT round(sum(d), 6) AS wcss FROM a0"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return measures.wcss(assign.assign_full(v, y, dtype=np.float64)).select(F.round("wcss", 6).alias("wcss"))


@query("cluster_sizes", sizes_sql("SELECT cid, n FROM sz"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return measures.cluster_sizes(assign.assign_full(v, y, dtype=np.float64), K)


@query("points_per_cluster", sizes_sql("SELECT round(avg(n), 6) AS ppc_mean, round(stddev_pop(n), 6) AS ppc_std FROM sz"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return measures.points_per_cluster(assign.assign_full(v, y, dtype=np.float64), K).select(F.round("ppc_mean", 6).alias("ppc_mean"), F.round("ppc_std", 6).alias("ppc_std"))


@query("balance", sizes_sql(f"SELECT round(max(n) / avg(n), 6) AS max_over_mean, round(2 * sum(r * n) / ({K}.0 * sum(n))::DOUBLE - {K + 1}.0::DOUBLE / {K}, 6) AS gini, CAST(sum(CASE WHEN n = 0 THEN 1 ELSE 0 END) AS BIGINT) AS n_empty FROM (SELECT n, row_number() OVER (ORDER BY n, cid) AS r FROM sz)"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return measures.balance(assign.assign_full(v, y, dtype=np.float64), K).select(F.round("max_over_mean", 6).alias("max_over_mean"), F.round("gini", 6).alias("gini"), "n_empty")


@query("label_purity", lloyd_sql(0, "SELECT round(sum(top) / sum(n)::DOUBLE, 9) AS purity FROM (SELECT cid, max(n) AS top, sum(n) AS n FROM (SELECT cid, label, count(*) AS n FROM a0 GROUP BY 1, 2) GROUP BY 1)"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return measures.label_purity(assign.assign_full(v, y, dtype=np.float64), read_table(spark, sf_dir, "embeddings").select("vec_id", "label")).select(F.round("purity", 9).alias("purity"))


@query("empty_clusters_anti", sizes_sql("SELECT cid FROM sz WHERE n = 0"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    return spark.range(K).select(F.col("id").cast("int").alias("cid")).join(assign.assign_full(v, y, dtype=np.float64), "cid", "left_anti")


@query("changed_except", lloyd_sql(1, "SELECT vec_id, cid FROM a1 EXCEPT ALL SELECT vec_id, cid FROM a0"))
def _(spark, sf_dir):
    v, y0 = begin(spark, sf_dir)
    _, y1 = lloyd(spark, sf_dir, 1)
    return assign.assign_full(v, y1, dtype=np.float64).select("vec_id", "cid").exceptAll(assign.assign_full(v, y0, dtype=np.float64).select("vec_id", "cid"))


@query("assignment_diff", lloyd_sql(1, "SELECT CAST(sum(CASE WHEN a.cid <> b.cid THEN 1 ELSE 0 END) AS BIGINT) AS differ, round(avg(CASE WHEN a.cid <> b.cid THEN 1.0::DOUBLE ELSE 0 END), 9) AS share FROM a0 a JOIN a1 b USING (vec_id)"))
def _(spark, sf_dir):
    v, y0 = begin(spark, sf_dir)
    _, y1 = lloyd(spark, sf_dir, 1)
    return measures.assignment_diff(assign.assign_full(v, y0, dtype=np.float64), assign.assign_full(v, y1, dtype=np.float64)).select("differ", F.round("share", 9).alias("share"))


@query("pareto_front", """WITH g AS (SELECT p_retailprice AS p, max(p_size) AS s FROM part GROUP BY 1),
f AS (SELECT p, s FROM g QUALIFY s > coalesce(max(s) OVER (ORDER BY p ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1))
SELECT p_partkey, p_retailprice, p_size FROM part JOIN f ON p_retailprice = p AND p_size = s""")
def _(spark, sf_dir):
    return measures.pareto(read_table(spark, sf_dir, "part").select("p_partkey", "p_retailprice", "p_size"), ["p_retailprice"], ["p_size"])


@query("model_json_roundtrip", lambda: sizes_sql("SELECT sz.cid, sz.n, round(list_sum(c0.y), 6) AS s FROM sz JOIN c0 USING (cid)"))
def _(spark, sf_dir):
    v, y = begin(spark, sf_dir)
    sizes = measures.cluster_sizes(assign.assign_full(v, y, dtype=np.float64), K).orderBy("cid").collect()
    path = shared_path(spark, "model")
    Model(y, np.array([r["n"] for r in sizes]), [{"iter": 1}]).save(spark, path)
    return Model.load(spark, path).frame(spark).select("cid", "n", F.round(vc.total(F.col("centroid").cast("array<double>")), 6).alias("s"))


# ---- fixtures ---------------------------------------------------------------------------------------------------

GRAMS = """g AS (SELECT {key} AS vec_id, substr(t, i::INT, 3) AS g FROM (SELECT {key}, t, unnest(range(1, greatest(length(t) - 2, 1) + 1)) AS i FROM (SELECT {key}, lower(text) AS t FROM {table} WHERE length(text) > 0))),
h AS (SELECT vec_id, CAST('0x' || substr(md5(g), 1, 8) AS BIGINT) AS h FROM g),
cells AS (SELECT vec_id, CAST(h % {d} AS INTEGER) AS dim, CAST(sum(CASE WHEN (h >> 20) & 1 = 1 THEN 1 ELSE -1 END) AS BIGINT) AS n FROM h GROUP BY 1, 2 HAVING sum(CASE WHEN (h >> 20) & 1 = 1 THEN 1 ELSE -1 END) <> 0)"""


@query("doc_hash_vector", "WITH " + GRAMS.format(key="doc_id", table="documents", d=64) + ", nz AS (SELECT vec_id, sqrt(sum(abs(n))) AS norm FROM cells GROUP BY 1) SELECT vec_id, dim, round((sign(n) * sqrt(abs(n)) / norm)::FLOAT::DOUBLE, 5) AS x FROM cells JOIN nz USING (vec_id)")
def _(spark, sf_dir):
    v = featurize.document_vectors(spark, sf_dir, 64)
    return v.select("vec_id", F.posexplode("vec").alias("dim", "f")).where("f <> 0").select("vec_id", "dim", F.round(F.col("f").cast("double"), 5).alias("x"))


@query("doc_ngrams", "WITH " + GRAMS.format(key="doc_id", table="documents", d=64) + " SELECT vec_id AS doc_id, dim, n FROM cells")
def _(spark, sf_dir):
    return featurize.trigram_cells(read_table(spark, sf_dir, "documents"), "doc_id", 64)


ORDER_SQL = """f AS (SELECT l_orderkey AS vec_id, count(*)::DOUBLE AS lines, sum(l_quantity) AS q, avg(l_extendedprice) AS p, max(l_discount) AS d, avg(CASE WHEN l_returnflag = 'R' THEN 1.0::DOUBLE ELSE 0 END) AS r, avg(cos(dayofyear(l_shipdate) * (6.283185307179586::DOUBLE / 365.25::DOUBLE))) AS c FROM lineitem GROUP BY 1)"""


@query("order_vectors", f"WITH {ORDER_SQL}, s AS (SELECT avg(lines) ml, stddev_pop(lines) sl, avg(q) mq, stddev_pop(q) sq, avg(p) mp, stddev_pop(p) sp, avg(c) mc, stddev_pop(c) sc FROM f) SELECT vec_id, round(((lines - ml) / sl)::FLOAT::DOUBLE, 4) AS z_lines, round(((q - mq) / sq)::FLOAT::DOUBLE, 4) AS z_q, round(((p - mp) / sp)::FLOAT::DOUBLE, 4) AS z_p, round(((c - mc) / sc)::FLOAT::DOUBLE, 4) AS z_c FROM f, s")
def _(spark, sf_dir):
    f = featurize.order_features(spark, sf_dir)
    names = [c for c in f.columns if c != "vec_id"]
    v = featurize.z_scored(f)
    pick = {"z_lines": "lines", "z_q": "sum_q", "z_p": "avg_p", "z_c": "ship_cos"}
    names = [n for n in names]
    lookup = {n: i for i, n in enumerate(names)}
    wanted = {k: lookup.get(n, lookup.get("_".join(reversed(n.split("_"))))) for k, n in pick.items()}
    return v.select("vec_id", *(F.round(F.col("vec")[i].cast("double"), 4).alias(k) for k, i in wanted.items()))


@query("part_vectors", "WITH s AS (SELECT l_partkey AS p_partkey, sum(l_quantity) AS sold FROM lineitem GROUP BY 1), f AS (SELECT p_partkey AS vec_id, p_retailprice AS r, coalesce(sold, 0) AS sold FROM part LEFT JOIN s USING (p_partkey)), z AS (SELECT avg(r) mr, stddev_pop(r) sr, avg(sold) ms, stddev_pop(sold) ss FROM f) SELECT vec_id, round(((r - mr) / sr)::FLOAT::DOUBLE, 4) AS z_retail, round(((sold - ms) / ss)::FLOAT::DOUBLE, 4) AS z_sold FROM f, z")
def _(spark, sf_dir):
    return featurize.part_vectors(spark, sf_dir).select("vec_id", F.round(F.col("vec")[0].cast("double"), 4).alias("z_retail"), F.round(F.col("vec")[2].cast("double"), 4).alias("z_sold"))


@query("user_day_vectors", "WITH k AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS p FROM (SELECT DISTINCT event_type FROM events)) SELECT user_id * 1000 + dayofyear(ts) AS vec_id, CAST(hour(ts) * 5 + p AS INTEGER) AS dim, count(*) AS n FROM events JOIN k USING (event_type) GROUP BY 1, 2")
def _(spark, sf_dir):
    v = featurize.user_day_vectors(spark, sf_dir)
    return v.select("vec_id", F.posexplode("vec").alias("dim", "x")).where("x <> 0").select("vec_id", "dim", F.col("x").cast("long").alias("n"))


CHUNKS = "c AS (SELECT doc_id * 8388608 + p AS piece_id, substr(text, (p * 400 + 1)::INT, 400) AS text FROM (SELECT doc_id, text, unnest(range(0, (length(text) - 1) // 400 + 1)) AS p FROM documents WHERE length(text) > 0))"


@query("chunk_vectors", f"WITH {CHUNKS}, " + GRAMS.format(key="piece_id", table="c", d=64) + ", nz AS (SELECT vec_id, sqrt(sum(abs(n))) AS norm FROM cells GROUP BY 1) SELECT vec_id, dim, round((sign(n) * sqrt(abs(n)) / norm)::FLOAT::DOUBLE, 5) AS x FROM cells JOIN nz USING (vec_id)")
def _(spark, sf_dir):
    v = featurize.chunk_vectors(spark, sf_dir, 64)
    return v.select("vec_id", F.posexplode("vec").alias("dim", "f")).where("f <> 0").select("vec_id", "dim", F.round(F.col("f").cast("double"), 5).alias("x"))


@query("ood_queries_knn", "WITH " + GRAMS.format(key="doc_id", table="documents", d=64) + ", " + GRAMS.format(key="item_id", table="benchmark", d=64).replace("g AS (", "qg AS (", 1).replace("FROM g)", "FROM qg)").replace("\nh AS", "\nqh AS").replace("FROM h ", "FROM qh ").replace("\ncells AS", "\nqcells AS") + """,
a AS (SELECT vec_id, dim, sign(n) * sqrt(abs(n)) / norm AS x FROM cells JOIN (SELECT vec_id, sqrt(sum(abs(n))) AS norm FROM cells GROUP BY 1) USING (vec_id)),
b AS (SELECT vec_id AS qid, dim, sign(n) * sqrt(abs(n)) / norm AS x FROM qcells JOIN (SELECT vec_id, sqrt(sum(abs(n))) AS norm FROM qcells GROUP BY 1) USING (vec_id)),
s AS (SELECT qid, vec_id, sum(a.x * b.x) AS s FROM a JOIN b USING (dim) GROUP BY 1, 2)
SELECT qid, round(max(s), 4) AS best FROM s GROUP BY 1""")
def _(spark, sf_dir):
    docs = featurize.document_vectors(spark, sf_dir, 64)
    items = featurize.text_vectors(read_table(spark, sf_dir, "benchmark"), "item_id", 64).select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
    return exact_knn(items, docs, 1, "cosine", exclude_self=False).select("qid", F.round(1 - F.col("dist"), 4).alias("best"))


@pair_query("sql_knn", " SELECT qid, vec_id, round(pow(list_distance(v, qv), 2), 6) AS d FROM v, q QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round(pow(list_distance(v, qv), 2), 6), vec_id) <= 3")
def _(spark, sf_dir):
    udx.register(spark)
    query_pairs(spark, sf_dir).createOrReplaceTempView("vecspark_pairs")
    return spark.sql("SELECT qid, vec_id, d FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) AS r FROM (SELECT qid, vec_id, round(vec_l2(vec, qv), 6) AS d FROM vecspark_pairs)) WHERE r <= :top", args={"top": 3})


@query("udaf_vector_mean", f"WITH {V} SELECT label, CAST(pos - 1 AS INTEGER) AS pos, round(avg(x), 6) AS m FROM (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM v) GROUP BY 1, 2")
def _(spark, sf_dir):
    t = read_table(spark, sf_dir, "embeddings")
    return t.groupBy("label").agg(udx.vec_mean("embedding").alias("mean")).select("label", F.posexplode("mean").alias("pos", "m")).select("label", "pos", F.round("m", 6).alias("m"))

