import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.operators.assign import assign_full
from vecspark.operators.clustering import BoundedKMeans, LloydKMeans, MiniBatchKMeans, PhasedKMeans, PivotKMeans, TwoLevelKMeans, share_k
from vecspark.operators.index import exact_knn, recall_at
from vecspark.operators.model import Model
from vecspark.operators.seeding import sample_queries, start_matrix
from vecspark.operators.stopping import Convergence, MaxIter, RecallPlateau
from vecspark.sources.vectors import embeddings, flaw, normalise, validate


@pytest.fixture(scope="module")
def vectors(spark, small):
    return embeddings(spark, small).cache()


def blobs(spark, n=600, d=64, k=12, seed=0):
    rng = np.random.default_rng(seed)
    y = rng.normal(size=(k, d)) * 2
    x = y[rng.integers(0, k, n)] + rng.normal(size=(n, d)) * 0.3
    return spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "vec_id long, vec array<float>")


def test_phased_equals_plain_iterations_without_pruning(vectors):
    y = start_matrix(vectors, 15, 0)
    plain = LloydKMeans(k=15, max_iter=4, empty="keep", dtype=np.float64).fit(vectors, y)
    phased = PhasedKMeans(k=15, max_iter=4, empty="keep", epsilon0=np.inf, dtype=np.float64).fit(vectors, y)
    assert np.allclose(plain.centroids, phased.centroids)
    assert [round(h["wcss"], 6) for h in plain.history] == [round(h["wcss"], 6) for h in phased.history]


def test_wcss_never_rises_and_parity_with_pruning(spark):
    v = blobs(spark)
    y = start_matrix(v, 12, 0)
    plain = LloydKMeans(k=12, max_iter=5, empty="keep").fit(v, y)
    phased = PhasedKMeans(k=12, max_iter=5, empty="keep").fit(v, y)
    w = [h["wcss"] for h in plain.history]
    assert all(a >= b - 1e-3 for a, b in zip(w, w[1:]))
    assert phased.history[-1]["wcss"] <= 1.01 * w[-1]
    assert sum(h["mul_adds"] for h in phased.history[1:]) < sum(h["mul_adds"] for h in plain.history[1:])


def test_same_result_for_any_partitioning(vectors):
    y = start_matrix(vectors, 10, 0)
    a = LloydKMeans(k=10, max_iter=3, dtype=np.float64).fit(vectors.repartition(1), y)
    b = LloydKMeans(k=10, max_iter=3, dtype=np.float64).fit(vectors.repartition(7), y)
    assert np.allclose(a.centroids, b.centroids)


def test_stop_rules(vectors):
    assert len(LloydKMeans(k=8, max_iter=9, stop=[MaxIter(3)]).fit(vectors).history) == 3
    assert len(LloydKMeans(k=8, max_iter=50, stop=[Convergence(1e-9)], empty="keep").fit(vectors).history) < 50
    rule = RecallPlateau(topk=10, n_queries=40, probe_frac=0.2, tol=1.0)
    model = PhasedKMeans(k=8, max_iter=9, stop=[rule]).fit(vectors)
    assert len(model.history) == 3 and len(rule.series) == 3 and all(0 <= r <= 1 for r in rule.series)


def test_bounded_variants_equal_plain(vectors):
    y = LloydKMeans(k=9, max_iter=3, empty="keep", dtype=np.float64).fit(vectors, start_matrix(vectors, 9, 0)).centroids
    for variant in ("elkan", "hamerly"):
        assert np.allclose(BoundedKMeans(9, 3, variant).fit(vectors).centroids, y)
    for variant in ("each", "all"):
        assert np.allclose(PivotKMeans(9, 3, empty="keep", variant=variant).fit(vectors).centroids, y)


def test_two_levels_and_refinement(spark):
    v = blobs(spark)
    method = TwoLevelKMeans(k=16)
    model = method.fit(v)
    assert model.k == 16
    assert method.transform(v, model).where("cid between 0 and 15").count() == 600
    assert [h["iter"] for h in model.history] == list(range(1, 9)) and model.counts.sum() == 600
    assert len(TwoLevelKMeans(k=16, refine_iter=2).fit(v).history) == 10
    assert TwoLevelKMeans(k=16, sample_frac=0.5, stop=[MaxIter(5)]).fit(v).k == 16
    assert TwoLevelKMeans(k=4).fit(v.limit(0)).k == 0
    plain = TwoLevelKMeans(k=16, pruned=False).fit(v)
    assert model.history[-1]["wcss"] < 1.15 * plain.history[-1]["wcss"]


def test_fine_stage_is_lloyd_inside_each_coarse_cluster(spark):
    v = blobs(spark, 300, 16, 5)
    method = TwoLevelKMeans(k=9, meso_iter=2, fine_iter=1, pruned=False, dtype=np.float64)
    coarse = LloydKMeans(k=3, max_iter=2, dtype=np.float64).fit(v)
    x = {r["vec_id"]: np.array(r["vec"]) for r in v.collect()}
    meso = {r["vec_id"]: r["cid"] for r in assign_full(v, coarse.centroids, dtype=np.float64).collect()}
    model = method.fit(v)
    sizes = np.bincount(list(meso.values()), minlength=3)
    ends = np.cumsum([n for _, n in sorted(share_k(dict(enumerate(sizes.tolist())), 9).items())])
    for c, (lo, hi) in enumerate(zip([0, *ends[:-1]], ends)):
        mean = np.mean([x[i] for i in x if meso[i] == c], axis=0)
        assert np.allclose((model.centroids[lo:hi] * model.counts[lo:hi, None]).sum(0) / sizes[c], mean)


@pytest.mark.parametrize("known", ["queries", "queries and truth"])
def test_recall_series_is_that_of_full_products(spark, known):
    """Queries and truth are supplied in the data's own space, and their ids clash with the data's."""
    v = blobs(spark)
    rng = np.random.default_rng(5)
    own = [(i, [float(x) for x in row]) for i, row in enumerate(np.array([r["vec"] for r in sample_queries(v, 40).select(F.col("qvec").alias("vec")).collect()]) + rng.normal(size=(40, 64)) * 0.01)]
    queries = spark.createDataFrame(own, "qid long, qvec array<float>")
    truth = exact_knn(queries, v, 10, exclude_self=False) if "truth" in known else None
    rule = lambda: RecallPlateau(0.0, topk=10, probe_frac=0.1, queries=queries, truth=truth, patience=9)
    start = start_matrix(v, 12, 0)
    full, phased, sampled = rule(), rule(), RecallPlateau(0.0, topk=10, probe_frac=0.1, n_queries=40, patience=9)
    LloydKMeans(k=12, max_iter=4, stop=[full]).fit(v, start)
    PhasedKMeans(k=12, max_iter=4, stop=[phased]).fit(v, start)
    PhasedKMeans(k=12, max_iter=4, stop=[sampled]).fit(v, start)
    assert np.allclose(full.series, phased.series, atol=0.01)
    assert min(phased.series[1:]) > 0.5 and np.allclose(full.series, sampled.series, atol=0.1)


def test_first_threshold_from_the_previous_centroid(spark):
    v = blobs(spark)
    y = start_matrix(v, 12, 0)
    plain = LloydKMeans(k=12, max_iter=4, empty="keep").fit(v, y)
    kept = PhasedKMeans(k=12, max_iter=4, empty="keep", seed_mode="previous").fit(v, y)
    assert np.allclose(plain.history[-1]["wcss"], kept.history[-1]["wcss"], rtol=0.01)
    assert kept.history[0]["changed"] is None and all(h["prune_rate"] > 0.5 for h in kept.history[1:])
    exact = PhasedKMeans(k=12, max_iter=4, empty="keep", seed_mode="previous", epsilon0=np.inf, dtype=np.float64).fit(v, y)
    want = LloydKMeans(k=12, max_iter=4, empty="keep", dtype=np.float64).fit(v, y)
    assert np.allclose(exact.centroids, want.centroids)
    assert PhasedKMeans(k=12, max_iter=2, seed_mode="previous").fit(v.union(v), y).counts.sum() == 1200


def test_stops_when_labels_no_longer_change(spark):
    v = blobs(spark)
    model = LloydKMeans(k=12, max_iter=30, empty="keep", stop=[Convergence(None, 0)]).fit(v, start_matrix(v, 12, 0))
    changed = [h["changed"] for h in model.history]
    assert changed[0] is None and changed[-1] == 0 and all(c > 0 for c in changed[1:-1]) and len(changed) < 30
    assert model.history_frame(spark).where("changed = 0").count() == 1


def test_mini_batch_prunes_rotated_vectors(spark):
    """Without rotation the head of unequal scales would mislead the test."""
    rng = np.random.default_rng(2)
    x = rng.normal(size=(800, 64)) * np.where(np.arange(64) < 32, 1.0, 0.3)
    v = spark.createDataFrame([(i, [float(a) for a in row]) for i, row in enumerate(x)], "vec_id long, vec array<float>")
    y = start_matrix(v, 20, 0)
    a, b = (MiniBatchKMeans(20, 1, 1.0, epsilon0=e).fit(v, y) for e in (2.1, np.inf))
    assert np.abs(a.counts - b.counts).sum() <= 0.005 * 800 * 2
    cid = ((x.astype(np.float32).astype(np.float64)[:, None] - y[None]) ** 2).sum(2).argmin(1)
    mean = np.array([x.astype(np.float32)[cid == c].mean(0) for c in range(20)])
    assert np.allclose(b.centroids, mean, atol=1e-6)


def test_bounds_follow_rows_and_skip_distances(spark):
    v = blobs(spark)
    for variant in ("elkan", "hamerly"):
        rates = [h["prune_rate"] for h in BoundedKMeans(12, 6, variant).fit(v).history]
        assert rates[0] == 0 and rates[-1] > 0.5


def test_mini_batches_move_toward_the_data(spark):
    v = blobs(spark)
    model = MiniBatchKMeans(12, batches=6, batch_frac=0.3).fit(v)
    start = start_matrix(v, 12, 0)
    cost = lambda y: assign_full(v, y).agg(F.sum("dist")).first()[0]
    assert cost(model.centroids) < cost(start)


def test_identical_points_and_more_clusters_than_points(spark):
    v = spark.createDataFrame([(i, [1.0, 1.0]) for i in range(4)], "vec_id long, vec array<float>")
    model = PhasedKMeans(k=3, max_iter=3, rotate=False).fit(v)
    assert model.k == 3 and model.counts.sum() == 4
    assert LloydKMeans(k=9, max_iter=2).fit(v).k == 4
    assert LloydKMeans(k=3).fit(v.limit(0)).k == 0


def test_two_groups_by_hand(spark):
    rows = [(0, [0.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 0.0]), (3, [10.0, 10.0]), (4, [10.0, 11.0]), (5, [11.0, 10.0])]
    v = spark.createDataFrame(rows, "vec_id long, vec array<float>")
    y = LloydKMeans(k=2, max_iter=5).fit(v, np.array([[0.0, 0.0], [10.0, 10.0]])).centroids
    assert np.allclose(y, [[1 / 3, 1 / 3], [31 / 3, 31 / 3]])


def test_validation_policies(spark):
    rows = [(0, [1.0, 2.0]), (1, [1.0]), (2, None), (3, [float("nan"), 1.0]), (4, [float("inf"), 1.0])]
    v = spark.createDataFrame(rows, "vec_id long, vec array<float>")
    assert [r["flaw"] for r in validate(v, 2, "quarantine").orderBy("vec_id").collect()] == [None, "length", "null", "not finite", "not finite"]
    assert validate(v, 2, "drop").count() == 1
    with pytest.raises(Exception, match="bad vector"):
        validate(v, 2).collect()
    assert normalise(spark.createDataFrame([(0, [0.0, 0.0]), (1, [3.0, 4.0])], "vec_id long, vec array<float>")).count() == 1
    assert flaw(2) is not None


def test_reduction_keeps_distances_on_average(spark):
    from vecspark.operators.reduce import reduce_dimensions

    v = blobs(spark, n=200)
    x = np.array([r["vec"] for r in v.orderBy("vec_id").collect()])
    for kind in ("prefix", "pca"):
        low = np.array([r["vec"] for r in reduce_dimensions(v, 16, kind).orderBy("vec_id").collect()])
        assert low.shape == (200, 16)
        ratio = ((low[1:] - low[:-1]) ** 2).sum() / ((x[1:] - x[:-1]) ** 2).sum()
        assert 0.7 < ratio < 1.3


def test_model_round_trip(spark, tmp_path):
    Model(np.eye(3), np.arange(3), [{"iter": 1, "wcss": 2.0}], None, 5, {"k": 3}).save(spark, str(tmp_path / "m"))
    back = Model.load(spark, str(tmp_path / "m"))
    assert np.allclose(back.centroids, np.eye(3)) and back.d1 == 5 and back.history[0]["wcss"] == 2.0


def test_search_with_all_lists_is_exact(spark, vectors):
    from vecspark.operators.index import index_search

    y = start_matrix(vectors, 8, 0)
    lists = vectors.join(assign_full(vectors, y).select("vec_id", "cid"), "vec_id")
    queries = sample_queries(vectors, 30)
    truth = exact_knn(queries, vectors, 5)
    assert recall_at(index_search(queries, lists, y, 5, 8), truth, 5).first()[0] == 1.0
    assert recall_at(index_search(queries, lists, y, 5, 1), truth, 5).first()[0] < 1.0


def plan_of(df):
    return df._jdf.queryExecution().toString()


def test_plans_have_no_products_and_prune_columns(spark, small, vectors):
    from vecspark.operators.assign import Kernel, iteration_sums, merge_sums
    from vecspark.plans.relational import band_join, interval_join

    y = start_matrix(vectors, 8, 0)
    v = embeddings(spark, small)
    one = plan_of(assign_full(v, y))
    assert "Exchange" not in one and "label" not in one.split("ReadSchema")[-1]
    assert plan_of(merge_sums(iteration_sums(v, Kernel(y)))).split("Physical Plan")[-1].count("Exchange hashpartitioning") == 1
    p = spark.read.parquet(f"{small}/part.parquet").select("p_partkey", "p_retailprice")
    banded = plan_of(band_join(p, p.toDF("b", "y"), "p_retailprice", "y", 0.1))
    assert "CartesianProduct" not in banded and "NestedLoop" not in banded
    assert interval_join is not None
