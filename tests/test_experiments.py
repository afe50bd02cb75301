"""Every experiment run on small inputs: its rows, and the ranking that is expected of it."""

import numpy as np
import pytest

from vecspark.experiments import runs

COLUMNS = ["workload", "fixture", "params", "metric", "value"]


@pytest.fixture(scope="module")
def blobs(spark):
    """Clustered vectors in place of the text vectors, whose dimensions are too many for a quick test."""
    rng = np.random.default_rng(0)
    y = rng.normal(size=(20, 64)) * 2
    x = y[rng.integers(0, 20, 900)] + rng.normal(size=(900, 64)) * 0.4
    return spark.createDataFrame([(i, [float(a) for a in row]) for i, row in enumerate(x)], "vec_id long, vec array<float>").cache()


@pytest.fixture(autouse=True)
def small_fixtures(monkeypatch, blobs):
    monkeypatch.setitem(runs.FIXTURES, "doc", lambda spark, sf_dir: blobs)
    made = runs.Bench.__init__
    monkeypatch.setattr(runs.Bench, "__init__", lambda self, spark, sf_dir, fixture, n_queries=60, topk=10, queries=None: made(self, spark, sf_dir, fixture, n_queries, topk, queries))


def values(df, metric, key=None):
    assert df.columns == COLUMNS
    rows = [r for r in df.collect() if r["metric"] == metric]
    return {r["params"].get(key): r["value"] for r in rows} if key else [r["value"] for r in rows]


def test_w01_quality_is_equal_at_less_work(spark, small):
    df = runs.w01_phased_against_full(spark, small, ("doc",), iterations=4).cache()
    work, recall, wcss = (values(df, m, "method") for m in ("mul_adds", "recall_10", "wcss"))
    assert work["phased"] < work["full"] and abs(recall["phased"] - recall["full"]) < 0.05 and wcss["phased"] < 1.02 * wcss["full"]
    assert {r["metric"] for r in runs.summary(df).collect()} >= {"recall_10", "explored", "ppc_std", "secs"}


def test_w03_work_grows_with_the_number_of_clusters(spark, small):
    work = values(runs.w03_cluster_counts(spark, small, (10, 40), 2).where("params['method'] = 'full'"), "mul_adds", "k")
    assert work["40"] > 3 * work["10"]


def test_w04_rules_stop_by_recall(spark, small):
    df = runs.w04_stopping(spark, small, cap=8).cache()
    n = values(df, "iterations", "rule")
    assert n["cap_10"] == 10 and 3 <= n["recall_.005"] <= n["recall_.0025"] <= 8
    series = [r["value"] for r in df.where("workload = 'w05' and metric = 'recall' and params['rule'] = 'recall_.0025'").collect()]
    assert len(series) >= 3 and min(series) > 0.3


def test_w06_samples_cost_less(spark, small):
    work = values(runs.w06_sampling(spark, small, fracs=(0.2, 1.0), k=12, seeds=1), "mul_adds", "frac")
    assert work["0.2"] < work["1.0"]


def test_w07_foreign_queries(spark, small, monkeypatch):
    monkeypatch.setattr(runs.featurize, "text_vectors", lambda df, key, d: runs.FIXTURES["doc"](spark, small).limit(20))
    assert all(0 <= v <= 1 for v in values(runs.w07_foreign_queries(spark, small, (0.5,)), "recall_10"))


def test_w08_and_w09_profiles(spark, small):
    assert values(runs.w08_partitions(spark, small, (1, 2)).where("params['method'] = 'full'"), "speedup", "tasks")["1"] == 1
    rows = runs.w09_phases(spark, small, iterations=3).collect()
    shares = {r["metric"]: r["value"] for r in rows if r["metric"].startswith("phase_")}
    assert set(shares) == {"phase_" + p for p in ("norms", "product", "first_threshold", "test", "refinement", "sums", "rotation", "update", "split")}
    assert abs(sum(shares.values()) - 1) < 1e-6


def test_w10_head_widths(spark, small):
    df = runs.w10_head_widths(spark, small, ("doc",), (0.125, 1.0), 2).cache()
    work = values(df.where("params['d1'] is not null"), "mul_adds", "d1")
    assert work["0.125"] < work["1.0"]
    assert len(values(df.where("params['controller'] is not null"), "d1")) == 10


def test_w11_ablation_by_work(spark, small):
    work = values(runs.w11_ablation(spark, small, iterations=3), "mul_adds", "variant")
    assert work["phased"] <= work["no_progressive"] < work["full"] and work["phased"] <= work["no_first_threshold"]


def test_w12_classical_vectors(spark, small):
    assert values(runs.w12_classical_vectors(spark, small, ("part",), 2), "wcss")


def test_w14_seeding(spark, small):
    wcss = values(runs.w14_seeding(spark, small, k=20, iterations=2).where("params['iterations'] = '1'"), "wcss", "init")
    assert wcss["kmeans++"] < wcss["random"]


def test_w15_and_w17_shapes(spark, small):
    assert values(runs.w15_space(spark, small), "numbers")[0] > 0
    assert max(values(runs.w17_batch_profiles(spark, small), "max_difference")) < 1e-9


def test_w16_other_variants_skip_distances(spark, small):
    df = runs.w16_other_variants(spark, small, k=12, iterations=3).cache()
    assert min(values(df, "skipped")) > 0
    wcss = values(df, "wcss", "method")
    assert np.allclose([wcss[m] for m in ("elkan", "hamerly", "pivot_each", "pivot_all")], wcss["elkan"], rtol=1e-6)


def test_w18_two_levels_cost_less(spark, small):
    df = runs.w18_two_levels(spark, small).cache()
    work = values(df, "mul_adds", "method")
    assert work["two_level_proportional"] < work["flat"]
    assert all(0 < v <= 1 for v in values(df, "recall_at_equal_exploration"))


def test_w19_grid_and_w22_refinement(spark, small):
    df = runs.w19_iteration_grid(spark, small, meso=(1, 3), fine=(1, 2), fracs=(0.5,)).cache()
    assert values(df, "on_front") and df.where("params['sample'] is not null").count()
    wcss = values(runs.w22_refinement(spark, small), "wcss", "refine")
    assert wcss["2"] <= wcss["0"] * 1.001


def test_lost_neighbours(spark, small):
    assert max(values(runs.false_prune_rate(spark, small, d1s=(8, 16), k=20), "disagree")) < 0.02
