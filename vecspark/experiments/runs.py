"""The experiment workloads on the given tables.  Each run returns rows (workload, fixture, params, metric, value).

Every run takes a session, the tables' folder and a number of seeds; quality is averaged over seeds by `summary`.
Absolute seconds depend on the machine; the measures to compare are ratios, recall, vectors explored and work.
"""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.functions.kernels import BatchPlan, CentroidBlocks, Work, assign_full, assign_pruned, elkan, hamerly
from vecspark.operators import measures
from vecspark.operators.clustering import BoundedKMeans, LloydKMeans, PhasedKMeans, PivotKMeans, TwoLevelKMeans
from vecspark.operators.index import exact_knn, match_explored, probe_curve, query_matrix
from vecspark.operators.model import Model
from vecspark.operators.rotation import random_rotation
from vecspark.operators.seeding import default_k, init_kmeanspp, sample_queries, sample_rows, start_matrix
from vecspark.operators.stopping import Convergence, RecallPlateau
from vecspark.sources import featurize
from vecspark.sources.files import settle
from vecspark.sources.vectors import embeddings, read_table

SCHEMA = "workload string, fixture string, params map<string,string>, metric string, value double"
FIXTURES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "emb": embeddings,
    "doc": lambda s, d: featurize.document_vectors(s, d, 512),
    "chunk": lambda s, d: featurize.chunk_vectors(s, d, 256),
    "line": featurize.order_vectors,
    "part": featurize.part_vectors,
    "event": featurize.user_day_vectors,
}


class Bench:
    """A fixture with queries and exact neighbours, made once."""

    def __init__(self, spark: SparkSession, sf_dir: str, fixture: str, n_queries: int = 1000, topk: int = 100, queries: DataFrame | None = None):
        self.spark, self.fixture, self.topk = spark, fixture, topk
        self.vectors = settle(FIXTURES[fixture](spark, sf_dir).repartition(spark.sparkContext.defaultParallelism), f"fixture-{fixture}")
        self.n = self.vectors.count()
        self.d = len(self.vectors.first()["vec"])
        self.k = default_k(self.n)
        began = time.perf_counter()
        self.queries = settle(queries if queries is not None else sample_queries(self.vectors, n_queries), "queries")
        self.truth = settle(exact_knn(self.queries, self.vectors, topk, exclude_self=queries is None), "truth")
        self.truth_secs = time.perf_counter() - began

    def measure(self, workload: str, params: dict, model: Model, secs: float, method=None, probe_fracs=(0.05,)) -> list[tuple]:
        lists = settle((method or LloydKMeans(k=model.k)).transform(self.vectors, model), "lists")
        levels = sorted({max(1, int(np.ceil(f * model.k))) for f in probe_fracs})
        curves = {k: probe_curve(self.queries, lists, model.centroids.astype(np.float64), self.truth, k, levels).collect() for k in sorted({min(10, self.topk), self.topk})}
        work = measures.work_report(model.history, self.n, model.k, self.d)
        size = measures.points_per_cluster(lists, model.k).first()
        out = {"secs": secs, "wcss": lists.agg(F.sum("dist")).first()[0], "mul_adds": work["mul_adds"], "work_of_full": work["of_full"], "iterations": len(model.history), "ppc_mean": size["ppc_mean"], "ppc_std": size["ppc_std"]}
        rates = [h["prune_rate"] for h in model.history if h.get("prune_rate") is not None]
        if rates:
            out["prune_rate"], out["d1"] = float(np.mean(rates)), model.history[-1]["d1"]
        rows = self.rows(workload, params, out)
        for k, curve in curves.items():
            for r in curve:
                rows += self.rows(workload, params | {"nprobe": r["nprobe"]}, {f"recall_{k}": r["recall"], "explored": r["explored"], "explored_share": r["explored"] / self.n})
        return rows

    def rows(self, workload: str, params: dict, values: dict) -> list[tuple]:
        return [(workload, self.fixture, {k: str(v) for k, v in params.items()}, m, float(v)) for m, v in values.items() if v is not None]

    def fit(self, workload: str, params: dict, method, start=None, **kw) -> tuple[list[tuple], Model]:
        began = time.perf_counter()
        model = method.fit(self.vectors) if start is None else method.fit(self.vectors, start)
        return self.measure(workload, params, model, time.perf_counter() - began, method if hasattr(method, "transform") else None, **kw), model


def frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, SCHEMA)


def summary(results: DataFrame) -> DataFrame:
    """Mean and deviation over seeds."""
    params = F.to_json(F.map_filter("params", lambda k, v: k != "seed")).alias("params")
    return results.groupBy("workload", "fixture", params, "metric").agg(F.avg("value").alias("mean"), F.stddev_pop("value").alias("std"), F.count(F.lit(1)).alias("seeds"))


def w01_phased_against_full(spark, sf_dir, fixtures=("emb", "doc"), iterations=25, seeds=1) -> DataFrame:
    """Also the quality table: equal recall, exploration and cost at less work."""
    rows = []
    for fixture in fixtures:
        b = Bench(spark, sf_dir, fixture)
        for seed in range(seeds):
            for name, cls in (("full", LloydKMeans), ("phased", PhasedKMeans)):
                rows += b.fit("w01", {"method": name, "seed": seed}, cls(k=b.k, max_iter=iterations, seed=seed), probe_fracs=(0.01, 0.05, 0.1))[0]
    return frame(spark, rows)


def w03_cluster_counts(spark, sf_dir, ks=(10, 32, 100, 400, 1000), iterations=5) -> DataFrame:
    b, rows = Bench(spark, sf_dir, "doc"), []
    for k in [k for k in ks if k < b.n]:
        for name, cls in (("full", LloydKMeans), ("phased", PhasedKMeans)):
            rows += b.fit("w03", {"method": name, "k": k}, cls(k=k, max_iter=iterations))[0]
    return frame(spark, rows)


def w04_stopping(spark, sf_dir, fixture="doc", cap=25) -> DataFrame:
    """Also exploration across iterations: the history of each rule."""
    b, rows = Bench(spark, sf_dir, fixture), []
    rules = {"recall_.005": [RecallPlateau(0.005, topk=b.topk, probe_frac=0.05, queries=b.queries, truth=b.truth, exclude_self=True)], "recall_.0025": [RecallPlateau(0.0025, topk=b.topk, probe_frac=0.05, queries=b.queries, truth=b.truth, exclude_self=True)], "cap_10": None, "movement": [Convergence(1e-3)]}
    for name, stop in rules.items():
        method = PhasedKMeans(k=b.k, max_iter=10 if stop is None else cap, stop=stop or [])
        own, model = b.fit("w04", {"rule": name}, method)
        rows += own
        for h in model.history:
            rows += b.rows("w05", {"rule": name, "iter": h["iter"]}, {m: h.get(m) for m in ("recall", "explored", "wcss", "shift")})
    return frame(spark, rows)


def w06_sampling(spark, sf_dir, fixture="doc", fracs=(0.05, 0.1, 0.2, 0.3, 0.5, 0.75, 1.0), k=40, seeds=3) -> DataFrame:
    b, rows = Bench(spark, sf_dir, fixture), []
    for frac in fracs:
        for seed in range(seeds):
            rows += b.fit("w06", {"frac": frac, "seed": seed}, PhasedKMeans(k=k, max_iter=8, sample_frac=frac, seed=seed))[0]
    return frame(spark, rows)


def w07_foreign_queries(spark, sf_dir, fracs=(0.1, 0.3, 1.0)) -> DataFrame:
    items = featurize.text_vectors(read_table(spark, sf_dir, "benchmark"), "item_id", 512).select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
    b, rows = Bench(spark, sf_dir, "doc", queries=items), []
    for frac in fracs:
        rows += b.fit("w07", {"frac": frac}, PhasedKMeans(k=40, max_iter=8, sample_frac=frac))[0]
    return frame(spark, rows)


def w08_partitions(spark, sf_dir, counts=(1, 2, 4, 8)) -> DataFrame:
    """Seconds of one iteration by the number of tasks that it may use at once."""
    b, rows = Bench(spark, sf_dir, "doc"), []
    start = start_matrix(b.vectors, b.k, 0)
    LloydKMeans(k=b.k, max_iter=1).fit(b.vectors, start)  # what a session does once is not measured
    one: dict[str, float] = {}
    for n in counts:
        own = settle(b.vectors.repartition(n), "parts")
        for name, cls in (("full", LloydKMeans), ("phased", PhasedKMeans)):
            began = time.perf_counter()
            cls(k=b.k, max_iter=3).fit(own, start)
            secs = time.perf_counter() - began
            rows += b.rows("w08", {"method": name, "tasks": n}, {"secs": secs, "speedup": measures.speedup(one.setdefault(name, secs), secs)})
    return frame(spark, rows)


def w09_phases(spark, sf_dir, fixture="doc", iterations=10) -> DataFrame:
    """Also the overhead of exact neighbours: shares of set-up, first iteration, head product and refinement."""
    b = Bench(spark, sf_dir, fixture)
    rule = RecallPlateau(-1.0, topk=b.topk, probe_frac=0.05, queries=b.queries, truth=b.truth, exclude_self=True)
    model = PhasedKMeans(k=b.k, max_iter=iterations, stop=[rule]).fit(b.vectors)
    later = model.history[1:]
    head, tail = sum(h["head_mul_adds"] for h in later), sum(h["tail_mul_adds"] for h in later)
    values = measures.phase_times(model.history) | {f"share_{k}": v for k, v in measures.overhead_shares(model.history, b.truth_secs, recall_secs=rule.secs).items()} | {f"phase_{k}": v for k, v in measures.phase_profile(model.history).items()} | {"head_share_of_work": head / max(1, head + tail)}
    return frame(spark, b.rows("w09", {}, values))


def w10_head_widths(spark, sf_dir, fixtures=("doc", "emb"), shares=(1 / 16, 1 / 8, 1 / 4, 1 / 2, 1.0), iterations=4) -> DataFrame:
    rows = []
    for fixture in fixtures:
        b = Bench(spark, sf_dir, fixture)
        for s in shares:
            rows += b.fit("w10", {"d1": s}, PhasedKMeans(k=b.k, max_iter=iterations, d1=max(1, int(b.d * s)), adapt=False))[0]
        model = PhasedKMeans(k=b.k, max_iter=10).fit(b.vectors)
        for h in model.history:
            rows += b.rows("w10", {"controller": 1, "iter": h["iter"]}, {"d1": h["d1"], "prune_rate": h["prune_rate"]})
    return frame(spark, rows)


def w11_ablation(spark, sf_dir, fixture="doc", iterations=6) -> DataFrame:
    b, rows = Bench(spark, sf_dir, fixture), []
    variants = {"phased": {}, "previous_centroid": {"seed_mode": "previous"}, "no_first_threshold": {"seed_mode": "first_batch", "plan": BatchPlan(4096, 128)}, "no_layout": {"layout": "rows"}, "no_progressive": {"progressive": False}, "no_adaptation": {"adapt": False}}
    for name, options in variants.items():
        rows += b.fit("w11", {"variant": name}, PhasedKMeans(k=b.k, max_iter=iterations, refinement="pairs", **options))[0]
    for name in ("grouped", "auto"):
        rows += b.fit("w11", {"variant": f"refinement_{name}"}, PhasedKMeans(k=b.k, max_iter=iterations, refinement=name))[0]
    rows += b.fit("w11", {"variant": "full"}, LloydKMeans(k=b.k, max_iter=iterations))[0]
    return frame(spark, rows)


def w12_classical_vectors(spark, sf_dir, fixtures=("line", "event", "part"), iterations=6) -> DataFrame:
    return w01_phased_against_full(spark, sf_dir, fixtures, iterations).withColumn("workload", F.lit("w12"))


def w14_seeding(spark, sf_dir, fixture="doc", k=40, iterations=6, seeds=1) -> DataFrame:
    b, rows = Bench(spark, sf_dir, fixture), []
    for seed in range(seeds):
        for name in ("random", "kmeans++"):
            began = time.perf_counter()
            start = init_kmeanspp(b.vectors, k, seed) if name == "kmeans++" else start_matrix(b.vectors, k, seed)
            secs = time.perf_counter() - began
            rows += b.rows("w14", {"init": name, "seed": seed}, {"init_secs": secs})
            for n in (1, iterations):
                rows += b.fit("w14", {"init": name, "iterations": n, "seed": seed}, PhasedKMeans(k=k, max_iter=n, seed=seed), start)[0]
    return frame(spark, rows)


def w15_space(spark, sf_dir) -> DataFrame:
    b = Bench(spark, sf_dir, "emb")
    return frame(spark, b.rows("w15", {"k": b.k}, {"numbers": measures.space_model(b.n, b.d, b.k), "numbers_in_place": measures.space_model(b.n, b.d, b.k, False), "buffer_bytes": BatchPlan().buffer_bytes()}))


def w16_other_variants(spark, sf_dir, fixture="doc", k=100, iterations=5) -> DataFrame:
    """Distances that triangle-inequality bounds skip: kept bounds in a task and distributed, pivots without state; the platform's own."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    b, rows = Bench(spark, sf_dir, fixture), []
    part = sample_rows(b.vectors, min(1.0, 5000 / b.n))
    x = query_matrix(part.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec")))[1]
    for name, f in (("elkan", elkan), ("hamerly", hamerly)):
        began = time.perf_counter()
        _, _, done, pairs = f(x, x[:k], iterations)
        rows += b.rows("w16", {"method": f"{name}_in_a_task"}, {"skipped": 1 - done / pairs, "secs": time.perf_counter() - began})
        rows += b.fit("w16", {"method": name}, BoundedKMeans(k, iterations, name))[0]
    for name in ("each", "all"):
        rows += b.fit("w16", {"method": f"pivot_{name}"}, PivotKMeans(k, iterations, variant=name))[0]
    rows += b.fit("w16", {"method": "phased"}, PhasedKMeans(k=k, max_iter=iterations))[0]
    ml = b.vectors.select("vec_id", array_to_vector("vec").alias("features"))
    for name, est in (("platform", KMeans(k=k, maxIter=iterations, initMode="random", seed=1)), ("platform_bisecting", BisectingKMeans(k=k, maxIter=iterations, seed=1))):
        began = time.perf_counter()
        fitted = est.fit(ml)
        rows += b.rows("w16", {"method": name}, {"secs": time.perf_counter() - began, "wcss": fitted.summary.trainingCost})
    return frame(spark, rows)


def w17_batch_profiles(spark, sf_dir, fixture="doc") -> DataFrame:
    """Also sensitivity to batch shapes: the same centroids for each shape, and seconds."""
    b, rows = Bench(spark, sf_dir, fixture), []
    start, base = start_matrix(b.vectors, b.k, 0), None
    for plan in (BatchPlan(1024, 256), BatchPlan(), BatchPlan(40_960, 10_240), BatchPlan.large()):
        began = time.perf_counter()
        y = PhasedKMeans(k=b.k, max_iter=3, epsilon0=np.inf, plan=plan, dtype=np.float64).fit(b.vectors, start).centroids
        base = y if base is None else base
        rows += b.rows("w17", {"x_rows": plan.x_rows, "y_rows": plan.y_rows}, {"secs": time.perf_counter() - began, "max_difference": np.abs(y - base).max()})
    return frame(spark, rows)


def w18_two_levels(spark, sf_dir, fixtures=("doc",), seeds=1) -> DataFrame:
    """Also equal exploration: the two-level index at the number of lists that explores as much as the flat one."""
    rows = []
    for fixture in fixtures:
        b = Bench(spark, sf_dir, fixture)
        for seed in range(seeds):
            flat_rows, flat = b.fit("w18", {"method": "flat", "seed": seed}, PhasedKMeans(k=b.k, max_iter=10, seed=seed))
            rows += flat_rows
            asked = next(r[4] for r in flat_rows if r[3] == "explored")
            for rule in ("proportional", "sqrt"):
                method = TwoLevelKMeans(k=b.k, fine_k=rule, seed=seed)
                own, model = b.fit("w18", {"method": f"two_level_{rule}", "seed": seed}, method)
                rows += own
                curve = probe_curve(b.queries, settle(method.transform(b.vectors, model), "lists"), model.centroids.astype(np.float64), b.truth, b.topk, list(range(1, min(model.k, 60), 2)))
                r = match_explored(curve, asked).first()
                rows += b.rows("w20", {"method": f"two_level_{rule}", "seed": seed}, {"recall_at_equal_exploration": r["recall"], "explored": r["explored"], "nprobe": r["nprobe"]})
    return frame(spark, rows)


def w19_iteration_grid(spark, sf_dir, fixture="doc", meso=(1, 3, 5), fine=(1, 5, 8), fracs=(0.3,)) -> DataFrame:
    """The rows of the front alone carry the metric `on_front`; also two levels on a sample of the rows."""
    b, rows, grid = Bench(spark, sf_dir, fixture), [], []
    for m in meso:
        for f in fine:
            own, model = b.fit("w19", {"meso": m, "fine": f}, TwoLevelKMeans(k=b.k, meso_iter=m, fine_iter=f))
            rows += own
            grid.append((m, f, float(sum(h["mul_adds"] for h in model.history)), next(r[4] for r in own if r[3].startswith("recall"))))
    for frac in fracs:
        rows += b.fit("w19", {"sample": frac}, TwoLevelKMeans(k=b.k, sample_frac=frac))[0]
    front = measures.pareto(spark.createDataFrame(grid, "meso int, fine int, work double, recall double"), ["work"], ["recall"]).collect()
    for r in front:
        rows += b.rows("w19", {"meso": r["meso"], "fine": r["fine"]}, {"on_front": 1.0})
    return frame(spark, rows)


def w22_refinement(spark, sf_dir, fixture="doc") -> DataFrame:
    b, rows = Bench(spark, sf_dir, fixture), []
    for n in (0, 1, 2):
        rows += b.fit("w22", {"refine": n}, TwoLevelKMeans(k=b.k, refine_iter=n))[0]
    return frame(spark, rows)


def false_prune_rate(spark, sf_dir, fixture="doc", d1s=(32, 64, 128), k=400) -> DataFrame:
    """Rows whose nearest centroid the default test gives up, and the share of work, by head width."""
    b, rows = Bench(spark, sf_dir, fixture), []
    x = query_matrix(sample_rows(b.vectors, min(1.0, 10_000 / b.n)).select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec")))[1] @ random_rotation(b.d, 0)
    y = x[:: max(1, len(x) // k)][:k]
    exact, _ = assign_full(x, y)
    for d1 in d1s:
        work = Work()
        cid, _ = assign_pruned(x, CentroidBlocks(y, d1, 64), work=work)
        rows += b.rows("c08", {"d1": d1}, {"disagree": float((cid != exact).mean()), "prune_rate": work.rejected_head / max(1, work.tested), "work_of_full": (work.head_mul_adds + work.tail_mul_adds) / (x.shape[0] * y.size)})
    return frame(spark, rows)


RUNS = {f.__name__.split("_")[0]: f for f in (w01_phased_against_full, w03_cluster_counts, w04_stopping, w06_sampling, w07_foreign_queries, w08_partitions, w09_phases, w10_head_widths, w11_ablation, w12_classical_vectors, w14_seeding, w15_space, w16_other_variants, w17_batch_profiles, w18_two_levels, w19_iteration_grid, w22_refinement)} | {"c08": false_prune_rate}


def main() -> None:
    """python -m vecspark.experiments.runs FOLDER NAME...: prints each run's summary."""
    import sys

    from vecspark.session import ship

    spark = ship(SparkSession.builder.appName("experiments").getOrCreate())
    for name in sys.argv[2:] or sorted(RUNS):
        print(name, (RUNS[name].__doc__ or "").split("\n")[0])
        summary(RUNS[name](spark, sys.argv[1])).orderBy("workload", "fixture", "metric", "params").show(400, False)


if __name__ == "__main__":
    main()
