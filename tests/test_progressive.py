import numpy as np

from vecspark.operators.assign import assign_full
from vecspark.operators.index import exact_knn, index_search
from vecspark.operators.progressive import ProgressiveIndex


def test_lists_are_built_where_queries_go(spark, tmp_path):
    rng = np.random.default_rng(4)
    y = rng.normal(size=(8, 16)) * 5
    x = y[rng.integers(0, 8, 500)] + rng.normal(size=(500, 16)) * 0.5
    v = spark.createDataFrame([(i, [float(a) for a in row]) for i, row in enumerate(x)], "vec_id long, vec array<float>").cache()
    near_one = spark.createDataFrame([(1000 + i, [float(a) for a in y[0] + rng.normal(size=16) * 0.3]) for i in range(12)], "qid long, qvec array<float>").cache()
    far = spark.createDataFrame([(2000 + i, [float(a) for a in y[1 + i % 7]]) for i in range(7)], "qid long, qvec array<float>").cache()
    index = ProgressiveIndex(v, 0, str(tmp_path / "lists"), nprobe=2, heat=5, centroids=y)
    rows = lambda df: sorted((r["qid"], r["rank"], r["vec_id"]) for r in df.collect())
    assert rows(index.search(near_one, 5)) == rows(exact_knn(near_one, v, 5)) and not index.built
    built = index.crack()
    assert 0 in built and len(built) < 8 and index.crack() == []
    assert index.lists().count() < 500
    whole = assign_full(v, y, dtype=np.float64, carry=("vec_id", "vec"))
    served = index.search(near_one.union(far), 5).cache()
    warm = [r for r in rows(served) if r[0] < 2000]
    assert warm and {r[0] for r in rows(served)} == {*range(1000, 1012), *range(2000, 2007)}
    assert [r for r in rows(served) if r[0] >= 2000] == rows(exact_knn(far, v, 5))
    assert len(set(warm) & set(rows(index_search(near_one, whole, y, 5, 2)))) == len(warm)
