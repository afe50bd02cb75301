"""Operators over whole inputs: every character, every query, every row."""

import hashlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.functions import kernels
from vecspark.operators import index, measures
from vecspark.operators.assign import assign_full
from vecspark.operators.quantise import tile_assign
from vecspark.operators.seeding import every_20th, start_matrix
from vecspark.operators.stopping import plateau, plateaus
from vecspark.queries import ORACLES, QUERIES
from vecspark.sources import featurize
from vecspark.sources.vectors import embeddings


def cells(text: str, d: int) -> dict:
    """The definition, gram by gram."""
    out, low = {}, text.lower()
    for i in range(max(1, len(low) - 2)):
        h = int(hashlib.md5(low[i : i + 3].encode()).hexdigest()[:8], 16)
        out[h % d] = out.get(h % d, 0) + (1 if h >> 20 & 1 else -1)
    return {k: v for k, v in out.items() if v}


def test_text_vectors_read_every_character(spark):
    rng = np.random.default_rng(0)
    texts = ["".join(rng.choice(list("abcé東 Z"), n)) for n in (1, 2, 3, 999, 1001, 1002, 1003, 2002, 2003, 7001)]
    docs = spark.createDataFrame([*enumerate(texts)], "doc_id long, text string")
    got: dict = {i: {} for i in range(len(texts))}
    for r in featurize.trigram_cells(docs, "doc_id", 64).collect():
        got[r["doc_id"]][r["dim"]] = r["n"]
    assert got == {i: cells(t, 64) for i, t in enumerate(texts)}
    tail = docs.where("doc_id = 9").withColumn("text", F.concat("text", F.lit("unseen ending " * 40)))
    whole = [featurize.text_vectors(x, "doc_id", 64).first()["vec"] for x in (docs.where("doc_id = 9"), tail)]
    assert whole[0] != whole[1]


def test_searches_take_any_number_of_queries_in_blocks(spark, small, monkeypatch):
    v = embeddings(spark, small)
    queries, y = every_20th(v), start_matrix(v, 10, 0)
    lists = v.join(assign_full(v, y, dtype=np.float64), "vec_id")
    ask = lambda: [sorted(map(tuple, df.collect())) for df in (index.exact_knn(queries, v, 5), index.index_search(queries, lists, y, 5, 3))]
    n, whole = queries.count(), ask()
    assert n > 7 and {r[0] for r in whole[0]} == {r[0] for r in queries.collect()}
    monkeypatch.setattr(index, "QUERY_BLOCK", 3)
    monkeypatch.setattr(index, "PAIRS_AT_ONCE", 50)
    assert ask() == whole
    assert len([*index.query_blocks(queries)]) == -(-n // 3)


@pytest.mark.parametrize("name", ["index_search_fitted", "index_on_disk_search_fitted", "index_search_10", "index_on_disk_search"])
def test_index_search_reaches_its_recall(spark, medium, name):
    v = embeddings(spark, medium)
    truth = index.exact_knn(every_20th(v), v, 10)
    recall = index.recall_at(QUERIES[name](spark, medium), truth, 10).first()[0]
    assert 0.9 <= recall < 1


def test_tiles_are_exact_ranks_without_one_task_of_all_rows(spark):
    rng = np.random.default_rng(2)
    for n in (0, 3, 1003):
        x = np.where(rng.random((n, 2)) < 0.4, 0.5, rng.random((n, 2)))
        df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, vec array<double>")
        got = tile_assign(df, 2, 4)
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("windowspecdefinition(") == plan.count("windowspecdefinition(range")
        want = {i: [] for i in range(n)}
        for c in range(2):
            for t, part in enumerate(np.array_split(np.lexsort((np.arange(n), x[:, c])), 4)):
                for i in part:
                    want[int(i)].append(str(t))
        assert {r["vec_id"]: r["tile"] for r in got.collect()} == {i: "_".join(t) for i, t in want.items()}


def test_sessions_open_at_the_end_are_kept(spark, tmp_path):
    rows = [(1, 0, "2024-01-01 00:00:00"), (2, 0, "2024-01-01 06:00:00"), (3, 0, "2024-01-01 12:00:01"), (4, 7, "2024-01-01 12:30:00")]
    events = spark.createDataFrame(rows, "event_id long, user_id long, ts string").withColumn("ts", F.to_timestamp_ntz("ts"))
    events.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = sorted((r["user_id"], r["start"], r["n"]) for r in QUERIES["stream_session"](spark, str(tmp_path)).collect())
    at = 1704067200
    con = duckdb.connect()
    con.sql(f"create view events as select * from read_parquet('{tmp_path}/events.parquet/*.parquet')")
    assert got == [(0, at, 2), (0, at + 43201, 1), (7, at + 45000, 1)] == sorted(con.sql(ORACLES["stream_session"]).fetchall())


def test_pair_queries_ask_every_20th_row(spark, small):
    v = embeddings(spark, small)
    wanted = {r["qid"] for r in every_20th(v).collect()}
    for name in ("l2_array", "sql_knn", "exact_knn_10"):
        assert {r["qid"] for r in QUERIES[name](spark, small).select("qid").distinct().collect()} == wanted
    assert QUERIES["scan_embeddings"](spark, small).where("NOT vec_id BETWEEN 10 AND 400").count() > 0


def test_a_search_lists_only_the_folders_it_needs(spark, small, tmp_path):
    from vecspark.operators.model import Model

    v = embeddings(spark, small)
    y = start_matrix(v, 16, 0)
    lists = index.build_index(v, Model(y, np.zeros(16, int)), str(tmp_path / "index"), cid_buckets=8)
    plan = index.only_lists(lists, [3, 11])._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [cid_bucket" in plan.replace("isnotnull(cid_bucket#", "") or "cid_bucket" in plan.split("PartitionFilters: [")[1].split("]")[0]
    assert {r[0] for r in index.only_lists(lists, [3, 11]).select("cid").distinct().collect()} <= {3, 11}
    assert len(index.only_lists(lists, [3, 11]).inputFiles()) <= len(lists.inputFiles())


def test_pieces_of_long_texts_keep_their_documents_apart(spark):
    docs = spark.createDataFrame([(1, "a" * 500_000), (2, "b" * 300), (1001, "c" * 10), (None, "x"), (3, None), (4, "")], "doc_id long, text string")
    got = featurize.chunks(docs, 400).collect()
    assert len({r["piece_id"] for r in got}) == len(got) == 1250 + 1 + 1
    assert {(r["piece_id"] // featurize.PIECES, r["text"][0]) for r in got} == {(1, "a"), (2, "b"), (1001, "c")}


@pytest.mark.parametrize("name", ["cosine_array", "exact_knn_sql", "head_plus_tail", "l2_by_inner_product", "rotation_preserves_l2"])
def test_pairs_are_scored_by_products_of_matrices(spark, medium, name):
    """Array functions took 17 microseconds a pair; rows are compared with the definition."""
    df = QUERIES[name](spark, medium)
    assert "lambdafunction" not in df._jdf.queryExecution().optimizedPlan().toString()
    got = df.toPandas()
    rows = embeddings(spark, medium).orderBy("vec_id").collect()
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], np.float64)
    q = x[ids % 20 == 0]
    d = ((q[:, None] - x[None]) ** 2).sum(2)
    if name == "exact_knn_sql":
        d[ids[ids % 20 == 0][:, None] == ids[None]] = np.inf
        want = np.sort(d, 1)[:, :10]
        assert np.allclose(got.sort_values(["qid", "rank"]).dist.to_numpy().reshape(want.shape), want, atol=1e-6)
        return
    if name == "cosine_array":
        d = q @ x.T / np.sqrt((q * q).sum(1)[:, None] * (x * x).sum(1)[None])
    assert len(got) == d.size and np.allclose(got.sort_values(["qid", "vec_id"]).iloc[:, 2].to_numpy().reshape(d.shape), d, atol=1e-6)


def test_pairs_of_odd_vectors(spark, monkeypatch):
    monkeypatch.setattr(index, "PAIRS_A_BATCH", 2)
    v = spark.createDataFrame([(0, [3.0, 4.0]), (1, [0.0, 0.0]), (2, None), (3, [1.0]), (20, [-4.0, 3.0]), (20, [4.0, -3.0])], "vec_id long, vec array<float>").coalesce(1)
    got = {}
    for r in index.pair_scores(every_20th(v), v, kernels.cosines, "s").collect():
        got.setdefault((r[0], r[1]), []).append(r[2])
    assert len(got) == 2 * 5 and sorted(got[0, 20]) == [0, 0] and got[0, 0] == [1] and np.isnan(got[0, 1]).all() and got[0, 2] == got[0, 3] == [None]
    assert sorted(got[20, 20]) == [-1, -1, 1, 1]
    none = index.pair_scores(every_20th(v).where("qid > 20"), v, kernels.cosines, "s")
    assert none.collect() == [] and none.columns == ["qid", "vec_id", "s"]


@pytest.mark.parametrize("name", ["controller_trace", "default_k_table", "iter_lag", "model_json_roundtrip", "pareto_front", "patience_trace", "recursive_iter_table", "space_model_table", "split_empty", "theta_table", "two_level_shares"])
def test_rows_come_from_a_given_table(spark, small, medium, name):
    """Made-up rows were the same whatever the tables held."""
    a, b = (sorted(map(str, QUERIES[name](spark, d).collect())) for d in (small, medium))
    assert a != b and a and b


def test_plateaus_are_those_of_every_prefix():
    rng = np.random.default_rng(0)
    for rule in ("patience", "window"):
        for patience in (1, 2, 3):
            x = np.round(rng.random(60), 2).tolist()
            assert plateaus(x, 0.1, patience, rule) == [plateau(x[: i + 1], 0.1, patience, rule) for i in range(60)]
    assert plateaus([], 0.1) == []


def test_pareto_front_is_that_of_all_pairs(spark):
    rng = np.random.default_rng(1)
    rows = [(i, int(a), float(b), int(c)) for i, (a, b, c) in enumerate(rng.integers(0, 30, (400, 3)))] + [(900, None, 1.0, 1), (901, 2, None, 3)]
    df = spark.createDataFrame(rows, "id int, a int, b double, c int").repartition(5)
    best = lambda r, s: s[1] <= r[1] and s[2] <= r[2] and s[3] >= r[3] and s[1:] != r[1:]
    full = [r for r in rows if None not in r]
    want = sorted(r[0] for r in full if not any(best(r, s) for s in full)) + [900, 901]
    front = measures.pareto(df, ["a", "b"], ["c"])
    assert sorted(r["id"] for r in front.collect()) == want and front.columns == df.columns
    assert measures.pareto(df.where("id < 0"), ["a"], ["c"]).collect() == []
