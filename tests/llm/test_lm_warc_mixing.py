import base64
import hashlib
import math
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.llm.lm import LmParams, packed, packed_keys, score_corpus, unpacked, unpacked_keys
from vecspark.llm.mixing import CHUNK, MixParams, mix_sources
from vecspark.llm.registry import ORACLES, QUERIES
from vecspark.llm.warc import read_archives, write_archives


def tokens(t):
    return [*re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")), None]


def brute_scores(rows, order, mu):
    grams, train = [Counter() for _ in range(order)], [t for _, t, held in rows if not held]
    for t in train:
        w = ["<s>", *tokens(t)]
        for n in range(1, order + 1):
            for i in range(len(w) - n + 1):
                if n > 1 or i:
                    grams[n - 1][tuple(w[i : i + n])] += 1
    total, kinds = sum(grams[0].values()), len(grams[0])
    out = {}
    for i, t, _ in rows:
        w = ["<s>", *tokens(t)]
        base = score = known = 0
        for k in range(1, len(w)):
            c = grams[0][(w[k],)]
            p = (c + 1) / (total + kinds + 1)
            base, known = base + math.log10(p), known + (c > 0)
            for n in range(2, order + 1):
                if k - n + 1 < 0:
                    break
                h = tuple(w[k - n + 1 : k])
                seen = len(train) if h == ("<s>",) else grams[n - 2][h]
                if seen:
                    p = (grams[n - 1][(*h, w[k])] + mu * p) / (seen + mu)
            score += math.log10(p)
        out[i] = (len(w) - 1, known, total, base, score)
    return out


@pytest.mark.parametrize("p", [LmParams(), LmParams(block_bytes=2000, range_bytes=1500), LmParams(order=3, block_bytes=5000), LmParams(order=1)])
def test_scores_equal_brute_force(make_docs, odd_texts, text, p):
    texts = [*odd_texts, *[text(i, 30) for i in range(15)], "The THE the É é", text(3, 30)]
    docs = make_docs(texts, extra=True)
    rows = [(i, t, i % 5 == 2) for i, t in enumerate(texts)]
    want = brute_scores(rows, p.order, p.mu)
    got = score_corpus(docs, F.col("doc_id") % 5 == 2, p).collect()
    assert len(got) == len(texts)
    for r in got:
        n, known, total, base, score = want[r["doc_id"]]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (n, known, total)
        assert math.isclose(r["base_score"], base, abs_tol=1e-5) and math.isclose(r["score"], score, abs_tol=1e-5)


def test_lm_without_training_and_without_rows(make_docs, text):
    docs = make_docs([text(1, 20), None])
    assert {(r["train_tokens"], r["n_known"], r["score"]) for r in score_corpus(docs, F.lit(True)).collect()} == {(0, 0, 0.0)}
    assert score_corpus(docs.where("false"), F.lit(False)).count() == 0
    for counts in ([], [0, 255], [256], [70_000], [2**40]):
        assert unpacked(packed(np.array(counts, np.int64))).tolist() == counts
    for keys in ([], [5], [1, 2**64 - 1], [3, 4, 300, 70_000], [2**63, 2**63 + 2**47]):
        assert unpacked_keys(packed_keys(np.array(keys, np.uint64))).tolist() == keys


def test_archives_round_trip(spark, tmp_path):
    rows = [(1, "http://a/\r\nx", "<p>é\r\n\r\nWARC/1.1\r\n</p>"), (2, None, None), (3, "u", ""), (4, "u", "<p>é\r\n\r\nWARC/1.1\r\n</p>"), (9, "u", "big" * 200_000), (None, "v", "big" * 200_000), (5, "v", "same"), (5, "v", "same"), (6, "v", "same")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload_digest", F.lit("clash"))
    for least in (0, 5):
        path = str(tmp_path / f"w{least}")
        write_archives(pages, path, least)
        got = sorted(((-1 if r["page_id"] is None else r["page_id"]), r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in read_archives(spark, path).collect())
        top = {}
        for i, _, h in rows:
            top[h or ""] = max(top.get(h or "", -1), -1 if i is None else i)
        want = []
        for i, _, h in rows:
            b = (h or "").encode()
            i = -1 if i is None else i
            again = len(b) >= least and i != top[h or ""]
            want.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "revisit" if again else "response", top[h or ""] if again else None))
        assert got == sorted(want, key=lambda r: r[:2])
        whole = {r["page_id"]: r["html"] for r in read_archives(spark, path).where("record_type = 'response'").collect()}
        assert whole[4] == rows[3][2]
    write_archives(pages.where("false"), str(tmp_path / "none"))
    assert read_archives(spark, str(tmp_path / "none")).count() == 0


def test_mixing_meets_the_weights(spark):
    rows = [(i, "x" * 100, None, f"s{min(i % 7, 3)}", 100) for i in range(6000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    weights = {"s0": 1.0, "s1": 2.0, "s2": 3.0, "s3": 4.0}
    out = mix_sources(docs, MixParams(weights=weights)).groupBy("source").agg(F.sum(F.length("text")).alias("n")).collect()
    total = sum(r["n"] for r in out)
    assert abs(total / 600_000 - 1) < 0.05
    for r in out:
        assert abs(r["n"] / total - weights[r["source"]] / 10) < 0.02
    assert mix_sources(docs, MixParams(weights={"s0": 1.0})).where("source <> 's0'").count() == 0


def test_replication_is_poisson_by_definition(spark):
    docs = spark.createDataFrame([(i, "xy", "en", "only", 2) for i in range(4000)], "doc_id long, text string, lang string, source string, n_chars long")
    got = dict(mix_sources(docs, MixParams(scale=1.7)).groupBy("doc_id").agg(F.max("copy_no"), F.count(F.lit(1))).select("doc_id", "count(1)").collect())
    for i in range(4000):
        u = int(hashlib.md5(f"{i}:17:1".encode()).hexdigest()[:13], 16) / 2**52
        k, p, c = 0, math.exp(-1.7), math.exp(-1.7)
        while c <= u:
            k += 1
            p *= 1.7 / k
            c += p
        assert got.get(i, 0) == k
    many = mix_sources(docs.limit(5), MixParams(scale=3.0 * CHUNK)).count()
    assert abs(many / (15 * CHUNK) - 1) < 0.2


def test_mixing_odd_rows_and_native_plan(make_docs, odd_texts, spark):
    docs = make_docs(odd_texts, extra=True)
    out = mix_sources(docs)
    assert sorted(out.columns) == sorted(docs.columns) and {r[0] for r in out.select("doc_id").collect()} <= set(range(len(odd_texts)))
    assert mix_sources(docs.where("false")).count() == 0
    assert mix_sources(docs.withColumn("source", F.lit(None).cast("string"))).count() > 0
    plan = out._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|InArrow|Cartesian", plan)
    places = [r["doc_id"] for r in mix_sources(make_docs(["t"] * 200)).collect()]
    assert places != sorted(places) and zlib is not None


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql_twins(spark, small, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.sql(f"create view {t} as select * from read_parquet('{small}/{t}.parquet')")
    got = QUERIES[name](spark, small).toPandas()
    want = con.sql(ORACLES[name]).df()[list(got.columns)]
    key = lambda df: sorted(map(str, df.astype(object).where(df.notna(), None).itertuples(index=False, name=None)))
    assert [re.sub(r"(\d)\.0\b", r"\1", x) for x in key(got)] == [re.sub(r"(\d)\.0\b", r"\1", x) for x in key(want)]


def test_the_empty_history_answers_by_token_and_grams_keep_their_order():
    """Every arc of the empty history was searched for among those of all states."""
    from vecspark.llm.lm import BackoffAutomaton, Grams, LmParams, ngram_keys

    tokens = np.array([5, 7, 5, 7, 9, 5], np.uint64) + np.uint64(1 << 40)
    doc = np.zeros(6, int)
    held = np.array([False] * 5 + [True])
    grams = [Grams(k, held) for k in ngram_keys(tokens, doc, 2)]
    for g, k in zip(grams, ngram_keys(tokens, doc, 2), strict=True):
        assert (np.diff(g.key.astype(object)) > 0).all() and (k[g.place] == g.key).all() and (g.key[g.number[k > 0]] == k[k > 0]).all()
    assert sorted(grams[0].own) == [1, 2, 2]
    a = BackoffAutomaton(tokens, grams, 5, 3, LmParams(order=2))
    assert a.root_count[a.token].tolist() == [2, 2, 2, 2, 1, 2] and (a.arc_key >= a.size).all()
    weight, to = a.step(np.zeros(6, np.int64), a.token)
    assert np.allclose(10**weight, (a.root_count[a.token] + 1) / 9) and (to == a.root_to[a.token]).all()


def test_arcs_are_found_by_place_and_grams_that_stand_alone_are_not_sorted(text):
    """Each arc was searched for by state and token among all arcs of the block, after a sort of every n-gram."""
    import pyarrow as pa

    from vecspark.llm.lm import BackoffAutomaton, Grams, LmParams, ngram_keys, sorting, token_stream
    from vecspark.llm.textkit import text_arrays

    texts = [text(i, 60) for i in range(30)] + ["", "once only", "once only"] + [text(3, 60)]
    tokens, doc = token_stream(*text_arrays(pa.array(texts, pa.large_string())))
    held, keys = doc % 4 == 1, ngram_keys(tokens, doc, 3)
    two = Grams(keys[1], held)
    once = np.append(two.size == 1, False)[two.number]
    alone = once | np.append(False, once[:-1])
    three, plain = Grams(keys[2], held, alone), Grams(keys[2], held)
    here = keys[2] > 0
    assert 0 < (alone & here).sum() < here.sum() and len(three.key) == len(plain.key)
    for name in ("key", "own", "size"):
        assert (getattr(three, name)[three.number[here]] == getattr(plain, name)[plain.number[here]]).all()
    a = BackoffAutomaton(tokens, [Grams(keys[0], held), two, three], 1000, 300, LmParams())
    seen = {k: i for i, k in enumerate(a.arc_key.tolist())}
    assert len(seen) == sum((g.own > 0).sum() for g in (two, three))
    state, fails = a.start, 0
    for i in np.flatnonzero(doc == 0)[1:]:
        while state:
            at = a.arc(np.array([state]), np.array([i]))[0]
            assert (at > 0) == (state * a.size + a.token[i] in seen)
            if at > 0:
                break
            state, fails = a.fail[state], fails + 1
        state = a.arc_to[at - a.arcs] if state else a.root_to[a.token[i]]
    assert state == 0 or state < len(a.fail)
    keys = np.array([5, 4, 5, 2**40 + 1, 2**40, 4], np.uint64)
    assert sorting(keys).tolist() == np.argsort(keys, kind="stable").tolist() == [1, 5, 0, 2, 4, 3]
    assert len(sorting(keys[:0])) == 0
