import re
from collections import Counter

from pyspark.sql import functions as F

from vecspark.llm import quality
from vecspark.llm.quality import QualityParams, assess_quality, filter_quality, fit, fit_quality

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    t = text or ""
    w = WORD.findall(t)
    grams = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    covered = {i + j for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for j in range(3)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), dup, len(covered)


def test_counts_equal_brute_force(make_docs, odd_texts, text):
    texts = [*odd_texts, "x y z x y z x y", "l\nl \nl\n\nl", "#a $b |c| <d>", text(4, 60) + "\n" + text(4, 60)]
    docs = make_docs(texts, extra=True)
    rows = {r["doc_id"]: r for r in assess_quality(docs, fit([], QualityParams())).collect()}
    for i, t in enumerate(texts):
        r = rows[i]
        n, chars, symbols, dup, rep = brute(t)
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, symbols, dup, rep)
        assert r["base_failed"] == (n < 50 or 100 * rep > 50 * n)
        assert not (r["base_failed"] and r["kept"])


def test_learns_and_filters(spark, medium):
    docs, labels = (spark.read.parquet(f"{medium}/{t}.parquet") for t in ("documents", "labels"))
    model = fit_quality(docs, labels.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 2 == 0))
    rows = assess_quality(docs, model).join(labels.select("doc_id", F.col("quality").alias("y")), "doc_id").where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 2 == 1).collect()
    good = [r for r in rows if r["y"] == 1 and not r["base_failed"]]
    bad = [r for r in rows if r["y"] == 0]
    assert sum(r["kept"] for r in good) / len(good) > 0.95
    assert sum(r["kept"] for r in bad) / len(bad) < 0.1
    out = filter_quality(docs, model)
    assert out.columns == docs.columns and {r[0] for r in out.select("doc_id").collect()} == {r["doc_id"] for r in assess_quality(docs, model).where("kept").collect()}


def test_empty_tables_and_one_class(spark, make_docs, text):
    none = make_docs([])
    assert assess_quality(none, fit([], QualityParams())).count() == 0 and filter_quality(none, fit([], QualityParams())).count() == 0
    labels = spark.createDataFrame([(0, 1), (1, 1), (None, 0), (2, None)], "doc_id long, quality int")
    docs = make_docs([text(i, 80) for i in range(3)])
    assert assess_quality(docs, fit_quality(docs, labels)).where("kept").count() == 3
    assert quality.platt is not None
