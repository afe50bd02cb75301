import numpy as np
from pyspark.sql import functions as F

from vecspark.llm.language import UNITS, LanguageParams, Lookup, fit_languages, identify_language, learn, op2_language_id
from vecspark.llm.textkit import text_arrays

import pyarrow as pa


def brute_bits(samples, text):
    """Code length of a text by the definition, with plain dictionaries."""
    counts = {}
    for s in samples:
        b = s.encode()
        for i, c in enumerate(b):
            for k in range(5):
                ctx = bytes(b[j] if j >= 0 else 0 for j in range(i - k, i))
                counts.setdefault((k, ctx), {}).setdefault(c, 0)
                counts[k, ctx][c] += 1
    total, b = 0, text.encode()
    for i, c in enumerate(b):
        for k in range(4, -2, -1):
            if k < 0:
                total += 8 * UNITS
                break
            own = counts.get((k, bytes(b[j] if j >= 0 else 0 for j in range(i - k, i))))
            if not own:
                continue
            t = sum(own.values()) + len(own)
            if c in own:
                total += np.rint(-np.log2(own[c] / t) * UNITS)
                break
            total += np.rint(-np.log2(len(own) / t) * UNITS)
    return int(total)


def test_code_lengths_equal_brute_force(text):
    samples = {"x": [text(1, 60), "abc"], "y": ["le la les un une des", text(3, 20)], "z": [""]}
    trees = learn(samples)
    texts = ["", "a", "le la", text(2, 40), "ünïcode ß 東京", "zzzzzzzzzz"]
    got = trees.code_lengths(*text_arrays(pa.array(texts, pa.large_string())))
    for i, t in enumerate(texts):
        for j, lang in enumerate(trees.languages):
            assert got[i, j] == brute_bits(samples[lang], t)


def test_lookup_finds_all_and_nothing_else():
    keys = np.unique(np.random.default_rng(0).integers(0, 2**63, 5000).astype(np.uint64))
    table = Lookup(keys)
    assert (table.find(keys) == np.arange(len(keys))).all()
    assert (table.find(keys + np.uint64(1))[~np.isin(keys + np.uint64(1), keys)] == -1).all()
    assert (Lookup(keys[:0]).find(keys) == -1).all()


def test_held_out_accuracy(spark, medium):
    got = op2_language_id(spark, medium).join(spark.read.parquet(f"{medium}/documents.parquet").select("doc_id", "lang"), "doc_id")
    row = got.where("held_out and lang is not null").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.min("score"), F.max("score")).first()
    assert row[0] > 0.97 and 0 <= row[1] and row[2] <= 1


def test_odd_texts_and_empty_tables(make_docs, odd_texts):
    docs = make_docs(odd_texts, extra=True)
    rows = {r["doc_id"]: r for r in identify_language(docs, fit_languages(docs)).collect()}
    assert [rows[i]["lang_pred"] for i in range(len(odd_texts))] == ["und", "und", "und", "en", "en", "en", "en", "en", "en", "und", "en"]
    assert {r["lang_pred"] for r in identify_language(docs, fit_languages(docs.where("false"))).collect()} == {"und"}
    assert identify_language(docs.where("false"), fit_languages(docs)).count() == 0


def test_more_languages_than_one_table_holds_and_only_long_texts(spark):
    """Every language is predictable, and one whose texts are all long is learned too."""
    alphabets = {f"l{i:02d}": [chr(97 + (i * 7 + j) % 26) + chr(97 + (i * 3 + j * j) % 26) + chr(97 + (i + 5 * j) % 26) for j in range(12)] for i in range(9)}
    rng = np.random.default_rng(1)
    rows = [(i * 100 + n, name, " ".join(rng.choice(parts, 9000 if name == "l08" else 60))) for i, (name, parts) in enumerate(alphabets.items()) for n in range(12)]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    one, sliced = fit_languages(docs), fit_languages(docs, LanguageParams(languages=2))
    assert len(one) == 1 and len(sliced) == 5
    predict = lambda trees: {r["doc_id"]: (r["lang_pred"], round(r["score"], 9), r["bits"]) for r in identify_language(docs, trees).collect()}
    got = predict(sliced)
    assert got == predict(one) and np.mean([got[i][0] == name for i, name, _ in rows]) > 0.95
