import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from vecspark.llm.textkit import text_arrays
from vecspark.llm.toxicity import ToxicParams, calibrated_threshold, fit, fit_toxicity, op5_toxicity, score_toxicity, word_parts

FAST = ToxicParams(steps=60, epochs=2)


def test_held_out_accuracy(spark, medium):
    rows = op5_toxicity(spark, medium).join(spark.read.parquet(f"{medium}/labels.parquet").select("doc_id", "toxic"), "doc_id").where("held_out").toPandas()
    rank, pos = rows.score.rank(), rows.toxic == 1
    auc = (rank[pos].sum() - pos.sum() * (pos.sum() + 1) / 2) / (pos.sum() * (~pos).sum())
    assert auc > 0.9 and (rows.predicted == (rows.score >= 0.5)).all() and rows.score.between(0, 1).all()


def test_a_score_depends_on_its_text_alone(text):
    rows = [(text(i, 40) + (" awful nasty" if i % 2 else ""), i % 2, "en") for i in range(60)]
    model = fit(rows, 0.5, FAST)
    texts = ["", "awful", text(3, 20), text(1, 30) + " nasty", "x"]
    whole = model.margins(*word_parts(*text_arrays(pa.array(texts, pa.large_string())), model.bits))
    for i, t in enumerate(texts):
        alone = model.margins(*word_parts(*text_arrays(pa.array([t], pa.large_string())), model.bits))
        assert np.isclose(alone[0], whole[i])


def test_odd_texts_no_labels_and_empty_tables(spark, make_docs, odd_texts):
    docs = make_docs(odd_texts, extra=True)
    labels = spark.createDataFrame([(0, 1), (1, 0), (None, 1), (2, None)], "doc_id long, toxic int")
    for own in (labels, labels.where("false")):
        rows = score_toxicity(docs, fit_toxicity(docs, own, FAST), F.lit(False)).collect()
        assert len(rows) == len(odd_texts) and all(0 <= r["score"] <= 1 for r in rows)
    assert score_toxicity(docs.where("false"), fit_toxicity(docs, labels, FAST), F.lit(True)).count() == 0


def test_threshold_reaches_the_precision():
    p, y = np.array([0.9, 0.8, 0.4, 0.3, 0.2]), np.array([1, 1, 1, 0, 0])
    assert calibrated_threshold(p, y, np.ones(5), 0.9) == 0.4
    assert calibrated_threshold(p, np.zeros(5), np.ones(5), 0.9) == 0.5


def test_scores_equal_a_plain_forward_pass(make_docs, text, odd_texts):
    """The network word by word and filter by filter: embeddings, every window of every width, max pooling, one neuron."""
    rows = [(text(i, 40) + (" awful nasty" if i % 2 else ""), i % 2, "en") for i in range(60)]
    model = fit(rows, 0.5, FAST)
    texts = [t for t in odd_texts if t is None or len(t) < 5000] + [text(2, 25) + " awful", "nasty"]
    docs = make_docs(texts)
    got = {r["doc_id"]: r["score"] for r in score_toxicity(docs, model, F.lit(False)).collect()}
    for i, t in enumerate(texts):
        parts, _ = word_parts(*text_arrays(pa.array([t], pa.large_string())), model.bits)
        e = [sum((model.embedding[model.row_of[p]].astype(float) for p in word), np.zeros(model.embedding.shape[1])) for word in parts]
        z = model.bias
        pooled = []
        for kernel, offset in zip(model.kernels, model.offsets, strict=True):
            for f in range(kernel.shape[2]):
                # a text is followed by places without a word, whose own responses are 0
                places = [sum(e[a + j] @ kernel[j, :, f] for j in range(len(kernel)) if a + j < len(e)) for a in range(len(e))] + [0.0]
                pooled.append(max(0.0, max(places) + offset[f]))
        z += float(np.dot(pooled, model.weights))
        p = 1 / (1 + np.exp(-np.clip(model.slope * z + model.shift, -30, 30)))
        want = p
        assert np.isclose(got[i], want, atol=1e-4), (i, got[i], want)


def test_every_labelled_row_and_character_is_learned_from(spark):
    """Counts, model and thresholds came from 1500 rows a label and 20000 characters of a text."""
    from vecspark.llm import toxicity as t

    params = ToxicParams(steps=30, epochs=2, shard_rows=1000, rounds=2)
    filler = "plain words and more of them " * 800
    rows = [(i, ("word " * (i % 5)) + ("awful nasty" if i % 2 else "fine day") + (filler + " zzrare" if i in (3, 5, 9, 11, 15) else ""), i % 2, "en" if i % 3 else None) for i in range(4000)]
    docs = spark.createDataFrame([(r[0], r[1], r[3]) for r in rows], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, toxic int")
    marks = labels.select("doc_id", F.col("toxic").alias("y"))
    hashed = t.hashed_rows(docs, marks, 4, params)
    held = {r[0] for r in docs.where("pmod(xxhash64(doc_id), 5) = 4").select("doc_id").collect()}
    assert hashed.count() == 4000 and hashed.where("held").count() == len(held)
    want = np.zeros((2, 1 << params.hash_bits))
    for i, text, y, _ in rows:
        if i not in held:
            parts = word_parts(*text_arrays(pa.array([text], pa.large_string())), params.hash_bits)[0]
            want[y][np.unique(parts[parts >= 0])] += 1
    assert (t.texts_by_row(hashed, params) == want).all()
    model = fit_toxicity(docs, labels, params)
    z, y, langs = t.held_margins(hashed, model)
    assert len(z) == len(held) and set(langs) == {"en", ""} and set(model.thresholds) == {"en", ""}
    again = t.calibrate(t.replace(model, thresholds={}), z, y, langs, 0.5, params)
    assert (again.slope, again.shift, again.thresholds) == (model.slope, model.shift, model.thresholds)
    assert ((model.probability(z) >= 0.5) == (y == 1)).all()
    rare = word_parts(*text_arrays(pa.array(["zzrare"], pa.large_string())), params.hash_bits)[0][0, 0]
    assert model.row_of[rare] < len(model.embedding) - 1
    assert all((r["score"] >= 0.5) == r["doc_id"] % 2 for r in score_toxicity(docs, model, F.lit(False)).collect())
    other = fit_toxicity(docs.repartition(7), labels.repartition(3), params)
    assert np.allclose(other.embedding, model.embedding, atol=1e-4) and np.isclose(other.shift, model.shift, atol=1e-3)


def test_training_and_scoring_kernels_equal_plain_ones(text, odd_texts, monkeypatch):
    """Prefixes, padded columns, convolution in slices, gradients of touched rows and margins of many texts at once."""
    from vecspark.llm import toxicity as t
    from vecspark.llm.textkit import Segments, lower_ascii, mix, prefix_hash, segment_hash, words

    texts = [x for x in odd_texts if x is None or len(x) < 5000] + [text(i, 30 + i) for i in range(20)]
    data, offsets = text_arrays(pa.array(texts, pa.large_string()))
    parts, per = word_parts(data, offsets, 15)
    low = lower_ascii(data)
    seg = words(low, offsets, t.WORD_BYTE)
    assert (parts[:, 0] == (segment_hash(low, seg) >> np.uint64(49)).astype(int)).all()
    for j, n in enumerate(t.PREFIXES, 1):
        head = segment_hash(low, Segments(seg.start, np.minimum(seg.end, seg.start + n), seg.doc, seg.n_docs))
        longer = seg.end - seg.start > n
        assert longer.any() and (prefix_hash(low, seg.start[longer], n) == head[longer]).all()
        assert (parts[:, j] == np.where(longer, (mix(head + np.uint64(n)) >> np.uint64(49)).astype(int), -1)).all()

    rng = np.random.default_rng(1)
    rows, slopes, zero = rng.integers(0, 9, (4, 50)), rng.normal(size=(50, 3)), 8
    want = np.zeros((9, 3))
    np.add.at(want, rows, slopes[None])
    touched, got = t.summed(rows, slopes, zero)
    assert np.allclose(got, want[touched], atol=1e-5) and set(touched) == set(rows[rows < zero])

    known = np.array([len(x or "") % 2 for x in texts])
    hashed = [parts[b - n : b] for n, b in zip(per, np.cumsum(per), strict=True)]
    counts = np.zeros((2, 1 << 15))
    for h, label in zip(hashed, known, strict=True):
        counts[label][np.unique(h[h >= 0])] += 1
    params = ToxicParams(epochs=2, batch=8, min_texts=1)
    model = t.start_model(counts, np.bincount(known, minlength=2), params)
    whole = model.margins(parts, per)
    monkeypatch.setattr(t, "WORDS_AT_ONCE", 7)
    monkeypatch.setattr(t, "NUMBERS_AT_ONCE", 100)
    assert np.allclose(model.margins(parts, per), whole, atol=1e-5)
    assert np.allclose([model.margins(h, np.array([len(h)]))[0] for h in hashed], whole, atol=1e-5)

    trained = t.train(model, hashed, known, np.array([1.0, 2.0]), 2, params)
    plain = plainly_trained(model, hashed, known, np.array([1.0, 2.0]), 2, params)
    for a, b in zip(t.pieces(trained), plain, strict=True):
        assert np.allclose(a, b, atol=1e-3), np.abs(a - b).max()
    assert np.abs(t.pieces(trained)[0] - t.pieces(model)[0]).max() > 0.01


def plainly_trained(model, hashed, y, label_weight, epochs, params):
    """Text by text and filter by filter in double precision, with whole gradients and moments of the embedding."""
    from vecspark.llm.toxicity import PAD, pieces

    values = [np.array(p, float) for p in pieces(model)]
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in values]
    rng, zero, step, n = np.random.default_rng([params.seed, 0]), len(values[0]) - 1, 0, params.filters
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(len(y)), max(1, len(y) // params.batch)):
            step += 1
            grads = [np.zeros_like(p) for p in values]
            embedding, kernels, offsets, weights, bias = values[0], values[1:4], values[4:7], values[7], values[8][0]
            for i in batch:
                ids = np.concatenate([model.row_of[hashed[i]], np.full((2 * PAD, 4), zero)])
                e = embedding[ids].sum(1)
                places, x = [], []
                for k, b in zip(kernels, offsets, strict=True):
                    r = np.array([[(e[a : a + len(k)] * k[:, :, f]).sum() for f in range(n)] for a in range(len(hashed[i]))] + [[0.0] * n])
                    places.append(r.argmax(0))
                    x.append(r.max(0) + b)
                flat = np.concatenate(x)
                active = np.maximum(flat, 0)
                g = label_weight[y[i]] * (1 / (1 + np.exp(-(active @ weights + bias))) - y[i]) / len(batch)
                grads[7] += active * g
                grads[8] += g
                gx = np.where(flat > 0, g * weights, 0)
                for w, k in enumerate(kernels):
                    for f in range(n):
                        own = gx[w * n + f]
                        grads[4 + w][f] += own
                        for j in range(len(k)):
                            at = places[w][f] + j
                            grads[1 + w][j, :, f] += own * e[at]
                            np.add.at(grads[0], ids[at], own * k[j, :, f])
            for q in (1, 2, 3, 7):
                grads[q] += 1e-4 * values[q]
            grads[0][zero] = 0
            for p, g, (m, v) in zip(values, grads, moments, strict=True):
                m[...] = 0.9 * m + 0.1 * g
                v[...] = 0.99 * v + 0.01 * g * g
                p -= params.rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-6)
    return values
