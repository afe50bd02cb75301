import re
from collections import Counter

import numpy as np
import pytest

from vecspark.llm import neardup
from vecspark.llm.components import components
from vecspark.llm.neardup import NearDupParams, bag_minhash, deduplicate, near_duplicates

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def bag(text, n=5):
    w = WORD.findall(text or "")
    m = min(n, len(w))
    return Counter(tuple(w[i : i + m]) for i in range(len(w) - m + 1)) if w else Counter()


def brute(ids, texts, limit=0.8):
    bags = [bag(t) for t in texts]
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            if bags[i] and bags[j] and sum((bags[i] & bags[j]).values()) >= limit * sum((bags[i] | bags[j]).values()):
                a, b = sorted((find(ids[i]), find(ids[j])))
                root[b] = a
    return {i: find(i) for i in ids}


def near_copies(text, n, edits):
    rng = np.random.default_rng(n)
    out = []
    for _ in range(n):
        w = text.split(" ")
        for k in rng.integers(0, len(w), edits):
            w[k] = f"edit{rng.integers(1e6)}"
        out.append(" ".join(w))
    return out


def test_classes_equal_brute_force(make_docs, odd_texts, text):
    base = text(7, 150)
    texts = [*odd_texts, base, base + " end", *near_copies(base, 30, 2), *near_copies(base, 30, 5), *[text(i, 60) for i in range(20, 30)], "one two", "one two", "one two three"]
    ids = list(range(len(texts)))
    got = {r["doc_id"]: r["class_id"] for r in near_duplicates(make_docs(texts, extra=True)).collect()}
    assert got == brute(ids, texts)


def test_small_blocks_change_nothing(make_docs, text):
    texts = near_copies(text(11, 120), 60, 4)
    want = brute(list(range(60)), texts)
    docs = make_docs(texts)
    for block in (5, 1000):
        assert {r["doc_id"]: r["class_id"] for r in near_duplicates(docs, NearDupParams(block=block)).collect()} == want


def test_signatures_estimate_weighted_jaccard():
    rng = np.random.default_rng(0)
    key = rng.integers(0, 2**63, 60).astype(np.uint64)
    a, b = rng.integers(1, 40, 60), rng.integers(1, 40, 60)
    m = 4000
    sig = bag_minhash(np.repeat([0, 1], 60), np.concatenate([key, key]), np.concatenate([a, b]), 2, m)
    exact = np.minimum(a, b).sum() / np.maximum(a, b).sum()
    assert abs((sig[0] == sig[1]).mean() - exact) < 4 * np.sqrt(exact * (1 - exact) / m)
    assert np.isinf(bag_minhash(np.empty(0, int), key[:0], a[:0], 1, 4)).all()


def test_stage_keeps_one_row_of_each_class(make_docs, text):
    a, b = text(1, 80), text(2, 80)
    docs = make_docs([a, a, b, None, "", a], [5, 3, 9, 10, None, 5])
    out = sorted((r["doc_id"] is None, r["doc_id"], r["text"]) for r in deduplicate(docs).collect())
    assert [(i, t) for _, i, t in out] == [(3, a), (9, b), (10, None), (None, "")]
    twice = make_docs([a, a], [4, 4])
    assert deduplicate(twice).count() == 1
    assert deduplicate(docs).columns == docs.columns and deduplicate(docs.where("false")).count() == 0


def test_rows_that_repeat_an_id_are_told_apart_by_their_texts(make_docs, text):
    a, b, c = text(1, 60), text(2, 60), text(3, 60)
    docs = make_docs([a, b, c, b, None, "", "", a + " end"], [1, 1, 2, 1, 4, 4, 4, 0])
    want = sorted([(0, a + " end"), (1, b), (2, c), (4, "")])
    for parts in (1, 5):
        assert sorted((r["doc_id"], r["text"] or "") for r in deduplicate(docs.repartition(parts)).collect()) == want
    only = deduplicate(make_docs([a, b, c], [1, 1, 2]))
    assert sorted((r["doc_id"], r["text"]) for r in only.collect()) == sorted([(1, a), (1, b), (2, c)])


def test_near_copies_that_are_similar_enough_are_found(make_docs, text):
    """Planted copies with one to nine edited words in 200; what is at 0.8 or more from the original by brute force is found."""
    rng = np.random.default_rng(3)
    texts, original = [], {}
    for g in range(25):
        base = text(100 + g, 200)
        first = len(texts)
        texts.append(base)
        for k in range(1, 10):
            w = base.split(" ")
            for at in rng.choice(200, k, replace=False):
                w[at] = f"edit{rng.integers(1e9)}"
            original[len(texts)] = first
            texts.append(" ".join(w))
    got = {r["doc_id"]: r["class_id"] for r in near_duplicates(make_docs(texts)).collect()}
    bags = [bag(t) for t in texts]
    close = [(i, j) for i, j in original.items() if sum((bags[i] & bags[j]).values()) >= 0.8 * sum((bags[i] | bags[j]).values())]
    assert len(close) > 80 and np.mean([got[i] == got[j] for i, j in close]) >= 0.99
    assert got == brute([*range(len(texts))], texts)


@pytest.mark.parametrize("links", [[], [(1, 2)], [(i, i + 1) for i in range(40)], [(0, i) for i in range(1, 50)], [(1, 2), (3, 4), (2, 3), (8, 9)]])
def test_components(spark, links):
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    got = {r["id"]: r["label"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root} and neardup.components is components
