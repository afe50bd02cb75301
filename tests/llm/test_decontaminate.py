import numpy as np
import pyarrow as pa
import pytest

from vecspark.llm.decontaminate import ItemIndex, LeakParams, drop_leaks, find_leaks, word_hashes
from vecspark.llm.textkit import text_arrays


@pytest.fixture
def items(spark, text):
    rows = [(i, text(500 + i, 30)) for i in range(8)] + [(8, None), (9, ""), (10, "two words"), (11, text(500, 30)), (None, text(600, 30))]
    return spark.createDataFrame(rows, "item_id long, text string")


def edited(t, every):
    w = t.split(" ")
    return " ".join("changed" if i % every == every - 1 else x for i, x in enumerate(w))


def test_copies_edits_and_clean_texts(make_docs, items, odd_texts, text):
    one, two = text(501, 30), text(502, 30)
    texts = [*odd_texts, text(3, 60) + " " + one + " " + text(4, 60), text(5, 40) + " " + edited(two, 5) + " " + text(6, 40), one.upper(), text(500, 30), text(7, 300), two.replace(" ", ", ")]
    k = len(odd_texts)
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in find_leaks(make_docs(texts, extra=True), items).collect()}
    assert set(got) == {(k, 1), (k + 1, 2), (k + 2, 1), (k + 3, 0), (k + 3, 11), (k + 5, 2)}
    assert got[k, 1] == 1.0 and 0.5 <= got[k + 1, 2] < 1


def test_slices_of_items_give_the_same(make_docs, items, text):
    docs = make_docs([text(3, 60) + " " + text(500 + i, 30) for i in range(8)])
    want = sorted(tuple(r) for r in find_leaks(docs, items).collect())
    assert sorted(tuple(r) for r in find_leaks(docs, items, LeakParams(slice_grams=40)).collect()) == want and len(want) >= 8


def test_a_leaked_everywhere_item_keeps_its_seeds(make_docs, items, text):
    docs = make_docs([text(1000 + i, 20) + " " + text(501, 30) for i in range(60)])
    assert find_leaks(docs, items, LeakParams(rare_texts=1)).where("item_id = 1").count() == 60


def test_alignment_equals_the_plain_recurrence():
    rng = np.random.default_rng(0)
    p = LeakParams()
    for _ in range(20):
        item = rng.integers(0, 6, 12).astype(np.uint64)
        window = rng.integers(0, 6, 40).astype(np.uint64)
        index = ItemIndex(np.array([0]), item, np.array([0, 12]), p)
        score, _ = index.align(window, np.array([0]), np.array([40]), np.array([0]))
        h = np.zeros((13, 41), int)
        for i in range(1, 13):
            for j in range(1, 41):
                h[i, j] = max(0, h[i - 1, j - 1] + (p.match if item[i - 1] == window[j - 1] else p.mismatch), h[i - 1, j] + p.gap, h[i, j - 1] + p.gap)
        assert score[0] == h.max()


def test_dropping_and_empty_tables(make_docs, items, text):
    docs = make_docs([text(3, 60), text(501, 30), None])
    assert sorted(r["doc_id"] for r in drop_leaks(docs, items).collect()) == [0, 2]
    none = items.where("false")
    assert drop_leaks(docs, none).count() == 3 and find_leaks(docs, none).count() == 0
    assert find_leaks(docs.where("false"), items).count() == 0 and drop_leaks(docs.where("false"), items).count() == 0
    h, seg = word_hashes(*text_arrays(pa.array(["A-b C", "a b c"], pa.large_string())))
    assert (h[:3] == h[3:]).all() and len(seg) == 6


def test_items_without_an_id_are_not_the_item_minus_one(spark, make_docs, text):
    items = spark.createDataFrame([(None, text(600, 30)), (-1, text(601, 30))], "item_id long, text string")
    got = sorted((r["doc_id"], r["item_id"]) for r in find_leaks(make_docs([text(600, 30), text(601, 30)]), items).collect() if r["item_id"] is not None)
    assert got == [(1, -1)]
    assert find_leaks(make_docs([text(600, 30)]), items).where("item_id is null").count() == 1


def test_recall_against_exhaustive_alignment(spark, make_docs):
    """Every text is aligned with every item; of the pairs at the threshold or above nine in ten or more are found."""
    rng = np.random.default_rng(8)
    p = LeakParams()
    vocabulary = [f"w{i}" for i in range(400)]
    item_words = [list(rng.choice(vocabulary, 25)) for _ in range(12)]
    texts = []
    for i in range(48):
        own = [w if rng.random() > (i % 6) * 0.1 else f"x{rng.integers(1e6)}" for w in item_words[i % 12]]
        texts.append(" ".join([*rng.choice(vocabulary, 30), *own, *rng.choice(vocabulary, 30)]))
    items = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(item_words)], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in find_leaks(make_docs(texts), items).collect()}
    wanted = set()
    for d, t in enumerate(texts):
        words = t.split(" ")
        for j, item in enumerate(item_words):
            h = np.zeros((len(item) + 1, len(words) + 1), int)
            for a in range(1, len(item) + 1):
                for b in range(1, len(words) + 1):
                    h[a, b] = max(0, h[a - 1, b - 1] + (p.match if item[a - 1] == words[b - 1] else p.mismatch), h[a - 1, b] + p.gap, h[a, b - 1] + p.gap)
            if h.max() >= p.threshold * p.match * len(item):
                wanted.add((d, j))
    assert got <= wanted and len(wanted) > 25 and len(got) >= 0.9 * len(wanted)
