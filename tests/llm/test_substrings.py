import hashlib

import numpy as np
import pytest

from vecspark.llm.substrings import SubstringParams, deduplicate_substrings, gram_hashes, merge_order, prefix_hashes, truly_sorted


def brute(rows, length):
    seen, out = set(), []
    for i, t in sorted(rows, key=lambda r: (-1 if r[0] is None else r[0], (r[1] or "").encode())):
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - length + 1):
            w = b[k : k + length]
            if w in seen:
                gone[k : k + length] = True
            seen.add(w)
        kept = np.frombuffer(b, np.uint8)[~gone].tobytes() if b else b""
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((-1 if i is None else i, len(b), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def run(docs, p):
    rows = deduplicate_substrings(docs, p).collect()
    assert all(hashlib.sha256(bytes(r["kept"])).hexdigest() == r["kept_sha256"] for r in rows)
    return sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in rows)


@pytest.mark.parametrize("p", [SubstringParams(), SubstringParams(block_bytes=4000, range_bytes=3000), SubstringParams(block_bytes=4000, range_bytes=3000, hot=2), SubstringParams(hot=1), SubstringParams(length=40, gram=10, block_bytes=9000)])
def test_equals_brute_force(make_docs, text, p):
    a, b = text(1, 60), text(2, 80)
    line = "Copyright holders: permission is hereby granted, free of charge, to any person who reads this very line of text; no more."
    texts = [None, "", "short", a, a, a[:200] + b[50:300], b + a[30:180] + b, "x" * 500, "ab" * 300, "x" * 120, "né " * 120, *[text(10 + i, 20) + line + text(40 + i, 20) for i in range(25)], b[:150] + "!" + b[151:], a[:99], a[:100], a + a]
    ids = list(range(len(texts)))
    assert run(make_docs(texts, ids, extra=True), p) == brute(list(zip(ids, texts)), p.length)


def test_repeated_and_null_ids(make_docs, text):
    a, b = text(1, 60), text(2, 60)
    rows = [(7, a), (7, a), (7, b), (3, b + a), (None, a), (9, None)]
    assert run(make_docs([t for _, t in rows], [i for i, _ in rows]), SubstringParams()) == brute(rows, 100)
    assert deduplicate_substrings(make_docs([])).count() == 0


def test_random_small_alphabet(make_docs):
    rng = np.random.default_rng(0)
    for seed in range(3):
        texts = ["".join(rng.choice(list("ab"), rng.integers(0, 120))) for _ in range(40)]
        p = SubstringParams(length=12, gram=4, block_bytes=500, range_bytes=400)
        assert run(make_docs(texts), p) == brute(list(enumerate(texts)), 12)


def test_suffix_sort_is_a_sort():
    rng = np.random.default_rng(1)
    text = rng.integers(97, 99, (200, 30)).astype(np.uint8)
    size = rng.integers(0, 31, 200)
    text[np.arange(30) >= size[:, None]] = 0
    group = np.sort(rng.integers(0, 9, 200))
    order, shared = merge_order(group, prefix_hashes(text, 0x9E3779B97F4A7C15), size, text)
    want = sorted(range(200), key=lambda i: (group[i], bytes(text[i, : size[i]]), i))
    assert order.tolist() == want and truly_sorted(text, size, order, shared)
    wrong = shared.copy()
    wrong[np.flatnonzero(shared > 0)[0]] += 1
    assert not truly_sorted(text, size, order, wrong)


def test_gram_hashes_tell_equal_grams():
    data = np.frombuffer(b"abcabcabdabc" * 3, np.uint8)
    for gram in (1, 3, 5, 8, 24):
        h = gram_hashes(data, gram)
        raw = [bytes(data[i : i + gram]) for i in range(len(data) - gram + 1)]
        assert len(h) == len(raw) and len(set(h.tolist())) == len(set(raw))
        assert len({(a, b) for a, b in zip(h.tolist(), raw)}) == len(set(raw))
