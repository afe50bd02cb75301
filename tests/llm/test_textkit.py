"""Hashes that no pattern of bytes collides under, and what rests on them."""

import numpy as np
import pyarrow as pa
import pytest

from vecspark.llm.lm import score_corpus
from vecspark.llm.neardup import deduplicate, near_duplicates
from vecspark.llm.quality import op7_quality_rules
from vecspark.llm.textkit import segment_hash, text_arrays, words


def twins() -> tuple[str, str]:
    """Unlike words of 1024 letters that are equal under every polynomial hash modulo a power of two."""
    a = "a"
    for _ in range(10):
        a += a.translate(str.maketrans("ab", "ba"))
    return a, a.translate(str.maketrans("ab", "ba"))


def hashes(text: str) -> np.ndarray:
    data, offsets = text_arrays(pa.array([text], pa.large_string()))
    return segment_hash(data, words(data, offsets))


def test_segment_hash_tells_words_apart_and_knows_them_again():
    a, b = twins()
    x, y, z = hashes(f"{a} {b} {a}")
    assert x == z != y
    many = [f"w{i}" for i in range(5000)] + ["x" * i for i in range(1, 60)] + ["a\0", "a", "a\0\0"]
    assert len(np.unique(hashes(" ".join(many)))) == len(many)
    assert (hashes("one two three") == hashes("zero  one two three")[1:]).all()


def test_near_duplicates_keep_texts_of_unlike_words_apart(make_docs):
    a, b = twins()
    docs = make_docs([" ".join([a] * 8), " ".join([b] * 8)])
    assert sorted(r["class_id"] for r in near_duplicates(docs).collect()) == [0, 1]
    assert deduplicate(docs).count() == 2


def test_quality_lines_and_scores_tell_them_apart(spark, make_docs, tmp_path):
    a, b = twins()
    make_docs([f"{a}\n{b}\n{a}"]).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    assert op7_quality_rules(spark, str(tmp_path)).first()["n_dup_lines"] == 1
    from pyspark.sql import functions as F

    rows = score_corpus(make_docs([a, b]), F.col("doc_id") == 1).collect()
    assert {r["doc_id"]: r["n_known"] for r in rows} == {0: 2, 1: 1}


@pytest.mark.parametrize("n", [70_000, 200_000])
def test_one_very_long_word(make_docs, n):
    from vecspark.llm.neardup import near_duplicates as classes
    from vecspark.llm.secrets import SecretParams, fit_secrets, scan_secrets

    word = "Ab1" * (n // 3)
    docs = make_docs([word, word, "token = " + "0123456789abcdef" * (n // 16), word + " end"])
    assert len({r["class_id"] for r in classes(docs).where("doc_id < 2").collect()}) == 1
    rows = {r["doc_id"]: r for r in scan_secrets(docs, fit_secrets(docs, SecretParams(epochs=1))).collect()}
    assert rows[2]["n_assign"] == 1 and rows[2]["n_hex"] == 1 and rows[0]["n_assign"] == 0


def test_segment_hashes_add_up_eight_bytes_at_a_time():
    """Lane by lane, with the first eight bytes of all segments taken at once; numbers mixed in slices."""
    from vecspark.llm.textkit import LANE_SEED, MIX_AT_ONCE, U64, Segments, mix, segment_hash

    x = np.arange(2 * MIX_AT_ONCE + 3, dtype=np.uint64)
    assert (mix(x) == np.concatenate([mix(x[i : i + 1000]) for i in range(0, len(x), 1000)])).all() and x[1] == 1
    assert mix(np.zeros(0, np.uint64)).shape == (0,) and mix(x[:6].reshape(2, 3).T).tolist() == mix(x[:6]).reshape(2, 3).T.tolist()
    data = np.frombuffer(bytes(range(1, 200)), np.uint8)
    start = np.array([0, 3, 3, 50, 100, 182, 7])
    size = np.array([1, 8, 9, 0, 99, 17, 16])
    got = segment_hash(data, Segments(start, start + size, start, 1), 3)
    for s, n, h in zip(start, size, got, strict=True):
        total = np.full(1, U64(n) if n else LANE_SEED ^ U64(3))
        for turn in range((n + 7) // 8):
            lane = np.frombuffer(data[s + 8 * turn : min(s + n, s + 8 * turn + 8)].tobytes().ljust(8, b"\0"), "<u8")
            total += mix(mix(lane ^ (LANE_SEED ^ U64(3))) + np.full(1, turn, np.uint64) * U64(0xA24BAED4963EE407))
        assert mix(total)[0] == h
