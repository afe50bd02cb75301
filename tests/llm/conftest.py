import pytest

LOREM = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def prose(seed: int, n: int) -> str:
    out, x = [], seed * 7919 + 1
    for i in range(n):
        x = (x * 1103515245 + 12345) % 2**31
        out.append(LOREM[(x >> 8) % len(LOREM)] + str((x >> 16) % 50))
        if i % 12 == 11:
            out[-1] += ".\n"
    return " ".join(out)


@pytest.fixture(scope="session")
def text():
    return prose


@pytest.fixture(scope="session")
def make_docs(spark):
    """Documents from texts; ids count up unless given; columns with names that operators use inside come on top."""

    def make(texts, ids=None, extra=False, lang="en", source="s"):
        ids = list(range(len(texts))) if ids is None else ids
        rows = [(i, t, lang, source, None if t is None else len(t)) for i, t in zip(ids, texts)]
        df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
        if extra:
            from pyspark.sql import functions as F

            for name in ("block", "part", "bands", "class_id", "rep", "kept", "score", "held_out", "copy_no", "label", "id", "a", "b", "n"):
                df = df.withColumn(name, F.lit("x"))
        return df

    return make


@pytest.fixture(scope="session")
def odd_texts(text):
    """Null, empty, white space, one word, non-Latin, repeated and very long texts."""
    long_ = text(99, 30_000)
    return [None, "", " \n\t ", "word", "né à Zürich — 東京 🎉", text(1, 80), text(1, 80), text(2, 200), long_, "1234 5678", "a\r\nb\r\n\r\nc"]
