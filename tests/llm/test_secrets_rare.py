import numpy as np

from vecspark.llm.secrets import SecretParams, fit_secrets, scan_secrets


def test_field_learns_where_secrets_are_rare(make_docs, text):
    """1 % of the texts have a base match, and the sample's bound is 300 of 10 000 texts."""
    rng = np.random.default_rng(3)
    key = lambda n: "".join(rng.choice(list("abcdef0123456789"), n))
    docs = make_docs([text(i, 40) + (f" password={key(20)} " if i % 100 == 7 else " ") + text(i + 5000, 20) for i in range(10_000)])
    model = fit_secrets(docs, SecretParams(sample_rows=300, epochs=6))
    hidden = make_docs([text(7000 + i, 30) + f" pwd={key(20)} " + text(8000 + i, 20) for i in range(20)])
    found = scan_secrets(hidden, model).where("n_crf = 1").count()
    assert found >= 15, found
    assert scan_secrets(make_docs([text(9000 + i, 200) for i in range(50)]), model).where("n_crf > 0").count() == 0
