"""Quality rules: hashed word and character n-gram logistic regression over whole texts, beside fixed base rules.

The regression is fitted on a bounded sample of labelled rows (`QualityParams.sample_rows`), its probabilities
are calibrated on rows held out of the fit, and texts are scored in Arrow batches against a fixed threshold.

Defined results: a null or empty text has no words, fails the base rules and is not kept; with no labelled
rows, or rows of one class, every text has the prior as its probability.  Repeated rows are scored each.
Columns other than doc_id and text are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import labelled_sample, table
from .textkit import blocks, first_seen, gram_hash, lines, mix, releasing, repeated, segment_hash, text_arrays, words

#: The symbols that the base rules count.
SYMBOLS = "#*$%&|<>"

WORD_BITS, PAIR_BITS, CHAR_BITS, CHAR_N = 16, 16, 16, 4
DIMENSIONS = (1 << WORD_BITS) + (1 << PAIR_BITS) + (1 << CHAR_BITS)
_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in SYMBOLS]] = True


@dataclass(frozen=True)
class QualityParams:
    sample_rows: int = 1600  #: bound of the labelled sample
    sample_chars: int = 20_000  #: longest text of that sample
    min_words: int = 50
    repeat_percent: int = 50
    threshold: float = 0.3  #: kept at this calibrated probability of good quality or above
    epochs: int = 120
    l2: float = 1e-5


@dataclass
class QualityModel:
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def probability(self, margin: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -30, 30)))


def features(data: np.ndarray, offsets: np.ndarray):
    """(doc, feature, value) of hashed word, word-pair and character 4-gram shares; and the words with their hashes."""
    seg = words(data, offsets)
    h = segment_hash(data, seg)
    families = [(seg.doc, (h >> np.uint64(64 - WORD_BITS)).astype(np.int64))]
    pair = gram_hash(h, 2)
    inside = seg.doc[1:] == seg.doc[:-1]
    families.append((seg.doc[:-1][inside], (pair[inside] >> np.uint64(64 - PAIR_BITS)).astype(np.int64) + (1 << WORD_BITS)))
    if len(data) >= CHAR_N:
        m = len(data) - CHAR_N + 1
        code = np.zeros(m, np.uint32)
        for i in range(CHAR_N):
            code = (code << np.uint32(8)) | data[i : i + m].astype(np.uint32)
        code *= np.uint32(0x9E3779B1)
        doc = np.searchsorted(offsets, np.arange(m), "right") - 1 if len(offsets) < 3 else np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))[:m]
        inside = np.ones(m, bool)
        for end in offsets[1:-1]:
            inside[max(0, end - CHAR_N + 1) : end] = False
        families.append((doc[inside], (code[inside] >> np.uint32(32 - CHAR_BITS)).astype(np.int64) + (1 << WORD_BITS) + (1 << PAIR_BITS)))
    return families, seg, h


def margins(families, weights: np.ndarray, bias: float, n_docs: int) -> np.ndarray:
    out = np.full(n_docs, bias)
    for doc, feature in families:
        total = np.bincount(doc, weights[feature], n_docs)
        out += total / np.maximum(1, np.bincount(doc, minlength=n_docs))
    return out


def fit(rows: list, params: QualityParams) -> QualityModel:
    """rows: (doc_id, text, y).  Adam on the mean log loss; Platt calibration on every fifth row."""
    y = np.array([r[2] for r in rows], float)
    if len(y) < 10 or y.min() == y.max():
        prior = (y.sum() + 1) / (len(y) + 1) if len(y) else 1.0
        prior = min(max(prior, 1e-3), 1 - 1e-3)
        return QualityModel(np.zeros(DIMENSIONS), 0.0, 1.0, float(np.log(prior / (1 - prior))))
    doc_parts, feature_parts, value_parts = [], [], []
    for at in range(0, len(rows), 100):
        data, offsets = text_arrays(pa.array([r[1] for r in rows[at : at + 100]], pa.large_string()))
        n = len(offsets) - 1
        for doc, feature in features(data, offsets)[0]:
            key, count = np.unique(doc * DIMENSIONS + feature, return_counts=True)
            d = key // DIMENSIONS
            doc_parts.append((d + at).astype(np.int32))
            feature_parts.append((key % DIMENSIONS).astype(np.int32))
            value_parts.append((count / np.maximum(1, np.bincount(doc, minlength=n))[d]).astype(np.float32))
    doc, feature, value = map(np.concatenate, (doc_parts, feature_parts, value_parts))
    held = np.arange(len(y)) % 5 == 4
    fit_on = ~held
    w, b = np.zeros(DIMENSIONS), float(np.log((y[fit_on].mean() + 1e-6) / (1 - y[fit_on].mean() + 1e-6)))
    m, v, mb, vb = np.zeros(DIMENSIONS), np.zeros(DIMENSIONS), 0.0, 0.0
    train = fit_on[doc]
    td, tf, tv = doc[train], feature[train], value[train]
    balance = np.where(y == 1, 0.5 / max(1, (y[fit_on] == 1).sum()), 0.5 / max(1, (y[fit_on] == 0).sum())) * fit_on
    for step in range(1, params.epochs + 1):
        z = np.bincount(td, w[tf] * tv, len(y)) + b
        g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * balance
        gw = np.bincount(tf, g[td] * tv, DIMENSIONS) + params.l2 * w
        gb = g.sum()
        m, v = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw * gw
        mb, vb = 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        c1, c2 = 1 - 0.9**step, 1 - 0.99**step
        w -= 0.3 * (m / c1) / (np.sqrt(v / c2) + 1e-5)
        b -= 0.05 * (mb / c1) / (np.sqrt(vb / c2) + 1e-8)
    z = np.bincount(doc, w[feature] * value, len(y)) + b
    slope, shift = platt(z[held], y[held])
    return QualityModel(w, b, slope, shift)


def platt(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a logistic calibration, by damped Newton steps with smoothed targets."""
    pos, neg = y.sum(), len(y) - y.sum()
    if not pos or not neg:
        return 1.0, 0.0
    t = np.where(y == 1, (pos + 1) / (pos + 2), 1 / (neg + 2))
    scale = max(1e-9, float(np.std(z)))
    x = np.stack([z / scale, np.ones_like(z)], 1)
    theta = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ theta, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        theta += np.clip(np.linalg.solve(h, x.T @ (t - p) - 1e-3 * theta), -2, 2)
    return float(max(theta[0], 1e-3) / scale), float(theta[1])


def base_counts(data: np.ndarray, offsets: np.ndarray, seg, h) -> dict[str, np.ndarray]:
    n = len(offsets) - 1

    def total(mask):
        c = np.concatenate([[0], np.cumsum(mask)])
        return c[offsets[1:]] - c[offsets[:-1]]

    space = (data == 0x20) | ((data >= 0x09) & (data <= 0x0D))
    out = {"n_words": seg.per_doc(), "word_chars": total(~space & ((data & 0xC0) != 0x80)), "n_symbols": total(_SYMBOL[data])}
    ln = lines(data, offsets)
    held = np.concatenate([[0], np.cumsum(~space)])
    with_word = held[ln.end] > held[ln.start]
    key = mix(segment_hash(data, ln) + ln.doc.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))[with_word]
    out["n_dup_lines"] = np.bincount(ln.doc[with_word], ~first_seen(key), n).astype(np.int64)
    three = gram_hash(h, 3)
    inside = np.flatnonzero(seg.doc[2:] == seg.doc[:-2])
    again = inside[repeated(mix(three[inside] + seg.doc[inside].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)))]
    covered = np.zeros(len(seg), bool)
    for i in range(3):
        covered[again + i] = True
    out["n_repeat_words"] = np.bincount(seg.doc[covered], minlength=n)
    return out


def assess_quality(documents: DataFrame, model: QualityModel, params: QualityParams = QualityParams()) -> DataFrame:
    """doc_id, the base counts, base_failed, kept and the calibrated probability; one row for each row."""
    shipped = documents.sparkSession.sparkContext.broadcast(model)

    def score(batches):
        m = shipped.value
        for rows, data, offsets in blocks(batches):
            families, seg, h = features(data, offsets)
            c = base_counts(data, offsets, seg, h)
            p = m.probability(margins(families, m.weights, m.bias, rows.num_rows))
            failed = (c["n_words"] < params.min_words) | (100 * c["n_repeat_words"] > params.repeat_percent * c["n_words"])
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), *(pa.array(c[k].astype(np.int64)) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), pa.array(failed), pa.array(~failed & (p >= params.threshold)), pa.array(p)],
                names=["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality"],
            )

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, quality double"
    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(score, schema)


def fit_quality(documents: DataFrame, labels: DataFrame, params: QualityParams = QualityParams()) -> QualityModel:
    return releasing(fit)(labelled_sample(documents, labels, "quality", params.sample_rows, params.sample_chars), params)


def filter_quality(documents: DataFrame, model: QualityModel, params: QualityParams = QualityParams()) -> DataFrame:
    """The rows of `documents` that are kept, with their own columns: the verdict is worked out in the same pass."""
    shipped = documents.sparkSession.sparkContext.broadcast(model)
    at = documents.columns.index("text")

    def passing(batches):
        m = shipped.value
        for rows, data, offsets in blocks(batches, rows_text):
            families, seg, h = features(data, offsets)
            c = base_counts(data, offsets, seg, h)
            p = m.probability(margins(families, m.weights, m.bias, rows.num_rows))
            failed = (c["n_words"] < params.min_words) | (100 * c["n_repeat_words"] > params.repeat_percent * c["n_words"])
            yield rows.filter(pa.array(~failed & (p >= params.threshold)))

    rows_text = documents.columns[at]
    return documents.mapInArrow(passing, documents.schema)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return assess_quality(documents, fit_quality(documents, table(spark, sf_dir, "labels")))
