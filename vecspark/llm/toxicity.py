"""Toxicity: a convolutional text classifier trained in numpy.

A word (letters and digits, A-Z in lower case) is the sum of hashed embeddings of itself and of its first 4, 5
and 6 bytes, so that inflected forms share what is learned; filters of widths 1, 2 and 3 slide over the whole
text, each keeps its largest response, and a logistic layer reads those.  Hash rows that fewer than
`min_texts` training texts hold are one zero row, which keeps rare words from being learned by heart.  The
probability is calibrated on rows held out of the training, to the share of toxic rows among all labels; a
threshold for each language is calibrated on the same rows and serves the `flagged` column alone.

Every labelled row teaches, by its whole text.  The rows' words are hashed once; the counts by hash row, and with them
the start, are those of all training rows.  Rows are dealt by a hash of the id to shards of about `shard_rows`; in
each round every shard goes on from the same model over all its rows, label-weighted so that both labels count alike, and
the shards' models are averaged by their rows (one shard is plain training).  Every fifth row by hash calibrates, and all
of those do: slope, shift and thresholds come from the margins of them all.  Rows that repeat an id teach each.
Defined results: a null text is the empty text and has the score of a text without words; with no usable labels
the score is the share of toxic labels, or 0 where there are none.  The score never sees lang, source or labels.
"""

from __future__ import annotations

import pickle
import uuid
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .decontaminate import WORD_BYTE
from .quality import platt
from .tables import discard, new_path, table
from .textkit import blocks, crc_mod, lower_ascii, mix, prefix_hash, releasing, segment_hash, text_arrays, words

WIDTHS = (1, 2, 3)
PAD = max(WIDTHS)
PREFIXES = (4, 5, 6)
WORDS_AT_ONCE = 1 << 14  #: of a convolution
NUMBERS_AT_ONCE = 1 << 16  #: of a step of Adam


def word_parts(data: np.ndarray, offsets: np.ndarray, bits: int):
    """(hash rows of each word and its prefixes, words by text); -1 where a word is no longer than the prefix."""
    low = lower_ascii(data)
    seg = words(low, offsets, WORD_BYTE)
    shift = np.uint64(64 - bits)
    rows = np.full((len(seg), 1 + len(PREFIXES)), -1, np.int64)
    rows[:, 0] = segment_hash(low, seg) >> shift
    size = seg.end - seg.start
    for j, n in enumerate(PREFIXES, 1):
        longer = np.flatnonzero(size > n)
        rows[longer, j] = mix(prefix_hash(low, seg.start[longer], n) + np.uint64(n)) >> shift
    return rows, seg.per_doc()


@dataclass(frozen=True)
class ToxicParams:
    shard_rows: int = 3000  #: about as many labelled rows train side by side with other shards
    rounds: int = 5  #: averages of the shards' models
    hash_bits: int = 15
    size: int = 12  #: of an embedding
    filters: int = 8  #: of each width
    min_texts: int = 3
    epochs: int = 10
    steps: int = 400  #: more epochs where a small sample would get fewer steps than this
    batch: int = 48
    rate: float = 0.01
    seed: int = 5
    precision: float = 0.9  #: aimed at by the thresholds by language


@dataclass
class ToxicModel:
    embedding: np.ndarray  #: the last row is the zero row
    row_of: np.ndarray
    kernels: list[np.ndarray]  #: by width: width x size x filters
    offsets: list[np.ndarray]
    weights: np.ndarray
    bias: float
    slope: float = 1.0
    shift: float = 0.0
    thresholds: dict[str, float] = field(default_factory=dict)

    @property
    def bits(self) -> int:
        return int(np.log2(len(self.row_of) - 1))

    def margins(self, parts: np.ndarray, per_doc: np.ndarray) -> np.ndarray:
        """parts: hash rows, as word_parts has them; the last entry of row_of serves -1."""
        ids, starts, pad = padded(self.row_of[parts], per_doc, len(self.embedding) - 1)
        e = embed(self.embedding, ids)
        pooled = np.concatenate([np.maximum.reduceat(convolve(e, pad, [k]), starts, axis=1).T + b for k, b in zip(self.kernels, self.offsets, strict=True)], 1)
        return np.maximum(pooled, 0) @ self.weights + self.bias

    def probability(self, z: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * z + self.shift, -30, 30)))


def padded(ids: np.ndarray, per_doc: np.ndarray, zero: int):
    """Each text's word rows, one column a word, with PAD zero columns behind them; where each text starts, and which columns pad."""
    starts = np.concatenate([[0], np.cumsum(per_doc + PAD)])
    out = np.full((ids.shape[1], starts[-1] + PAD), zero, np.int64)
    first = np.concatenate([[0], np.cumsum(per_doc)])[:-1]
    place = np.arange(len(ids)) + np.repeat(starts[:-1] - first, per_doc)
    for row, own in zip(out, ids.T, strict=True):
        row[place] = own
    return out, starts[:-1], padding(starts[1:])


def padding(ends: np.ndarray) -> np.ndarray:
    return (ends[:, None] - np.arange(PAD, 0, -1)).ravel()


def embed(embedding: np.ndarray, ids: np.ndarray) -> np.ndarray:
    e = embedding.take(ids[0], axis=0)
    for own in ids[1:]:
        e += embedding.take(own, axis=0)
    return e


def convolve(e: np.ndarray, pad: np.ndarray, kernels: list[np.ndarray]) -> np.ndarray:
    """Responses of all filters, a row each, at every place but the last PAD; those of padding are 0, whatever follows it."""
    n, n_filters = len(e) - PAD, kernels[0].shape[2]
    flat = np.concatenate([column.T for k in kernels for column in k])
    out = np.empty((n_filters * len(kernels), n), np.float32)
    for a in range(0, n, WORDS_AT_ONCE):
        b = min(n, a + WORDS_AT_ONCE)
        # one product for all filters and places in a window, whose rows are then added with a shift
        r = (flat @ e[a : b + PAD].T).reshape(-1, n_filters, b - a + PAD)
        at = 0
        for k, own in zip(kernels, out.reshape(len(kernels), n_filters, n), strict=True):
            own[:, a:b] = r[at, :, : b - a]
            for j in range(1, len(k)):
                own[:, a:b] += r[at + j, :, j : b - a + j]
            at += len(k)
    out[:, pad] = 0
    return out


def prior_model(prior: float, params: ToxicParams) -> ToxicModel:
    """Scores every text by the share of toxic labels."""
    p, size, n_filters = min(max(prior, 1e-4), 1 - 1e-4), params.size, params.filters
    return ToxicModel(np.zeros((1, size), np.float32), np.zeros((1 << params.hash_bits) + 1, np.int64), [np.zeros((w, size, n_filters), np.float32) for w in WIDTHS], [np.zeros(n_filters, np.float32) for _ in WIDTHS], np.zeros(n_filters * len(WIDTHS)), 0.0, 1.0, float(np.log(p / (1 - p))))


def start_model(texts_with: np.ndarray, n: np.ndarray, params: ToxicParams) -> ToxicModel:
    """texts_with: by label and hash row the training texts that hold it; n: the training texts by label."""
    rng = np.random.default_rng(params.seed)
    size, n_filters = params.size, params.filters
    known = np.flatnonzero(texts_with.sum(0) >= params.min_texts)
    zero = len(known)
    row_of = np.full((1 << params.hash_bits) + 1, zero, np.int64)
    row_of[known] = np.arange(zero)
    embedding = rng.normal(0, 0.1, (zero + 1, size)).astype(np.float32)
    n0, n1 = max(1, n[0]), max(1, n[1])
    embedding[:zero, 0] = np.log((texts_with[1, known] + 0.5) / (n1 + 1)) - np.log((texts_with[0, known] + 0.5) / (n0 + 1))
    embedding[zero] = 0
    kernels = [rng.normal(0, 0.3 / np.sqrt(w * size), (w, size, n_filters)).astype(np.float32) for w in WIDTHS]
    for k in kernels:
        k[0, 0] += 0.3
    return ToxicModel(embedding, row_of, kernels, [np.zeros(n_filters, np.float32) for _ in WIDTHS], rng.normal(0, 0.2, n_filters * len(WIDTHS)) + 0.1, 0.0)


def epochs_of(n: int, params: ToxicParams) -> int:
    return max(params.epochs, -(-params.steps // max(1, n // params.batch)))


def train(model: ToxicModel, hashed: list, y: np.ndarray, label_weight: np.ndarray, epochs: int, params: ToxicParams, turn: int = 0) -> ToxicModel:
    """Adam on the log loss from the given model over all the rows; hashed: each text's hash rows."""
    rng = np.random.default_rng([params.seed, turn])
    n_filters, zero = params.filters, len(model.embedding) - 1
    model = replace(model, embedding=model.embedding.copy(), kernels=[k.copy() for k in model.kernels], offsets=[b.copy() for b in model.offsets], weights=model.weights.copy())
    ids = []
    for h in hashed:
        own = np.full((h.shape[1], len(h) + PAD), zero, np.int64)
        own[:, : len(h)] = model.row_of.take(h.T)
        ids.append(own)
    tail = np.full((1 + len(PREFIXES), PAD), zero, np.int64)
    state: dict[str, tuple] = {}

    def adam(name, value, grad, step, rows=slice(None)):
        """grad: of the given rows, others have none."""
        if name not in state:
            state[name] = np.zeros_like(value), np.zeros_like(value)
        m, v = state[name]
        m *= 0.9
        m[rows] += 0.1 * grad
        v *= 0.99
        v[rows] += 0.01 * grad * grad
        first, second = 1 - 0.9**step, np.sqrt(1 - 0.99**step)
        moved = np.empty(min(value.size, NUMBERS_AT_ONCE), value.dtype)
        x, m, v = value.reshape(-1), m.reshape(-1), v.reshape(-1)
        for a in range(0, len(x), NUMBERS_AT_ONCE):
            b = min(len(x), a + NUMBERS_AT_ONCE)
            t = np.sqrt(v[a:b], out=moved[: b - a])
            t += 1e-6 * second
            np.divide(m[a:b], t, out=t)
            t *= params.rate * second / first
            x[a:b] -= t

    bias, step = np.full(1, model.bias), 0
    batches, column = max(1, len(ids) // params.batch), np.arange(n_filters * len(WIDTHS))
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(len(ids)), batches):
            step += 1
            texts = [ids[i] for i in batch]
            ends = np.cumsum([x.shape[1] for x in texts])
            seq = np.concatenate([*texts, tail], axis=1)
            vectors = embed(model.embedding, seq)
            r = convolve(vectors, padding(ends), model.kernels)
            at = np.stack([a + r[:, a:b].argmax(1) for a, b in zip([0, *ends[:-1]], ends, strict=True)])
            x = r[column, at] + np.concatenate(model.offsets)
            active = np.maximum(x, 0)
            g = label_weight[y[batch]] * (1 / (1 + np.exp(-np.clip(active @ model.weights + bias[0], -30, 30))) - y[batch]) / len(batch)
            gx = np.where(x > 0, g[:, None] * model.weights, 0).astype(np.float32)
            adam("weights", model.weights, active.T @ g + 1e-4 * model.weights, step)
            adam("bias", bias, np.array([g.sum()]), step)
            places, slopes = [], []
            for w, k in enumerate(model.kernels):
                gw, own = gx[:, w * n_filters : (w + 1) * n_filters], at[:, w * n_filters : (w + 1) * n_filters]
                gk, on = np.zeros_like(k), np.nonzero(gw)
                for j in range(len(k)):
                    gk[j] = np.einsum("bfd,bf->df", vectors[own + j], gw)
                    places.append(own[on] + j)
                    slopes.append(gw[on][:, None] * k[j].T[on[1]])
                adam(f"kernel{w}", k, gk + 1e-4 * k, step)
                adam(f"offset{w}", model.offsets[w], gw.sum(0), step)
            touched, ge = summed(seq[:, np.concatenate(places)], np.concatenate(slopes), zero)
            adam("embedding", model.embedding, ge, step, touched)
    model.bias = float(bias[0])
    return model


def summed(rows: np.ndarray, slopes: np.ndarray, zero: int) -> tuple[np.ndarray, np.ndarray]:
    """(embedding rows, their gradients): each word's slope is added to all its rows but the zero row, the last one."""
    part, word = np.nonzero(rows < zero)
    row, size = rows[part, word], slopes.shape[1]
    found = np.zeros(zero, bool)
    found[row] = True
    touched = np.flatnonzero(found)
    number = np.empty(zero, np.int64)
    number[touched] = np.arange(len(touched))
    cell = (number[row] * size)[:, None] + np.arange(size)
    return touched, np.bincount(cell.ravel(), slopes[word].ravel(), len(touched) * size).astype(np.float32).reshape(-1, size)


def calibrate(model: ToxicModel, z: np.ndarray, y: np.ndarray, langs: np.ndarray, prior: float, params: ToxicParams) -> ToxicModel:
    """Slope, shift and thresholds by language from the margins of all rows held out of the training."""
    model.slope, model.shift = platt(z, y) if len(y) else (1.0, 0.0)
    prior = min(max(prior, 1e-3), 1 - 1e-3)
    share = min(max(y.mean(), 1e-3), 1 - 1e-3) if len(y) else prior
    model.shift += float(np.log(prior / (1 - prior)) - np.log(share / (1 - share)))
    p = model.probability(z)
    weight = np.where(y == 1, prior / share, (1 - prior) / (1 - share))
    for lang in np.unique(langs):
        mine = langs == lang
        model.thresholds[str(lang)] = calibrated_threshold(p[mine], y[mine], weight[mine], params.precision)
    return model


def weights_of(n: np.ndarray) -> np.ndarray:
    return n.sum() / (2 * np.maximum(1, n))


def fit(rows: list, prior: float, params: ToxicParams) -> ToxicModel:
    """rows: (text, y, lang), all at once; every fifth row calibrates."""
    y = np.array([r[1] for r in rows], np.int64)
    if len(y) < 10 or y.min() == y.max():
        return prior_model(prior, params)
    hashed = [word_parts(*text_arrays(pa.array([text], pa.large_string())), params.hash_bits)[0] for text, *_ in rows]
    held = np.arange(len(y)) % 5 == 4
    own = np.flatnonzero(~held)
    texts_with = np.zeros((2, 1 << params.hash_bits))
    for i in own:
        texts_with[y[i]][np.unique(hashed[i][hashed[i] >= 0])] += 1
    n = np.bincount(y[own], minlength=2)
    model = train(start_model(texts_with, n, params), [hashed[i] for i in own], y[own], weights_of(n), epochs_of(len(own), params), params)
    z = np.array([model.margins(hashed[i], np.array([len(hashed[i])]))[0] for i in np.flatnonzero(held)])
    return calibrate(model, z, y[held], np.array([r[2] or "" for r in rows])[held], prior, params)


def calibrated_threshold(p: np.ndarray, y: np.ndarray, weight: np.ndarray, precision: float) -> float:
    """The lowest threshold at which the precision aimed at holds, rows weighted as labels have them; 0.5 where no row is toxic."""
    if not y.any():
        return 0.5
    order = np.argsort(-p, kind="stable")
    reached = np.flatnonzero(np.cumsum((y * weight)[order]) / np.cumsum(weight[order]) >= precision)
    return float(min(0.5, p[order][reached[-1]])) if len(reached) else 0.5


def narrow(bits: int) -> type:
    return np.int16 if bits < 16 else np.int32


def unpacked(blob, bits: int) -> np.ndarray:
    return np.frombuffer(blob.as_buffer(), narrow(bits)).reshape(-1, 1 + len(PREFIXES)).astype(np.int64)


def hashed_rows(documents: DataFrame, marks: DataFrame, shards: int, params: ToxicParams) -> DataFrame:
    """(shard, held, y, lang, parts) of every labelled text, bucketed by shard: hash rows of its words."""
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("lang")).where("text is not null")
    h = F.xxhash64("doc_id", F.lit("shard"))
    rows = texts.join(marks.hint("merge"), "doc_id").select(F.pmod(h, F.lit(shards)).cast("int").alias("shard"), (F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 4).alias("held"), "y", "lang", "text")

    def hashing(batches):
        for batch, data, offsets in blocks(batches):
            parts, per = word_parts(data, offsets, params.hash_bits)
            flat = parts.astype(narrow(params.hash_bits)).tobytes()
            ends = np.concatenate([[0], np.cumsum(per)]) * parts.shape[1] * np.dtype(narrow(params.hash_bits)).itemsize
            out = pa.array([flat[a:b] for a, b in zip(ends, ends[1:])], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], out], names=["shard", "held", "y", "lang", "parts"])

    spark = documents.sparkSession
    name, buckets = f"vecspark_{uuid.uuid4().hex}", min(shards, 4 * spark.sparkContext.defaultParallelism)
    hashed = rows.mapInArrow(hashing, "shard int, held boolean, y int, lang string, parts binary")
    hashed.write.bucketBy(buckets, "shard").option("path", new_path(spark, "hashed")).saveAsTable(name)
    return spark.table(name)


def texts_by_row(rows: DataFrame, params: ToxicParams) -> np.ndarray:
    """By label and hash row the number of training texts that hold it."""
    size = 1 << params.hash_bits

    def count(batches):
        total = np.zeros(2 * size, np.int64)
        for batch in batches:
            for y, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                held = np.zeros(size + 1, bool)  # -1 is the last one
                held[unpacked(blob, params.hash_bits)] = True
                total[size * y : size * (y + 1)] += held[:-1]
        cell = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(cell.astype(np.int32)), pa.array(total[cell])], names=["cell", "n"])

    found = rows.where("not held").select("y", "parts").mapInArrow(count, "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).collect()
    out = np.zeros(2 * size)
    out[[r["cell"] for r in found]] = [r["n"] for r in found]
    return out.reshape(2, size)


def pieces(model: ToxicModel) -> list[np.ndarray]:
    return [model.embedding, *model.kernels, *model.offsets, model.weights, np.array([model.bias])]


def averaged_round(rows: DataFrame, model: ToxicModel, label_weight: np.ndarray, epochs: int, params: ToxicParams, turn: int) -> ToxicModel:
    """Every shard goes on from the model; their models' mean, weighted by rows, is added up on the executors."""
    shipped = rows.sparkSession.sparkContext.broadcast(model)

    def go_on(group: pa.Table) -> pa.Table:
        y, m = group["y"].to_numpy().astype(np.int64), shipped.value
        hashed = [unpacked(x, params.hash_bits) for x in group["parts"]]
        by = np.lexsort(([h.sum() for h in hashed], [len(h) for h in hashed], y))  # files come in any order
        done = train(m, [hashed[i] for i in by], y[by], label_weight, epochs, params, turn)
        return pa.table({"n": pa.array([len(y)]), "blob": pa.array([pickle.dumps([np.float32(len(y)) * p.astype(np.float32) for p in pieces(done)])], pa.binary())})

    def add_up(batches):
        n, total = 0, None
        for batch in batches:
            for k, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = pickle.loads(blob.as_py())
                n, total = n + k, own if total is None else [a + b for a, b in zip(total, own, strict=True)]
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([pickle.dumps(total)], pa.binary())], names=["n", "blob"])

    kind = "n long, blob binary"
    sums = rows.where("not held").select("shard", "y", "parts").groupBy("shard").applyInArrow(releasing(go_on), kind).mapInArrow(add_up, kind)
    n, blob = sums.repartition(1).mapInArrow(add_up, kind).first()
    mean = [p.astype(np.float64) / n for p in pickle.loads(blob)]
    k = len(WIDTHS)
    return replace(model, embedding=mean[0].astype(np.float32), kernels=[x.astype(np.float32) for x in mean[1 : 1 + k]], offsets=[x.astype(np.float32) for x in mean[1 + k : 1 + 2 * k]], weights=mean[-2], bias=float(mean[-1][0]))


def held_margins(rows: DataFrame, model: ToxicModel) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(margins, labels, languages) of every row that calibrates."""
    shipped = rows.sparkSession.sparkContext.broadcast(model)

    def margins(batches):
        for batch in batches:
            parts = [unpacked(x, shipped.value.bits) for x in batch.column(2)]
            per = np.array([len(p) for p in parts], np.int64)
            z, turn = np.empty(len(per)), (np.cumsum(per) - per) // WORDS_AT_ONCE
            for t in np.unique(turn):
                own = np.flatnonzero(turn == t)
                z[own] = shipped.value.margins(np.concatenate([parts[i] for i in own]), per[own])
            yield pa.RecordBatch.from_arrays([pa.array(z), *batch.columns[:2]], names=["z", "y", "lang"])

    found = rows.where("held").select("y", "lang", "parts").mapInArrow(margins, "z double, y int, lang string").toPandas().sort_values(["z", "y", "lang"])
    return found.z.to_numpy(), found.y.to_numpy(), found.lang.to_numpy(str)


def fit_toxicity(documents: DataFrame, labels: DataFrame, params: ToxicParams = ToxicParams(), where=None) -> ToxicModel:
    use = labels.where("toxic is not null")
    if where is not None:
        use = use.where(where(F.col("doc_id")))
    n, toxic = use.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.when(F.col("toxic") > 0, 1).otherwise(0)), F.lit(0))).first()
    prior = toxic / n if n else 0.0
    marks = use.where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max((F.col("toxic") > 0).cast("int")).alias("y"))
    shards = max(1, round(n / params.shard_rows))
    rows = hashed_rows(documents, marks, shards, params)
    counts = {(r["held"], r["y"]): r["n"] for r in rows.groupBy("held", "y").agg(F.count(F.lit(1)).alias("n")).collect()}
    by_label = np.array([counts.get((False, y), 0) for y in (0, 1)])
    if sum(counts.values()) < 10 or not by_label.all():
        return prior_model(prior, params)
    rounds, epochs = params.rounds if shards > 1 else 1, epochs_of(by_label.sum() // shards, params)
    model = start_model(texts_by_row(rows, params), by_label, params)
    for turn in range(rounds):
        model = averaged_round(rows, model, weights_of(by_label), -(-epochs // rounds), params, turn)
    model = calibrate(model, *held_margins(rows, model), prior, params)
    discard(rows)
    return model


def score_toxicity(documents: DataFrame, model: ToxicModel, held_out) -> DataFrame:
    """doc_id, held_out, score, predicted, flagged (by the threshold of the row's language)."""
    shipped = documents.sparkSession.sparkContext.broadcast(model)

    def score(batches):
        m = shipped.value
        for rows, data, offsets in blocks(batches, limit=1 << 20):
            p = m.probability(m.margins(*word_parts(data, offsets, m.bits)))
            limit = np.array([m.thresholds.get(x or "", 0.5) for x in rows.column(3).to_pylist()])
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(p), pa.array((p >= 0.5).astype(np.int32)), pa.array(p >= limit)], names=["doc_id", "held_out", "score", "predicted", "flagged"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), held_out.alias("held_out"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    return docs.mapInArrow(score, "doc_id long, held_out boolean, score double, predicted int, flagged boolean")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    held = lambda c: crc_mod(c, 5) == 0
    model = fit_toxicity(documents, table(spark, sf_dir, "labels"), where=lambda c: ~held(c))
    return score_toxicity(documents, model, held(F.col("doc_id")))
