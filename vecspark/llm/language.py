"""Language identification by prediction by partial matching over bytes.

Each language has a variable-order byte context tree (orders 4 to 0) with escape probabilities by method C:
a symbol seen n times in a context of t visits and q different symbols costs -log2(n/(t+q)) bits, an unseen one
costs -log2(q/(t+q)) bits and is coded one order lower; below order 0 every byte costs 8 bits.  The statistics
are frozen after training, so the code length of a whole text is a sum over its bytes and does not depend on
the order in which texts are scored.  The trees are flattened: for every (context, symbol) that any language
has seen, one table row holds the finished code length under each language.

Defined results: a null text or one without a letter is `und` with score 0, and so is every text where no
language could be learned.  Equal code lengths are settled by the language's name.  The languages are learned
from a bounded sample of rows a language (`LanguageParams`); all texts are scored whole.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .tables import stretch, table
from .textkit import blocks, crc_mod, has_letter, releasing, text_arrays

ORDER = 4
UNITS = 4096  #: code lengths are whole numbers of 1/4096 bit, so that sums are exact


@dataclass(frozen=True)
class LanguageParams:
    rows_per_language: int = 300  #: bound of the sample
    languages: int = 400  #: languages whose trees stand in one table; more languages make more tables, none is left out
    total_rows: int = 12_000  #: bound over all languages, shared out evenly where there are many, one row each at the least
    sample_chars: int = 20_000  #: characters of a text that the sample takes, from a place drawn by a hash
    min_rows: int = 1


class Lookup:
    """Open addressing over 64-bit keys; rows of -1 where a key is missing."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        self.bits = max(4, int(np.ceil(np.log2(max(1, len(keys)) * 2))))
        self.slots = np.full(1 << self.bits, -1, np.int32)
        todo, slot = np.arange(len(keys)), self._slot(keys)
        while len(todo):
            free = self.slots[slot] < 0
            at, which = np.unique(np.where(free, slot, -1), return_index=True)
            which, at = which[at >= 0], at[at >= 0]
            self.slots[at] = todo[which]
            left = np.ones(len(todo), bool)
            left[which] = False
            todo, slot = todo[left], slot[left]
            slot = np.where(self.slots[slot] >= 0, (slot + 1) & (len(self.slots) - 1), slot)

    def _slot(self, keys):
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(keys), -1, np.int32)
        slot = self._slot(keys)
        row = self.slots[slot]
        wrong = np.flatnonzero((row >= 0) & (self.keys[row] != keys))
        while len(wrong):
            slot[wrong] = (slot[wrong] + 1) & (len(self.slots) - 1)
            row[wrong] = self.slots[slot[wrong]]
            wrong = wrong[(row[wrong] >= 0) & (self.keys[row[wrong]] != keys[wrong])]
        return row


def context_keys(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """The byte and the ORDER bytes before it as one number, zeros before the text's start."""
    key = data.astype(np.uint64)
    wide = key.copy()
    starts = offsets[:-1]
    length = np.diff(offsets)
    for back in range(1, ORDER + 1):
        key[back:] |= wide[:-back] << np.uint64(8 * back)
        for t in range(back):
            at = starts[length > t] + t
            key[at] &= np.uint64((1 << (8 * (t + 1))) - 1)
    return key


@dataclass
class ContextTrees:
    languages: list[str]
    symbols: list[Lookup]  #: by order
    cost: list[np.ndarray]
    contexts: list[Lookup]
    escape: list[np.ndarray]

    def code_lengths(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """In 1/UNITS bit, by document and language."""
        n_docs, n_lang = len(offsets) - 1, len(self.languages)
        total = np.zeros((n_docs, n_lang), np.int64)
        if not len(data):
            return total
        key = context_keys(data, offsets)
        row = self.symbols[ORDER].find(key)
        cost = self.cost[ORDER][np.maximum(row, 0)]
        left = np.flatnonzero(row < 0)
        if len(left):
            cost[left] = self._shorter(key[left])
        full = np.flatnonzero(np.diff(offsets) > 0)
        total[full] = np.add.reduceat(cost, offsets[:-1][full], axis=0, dtype=np.int64)
        return total

    def _shorter(self, key: np.ndarray) -> np.ndarray:
        """Code lengths of symbols that no language has seen after the longest context."""
        out = np.zeros((len(key), len(self.languages)), np.int32)
        left = np.arange(len(key))
        for order in range(ORDER, -1, -1):
            k = key[left] & np.uint64((1 << (8 * (order + 1))) - 1)
            if order < ORDER:
                row = self.symbols[order].find(k)
                hit = row >= 0
                out[left[hit]] += self.cost[order][row[hit]]
                left, k = left[~hit], k[~hit]
            context = self.contexts[order].find(k >> np.uint64(8))
            known = context >= 0
            out[left[known]] += self.escape[order][context[known]]
        out[left] += 8 * UNITS
        return out


def learn(samples: dict[str, list[str]]) -> ContextTrees:
    """The flattened trees of each language's sample texts."""
    names = sorted(samples)
    keys = [context_keys(*text_arrays(pa.array(samples[name], pa.large_string()))) for name in names]
    trees = ContextTrees(names, [], [], [], [])
    for order in range(ORDER + 1):
        mask = np.uint64((1 << (8 * (order + 1))) - 1)
        counted = [np.unique(k & mask, return_counts=True) for k in keys]
        union = np.unique(np.concatenate([c[0] for c in counted] or [np.empty(0, np.uint64)]))
        contexts = np.unique(union >> np.uint64(8))
        if order:
            below = trees.cost[order - 1][trees.symbols[order - 1].find(union & (mask >> np.uint64(8)))]
        else:
            below = np.full((len(union), len(names)), 8 * UNITS, np.int32)
        cost, escape = below.copy(), np.zeros((len(contexts), len(names)), np.int32)
        for j, (symbol, count) in enumerate(counted):
            where = np.searchsorted(contexts, symbol >> np.uint64(8))
            visits, kinds = np.bincount(where, count, len(contexts)), np.bincount(where, minlength=len(contexts))
            seen = visits > 0
            with np.errstate(divide="ignore", invalid="ignore"):
                escape[seen, j] = np.rint(-np.log2(kinds[seen] / (visits + kinds)[seen]) * UNITS)
            cost[:, j] += escape[np.searchsorted(contexts, union >> np.uint64(8)), j]
            cost[np.searchsorted(union, symbol), j] = np.rint(-np.log2(count / (visits + kinds)[where]) * UNITS)
        trees.symbols.append(Lookup(union))
        trees.cost.append(cost)
        trees.contexts.append(Lookup(contexts))
        trees.escape.append(escape)
    return trees


def fit_languages(documents: DataFrame, params: LanguageParams = LanguageParams(), where=None) -> list[ContextTrees]:
    """Learns from text and lang alone; doc_id only picks rows of the bounded sample.  Tables of languages in the order of their names."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", F.length("text").alias("n")).where("lang is not null and n >= 1")
    if where is not None:
        rows = rows.where(where)
    top = rows.groupBy("lang").count()
    per_language = max(1, min(params.rows_per_language, params.total_rows // max(1, top.count())))
    order = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    # four times the rows wanted are let through, so that a frequent language doesn't meet in one task
    share = (F.xxhash64("doc_id") / F.lit(float(2**64)) + 0.5) <= F.lit(4.0 * per_language) / F.col("count")
    ids = rows.join(top, "lang").where(share).withColumn("at", F.row_number().over(order)).where(F.col("at") <= per_language).select("doc_id", "lang").distinct()
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", F.col("text").cast("string").alias("text")).where("length(text) >= 1")
    found = texts.join(F.broadcast(ids), ["doc_id", "lang"]).withColumn("text", stretch(F.col("text"), F.col("doc_id"), params.sample_chars))
    samples: dict[str, list[str]] = {}
    for lang, text in found.groupBy("doc_id", "lang").agg(F.min("text").alias("text")).select("lang", "text").collect():
        samples.setdefault(lang, []).append(text)
    names = sorted(k for k, v in samples.items() if len(v) >= params.min_rows)
    parts = [names[i : i + params.languages] for i in range(0, len(names), params.languages)] or [[]]
    return [releasing(learn)({k: sorted(samples[k]) for k in part}) for part in parts]


def identify_language(documents: DataFrame, trees: list[ContextTrees], held_out=None) -> DataFrame:
    """doc_id, held_out, lang_pred, score (posterior under equal priors), bits (code length of the best)."""
    shipped = documents.sparkSession.sparkContext.broadcast(trees)

    def score(batches):
        models = [m for m in shipped.value if m.languages]
        names = np.array([*(name for m in models for name in m.languages), "und"], object)
        for rows, data, offsets in blocks(batches):
            n = rows.num_rows
            if models:
                bits = np.concatenate([m.code_lengths(data, offsets) for m in models], 1) / UNITS
                best = bits.argmin(1)
                least = bits[np.arange(n), best]
                post = 1 / np.exp2(np.minimum(60, bits - least[:, None]) * -1).sum(1)
            else:
                best, least, post = np.zeros(n, int), np.zeros(n), np.zeros(n)
            known = has_letter(data, offsets) & bool(models)
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), rows.column(1), pa.array(names[np.where(known, best, len(names) - 1)], pa.string()), pa.array(np.where(known, post, 0.0)), pa.array(np.where(known, least, 0.0))],
                names=["doc_id", "held_out", "lang_pred", "score", "bits"],
            )

    held = F.lit(False) if held_out is None else held_out
    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), held.alias("held_out"), F.col("text").cast("string").alias("text")).mapInArrow(score, "doc_id long, held_out boolean, lang_pred string, score double, bits double")


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    held = crc_mod(F.col("doc_id"), 4) == 2
    return identify_language(documents, fit_languages(documents, where=~(crc_mod(F.col("doc_id"), 4) == 2)), held)
