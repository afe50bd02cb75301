"""Benchmark decontamination: rare word n-gram seeds, then Smith-Waterman alignment on words.

The test items are the stated query set.  Their n-grams are counted over all training texts (by document); of
each item those n-grams are seeds that are rare in the corpus or no more frequent than the item's median one, so
an item that has leaked everywhere keeps seeds.  Where a text holds seeds of an item, the words around them are
aligned with the whole item (match +2, mismatch and gap -1); the score is the best local alignment over that of
a perfect copy, and `threshold` or more is a leak.

The index is broadcast in slices of at most `slice_grams` n-grams, so its size has a bound at any number of
items; each slice is one pass over the texts.  Words are runs of letters and digits, A-Z in lower case.

Defined results: null and empty texts and items match nothing; items of fewer words than the seed length match
nothing; items of equal text are reported each; an empty table of either kind gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .language import Lookup
from .tables import table
from .textkit import blocks, gram_hash, lower_ascii, segment_hash, text_arrays, words

WORD_BYTE = np.zeros(256, bool)
WORD_BYTE[48:58] = WORD_BYTE[65:91] = WORD_BYTE[97:123] = WORD_BYTE[128:] = True


@dataclass(frozen=True)
class LeakParams:
    seed_words: int = 3
    rare_share: float = 1e-3  #: rare: in at most this share of all texts,
    rare_texts: int = 20  #: or in at most so many
    match: int = 2
    mismatch: int = -1
    gap: int = -1
    threshold: float = 0.5
    slice_grams: int = 2_000_000


def word_hashes(data: np.ndarray, offsets: np.ndarray):
    low = lower_ascii(data)
    seg = words(low, offsets, WORD_BYTE)
    return segment_hash(low, seg), seg


class ItemIndex:
    """The seeds of a slice of items: n-gram -> (item, ...)."""

    def __init__(self, item_ids: np.ndarray, tokens: np.ndarray, first: np.ndarray, params: LeakParams, unnamed: np.ndarray | None = None):
        self.ids, self.tokens, self.first, self.params = item_ids, tokens, first, params
        self.unnamed = np.zeros(len(item_ids), bool) if unnamed is None else unnamed  #: items whose id is null
        n = params.seed_words
        item = np.repeat(np.arange(len(item_ids)), np.diff(first))
        grams = gram_hash(tokens, n)
        inside = item[n - 1 :] == item[: len(grams)] if len(grams) else np.empty(0, bool)
        pairs = np.unique(np.stack([grams[inside], item[: len(grams)][inside].astype(np.uint64)], 1), axis=0) if len(grams) else np.empty((0, 2), np.uint64)
        self.link(pairs[:, 0], pairs[:, 1].astype(np.int64))

    def link(self, gram: np.ndarray, item: np.ndarray) -> None:
        order = np.argsort(gram, kind="stable")
        self.gram, self.item = gram[order], item[order]
        keys, self.start, self.size = np.unique(self.gram, return_index=True, return_counts=True)
        self.find = Lookup(keys)

    def keep_rare(self, texts_with: np.ndarray, texts: int) -> None:
        """texts_with: by distinct n-gram, how many texts hold it."""
        count = np.repeat(texts_with, self.size)
        limit = np.zeros(len(self.ids))
        order = np.lexsort((count, self.item))
        ends = np.cumsum(np.bincount(self.item, minlength=len(self.ids)))
        begins = ends - np.bincount(self.item, minlength=len(self.ids))
        full = np.flatnonzero(ends > begins)
        limit[full] = count[order][(begins[full] + ends[full]) // 2]
        rare = (count <= max(self.params.rare_texts, self.params.rare_share * texts)) | (count <= limit[self.item])
        self.link(self.gram[rare], self.item[rare])

    def hits(self, tokens: np.ndarray, doc: np.ndarray):
        """(place, row of the distinct n-gram) of each seed in a block of texts."""
        n = self.params.seed_words
        grams = gram_hash(tokens, n)
        row = self.find.find(grams)
        at = np.flatnonzero(row >= 0)
        at = at[doc[at] == doc[at + n - 1]]
        return at, row[at]

    def leaks(self, tokens: np.ndarray, doc: np.ndarray, n_docs: int):
        """(doc, item, score, first word, last word + 1) of the best alignment of each text with each item that leaks."""
        at, row = self.hits(tokens, doc)
        if not len(at):
            return (np.empty(0, np.int64),) * 2 + (np.empty(0),) + (np.empty(0, np.int64),) * 2
        each = self.size[row]
        place = np.repeat(at, each)
        item = self.item[np.repeat(self.start[row], each) + np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)]
        order = np.lexsort((place, item, doc[place]))
        place, item = place[order], item[order]
        d = doc[place]
        length = np.diff(self.first)[item]
        new = np.concatenate([[True], (d[1:] != d[:-1]) | (item[1:] != item[:-1]) | (place[1:] - place[:-1] > length[1:])])
        begin = np.flatnonzero(new)
        end = np.concatenate([begin[1:], [len(place)]]) - 1
        d, item, length = d[begin], item[begin], length[begin]
        doc_first = np.searchsorted(doc, np.arange(n_docs))
        doc_last = np.searchsorted(doc, np.arange(n_docs), "right")
        lo = np.maximum(place[begin] - length - length // 4, doc_first[d])
        hi = np.minimum(place[end] + length + length // 4 + self.params.seed_words, doc_last[d])
        score, stop = self.align(tokens, lo, hi, item)
        share = score / (self.params.match * length)
        good = np.flatnonzero(share >= self.params.threshold)
        good = good[np.lexsort((-share[good], item[good], d[good]))]
        best = good[np.concatenate([[True], (d[good][1:] != d[good][:-1]) | (item[good][1:] != item[good][:-1])])] if len(good) else good
        return d[best], item[best], share[best], lo[best] - doc_first[d[best]], stop[best] - doc_first[d[best]]

    def align(self, tokens, lo, hi, item):
        """Best local score of each window against its item, and where it ends; all windows of a chunk by item word."""
        p = self.params
        score, stop = np.zeros(len(lo), np.int64), np.zeros(len(lo), np.int64)
        wide = hi - lo
        order = np.argsort(wide, kind="stable")
        at = 0
        while at < len(order):
            to = at + 1
            while to < len(order) and (to - at + 1) * wide[order[to]] <= 400_000:
                to += 1
            rows = order[at:to]
            w = int(wide[rows].max())
            cols = np.arange(w)
            inside = cols < wide[rows][:, None]
            text = tokens[np.minimum(lo[rows][:, None] + cols, len(tokens) - 1)]
            n = np.diff(self.first)[item[rows]]
            h = np.zeros((len(rows), w + 1), np.int32)
            best, where = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
            slope = (np.arange(w + 1) * -p.gap).astype(np.int32)
            for i in range(int(n.max())):
                word = self.tokens[np.minimum(self.first[item[rows]] + i, len(self.tokens) - 1)]
                step = np.where((text == word[:, None]) & inside, p.match, p.mismatch).astype(np.int32)
                new = np.zeros_like(h)
                np.maximum(h[:, :-1] + step, h[:, 1:] + p.gap, out=new[:, 1:])
                np.maximum(new, 0, out=new)
                new = np.maximum.accumulate(new + slope, axis=1) - slope
                live = i < n
                h = np.where(live[:, None], new, 0)
                top = h.argmax(1)
                value = h[np.arange(len(rows)), top]
                better = value > best
                best[better], where[better] = value[better], top[better]
            score[rows], stop[rows] = best, lo[rows] + where
            at = to
        return score, stop


def item_slices(items: DataFrame, params: LeakParams) -> Iterator[ItemIndex]:
    """Indexes of the items, in the order of their ids, each within the bound."""
    rows = items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null").repartitionByRange("item_id").sortWithinPartitions("item_id", "text")
    ids, parts, held = [], [], 0

    def index() -> ItemIndex:
        first = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int64)
        return ItemIndex(np.array([-1 if i is None else i for i in ids], np.int64), np.concatenate(parts), first, params, np.array([i is None for i in ids]))

    for row in rows.toLocalIterator():
        h, _ = word_hashes(*text_arrays(pa.array([row["text"]], pa.large_string())))
        if len(h) < params.seed_words:
            continue
        if held and held + len(h) > params.slice_grams:
            yield index()
            ids, parts, held = [], [], 0
        ids.append(row["item_id"])
        parts.append(h)
        held += len(h)
    if held:
        yield index()


def rare_index(texts: DataFrame, index: ItemIndex) -> ItemIndex:
    """The index with its seeds chosen by their counts over all texts."""
    shipped = texts.sparkSession.sparkContext.broadcast(index)

    def count(batches):
        own = shipped.value
        found, n = np.zeros(len(own.start), np.int64), 0
        for rows, data, offsets in blocks(batches):
            h, seg = word_hashes(data, offsets)
            at, row = own.hits(h, seg.doc)
            once = np.unique(seg.doc[at] * len(own.start) + row) % max(1, len(own.start))
            found += np.bincount(once, minlength=len(found))
            n += rows.num_rows
        some = np.flatnonzero(found)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(found[some], n))], names=["seed", "texts"])

    counted = texts.select("text").mapInArrow(count, "seed long, texts long").groupBy("seed").agg(F.sum("texts").alias("texts")).collect()
    total, with_seed = 0, np.zeros(len(index.start), np.int64)
    for seed, n in counted:
        if seed < 0:
            total = n
        else:
            with_seed[seed] = n
    index.keep_rare(with_seed, total)
    return index


def find_leaks(documents: DataFrame, items: DataFrame, params: LeakParams = LeakParams()) -> DataFrame:
    """doc_id, item_id, score, first_word, end_word: the best alignment of every text with every item that it leaks."""
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, item_id long, score double, first_word long, end_word long"
    found = []
    for index in item_slices(items, params):
        shipped = documents.sparkSession.sparkContext.broadcast(rare_index(texts, index))

        def search(batches, shipped=shipped):
            own = shipped.value
            for rows, data, offsets in blocks(batches):
                h, seg = word_hashes(data, offsets)
                d, item, share, lo, hi = own.leaks(h, seg.doc, rows.num_rows)
                if len(d):
                    yield pa.RecordBatch.from_arrays([rows.column(0).take(pa.array(d)), pa.array(own.ids[item], mask=own.unnamed[item]), pa.array(share), pa.array(lo), pa.array(hi)], names=["doc_id", "item_id", "score", "first_word", "end_word"])

        found.append(texts.mapInArrow(search, schema))
    return reduce(DataFrame.union, found) if found else documents.sparkSession.createDataFrame([], schema)


def drop_leaks(documents: DataFrame, items: DataFrame, params: LeakParams = LeakParams()) -> DataFrame:
    """The rows of `documents`, with their own columns, that leak no item."""
    out = documents
    for index in item_slices(items, params):
        shipped = documents.sparkSession.sparkContext.broadcast(rare_index(documents.select("text"), index))

        def passing(batches, shipped=shipped):
            own = shipped.value
            for rows, data, offsets in blocks(batches):
                h, seg = word_hashes(data, offsets)
                clean = np.ones(rows.num_rows, bool)
                clean[own.leaks(h, seg.doc, rows.num_rows)[0]] = False
                yield rows.filter(pa.array(clean))

        out = out.mapInArrow(passing, documents.schema)
    return out


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
