"""Exact substring deduplication by a hash-compared suffix sort.

A byte goes if a `length`-byte string that covers it also starts earlier: in a document of smaller id, or
earlier in the same document.

Candidates.  Every `length`-byte string has an anchor, the least-hashed `gram`-byte string in it, so equal strings
have equal anchors at equal places, and about one byte in forty is an anchor.  The strings that share an anchor
occurrence lie in one context of less than 2 * `length` bytes.  Texts are dealt into blocks of a few MB; a block
asks an anchor's key range about each distinct (anchor, context) that it holds, and learns whether the context
repeats an earlier one as a whole (all its strings go), or is the first of its kind while other contexts share
its anchor.  Only the latter are sent on, so exact copies never are.

Equal contexts are recognised by a 64-bit hash of their bytes beside the 64-bit key of their anchor, and the strings of hot
anchors by two 64-bit hashes; contexts that are sorted are compared byte by byte.

Hot anchors.  A line that very many texts hold gives an anchor of very many contexts, all of which would meet in
one key range.  The strings of such contexts are therefore dealt out by their own hash (of 128 bits), first of all
inside the block, so that a string that is everywhere comes once a block and others spread over all ranges.

Suffix sort.  In a key range the contexts of each anchor are suffix-sorted to the right of the anchor, and
their reversed left sides to the left, by mergesort.  Two suffixes are compared by a binary search for their
common extension over prefix polynomial hashes, then by the next byte, so a comparison takes a logarithmic number
of hash probes.  The common extensions of neighbours give, for every offset, which strings are equal: all but the
first in document order go.  Neighbours are then compared byte by byte; if a hash has collided, the sort is done
again with another base.

Defined results: null and empty texts have 0 bytes; a null doc_id comes before all others; rows that repeat an id
are documents of their own, in the order of their texts.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .lm import cuts
from .tables import table
from .textkit import BYTE_CODE, U64, Segments, mix, releasing, segment_hash, text_arrays

FIRST_ID = -(1 << 63)


@dataclass(frozen=True)
class SubstringParams:
    length: int = 100
    gram: int = 24
    block_bytes: int = 2 << 20
    range_bytes: int = 4 << 20
    hot: int = 1000  #: anchors of more distinct contexts than this are decided string by string


def _slide(x: np.ndarray, width: int, take) -> np.ndarray:
    """take over each run of `width` entries, by doubling."""
    have = 1
    out = x
    while have * 2 <= width:
        out = take(out[:-have], out[have:])
        have *= 2
    if have < width:
        out = take(out[: len(out) - (width - have)], out[width - have :])
    return out


def gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """64-bit hash of the bytes from each place, by doubling."""
    base = 0xD1342543DE82EF95
    done, at = None, 0
    width, h = 1, BYTE_CODE[data]
    while width <= gram:
        if gram & width:
            # the widths that make up `gram` are put together, the narrower ones first
            n = len(data) - (at + width) + 1
            done = h[:n] if done is None else done[:n] * U64(pow(base, width, 2**64)) + h[at : at + n]
            at += width
        if width * 2 > gram:
            break
        h = h[:-width] * U64(pow(base, width, 2**64)) + h[width:]
        width *= 2
    return mix(done)


@dataclass
class Anchors:
    """Per anchor occurrence: key, place, and the first and last start of the strings that it stands for."""

    key: np.ndarray
    place: np.ndarray
    lo: np.ndarray
    hi: np.ndarray


def anchors(data: np.ndarray, offsets: np.ndarray, p: SubstringParams) -> Anchors:
    n, width = len(data), p.length - p.gram + 1
    none = np.empty(0, np.int64)
    if n < p.length or not (np.diff(offsets) >= p.length).any():
        return Anchors(none.astype(np.uint64), none, none, none)
    key = gram_hashes(data, p.gram)
    rank = np.maximum((key >> U64(32)).astype(np.uint32), 1)
    least = _slide(rank, width, np.minimum).copy()
    whole = np.zeros(n + 1, np.int8)
    long_ = np.flatnonzero(np.diff(offsets) >= p.length)
    np.add.at(whole, offsets[long_], 1)
    np.add.at(whole, offsets[long_ + 1] - p.length + 1, -1)
    least[np.cumsum(whole[: len(least)], dtype=np.int8) == 0] = 0
    ahead = np.concatenate([np.zeros(width - 1, np.uint32), least, np.zeros(width - 1, np.uint32)])
    place = np.flatnonzero(rank == _slide(ahead, width, np.maximum)[: len(rank)])
    # anchors have the least of hashes, so their keys are mixed once more to spread over the key ranges
    key = mix(key[place] + U64(0xA24BAED4963EE407))
    ranked = rank[place]
    lo, hi = np.empty(len(place), np.int64), np.empty(len(place), np.int64)
    for at in range(0, len(place), 20_000):
        own = place[at : at + 20_000]
        same = ahead[own[:, None] + np.arange(width)] == ranked[at : at + 20_000][:, None]
        first = same.argmax(1)
        lo[at : at + 20_000] = own - (width - 1) + first
        hi[at : at + 20_000] = lo[at : at + 20_000] + same.sum(1) - 1
    tie = np.flatnonzero((ranked[1:] == ranked[:-1]) & (place[:-1] >= lo[1:])) + 1
    lo[tie] = place[tie - 1] + 1
    ok = lo <= hi
    return Anchors(key[ok], place[ok], lo[ok], hi[ok])


class Block:
    """A block's texts in the order of id and text, its anchors, and its distinct questions."""

    def __init__(self, group: pa.Table, p: SubstringParams, ask: bool = True):
        ids = np.array([FIRST_ID if x is None else x for x in group["doc_id"].to_pylist()], np.int64)
        texts = group["text"].combine_chunks()
        self.order = np.argsort(ids, kind="stable")
        twice = np.flatnonzero(ids[self.order][1:] == ids[self.order][:-1])
        if len(twice):
            plain = texts.fill_null("").to_pylist()
            self.order = np.array(sorted(range(len(ids)), key=lambda i: (ids[i], plain[i].encode())))
        self.ids = ids[self.order]
        self.null = np.array(group["doc_id"].is_null())[self.order]
        self.data, self.offsets = text_arrays(texts.take(pa.array(self.order)))
        if not ask:
            return
        a = self.anchors = anchors(self.data, self.offsets, p)
        doc = np.searchsorted(self.offsets, a.lo, "right") - 1
        sub = np.arange(len(self.ids)) - np.searchsorted(self.ids, self.ids)
        self.id_of = self.ids[doc]
        self.at = (sub[doc].astype(np.int64) << 40) + a.lo - self.offsets[doc]
        end = a.hi + p.length
        context = segment_hash(self.data, Segments(a.lo, end, doc, len(self.ids)))
        context = mix(context + (a.place - a.lo).astype(np.uint64) * U64(0x9E3779B97F4A7C15))
        by = np.lexsort((self.at, self.id_of, context, a.key))
        k, c = a.key[by], context[by]
        new = np.concatenate([[True], (k[1:] != k[:-1]) | (c[1:] != c[:-1])]) if len(by) else np.empty(0, bool)
        self.asked, self.again = by[new], by[~new]
        self.context = context


def hot_strings(b: Block, contexts: np.ndarray, p: SubstringParams) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """(the block's first occurrence of each string of these contexts, by hash; the starts of the others)."""
    a = b.anchors
    count = a.hi[contexts] - a.lo[contexts] + 1
    which = np.repeat(contexts, count)
    start = np.arange(count.sum()) + np.repeat(a.lo[contexts] - np.concatenate([[0], np.cumsum(count)])[:-1], count)
    seg = Segments(start, start + p.length, start, len(b.ids))
    key = segment_hash(b.data, seg) if len(start) else np.empty(0, np.uint64)
    check = segment_hash(b.data, seg, 0x5851F42D4C957F2D) if len(start) else key
    doc, at = b.id_of[which], b.at[which] + start - a.lo[which]
    order = np.lexsort((at, doc, check, key))
    k, c = key[order], check[order]
    new = np.concatenate([[True], (k[1:] != k[:-1]) | (c[1:] != c[:-1])]) if len(order) else np.empty(0, bool)
    first = order[new]
    return {"key": key[first], "check": check[first], "id": doc[first], "at": at[first], "base": start[first]}, start[order[~new]]


def merge_order(group: np.ndarray, prefix: np.ndarray, size: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mergesort of suffixes inside each group (groups stand together); (order, common extension with the one before).

    prefix[i, m] is the polynomial hash of the first m bytes of suffix i.
    """
    n = len(group)

    def common(x, y):
        lo, hi = np.zeros(len(x), np.int64), np.minimum(size[x], size[y])
        while (lo < hi).any():
            mid = (lo + hi + 1) // 2
            same = prefix[x, mid] == prefix[y, mid]
            lo, hi = np.where(same, mid, lo), np.where(same, hi, mid - 1)
        return lo

    def less(x, y, or_equal):
        e = common(x, y)
        end_x, end_y = e >= size[x], e >= size[y]
        last = text.shape[1] - 1
        step = text[x, np.minimum(e, last)] < text[y, np.minimum(e, last)]
        return np.where(end_x, or_equal | ~end_y, np.where(end_y, False, step))

    first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if n else np.empty(0, np.int64)
    count = np.diff(np.concatenate([first, [n]]))
    start, total = np.repeat(first, count), np.repeat(count, count)
    order = np.arange(n)
    width = 1
    while n and width < count.max():
        slot = np.arange(n) - start
        pair = slot // (2 * width) * (2 * width)
        left = slot - pair < width
        other_lo = start + pair + np.where(left, width, 0)
        other_hi = np.minimum(start + pair + np.where(left, 2 * width, width), start + total)
        live = np.flatnonzero(other_lo < other_hi)
        lo, hi = other_lo[live].copy(), other_hi[live].copy()
        own, is_left = order[live], left[live]
        while True:
            go = np.flatnonzero(lo < hi)
            if not len(go):
                break
            mid = (lo[go] + hi[go]) // 2
            # the left run's entries go before equal ones of the right run
            before = less(order[mid], own[go], ~is_left[go])
            lo[go], hi[go] = np.where(before, mid + 1, lo[go]), np.where(before, hi[go], mid)
        to = np.arange(n)
        inside = slot[live] - pair[live] - np.where(is_left, 0, width)
        to[live] = start[live] + pair[live] + inside + lo - other_lo[live]
        merged = np.empty(n, np.int64)
        merged[to] = order
        order = merged
        width *= 2
    shared = np.zeros(n, np.int64)
    if n > 1:
        same = np.flatnonzero(group[order][1:] == group[order][:-1]) + 1
        shared[same] = common(order[same - 1], order[same])
    shared[first] = -1
    return order, shared


def sides(buffer: np.ndarray, start: np.ndarray, left: np.ndarray, size: np.ndarray, length: int):
    """Byte matrices of what lies right of the anchors, and reversed left of them."""
    right_size, width = size - left, length
    cols = np.arange(width)
    right = np.where(cols < right_size[:, None], buffer[np.minimum((start + left)[:, None] + cols, len(buffer) - 1)], 0).astype(np.uint8)
    cols = np.arange(max(1, int(left.max(initial=0))))
    back = np.where(cols < left[:, None], buffer[np.maximum((start + left)[:, None] - 1 - cols, 0)], 0).astype(np.uint8)
    return (right, right_size), (back, left)


def prefix_hashes(text: np.ndarray, base: int) -> np.ndarray:
    out = np.zeros((len(text), text.shape[1] + 1), np.uint64)
    for i in range(text.shape[1]):
        out[:, i + 1] = out[:, i] * U64(base) + BYTE_CODE[text[:, i]]
    return out


def truly_sorted(text: np.ndarray, size: np.ndarray, order: np.ndarray, shared: np.ndarray) -> bool:
    """Whether neighbours of a group agree on just the bytes that the hashes say, and are in order."""
    at = np.flatnonzero(shared >= 0)
    x, y, e = order[at - 1], order[at], shared[at]
    cols = np.arange(text.shape[1])
    agree = ((text[x] == text[y]) | (cols >= e[:, None])).all(1)
    end = (e >= size[x]) | (e >= size[y])
    last = np.minimum(e, text.shape[1] - 1)
    return bool((agree & np.where(end, size[x] <= np.maximum(e, 0), text[x, last] < text[y, last])).all())


def repeated_strings(key, doc, at, left, size, buffer, start, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context, least offset, greatest offset) of strings that start earlier elsewhere.

    A string's offset is how far it starts left of the anchor.
    """
    by = np.argsort(key, kind="stable")
    group = key[by]
    tables = sides(buffer, start[by], left[by], size[by], length)
    sorts = []
    for text, own in tables:
        for base in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93):
            order, shared = merge_order(group, prefix_hashes(text, base), own, text)
            if truly_sorted(text, own, order, shared):
                break
        else:
            raise ArithmeticError("four bases have collided")
        sorts.append((order, shared))
    n = len(by)
    turn = np.lexsort(((at + left)[by], doc[by]))
    least = left[by] - (size[by] - length)
    gone = np.zeros((n, int(left.max(initial=0)) + 1), bool)
    index = np.arange(n)
    for offset in range(gone.shape[1]):
        has = (least <= offset) & (offset <= left[by])
        if not has.any():
            continue
        kind = np.zeros(n, np.int64)
        for (order, shared), need in zip(sorts, (length - offset, offset), strict=True):
            cls = np.empty(n, np.int64)
            cls[order] = np.maximum.accumulate(np.where(shared < need, index, 0))
            kind = kind * n + cls
        some = turn[has[turn]]
        first = np.unique(kind[some], return_index=True)[1]
        mark = np.ones(len(some), bool)
        mark[first] = False
        gone[some[mark], offset] = True
    edge = np.diff(np.pad(gone, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    x, lo = np.nonzero(edge == 1)
    _, hi = np.nonzero(edge == -1)
    return by[x], lo, hi - 1


def deduplicate_substrings(documents: DataFrame, p: SubstringParams = SubstringParams(), with_bytes: bool = True) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (the remaining bytes; null without `with_bytes`)."""
    size = documents.agg(F.sum(F.octet_length(F.col("text").cast("string")))).first()[0] or 0
    n_blocks = max(1, -(-size // p.block_bytes))
    ranges = max(1, -(-size // p.range_bytes))
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    docs = docs.withColumn("block", F.pmod(F.xxhash64("doc_id"), F.lit(n_blocks)).cast("int")).repartition("block")
    blob = lambda x, at, kind: pa.array([x[a:b].astype(kind).tobytes() for a, b in zip(at, at[1:])], pa.binary())

    def ask(group: pa.Table) -> pa.Table:
        b = Block(group, p)
        i = b.asked
        at = cuts(b.anchors.key[i], ranges)
        part = np.flatnonzero(np.diff(at))  # ranges that the block has nothing for get no row, so messages grow with the data alone
        some = lambda x, kind: pa.array([x[at[j] : at[j + 1]].astype(kind).tobytes() for j in part], pa.binary())
        number = np.full(len(part), group["block"][0].as_py(), np.int32)
        return pa.table({"block": pa.array(number), "part": pa.array(part.astype(np.int32)), "key": some(b.anchors.key[i], np.uint64), "context": some(b.context[i], np.uint64), "id": some(b.id_of[i], np.int64), "at": some(b.at[i], np.int64)})

    def answer(group: pa.Table) -> pa.Table:
        read = lambda name, kind: [np.frombuffer(x.as_py(), kind) for x in group[name]]
        keys = read("key", np.uint64)
        at = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
        key, context, doc, place = np.concatenate(keys), *(np.concatenate(read(c, k)) for c, k in (("context", np.uint64), ("id", np.int64), ("at", np.int64)))
        state = np.zeros(len(key), np.uint8)
        order = np.argsort(key, kind="stable")
        k = key[order]
        dup = np.zeros(len(k), bool)
        same = k[1:] == k[:-1]
        dup[1:] |= same
        dup[:-1] |= same
        order = order[dup]
        order = order[np.lexsort((place[order], doc[order], context[order], key[order]))]
        k, c = key[order], context[order]
        if len(order):
            new_key = np.concatenate([[True], k[1:] != k[:-1]])
            new = new_key | np.concatenate([[True], c[1:] != c[:-1]])
            kinds = np.bincount(np.cumsum(new_key) - 1, new)[np.cumsum(new_key) - 1]
            state[order] = np.where(new, np.where(kinds > p.hot, 3, np.where(kinds > 1, 2, 0)), 1)
        return pa.table({"block": group["block"], "part": group["part"], "state": blob(state, at, np.uint8)})

    contexts = "part long, block int, key binary, id binary, at binary, base binary, left binary, size binary, bytes binary"

    def send(texts: pa.Table, answers: pa.Table) -> pa.Table:
        """The contexts to be sorted, by key range; and the block's own ranges to remove, which pass through as they are."""
        schema = pa.schema([("part", pa.int64()), ("block", pa.int32()), *((c, pa.binary()) for c in ("key", "id", "at", "base", "left", "size", "bytes"))])
        if not texts.num_rows:
            return schema.empty_table()
        b = Block(texts, p)
        state = np.concatenate([np.empty(0, np.uint8), *(np.frombuffer(x.as_py(), np.uint8) for x in answers.sort_by("part")["state"])])
        a = b.anchors
        gone = np.concatenate([b.again, b.asked[state == 1]])
        number = texts["block"][0].as_py()
        hot, again = hot_strings(b, b.asked[state == 3], p)
        lo, hi = union_ranges(np.concatenate([a.lo[gone], again]), np.concatenate([a.hi[gone], again]) + p.length)
        i = b.asked[state == 2]
        at = cuts(a.key[i], ranges)
        length = a.hi[i] + p.length - a.lo[i]
        where = np.arange(length.sum()) + np.repeat(a.lo[i] - np.concatenate([[0], np.cumsum(length)])[:-1], length)
        text = b.data[where]
        ends = np.concatenate([[0], np.cumsum(length)])[at]
        rows = {"part": pa.array(np.arange(ranges, dtype=np.int64)), "block": pa.array(np.full(ranges, number, np.int32)), "key": blob(a.key[i], at, np.uint64), "id": blob(b.id_of[i], at, np.int64), "at": blob(b.at[i], at, np.int64), "base": blob(a.lo[i], at, np.int64), "left": blob(a.place[i] - a.lo[i], at, np.uint8), "size": blob(length, at, np.uint16), "bytes": blob(text, ends, np.uint8)}
        out = pa.table(rows, schema=schema).filter(pa.array(np.diff(at) > 0))
        own = pa.table({"part": pa.array([-1 - number], pa.int64()), "block": pa.array([number], pa.int32()), "key": pa.array([lo.tobytes()], pa.binary()), "id": pa.array([hi.tobytes()], pa.binary()), **{c: pa.array([b""], pa.binary()) for c in ("at", "base", "left", "size", "bytes")}}, schema=schema)
        at = cuts(hot["key"], ranges)
        empty = pa.array([b""] * ranges, pa.binary())
        strings = pa.table({"part": pa.array(np.arange(ranges, 2 * ranges, dtype=np.int64)), "block": pa.array(np.full(ranges, number, np.int32)), **{c: blob(hot[c], at, hot[c].dtype) for c in ("key", "id", "at", "base")}, "left": empty, "size": empty, "bytes": blob(hot["check"], at, np.uint64)}, schema=schema).filter(pa.array(np.diff(at) > 0))
        return pa.concat_tables([out, own, strings])

    def sort(group: pa.Table) -> pa.Table:
        if group["part"][0].as_py() < 0:
            return pa.table({"block": group["block"], "lo": group["key"], "hi": group["id"]})
        read = lambda name, kind: [np.frombuffer(x.as_py(), kind) for x in group[name]]
        keys = read("key", np.uint64)
        row = np.repeat(np.arange(len(keys)), [len(k) for k in keys])
        key, doc, at, base = np.concatenate(keys), *(np.concatenate(read(c, np.int64)) for c in ("id", "at", "base"))
        if group["part"][0].as_py() >= ranges:
            check = np.concatenate(read("bytes", np.uint64))
            order = np.lexsort((at, doc, check, key))
            k, c = key[order], check[order]
            again = order[1:][(k[1:] == k[:-1]) & (c[1:] == c[:-1])]
            marks = [union_ranges(base[own], base[own] + p.length) for own in np.split(again[np.argsort(row[again], kind="stable")], np.searchsorted(np.sort(row[again]), np.arange(1, len(keys))))]
            return pa.table({"block": group["block"], "lo": pa.array([m[0].tobytes() for m in marks], pa.binary()), "hi": pa.array([m[1].tobytes() for m in marks], pa.binary())})
        left, size = np.concatenate(read("left", np.uint8)).astype(np.int64), np.concatenate(read("size", np.uint16)).astype(np.int64)
        buffer = np.concatenate(read("bytes", np.uint8))
        start = np.concatenate([[0], np.cumsum(size)])[:-1]
        x, low, high = repeated_strings(key, doc, at, left, size, buffer, start, p.length)
        lo, hi = base[x] + left[x] - high, base[x] + left[x] - low + p.length
        found = np.argsort(row[x], kind="stable")
        to = np.searchsorted(row[x][found], np.arange(len(keys) + 1))
        return pa.table({"block": group["block"], "lo": blob(lo[found], to, np.int64), "hi": blob(hi[found], to, np.int64)})

    def cut(texts: pa.Table, answers: pa.Table) -> pa.Table:
        schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.binary())])
        if not texts.num_rows:
            return schema.empty_table()
        b = Block(texts, p, ask=False)
        n = len(b.data)
        lo = np.concatenate([np.frombuffer(x.as_py(), np.int64) for x in answers["lo"]] or [np.empty(0, np.int64)])
        hi = np.concatenate([np.frombuffer(x.as_py(), np.int64) for x in answers["hi"]] or [np.empty(0, np.int64)])
        gone = np.cumsum(np.bincount(lo, minlength=n + 1) - np.bincount(hi, minlength=n + 1))[:n] > 0
        begins = gone.copy()
        edge = np.zeros(n + 1, bool)
        edge[b.offsets] = True
        begins[1:] &= ~gone[:-1] | edge[1:n]
        total = lambda mask: (c := np.concatenate([[0], np.cumsum(mask)]))[b.offsets[1:]] - c[b.offsets[:-1]]
        removed = total(gone)
        kept = [b.data[s:e].tobytes() if not r else b.data[s:e][~gone[s:e]].tobytes() for s, e, r in zip(b.offsets, b.offsets[1:], removed)]
        digests = [hashlib.sha256(k).hexdigest() for k in kept]
        return pa.table([pa.array(b.ids, pa.int64(), mask=b.null), pa.array(np.diff(b.offsets)), pa.array(removed), pa.array(total(begins)), pa.array(digests), pa.array(kept, pa.binary()) if with_bytes else pa.nulls(len(kept), pa.binary())], schema=schema)

    asked = docs.groupBy("block").applyInArrow(releasing(ask), "block int, part int, key binary, context binary, id binary, at binary")
    answered = asked.groupBy("part").applyInArrow(releasing(answer), "block int, part int, state binary")
    sent = docs.groupBy("block").cogroup(answered.groupBy("block")).applyInArrow(releasing(send), contexts)
    found = sent.groupBy("part").applyInArrow(releasing(sort), "block int, lo binary, hi binary")
    return docs.groupBy("block").cogroup(found.groupBy("block")).applyInArrow(releasing(cut), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def union_ranges(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same bytes in as few ranges as will do."""
    if not len(lo):
        return lo.astype(np.int64), hi.astype(np.int64)
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    first = np.concatenate([[True], lo[1:] > hi[:-1]])
    at = np.flatnonzero(first)
    return lo[at].astype(np.int64), hi[np.concatenate([at[1:] - 1, [len(hi) - 1]])].astype(np.int64)


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate_substrings(table(spark, sf_dir, "documents"), with_bytes=False).drop("kept")
