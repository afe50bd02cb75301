"""Numpy views of Arrow text: blocks of UTF-8 bytes, tokens, segment hashes.

Everything here works on one bounded block of texts at a time (``BLOCK_BYTES``; a single longer text is a
block of its own).  A null text counts as the empty text.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator
from inspect import signature

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK_BYTES = 1 << 20
U64 = np.uint64

#: The bytes that separate words, [\x20\x09-\x0D].
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)

IS_SPACE = np.zeros(256, bool)
IS_SPACE[list(SPACE_BYTES)] = True

_RNG = np.random.default_rng(20_240_601)
BYTE_CODE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * U64(2) + U64(1)
LANE_SEED = U64(0x2545F4914F6CDD1D)


def release() -> None:
    """Gives freed memory back to the system: an idle Python worker would keep it from the executor's other work."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # a C library without it
        pass


def releasing(f: Callable) -> Callable:
    """f, with memory given back after each call; Spark looks at the number of arguments, so one and two stay so."""

    def run(*args):
        try:
            return f(*args)
        finally:
            release()

    def one(x):
        return run(x)

    def two(x, y):
        return run(x, y)

    return {1: one, 2: two}.get(len(signature(f).parameters), run)


def crc_mod(doc_id: Column, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n (a null id counts as empty text)."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(n))


MIX_AT_ONCE = 1 << 14  #: numbers that stay in a core's own cache between the steps


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (the published splitmix64 constants)."""
    x = np.array(x, np.uint64, copy=True, order="C")
    flat = x.reshape(-1)
    moved = np.empty(min(len(flat), MIX_AT_ONCE), np.uint64)
    for at in range(0, len(flat), MIX_AT_ONCE):
        part = flat[at : at + MIX_AT_ONCE]
        m = moved[: len(part)]
        part ^= np.right_shift(part, U64(30), out=m)
        part *= U64(0xBF58476D1CE4E5B9)
        part ^= np.right_shift(part, U64(27), out=m)
        part *= U64(0x94D049BB133111EB)
        part ^= np.right_shift(part, U64(31), out=m)
    return x


def text_arrays(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; the offsets start at 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if not n:
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, column.offset * 8)
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(batches: Iterable[pa.RecordBatch], text: str = "text", limit: int = BLOCK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, bytes, offsets) with at most `limit` bytes of text, or one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        data, offsets = text_arrays(batch.column(batch.schema.get_field_index(text)))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
            yield batch.slice(at, to - at), data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
            at = to
    release()


class Segments:
    """Byte ranges [start, end) of a block, each inside one document."""

    __slots__ = ("start", "end", "doc", "n_docs")

    def __init__(self, start, end, doc, n_docs):
        self.start, self.end, self.doc, self.n_docs = start, end, doc, n_docs

    def __len__(self):
        return len(self.start)

    def per_doc(self) -> np.ndarray:
        return np.bincount(self.doc, minlength=self.n_docs)


def words(data: np.ndarray, offsets: np.ndarray, word_byte: np.ndarray | None = None) -> Segments:
    """Maximal runs of word bytes (not white space, unless given otherwise); none crosses two documents."""
    n, n_docs = len(data), len(offsets) - 1
    if not n:
        e = np.empty(0, np.int64)
        return Segments(e, e, e, n_docs)
    on = ~IS_SPACE[data] if word_byte is None else word_byte[data]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    first, last = on.copy(), on.copy()
    first[1:] &= ~on[:-1] | edge[1:n]
    last[:-1] &= ~on[1:] | edge[1:n]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return Segments(start, end, np.searchsorted(offsets, start, "right") - 1, n_docs)


def lines(data: np.ndarray, offsets: np.ndarray) -> Segments:
    """What lies between line feeds, of every document; an empty document has one empty line."""
    n_docs = len(offsets) - 1
    feeds = np.flatnonzero(data == 0x0A)
    start = np.concatenate([offsets[:-1], feeds + 1])
    end = np.concatenate([feeds, offsets[1:]])
    doc = np.searchsorted(offsets, feeds, "right") - 1
    order = np.lexsort((start, np.concatenate([np.arange(n_docs), doc])))
    back = np.lexsort((end, np.concatenate([doc, np.arange(n_docs)])))
    return Segments(start[order], end[back], np.concatenate([np.arange(n_docs), doc])[order], n_docs)


def segment_hash(data: np.ndarray, seg: Segments, salt: int = 0) -> np.ndarray:
    """64-bit hash of each segment's bytes, the same wherever it stands; segments may overlap.

    Eight bytes at a time, every (place, value) has a pseudo-random number of its own and these are added up, so no
    pattern of bytes collides by its form, as some do under any polynomial modulo a power of two.
    """
    seed = LANE_SEED ^ U64(salt)
    size = seg.end - seg.start
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eights = np.ndarray(len(data) + 1, "<u8", padded, strides=(1,))

    def lanes(start, rest):
        return (eights[start] & (U64(2**64 - 1) >> ((8 - np.minimum(rest, 8)) << 3).astype(np.uint64))) ^ seed

    # the first eight bytes of all, then what follows them of the longer segments
    out = np.full(len(seg), seed)
    full = np.flatnonzero(size)
    out[full] = mix(mix(lanes(seg.start[full], size[full]))) + size[full].astype(np.uint64)
    longer = np.flatnonzero(size > 8)
    if len(longer):
        count = (size[longer] - 1) // 8
        first = np.cumsum(count) - count
        turn = np.arange(1, count.sum() + 1) - np.repeat(first, count)
        lane = lanes(np.repeat(seg.start[longer], count) + 8 * turn, np.repeat(size[longer], count) - 8 * turn)
        out[longer] += np.add.reduceat(mix(mix(lane) + turn.astype(np.uint64) * U64(0xA24BAED4963EE407)), first)
    return mix(out)


def prefix_hash(data: np.ndarray, start: np.ndarray, n: int) -> np.ndarray:
    """segment_hash of the n bytes, 8 at most, that begin at each start."""
    eights = np.ndarray(len(data) + 1, "<u8", np.concatenate([data, np.zeros(8, np.uint8)]), strides=(1,))
    return mix(mix(mix((eights[start] & (U64(2**64 - 1) >> U64(64 - 8 * n))) ^ LANE_SEED)) + U64(n))


def lower_ascii(data: np.ndarray) -> np.ndarray:
    """A-Z in lower case; all else as it is."""
    return np.where((data >= 65) & (data <= 90), data | 0x20, data).astype(np.uint8)


def gram_hash(tokens: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n tokens that start at each place (shorter by n - 1); equal only for equal order."""
    m = max(0, len(tokens) - n + 1)
    out = np.full(m, 0x1234567 + n, np.uint64)
    for i in range(n):
        out = mix(out * U64(0x9DDFEA08EB382D69 | 1) + tokens[i : i + m])
    return out


def first_seen(keys: np.ndarray) -> np.ndarray:
    """True where a key stands for the first time."""
    out = np.zeros(len(keys), bool)
    out[np.unique(keys, return_index=True)[1]] = True
    return out


def repeated(keys: np.ndarray) -> np.ndarray:
    """True where a key stands more than once."""
    if not len(keys):
        return np.zeros(0, bool)
    order = np.argsort(keys)
    k = keys[order]
    same = k[1:] == k[:-1]
    flag = np.zeros(len(keys), bool)
    flag[1:] |= same
    flag[:-1] |= same
    out = np.empty(len(keys), bool)
    out[order] = flag
    return out


def has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Whether each text holds a letter of any script."""
    low = data | 0x20
    letters = np.concatenate([[0], np.cumsum((low >= 97) & (low <= 122))])
    out = (letters[offsets[1:]] - letters[offsets[:-1]]) > 0
    for i in np.flatnonzero(~out & (np.diff(offsets) > 0)):
        out[i] = any(c.isalpha() for c in data[offsets[i] : offsets[i + 1]].tobytes().decode("utf-8", "replace"))
    return out
