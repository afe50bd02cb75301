"""Secret scans: fixed base patterns, and a linear-chain conditional random field that adds spans.

The field tags the tokens of each line as begin, inside or outside of a secret.  Its features are the token's
shape, the words on either side, what separates it from the token before, and features of the whole file.  It is
trained in numpy by maximum likelihood on a bounded sample of texts (`SecretParams`) whose labels are the base
matches, with variants of those lines in which the keyword is another word; texts are scanned whole, and tags
are decoded by Viterbi.  A line whose every token prefers `outside` by more than any transition could gain back
is all outside, which is Viterbi's own answer; only the other lines are decoded step by step.

Defined results: a null text is the empty text; spans are in code points, ends exclusive.  An added span is of
kind `crf`, overlaps no base span, and beats the all-outside tagging by at least `margin`; without training
material nothing is added.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import discard, settle, table
from .textkit import Segments, blocks, lower_ascii, releasing, segment_hash, text_arrays, words

#: The base patterns, their least lengths, and the order of kinds.
ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE)
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24
KINDS = ("assign", "access", "hex", "crf")

OUT, BEGIN, INSIDE = 0, 1, 2


def _mask(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_DIGIT, _LOWER, _UPPER = _mask(b"0123456789"), _mask(bytes(range(97, 123))), _mask(bytes(range(65, 91)))
_SYMBOL, _HEX = _mask(b"+/_.-"), _mask(b"0123456789abcdef")
_WIDE = np.arange(256) >= 128
TOKEN_BYTE = _DIGIT | _LOWER | _UPPER | _SYMBOL | _WIDE
#: Four 16-bit counters in one number each: lower, upper, digit, symbol; and hex, wide.
_COUNT_1 = (_LOWER.astype(np.uint64)) | (_UPPER.astype(np.uint64) << np.uint64(16)) | (_DIGIT.astype(np.uint64) << np.uint64(32)) | (_SYMBOL.astype(np.uint64) << np.uint64(48))
_COUNT_2 = (_HEX.astype(np.uint64)) | (_WIDE.astype(np.uint64) << np.uint64(16))
_SEPARATOR = np.full(256, 5, np.int64)
_SEPARATOR[[0x20, 0x09]] = 1
_SEPARATOR[ord("=")] = 2
_SEPARATOR[ord(":")] = 3
_SEPARATOR[[ord('"'), ord("'"), ord("`")]] = 4
_SEPARATOR[0x0A] = 0

WORD_ROWS = 4096
_SIZES = {"bias": 1, "length": 24, "shape": 32, "digits": 12, "changes": 12, "hexrun": 26, "head": 1024, "mark": 36, "before": WORD_ROWS, "after": WORD_ROWS, "file": 64, "file_mark": 64}
_FIRST = dict(zip(_SIZES, np.concatenate([[0], np.cumsum(list(_SIZES.values()))])[:-1].tolist(), strict=True))
N_FEATURES = sum(_SIZES.values())


@dataclass(frozen=True)
class SecretParams:
    sample_rows: int = 3000  #: bound of the sample of texts
    sample_chars: int = 20_000  #: of a longer text, as many characters from its first base match (or from a drawn place) on
    lines: int = 4000  #: bound of the lines of either sort
    window: int = 40  #: tokens of a training line
    epochs: int = 8
    batch: int = 200
    rate: float = 0.05
    l2: float = 1e-4
    margin: float = 4.0
    least: int = 12  #: bytes of an added span
    seed: int = 3


@dataclass
class SecretModel:
    weights: np.ndarray  #: N_FEATURES x 3
    moves: np.ndarray  #: 3 x 3, from x to
    start: np.ndarray


def _bucket(x: np.ndarray, top: int) -> np.ndarray:
    return np.minimum(np.where(x <= 4, x, (4 + np.log2(np.maximum(x, 4) / 4) * 3)).astype(np.int64), top - 1)


def tokenise(data: np.ndarray, offsets: np.ndarray):
    """(tokens, line number of each, feature rows of each)."""
    seg = words(data, offsets, TOKEN_BYTE)
    n = len(seg)
    if not n:
        return seg, np.empty(0, np.int64), np.empty((0, len(_SIZES)), np.int64)

    def counted(table):
        c = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(table[data], out=c[1:])
        return c[seg.end] - c[seg.start]

    length = seg.end - seg.start
    if length.max() > 0xFFFF:  # the packed counters would run over
        low, up, dig, sym, hexa, wide = (counted(mask).astype(np.int64) for mask in (_LOWER, _UPPER, _DIGIT, _SYMBOL, _HEX, _WIDE))
    else:
        one, two = counted(_COUNT_1), counted(_COUNT_2)
        part = lambda x, i: ((x >> np.uint64(16 * i)) & np.uint64(0xFFFF)).astype(np.int64)
        low, up, dig, sym, hexa, wide = part(one, 0), part(one, 1), part(one, 2), part(one, 3), part(two, 0), part(two, 1)
    kind = (_DIGIT.astype(np.int8) + 2 * (_LOWER | _UPPER | _WIDE))[data]
    turn = np.zeros(len(data) + 1, np.int32)
    np.cumsum(kind[1:] != kind[:-1], out=turn[1:-1])
    turn[-1] = turn[-2] if len(data) > 1 else 0
    changes = (turn[seg.end - 1] - turn[seg.start]).astype(np.int64)
    feeds = np.concatenate([[0], np.cumsum(data == 0x0A)])
    line = feeds[seg.start] + seg.doc
    lowered = lower_ascii(data)
    h = (segment_hash(lowered, seg) >> np.uint64(52)).astype(np.int64)
    head = Segments(seg.start, np.minimum(seg.end, seg.start + 4), seg.doc, seg.n_docs)
    same_before = np.concatenate([[False], line[1:] == line[:-1]])
    before = np.where(same_before, np.concatenate([[0], h[:-1]]), 0)
    after = np.where(np.concatenate([same_before[1:], [False]]), np.concatenate([h[1:], [0]]), 0)
    touch = np.where(seg.start > offsets[seg.doc], _SEPARATOR[data[np.maximum(seg.start - 1, 0)]], 0)
    gap_from = np.where(same_before, np.concatenate([[0], seg.end[:-1]]), seg.start)
    equals = np.concatenate([[0], np.cumsum((data == ord("=")) | (data == ord(":")))])
    assigned = (equals[seg.start] > equals[gap_from]) & (seg.start - gap_from <= 6)
    mark = touch * 6 + assigned * 3 + np.minimum(2, seg.start - gap_from)
    shape = (low > 0) + 2 * (up > 0) + 4 * (dig > 0) + 8 * (sym > 0) + 16 * (wide > 0)
    size = np.maximum(1, np.diff(offsets))
    code = np.concatenate([[0], np.cumsum(_mask(b"={}();<>[]$")[data])])
    tall = np.diff(feeds[offsets])
    file = _bucket((code[offsets[1:]] - code[offsets[:-1]]) * 1000 // size, 8) * 8 + _bucket(tall, 8)
    columns = {
        "bias": np.zeros(n, np.int64),
        "length": _bucket(length, 24),
        "shape": shape,
        "digits": _bucket(dig, 12),
        "changes": _bucket(changes, 12),
        "hexrun": np.where((hexa == length) & (dig > 0), 1 + _bucket(length, 24), 0),
        "head": (segment_hash(data, head) >> np.uint64(54)).astype(np.int64),
        "mark": mark,
        "before": before,
        "after": after,
        "file": file[seg.doc],
        "file_mark": np.minimum(63, file[seg.doc] // 8 * 8 + assigned * 4 + (dig > 0) * 2 + (length >= 12)),
    }
    return seg, line, np.stack([columns[k] + _FIRST[k] for k in _SIZES], 1)


def base_spans(data: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, int, int]]:
    """(doc, kind, start, end, start of the value) in bytes of the block."""
    out = []
    joined = np.concatenate([[0], np.cumsum((data == ord("=")) | (data == ord(":")))])
    with_mark = np.flatnonzero(joined[offsets[1:]] > joined[offsets[:-1]])
    raw = data.tobytes()
    for d in with_mark:
        for m in ASSIGN.finditer(raw, offsets[d], offsets[d + 1]):
            if m.end(2) - m.start(2) >= ASSIGN_LEAST:
                out.append((int(d), 0, m.start(), m.end(), m.start(2)))
    at, docs = raw.find(b"AKIA"), set()
    while at >= 0:
        docs.add(int(np.searchsorted(offsets, at, "right") - 1))
        at = raw.find(b"AKIA", at + 4)
    for d in docs:
        for m in ACCESS.finditer(raw, offsets[d], offsets[d + 1]):
            if m.end() - m.start() >= ACCESS_LEAST:
                out.append((d, 1, m.start(), m.end(), m.start()))
    runs = words(data, offsets, _HEX)
    for i in np.flatnonzero(runs.end - runs.start >= HEX_LEAST):
        out.append((int(runs.doc[i]), 2, int(runs.start[i]), int(runs.end[i]), int(runs.start[i])))
    return sorted(out, key=lambda s: (s[0], s[2], s[1]))


def viterbi(scores: np.ndarray, lengths: np.ndarray, model: SecretModel) -> np.ndarray:
    """Tags of padded lines (lines x steps x 3), by dynamic programming over steps, all lines at once."""
    n, steps, _ = scores.shape
    back = np.zeros((n, steps, 3), np.int8)
    v = scores[:, 0] + model.start
    ends = v.copy()
    for t in range(1, steps):
        cand = v[:, :, None] + model.moves[None]
        back[:, t] = cand.argmax(1)
        v = cand.max(1) + scores[:, t]
        ends[lengths > t] = v[lengths > t]
    tags = np.zeros((n, steps), np.int8)
    tag = ends.argmax(1)
    rows = np.arange(n)
    for t in range(steps - 1, -1, -1):
        tag = np.where(t == lengths - 1, ends.argmax(1), tag)
        tags[:, t] = np.where(t < lengths, tag, 0)
        tag = np.where(t < lengths, back[rows, t, tag], tag)
    return tags


def decode(emission: np.ndarray, line: np.ndarray, model: SecretModel) -> np.ndarray:
    """The tag of every token."""
    tags = np.zeros(len(line), np.int8)
    if not len(line):
        return tags
    gain = float(model.moves.max() - model.moves[OUT, OUT] + max(0.0, model.moves.max() - model.moves[OUT, OUT], float(model.start.max() - model.start[OUT])))
    open_ = (emission[:, 1:].max(1) - emission[:, OUT]) + gain > 0
    if not open_.any():
        return tags
    first = np.flatnonzero(np.concatenate([[True], line[1:] != line[:-1]]))
    size = np.diff(np.concatenate([first, [len(line)]]))
    wanted = np.flatnonzero(np.add.reduceat(open_, first) > 0)
    wanted = wanted[np.argsort(size[wanted], kind="stable")]
    at = 0
    while at < len(wanted):
        to = at + 1
        while to < len(wanted) and (to - at + 1) * size[wanted[to]] <= 200_000:
            to += 1
        rows = wanted[at:to]
        steps = int(size[rows].max())
        place = np.minimum(first[rows][:, None] + np.arange(steps), len(line) - 1)
        got = viterbi(emission[place], size[rows], model)
        inside = np.arange(steps) < size[rows][:, None]
        tags[place[inside]] = got[inside]
        at = to
    return tags


def added_spans(data: np.ndarray, offsets: np.ndarray, base, model: SecretModel, params: SecretParams):
    """(doc, kind, start, end, start) of the field's own spans."""
    seg, line, rows = tokenise(data, offsets)
    if not len(seg):
        return []
    emission = model.weights[rows[:, 0]].copy()
    for j in range(1, rows.shape[1]):
        emission += model.weights[rows[:, j]]
    tags = decode(emission, line, model)
    begin = np.flatnonzero((tags == BEGIN) | ((tags == INSIDE) & np.concatenate([[True], (tags[:-1] == OUT) | (line[1:] != line[:-1])])))
    out = []
    base_start, base_end = np.array([s[2] for s in base] or [0]), np.array([s[3] for s in base] or [0])
    taken = np.zeros(len(data) + 1, bool)
    for a, b in zip(base_start, base_end, strict=True):
        taken[a:b] = True
    for i in begin:
        j = i + 1
        while j < len(tags) and tags[j] == INSIDE and line[j] == line[i]:
            j += 1
        a, b = int(seg.start[i]), int(seg.end[j - 1])
        gained = float((emission[np.arange(i, j), tags[i:j]] - emission[i:j, OUT]).sum())
        if b - a >= params.least and gained >= params.margin and not taken[a:b].any():
            out.append((int(seg.doc[i]), 3, a, b, a))
    return out


def _training_lines(texts: list[str], params: SecretParams):
    """(feature rows, tags) of lines with a base match, variants of them, and lines without."""
    rng = np.random.default_rng(params.seed)
    found, plain = [], []
    for at in range(0, len(texts), 100):
        data, offsets = text_arrays(pa.array(texts[at : at + 100], pa.large_string()))
        seg, line, rows = tokenise(data, offsets)
        tags = np.zeros(len(seg), np.int8)
        for _, _, _, end, value in base_spans(data, offsets):
            inside = np.flatnonzero((seg.end > value) & (seg.start < end))
            if len(inside):
                tags[inside] = INSIDE
                tags[inside[0]] = BEGIN
        first = np.flatnonzero(np.concatenate([[True], line[1:] != line[:-1]])) if len(line) else np.empty(0, np.int64)
        for a, b in zip(first, np.concatenate([first[1:], [len(line)]])):
            hit = np.flatnonzero(tags[a:b])
            if len(hit):
                lo = max(a, a + hit[0] - int(rng.integers(0, params.window // 2)))
                hi = min(b, max(a + hit[-1] + 1, lo + params.window))
                found.append((rows[lo:hi], tags[lo:hi]))
            else:
                lo = a if b - a <= params.window else int(rng.integers(a, b - params.window))
                plain.append((rows[lo : lo + min(params.window, b - a)], tags[lo : lo + min(params.window, b - a)]))
    pick = lambda x, n: [x[i] for i in rng.permutation(len(x))[:n]]
    found, plain = pick(found, params.lines), pick(plain, params.lines)
    before = list(_SIZES).index("before")
    variants = []
    for rows, tags in found:
        other = rows.copy()
        other[:, before] = _FIRST["before"] + rng.integers(0, WORD_ROWS, len(rows))
        variants.append((other, tags))
    return found + variants + plain if found else []


def _log_sum(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis, keepdims=True))).squeeze(axis)


def fit(texts: list[str], params: SecretParams) -> SecretModel:
    """Maximum likelihood by Adam, with the gradient from forward and backward sums."""
    never = -1e4
    model = SecretModel(np.zeros((N_FEATURES, 3), np.float32), np.zeros((3, 3)), np.zeros(3))
    allowed, allowed_start = np.zeros((3, 3)), np.zeros(3)
    allowed[OUT, INSIDE], allowed_start[INSIDE] = never, never
    material = _training_lines(texts, params)
    if not material:
        model.weights[_FIRST["bias"], 1:] = never
        model.moves, model.start = model.moves + allowed, model.start + allowed_start
        return model
    rng = np.random.default_rng(params.seed)
    values = {"w": np.zeros((N_FEATURES, 3)), "m": np.zeros((3, 3)), "s": np.zeros(3)}
    first = {k: np.zeros_like(v) for k, v in values.items()}
    second = {k: np.zeros_like(v) for k, v in values.items()}
    step = 0
    for _ in range(params.epochs):
        for batch in np.array_split(rng.permutation(len(material)), max(1, len(material) // params.batch)):
            step += 1
            lengths = np.array([len(material[i][1]) for i in batch])
            steps = int(lengths.max())
            rows = np.zeros((len(batch), steps, len(_SIZES)), np.int64)
            tags = np.zeros((len(batch), steps), np.int64)
            for b, i in enumerate(batch):
                rows[b, : lengths[b]], tags[b, : lengths[b]] = material[i]
            live = np.arange(steps) < lengths[:, None]
            e = values["w"][rows].sum(2)
            moves, start = values["m"] + allowed, values["s"] + allowed_start
            forward = np.zeros_like(e)
            forward[:, 0] = e[:, 0] + start
            for t in range(1, steps):
                forward[:, t] = np.where(live[:, t, None], _log_sum(forward[:, t - 1][:, :, None] + moves[None], 1) + e[:, t], forward[:, t - 1])
            z = _log_sum(forward[:, -1], 1)
            backward = np.zeros_like(e)
            for t in range(steps - 2, -1, -1):
                backward[:, t] = np.where(live[:, t + 1, None], _log_sum(moves[None] + (e[:, t + 1] + backward[:, t + 1])[:, None, :], 2), backward[:, t + 1])
            mass = np.exp(forward + backward - z[:, None, None]) * live[:, :, None]
            ge = mass.copy()
            np.put_along_axis(ge, tags[:, :, None], np.take_along_axis(ge, tags[:, :, None], 2) - live[:, :, None], 2)
            pair = np.exp(forward[:, :-1, :, None] + moves + (e + backward)[:, 1:, None, :] - z[:, None, None, None]) * live[:, 1:, None, None]
            gm = pair.sum((0, 1))
            np.add.at(gm, (tags[:, :-1][live[:, 1:]], tags[:, 1:][live[:, 1:]]), -1)
            flat, g = rows[live], ge[live]
            grad = {"w": np.stack([np.bincount(flat.ravel(), np.repeat(g[:, c], flat.shape[1]), N_FEATURES) for c in range(3)], 1) / len(batch), "m": gm / len(batch), "s": ge[:, 0].sum(0) / len(batch)}
            for k, v in values.items():
                d = grad[k] + params.l2 * v
                first[k] = 0.9 * first[k] + 0.1 * d
                second[k] = 0.99 * second[k] + 0.01 * d * d
                v -= params.rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-6)
    return SecretModel(values["w"].astype(np.float32), values["m"] + allowed, values["s"] + allowed_start)


def fit_secrets(documents: DataFrame, params: SecretParams = SecretParams()) -> SecretModel:
    """Half of the sample's bound is for texts with a base match, which one scan of all texts finds; half for others."""
    short = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("length(text) >= 1")

    def cut(batches):
        for rows, data, offsets in blocks(batches):
            ids, texts = rows.column(0).to_pylist(), rows.column(1).to_pylist()
            long_ = [i for i, t in enumerate(texts) if len(t) > params.sample_chars]
            first = {}
            for s in base_spans(data, offsets) if long_ else []:
                first.setdefault(s[0], int(s[2]))
            for i in long_:
                begin = int(offsets[i])
                at = len(data[begin : first[i]].tobytes().decode("utf-8", "replace")) if i in first else ((ids[i] or 0) * 2654435761) % len(texts[i])
                at = max(0, min(at - 200, len(texts[i]) - params.sample_chars))
                texts[i] = texts[i][at : at + params.sample_chars]
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    def matched(batches):
        for rows, data, offsets in blocks(batches):
            held = np.zeros(rows.num_rows, bool)
            held[[s[0] for s in base_spans(data, offsets)]] = True
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(held)], names=["doc_id", "held"])

    marks = settle(short.mapInArrow(matched, "doc_id long, held boolean").groupBy("doc_id").agg(F.max("held").alias("held")), "secret-marks")
    some = lambda w: marks.where(w).select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(max(1, params.sample_rows // 2))
    chosen = short.join(F.broadcast(some("held").union(some("NOT held"))), "doc_id").select("doc_id", "text")
    rows = chosen.mapInArrow(cut, "doc_id long, text string").groupBy("doc_id").agg(F.min("text").alias("text")).collect()
    discard(marks)
    return releasing(fit)([r[1] for r in sorted(rows)], params)


def scan_block(data: np.ndarray, offsets: np.ndarray, model: SecretModel, params: SecretParams):
    base = base_spans(data, offsets)
    return base, sorted(base + added_spans(data, offsets, base, model, params), key=lambda s: (s[0], s[2], s[1]))


def scan_secrets(documents: DataFrame, model: SecretModel, params: SecretParams = SecretParams()) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_crf."""
    shipped = documents.sparkSession.sparkContext.broadcast(model)

    def spelled(spans, n_docs, point, offsets):
        out = [""] * n_docs
        for d, kind, a, b, _ in spans:
            at = point[offsets[d]]
            out[d] += f"{',' if out[d] else ''}{KINDS[kind]}:{point[a] - at}:{point[b] - at}"
        return out

    def scan(batches):
        for rows, data, offsets in blocks(batches):
            n = rows.num_rows
            base, every = scan_block(data, offsets, shipped.value, params)
            point = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
            count = np.zeros((4, n), np.int64)
            for s in every:
                count[s[1], s[0]] += 1
            digests = [hashlib.sha256(x.encode()).hexdigest() for x in spelled(base, n, point, offsets)]
            yield pa.RecordBatch.from_arrays([rows.column(0), *(pa.array(count[k]) for k in range(3)), pa.array(digests), pa.array(spelled(every, n, point, offsets)), pa.array(count[3])], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_crf"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(scan, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_crf long")


def redact_secrets(documents: DataFrame, model: SecretModel, params: SecretParams = SecretParams(), mask: str = "[SECRET]") -> DataFrame:
    """The rows of `documents` with every span replaced by the mask; n_chars, where there is one, is set to the new length."""
    shipped = documents.sparkSession.sparkContext.broadcast(model)
    schema = documents.schema
    names = documents.columns
    at = names.index("text")

    def redact(batches):
        for rows, data, offsets in blocks(batches):
            _, every = scan_block(data, offsets, shipped.value, params)
            if not every:
                yield rows
                continue
            texts = rows.column(at).to_pylist()
            spans: dict[int, list] = {}
            for d, _, a, b, _ in every:
                own = spans.setdefault(d, [])
                if own and a <= own[-1][1]:
                    own[-1][1] = max(own[-1][1], b)
                else:
                    own.append([a, b])
            lengths = rows.column(names.index("n_chars")).to_pylist() if "n_chars" in names else None
            for d, own in spans.items():
                out, last = [], int(offsets[d])
                for a, b in own:
                    out += [data[last:a].tobytes(), mask.encode()]
                    last = b
                texts[d] = b"".join([*out, data[last : int(offsets[d + 1])].tobytes()]).decode("utf-8", "replace")
                if lengths is not None and lengths[d] is not None:
                    lengths[d] = len(texts[d])
            columns = list(rows.columns)
            columns[at] = pa.array(texts, rows.schema.field(at).type)
            if lengths is not None:
                j = names.index("n_chars")
                columns[j] = pa.array(lengths, rows.schema.field(j).type)
            yield pa.RecordBatch.from_arrays(columns, schema=rows.schema)

    return documents.mapInArrow(redact, schema)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return scan_secrets(documents, fit_secrets(documents))
