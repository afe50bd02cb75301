"""Language-model scoring with a weighted backoff automaton learned from the whole corpus.

States are the empty history and every history of up to order - 1 tokens that training has seen.  An arc of a state
carries the log probability of a token seen after it and leads to the state of the longest known history that ends in
that token; a state's failure arc leads to its shorter history and carries the backoff weight mu / (count + mu).
Probabilities are Dirichlet-smoothed at each order over the order below, down to (c + 1) / (N + V + 1), so an unseen
token is the product of the backoff weights on the way and the probability at the state that knows it.  A text is
one left-to-right traversal that carries its state and adds up weights; texts, cut into stretches, go side by
side, and a stretch first reads the order - 1 tokens before it, which fix the state it would have been in.

The corpus's counts are not cut, capped or sampled, and neither counts nor automaton ever meet in one place:
texts are packed into blocks of a few MB; a block sends each n-gram that it holds once, with its training count,
to the n-gram's key range (ranges that it has nothing for get no row); a key range adds up and answers every block in
the order of its questions (so an answer is counts alone); a block then builds the part of the automaton that its
texts can reach and traverses it.  Hot n-grams come once a block.  N and V are summed over the key ranges.
Tokens and pairs are asked about first, longer n-grams by a round each: where either shorter n-gram inside one occurs in
no other block, neither does it, so its count is the block's own and no question is sent.

Defined results: a null text is the empty text, whose one token is the end; with no training rows c, N and V are
0 and every token costs log10(1) = 0.  Sums of logarithms are taken in whole 1e-9, so that they do not depend
on the order.  Rows of equal id are scored each.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import new_path, settle, table
from .textkit import U64, crc_mod, lower_ascii, mix, release, releasing, segment_hash, text_arrays, words

QUANTUM = 1e9
END_TOKEN = U64(0xE4D0E4D0E4D0E4D1)
START_TOKEN = U64(0x57A9757A9757A975)


@dataclass(frozen=True)
class LmParams:
    order: int = 3
    mu: float = 5.0
    block_bytes: int = 4 << 20
    range_bytes: int = 24 << 20
    stretch: int = 256  #: tokens that a step-by-step traversal reads of a text before the next stretch of it begins


def token_stream(data: np.ndarray, offsets: np.ndarray):
    """(tokens, doc): a start, the words' hashes and an end for each text."""
    n_docs = len(offsets) - 1
    low = lower_ascii(data)
    seg = words(low, offsets)
    per = seg.per_doc()
    first = np.concatenate([[0], np.cumsum(per + 2)])
    out = np.empty(first[-1], np.uint64)
    out[first[:-1]] = START_TOKEN
    out[first[1:] - 1] = END_TOKEN
    before = np.concatenate([[0], np.cumsum(per)])[:-1]
    out[np.arange(len(seg)) + (first[:-1] - before)[seg.doc] + 1] = segment_hash(low, seg)
    return out, np.repeat(np.arange(n_docs), per + 2)


def ngram_keys(tokens: np.ndarray, doc: np.ndarray, order: int) -> list[np.ndarray]:
    """For n = 1..order the key of the n-gram that ends at each token; 0 where the text has no n tokens there.

    The two low bits of a key hold n - 1.  A start symbol alone is no n-gram: its history count is that of ends.
    """
    keys, h = [], np.full(len(tokens), 78, np.uint64)
    for n in range(1, order + 1):
        key = np.zeros(len(tokens), np.uint64)
        if len(tokens) >= n:
            # h: of the n tokens that start at each place, grown by a token each time
            h = mix(h[: len(tokens) - n + 1] * U64(0x9DDFEA08EB382D69) + tokens[n - 1 :])
            inside = doc[n - 1 :] == doc[: len(doc) - n + 1]
            key[n - 1 :] = np.where(inside, (h & ~U64(3)) | U64(n - 1), U64(0))
        key[tokens == START_TOKEN] = 0
        keys.append(key)
    return keys


def sorting(keys: np.ndarray) -> np.ndarray:
    """A stable argsort of hashes: numbers are sorted, several times faster than their places, with the place in the low bits."""
    bits = U64(len(keys).bit_length())
    places = np.sort((keys >> bits << bits) | np.arange(len(keys), dtype=np.uint64))
    places &= (U64(1) << bits) - U64(1)
    by = places.view(np.int64)
    ordered = keys[by]
    # keys that differ in the low bits alone may stand in the wrong order
    return np.argsort(keys, kind="stable") if (ordered[1:] < ordered[:-1]).any() else by


class Grams:
    """The distinct n-grams of one order in a block: keys, a place of each, its number by place (-1: none), counts.

    `alone` marks places whose n-gram is known to stand nowhere else in the block; the others come first, sorted by key,
    and those follow in the order of the text.
    """

    def __init__(self, key: np.ndarray, held: np.ndarray, alone: np.ndarray | None = None):
        at = np.flatnonzero(key if alone is None else (key > 0) & ~alone)
        at = at[sorting(key[at])]
        ordered = key[at]
        new = np.ones(len(at), bool)
        new[1:] = ordered[1:] != ordered[:-1]
        first = np.flatnonzero(new)
        self.key, self.place = ordered[first], at[first]
        self.number = np.full(len(key), -1, np.int32)
        self.number[at] = np.cumsum(new, dtype=np.int32) - 1
        taught = np.concatenate([[0], np.cumsum(~held[at])])
        self.size = np.diff(np.append(first, len(at)))  #: places of each n-gram
        self.own = np.diff(taught[np.append(first, len(at))])
        if alone is not None:
            rest = np.flatnonzero(alone & (key > 0))
            self.number[rest] = np.arange(len(first), len(first) + len(rest), dtype=np.int32)
            self.key, self.place = np.concatenate([self.key, key[rest]]), np.concatenate([self.place, rest])
            self.size, self.own = np.concatenate([self.size, np.ones(len(rest), np.int64)]), np.concatenate([self.own, ~held[rest]])
        self.total, self.shared = self.own.copy(), np.zeros(len(self.key), bool)


class Counted:
    """A block's n-grams with what the corpus has answered about them, round by round.

    `asked` and `own` are the sorted n-grams that the round asks about, and their training counts in the block.
    """

    def __init__(self, rows: pa.Table, order: int):
        data, offsets = text_arrays(rows["text"].combine_chunks())
        self.tokens, self.doc = token_stream(data, offsets)
        self.keys = ngram_keys(self.tokens, self.doc, order)
        self.held = rows["held_out"].to_numpy()[self.doc]
        self.order = order
        self.grams = [Grams(key, self.held) for key in self.keys[:2]]
        self.ask([np.ones(len(g.key), bool) for g in self.grams])

    def ask(self, which: list[np.ndarray]) -> None:
        """The last orders, one mask each, and of those the n-grams that the masks name."""
        self.which = list(zip(self.grams[-len(which) :], which, strict=True))
        keys = np.concatenate([g.key[w] for g, w in self.which])
        self.by = sorting(keys)
        self.asked, self.own = keys[self.by], np.concatenate([g.own[w] for g, w in self.which])[self.by]

    def hear(self, found: np.ndarray) -> None:
        """Takes the answers to what is asked in this round; then `asked` is what the next one asks.

        An answer is twice the training count, and one more where another block holds the n-gram too, in training or not.
        """
        answers = np.empty(len(found), np.int64)
        answers[self.by] = found
        at = 0
        for g, w in self.which:
            mine = answers[at : at + w.sum()]
            g.total[w], g.shared[w] = mine >> 1, (mine & 1) > 0
            at += len(mine)
        if len(self.grams) == self.order:
            return
        # an n-gram is in another block, or at another place of this one, only where both (n - 1)-grams inside it are
        before, key = self.grams[-1], self.keys[len(self.grams)]
        elsewhere = np.append(before.shared, False)[before.number]
        once = np.append(before.size == 1, False)[before.number]
        alone = once.copy()
        alone[1:] |= once[:-1]
        g = Grams(key, self.held, alone)
        self.grams.append(g)
        self.ask([elsewhere[g.place] & elsewhere[g.place - 1]])


def packed(counts: np.ndarray) -> bytes:
    """Counts in the narrowest unsigned type that holds them, its width first."""
    top = int(counts.max()) if len(counts) else 0
    width = next(w for w in (1, 2, 4, 8) if top < 1 << (8 * w))
    return bytes([width]) + counts.astype(f"u{width}").tobytes()


def unpacked(blob: bytes) -> np.ndarray:
    return np.frombuffer(blob, f"u{blob[0]}", offset=1).astype(np.int64)


def packed_keys(keys: np.ndarray) -> bytes:
    """Sorted keys as the first one and the steps between them, in as many bytes as the largest step needs."""
    if not len(keys):
        return b""
    steps = np.diff(keys)
    top = int(steps.max()) if len(steps) else 0
    width = next(w for w in range(1, 9) if top < 1 << (8 * w))
    return bytes([width]) + keys[:1].tobytes() + steps.view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def unpacked_keys(blob: bytes) -> np.ndarray:
    if not blob:
        return np.empty(0, np.uint64)
    steps = np.frombuffer(blob, np.uint8, offset=9).reshape(-1, blob[0])
    wide = np.zeros((len(steps) + 1, 8), np.uint8)
    wide[0] = np.frombuffer(blob, np.uint8, 8, 1)
    wide[1:, : blob[0]] = steps
    return np.cumsum(wide.view(np.uint64).ravel(), dtype=np.uint64)


def cuts(keys: np.ndarray, ranges: int) -> np.ndarray:
    """Where in the sorted keys each of the equal ranges of their upper 32 bits begins and ends."""
    edges = np.array([(i << 32) // ranges for i in range(1, ranges)], np.uint64) << U64(32)
    return np.concatenate([[0], np.searchsorted(keys, edges), [len(keys)]]).astype(np.int64)


class BackoffAutomaton:
    """The states, arcs and failure arcs that a block's n-grams with training counts span.

    State 0 is the empty history; behind it stand the tokens, the start and the longer n-grams of fewer than `order`
    tokens, each at its number.  The n-grams seen in training are the arcs, and the states among them those that can be reached.
    An arc of a state other than the empty one is found by the place of its token: of the n-grams that end there it
    is the one that is a token longer than the state's history.
    """

    def __init__(self, tokens: np.ndarray, grams: list[Grams], total: int, kinds: int, params: LmParams):
        self.order, self.total, self.kinds = len(grams), total, kinds
        mu = params.mu
        self.unseen = np.log10(1 / (total + (kinds + 1)))
        # the token of an arc is its number among the block's tokens, and the start symbol's is behind them
        starts = grams[0].number < 0
        self.size = len(grams[0].key) + 1
        self.token = np.where(starts, np.int32(self.size - 1), grams[0].number)
        end_key = ngram_keys(np.array([END_TOKEN]), np.zeros(1, int), 1)[0]
        ends = int(grams[0].total[grams[0].key == end_key].sum())
        # the empty history's arcs stand by token
        self.root_count = np.append(grams[0].total, 0)
        p = (self.root_count + 1) / (total + (kinds + 1))
        self.root_base = np.log10(p)
        self.root_weight, self.root_to = self.root_base, np.where(self.root_count > 0, np.arange(1, self.size + 1), 0)
        if self.order == 1:
            self.root_to = np.zeros(self.size, np.int64)
        # the start of a text is a history of its own, as often as texts end
        self.start = self.size if self.order > 1 and ends and starts.any() else 0
        state_count = np.append(grams[0].total, ends)  # of the histories of this length, by number
        self.first = [1]  # state of each history length's number 0
        fail, counts = [np.zeros(1 + self.size, np.int32)], [np.zeros(1, np.int64), state_count]
        number, states = self.token, np.where(state_count > 0, np.arange(1, self.size + 1, dtype=np.int32), np.int32(0))
        history = states[number]  # by place: the state of the n - 1 tokens that end there, 0 where training has not seen them
        to, weights, self.arc_at, self.sources = [], [], [], []
        for n, gram in enumerate(grams[1:], 2):
            at, c = gram.place, gram.total
            base = self.first[-1] + len(state_count)
            # an arc's history and the n-gram one token shorter have been seen where the arc has; no other arc is ever taken
            p = (c + mu * p[number[at]]) / (state_count[number[at - 1]] + mu)
            weights.append(np.log10(p))
            states = np.where(c > 0, np.arange(base, base + len(c), dtype=np.int32), np.int32(0))
            # arcs are numbered as the states of their n-grams are or would be
            mine = np.append(states, 0)[gram.number]
            self.arc_at.append(mine)
            self.sources.append((history, at[c > 0]))
            if n == self.order:
                # an arc of the longest history leads to the state of what ends it one token shorter
                to.append(history[at])
                break
            to.append(states)
            fail.append(history[at])
            counts.append(c)
            self.first.append(base)
            # a place without such an n-gram has none of a longer one either
            number, state_count, history = gram.number, c, mine
        none = np.empty(0, np.int32)
        self.arcs = 1 + self.size  # number of the first arc that is not the empty history's
        self.arc_weight, self.arc_to = np.concatenate([np.empty(0), *weights]), np.concatenate([none, *to])
        self.fail, weights = np.concatenate(fail), np.concatenate(counts)
        self.fail_weight = np.where(weights > 0, np.log10(mu / (weights + mu)), 0.0)

    @property
    def arc_key(self) -> np.ndarray:
        """State and token of every arc but the empty history's, as one number."""
        none = np.empty(0, np.int64)
        return np.concatenate([none, *(state[at - 1].astype(np.int64) * self.size + self.token[at] for state, at in self.sources)])

    def arc(self, state: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Arcs of these states, none of them the empty history, for the tokens at these places; 0 where there is none."""
        at = self.arc_at[0][place]
        for first, longer in zip(self.first[1:], self.arc_at[1:], strict=True):
            at = np.where(state >= first, longer[place], at)
        return at

    def step(self, state: np.ndarray, token: np.ndarray, place: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(weight, next state) of one token from each state: failure arcs until a state has an arc for it.

        The empty history needs the token alone, other states its place.
        """
        weight, to, state = np.zeros(len(state)), np.zeros(len(state), np.int32), state.copy()
        left = np.flatnonzero(state)
        while len(left):
            at = self.arc(state[left], place[left])
            found = at > 0
            done, at = left[found], at[found] - self.arcs
            weight[done] += self.arc_weight[at]
            to[done] = self.arc_to[at]
            state[done] = -1
            left = left[~found]
            failed = state[left]
            weight[left] += self.fail_weight[failed]
            state[left] = self.fail[failed]
            left = left[state[left] > 0]
        root = np.flatnonzero(state == 0)
        own = token[root]
        weight[root] += self.root_weight[own]
        to[root] = self.root_to[own]
        return weight, to

    def traverse(self, tokens: np.ndarray, doc: np.ndarray, stretch: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(log10 base probability, log10 weight, training count) of each token; a text's start symbol has none."""
        n = len(tokens)
        weight = np.zeros(n)
        opens = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]])) if n else np.empty(0, np.int64)
        size = np.diff(np.concatenate([opens, [n]]))
        pieces = np.maximum(1, -(-(size - 1) // stretch))
        turn = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        text_open = np.repeat(opens, pieces)
        begin = text_open + 1 + turn * stretch
        end = np.minimum(begin + stretch, text_open + np.repeat(size, pieces))
        place = np.maximum(begin - (self.order - 1), text_open + 1)  # reads itself into the state before `begin`
        # the longest stretches first, so that those which go on are always the first ones
        by = np.argsort(place - end, kind="stable")
        place, begin, left = place[by], begin[by], (end - place)[by]
        state = np.where(place == text_open[by] + 1, np.int32(self.start), np.int32(0))
        live = len(left) - np.searchsorted(left[::-1], np.arange(left[0] if len(left) else 0), "right")
        for done, m in enumerate(live):
            here = place[:m] + done
            w, state = self.step(state[:m], self.token[here], here)
            if done < self.order - 1:
                own = here >= begin[:m]
                here, w = here[own], w[own]
            weight[here] = w
        return self.root_base[self.token], weight, self.root_count[self.token]


def whole_sum(values: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(doc, np.rint(values * QUANTUM), n) / QUANTUM


MOST_BUCKETS = 100_000


def packed_texts(documents: DataFrame, held_out, limit: int, size: int) -> DataFrame:
    """(block, rows): the texts in blocks of about `limit` bytes, each one compressed Arrow table.

    A block is a run of rows of one input partition and is named by that partition and its turn there.  The table is
    bucketed by block, so that answers travel to the texts and texts never travel.
    """

    def pack(batches):
        from pyspark import TaskContext

        number, turn, held, size = TaskContext.get().partitionId(), 0, [], 0
        for batch in batches:
            text = batch.column(2)
            ends = np.cumsum(pa.compute.fill_null(pa.compute.binary_length(text), 0).to_numpy(zero_copy_only=False))
            at = 0
            while at < batch.num_rows:
                before = ends[at - 1] if at else 0
                to = min(batch.num_rows, max(at + 1, int(np.searchsorted(ends, before + limit - size, "right"))))
                held.append(batch.slice(at, to - at))
                size += int(ends[to - 1] - before)
                at = to
                if size >= limit or at < batch.num_rows:
                    yield squeezed(number, turn, held)
                    turn, held, size = turn + 1, [], 0
        if held:
            yield squeezed(number, turn, held)

    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), held_out.alias("held_out"), F.col("text").cast("string").alias("text"))
    spark = documents.sparkSession
    buckets = min(MOST_BUCKETS, max(2 * spark.sparkContext.defaultParallelism, -(-size // (8 * limit))))
    name = f"vecspark_{uuid.uuid4().hex}"
    packed_rows = rows.mapInArrow(pack, "block long, rows binary")
    packed_rows.write.bucketBy(buckets, "block").option("path", new_path(spark, "blocks")).saveAsTable(name)
    return spark.table(name)


def squeezed(number: int, turn: int, held: list) -> pa.RecordBatch:
    sink = pa.BufferOutputStream()
    whole = pa.Table.from_batches(held).combine_chunks()
    with pa.ipc.new_stream(sink, whole.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(whole)
    return pa.RecordBatch.from_arrays([pa.array([number << 32 | turn], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "rows"])


def unsqueezed(blob: pa.Scalar) -> pa.Table:
    return pa.ipc.open_stream(blob.as_buffer()).read_all().combine_chunks()


def spread(keys: np.ndarray, counts: np.ndarray, block: int, ranges: int) -> dict:
    """A block's questions by key range."""
    at = cuts(keys, ranges)
    part = np.flatnonzero(np.diff(at))
    pieces = list(zip(at[part], at[part + 1], strict=True))
    return {
        "block": pa.array(np.full(len(part), block, np.int64)),
        "part": pa.array(part.astype(np.int32)),
        "keys": pa.array([packed_keys(keys[a:b]) for a, b in pieces], pa.binary()),
        "counts": pa.array([packed(counts[a:b]) for a, b in pieces], pa.binary()),
    }


def answer(group: pa.Table) -> pa.Table:
    """A key range's counts added up, for each block in the order of its questions; see `Counted.hear` for the form."""
    blobs = [unpacked_keys(x.as_py()) for x in group["keys"]]
    counts = np.concatenate([unpacked(x.as_py()) for x in group["counts"]])
    union, place = np.unique(np.concatenate(blobs), return_inverse=True)
    totals = np.bincount(place, counts, len(union)).astype(np.int64)
    single = (union & U64(3)) == 0
    at = np.concatenate([[0], np.cumsum([len(b) for b in blobs])])
    found = 2 * totals[place] + (np.bincount(place, minlength=len(union)) > 1)[place]
    first = np.arange(group.num_rows) == 0  # the range's own share of N and V stands in one row
    return pa.table(
        {
            "block": group["block"],
            "part": group["part"],
            "found": pa.array([packed(found[a:b]) for a, b in zip(at, at[1:])], pa.binary()),
            "tokens": pa.array(np.where(first, totals[single].sum(), 0)),
            "kinds": pa.array(np.where(first, (totals[single] > 0).sum(), 0)),
        }
    )


def heard(texts: pa.Table, answers: pa.Table, order: int, rounds: int) -> tuple[pa.Table, Counted]:
    rows = unsqueezed(texts["rows"][0])
    counted = Counted(rows, order)
    turn, part = answers["turn"].to_numpy(), answers["part"].to_numpy()
    by = np.lexsort((part, turn))
    for r in range(rounds):
        mine = by[turn[by] == r]
        counted.hear(np.concatenate([np.empty(0, np.int64), *(unpacked(answers["found"][int(i)].as_py()) for i in mine)]))
    return rows, counted


QUESTIONS = "block long, part int, keys binary, counts binary"
ANSWERS = "block long, part int, found binary, tokens long, kinds long"
SCORED = (("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()))


def score_corpus(documents: DataFrame, held_out, params: LmParams = LmParams()) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; held-out rows teach nothing."""
    size = documents.agg(F.sum(F.octet_length(F.col("text").cast("string")))).first()[0] or 0
    ranges = max(1, -(-size * 6 // (5 * params.range_bytes)))
    docs, order = packed_texts(documents, held_out, params.block_bytes, size), params.order

    def first_questions(batches):
        for batch in batches:
            for block, blob in zip(batch.column(0), batch.column(1), strict=True):
                counted = Counted(unsqueezed(blob), min(order, 2))
                yield pa.RecordBatch.from_pydict(spread(counted.asked, counted.own, block.as_py(), ranges))
            release()

    def more_questions(rounds: int):
        def ask(texts: pa.Table, answers: pa.Table) -> pa.Table:
            if not texts.num_rows:
                return pa.table(spread(np.empty(0, np.uint64), np.empty(0, np.int64), 0, ranges))
            _, counted = heard(texts, answers, order, rounds)
            return pa.table(spread(counted.asked, counted.own, texts["block"][0].as_py(), ranges))

        return ask

    def score(texts: pa.Table, answers: pa.Table) -> pa.Table:
        if not texts.num_rows:
            return pa.schema(SCORED).empty_table()
        rows, counted = heard(texts, answers, order, rounds)
        n, tokens, doc = rows.num_rows, counted.tokens, counted.doc
        grams = counted.grams
        del counted
        automaton = BackoffAutomaton(tokens, grams, total, kinds, params)
        del grams
        base, weight, c = automaton.traverse(tokens, doc, params.stretch)
        real = tokens != START_TOKEN
        d = doc[real]
        columns = [rows["doc_id"], rows["held_out"], np.bincount(d, minlength=n), np.bincount(d, c[real] > 0, n).astype(np.int64), np.full(n, total), whole_sum(base[real], d, n), whole_sum(weight[real], d, n)]
        return pa.table([pa.array(x) if isinstance(x, np.ndarray) else x for x in columns], schema=pa.schema(SCORED))

    rounds, answers = max(1, order - 1), None
    for turn in range(rounds):
        if turn == 0:
            asked = docs.mapInArrow(first_questions, QUESTIONS)
        else:
            asked = docs.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(releasing(more_questions(turn)), QUESTIONS)
        found = settle(asked.groupBy("part").applyInArrow(releasing(answer), ANSWERS), "answers")
        if turn == 0:
            total, kinds = (int(x or 0) for x in found.agg(F.sum("tokens"), F.sum("kinds")).first())
        own = found.select("block", F.lit(turn).alias("turn"), "part", "found")
        answers = own if answers is None else answers.union(own)
    return docs.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(releasing(score), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op10_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_corpus(table(spark, sf_dir, "documents"), crc_mod(F.col("doc_id"), 7) == 2)


#: crc32 in SQL: eight shift steps for each byte of the id's decimal text.
CRC_SQL = """(list_reduce(
  list_prepend(4294967295::BIGINT, list_transform(string_split(CAST(doc_id AS VARCHAR), ''), lambda ch: CAST(ascii(ch) AS BIGINT))),
  lambda crc, b: list_reduce(list_prepend(xor(crc, b), [0::BIGINT, 0, 0, 0, 0, 0, 0, 0]), lambda x, i: CASE WHEN x & 1 = 1 THEN xor(x >> 1, 3988292384::BIGINT) ELSE x >> 1 END))
)"""

OP10_SQL = f"""
WITH docs AS (
  SELECT doc_id, xor({CRC_SQL}, 4294967295::BIGINT) % 7 = 2 AS held_out,
    list_concat(['0'], list_concat(list_transform(list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \\t-\\r]+'), lambda w: w <> ''), lambda w: '1:' || w), ['2'])) AS words
  FROM documents
), toks AS (
  SELECT doc_id, held_out, unnest(words) AS w, unnest(list_concat([NULL], words[:-2])) AS h1, unnest(list_concat([NULL, NULL], words[:-3])) AS h0, unnest(range(len(words))) AS i FROM docs
), seen AS (
  SELECT doc_id, held_out, w, h1, h0 || ' ' || h1 AS h2 FROM toks WHERE i > 0
), uni AS (
  SELECT w, count(*) AS c FROM seen WHERE NOT held_out GROUP BY 1
), total AS (
  SELECT CAST(coalesce(sum(c), 0) AS BIGINT) AS n, count(*) AS v FROM uni
), pair AS (
  SELECT h1, w, count(*) AS c FROM seen WHERE NOT held_out GROUP BY 1, 2
), three AS (
  SELECT h2, w, count(*) AS c FROM seen WHERE NOT held_out AND h2 IS NOT NULL GROUP BY 1, 2
), one_back AS (
  SELECT CASE WHEN w = '2' THEN '0' ELSE w END AS h1, c FROM uni
), two_back AS (
  SELECT h1 || ' ' || w AS h2, c FROM pair
), found AS (
  SELECT s.doc_id, s.held_out, coalesce(u.c, 0) AS c, t.n, (coalesce(u.c, 0) + 1)::DOUBLE / (t.n + t.v + 1)::DOUBLE AS p1,
    coalesce(p.c, 0) AS c2, coalesce(x.c, 0) AS n1, coalesce(q.c, 0) AS c3, coalesce(y.c, 0) AS n2
  FROM seen s CROSS JOIN total t LEFT JOIN uni u USING (w) LEFT JOIN pair p ON p.h1 = s.h1 AND p.w = s.w LEFT JOIN one_back x ON x.h1 = s.h1
    LEFT JOIN three q ON q.h2 = s.h2 AND q.w = s.w LEFT JOIN two_back y ON y.h2 = s.h2
), arcs AS (
  SELECT *, (c2 + 5.0::DOUBLE * p1) / (n1 + 5.0::DOUBLE) AS p2, log10(5.0::DOUBLE / (n1 + 5.0::DOUBLE)) AS back1, log10(5.0::DOUBLE / (n2 + 5.0::DOUBLE)) AS back2 FROM found
), walked AS (
  SELECT *, CASE WHEN c3 > 0 THEN log10((c3 + 5.0::DOUBLE * p2) / (n2 + 5.0::DOUBLE))
    WHEN c2 > 0 THEN CASE WHEN n2 > 0 THEN back2 ELSE 0 END + log10(p2)
    ELSE CASE WHEN n2 > 0 THEN back2 ELSE 0 END + CASE WHEN n1 > 0 THEN back1 ELSE 0 END + log10(p1) END AS weight FROM arcs
)
SELECT doc_id, held_out, count(*) AS n_tokens, count(*) FILTER (c > 0) AS n_known, n AS train_tokens,
  CAST(sum(CAST(round_even(log10(p1) * 1e9::DOUBLE, 0) AS BIGINT)) AS DOUBLE) / 1e9::DOUBLE AS base_score,
  CAST(sum(CAST(round_even(weight * 1e9::DOUBLE, 0) AS BIGINT)) AS DOUBLE) / 1e9::DOUBLE AS score
FROM walked GROUP BY doc_id, held_out, n
"""
