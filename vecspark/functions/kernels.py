"""Numpy kernels.  Pure functions of arrays; nothing here knows Spark."""

from __future__ import annotations

from dataclasses import dataclass, field
from time import perf_counter

import numpy as np


@dataclass(frozen=True)
class BatchPlan:
    """Rows of data and of centroids that one product takes; the buffer holds their product."""

    x_rows: int = 4096
    y_rows: int = 1024

    @classmethod
    def large(cls) -> BatchPlan:
        return cls(65_536, 4096)

    def buffer_bytes(self, width: int = 4) -> int:
        return self.x_rows * self.y_rows * width


#: What a task's seconds are counted for.
PHASES = ("norms", "product", "first_threshold", "test", "refinement", "sums")


@dataclass
class Work:
    """What an assignment did: multiply-adds in products and in refinement, pairs tested and rejected by stage, seconds by phase."""

    rows: int = 0
    head_mul_adds: int = 0
    tail_mul_adds: int = 0
    tested: int = 0
    rejected_head: int = 0
    block_tested: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    block_rejected: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    secs: np.ndarray = field(default_factory=lambda: np.zeros(len(PHASES)))
    since: float = 0.0

    def lap(self, phase: str | None = None) -> None:
        """The time since the last lap goes to `phase`; without one a lap begins."""
        now = perf_counter()
        if phase:
            self.secs[PHASES.index(phase)] += now - self.since
        self.since = now

    def block(self, i: int, tested: int, rejected: int) -> None:
        if len(self.block_tested) <= i:
            grow = i + 1 - len(self.block_tested)
            self.block_tested = np.pad(self.block_tested, (0, grow))
            self.block_rejected = np.pad(self.block_rejected, (0, grow))
        self.block_tested[i] += tested
        self.block_rejected[i] += rejected


def sq_norms(x: np.ndarray) -> np.ndarray:
    return np.einsum("ij,ij->i", x, x)


def sq_dists(x, y, x_sq=None, y_sq=None) -> np.ndarray:
    """Squared distances through one matrix product; rounding below zero is clamped."""
    out = x @ y.T
    out *= -2
    out += (sq_norms(x) if x_sq is None else x_sq)[:, None]
    out += (sq_norms(y) if y_sq is None else y_sq)[None, :]
    return np.maximum(out, 0, out=out)


def cosines(x, y) -> np.ndarray:
    """Cosines of all pairs; NaN where a vector is all zero."""
    norms = np.sqrt(sq_norms(x)[:, None] * sq_norms(y)[None, :])
    with np.errstate(invalid="ignore", divide="ignore"):
        return (x @ y.T) / norms


def threshold(b, d: int, tau, epsilon0: float = 2.1):
    """The squared partial distance over b of d rotated dimensions above which a pair is given up.

    The adaptive-sampling test in squared form: tau * b/d * (1 + epsilon0/sqrt(b))**2.  At b = d the exact
    distance is known and the limit is tau; an infinite epsilon0 gives no pair up before that.
    """
    if b >= d:
        return tau
    if np.isinf(epsilon0):
        return np.full_like(tau, np.inf) if isinstance(tau, np.ndarray) else np.inf
    return tau * (b / d) * (1 + epsilon0 / np.sqrt(b)) ** 2


@dataclass
class CentroidBlocks:
    """Centroids as a head and, behind it, contiguous blocks of `step` dimensions (the last may be shorter)."""

    full: np.ndarray
    d1: int
    step: int
    layout: str = "blocks"

    def __post_init__(self):
        self.k, self.d = self.full.shape
        self.d1 = min(self.d, max(1, self.d1))
        self.head = np.ascontiguousarray(self.full[:, : self.d1])
        self.head_sq, self.full_sq = sq_norms(self.head), sq_norms(self.full)
        self.tail = np.ascontiguousarray(self.full[:, self.d1 :])
        self.tail_sq = sq_norms(self.tail)
        self.cuts = [*range(self.d1, self.d, self.step), self.d]
        pairs = list(zip(self.cuts[:-1], self.cuts[1:], strict=True))
        self.blocks = [np.ascontiguousarray(self.full[:, a:b]) if self.layout == "blocks" else self.full[:, a:b] for a, b in pairs]

    def __reduce__(self):
        """One copy travels; head, tail and blocks are cut where it arrives."""
        return CentroidBlocks, (self.full, self.d1, self.step, self.layout)


def assign_full(x: np.ndarray, y: CentroidBlocks | np.ndarray, plan: BatchPlan = BatchPlan(), work: Work | None = None):
    """(nearest centroid, squared distance), ties to the lower number; the running best is kept across slices of y."""
    work = work or Work()
    work.lap()
    full = y.full if isinstance(y, CentroidBlocks) else y
    y_sq = y.full_sq if isinstance(y, CentroidBlocks) else sq_norms(full)
    cid, dist = np.zeros(len(x), np.int64), np.full(len(x), np.inf, x.dtype)
    folded_y = np.ascontiguousarray(np.concatenate([-2 * full, y_sq[:, None]], 1).T)
    for at in range(0, len(x), plan.x_rows):
        part = slice(at, at + plan.x_rows)
        xb, xn = folded(x[part]), sq_norms(x[part])
        work.lap("norms")
        for lo in range(0, len(full), plan.y_rows):
            d = xb @ folded_y[:, lo : lo + plan.y_rows]
            work.lap("product")
            j = d.argmin(1)
            best = np.maximum(d[np.arange(len(xb)), j] + xn, 0)
            closer = best < dist[part]
            cid[part] = np.where(closer, j + lo, cid[part])
            dist[part] = np.where(closer, best, dist[part])
            work.lap("test")
    work.rows += len(x)
    work.head_mul_adds += len(x) * full.size
    return cid, dist


def refine(x_blocks, blocks: CentroidBlocks, rows, cols, partial, tau, epsilon0, progressive, work: Work | None, pair_limit: int = 1 << 15):
    """The pairs (rows, cols) whose exact distance was reached, with it; the others were given up on the way.

    `x_blocks(i)` is the batch's i-th block of dimensions, contiguous like the centroids' one, so a pair costs two short
    copies; pairs go in pieces that fit a cache and are compacted after each block.  A pair that has been given up
    never comes back, whatever its partial distance.
    """
    cuts = blocks.cuts if progressive else [blocks.d1, blocks.d]
    for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
        if not len(rows):
            break
        x, own = x_blocks(a, b), blocks.blocks[i] if progressive else blocks.tail
        limit, tested, kept = threshold(b, blocks.d, tau, epsilon0), len(rows), []
        for at in range(0, tested, pair_limit):
            part = slice(at, at + pair_limit)
            diff = x.take(rows[part], 0)
            diff -= own.take(cols[part], 0)
            partial[part] += np.einsum("ij,ij->i", diff, diff)
            kept.append(np.flatnonzero(partial[part] <= limit.take(rows[part])) + at)
        keep = np.concatenate(kept)
        rows, cols, partial = rows[keep], cols[keep], partial[keep]
        if work is not None:
            work.tail_mul_adds += tested * (b - a)
            work.block(i, tested, tested - len(rows))
    return rows, cols, partial


def refine_grouped(tail, y: CentroidBlocks, lo: int, d, keep, best, tau, work: Work | None) -> None:
    """Exact distances by small products: rows of one nearest centroid share most of their candidates.

    Each such group takes one product over the tail with the union of its rows' candidates.  It multiplies more
    than going pair by pair, but gathers nothing.  best and tau are updated.
    """
    tail_sq = sq_norms(tail)
    order = np.argsort(best, kind="stable")
    first = np.flatnonzero(np.concatenate([[True], best[order][1:] != best[order][:-1]]))
    for a, b in zip(first, np.concatenate([first[1:], [len(order)]]), strict=True):
        rows = order[a:b]
        cols = np.flatnonzero(keep[rows].any(0))
        if not len(cols):
            continue
        exact = sq_dists(tail[rows], y.tail[lo + cols], tail_sq[rows], y.tail_sq[lo + cols])
        exact += d[rows[:, None], cols]
        if work is not None:
            work.tail_mul_adds += len(rows) * len(cols) * tail.shape[1]
        j = exact.argmin(1)
        value, c = exact[np.arange(len(rows)), j], cols[j] + lo
        closer = (value < tau[rows]) | ((value == tau[rows]) & (c < best[rows]))
        best[rows[closer]], tau[rows[closer]] = c[closer], value[closer]


DENSE_SHARE = 1 / 12  #: of a slice's pairs, beyond which "auto" takes one product


def folded(x: np.ndarray) -> np.ndarray:
    """x and a column of ones: with centroids as (-2 y, |y|^2) one product gives distances less the rows' own norms."""
    out = np.ones((len(x), x.shape[1] + 1), x.dtype)
    out[:, :-1] = x
    return out


def assign_pruned(x, y: CentroidBlocks, prev=None, epsilon0: float = 2.1, progressive: bool = True, seed_mode: str = "head_nearest", plan: BatchPlan = BatchPlan(), work: Work | None = None, refinement: str = "auto"):
    """Nearest centroids by a head product for all pairs and block-wise refinement of those that the test leaves.

    seed_mode names the first threshold: "previous" (distance to the centroid `prev`), "head_nearest" (exact
    distance to the centroid that is nearest over the head; needs no state) or "first_batch" (a full product with
    the first slice of centroids).  refinement names how the pairs that the head leaves are decided: "pairs" (each on
    its own, block by block), "auto" (so too, but by a product over the tail where the head leaves many of a slice's
    pairs) or "grouped" (small products, see `refine_grouped`).
    """
    if y.d1 >= y.d:
        return assign_full(x, y, plan, work)
    work = work or Work()
    work.lap()
    n = len(x)
    cid, dist = np.zeros(n, np.int64), np.full(n, np.inf, x.dtype)
    head_y = np.ascontiguousarray(np.concatenate([-2 * y.head, y.head_sq[:, None]], 1).T)
    tail_y = np.ascontiguousarray(np.concatenate([-2 * y.tail, y.tail_sq[:, None]], 1).T) if refinement == "auto" else None
    for at in range(0, n, plan.x_rows):
        xb = x[at : at + plan.x_rows]
        m = len(xb)
        every = np.arange(m)
        head = folded(xb[:, : y.d1])
        head_sq, row_sq = sq_norms(xb[:, : y.d1]), sq_norms(xb)
        work.lap("norms")
        cut: dict[int, np.ndarray] = {}

        def x_blocks(a: int, b: int, xb=xb, cut=cut) -> np.ndarray:
            if a not in cut:
                cut[a] = np.ascontiguousarray(xb[:, a:b])
            return cut[a]

        best, tau = np.zeros(m, np.int64), np.full(m, np.inf, x.dtype)
        if seed_mode == "previous":
            best = np.asarray(prev[at : at + plan.x_rows], np.int64).copy()
            diff = xb - y.full.take(best, 0)
            tau = sq_norms(diff)
            work.tail_mul_adds += diff.size
            work.lap("first_threshold")
        for lo in range(0, y.k, plan.y_rows):
            hi = min(y.k, lo + plan.y_rows)
            if seed_mode == "first_batch" and lo == 0:
                d = sq_dists(xb, y.full[lo:hi], None, y.full_sq[lo:hi])
                best = d.argmin(1)
                tau = d[every, best]
                work.head_mul_adds += m * (hi - lo) * y.d
                work.lap("first_threshold")
                continue
            d = head @ head_y[:, lo:hi]  # less head_sq
            work.head_mul_adds += m * (hi - lo) * y.d1
            work.lap("product")
            if seed_mode == "head_nearest":
                j = d.argmin(1) + lo
                diff = xb - y.full.take(j, 0)
                exact = sq_norms(diff)
                closer = (exact < tau) | ((exact == tau) & (j < best))
                best, tau = np.where(closer, j, best), np.where(closer, exact, tau)
                d[every, j - lo] = np.inf  # decided already
                work.tail_mul_adds += diff.size
            elif seed_mode == "previous":
                own = np.flatnonzero((best >= lo) & (best < hi))
                d[own, best[own] - lo] = np.inf
            work.lap("first_threshold")
            keep = d <= (threshold(y.d1, y.d, tau, epsilon0) - head_sq)[:, None]
            work.tested += d.size
            work.rejected_head += int(d.size - np.count_nonzero(keep))
            work.lap("test")
            if refinement == "grouped":
                d += head_sq[:, None]
                refine_grouped(xb[:, y.d1 :], y, lo, d, keep, best, tau, work)
                work.lap("refinement")
                continue
            flat = np.flatnonzero(keep)
            if not len(flat):
                continue
            if refinement == "auto" and len(flat) > DENSE_SHARE * d.size:
                # so many pairs are left that one product over the tail costs less than going pair by pair
                d += folded(xb[:, y.d1 :]) @ tail_y[:, lo:hi]
                d[~keep] = np.inf
                j = d.argmin(1)
                exact = np.maximum(d[every, j] + row_sq, 0)
                closer = (exact < tau) | ((exact == tau) & (j + lo < best))
                best, tau = np.where(closer, j + lo, best), np.where(closer, exact, tau)
                work.tail_mul_adds += m * (hi - lo) * (y.d - y.d1)
                work.lap("refinement")
                continue
            r = flat // (hi - lo)
            c = flat - r * (hi - lo)
            partial = np.maximum(d.ravel()[flat] + head_sq[r], 0)
            work.lap("test")
            r, c, exact = refine(x_blocks, y, r, c + lo, partial, tau, epsilon0, progressive, work)
            work.lap("refinement")
            if not len(r):
                continue
            order = np.lexsort((c, exact, r))
            first = order[np.concatenate([[True], r[order][1:] != r[order][:-1]])]
            r, c, exact = r[first], c[first], exact[first]
            closer = (exact < tau[r]) | ((exact == tau[r]) & (c < best[r]))
            best[r[closer]], tau[r[closer]] = c[closer], exact[closer]
        cid[at : at + m], dist[at : at + m] = best, tau
    work.rows += n
    return cid, dist


def centroid_sums(x: np.ndarray, cid: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(centroids present, counts, sums in double) of a batch."""
    order = np.argsort(cid, kind="stable")
    own, first = np.unique(cid[order], return_index=True)
    return own, np.diff(np.concatenate([first, [len(cid)]])), np.add.reduceat(x[order].astype(np.float64), first, axis=0) if len(cid) else np.zeros((0, x.shape[1]))


def lloyd(x: np.ndarray, y: np.ndarray, iterations: int, assign=assign_full) -> np.ndarray:
    """Plain iterations inside one task; an empty cluster keeps its centroid."""
    y = y.copy()
    for _ in range(iterations):
        cid, _ = assign(x, y)
        own, n, sums = centroid_sums(x, cid, len(y))
        y[own] = (sums / n[:, None]).astype(y.dtype)
    return y


def moved_means(x: np.ndarray, y: np.ndarray, cid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(means of the labels' rows, how far each moved); an empty cluster keeps its centroid."""
    own, count, sums = centroid_sums(x, cid, len(y))
    new = y.copy()
    new[own] = sums / count[:, None]
    return new, np.sqrt(sq_norms(new - y))


def elkan_start(x: np.ndarray, y: np.ndarray):
    """(labels, upper bounds, lower bounds of every pair, distances computed)."""
    lower = np.sqrt(sq_dists(x, y))
    cid = lower.argmin(1)
    return cid, lower[np.arange(len(x)), cid], lower, lower.size


def elkan_step(x: np.ndarray, y: np.ndarray, shift: np.ndarray, cid: np.ndarray, upper: np.ndarray, lower: np.ndarray):
    """The same after the centroids have moved by `shift` to y: only pairs that the bounds leave open are computed."""
    cid, lower, upper = cid.copy(), np.maximum(lower - shift, 0), upper + shift[cid]
    between = np.sqrt(sq_dists(y, y)) / 2
    np.fill_diagonal(between, np.inf)
    open_ = np.flatnonzero(upper > between.min(1)[cid])
    done = len(open_)
    if done:
        exact = np.sqrt(sq_norms(x[open_] - y[cid[open_]]))
        upper[open_] = lower[open_, cid[open_]] = exact
        may = (upper[open_][:, None] >= lower[open_]) & (upper[open_][:, None] >= between[cid[open_]])
        r, c = np.nonzero(may)
        lower[open_[r], c] = np.sqrt(sq_norms(x[open_[r]] - y[c]))
        done += len(r)
        seen = np.where(may, lower[open_], np.inf)
        seen[np.arange(len(open_)), cid[open_]] = upper[open_]
        cid[open_], upper[open_] = seen.argmin(1), seen.min(1)
    return cid, upper, lower, done


def hamerly_start(x: np.ndarray, y: np.ndarray):
    """(labels, upper bounds, a lower bound of all other centroids, distances computed)."""
    d = np.sqrt(sq_dists(x, y))
    cid = d.argmin(1)
    rows = np.arange(len(x))
    upper = d[rows, cid].copy()
    d[rows, cid] = np.inf
    return cid, upper, d.min(1) if len(y) > 1 else np.full(len(x), np.inf), d.size


def hamerly_step(x: np.ndarray, y: np.ndarray, shift: np.ndarray, cid: np.ndarray, upper: np.ndarray, lower: np.ndarray):
    cid, upper, lower = cid.copy(), upper + shift[cid], lower - shift.max(initial=0)
    between = np.sqrt(sq_dists(y, y))
    np.fill_diagonal(between, np.inf)
    bound = np.maximum(between.min(1)[cid] / 2, lower)
    open_ = np.flatnonzero(upper >= bound)
    upper[open_] = np.sqrt(sq_norms(x[open_] - y[cid[open_]]))
    done = len(open_)
    open_ = open_[upper[open_] >= bound[open_]]
    if len(open_):
        cid[open_], upper[open_], lower[open_], more = hamerly_start(x[open_], y)
        done += more
    return cid, upper, lower, done


BOUNDS = {"elkan": (elkan_start, elkan_step), "hamerly": (hamerly_start, hamerly_step)}


def bounded(x: np.ndarray, y: np.ndarray, iterations: int, variant: str):
    """Lloyd's labels with triangle-inequality bounds, inside one task; (labels, centroids, distances computed, pairs)."""
    begin, step = BOUNDS[variant]
    x, y = x.astype(np.float64), y.astype(np.float64)
    cid, upper, lower, done = begin(x, y)
    for turn in range(iterations):
        y, shift = moved_means(x, y, cid)
        if turn < iterations - 1:
            cid, upper, lower, more = step(x, y, shift, cid, upper, lower)
            done += more
    return cid, y, done, iterations * len(x) * len(y)


def elkan(x: np.ndarray, y: np.ndarray, iterations: int):
    return bounded(x, y, iterations, "elkan")


def hamerly(x: np.ndarray, y: np.ndarray, iterations: int):
    return bounded(x, y, iterations, "hamerly")


def pivot_scan(x: np.ndarray, y: np.ndarray, variant: str):
    """Exact nearest centroids without any state; (cid, squared distance, distances computed).

    Each row first meets some pivot centroids.  "each" then drops every centroid at least twice as far from the nearest
    pivot as the row is; "all" drops all of them at once if the nearest one is.
    """
    between = np.sqrt(sq_dists(y, y)) / 2
    np.fill_diagonal(between, np.inf)
    pivots = np.arange(0, len(y), max(1, len(y) // max(1, int(np.sqrt(len(y))))))
    d = np.sqrt(sq_dists(x, y[pivots]))
    cid, upper, rows = pivots[d.argmin(1)], d.min(1) * (1 + 1e-12), np.arange(len(x))
    if variant == "each":
        may = upper[:, None] >= between[cid]
    else:
        may = np.repeat((upper >= between.min(1)[cid])[:, None], len(y), 1)
    may[rows, cid] = True
    r, c = np.nonzero(may)
    exact = np.full((len(x), len(y)), np.inf)
    exact[r, c] = sq_norms(x[r] - y[c])
    best = exact.argmin(1)
    return best, exact[rows, best], d.size + len(r)
