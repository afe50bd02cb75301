"""Iterative clusterings: plain iterations, the phased method, two levels, mini-batches, bounds, and their shared loop."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecspark.functions import kernels
from vecspark.functions.kernels import BatchPlan, CentroidBlocks, Work

from .assign import SUMS, Kernel, Sums, assign_full, assign_pruned, collect_sums, default_step, in_slices, iteration_sums, labelled_sums, slices, work_row
from .model import BROADCAST_BYTES, Model, matrix
from .rotation import random_rotation, rotate, unrotate
from .seeding import default_k, hash_order, init_kmeanspp, sample_rows, start_matrix
from .state import RowState
from .stopping import StopRule


def repair_empty(centroids: np.ndarray, counts: np.ndarray, policy: str = "split", eps: float = 1 / 1024, seed: int = 0, far: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Fills empty clusters.

    "split": a cluster drawn with probability growing with its size is parted in two by a small symmetric
    perturbation with alternating signs; "farthest": the rows `far` take the empty places; "keep": nothing is done.
    """
    empty = np.flatnonzero(counts == 0)
    if not len(empty) or policy == "keep":
        return centroids, counts
    centroids, counts = centroids.copy(), counts.copy()
    if policy == "farthest":
        for e, row in zip(empty, far if far is not None else [], strict=False):
            centroids[e] = row
        return centroids, counts
    rng = np.random.default_rng(seed)
    sign = np.where(np.arange(centroids.shape[1]) % 2 == 0, 1.0, -1.0)
    for e in empty:
        weight = np.maximum(counts - 1, 0).astype(np.float64)
        if not weight.sum():
            break
        big = rng.choice(len(counts), p=weight / weight.sum())
        step = eps * np.where(centroids[big] != 0, np.abs(centroids[big]), 1e-6) * sign
        centroids[e], centroids[big] = centroids[big] + step, centroids[big] - step
        counts[e] = counts[big] // 2
        counts[big] -= counts[e]
    return centroids, counts


def adjust_head(d1: int, rate: float | None, d: int, lo: float = 0.95, hi: float = 0.97, factor: float = 0.2, grid: int = 1) -> int:
    """The next head width: wider while the test rejects too little, narrower while it rejects more than it need."""
    if rate is None or lo <= rate <= hi:
        return d1
    wide = math.ceil(d1 * (1 + factor)) if rate < lo else math.floor(d1 * (1 - factor))
    if grid > 1:
        wide = (math.ceil if rate < lo else math.floor)(wide / grid) * grid
    return int(min(d, max(max(1, d // 64), wide)))


@dataclass
class LloydKMeans:
    """Plain iterations with full products."""

    k: int | None = None
    max_iter: int = 25
    init: str = "random"
    empty: str = "split"
    tol_shift: float | None = None
    stop: list[StopRule] = field(default_factory=list)
    sample_frac: float | None = None
    max_per_centroid: int | None = None
    plan: BatchPlan = BatchPlan()
    metric: str = "l2"
    dtype: type = np.float32
    seed: int = 0

    @classmethod
    def preset(cls, name: str, k: int | None = None, **options) -> LloydKMeans:
        """"general": 25 iterations; "index": 10; both on at most 256 rows a centroid; "toolkit": up to 300, until nothing moves."""
        own = {"general": {"max_iter": 25, "max_per_centroid": 256}, "index": {"max_iter": 10, "max_per_centroid": 256}, "toolkit": {"max_iter": 300, "tol_shift": 1e-4, "empty": "farthest"}}[name]
        return cls(k=k, **(own | options))

    def kernel(self, centroids: np.ndarray, turn: int, d1: int) -> Kernel:
        return Kernel(centroids, plan=self.plan, dtype=self.dtype)

    def prepare(self, vectors: DataFrame, d: int) -> tuple[DataFrame, np.ndarray | None]:
        return vectors, None

    def first_head(self, d: int) -> int:
        return d

    def next_head(self, d1: int, rate: float | None, d: int) -> int:
        return d1

    def fit(self, vectors: DataFrame, start: np.ndarray | None = None) -> Model:
        """Each iteration is one scan that returns sums; no plan grows over iterations."""
        began = time.perf_counter()
        vectors = vectors.select("vec_id", "vec")
        first = vectors.limit(1).collect()
        if not first:
            return Model(np.zeros((0, 0), np.float32), np.zeros(0, np.int64))
        d = len(first[0]["vec"])
        n = vectors.count() if self.k is None or self.max_per_centroid else None
        k = self.k or default_k(n)
        if self.sample_frac or self.max_per_centroid:
            vectors = sample_rows(vectors, self.sample_frac, self.max_per_centroid, k, self.seed, n)
        turned = time.perf_counter()
        data, rotation = self.prepare(vectors, d)
        turned = time.perf_counter() - turned
        if start is not None:
            y = start.astype(np.float64) @ rotation if rotation is not None else start.astype(np.float64)
        elif self.init == "kmeans++":
            y = init_kmeanspp(data, k, self.seed)
        else:
            y = start_matrix(data, k, self.seed)
        k = len(y)
        for rule in self.stop:
            rule.prepare(data, k, rotation)
        state = RowState(data, d) if self.keeps_labels() else None
        d1, history, counts = self.first_head(d), [], np.zeros(k, np.int64)
        scale = None
        setup = time.perf_counter() - began
        for turn in range(1, self.max_iter + 1):
            at = time.perf_counter()
            sums, work = self.scan(data, y, turn, d1) if state is None else self.carried(state, y, turn, d1)
            updated = time.perf_counter()
            new, counts = y.copy(), np.zeros(k, np.int64)
            for cid, (rows, _, total) in sums.items():
                new[cid], counts[cid] = total / rows, rows
            updated = time.perf_counter() - updated
            if self.metric == "cosine":
                norm = np.linalg.norm(new, axis=1, keepdims=True)
                new = np.where(norm > 0, new / np.where(norm > 0, norm, 1), new)
            n_empty = int((counts == 0).sum())
            far = None
            if n_empty and self.empty == "farthest":
                far = self.farthest(data, y, n_empty)
            lists, split = counts, time.perf_counter()
            new, counts = repair_empty(new, counts, self.empty, seed=self.seed * 1000 + turn, far=far)
            split = time.perf_counter() - split
            rate = work["rejected"] / work["tested"] if work["tested"] else None
            record = {
                "iter": turn, "d1": d1, "prune_rate": rate, "wcss": sum(s[1] for s in sums.values()), "shift": float(((new - y) ** 2).sum()), "empty": n_empty,
                "mul_adds": int(work["head_mul_adds"] + work["tail_mul_adds"]), "head_mul_adds": int(work["head_mul_adds"]), "tail_mul_adds": int(work["tail_mul_adds"]), "tested": int(work["tested"]), "rejected": int(work["rejected"]),
                "block_prune": [r / t if t else 0.0 for r, t in zip(work["block_rejected"], work["block_tested"], strict=True)], "rows": int(work["rows"]), "counts": lists, "changed": work.get("changed"),
            }
            scale = scale if scale is not None else max(record["wcss"] / max(1, record["rows"]), 1e-12)
            previous, y = y, new
            over = any([rule.observe(record, y, data, previous) for rule in self.stop])
            record["secs"] = time.perf_counter() - at
            record["setup_secs"] = setup if turn == 1 else 0.0
            record["phases"] = dict(zip(kernels.PHASES, work.get("secs") or [], strict=False)) | {"rotation": turned if turn == 1 else 0.0, "update": updated, "split": split}
            record.pop("counts")
            history.append(record)
            if over or (self.tol_shift is not None and record["shift"] <= self.tol_shift * scale):
                break
            d1 = self.next_head(d1, rate, d)
        if state is not None:
            state.close()
        params = {"k": k, "d": d, "method": type(self).__name__, "seed": self.seed}
        out = unrotate(y, rotation) if rotation is not None else y
        return Model(out, counts, history, rotation, d1, params)

    def keeps_labels(self) -> bool:
        """Whether an iteration needs each row's label of the one before."""
        return any(rule.needs_labels for rule in self.stop)

    def scan(self, data: DataFrame, y: np.ndarray, turn: int, d1: int):
        """(sums, work) of one iteration: one scan, over slices of the centroids where they are too large for one broadcast."""
        if len(slices(y)) == 1:
            return collect_sums(iteration_sums(data, self.kernel(y, turn, d1)))
        found = in_slices(data, y, BROADCAST_BYTES, ("vec",), lambda piece: self.kernel(piece, turn, d1))
        return collect_sums(labelled_sums(found, *y.shape))

    def carried(self, state: RowState, y: np.ndarray, turn: int, d1: int):
        """The same with each row's label kept: one scan that writes labels, one that adds up."""
        shipped = state.spark.sparkContext.broadcast(self.kernel(y, turn, d1))

        def step(x, old, upper, lower, work):
            return *shipped.value(x, old, work), None, None

        work = state.advance(step)
        return state.sums(len(y)), work

    def farthest(self, data: DataFrame, centroids: np.ndarray, n: int) -> np.ndarray:
        near = assign_full(data, centroids, self.plan, self.dtype, carry=("vec_id", "vec"))
        rows = near.orderBy(F.desc("dist"), "vec_id").limit(n).collect()
        return np.array([r["vec"] for r in rows], np.float64)

    def transform(self, vectors: DataFrame, model: Model, carry: tuple[str, ...] = ("vec_id",)) -> DataFrame:
        return assign_full(vectors, model.centroids, self.plan, self.dtype, carry=carry)


@dataclass
class PhasedKMeans(LloydKMeans):
    """Iterations that take a full product once, and from then on a head product and progressive pruning.

    The data is rotated once and the centroids are rotated back at the end.  The head width follows the share of
    pairs that the head test rejects.  The first threshold of a row needs no state by default ("head_nearest"); with
    `seed_mode="previous"` it is the distance to the centroid of the iteration before, whose labels are then kept beside
    the data.  "first_batch" and the other switches are for ablations.
    """

    d1: int | None = None
    step: int | None = None
    epsilon0: float = 2.1
    adapt: bool = True
    progressive: bool = True
    layout: str = "blocks"
    seed_mode: str = "head_nearest"
    refinement: str = "auto"  #: "pairs": always pair by pair, block by block; "grouped": by small products
    rotate: bool = True

    def prepare(self, vectors, d):
        if not self.rotate:
            return vectors, None
        rotation = random_rotation(d, self.seed)
        from vecspark.sources.files import settle

        return settle(rotate(vectors, rotation, self.dtype), "rotated"), rotation

    def first_head(self, d):
        return self.d1 or max(1, d // 8)

    def next_head(self, d1, rate, d):
        return adjust_head(d1, rate, d) if self.adapt else d1

    def kernel(self, centroids, turn, d1):
        if turn == 1:
            return Kernel(centroids, plan=self.plan, dtype=self.dtype)
        return self.pruned(centroids, d1)

    def keeps_labels(self):
        return self.seed_mode == "previous" or super().keeps_labels()

    def pruned(self, centroids, d1):
        d = centroids.shape[1]
        return Kernel(centroids, True, d1, self.step or default_step(d), self.epsilon0, self.progressive, self.layout, self.seed_mode, self.plan, self.dtype, self.refinement)

    def transform(self, vectors, model, carry=("vec_id",)):
        """The last assignment, by the same pruned kernel; the data is rotated on the way, in no pass of its own."""
        if model.rotation is None:
            return super().transform(vectors, model, carry)
        seed_mode = "head_nearest" if self.seed_mode == "previous" else self.seed_mode
        options = {"progressive": self.progressive, "layout": self.layout, "seed_mode": seed_mode, "plan": self.plan, "dtype": self.dtype, "refinement": self.refinement}
        return assign_pruned(vectors, model.centroids @ model.rotation, model.d1, self.step, self.epsilon0, rotation=model.rotation, carry=carry, **options)


def share_k(sizes: dict[int, int], k: int, rule: str = "proportional") -> dict[int, int]:
    """How many fine clusters each coarse one gets.

    "proportional": k by size with largest remainders, at least 1 and at most its rows; "sqrt": the floor of the
    root of its size, at least 1, whatever they add up to.
    """
    live = {c: n for c, n in sizes.items() if n > 0}
    if rule == "sqrt":
        return {c: max(1, math.isqrt(n)) for c, n in live.items()}
    total = sum(live.values())
    k = max(len(live), min(k, total))
    exact = {c: k * n / total for c, n in live.items()}
    out = {c: min(n, max(1, math.floor(exact[c]))) for c, n in live.items()}
    while (left := k - sum(out.values())) > 0:
        open_ = sorted((c for c in live if out[c] < live[c]), key=lambda c: (-(exact[c] - out[c]), c))
        for c in open_[:left]:
            out[c] += 1
    while (over := sum(out.values()) - k) > 0:
        for c in sorted((c for c in live if out[c] > 1), key=lambda c: (exact[c] - out[c], c))[:over]:
            out[c] -= 1
    return out


@dataclass
class TwoLevelKMeans:
    """A few coarse clusters first, then fine ones inside each; optionally a few flat iterations after.

    Both stages use the pruned kernel.  The fine stage is one loop over all coarse clusters at once: rows are dealt by
    (coarse cluster, hash), so tasks are of one size whatever the clusters' sizes, and an iteration is one scan in
    which a row meets the centroids of its own coarse cluster alone.
    """

    k: int
    meso_iter: int = 3
    fine_iter: int = 5
    fine_k: str = "proportional"
    refine_iter: int = 0
    pruned: bool = True
    sample_frac: float | None = None
    stop: list[StopRule] = field(default_factory=list)  #: rules of the fine stage
    seed: int = 0
    dtype: type = np.float32

    def level(self, k: int, iterations: int, rotated: bool = False) -> LloydKMeans:
        if not self.pruned:
            return LloydKMeans(k=k, max_iter=iterations, seed=self.seed, dtype=self.dtype)
        return PhasedKMeans(k=k, max_iter=iterations, seed=self.seed, dtype=self.dtype, rotate=not rotated)

    def fit(self, vectors: DataFrame) -> Model:
        from vecspark.sources.files import settle

        began = time.perf_counter()
        vectors = vectors.select("vec_id", "vec")
        if self.sample_frac:
            vectors = sample_rows(vectors, self.sample_frac, seed=self.seed)
        first = vectors.limit(1).collect()
        if not first:
            return Model(np.zeros((0, 0), np.float32), np.zeros(0, np.int64))
        d = len(first[0]["vec"])
        rotation = random_rotation(d, self.seed) if self.pruned else None
        data = settle(rotate(vectors, rotation, self.dtype), "rotated") if self.pruned else vectors
        coarse = self.level(max(1, math.isqrt(self.k)), self.meso_iter, True)
        meso = coarse.fit(data)
        if self.pruned:
            placed = assign_pruned(data, meso.centroids, meso.d1, carry=("vec_id", "vec"), dtype=self.dtype)
        else:
            placed = assign_full(data, meso.centroids, dtype=self.dtype, carry=("vec_id", "vec"))
        placed = placed.select("vec_id", "vec", F.col("cid").alias("meso"))
        tasks = data.sparkSession.sparkContext.defaultParallelism
        tasks = max(tasks, data._jdf.queryExecution().toRdd().getNumPartitions())
        placed = settle(placed.repartitionByRange(tasks, "meso", F.xxhash64("vec_id")), "meso")
        sizes = {r["meso"]: r["count"] for r in placed.groupBy("meso").count().collect()}  # at most sqrt(k) rows
        shares = share_k(sizes, self.k, self.fine_k)
        y, first_of = self.starts(placed, sizes, shares)
        for rule in self.stop:
            rule.prepare(data, len(y), rotation)
        d1, counts, history = max(1, d // 8), np.zeros(len(y), np.int64), list(meso.history)
        history[0]["setup_secs"] = time.perf_counter() - began - sum(h["secs"] for h in history)
        for turn in range(1, self.fine_iter + 1):
            at = time.perf_counter()
            sums, work = collect_sums(self.fine_sums(placed, y, first_of, turn, d1))
            new, counts = y.copy(), np.zeros(len(y), np.int64)
            for cid, (rows, _, total) in sums.items():
                new[cid], counts[cid] = total / rows, rows
            empty, lists = int((counts == 0).sum()), counts
            for c, (lo, hi) in first_of.items():
                new[lo:hi], counts[lo:hi] = repair_empty(new[lo:hi], counts[lo:hi], seed=self.seed + 7919 * c + turn)
            rate = work["rejected"] / work["tested"] if work["tested"] else None
            previous, y = y, new
            record = {"iter": len(history) + 1, "d1": d1, "prune_rate": rate, "wcss": sum(s[1] for s in sums.values()), "shift": float(((y - previous) ** 2).sum()), "empty": empty, "mul_adds": int(work["head_mul_adds"] + work["tail_mul_adds"]), "head_mul_adds": int(work["head_mul_adds"]), "tail_mul_adds": int(work["tail_mul_adds"]), "tested": int(work["tested"]), "rejected": int(work["rejected"]), "counts": lists}
            over = any([rule.observe(record, y, data, previous) for rule in self.stop])
            record.pop("counts")
            record["secs"] = time.perf_counter() - at
            history.append(record)
            if over:
                break
            d1 = adjust_head(d1, rate, d) if self.pruned else d
        out = unrotate(y, rotation) if self.pruned else y
        model = Model(out, counts, history, rotation, d1, {"k": len(y), "method": "TwoLevelKMeans"})
        if self.refine_iter:
            flat = self.level(len(y), self.refine_iter).fit(vectors, out)
            model = Model(flat.centroids, flat.counts, history + flat.history, flat.rotation, flat.d1, model.params)
        return model

    def starts(self, placed: DataFrame, sizes: dict[int, int], shares: dict[int, int]) -> tuple[np.ndarray, dict[int, tuple[int, int]]]:
        """Random rows of each coarse cluster as its first fine centroids, and each cluster's range of centroid numbers.

        A hashed share that holds more than enough rows of each cluster is ranked, never a whole cluster.
        """
        spark = placed.sparkSession
        few = [(c, shares[c], min(1.0, (2.0 * shares[c] + 40) / sizes[c])) for c in sorted(shares)]
        wanted = F.broadcast(spark.createDataFrame(few, "meso int, wanted int, share double"))  # at most sqrt(k) rows
        u = F.conv(F.substring(hash_order(self.seed)[0], 1, 8), 16, 10).cast("double") / float(2**32)
        drawn = placed.join(wanted, "meso").where(u < F.col("share"))
        rank = F.row_number().over(Window.partitionBy("meso").orderBy(*hash_order(self.seed)))
        rows = drawn.withColumn("rank", rank).where("rank <= wanted").select("meso", "rank", "vec").collect()  # at most k rows
        first_of, at = {}, 0
        for c in sorted(shares):
            first_of[c] = (at, at + shares[c])
            at += shares[c]
        y = np.zeros((at, len(rows[0]["vec"])), np.float64)
        got = dict.fromkeys(first_of, 0)
        for r in rows:
            y[first_of[r["meso"]][0] + r["rank"] - 1] = r["vec"]
            got[r["meso"]] += 1
        for c, (lo, hi) in first_of.items():  # a draw that fell short repeats rows; the split of empty clusters parts them
            short = np.arange(lo + got[c], hi)
            y[short] = y[lo + (short - lo) % max(1, got[c])]
        return y, first_of

    def fine_sums(self, placed: DataFrame, y: np.ndarray, first_of: dict[int, tuple[int, int]], turn: int, d1: int) -> DataFrame:
        k, d = y.shape
        pruned, dtype, step = self.pruned and turn > 1, self.dtype, default_step(d)
        shipped = placed.sparkSession.sparkContext.broadcast((y.astype(dtype), first_of))

        def scan(batches):
            own, ranges = shipped.value
            sums, work, kept = Sums(k, d), Work(), {}
            for batch in batches:
                if not batch.num_rows:
                    continue
                x, meso = matrix(batch.column(0), dtype), batch.column(1).to_numpy()
                for c in np.unique(meso):
                    rows = np.flatnonzero(meso == c)
                    lo, hi = ranges[int(c)]
                    if c not in kept:
                        kept = {c: CentroidBlocks(own[lo:hi], d1 if pruned else d, step)}  # rows come by coarse cluster
                    mine = x if len(rows) == len(x) else x[rows]
                    cid, dist = kernels.assign_pruned(mine, kept[c], work=work)
                    yield from sums.add(mine, cid + lo, dist)
            yield from sums.rest()
            yield work_row(work)

        return placed.select("vec", "meso").mapInArrow(scan, SUMS)

    def transform(self, vectors: DataFrame, model: Model, carry: tuple[str, ...] = ("vec_id",)) -> DataFrame:
        return self.level(model.k, 1).transform(vectors, model, carry)


@dataclass
class MiniBatchKMeans:
    """Batches by hash; each is assigned by the pruned kernel, on rotated data, and moves centroids at a rate of 1 over their count."""

    k: int
    batches: int = 10
    batch_frac: float = 0.1
    epsilon0: float = 2.1
    stop: list[StopRule] = field(default_factory=list)
    seed: int = 0

    def fit(self, vectors: DataFrame, start: np.ndarray | None = None) -> Model:
        vectors = vectors.select("vec_id", "vec")
        y = start_matrix(vectors, self.k, self.seed) if start is None else start.astype(np.float64)
        counts, history = np.zeros(len(y), np.int64), []
        rotation = random_rotation(y.shape[1], self.seed) if len(y) else None
        for rule in self.stop:
            rule.prepare(vectors, self.k, None)
        for turn in range(1, self.batches + 1):
            record = self.update(sample_rows(vectors, self.batch_frac, seed=self.seed + turn), y, counts, rotation, self.epsilon0)
            record["iter"] = turn
            history.append(record)
            if any([rule.observe(record, y, vectors, y) for rule in self.stop]):
                break
        return Model(y, counts, history, None, 0, {"k": len(y), "method": "MiniBatchKMeans"})

    @staticmethod
    def update(batch: DataFrame, y: np.ndarray, counts: np.ndarray, rotation: np.ndarray, epsilon0: float = 2.1) -> dict:
        """One batch, in place: a cluster's n new rows of mean m move it by n/(count+n) of the way to m.

        The test of the pruned kernel holds for rotated vectors only, so tasks rotate the batch; sums are in its own space.
        """
        d = y.shape[1]
        kernel = Kernel(y @ rotation, True, max(1, d // 2), default_step(d), epsilon0, dtype=np.float64, rotation=rotation)
        sums, work = collect_sums(iteration_sums(batch, kernel))
        before = y.copy()
        for cid, (n, _, total) in sums.items():
            counts[cid] += n
            y[cid] += (total - n * y[cid]) / counts[cid]
        return {"wcss": sum(s[1] for s in sums.values()), "shift": float(((y - before) ** 2).sum()), "mul_adds": int(work["head_mul_adds"] + work["tail_mul_adds"]), "empty": int((counts == 0).sum()), "secs": 0.0}


@dataclass
class BoundedKMeans:
    """Triangle-inequality variants, "elkan" or "hamerly", with exactly the labels of plain iterations.

    Each row's bounds follow it from one iteration to the next in a table beside the data: an upper bound of the distance
    to its own centroid and lower bounds of all k ("elkan") or of the nearest other one ("hamerly").
    """

    k: int
    max_iter: int = 10
    variant: str = "elkan"
    seed: int = 0

    def fit(self, vectors: DataFrame, start: np.ndarray | None = None) -> Model:
        vectors = vectors.select("vec_id", "vec")
        y = start_matrix(vectors, self.k, self.seed) if start is None else start.astype(np.float64)
        history, counts, shift = [], np.zeros(len(y), np.int64), None
        if not len(y):
            return Model(y, counts)
        k, d = y.shape
        state = RowState(vectors, d, k if self.variant == "elkan" else 1)
        for turn in range(1, self.max_iter + 1):
            at = time.perf_counter()
            shipped = vectors.sparkSession.sparkContext.broadcast((y, shift))
            variant = self.variant

            def step(x, cid, upper, lower, work, shipped=shipped, variant=variant):
                own, moved = shipped.value
                begin, again = kernels.BOUNDS[variant]
                if cid is None:
                    cid, upper, lower, done = begin(x, own)
                else:
                    cid, upper, lower, done = again(x, own, moved, cid, upper, lower if variant == "elkan" else lower.ravel())
                work.rows += len(x)
                work.tested += len(x) * len(own)
                work.rejected_head += len(x) * len(own) - done
                work.head_mul_adds += done * own.shape[1]
                return cid, kernels.sq_norms(x - own[cid]), upper, lower

            work = state.advance(step)
            sums = state.sums(k)
            new, counts = y.copy(), np.zeros(k, np.int64)
            for cid, (n, _, total) in sums.items():
                new[cid], counts[cid] = total / n, n
            shift = np.sqrt(kernels.sq_norms(new - y))
            history.append({"iter": turn, "d1": d, "wcss": sum(s[1] for s in sums.values()), "shift": float((shift**2).sum()), "empty": int((counts == 0).sum()), "changed": work["changed"], "mul_adds": work["head_mul_adds"], "tested": work["tested"], "rejected": work["rejected"], "prune_rate": work["rejected"] / max(1, work["tested"]), "secs": time.perf_counter() - at})
            y = new
            if not shift.any():
                break
        state.close()
        return Model(y, counts, history, None, 0, {"k": k, "method": self.variant})


class PivotKernel(Kernel):
    """Full products replaced by the triangle inequality around pivot centroids."""

    def __init__(self, centroids: np.ndarray, variant: str):
        super().__init__(centroids, dtype=np.float64)
        self.variant = variant

    def __call__(self, x, prev=None, work=None):
        cid, dist, done = kernels.pivot_scan(x, self.blocks.full, self.variant)
        if work is not None:
            work.rows += len(x)
            work.tested += len(x) * self.blocks.k
            work.rejected_head += len(x) * self.blocks.k - done
            work.head_mul_adds += done * self.blocks.d
        return cid, dist


@dataclass
class PivotKMeans(LloydKMeans):
    """The stateless relative of the bounded variants: labels of plain iterations, pivots in place of kept bounds."""

    variant: str = "each"

    def kernel(self, centroids, turn, d1):
        return PivotKernel(centroids, self.variant)
