"""When an iterative clustering stops.  A rule sees each iteration's record and says whether it was the last."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.sources.files import discard, settle

from .assign import assign_full
from .index import exact_knn, route
from .rotation import rotate
from .seeding import sample_queries


class StopRule:
    needs_labels = False  #: whether `changed`, the number of labels that changed, is wanted in the record

    def prepare(self, vectors: DataFrame, k: int, rotation: np.ndarray | None = None) -> None:
        """Called once before the first iteration, with the space that vectors and centroids will be in."""

    def observe(self, record: dict, centroids: np.ndarray, vectors: DataFrame, assigned: np.ndarray) -> bool:
        """`centroids` are the updated ones; `assigned` those that this iteration's lists were built with."""
        raise NotImplementedError


@dataclass
class MaxIter(StopRule):
    n: int

    def observe(self, record, centroids, vectors, assigned) -> bool:
        return record["iter"] >= self.n


@dataclass
class Convergence(StopRule):
    """Centroids move (in sum of squares) or labels change no more than the tolerance."""

    tol_shift: float | None = 0.0
    tol_changed: int | None = None

    @property
    def needs_labels(self) -> bool:
        return self.tol_changed is not None

    def observe(self, record, centroids, vectors, assigned) -> bool:
        moved = self.tol_shift is not None and record["shift"] <= self.tol_shift
        same = self.tol_changed is not None and record.get("changed") is not None and record["changed"] <= self.tol_changed
        return moved or same


def plateau(series: list[float], tol: float, patience: int = 2, rule: str = "patience") -> bool:
    """Whether a series of recalls has stopped improving.

    "patience": the last `patience` values each gained no more than tol over the best before them;
    "window": the last value exceeds the one `patience` steps earlier by no more than tol.
    """
    if len(series) <= patience:
        return False
    if rule == "window":
        return series[-1] - series[-1 - patience] <= tol
    best, stale = series[0], 0
    for r in series[1:]:
        stale = stale + 1 if r - best <= tol else 0
        best = max(best, r)
    return stale >= patience


def plateaus(series: list[float], tol: float, patience: int = 2, rule: str = "patience") -> list[bool]:
    """What `plateau` says of the series after each of its values, in one pass."""
    out, best, stale = [], float("nan"), 0
    for i, r in enumerate(series):
        if rule == "window":
            out.append(i >= patience and r - series[i - patience] <= tol)
            continue
        stale = stale + 1 if i and r - best <= tol else 0
        best = max(best, r) if i else r
        out.append(i >= patience and stale >= patience)
    return out


@dataclass
class RecallPlateau(StopRule):
    """Stops when the recall that the centroids would give no longer improves; works with any iterative clustering.

    Queries and their true neighbours stay distributed: an iteration places the neighbours, routes the queries and joins
    the two.  Supplied queries are in the data's own space and are rotated with it.  By default a query is not its
    own neighbour where it was drawn from the data, and ids of supplied queries have nothing to do with those of the data.
    """

    tol: float = 0.005
    patience: int = 2
    topk: int = 100
    probe_frac: float = 0.01
    rule: str = "patience"
    lists: str = "current"  #: "current": lists of the assignment just computed; "reassign": of the updated centroids
    queries: DataFrame | None = None
    truth: DataFrame | None = None
    exclude_self: bool | None = None
    n_queries: int = 1000
    seed: int = 1
    series: list[float] = field(default_factory=list)
    secs: float = 0.0  #: what the rule itself has taken

    def prepare(self, vectors: DataFrame, k: int, rotation: np.ndarray | None = None) -> None:
        self.series, self.secs = [], 0.0
        if self.queries is None:
            queries = sample_queries(vectors, self.n_queries, self.seed)
        else:
            queries = self.queries.select("qid", F.col("qvec").alias("vec"))
            if rotation is not None:
                queries = rotate(queries, rotation, np.float64)
            queries = queries.select("qid", F.col("vec").alias("qvec"))
        self.asked = settle(queries, "asked")
        own = self.queries is None if self.exclude_self is None else self.exclude_self
        truth = self.truth if self.truth is not None else exact_knn(self.asked, vectors, self.topk, exclude_self=own)
        self.wanted = settle(truth.where(F.col("rank") <= self.topk).select("qid", "vec_id").distinct(), "wanted")
        self.n_wanted, self.n_asked = self.wanted.count(), self.asked.count()
        ids = self.wanted.select("vec_id").distinct()
        self.neighbours = settle(vectors.join(ids, "vec_id", "left_semi").select("vec_id", "vec"), "neighbours")

    def observe(self, record, centroids, vectors, assigned) -> bool:
        began = time.perf_counter()
        nprobe = max(1, int(np.ceil(self.probe_frac * len(centroids))))
        lists = centroids if self.lists == "reassign" else assigned
        home = assign_full(self.neighbours, np.asarray(lists, np.float64), dtype=np.float64)
        probes = settle(route(vectors.sparkSession, self.asked, centroids, nprobe).select("qid", "cid"), "probes")
        placed = self.wanted.join(home.select("vec_id", "cid"), "vec_id")
        hits = placed.join(probes, ["qid", "cid"], "left_semi").select("qid", "vec_id").distinct().count()
        record["recall"] = hits / max(1, self.n_wanted)
        counts = record.get("counts")
        if counts is not None and self.n_asked:
            asked = probes.groupBy("cid").count().collect()  # at most k rows
            record["explored"] = float(sum(r["count"] * counts[r["cid"]] for r in asked) / self.n_asked)
        discard(probes)
        self.secs += time.perf_counter() - began
        self.series.append(record["recall"])
        return plateau(self.series, self.tol, self.patience, self.rule)
