"""Quality, balance, work and space of a clustering."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def wcss(assignment: DataFrame) -> DataFrame:
    return assignment.agg(F.sum("dist").alias("wcss"))


def cluster_sizes(assignment: DataFrame, k: int) -> DataFrame:
    """(cid, n) for every cluster, empty ones with 0."""
    every = assignment.sparkSession.range(k).select(F.col("id").cast("int").alias("cid"))
    return every.join(assignment.groupBy("cid").agg(F.count(F.lit(1)).alias("n")), "cid", "left").select("cid", F.coalesce("n", F.lit(0)).alias("n"))


def points_per_cluster(assignment: DataFrame, k: int) -> DataFrame:
    return cluster_sizes(assignment, k).agg(F.avg("n").alias("ppc_mean"), F.stddev_pop("n").alias("ppc_std"))


def balance(assignment: DataFrame, k: int) -> DataFrame:
    """Largest over mean size, Gini index of sizes, number of empty clusters; k rows are ranked."""
    ranked = cluster_sizes(assignment, k).withColumn("r", F.row_number().over(Window.orderBy("n", "cid")))
    gini = 2 * F.sum(F.col("r") * F.col("n")) / (F.lit(k) * F.sum("n")) - F.lit((k + 1) / k)
    return ranked.agg((F.max("n") / F.avg("n")).alias("max_over_mean"), gini.alias("gini"), F.sum((F.col("n") == 0).cast("int")).alias("n_empty"))


def assignment_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.select("vec_id", "cid").join(b.select("vec_id", F.col("cid").alias("other")), "vec_id")
    return both.agg(F.sum((F.col("cid") != F.col("other")).cast("int")).alias("differ"), F.avg((F.col("cid") != F.col("other")).cast("double")).alias("share"))


def label_purity(assignment: DataFrame, labels: DataFrame) -> DataFrame:
    """Share of rows that carry their cluster's most frequent label."""
    counted = assignment.join(labels, "vec_id").groupBy("cid", "label").agg(F.count(F.lit(1)).alias("n"))
    return counted.groupBy("cid").agg(F.max("n").alias("top"), F.sum("n").alias("all")).agg((F.sum("top") / F.sum("all")).alias("purity"))


def prune_report(history: list[dict]) -> list[dict]:
    return [{"iter": h["iter"], "d1": h["d1"], "prune_rate": h["prune_rate"], "block_prune": h.get("block_prune", [])} for h in history]


def work_report(history: list[dict], n: int, k: int, d: int) -> dict:
    """Multiply-adds in all, in head products and in refinement, and over those of full products."""
    total = sum(h["mul_adds"] for h in history)
    return {"mul_adds": total, "head": sum(h.get("head_mul_adds", h["mul_adds"]) for h in history), "tail": sum(h.get("tail_mul_adds", 0) for h in history), "of_full": total / max(1, len(history) * n * k * d)}


def phase_times(history: list[dict]) -> dict[str, float]:
    """Seconds of set-up, of the first iteration and of the rest."""
    return {"setup": sum(h.get("setup_secs", 0.0) for h in history), "first": history[0]["secs"] if history else 0.0, "rest": sum(h["secs"] for h in history[1:])}


def phase_profile(history: list[dict]) -> dict[str, float]:
    """Each phase's share of the seconds that tasks (norms, products, test, refinement, sums) and driver (rotation, update,
    split) have counted, added up over iterations; tasks count side by side, so the shares are of work and not of the clock."""
    total: dict[str, float] = {}
    for h in history:
        for phase, secs in (h.get("phases") or {}).items():
            total[phase] = total.get(phase, 0.0) + secs
    return {phase: secs / max(1e-12, sum(total.values())) for phase, secs in total.items()}


def overhead_shares(history: list[dict], truth_secs: float = 0.0, init_secs: float = 0.0, recall_secs: float = 0.0) -> dict[str, float]:
    loop = sum(h["secs"] for h in history)
    total = max(1e-12, loop + truth_secs + init_secs)
    return {"truth": truth_secs / total, "recall": recall_secs / total, "init": init_secs / total, "first_iteration": (history[0]["secs"] if history else 0.0) / max(1e-12, loop)}


def speedup(base_secs: float, secs: float) -> float:
    return base_secs / secs


def iterations_to_stop(history: list[dict]) -> int:
    return len(history)


def space_model(n: int, d: int, k: int, copy: bool = True) -> int:
    """Numbers held: data (and its rotated copy), centroids, norms, assignments, distances."""
    return (2 if copy else 1) * n * d + k * d + 3 * n + k


def beaten(a: list, b: list, signs: list[int], at_once: int = 1 << 20):
    """Which rows of the columns `a` some row of `b` matches in every measure and beats in one (sign 1: less is better)."""
    out = np.zeros(len(a[0]), bool)
    few = max(1, at_once // max(1, len(b[0])))
    for at in range(0, len(out), few):
        no_worse, better = True, False
        for x, y, sign in zip(a, b, signs, strict=True):
            x = x[at : at + few, None]
            no_worse, better = no_worse & (y <= x if sign > 0 else y >= x), better | (y < x if sign > 0 else y > x)
        out[at : at + few] = (no_worse & better).any(1)
    return out


def pareto(results: DataFrame, minimise: list[str], maximise: list[str]) -> DataFrame:
    """Rows that no other row matches in every measure and beats in one.

    Each task drops what its own rows beat, and what is left of all tasks is compared; a row with a null beats and is beaten by none.
    """
    names, signs = [*minimise, *maximise], [1] * len(minimise) + [-1] * len(maximise)

    def own_front(batches):
        front = None
        for batch in batches:
            table = pa.Table.from_batches([batch])
            table = table if front is None else pa.concat_tables([front, table])
            # what the batch adds meets the distinct measures of the front before the rest meets itself
            plain = np.ones(table.num_rows, bool)
            for c in names:
                plain &= table[c].is_valid().to_numpy()
            rows = np.flatnonzero(plain)
            columns = [table[c].take(pa.array(rows)).to_numpy() for c in names]
            if front is not None:
                n_old = int(plain[: front.num_rows].sum())
                old = [c[:n_old] for c in columns]
                rest = np.concatenate([np.ones(n_old, bool), ~beaten([c[n_old:] for c in columns], old, signs)])
                rows, columns = rows[rest], [c[rest] for c in columns]
            by = np.lexsort(columns[::-1])
            new = np.ones(len(by), bool)
            if len(by):
                new[1:] = np.any([c[by][1:] != c[by][:-1] for c in columns], 0)
            points = [c[by][new] for c in columns]
            lost = np.empty(len(by), bool)
            lost[by] = beaten(points, points, signs)[np.cumsum(new) - 1]
            keep = ~plain
            keep[rows[~lost]] = True
            front = table.filter(pa.array(keep))
        if front is not None:
            yield from front.combine_chunks().to_batches()

    own = results.mapInArrow(own_front, results.schema)
    a, b = own.alias("a"), F.broadcast(own.select(*names).distinct()).alias("b")
    no_worse, better = F.lit(True), F.lit(False)
    for c in minimise:
        no_worse, better = no_worse & (F.col(f"b.{c}") <= F.col(f"a.{c}")), better | (F.col(f"b.{c}") < F.col(f"a.{c}"))
    for c in maximise:
        no_worse, better = no_worse & (F.col(f"b.{c}") >= F.col(f"a.{c}")), better | (F.col(f"b.{c}") > F.col(f"a.{c}"))
    return a.join(b, no_worse & better, "left_anti")
