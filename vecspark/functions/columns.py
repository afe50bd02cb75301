"""Vector arithmetic as column expressions (double precision, JVM side)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _d(c) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("array<double>")


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, v: s + v)


def dot(a, b) -> Column:
    return total(F.zip_with(_d(a), _d(b), lambda x, y: x * y))


def sq_norm(a) -> Column:
    return dot(a, a)


def l2(a, b) -> Column:
    """Squared distance."""
    return total(F.zip_with(_d(a), _d(b), lambda x, y: (x - y) * (x - y)))


def cosine(a, b) -> Column:
    return dot(a, b) / F.sqrt(sq_norm(a) * sq_norm(b))


def head(a, d1: int) -> Column:
    return F.slice(a, 1, d1)


def tail(a, d1: int, d: int) -> Column:
    return F.slice(a, d1 + 1, d - d1)


def blocks(a, d1: int, d: int, step: int) -> Column:
    """array<struct<blk, vals>> of the dimensions behind the head; the last block may be shorter."""
    cuts = list(range(d1, d, step))
    return F.array(*(F.struct(F.lit(i).alias("blk"), F.slice(a, at + 1, min(step, d - at)).alias("vals")) for i, at in enumerate(cuts)))


def prefix_sq(a, grid: int, d: int) -> Column:
    """Squared norms of the first grid, 2 * grid, ... dimensions."""
    return F.array(*(sq_norm(F.slice(a, 1, n)) for n in range(grid, d + 1, grid)))


def limit(b: Column, d: int, tau: Column, epsilon0: float) -> Column:
    """The pruning test's limit on a partial squared distance over b of d dimensions."""
    inner = tau * (b / F.lit(float(d))) * F.pow(F.lit(1.0) + F.lit(epsilon0) / F.sqrt(b), F.lit(2.0))
    return F.when(b >= d, tau).otherwise(inner)
