"""Connected components of links between ids, distributed: hooking to the least neighbour on a graph that shrinks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import discard, settle


def renamed(df: DataFrame, column: str, to: DataFrame) -> DataFrame:
    """df with the ids in `column` replaced by what (id, label) says; an id that is not listed stays."""
    moved = to.select(F.col("id").alias(column), F.col("label").alias("__to"))
    return df.join(moved, column, "left").withColumn(column, F.coalesce("__to", column)).drop("__to")


def components(links: DataFrame) -> DataFrame:
    """(a, b) -> (id, label) of one orderable type, label the least id of its component; ids without links are not listed.

    In a round every id takes the least of its neighbours and itself, and what that one takes; links then name what
    their ends have taken, and those inside one label or told twice go, so rounds get smaller and smaller.  Every round
    is written to the shared folder, so that the plan stays short and a lost executor costs a task.
    """
    kind = links.schema["a"].dataType
    pair = lambda df: df.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    edges, labels = settle(pair(links), "links"), None
    while edges.limit(1).count():
        near = edges.select(F.col("a").alias("id"), F.col("b").alias("n")).union(edges.select(F.col("b").alias("id"), F.col("a").alias("n")))
        taken = settle(near.groupBy("id").agg(F.least("id", F.min("n")).alias("label")), "taken")
        jumped = settle(renamed(taken, "label", taken), "taken")
        discard(taken)
        fewer = settle(pair(renamed(renamed(edges, "a", jumped), "b", jumped)), "links")
        discard(edges)
        edges = fewer
        if labels is None:
            labels = jumped
            continue
        further = settle(renamed(labels, "label", jumped), "labels")
        discard(labels)
        discard(jumped)
        labels = further
    if labels is None:
        return links.sparkSession.createDataFrame([], f"id {kind.simpleString()}, label {kind.simpleString()}")
    discard(edges)
    return labels
