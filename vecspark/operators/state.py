"""What each row carries from one iteration to the next, beside the data and never shuffled with it."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.kernels import Work
from vecspark.sources.files import discard, shared_path

from .assign import collect_sums, labelled_sums
from .model import matrix, vector_rows

BUCKET_BYTES = 128 << 20
WORK = ("rows", "head_mul_adds", "tail_mul_adds", "tested", "rejected")


class RowState:
    """Vectors and their state as two tables bucketed alike by a row number, so that they meet without an exchange.

    `advance` runs one step over all rows and writes the new state; the old one is dropped.  A row's state is its label
    and distance, and bounds where the step keeps any.
    """

    def __init__(self, vectors: DataFrame, d: int, bounds: int = 0):
        self.spark, self.d, self.bounds, self.state = vectors.sparkSession, d, bounds, None
        self.names: list[str] = []
        numbered = vectors.select(F.monotonically_increasing_id().alias("row_id"), "vec")
        path = shared_path(self.spark, "numbered")
        numbered.write.parquet(path)
        numbered = self.spark.read.parquet(path)
        self.buckets = max(self.spark.sparkContext.defaultParallelism, -(-numbered.count() * d * 4 // BUCKET_BYTES))
        self.data = self.table(numbered.repartition(self.buckets, "row_id"))
        discard(numbered)

    def table(self, df: DataFrame) -> DataFrame:
        name = f"vecspark_{uuid.uuid4().hex}"
        df.write.bucketBy(self.buckets, "row_id").sortBy("row_id").option("path", shared_path(self.spark, "state")).saveAsTable(name)
        self.names.append(name)
        return self.spark.table(name)

    def joined(self) -> DataFrame:
        return self.data if self.state is None else self.data.join(self.state.hint("merge"), "row_id")

    def advance(self, step) -> dict:
        """step(x, cid, upper, lower, work) -> (cid, dist, upper, lower); all but x and work are None at first.

        Returns the sums over rows of the step's work, and the number of labels that changed (None at first).
        """
        first, bounded, d_type = self.state is None, bool(self.bounds), np.float64 if self.bounds else np.float32
        keep = ["row_id", "vec"] + ([] if first else ["cid"] + (["upper", "lower"] if bounded else []))

        def run(batches):
            for batch in batches:
                if not batch.num_rows:
                    continue
                x, work = matrix(batch.column(1), d_type), Work()
                old = None if first else batch.column(2).to_numpy().astype(np.int64)
                upper, lower = (batch.column(3).to_numpy(), matrix(batch.column(4), np.float64)) if bounded and not first else (None, None)
                cid, dist, upper, lower = step(x, old, upper, lower, work)
                n = len(x)
                out = [batch.column(0), pa.array(cid.astype(np.int32)), pa.array(dist.astype(np.float64))]
                if bounded:
                    out += [pa.array(upper), vector_rows(np.asarray(lower).reshape(n, -1), pa.float64())]
                changed = np.zeros(n, np.int64) if first else (cid != old).astype(np.int64)
                spent = (work.rows, work.head_mul_adds, work.tail_mul_adds, work.tested, work.rejected_head)
                # a batch's work stands in its first row
                out += [pa.array(changed), *(pa.array(np.where(np.arange(n) == 0, v, 0)) for v in spent)]
                yield pa.RecordBatch.from_arrays(out, names=names)

        schema = "row_id long, cid int, dist double, " + ("upper double, lower array<double>, " if bounded else "") + "changed long, " + ", ".join(f"{c} long" for c in WORK)
        names = [c.split()[0] for c in schema.split(", ")]
        old = self.state
        new = self.table(self.joined().select(*keep).mapInArrow(run, schema))
        total = new.agg(*(F.sum(c).alias(c) for c in ("changed", *WORK))).first()
        if old is not None:
            self.drop(self.names.pop(-2))
        self.state = new
        return {c: total[c] or 0 for c in WORK} | {"changed": None if first else total["changed"] or 0, "block_tested": [], "block_rejected": []}

    def sums(self, k: int) -> dict:
        return collect_sums(labelled_sums(self.joined(), k, self.d))[0]

    def drop(self, name: str) -> None:
        discard(self.spark.table(name))
        self.spark.sql(f"DROP TABLE {name}")

    def close(self) -> None:
        while self.names:
            self.drop(self.names.pop())
