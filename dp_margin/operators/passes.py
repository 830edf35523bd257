"""One pass over the data for a sum of per-row arrays: the unit of every solver.

Each task multiplies whole Arrow batches and emits one row of partial sums; the sums meet in two hash aggregations. Partial sums are
rows, not accumulators, so retried and speculative tasks cannot count twice. Nothing is cached: maps are computed again in each pass.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Up to this many features, sums stay plain SQL aggregates.
SQL_FEATURES = 64
BUCKETS = 64
#: Sums of more numbers than this travel as blocks of so many, as bytes, and are added by numpy.
BLOCK = 1 << 13


def matrix(column: pa.Array) -> np.ndarray:
    """(rows, features) of a list column without nulls inside."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def sum_pass(df: DataFrame, size: int, batch: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """Sum over all rows of ``batch(X, y, weight)``, an array of ``size`` numbers for each batch.

    Many numbers (a Gram matrix) leave a task as one row a block, not as one row a number; tasks of a bucket are added first, then
    buckets, so a task that adds blocks holds two of them. The driver gets one row a block.
    """
    weighted = "weight" in df.columns
    cols = df.select("x", "y", *(["weight"] if weighted else []))

    def run(batches):
        total = np.zeros(size)
        for b in batches:
            if b.num_rows:
                y = b.column(1).to_numpy(zero_copy_only=False)
                total += batch(matrix(b.column(0)), y, b.column(2).to_numpy(zero_copy_only=False) if weighted else np.ones(len(y)))
        from pyspark import TaskContext

        if size > BLOCK:
            for at in range(0, size, BLOCK):
                yield _blocks([TaskContext.get().partitionId() % BUCKETS], [at], [total[at : at + BLOCK]])
            return
        yield pa.record_batch([pa.array([TaskContext.get().partitionId() % BUCKETS], pa.int32()), pa.array([total.tolist()], pa.list_(pa.float64()))], ["bucket", "s"])

    if size > BLOCK:
        rows = _add_blocks(_add_blocks(cols.mapInArrow(run, _BLOCKS), "bucket", "at"), "at").collect()
        out = np.zeros(size)
        for r in rows:
            out[r.at : r.at + BLOCK] = np.frombuffer(r.v, "<f8")
        return out
    part = cols.mapInArrow(run, "bucket int, s array<double>")
    long = part.select("bucket", F.posexplode("s").alias("pos", "v"))
    rows = long.groupBy("bucket", "pos").agg(F.sum("v").alias("v")).groupBy("pos").agg(F.sum("v").alias("v")).collect()  # one row a feature
    out = np.zeros(size)
    for r in rows:
        out[r.pos] = r.v
    return out


_BLOCKS = "bucket int, at long, v binary"


def _blocks(buckets, starts, values) -> pa.RecordBatch:
    return pa.record_batch([pa.array(buckets, pa.int32()), pa.array(starts, pa.int64()), pa.array([x.astype("<f8").tobytes() for x in values], pa.binary())], ["bucket", "at", "v"])


def _add_blocks(df: DataFrame, *keys: str) -> DataFrame:
    """One row a key, its blocks added in batches."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            for x in b.column(2):
                block = np.frombuffer(x.as_buffer(), "<f8")
                total = block.copy() if total is None else total + block
                bucket, at = b.column(0)[0].as_py(), b.column(1)[0].as_py()
        if total is not None:
            yield _blocks([bucket], [at], [total])

    return df.groupBy(*keys).applyInArrow(add, _BLOCKS)


def sql_sums(df: DataFrame, terms: dict) -> dict:
    """One row of plain aggregates, computed in one stage with partial aggregation."""
    row = df.agg(*[F.sum(c).alias(k) for k, c in terms.items()]).first()
    return {k: float(row[k] or 0.0) for k in terms}
