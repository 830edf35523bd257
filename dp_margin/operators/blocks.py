"""Every row with every other, for any number of rows: blocks of rows meet in tasks, and a meeting leaves a number a row, never pairs.

The work grows with the square of the rows, what a task holds does not. Rows are (row_id, x, ...), ids being unique; a null x counts as a row without a value.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import Kernel, trig_batch

#: Rows of a block.
ROWS = 1024
#: Numbers that a strip of a kernel matrix holds before its coordinates are added.
STRIP = 1 << 20


def gram(z: np.ndarray, x: np.ndarray, kernel: Kernel | None, rho: np.ndarray | None = None) -> np.ndarray:
    if rho is not None:
        return trig_batch(z, rho) @ trig_batch(x, rho).T
    if kernel is None:
        return z @ x.T
    step = max(1, STRIP // max(1, x.size))
    return np.concatenate([kernel.numpy(z[lo : lo + step, None, :] - x[None, :, :]) for lo in range(0, len(z), step)])


class Block:
    """Rows of one side of a meeting: ids, x (NaN where it is null), which x are known, and other columns by name."""

    def __init__(self, rows: pa.StructArray):
        x = rows.field("x")
        self.ids, self.known = rows.field("row_id").to_numpy(zero_copy_only=False), ~np.asarray(x.is_null())
        flat = x.flatten().to_numpy(zero_copy_only=False)
        self.x = np.full((len(x), len(flat) // max(1, self.known.sum())), np.nan)
        self.x[self.known] = flat.reshape(-1, self.x.shape[1])
        self.rows = rows

    def __getitem__(self, name: str) -> np.ndarray:
        return self.rows.field(name).to_numpy(zero_copy_only=False)


def _dealt(df: DataFrame, rows: int) -> tuple[DataFrame, int]:
    blocks = max(1, -(-df.count() // rows))
    b = df.select(F.pmod(F.xxhash64("row_id"), F.lit(blocks)).cast("int").alias("block"), F.struct(*df.columns).alias("r"))
    return b.groupBy("block").agg(F.collect_list("r").alias("r")), blocks


def meet(left: DataFrame, right: DataFrame | None, run: Callable[[Block, Block, bool], Iterator[pa.RecordBatch]], schema: str, rows: int = ROWS) -> DataFrame:
    """``run(a, b, same)`` for every block of left with every block of right (of the same columns); without right, for all pairs of left's own blocks once, ``same`` for a block with itself."""
    a, n = _dealt(left, rows)
    b, m = (a, n) if right is None else _dealt(right, rows)
    there = F.sequence(F.col("block") if right is None else F.lit(0), F.lit(m - 1))
    back = F.sequence(F.lit(0), F.col("block") if right is None else F.lit(n - 1))
    sides = a.select(F.col("block").alias("p"), F.explode(there).alias("q"), F.lit(0).alias("side"), "r").union(b.select(F.explode(back).alias("p"), F.col("block").alias("q"), F.lit(1).alias("side"), "r"))
    meetings = n * (n + 1) // 2 if right is None else n * m
    alone = right is None

    def both(batches):
        held = None
        for batch in batches:
            p, q, side = (batch.column(k).to_pylist() for k in range(3))
            for k in range(batch.num_rows):
                block = Block(batch.column(3)[k].values)
                if side[k] == 0:
                    held = (p[k], q[k], block)
                elif held is not None and held[:2] == (p[k], q[k]):
                    yield from run(held[2], block, alone and p[k] == q[k])

    return sides.repartition(meetings if meetings <= 2000 else max(2000, meetings // 8), "p", "q").sortWithinPartitions("p", "q", "side").mapInArrow(both, schema)


def row_measures(df: DataFrame, matrix: Callable[[np.ndarray, np.ndarray], np.ndarray], rows: int = ROWS) -> DataFrame:
    """(i, others, total, least, most): every row's count, sum, least and largest entry in the matrix over all rows of other ids."""

    def side(a: Block, k: np.ndarray, use: np.ndarray, seen: np.ndarray) -> pa.RecordBatch:
        none = ~seen.any(axis=1)
        cols = [use.sum(axis=1), np.where(seen, k, 0.0).sum(axis=1), np.where(seen, k, np.inf).min(axis=1), np.where(seen, k, -np.inf).max(axis=1)]
        return pa.record_batch([pa.array(a.ids, pa.int64()), pa.array(cols[0], pa.int64()), *[pa.array(c, mask=none) for c in cols[1:]]], ["i", "others", "total", "least", "most"])

    def run(a, b, same):
        k, use = matrix(a.x, b.x), a.ids[:, None] != b.ids[None, :]
        seen = use & a.known[:, None] & b.known[None, :]
        yield side(a, k, use, seen)
        if not same:
            yield side(b, k.T, use.T, seen.T)

    met = meet(df.select("row_id", "x"), None, run, "i long, others long, total double, least double, most double", rows)
    return met.groupBy("i").agg(F.sum("others").alias("others"), F.sum("total").alias("total"), F.min("least").alias("least"), F.max("most").alias("most")).where("others > 0")


def expansions(df: DataFrame, matrices: list[Callable[[np.ndarray, np.ndarray], np.ndarray]], terms: dict[str, tuple[int, str]], apart: str | None = None, rows: int = ROWS) -> DataFrame:
    """(row_id, a column a term): for a term (k, c), the sum of column c times the k-th matrix over all rows, the row itself included; ``apart`` names the largest difference of the first two matrices."""
    columns = sorted({c for _, c in terms.values()})
    names = [*terms, *([apart] if apart else [])]

    def side(a: Block, ks: list[np.ndarray], held: dict[str, np.ndarray]) -> pa.RecordBatch:
        made = [ks[k] @ held[c] for k, c in terms.values()] + ([np.abs(ks[0] - ks[1]).max(axis=1)] if apart else [])
        return pa.record_batch([pa.array(a.ids, pa.int64()), *map(pa.array, made)], ["row_id", *names])

    def run(a, b, same):
        ks = [m(a.x, b.x) for m in matrices]
        yield side(a, ks, {c: b[c] for c in columns})
        if not same:
            yield side(b, [k.T for k in ks], {c: a[c] for c in columns})

    met = meet(df.select("row_id", "x", *columns), None, run, "row_id long, " + ", ".join(f"{c} double" for c in names), rows)
    return met.groupBy("row_id").agg(*[F.sum(c).alias(c) for c in terms], *([F.max(apart).alias(apart)] if apart else []))


def crossed(test: DataFrame, train: DataFrame, matrix: Callable[[np.ndarray, np.ndarray], np.ndarray], rows: int = ROWS) -> DataFrame:
    """(row_id, value): for every row of test (row_id, x), the sum of c times the matrix over all rows of train (row_id, x, c)."""

    def run(a, b, same):
        yield pa.record_batch([pa.array(a.ids, pa.int64()), pa.array(matrix(a.x, b.x) @ b["c"])], ["row_id", "value"])

    met = meet(test.select("row_id", "x", F.lit(0.0).alias("c")), train.select("row_id", "x", "c"), run, "row_id long, value double", rows)
    return met.groupBy("row_id").agg(F.sum("value").alias("value"))
