"""Orthogonal-triangular factorisation of tall matrices by a merge tree that needs no full rank."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from ..cost import timed
from ..kernels import pivot_rows, r_of, triangular_solve
from ..matrix import ROW_SCHEMA, RowFrame, row_batch, rows_of, sound_rows
from ..session import SMALL_BYTES, durable
from . import reduce as tree


def _same(x: np.ndarray) -> np.ndarray:
    return x


def r_factor(a: RowFrame, width: int | None = None, before=_same) -> np.ndarray:
    """R (width x width, zero rows at the end if there are fewer rows) of the rows of a; before: what is done to a block of rows first.

    A task keeps one R, whatever number of rows it reads.  ``a.m`` is known afterwards; rows that are not sound raise ValueError.
    """
    width = width or a.n
    partials = tree.folded(a, lambda r, x: r_of(r, before(x)), (0, width), max(4 * a.n, 1024))
    r, a.m = tree.merged(partials, lambda rs: r_of(*rs), a.tasks, 8 * width * width)
    out = np.zeros((width, width))
    if r is not None:
        out[: len(r)] = tree.finite(r)
    return out


def apply_rows(a: RowFrame, f, width: int) -> RowFrame:
    """Each block of rows through f, lazily; row_id stays."""
    n = a.n

    def kernel(batches):
        for batch in batches:
            if batch.num_rows:
                yield row_batch(batch.column("row_id"), f(rows_of(batch, n)))

    return RowFrame(a.df.select("row_id", "vec").mapInArrow(timed(a.df.sparkSession, kernel), ROW_SCHEMA), width, a.m, tasks=a.tasks)


def substitution(r: np.ndarray, keep: np.ndarray, before=_same):
    """Rows to rows of Q: the kept columns against the kept part of R."""
    rk = np.ascontiguousarray(r[np.ix_(keep, keep)])
    return lambda x: triangular_solve(before(x)[:, keep], rk)


def solved(a: RowFrame, r: np.ndarray, keep: np.ndarray, before=_same) -> RowFrame:
    """Q by substitution against R, lazily."""
    sent = a.df.sparkSession.sparkContext.broadcast(substitution(r, keep, before)) if r.nbytes > 1 << 20 and before is _same else None
    f = (lambda x: sent.value(x)) if sent else substitution(r, keep, before)
    return apply_rows(a, f, len(keep))


def block_rows(n: int) -> int:
    """Rows of a block: 4 n at least, more where that is less than 16 MB."""
    return max(4 * n, min(64 * n, (1 << 24) // (8 * max(n, 1))), 256)


def blocked(a: RowFrame, rows: int | None = None):
    """(part, ids, data): the rows in numbered blocks, written once, so that every sweep meets the same rows in the same order."""
    n, most = a.n, rows or block_rows(a.n)

    def kernel(batches):
        from pyspark import TaskContext

        task, k = TaskContext.get().partitionId(), 0
        ids, held, size = [], [], 0

        def block():
            return pa.RecordBatch.from_arrays([pa.array([task], pa.int32()), pa.array([k], pa.int32()), pa.array([np.concatenate(ids).astype("<i8").tobytes()]), pa.array([np.concatenate(held).tobytes()])], ["task", "k", "ids", "data"])

        for batch in batches:
            x = sound_rows(batch, n)
            x = np.full((batch.num_rows, n), np.nan) if x is None else x
            of = batch.column("row_id").to_numpy()
            while len(x):
                some = most - size
                ids.append(of[:some])
                held.append(x[:some])
                size += len(held[-1])
                x, of = x[some:], of[some:]
                if size == most:
                    yield block()
                    ids, held, size, k = [], [], 0, k + 1
        if size:
            yield block()

    written = durable(a.df.select("row_id", "vec").mapInArrow(timed(a.df.sparkSession, kernel), "task int, k int, ids binary, data binary"))
    counts = written.groupBy("task").agg(F.count("*").alias("c")).orderBy("task").collect()  # a row a task
    first, at = {}, 0
    for r in counts:
        first[r["task"]] = at
        at += r["c"]
    before = a.df.sparkSession.createDataFrame(pd.DataFrame({"task": list(first), "first": list(first.values())}), "task int, first int")
    return written.join(F.broadcast(before), "task").select((F.col("first") + F.col("k")).alias("part"), "ids", "data"), at


def q_direct(a: RowFrame, width: int, before=_same, rows: int | None = None, small: int = SMALL_BYTES // 4) -> tuple[RowFrame, np.ndarray]:
    """Q (orthonormal whatever the rank) and R by a sweep up the tree and one down.

    Leaves are blocks of at most ``rows`` rows, so a worker holds one block at a time.  The coefficients of the blocks, n x r each, meet
    them by broadcast where all together are within ``small`` bytes, else by a shuffle.
    """
    spark, n = a.df.sparkSession, a.n
    blocks, count = blocked(a, rows)

    def block_of(data: bytes) -> np.ndarray:
        return before(np.frombuffer(data, np.float64).reshape(-1, n))

    def up(batches):
        for batch in batches:
            for part, ids, data in zip(*(batch.column(c).to_pylist() for c in ("part", "ids", "data")), strict=True):
                yield tree.partial_batch(part, np.linalg.qr(block_of(data), mode="r"), len(ids) // 8)

    levels = tree.tree(blocks.mapInArrow(timed(spark, up), tree.PARTIAL), lambda rs: r_of(*rs))
    top = tree.ordered(levels[-1].collect())
    out = np.zeros((width, width))
    if not top:
        a.m = 0
        return RowFrame(spark.createDataFrame([], ROW_SCHEMA), width, 0), out
    a.m = sum(x.seen for x in top)
    q, r = np.linalg.qr(tree.finite(np.vstack([tree.matrix_of(x) for x in top])))
    out[: len(r)] = r
    cuts = np.cumsum([x.rows for x in top])[:-1]
    coefficients = spark.createDataFrame(pd.concat([tree.partial_rows(x.part, b) for x, b in zip(top, np.vsplit(q, cuts), strict=True)]), tree.PARTIAL)

    def down(kids: pd.DataFrame, mine: pd.DataFrame) -> pd.DataFrame:
        rows_ = tree.ordered(kids.itertuples())
        q_ = np.linalg.qr(np.vstack([tree.matrix_of(x) for x in rows_]))[0] @ tree.matrix_of(next(mine.itertuples()))
        parts = np.vsplit(q_, np.cumsum([x.rows for x in rows_])[:-1])
        return pd.concat([tree.partial_rows(x.part, p) for x, p in zip(rows_, parts, strict=True)])

    for level in reversed(levels[:-1]):
        left = level.withColumn("bucket", F.floor(F.col("part") / tree.FAN_IN).cast("int"))
        coefficients = durable(left.groupBy("bucket").cogroup(coefficients.withColumn("bucket", F.col("part")).groupBy("bucket")).applyInPandas(timed(spark, down), tree.PARTIAL))
    rank = q.shape[1]
    known = coefficients.select("part", F.col("rows").alias("crows"), F.col("data").alias("c"))
    if count * width * rank * 8 <= small:
        known = F.broadcast(known)

    def rows_out(batches):
        for batch in batches:
            for ids, data, height, c in zip(*(batch.column(x).to_pylist() for x in ("ids", "data", "crows", "c")), strict=True):
                yield row_batch(np.frombuffer(ids, "<i8"), np.linalg.qr(block_of(data))[0] @ np.frombuffer(c, np.float64).reshape(height, -1))

    return RowFrame(blocks.join(known, "part").mapInArrow(timed(spark, rows_out), ROW_SCHEMA), rank, a.m), out


def pivot_block(a: RowFrame) -> np.ndarray:
    """n rows of a tall matrix that a tournament of partial pivoting picks; a times its inverse is a lower-trapezoidal tracker."""
    partials = tree.folded(a, lambda held, x: pivot_rows(np.vstack((held, x))), (0, a.n))
    found, a.m = tree.merged(partials, lambda xs: pivot_rows(np.vstack(xs)), a.tasks, 8 * a.n * a.n)
    return np.zeros((0, a.n)) if found is None else tree.finite(found)
