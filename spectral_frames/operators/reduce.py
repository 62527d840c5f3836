"""Sums and merges of per-task partial results by trees of bounded fan-in."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cost import timed
from ..matrix import RowFrame, sound_rows
from ..session import SMALL_BYTES, durable

#: Children of a node.
FAN_IN = 16
PARTIAL = "part int, seen long, rows int, cols int, data binary"


def partial_rows(part: int, x: np.ndarray, seen: int = 0) -> pd.DataFrame:
    """One partial: a matrix and how many rows of the input it stands for."""
    x = np.ascontiguousarray(x, dtype=np.float64)
    return pd.DataFrame({"part": [part], "seen": [seen], "rows": [x.shape[0]], "cols": [x.shape[1]], "data": [x.tobytes()]})


def partial_batch(part: int, x: np.ndarray, seen: int = 0) -> pa.RecordBatch:
    x = np.ascontiguousarray(x, dtype=np.float64)
    columns = [pa.array([v], kind) for v, kind in ((part, pa.int32()), (seen, pa.int64()), (x.shape[0], pa.int32()), (x.shape[1], pa.int32()), (x.tobytes(), pa.binary()))]
    return pa.RecordBatch.from_arrays(columns, ["part", "seen", "rows", "cols", "data"])


def matrix_of(r) -> np.ndarray:
    return np.frombuffer(r.data, np.float64).reshape(r.rows, r.cols)


def ordered(rows) -> list:
    return sorted(rows, key=lambda r: r.part)


def folded(a: RowFrame, step, shape: tuple[int, int], block: int = 8192) -> DataFrame:
    """A partial per task: ``step(state, rows)`` over blocks of its rows, from zeros of ``shape``.  Rows that are ragged or hold nulls leave NaN."""
    n = a.n

    def kernel(batches):
        from pyspark import TaskContext

        state, seen = np.zeros(shape), 0
        for batch in batches:
            x = sound_rows(batch, n)
            if x is None:
                state, seen = np.full((max(1, shape[0]), shape[1]), np.nan), 1
                break
            for lo in range(0, len(x), block):
                state = step(state, x[lo : lo + block])
            seen += len(x)
        if seen:
            yield partial_batch(TaskContext.get().partitionId(), state, seen)

    return a.df.select("vec").mapInArrow(timed(a.df.sparkSession, kernel), PARTIAL)


def _level(partials: DataFrame, merge, fan_in: int) -> DataFrame:
    def node(frame: pd.DataFrame) -> pd.DataFrame:
        kids = ordered(frame.itertuples())
        return partial_rows(kids[0].part // fan_in, merge([matrix_of(r) for r in kids]), sum(r.seen for r in kids))

    grouped = partials.withColumn("bucket", F.floor(F.col("part") / fan_in).cast("int")).groupBy("bucket")
    return grouped.applyInPandas(timed(partials.sparkSession, node), PARTIAL)


def tree(partials: DataFrame, merge, fan_in: int = FAN_IN) -> list[DataFrame]:
    """Levels of a merge tree over ``partials``, each durable, for sweeps that come back down; the last has at most fan_in rows.

    merge: a list of matrices, in the order of their parts, to one.
    """
    levels = [durable(partials)]
    while levels[-1].count() > fan_in:
        levels.append(durable(_level(levels[-1], merge, fan_in)))
    return levels


def merged(partials: DataFrame, merge, tasks: int | None = None, size: int = 0, fan_in: int = FAN_IN) -> tuple[np.ndarray | None, int]:
    """What ``merge`` makes of all partials, and the rows that they stand for; None if there are none.

    ``tasks``: the number of tasks, where it is known.  The levels of the tree are chained in one job then; else the partials are
    written and counted first.  The driver meets fan_in partials, or all where they are ``size`` bytes each and within a quarter of SMALL_BYTES.
    """
    if tasks is None:
        partials = durable(partials)
        tasks = partials.count()
    while tasks > fan_in and (not size or tasks * size > SMALL_BYTES // 4):
        partials = _level(partials, merge, fan_in)
        tasks = -(-tasks // fan_in)
    rows = ordered(partials.collect())
    if not rows:
        return None, 0
    return merge([matrix_of(r) for r in rows]), sum(r.seen for r in rows)


def added(xs: list[np.ndarray]) -> np.ndarray:
    """The sum of matrices, in their order, with room for one more beside them."""
    out = xs[0].copy()
    for x in xs[1:]:
        out += x
    return out


def total(a: RowFrame, step, shape: tuple[int, int]) -> np.ndarray:
    """Sum over all rows of what ``step`` adds up; a non-finite sum raises ValueError.  ``a.m`` is known afterwards."""
    found, seen = merged(folded(a, step, shape), added, a.tasks, 8 * shape[0] * shape[1])
    a.m = seen
    return finite(np.zeros(shape) if found is None else found)


def finite(x: np.ndarray) -> np.ndarray:
    if not np.isfinite(x).all():
        raise ValueError("a row is ragged, or holds null, NaN or infinity, or values whose products overflow")
    return x
