"""Products of a matrix in any layout with a tall factor held by rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..matrix import ROW_SCHEMA, EntryFrame, RowFrame, SparseRowFrame, TileFrame, row_batch
from ..session import SMALL_BYTES
from . import reduce as tree
from .thin import times_small

Matrix = RowFrame | SparseRowFrame | EntryFrame | TileFrame


#: Bytes up to which a factor joins entries by broadcast.
BROADCAST_BYTES = SMALL_BYTES // 4
#: Sparse tiles of a band that a part of it has at most; each part gets the band's rows of a factor once.
BAND_TILES = 1024


def dense(q: RowFrame, rows: int) -> np.ndarray:
    """A factor of checked size in the driver's memory, absent rows zero."""
    if rows * q.n * 8 > SMALL_BYTES:
        raise ValueError(f"a factor of {rows * q.n * 8} bytes is too large for the driver")
    out = np.zeros((rows, q.n))
    table = q.df.select("row_id", "vec").toArrow()
    if table.num_rows:
        out[table.column("row_id").to_numpy()] = np.asarray(table.column("vec").combine_chunks().flatten()).reshape(-1, q.n)
    return out


def from_dense(spark, x: np.ndarray) -> RowFrame:
    return RowFrame(spark.createDataFrame(pa.Table.from_batches([row_batch(np.arange(len(x)), x)])), x.shape[1], len(x))


def multiply(a: Matrix, q: RowFrame) -> RowFrame:
    """A Q, with q's row_id the columns of A; rows of zeros may be absent.

    Entries meet a factor of up to BROADCAST_BYTES where they lie; a larger one by a shuffle, in which adaptive execution splits hot columns.
    """
    if isinstance(a, RowFrame):
        if a.n * q.n * 8 > SMALL_BYTES:
            return multiply(a.to_entries(), q)
        return times_small(a, dense(q, a.n))
    if isinstance(a, TileFrame):
        return _tiles(a, q)
    if isinstance(a, SparseRowFrame):
        a = a.to_entries()
    factor = q.df.select(F.col("row_id").alias("j"), "vec")
    joined = a.df.join(F.broadcast(factor) if a.n * q.n * 8 <= BROADCAST_BYTES else factor, "j")
    sums = joined.groupBy("i").agg(*[F.sum(F.col("v") * F.col("vec")[k]).alias(f"s{k}") for k in range(q.n)])
    return RowFrame(sums.select(F.col("i").alias("row_id"), F.array(*[F.col(f"s{k}") for k in range(q.n)]).alias("vec")), q.n, a.m)


def multiply_t(a: Matrix, q: RowFrame) -> RowFrame:
    """A* Q, with q's row_id the rows of A; the result is by columns of A."""
    if isinstance(a, EntryFrame):
        a.height()
        return multiply(a.transpose(), q)
    if isinstance(a, TileFrame):
        return _tiles(a, q, turned=True)
    if isinstance(a, SparseRowFrame):
        return _sparse_rows_t(a, q)
    n, r = a.n, q.n
    if n * r * 8 > SMALL_BYTES:
        return multiply_t(a.to_entries(), q)
    both = RowFrame(a.df.select("row_id", "vec").join(q.df.select("row_id", F.col("vec").alias("q")), "row_id").select("row_id", F.concat("vec", "q").alias("vec")), n + r)
    return from_dense(a.df.sparkSession, tree.total(both, lambda s, x: s + x[:, :n].T @ x[:, n:], (n, r)))


def _sparse_rows_t(a: SparseRowFrame, q: RowFrame) -> RowFrame:
    """A* Q by sparse rows: a partial sum a task, as large as the result; columns without entries are left out."""
    n, r = a.n, q.n
    if n * (r + 1) * 8 > SMALL_BYTES // tree.FAN_IN:
        return multiply_t(a.to_entries(), q)
    both = a.df.join(q.df.select("row_id", F.col("vec").alias("q")), "row_id").select("at", "val", "q")

    def kernel(batches):
        from pyspark import TaskContext

        total = np.zeros((n, r + 1))
        for batch in batches:
            at, val = (batch.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("at", "val"))
            of = np.repeat(np.arange(batch.num_rows), np.diff(batch.column("at").offsets.to_numpy()))
            x = np.asarray(batch.column("q").flatten()).reshape(-1, r)
            for k in range(r):
                total[:, k] += np.bincount(at, val * x[of, k], n)
            total[:, r] += np.bincount(at, minlength=n)
        yield tree.partial_batch(TaskContext.get().partitionId(), total)

    found, _ = tree.merged(both.mapInArrow(kernel, tree.PARTIAL), lambda xs: np.sum(xs, axis=0), None, 8 * n * (r + 1))
    found = tree.finite(np.zeros((n, r + 1)) if found is None else found)
    there = np.flatnonzero(found[:, r])
    return RowFrame(a.df.sparkSession.createDataFrame(pa.Table.from_batches([row_batch(there, found[there, :r])])), r, n)


def through_rows(a: RowFrame, f, r: int) -> RowFrame:
    """A* f(A) for a function of blocks of rows with r columns, in one scan: nothing of f(A) is kept, and A is not joined with it."""
    return from_dense(a.df.sparkSession, tree.total(a, lambda s, x: s + x.T @ f(x), (a.n, r)))


def _tiles(a: TileFrame, q: RowFrame, turned: bool = False) -> RowFrame:
    """Tiles meet the band of q that they multiply; partial bands are summed by row."""
    across, down = (a.rows, a.cols) if turned else (a.cols, a.rows)
    r = q.n
    tiles = a.df.withColumns({"band": F.col("bi" if turned else "bj"), "out": F.col("bj" if turned else "bi")})
    rows = q.df.select(F.floor(F.col("row_id") / across).cast("int").alias("band"), "row_id", "vec")

    def kernel(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                t = np.asarray(batch.column("data").slice(k, 1).flatten()).reshape(batch.column("nrows")[k].as_py(), batch.column("ncols")[k].as_py())
                t = t.T if turned else t
                x = batch.column("q").slice(k, 1).flatten()
                band = np.zeros((t.shape[1], r))
                band[x.field("row_id").to_numpy() - batch.column("band")[k].as_py() * across] = np.asarray(x.field("vec").flatten()).reshape(-1, r)
                yield row_batch(np.arange(len(t)) + batch.column("out")[k].as_py() * down, t @ band)

    def sparse_kernel(batches):  # rows of q come before the tiles that they meet; a batch of tiles at once: work and memory follow the entries
        last, known, vecs = None, np.zeros(0, np.int64), np.zeros((0, r))
        for batch in batches:
            col = lambda c: batch.column(c).to_numpy().astype(np.int64)  # noqa: E731, B023
            group, place, is_tile = np.stack((col("band"), col("part")), axis=1), col("place"), col("role") == 1
            x = batch.filter(pa.array(~is_tile)).column("data")
            known, vecs = np.concatenate((known, place[~is_tile])), np.concatenate((vecs, np.asarray(x.flatten(), np.float64).reshape(-1, r)))
            owner = np.concatenate((np.repeat(last, len(known) - (~is_tile).sum(), axis=0) if last is not None else group[:0], group[~is_tile]))
            ids, first = np.unique(known, return_index=True)
            picked = batch.filter(pa.array(is_tile))
            of = np.repeat(np.flatnonzero(is_tile), np.diff(picked.column("at").offsets.to_numpy()))
            at, v = (picked.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("at", "data"))
            width = col("ncols")[of]
            i, j = at // width, at % width
            if turned:
                i, j = j, i
            i, j = i + place[of] * down, j + group[of, 0] * across
            at = np.minimum(np.searchsorted(ids, j), max(len(ids) - 1, 0))
            met = ids[at] == j if len(ids) else np.zeros(len(j), bool)
            i, at, v = i[met], first[at[met]], v[met]
            out, which = np.unique(i, return_inverse=True)
            if len(out):
                yield row_batch(out, np.stack([np.bincount(which, v * vecs[at, k], len(out)) for k in range(r)], axis=1) if r else np.zeros((len(out), 0)))
            if batch.num_rows:  # the group that the next batch may go on with
                last = group[-1:]
                stay = (owner == last).all(axis=1)
                known, vecs = known[stay], vecs[stay]

    if a.sparse:
        part = F.floor(F.col("out") / BAND_TILES).cast("int").alias("part")
        parts = tiles.select("band", part).distinct()
        sent = rows.join(parts, "band").select("band", "part", F.lit(0).alias("role"), F.col("row_id").alias("place"), F.lit(0).alias("ncols"), F.col("vec").alias("data"), F.array().cast("array<int>").alias("at"))
        sent = sent.unionByName(tiles.select("band", part, F.lit(1).alias("role"), F.col("out").cast("long").alias("place"), "ncols", "data", "at"))
        parts = sent.repartition("band", "part").sortWithinPartitions("band", "part", "role").mapInArrow(sparse_kernel, ROW_SCHEMA)
    else:
        packed = rows.groupBy("band").agg(F.collect_list(F.struct("row_id", "vec")).alias("q"))
        parts = tiles.join(packed, "band").mapInArrow(kernel, ROW_SCHEMA)
    sums = parts.groupBy("row_id").agg(*[F.sum(F.col("vec")[k]).alias(f"s{k}") for k in range(r)])
    return RowFrame(sums.select("row_id", F.array(*[F.col(f"s{k}") for k in range(r)]).alias("vec")), r, a.n if turned else a.m)


__all__ = ["Matrix", "dense", "from_dense", "multiply", "multiply_t", "through_rows"]
