"""Measures of accuracy: spectral residual, defects of orthonormality, range error, scaling exponents."""

from __future__ import annotations

from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..cost import timed
from ..matrix import EntryFrame, RowFrame, rows_of
from ..session import durable
from . import gram
from . import reduce as tree
from .products import Matrix, dense, multiply, multiply_t
from .thin import SVDResult


def _power_method(spark, pairs: DataFrame, n: int, r: int, image, w: np.ndarray, iterations: int, seed: int) -> float:
    """Power method on A - U W with one scan a step.  ``image(batch, x, wx, total)`` adds what a batch of (row of A, row of U) gives to E*E x."""
    x = np.random.default_rng(seed).standard_normal(n)
    x /= np.linalg.norm(x)
    size, tasks = 0.0, pairs.rdd.getNumPartitions()
    for _ in range(iterations):
        sent = spark.sparkContext.broadcast((x, w @ x))

        def kernel(batches, sent=sent):
            from pyspark import TaskContext

            total = np.zeros(n + r)
            for batch in batches:
                if batch.num_rows:
                    image(batch, *sent.value, total)
            yield tree.partial_batch(TaskContext.get().partitionId(), total[None, :])

        got, _ = tree.merged(pairs.mapInArrow(timed(spark, kernel), tree.PARTIAL), lambda xs: np.sum(xs, axis=0), tasks, 8 * (n + r))
        got = tree.finite(np.zeros((1, n + r)) if got is None else got)[0]
        z = got[:n] - w.T @ got[n:]
        size = float(np.linalg.norm(z))
        if size == 0:
            break
        x = z / size
    return float(np.sqrt(size))


def _residual_by_rows(a: RowFrame, u: RowFrame, w: np.ndarray, iterations: int, seed: int) -> float:
    n, r = a.n, u.n
    pairs = durable(a.df.select("row_id", "vec").join(u.df.select("row_id", F.col("vec").alias("u")), "row_id").select("vec", "u"))

    def image(batch, x, wx, total):
        vec, uu = rows_of(batch, n), rows_of(batch, r, "u") if r else np.zeros((batch.num_rows, 0))
        y = vec @ x - uu @ wx
        total[:n] += vec.T @ y
        total[n:] += uu.T @ y

    return _power_method(a.df.sparkSession, pairs, n, r, image, w, iterations, seed)


def _residual_by_entries(a: EntryFrame, u: RowFrame, w: np.ndarray, iterations: int, seed: int) -> float:
    """A row's entries stay entries: written once beside the row of U, they are scanned in each step; nothing is made dense but vectors."""
    n, r = a.n, u.n
    sparse = a.df.groupBy("i").agg(F.collect_list(F.struct("j", "v")).alias("e"))
    pairs = sparse.join(u.df.select(F.col("row_id").alias("i"), F.col("vec").alias("u")), "i", "full")
    pairs = durable(pairs.select(F.coalesce(F.col("e.j"), F.array().cast("array<bigint>")).alias("j"), F.coalesce(F.col("e.v"), F.array().cast("array<double>")).alias("v"), F.coalesce("u", F.array_repeat(F.lit(0.0), r)).alias("u")))

    def image(batch, x, wx, total):
        j, v = (batch.column(c).flatten().to_numpy(zero_copy_only=False) for c in ("j", "v"))
        of = np.repeat(np.arange(batch.num_rows), np.diff(batch.column("j").offsets.to_numpy()))
        uu = rows_of(batch, r, "u") if r else np.zeros((batch.num_rows, 0))
        y = np.bincount(of, v * x[j], batch.num_rows) - uu @ wx
        total[:n] += np.bincount(j, v * y[of], n)
        total[n:] += uu.T @ y

    return _power_method(a.df.sparkSession, pairs, n, r, image, w, iterations, seed)


def _residual(a: Matrix, u: RowFrame, w: np.ndarray, iterations: int, seed: int) -> float:
    if isinstance(a, RowFrame):
        return _residual_by_rows(a, u, w, iterations, seed)
    return _residual_by_entries(a if isinstance(a, EntryFrame) else a.to_entries(), u, w, iterations, seed)


def spectral_residual(a: Matrix, result: SVDResult, iterations: int = 20, seed: int = 1) -> float:
    """Spectral norm of A - U diag(sigma) V* by the power method: a lower bound that ``iterations`` steps make close."""
    return _residual(a, result.U, result.sigma[:, None] * result.v_dense(a.n).T, iterations, seed)


def range_residual(a: Matrix, q: RowFrame, iterations: int = 20, seed: int = 1) -> float:
    """Spectral norm of A - Q Q* A."""
    return _residual(a, q, dense(multiply_t(a, q), a.n).T, iterations, seed)


def gram_defect(u: RowFrame | np.ndarray) -> float:
    """Largest entry, in magnitude, of U*U - I."""
    g = u.T @ u if isinstance(u, np.ndarray) else gram.gram_matrix(u)
    return float(np.abs(g - np.eye(len(g))).max(initial=0.0))


@dataclass
class AccuracyReport:
    residual: float
    iterations: int
    u_defect: float
    v_defect: float
    rank: int
    excess: float | None = None

    def df(self, spark) -> DataFrame:
        return spark.createDataFrame(pd.DataFrame([asdict(self)]))


def report(a: Matrix, result: SVDResult, sigma: np.ndarray | None = None, iterations: int = 20) -> AccuracyReport:
    """All measures; with the true singular values, also the residual over the least possible one."""
    residual = spectral_residual(a, result, iterations)
    best = kernels.optimal_error(sigma, result.rank) if sigma is not None else 0.0
    v = result.V if isinstance(result.V, RowFrame) else np.asarray(result.V)
    return AccuracyReport(residual, iterations, gram_defect(result.U), gram_defect(v), result.rank, residual / best if best else None)


def sigma_error(found: np.ndarray, true: np.ndarray) -> float:
    """Largest error of a singular value over the largest true one; missing ones count as zero."""
    n = max(len(found), len(true))
    pad = lambda s: np.concatenate((s, np.zeros(n - len(s))))
    return float(np.abs(pad(found) - pad(true)).max(initial=0) / max(true.max(initial=0), np.finfo(float).tiny))


def scaling_slope(costs: DataFrame, size: str, cost: str) -> float:
    """Exponent of cost in size: slope of the logarithms."""
    return float(costs.agg(F.regr_slope(F.log(cost), F.log(size))).first()[0])


__all__ = ["AccuracyReport", "gram_defect", "multiply", "range_residual", "report", "scaling_slope", "sigma_error", "spectral_residual"]
