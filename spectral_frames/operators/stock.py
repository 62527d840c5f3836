"""The stock implementations to compare with.  MLlib's distributed matrices are RDDs, and only here are they used."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..matrix import RowFrame, from_numpy
from .thin import SVDResult


def _indexed(a: RowFrame):
    from pyspark.mllib.linalg.distributed import IndexedRow, IndexedRowMatrix

    return IndexedRowMatrix(a.df.select("row_id", "vec").rdd.map(lambda r: IndexedRow(r[0], r[1])))


def stock_thin(a: RowFrame, k: int | None = None, r_cond: float = 1e-9) -> SVDResult:
    """MLlib's SVD: left vectors are A V / sigma with sigma from eigenvalues, not from measured norms."""
    found = _indexed(a).computeSVD(k or a.n, True, r_cond)
    sigma = np.array(found.s.toArray())
    spark = a.df.sparkSession
    u = spark.createDataFrame(found.U.rows.map(lambda r: (int(r.index), [float(x) for x in r.vector.toArray()])), "row_id long, vec array<double>")
    return SVDResult(RowFrame(u, len(sigma), a.m), sigma, found.V.toArray(), k or a.n, r_cond, "stock", 1)


def stock_low_rank(a: RowFrame, l: int, r_cond: float = 1e-9) -> SVDResult:  # noqa: E741
    """The same call for a few vectors: an Arnoldi loop on the driver with a job per product."""
    return stock_thin(a, l, r_cond)


def stock_tsqr(a: RowFrame) -> tuple[np.ndarray, np.ndarray]:
    """MLlib's tree QR, which breaks down without full rank; Q and R in memory."""
    found = _indexed(a).toRowMatrix().tallSkinnyQR(True)
    return np.array([r.toArray() for r in found.Q.rows.collect()]), found.R.toArray()


def stock_pca(a: RowFrame, k: int) -> np.ndarray:
    """MLlib's principal components, n x k."""
    return _indexed(a).toRowMatrix().computePrincipalComponents(k).toArray()


def ml_pca(a: RowFrame, k: int) -> np.ndarray:
    """The same from the DataFrame API."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    model = PCA(k=k, inputCol="x", outputCol="y").fit(a.df.select(array_to_vector(F.col("vec")).alias("x")))
    return model.pc.toArray()


def exact_local(a: RowFrame, largest: int = 50_000_000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """NumPy's SVD of a matrix with at most ``largest`` entries."""
    if a.height() * a.n > largest:
        raise ValueError("too large for the driver")
    u, s, vt = np.linalg.svd(a.collect(), full_matrices=False)
    return u, s, vt.T


def pivoted_tree_qr(a: RowFrame, k: int) -> np.ndarray:
    """Indices of k columns that a tournament of pivoted factorisations picks, on the R factor of A."""
    from .tree_qr import r_factor

    def best(r: np.ndarray, cols: np.ndarray) -> np.ndarray:
        x, left, chosen = r[:, cols].copy(), cols.tolist(), []
        while left and len(chosen) < k:
            p = int((x * x).sum(axis=0).argmax())
            size = np.linalg.norm(x[:, p])
            if size == 0:
                break
            q = x[:, p] / size
            chosen.append(left.pop(p))
            x = np.delete(x, p, axis=1)
            x -= np.outer(q, q @ x)
        return np.array(chosen, int)

    r = r_factor(a)
    teams = [np.arange(lo, min(lo + 2 * k, a.n)) for lo in range(0, a.n, 2 * k)]
    while len(teams) > 1:
        won = [best(r, t) for t in teams]
        teams = [np.concatenate(won[i : i + 2]) for i in range(0, len(won), 2)]
    return best(r, teams[0])


__all__ = ["exact_local", "from_numpy", "ml_pca", "pivoted_tree_qr", "stock_low_rank", "stock_pca", "stock_thin", "stock_tsqr"]
