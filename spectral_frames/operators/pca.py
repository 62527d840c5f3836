"""Principal components: a thin SVD of centred columns."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession

from ..matrix import RowFrame
from . import reduce as tree
from .thin import SVDResult, scale_columns, thin_svd
from .tree_qr import apply_rows


def column_sums(a: RowFrame, centre: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, int]:
    """Sums and sums of squares of the columns (of their differences from centre), and the number of rows."""
    n = a.n
    c = np.zeros(n) if centre is None else centre

    def step(state: np.ndarray, x: np.ndarray) -> np.ndarray:
        x = x - c
        return state + np.stack((x.sum(axis=0), (x * x).sum(axis=0)))

    s = tree.total(a, step, (2, n))
    return s[0], s[1], a.m


@dataclass
class PCAResult:
    svd: SVDResult
    mean: np.ndarray
    scale: np.ndarray
    m: int

    @property
    def explained_variance(self) -> np.ndarray:
        return self.svd.sigma**2 / max(1, self.m - 1)

    @property
    def explained_ratio(self) -> np.ndarray:
        return self.svd.sigma**2 / max((self.svd.sigma**2).sum(), np.finfo(float).tiny)

    def scores(self) -> RowFrame:
        return scale_columns(self.svd.U, self.svd.sigma)

    def save(self, path: str) -> None:
        """The factorisation, and the mean and scale that new rows need."""
        self.svd.save(path)
        frame = pd.DataFrame({"j": np.arange(len(self.mean)), "mean": self.mean, "scale": self.scale, "m": self.m})
        self.svd.spark.createDataFrame(frame, "j long, mean double, scale double, m long").write.parquet(f"{path}/centre")

    @staticmethod
    def load(spark: SparkSession, path: str) -> PCAResult:
        centre = spark.read.parquet(f"{path}/centre").toPandas().sort_values("j")  # a row a column
        return PCAResult(SVDResult.load(spark, path), centre["mean"].to_numpy(), centre["scale"].to_numpy(), int(centre["m"].iloc[0]))

    def transform(self, rows: RowFrame) -> RowFrame:
        """Scores of new rows."""
        mean, scale, v = self.mean, self.scale, self.svd.v_numpy()
        return apply_rows(rows, lambda x: ((x - mean) / scale) @ v, v.shape[1])


def pca(a: RowFrame, k: int | None = None, core: str = "mixed_qr", passes: int = 2, center: bool = True, scale: bool = False, **options) -> PCAResult:
    """Columns are centred by subtraction, before any product is formed; subtracting a mean's square from a Gram matrix would cancel."""
    total, squares, m = column_sums(a)
    mean = total / max(1, m) if center else np.zeros(a.n)
    spread = np.ones(a.n)
    if scale:
        _, squares, _ = column_sums(a, mean)
        spread = np.sqrt(squares / max(1, m - 1))
        spread[spread == 0] = 1.0
    centred = apply_rows(a, lambda x: (x - mean) / spread, a.n)
    found = thin_svd(centred, core, passes, **options)
    return PCAResult(found.truncate(k) if k else found, mean, spread, m)
