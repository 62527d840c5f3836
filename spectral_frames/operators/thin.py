"""Singular value decomposition of tall matrices whose rows fit on a machine.

Two cores, each with one or two orthonormalisation passes: ``mixed_qr`` mixes the columns at random, factors by
a merge tree and drops what the diagonal of R shows to be zero; ``gram`` takes eigenvectors of A*A, measures
the norms of A V rather than trusting eigenvalues, and normalises by them.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import kernels
from ..matrix import EntryFrame, RowFrame, row_batch
from ..mixing import MixingPlan
from ..session import SMALL_BYTES, durable
from . import gram, tree_qr


@dataclass
class SVDResult:
    """A ~ U diag(sigma) V*.  U: RowFrame with A's row_id; V: n x r in memory, or a RowFrame by column where n is large."""

    U: RowFrame
    sigma: np.ndarray
    V: np.ndarray | RowFrame
    requested: int
    working_precision: float
    core: str
    passes: int
    seed: int = 0
    stats: dict = field(default_factory=dict)

    @property
    def rank(self) -> int:
        return len(self.sigma)

    @property
    def spark(self) -> SparkSession:
        return self.U.df.sparkSession

    def v_numpy(self) -> np.ndarray:
        return self.V.collect() if isinstance(self.V, RowFrame) else self.V

    def v_dense(self, n: int) -> np.ndarray:
        """V in memory, n rows; those of columns without entries are zero."""
        if not isinstance(self.V, RowFrame):
            return self.V
        out = np.zeros((n, self.rank))
        for r in self.V.df.collect():
            out[r["row_id"]] = r["vec"]
        return out

    def sigma_df(self) -> DataFrame:
        frame = pd.DataFrame({"k": np.arange(1, self.rank + 1, dtype=np.int32), "sigma": self.sigma})
        return self.spark.createDataFrame(frame, "k int, sigma double")

    def v_df(self) -> DataFrame:
        """(j, vec): the rows of V."""
        if isinstance(self.V, RowFrame):
            return self.V.df.select(F.col("row_id").alias("j"), "vec")
        frame = pd.DataFrame({"j": np.arange(len(self.V)), "vec": [r.tolist() for r in self.V]})
        return self.spark.createDataFrame(frame, "j long, vec array<double>")

    def truncate(self, k: int) -> SVDResult:
        k = min(k, self.rank)
        cut = RowFrame(self.U.df.select("row_id", F.slice("vec", 1, k).alias("vec")), k, self.U.m, tasks=self.U.tasks)
        v = RowFrame(self.V.df.select("row_id", F.slice("vec", 1, k).alias("vec")), k, self.V.m) if isinstance(self.V, RowFrame) else self.V[:, :k]
        return SVDResult(cut, self.sigma[:k], v, self.requested, self.working_precision, self.core, self.passes, self.seed, dict(self.stats))

    def reconstruct(self) -> RowFrame:
        """U diag(sigma) V*, by rows."""
        return times_small(self.U, self.sigma[:, None] * self.v_numpy().T)

    def project(self, rows: RowFrame) -> RowFrame:
        """Scores of new rows: rows V."""
        return times_small(rows, self.v_numpy())

    def save(self, path: str) -> None:
        self.U.df.write.parquet(f"{path}/u")
        self.v_df().write.parquet(f"{path}/v")
        meta = pd.DataFrame({"k": np.arange(1, self.rank + 1, dtype=np.int32), "sigma": self.sigma})
        meta = meta.assign(requested=self.requested, working_precision=self.working_precision, core=self.core, passes=self.passes, seed=self.seed)
        self.spark.createDataFrame(meta).write.parquet(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> SVDResult:
        meta = spark.read.parquet(f"{path}/meta").toPandas().sort_values("k")
        r, m = len(meta), meta.iloc[0]
        v = RowFrame(spark.read.parquet(f"{path}/v").withColumnRenamed("j", "row_id"), r).collect()
        return SVDResult(RowFrame(spark.read.parquet(f"{path}/u"), r), meta.sigma.to_numpy(), v, int(m.requested), float(m.working_precision), m.core, int(m.passes), int(m.seed))


def times_small(a: RowFrame, w: np.ndarray) -> RowFrame:
    """A W for a W of checked size, lazily."""
    if w.nbytes > SMALL_BYTES:
        raise ValueError(f"a factor of {w.nbytes} bytes is too large to broadcast; use products.multiply")
    sent = a.df.sparkSession.sparkContext.broadcast(np.ascontiguousarray(w))
    return tree_qr.apply_rows(a, lambda x: x @ sent.value, w.shape[1])


def scale_columns(a: RowFrame, d: np.ndarray) -> RowFrame:
    """A diag(d), in a Catalyst expression for narrow rows."""
    if a.n <= 64:
        factor = F.array(*[F.lit(float(x)) for x in d])
        return RowFrame(a.df.select("row_id", F.zip_with("vec", factor, lambda x, y: x * y).alias("vec")), a.n, a.m, tasks=a.tasks)
    return tree_qr.apply_rows(a, lambda x: x * d, a.n)


def stored(a: RowFrame) -> RowFrame:
    """Written, read from there; how many tasks read it is known."""
    df = durable(a.df.select("row_id", "vec"))
    return RowFrame(df, a.n, a.m, tasks=df.rdd.getNumPartitions())


def _empty(a: RowFrame, result: dict) -> SVDResult:
    none = RowFrame(a.df.select("row_id", F.array().cast("array<double>").alias("vec")), 0, a.m)
    return SVDResult(none, np.zeros(0), np.zeros((a.n, 0)), **result)


def _finish(u: RowFrame, turn: np.ndarray, sigma: np.ndarray, v: np.ndarray, result: dict, stats: dict) -> SVDResult:
    sign = kernels.canonical(v)
    return SVDResult(times_small(u, turn * sign), sigma, v * sign, stats=stats, **result)


def mixed_factor(a: RowFrame, plan: MixingPlan, wp: float, first=lambda x: x):
    """One pass over the rows ``first`` makes of a's: what turns such a row into one of Q (None at rank zero), and R's kept rows.  ``a.m`` is known afterwards."""
    before = lambda x: plan.forward(first(x))
    r = tree_qr.r_factor(a, plan.width, before)
    keep = kernels.retain_by_diagonal(r, wp)
    return (tree_qr.substitution(r, keep, before) if len(keep) else None), r[keep]


def _direct(a: RowFrame, wp: float, *how) -> tuple[RowFrame, np.ndarray]:
    """Kept columns of Q by a sweep up the tree and one down, and R's kept rows."""
    q, r = tree_qr.q_direct(a, *how)
    keep = kernels.retain_by_diagonal(r, wp)
    return tree_qr.apply_rows(q, lambda x: x[:, keep], len(keep)), r[keep]


def _mixed_qr(a: RowFrame, passes: int, wp: float, plan: MixingPlan, q_form: str, result: dict) -> SVDResult:
    if q_form == "direct" or q_form == "auto" and passes == 1:
        (q, t), scans = _direct(a, wp, plan.width, plan.forward), 3
        if not len(t):
            return _empty(a, result)
    else:
        f, t = mixed_factor(a, plan, wp)
        if f is None:
            return _empty(a, result)
        q, scans = tree_qr.apply_rows(a, f, len(t)), 2
    kept = len(t)
    if passes == 2 and q_form == "direct":
        q, r2 = _direct(q, wp, kept)  # its blocks are the one copy that all sweeps read
        t = r2 @ t
    elif passes == 2:
        q = stored(q)  # both consumers below must read the same copy
        r2 = tree_qr.r_factor(q)
        keep2 = kernels.retain_by_diagonal(r2, wp)
        q = tree_qr.solved(q, r2, keep2)
        t = r2[keep2] @ t
    u, sigma, v = kernels.exact_svd(t)
    v = plan.inverse(v.T).T
    return _finish(q, u, sigma, v, result, {"scans": scans, "kept_first": kept})


def _gram(a: RowFrame, passes: int, wp: float, normalise: str, result: dict) -> SVDResult:
    b = gram.gram_matrix(a)
    v = kernels.eigen(b)
    if normalise == "eigenvalue":  # what trusting the eigenvalues gives: left vectors that may have no length
        values = np.linalg.eigvalsh((b + b.T) / 2)[::-1]
        norms = np.sqrt(np.maximum(values, 0))
        keep = np.flatnonzero((norms > 0) & (norms >= norms.max(initial=0) * 1e-9))
        if not len(keep):
            return _empty(a, result)
        return _finish(a, v[:, keep] / norms[keep], norms[keep], v[:, keep], result, {"scans": 2})
    del b  # as large as v
    norms = gram.projected_norms(a, v)
    keep = kernels.retain_by_norm(norms, wp)
    if not len(keep):
        return _empty(a, result)
    keep = keep[np.argsort(-norms[keep], kind="stable")]
    v, norms = v[:, keep], norms[keep]
    if passes == 1:
        return _finish(a, v / norms, norms, v, result, {"scans": 3})
    y = stored(times_small(a, v / norms))
    w = kernels.eigen(gram.gram_matrix(y))
    lengths = gram.projected_norms(y, w)
    keep2 = kernels.retain_by_norm(lengths, wp)
    w, lengths = w[:, keep2], lengths[keep2]
    p, sigma, v2 = kernels.exact_svd((lengths[:, None] * w.T * norms) @ v.T)
    q = times_small(y, w / lengths)
    return _finish(q, p, sigma, v2, result, {"scans": 3, "kept_first": len(keep)})


def _through_transpose(a: RowFrame, options: dict, result: dict) -> SVDResult:
    """A matrix with fewer rows than columns (so few that the driver knows them): the factors of its transpose, exchanged."""
    spark = a.df.sparkSession
    ids = np.sort(a.df.select("row_id").toPandas()["row_id"].to_numpy(np.int64))
    places = F.broadcast(spark.createDataFrame(pd.DataFrame({"i": ids, "place": np.arange(len(ids))}), "i long, place long"))
    turned = EntryFrame(a.to_entries().df.join(places, "i").select(F.col("j").alias("i"), F.col("place").alias("j"), "v"), len(ids), a.n).to_rows()
    found = thin_svd(stored(turned), wide="keep", **options)
    if not found.rank:
        return _empty(a, result)
    v = np.zeros((a.n, found.rank))
    for r in found.U.df.collect():  # a.n rows, as wide as there are rows in A
        v[r["row_id"]] = r["vec"]
    sign = kernels.canonical(v)
    u = spark.createDataFrame(pa.Table.from_batches([row_batch(ids, found.v_numpy() * sign)]))
    return SVDResult(RowFrame(u, found.rank, len(ids)), found.sigma, v * sign, stats=found.stats | {"transposed": True}, **result)


def thin_svd(
    a: RowFrame, core: str = "mixed_qr", passes: int = 2, working_precision: float = 1e-11, mixing: str = "fourier", rounds: int | str = 2,
    q_form: str = "auto", normalise: str = "explicit", seed: int = 0, widest: int = 10_000, wide: str = "transpose",
) -> SVDResult:
    """SVD of a tall matrix.

    ``working_precision`` decides a priori what counts as zero (0: only exact zeros).  ``q_form``: "indirect" substitutes against R, "direct"
    sweeps the tree back down, in each pass; "auto" is direct for one pass.  ``normalise="eigenvalue"`` is the ablation without measured norms.
    ``wide``: a matrix with more columns than rows is factored through its transpose, or "raise", or "keep" (factored as it stands).
    Ragged rows, nulls, NaN and infinities raise ValueError.
    """
    if core not in ("mixed_qr", "gram") or passes not in (1, 2) or wide not in ("transpose", "raise", "keep") or q_form not in ("auto", "direct", "indirect"):
        raise ValueError("core is mixed_qr or gram, passes 1 or 2, wide one of transpose, raise and keep, q_form one of auto, direct and indirect")
    if not 0 <= working_precision < 1:
        raise ValueError("working_precision lies in [0, 1)")
    if a.n > widest:
        raise ValueError(f"rows of {a.n} are over the driver's limit of {widest}; use low_rank_svd")
    result = {"requested": a.n, "working_precision": working_precision, "core": core, "passes": passes, "seed": seed}
    if wide != "keep" and (a.df.limit(a.n).count() if a.m is None else a.m) < a.n:
        a.m = a.df.count()
        if wide == "raise":
            raise ValueError(f"a matrix of {a.m} rows and {a.n} columns is not tall")
        if a.m:
            a.checked()
            options = {"core": core, "passes": passes, "working_precision": working_precision, "mixing": mixing, "rounds": rounds, "q_form": q_form, "normalise": normalise, "seed": seed, "widest": widest}
            return _through_transpose(a, options, result)
    if core == "gram":
        return _gram(a, passes, working_precision, normalise, result)
    return _mixed_qr(a, passes, working_precision, MixingPlan.build(a.n, seed, rounds, mixing), q_form, result)


def as_qr(result: SVDResult) -> tuple[RowFrame, np.ndarray]:
    """Q = U and the square R = diag(sigma) V*: an SVD read as an orthogonal factorisation."""
    return result.U, result.sigma[:, None] * result.v_numpy().T
