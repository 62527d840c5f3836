"""Low-rank approximation by randomised subspace iteration over either thin core."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession

from .. import kernels
from ..matrix import ROW_SCHEMA, RowFrame, row_batch
from ..mixing import MixingPlan
from ..session import SMALL_BYTES, ship
from . import gram, tree_qr
from .products import Matrix, dense, multiply, multiply_t, through_rows
from .thin import SVDResult, mixed_factor, stored, thin_svd, times_small


def gaussian_frame(spark: SparkSession, n: int, l: int, seed: int = 0, partitions: int | None = None) -> RowFrame:  # noqa: E741
    """n x l independent normals; a row's values follow from the seed and its id, however rows are dealt out."""
    ship(spark)

    def kernel(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            x = np.stack([np.random.Generator(np.random.Philox(key=[seed, int(i)])).standard_normal(l) for i in ids]) if len(ids) else np.zeros((0, l))
            yield row_batch(ids, x)

    rows = spark.range(n, numPartitions=partitions) if partitions else spark.range(n)
    return RowFrame(rows.mapInArrow(kernel, ROW_SCHEMA), l, n)


def track(y: RowFrame, core: str, working_precision: float, tracker: str, seed: int) -> RowFrame:
    """A basis of the columns of y (a written table) while the iteration only follows a subspace; lazily, as the next product reads it once.

    "svd": left vectors of a one-pass thin SVD; "q_only": the orthogonal factor without the small SVD; "lu": the lower factor of a pivoted elimination.
    """
    if tracker == "svd":
        return thin_svd(y, core, 1, working_precision, seed=seed, q_form="indirect", wide="keep").U
    plan = MixingPlan.build(y.n, seed)
    if tracker == "q_only":
        f, r = mixed_factor(y, plan, working_precision)
        return tree_qr.apply_rows(y, f or (lambda x: x[:, :0]), len(r))
    if tracker == "lu":
        r = tree_qr.r_factor(y, plan.width, plan.forward)
        keep = kernels.retain_by_diagonal(r, working_precision)
        mixed = stored(tree_qr.apply_rows(y, lambda x: plan.forward(x)[:, keep], len(keep)))
        s = tree_qr.pivot_block(mixed)
        return tree_qr.apply_rows(mixed, lambda x: np.linalg.solve(s.T, x.T).T, len(keep))
    raise ValueError(f"tracker {tracker!r} is none of svd, q_only, lu")


def _there_and_back(a: RowFrame, q: RowFrame, core: str, working_precision: float, tracker: str, seed: int) -> RowFrame:
    """A* times a tracked basis of A Q, for a matrix by rows: a row of the basis follows from its row of A, so A is scanned and never shuffled."""
    w = dense(q, a.n)
    sent = a.df.sparkSession.sparkContext.broadcast(w)
    if core == "mixed_qr" and tracker in ("svd", "q_only"):
        f, r = mixed_factor(a, MixingPlan.build(q.n, seed), working_precision, lambda x: x @ sent.value)
        turn = kernels.exact_svd(r)[0] if tracker == "svd" and f else np.eye(len(r))
        return through_rows(a, (lambda x: f(x) @ turn) if f else (lambda x: x[:, :0]), len(r))
    if core == "gram" and tracker == "svd":
        y = stored(times_small(a, w))  # narrow beside A
        v = kernels.eigen(gram.gram_matrix(y))
        norms = gram.projected_norms(y, v)
        keep = kernels.retain_by_norm(norms, working_precision)
        turn = w @ (v[:, keep] / norms[keep])
        return through_rows(a, lambda x: x @ turn, len(keep))
    return multiply_t(a, track(stored(times_small(a, w)), core, working_precision, tracker, seed))


def range_finder(a: Matrix, l: int, iterations: int = 2, core: str = "mixed_qr", working_precision: float = 1e-11, seed: int = 0, tracker: str = "svd") -> RowFrame:  # noqa: E741
    """Q, at most l orthonormal columns, whose span nearly holds the range of A; 2 * iterations + 1 passes over A."""
    m, n = a.height(), a.n
    if not 0 < l < min(m, n):
        raise ValueError(f"l = {l} must lie between 0 and min(m, n) = {min(m, n)}, both excluded")
    if iterations < 0:
        raise ValueError("iterations must not be negative")
    q = gaussian_frame(a.df.sparkSession, n, l, seed)
    for step in range(iterations):
        if isinstance(a, RowFrame) and n * l * 8 <= SMALL_BYTES:
            z = _there_and_back(a, q, core, working_precision, tracker, seed + 2 * step)
        else:
            z = multiply_t(a, track(stored(multiply(a, q)), core, working_precision, tracker, seed + 2 * step))
        q = track(stored(z), core, working_precision, tracker, seed + 2 * step + 1)
    return stored(thin_svd(stored(multiply(a, q)), core, 2, working_precision, seed=seed, wide="keep").U)


def project_svd(a: Matrix, q: RowFrame, core: str = "mixed_qr", working_precision: float = 1e-11, seed: int = 0) -> SVDResult:
    """SVD of Q Q* A: the transpose of Q* A is tall, so a thin core factors it, and V stays a table."""
    b = stored(multiply_t(a, q))
    found = thin_svd(b, core, 2, working_precision, seed=seed, wide="keep")
    turn = found.v_numpy()
    return SVDResult(times_small(q, turn), found.sigma, stored(found.U), q.n, working_precision, core, 2, seed)


def low_rank_svd(a: Matrix, l: int, iterations: int = 2, core: str = "mixed_qr", working_precision: float = 1e-11, seed: int = 0, tracker: str = "svd") -> SVDResult:  # noqa: E741
    """Rank-l approximation: single orthonormalisation while tracking, double at the end; 2 * iterations + 2 passes over A.

    Entries that are null, NaN or infinite raise ValueError, as rows do.
    """
    q = range_finder(a, l, iterations, core, working_precision, seed, tracker)
    found = project_svd(a, q, core, working_precision, seed)
    found.requested = l
    found.stats |= {"scans": 2 * iterations + 2}
    return found
