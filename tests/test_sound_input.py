"""What every method refuses, and what it makes of wide input."""

import numpy as np
import pytest

from spectral_frames import serial
from spectral_frames.matrix import EntryFrame, RowFrame, from_numpy
from spectral_frames.operators import accuracy, low_rank, thin, tree_qr

METHODS = [("mixed_qr", 1), ("mixed_qr", 2), ("gram", 1), ("gram", 2)]
BAD = {
    "nan": [(0, [1.0, 2.0]), (1, [float("nan"), 1.0]), (2, [3.0, 1.0])],
    "infinite": [(0, [1.0, 2.0]), (1, [float("inf"), 1.0]), (2, [3.0, 1.0])],
    "null": [(0, [1.0, 2.0]), (1, [None, 1.0]), (2, [3.0, 1.0])],
    "no row": [(0, [1.0, 2.0]), (1, None), (2, [3.0, 1.0])],
    "ragged": [(0, [1.0]), (1, [1.0, 2.0, 3.0]), (2, [3.0, 1.0])],
}


@pytest.mark.parametrize("core,passes", METHODS)
@pytest.mark.parametrize("kind", BAD)
def test_rows(spark, core, passes, kind):
    for form in ("direct", "indirect"):
        a = RowFrame(spark.createDataFrame(BAD[kind], "row_id long, vec array<double>").repartition(2), 2)
        with pytest.raises(ValueError, match="ragged"):
            thin.thin_svd(a, core, passes, q_form=form)


@pytest.mark.parametrize("kind", ["nan", "infinite"])
def test_wider_rows_go_through_arrow(spark, kind):
    x = np.ones((40, 20))
    x[7, 3] = {"nan": np.nan, "infinite": np.inf}[kind]
    for core, passes in METHODS:
        with pytest.raises(ValueError):
            thin.thin_svd(from_numpy(spark, x, 3), core, passes)


@pytest.mark.parametrize("core", ["mixed_qr", "gram"])
def test_low_rank_layouts(spark, core):
    x = np.random.default_rng(0).standard_normal((20, 12))
    x[3, 4] = np.nan
    entries = EntryFrame(from_numpy(spark, x, 2).to_entries().df, 12, 20)
    for a in (from_numpy(spark, x, 2), entries, from_numpy(spark, x, 2).to_tiles(8, 8)):
        with pytest.raises(ValueError):
            low_rank.low_rank_svd(a, 3, 1, core)


@pytest.mark.parametrize("core,passes", METHODS)
def test_wide(spark, core, passes):
    x = np.random.default_rng(1).standard_normal((4, 9))
    x[:, 5] = 0
    with pytest.raises(ValueError, match="not tall"):
        thin.thin_svd(from_numpy(spark, x, 2), core, passes, wide="raise")
    r = thin.thin_svd(from_numpy(spark, x, 2), core, passes)
    assert r.stats["transposed"] and np.allclose(r.sigma, np.linalg.svd(x, compute_uv=False))
    assert np.allclose(r.reconstruct().collect(), x) and accuracy.gram_defect(r.v_numpy()) < 1e-10
    u, s, v = serial.thin_svd(x, core, passes)
    assert np.allclose(s, r.sigma) and np.allclose((u * s) @ v.T, x)


@pytest.mark.parametrize("small", [0, 1 << 20])
@pytest.mark.parametrize("rows", [8, 33, 1000])
def test_direct_q_by_blocks(spark, rows, small):
    x = np.random.default_rng(2).standard_normal((300, 6))
    x[:, 4] = x[:, 1]  # not of full rank
    a = from_numpy(spark, x, 5)
    q, r = tree_qr.q_direct(a, 6, rows=rows, small=small)
    q = q.collect()
    assert np.allclose(q @ r, x) and np.allclose(q.T @ q, np.eye(6)) and a.m == 300


def test_residual_of_entries_stays_sparse(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((40, 30)) * (rng.random((40, 30)) < 0.1)
    x[5], x[:, 7] = 0, 0
    a = from_numpy(spark, x, 2)
    r = low_rank.low_rank_svd(a.to_entries(), 6, 2)
    rest = x - sum(r.sigma[k] * np.outer(*(m[:, k] for m in (_rows(r.U, 40), r.v_dense(30)))) for k in range(r.rank))
    for b in (a, a.to_entries(), a.to_tiles(16, 16)):
        assert np.isclose(accuracy.spectral_residual(b, r, 60), np.linalg.norm(rest, 2), rtol=1e-3)


def _rows(u, m):
    out = np.zeros((m, u.n))
    for r in u.df.collect():
        out[r["row_id"]] = r["vec"]
    return out


@pytest.mark.parametrize("core,passes", METHODS)
def test_serial_methods(core, passes):
    x = np.random.default_rng(4).standard_normal((50, 6)) * [1, 2, 3, 4, 5, 6]
    u, s, v = serial.thin_svd(x, core, passes)
    assert np.allclose(s, np.linalg.svd(x, compute_uv=False)) and np.allclose((u * s) @ v.T, x)
    with pytest.raises(ValueError):
        serial.thin_svd(np.array([[1.0, np.nan]]))
    with pytest.raises(ValueError):
        serial.range_finder(x, 6)


def test_measures_of_a_spectrum():
    from spectral_frames import kernels

    assert accuracy.sigma_error(np.array([2.0, 1.0]), np.array([2.0, 1.5, 0.5])) == 0.25
    assert kernels.optimal_error(np.array([3.0, 2.0, 1.0]), 1) == 2 and kernels.optimal_error(np.array([3.0]), 1) == 0
