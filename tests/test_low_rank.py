import numpy as np
import pytest

from spectral_frames.matrix import from_numpy
from spectral_frames.operators import accuracy, low_rank, products, stock, thin
from spectral_frames.sources import synth


@pytest.mark.parametrize("core,wp,rank,residual", [("mixed_qr", 1e-10, 5, 7.74e-12), ("gram", 1e-11, 3, 2.15e-7)])
def test_residual_is_the_first_value_cut_off(spark, core, wp, rank, residual):
    a = thin.stored(synth.geo_low(spark, 400, 100, 10, 2))
    r = low_rank.low_rank_svd(a, 10, 2, core, wp)
    r.U = thin.stored(r.U)
    m = accuracy.report(a, r, synth.geometric(10))
    assert m.rank == rank and np.isclose(m.residual, residual, rtol=0.01)
    assert m.u_defect < 1e-12 and m.v_defect < 1e-12 and np.isclose(m.excess, 1, rtol=0.01)


def test_layouts_agree(spark):
    x = np.random.default_rng(0).standard_normal((60, 5)) @ np.random.default_rng(1).standard_normal((5, 40))
    a = from_numpy(spark, x, 2)
    s = np.linalg.svd(x, compute_uv=False)[:5]
    for b in (a, a.to_entries(), a.to_tiles(16, 16)):
        r = low_rank.low_rank_svd(b, 8, 1)
        assert np.allclose(r.sigma, s) and np.allclose(r.reconstruct().collect(), x)
    assert np.allclose(a.to_tiles(16, 8).to_rows().collect(), x)
    for turned in (a.to_entries().to_tiles(7, 9).transpose(), a.to_tiles(16, 4).transpose()):
        assert np.allclose(turned.to_rows().collect(), x.T)


def test_products(spark):
    x, q, p = (np.random.default_rng(k).standard_normal(s) for k, s in enumerate([(30, 12), (12, 3), (30, 2)]))
    a = from_numpy(spark, x, 3)
    for b in (a, a.to_entries(), a.to_tiles(8, 5)):
        assert np.allclose(products.multiply(b, from_numpy(spark, q)).collect(), x @ q)
        assert np.allclose(products.multiply_t(b, from_numpy(spark, p)).collect(), x.T @ p)


@pytest.mark.parametrize("l", [0, 3, 5])
def test_sketch_width_must_be_smaller_than_both_sides(spark, l):  # noqa: E741
    with pytest.raises(ValueError):
        low_rank.range_finder(from_numpy(spark, np.ones((5, 3))), l)
    with pytest.raises(ValueError):
        low_rank.range_finder(from_numpy(spark, np.ones((5, 3))), 1, -1)


@pytest.mark.parametrize("tracker", ["svd", "q_only", "lu"])
def test_trackers(spark, tracker):
    a = thin.stored(synth.cosine_matrix(spark, 200, 60, 10.0 ** -np.arange(6.0), 2))
    r = low_rank.low_rank_svd(a, 10, 1, tracker=tracker)
    assert np.allclose(r.sigma[:6], 10.0 ** -np.arange(6.0))


def test_gaussian_rows_do_not_depend_on_partitions(spark):
    assert np.array_equal(low_rank.gaussian_frame(spark, 20, 3, 1, 1).collect(), low_rank.gaussian_frame(spark, 20, 3, 1, 7).collect())


def test_stock_left_vectors_are_not_orthonormal(spark):
    a = thin.stored(synth.geo_low(spark, 500, 100, 20, 2))
    r = stock.stock_low_rank(a, 20)
    assert accuracy.gram_defect(r.U) > 0.5 and accuracy.spectral_residual(a, r) < 1e-8
