import numpy as np
import pytest

from spectral_frames.matrix import RowFrame, from_numpy
from spectral_frames.operators import accuracy, gram, pca, thin, tree_qr
from spectral_frames.sources import synth

CASES = [("mixed_qr", 1, "direct"), ("mixed_qr", 1, "indirect"), ("mixed_qr", 2, "direct"), ("mixed_qr", 2, "indirect"), ("gram", 1, "auto"), ("gram", 2, "auto")]


@pytest.mark.parametrize("core,passes,form", CASES)
def test_against_exact(spark, core, passes, form):
    x = np.random.default_rng(0).standard_normal((120, 7)) * [1, 2, 3, 4, 5, 6, 7]
    r = thin.thin_svd(from_numpy(spark, x, 3), core, passes, q_form=form)
    assert np.allclose(r.sigma, np.linalg.svd(x, compute_uv=False))
    assert np.allclose(r.reconstruct().collect(), x)
    assert accuracy.gram_defect(r.v_numpy()) < 1e-12 and accuracy.gram_defect(r.U) < 1e-10
    assert (np.diff(r.sigma) <= 1e-12).all()


@pytest.mark.parametrize("core", ["mixed_qr", "gram"])
def test_two_passes_repair_left_vectors(spark, core):
    a = thin.stored(synth.geo_thin(spark, 800, 48, 3))
    one = thin.thin_svd(a, core, 1, q_form="indirect")
    two = thin.thin_svd(a, core, 2)
    first, second = (accuracy.gram_defect(thin.stored(r.U)) for r in (one, two))
    assert second < 1e-12 and first > 10 * second
    assert np.isclose(accuracy.spectral_residual(a, one), accuracy.spectral_residual(a, two), rtol=0.05)


def test_mixed_qr_reconstructs_better_than_gram(spark):
    a = thin.stored(synth.geo_thin(spark, 800, 48, 3))
    qr, gr = (accuracy.spectral_residual(a, thin.thin_svd(a, c, 2)) for c in ("mixed_qr", "gram"))
    assert qr < 1e-10 < 1e-7 < gr


@pytest.mark.parametrize("core,passes,form", CASES)
@pytest.mark.parametrize("x", [np.zeros((5, 3)), np.ones((1, 1)), np.ones((1, 4)), np.eye(2), np.array([[1.0, 1, 0], [2, 2, 0], [3, 3, 0]]), np.ones((2, 5)) * [[1], [2]]], ids=["zero", "one", "row", "two", "copies", "wide"])
def test_degenerate(spark, core, passes, form, x):
    r = thin.thin_svd(from_numpy(spark, x, 2), core, passes, q_form=form)
    rank = np.linalg.matrix_rank(x)
    assert r.rank == rank
    if rank:
        assert np.allclose(r.reconstruct().collect(), x)


def test_scaled_values_and_signs(spark):
    x = np.random.default_rng(3).standard_normal((30, 4))
    for scale in (1e-150, 1e150):
        r = thin.thin_svd(from_numpy(spark, x * scale), "mixed_qr", 2)
        assert np.allclose(r.sigma / scale, np.linalg.svd(x, compute_uv=False))
    v = r.v_numpy()
    assert (v[np.abs(v).argmax(axis=0), np.arange(4)] > 0).all()


def test_rejected(spark):
    a = from_numpy(spark, np.ones((3, 2)))
    for bad in ({"core": "x"}, {"passes": 3}, {"working_precision": 1.0}, {"widest": 1}):
        with pytest.raises(ValueError):
            thin.thin_svd(a, **bad)
    ragged = spark.createDataFrame([(0, [1.0]), (1, [1.0, 2.0])], "row_id long, vec array<double>")
    with pytest.raises(ValueError):
        RowFrame(ragged, 2).checked()
    holes = RowFrame(spark.createDataFrame([(0, [1.0, None]), (1, [1.0, 2.0])], "row_id long, vec array<double>"), 2)
    with pytest.raises(ValueError):
        holes.checked()
    assert holes.checked("zero").height() == 2 and holes.checked("drop").height() == 1


def test_empty_partitions_and_partition_counts(spark):
    x = np.random.default_rng(5).standard_normal((9, 3))
    base = np.linalg.svd(x, compute_uv=False)
    for p in (1, 20, 40):
        a = from_numpy(spark, x, p)
        for form in ("direct", "indirect"):
            r = thin.thin_svd(a, "mixed_qr", 2, q_form=form)
            assert np.allclose(r.sigma, base) and np.allclose(r.reconstruct().collect(), x)


def test_gram_forms_agree(spark):
    x = np.random.default_rng(6).integers(-3, 4, (40, 5)).astype(float)
    a = from_numpy(spark, x, 3)
    assert np.allclose(gram.gram_catalyst(a), x.T @ x) and np.allclose(gram.gram_arrow(a), x.T @ x)
    for i, j, v in gram.gram_relational(a.to_entries()).collect():
        assert np.isclose((x.T @ x)[i, j], v)


def test_r_factor_of_few_rows(spark):
    r = tree_qr.r_factor(from_numpy(spark, np.ones((1, 4))))
    assert r.shape == (4, 4) and np.allclose(r.T @ r, np.ones((4, 4)))


def test_pca_and_new_rows(spark):
    x = np.random.default_rng(7).standard_normal((60, 4)) * [1, 2, 3, 4] + 100
    p = pca.pca(from_numpy(spark, x, 2))
    c = x - x.mean(axis=0)
    assert np.allclose(p.explained_variance, np.linalg.svd(c, compute_uv=False) ** 2 / 59)
    assert np.allclose(p.scores().collect(), p.transform(from_numpy(spark, x)).collect())
    assert np.allclose(pca.pca(from_numpy(spark, x), scale=True).explained_variance.sum(), 4)


def test_save_and_load(spark, tmp_path):
    x = np.random.default_rng(8).standard_normal((20, 3))
    r = thin.thin_svd(from_numpy(spark, x))
    r.save(str(tmp_path / "m"))
    back = thin.SVDResult.load(spark, str(tmp_path / "m"))
    assert np.allclose(back.reconstruct().collect(), x) and back.truncate(2).rank == 2
