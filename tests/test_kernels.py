import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spectral_frames import kernels
from spectral_frames.mixing import MixingPlan
from spectral_frames.sources import synth


@pytest.mark.parametrize("kind,rounds", [("fourier", 1), ("fourier", 2), ("fourier", "log"), ("gaussian", 2), ("none", 2)])
@pytest.mark.parametrize("n", [1, 2, 3, 8, 15])
def test_mixing_is_orthogonal_and_undone(kind, rounds, n):
    x = np.random.default_rng(0).standard_normal((6, n))
    plan = MixingPlan.build(n, 4, rounds, kind)
    y = plan.forward(x)
    assert y.shape == (6, plan.width)
    assert np.allclose(np.linalg.norm(y, axis=1), np.linalg.norm(x, axis=1))
    assert np.allclose(plan.inverse(y), x)


def test_diagonal_rule_drops_columns_that_are_not_trailing():
    r = np.diag([2.0, 1e-13, 1.0, 0.0])
    assert kernels.retain_by_diagonal(r, 1e-11).tolist() == [0, 2]
    assert kernels.retain_by_diagonal(r, 0.0).tolist() == [0, 1, 2]
    assert kernels.retain_by_diagonal(np.zeros((3, 3)), 0.0).tolist() == []


def test_norm_rule_takes_the_root_of_the_working_precision():
    assert kernels.retain_by_norm(np.array([1.0, 1e-5, 1e-6, 0.0]), 1e-11).tolist() == [0, 1]


def test_staircase_values():
    values, counts = np.unique(synth.staircase(20), return_counts=True)
    assert np.allclose(values, [0, 31 / 63, 32 / 63, 1]) and counts.tolist() == [1, 2, 3, 14]
    assert len(np.unique(synth.staircase(2000))) == 36
    assert synth.staircase(10).tolist()[:7] == [1.0] * 7


def test_geometric_ends():
    s = synth.geometric(20)
    assert s[0] == 1 and np.isclose(s[-1], 1e-20) and synth.geometric(1).tolist() == [1.0]


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 90), st.integers(0, 10**6))
def test_triangular_solve(n, seed):
    rng = np.random.default_rng(seed)
    r = np.triu(rng.standard_normal((n, n))) + np.eye(n) * n
    x = rng.standard_normal((5, n))
    assert np.allclose(kernels.triangular_solve(x @ r, r), x)


def test_r_factors_merge_in_any_order():
    rng = np.random.default_rng(1)
    x = [rng.standard_normal((7, 4)) for _ in range(5)]
    one = kernels.r_of(*[kernels.r_of(b) for b in x])
    two = kernels.r_of(kernels.r_of(*x[3:]), kernels.r_of(*x[:3]))
    assert np.allclose(one.T @ one, two.T @ two)
    assert np.allclose(one.T @ one, sum(b.T @ b for b in x))


def test_pivot_rows_span():
    y = np.random.default_rng(2).standard_normal((50, 5))
    s = kernels.pivot_rows(y)
    assert np.abs(np.linalg.solve(s.T, y.T)).max() < 50


def test_cosine_basis_is_orthonormal():
    u = synth.cosine_rows(np.arange(40), 40, 40)
    assert np.allclose(u.T @ u, np.eye(40))
