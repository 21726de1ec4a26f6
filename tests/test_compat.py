import numpy as np
import pytest

from compatgraph.functions import compat as C


def test_strengths_and_powers():
    K = C.strength_compat(8)
    tops = [np.linalg.matrix_power(K, l).max() for l in (1, 2, 3, 4)]
    assert np.allclose(tops, [0.8, 0.66, 0.562, 0.4934])
    assert np.allclose([C.radius(C.center(C.strength_compat(h))) for h in (2, 3, 5, 8)], [0.25, 0.4, 4 / 7, 0.7])


def test_row_image_is_shift_invariant():
    K, x = C.strength_compat(8), np.array([2, -1, -1])
    assert np.allclose(x @ K, [-0.7, 1.4, -0.7]) and np.allclose(x @ C.center(K), x @ K)


@pytest.mark.parametrize("k", [2, 3, 5])
def test_free_basis_spans_symmetric_sum_one(k):
    h = np.random.default_rng(k).uniform(size=k * (k - 1) // 2)
    K = C.compat_from_free(h, k)
    assert np.allclose(K, K.T) and np.allclose(K.sum(1), 1)


def test_projection_is_nearest():
    T = np.random.default_rng(1).uniform(size=(4, 4))
    K = C.nearest_compat(T)
    assert np.allclose(K, K.T) and np.allclose(K.sum(1), 1)
    origin, basis = C.free_basis(4)
    h = np.linalg.lstsq(np.array([b.ravel() for b in basis]).T, (T - origin).ravel(), rcond=None)[0]
    assert np.allclose(K, origin + np.tensordot(h, basis, 1))
    P = C.nearest_compat(np.diag([3.0, 0, 0, 0]) - 0.5, nonneg=True)
    assert P.min() > -1e-6 and np.allclose(P.sum(1), 1, atol=1e-6)


def test_energy_solvers_agree():
    rng = np.random.default_rng(2)
    N, X = rng.uniform(size=(40, 3)), np.eye(3)[rng.integers(0, 3, 40)]
    free, bound = (C.solve_energy(N.T @ N, N.T @ X, m) for m in ("free", "constrained"))
    assert np.allclose(free, bound)


@pytest.mark.parametrize("variant", [1, 2, 3])
def test_recovery_from_full_counts(variant):
    M = 36 * (C.strength_compat(8) * 10)
    assert np.allclose(C.nearest_compat(C.normalize_counts(M, variant)), C.strength_compat(8))


def test_power_fit_recovers_and_one_hop_is_its_first_case():
    K = C.strength_compat(5)
    got, loss = C.fit_powers([np.linalg.matrix_power(K, l) for l in range(1, 6)])
    assert np.allclose(got, K, atol=1e-6) and loss < 1e-10
    T = C.normalize_counts(np.array([[3, 9, 1], [9, 2, 4], [1, 4, 8]]))
    assert np.allclose(C.fit_powers([T])[0], C.nearest_compat(T), atol=1e-7)


def test_budgets_and_empty_rows():
    M = C.edge_budget(1080, C.strength_compat(8))
    assert M.sum() == 1080 and (M == 36 * np.array([[1, 8, 1], [8, 1, 1], [1, 1, 8]])).all()
    assert np.allclose(C.normalize_counts(np.array([[0, 0, 0], [0, 2, 2], [0, 2, 0]]))[0], 1 / 3)
    assert np.allclose(C.normalize_counts(np.array([[0, 0, 0], [0, 2, 2], [0, 2, 0]]), 2)[0], 1 / 3) and C.empty_rows([[0, 0], [0, 1]]) == [0]
    assert np.allclose(C.degree_ratio(C.strength_compat(8), [1 / 6, 1 / 3, 1 / 2]), np.array([18, 9, 6]) / 18)
