"""k x k numerics on the driver: compatibility matrices, normalisations, projections and fits."""

from __future__ import annotations

import numpy as np


def strength_compat(h: float) -> np.ndarray:
    """Classes 0 and 1 attract each other, class 2 itself, ``h`` times as strongly as the rest."""
    return np.array([[1, h, 1], [h, 1, 1], [1, 1, h]]) / (h + 2)


def identity_compat(k: int) -> np.ndarray:
    return np.eye(k)


def center(K: np.ndarray) -> np.ndarray:
    return K - 1 / len(K)


def free_basis(k: int, total: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
    """K = origin + sum of h_i * basis_i: symmetric with rows of sum ``total``, by the k(k-1)/2 entries above the last row and column.

    Residual matrices (K less 1/k everywhere) have rows of sum 0: then the origin is zero and the map is linear.
    """
    spots = [(c, d) for c in range(k - 1) for d in range(c, k - 1)]
    basis = np.zeros((len(spots), k, k))
    for i, (c, d) in enumerate(spots):
        for x, y in {(c, d), (d, c)}:
            basis[i, x, y] += 1
            basis[i, x, k - 1] -= 1
            basis[i, k - 1, y] -= 1
            basis[i, k - 1, k - 1] += 1
    origin = np.zeros((k, k))
    origin[:-1, -1] = origin[-1, :-1] = total
    origin[-1, -1] = (2 - k) * total
    return origin, basis


def compat_from_free(h, k: int) -> np.ndarray:
    origin, basis = free_basis(k)
    return origin + np.tensordot(np.asarray(h, float), basis, 1)


def normalize_counts(M: np.ndarray, variant: int = 1) -> np.ndarray:
    """1: rows of sum 1; 2: by the roots of both sums; 3: mean entry 1/k.  The row of a class without pairs becomes uniform in 1 and 2."""
    M = np.asarray(M, float)
    k, sums = len(M), M.sum(1)
    if variant == 1:
        return np.where(sums[:, None] > 0, M / np.where(sums > 0, sums, 1)[:, None], 1 / k)
    if variant == 2:
        root = np.where(sums > 0, sums, 1) ** -0.5
        return np.where(sums[:, None] > 0, M * root[:, None] * root[None, :], 1 / k)
    return k * M / M.sum() if M.sum() else np.full((k, k), 1 / k)


def empty_rows(M: np.ndarray) -> list[int]:
    """Classes without any pair: their rows say nothing."""
    return [int(c) for c in np.flatnonzero(np.asarray(M).sum(1) == 0)]


def nearest_compat(T: np.ndarray, nonneg: bool = False, total: float = 1.0) -> np.ndarray:
    """Nearest symmetric matrix with rows of sum ``total``; with ``nonneg`` by alternating projections (Dykstra)."""
    def project(S):
        S = (S + S.T) / 2
        k, rho = len(S), total - S.sum(1)
        u = (rho - rho.sum() / (2 * k)) / k
        return S + u[:, None] + u[None, :]

    K = project(T)
    fix = np.zeros_like(K)
    for _ in range(200 if nonneg and (K < 0).any() else 0):
        up = np.maximum(K + fix, 0)
        fix = K + fix - up
        K = project(up)
    return K


def solve_energy(NN: np.ndarray, NX: np.ndarray, mode: str = "free") -> np.ndarray:
    """min |X - N K|^2 over symmetric K of row sum 1, from N'N and N'X: least squares in the free entries, by constraints (KKT), or
    in the residual entries (``residual``: the answer then has rows of sum 0 and is K less 1/k)."""
    k = len(NN)
    if mode in ("free", "residual"):
        if mode == "residual":
            NX = NX - NN @ np.full((k, k), 1 / k)
        origin, basis = free_basis(k, 0.0 if mode == "residual" else 1.0)
        A = np.array([[np.sum(a * (NN @ b)) for b in basis] for a in basis])
        r = np.array([np.sum(a * (NX - NN @ origin)) for a in basis])
        return origin + np.tensordot(np.linalg.lstsq(A, r, rcond=None)[0], basis, 1)
    quad, lin, rows, rhs = np.kron(NN, np.eye(k)), NX.reshape(-1), [], []
    for c in range(k):
        row = np.zeros((k, k))
        row[c] = 1
        rows.append(row.reshape(-1)), rhs.append(1.0)
        for d in range(c):
            row = np.zeros((k, k))
            row[c, d], row[d, c] = 1, -1
            rows.append(row.reshape(-1)), rhs.append(0.0)
    C = np.array(rows)
    system = np.block([[quad, C.T], [C, np.zeros((len(C), len(C)))]])
    return np.linalg.lstsq(system, np.concatenate([lin, rhs]), rcond=None)[0][: k * k].reshape(k, k)


def fit_powers(T: list[np.ndarray], lam: float = 10.0, starts: int = 8, seed: int = 0, residual: bool = False) -> tuple[np.ndarray, float]:
    """min over K of sum of lam^(l-1) * |K^l - T_l|^2 by damped Gauss-Newton from several starts; the best K and its loss.

    Powers are not convex, and even ones can't see signs: the first start is the one-hop solution.  With ``residual`` the same fit in
    residual entries: K^l less 1/k is the l-th power of K less 1/k, which is what is returned.
    """
    k, weights = len(T[0]), np.sqrt([lam**i for i in range(len(T))])
    total = 0.0 if residual else 1.0
    T = [t - 1 / k for t in T] if residual else T
    origin, basis = free_basis(k, total)
    spots = [(c, d) for c in range(k - 1) for d in range(c, k - 1)]

    def gaps(h):
        K = origin + np.tensordot(h, basis, 1)
        powers = [np.eye(k)]
        for _ in T:
            powers.append(powers[-1] @ K)
        r = np.concatenate([w * (powers[i + 1] - t).ravel() for i, (w, t) in enumerate(zip(weights, T, strict=True))])
        J = np.array([np.concatenate([w * sum(powers[a] @ E @ powers[i - a] for a in range(i + 1)).ravel() for i, w in enumerate(weights)]) for E in basis]).T
        return r, J

    rng, best = np.random.default_rng(seed), (None, np.inf)
    first = nearest_compat(T[0], total=total)
    for s in range(starts):
        h = np.array([first[c, d] for c, d in spots]) if s == 0 else rng.uniform(0, 2 / k, len(spots)) - (1 / k if residual else 0)
        mu, (r, J) = 1e-2, gaps(h)
        for _ in range(200):
            step = np.linalg.solve(J.T @ J + mu * np.eye(len(h)), -J.T @ r)
            r2, J2 = gaps(h + step)
            if r2 @ r2 < r @ r:
                h, r, J, mu = h + step, r2, J2, mu / 3
                if np.abs(step).max() < 1e-12:
                    break
            else:
                mu *= 4
                if mu > 1e12:
                    break
        if r @ r < best[1] - 1e-12:
            best = (origin + np.tensordot(h, basis, 1), float(r @ r))
    return best


def radius(K: np.ndarray) -> float:
    return float(np.abs(np.linalg.eigvals(K)).max())


def edge_budget(m: int, K: np.ndarray) -> np.ndarray:
    """Integer class-pair budgets of sum ``m`` in proportion to K, by largest remainders; symmetric where K is (up to one arc)."""
    exact = m * K / K.sum()
    M = np.floor(exact + 1e-9).astype(int)
    left = m - M.sum()
    order = sorted(np.ndindex(*M.shape), key=lambda p: (-(exact[p] - M[p]), min(p), max(p), p))
    for p in order[:left]:
        M[p] += 1
    return M


def degree_ratio(K: np.ndarray, alpha) -> np.ndarray:
    """Mean out-degrees up to a factor: row sums over class shares."""
    d = K.sum(1) / np.asarray(alpha)
    return d / d.max()


def coloring_compat(k: int = 3) -> np.ndarray:
    """Every class attracts all others and not itself: a graph fits exactly if its classes are a proper colouring."""
    return (np.ones((k, k)) - np.eye(k)) / (k - 1)


def cyclic_compat(h: float) -> np.ndarray:
    """Each of three classes attracts the next, ``h`` times as strongly as the rest; not symmetric (directed graphs)."""
    return np.array([[1, h, 1], [1, 1, h], [h, 1, 1]]) / (h + 2)


def balanced_rows(K: np.ndarray, alpha) -> np.ndarray:
    """K with rows weighted by class shares, so that all classes have one mean out-degree."""
    return K * (np.asarray(alpha, float) / K.sum(1))[:, None]
