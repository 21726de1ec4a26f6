"""Small gradient-boosted trees in numpy, for models that are fitted on the driver from a bounded sample."""

from __future__ import annotations

import numpy as np


def _split(x, g, h, rows, cuts):
    best = (1e-6, None, None)
    G, H = g[rows].sum(), h[rows].sum()
    for j, at in enumerate(cuts):
        v = x[rows, j]
        for c in at:
            left = v <= c
            gl, hl = g[rows][left].sum(), h[rows][left].sum()
            if min(hl, H - hl) < 1:
                continue
            gain = gl**2 / (hl + 1) + (G - gl) ** 2 / (H - hl + 1) - G**2 / (H + 1)
            if gain > best[0]:
                best = (gain, j, c)
    return best[1:]


def _grow(x, g, h, rows, cuts, depth, rate):
    j, c = _split(x, g, h, rows, cuts) if depth else (None, None)
    if j is None:
        return float(rate * g[rows].sum() / (h[rows].sum() + 1))
    left = x[rows, j] <= c
    return (j, float(c), _grow(x, g, h, rows[left], cuts, depth - 1, rate), _grow(x, g, h, rows[~left], cuts, depth - 1, rate))


def _value(tree, x, out, rows):
    if isinstance(tree, float):
        out[rows] += tree
        return
    j, c, a, b = tree
    left = x[rows, j] <= c
    _value(a, x, out, rows[left])
    _value(b, x, out, rows[~left])


def margin(model: dict, x: np.ndarray) -> np.ndarray:
    out = np.full(len(x), model["base"])
    for t in model["trees"]:
        _value(t, x, out, np.arange(len(x)))
    return out


def fit(x: np.ndarray, y: np.ndarray, *, rounds: int = 40, depth: int = 3, rate: float = 0.3) -> dict:
    """Second-order boosting of the logistic loss."""
    p0 = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    model = {"base": float(np.log(p0 / (1 - p0))), "trees": []}
    f = np.full(len(x), model["base"])
    cuts = []
    for j in range(x.shape[1]):
        v = np.unique(x[:, j])
        at = (v[1:] + v[:-1]) / 2
        cuts.append(at if len(at) <= 12 else np.unique(np.quantile(x[:, j], np.linspace(0.05, 0.95, 12))))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-f))
        tree = _grow(x, y - p, p * (1 - p), np.arange(len(x)), cuts, depth, rate)
        model["trees"].append(tree)
        _value(tree, x, f, np.arange(len(x)))
    return model


def calibrate(m: np.ndarray, y: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Slope and offset of a logistic curve through held-out margins."""
    a, b = 1.0, 0.0
    z = np.column_stack([m, np.ones(len(m))])
    w = np.array([a, b])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        w += np.linalg.solve((z * (p * (1 - p) + 1e-6)[:, None]).T @ z + 1e-2 * np.eye(2), z.T @ (y - p) - 1e-2 * (w - [1, 0]))
    return float(w[0]), float(w[1])


def probability(model: dict, x: np.ndarray) -> np.ndarray:
    a, b = model["curve"]
    return 1 / (1 + np.exp(-np.clip(a * margin(model, x) + b, -30, 30)))
