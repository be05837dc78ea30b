"""Small logistic models fitted on the driver from bounded samples."""

from __future__ import annotations

import numpy as np


def sigmoid(z):
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


def fit_logistic(
    x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, l2: float = 1e-2, steps: int = 60
) -> np.ndarray:
    """Coefficients, intercept last, for dense `x` and targets in [0, 1]; damped Newton steps."""
    n, d = x.shape
    z = np.concatenate([x, np.ones((n, 1))], axis=1)
    w = np.ones(n) if weight is None else weight
    beta = np.zeros(d + 1)
    ridge = np.full(d + 1, l2 * max(w.sum(), 1e-9))
    ridge[-1] = 1e-6 * max(w.sum(), 1e-9)

    def loss(b):
        m = z @ b
        return (w * (np.logaddexp(0, m) - y * m)).sum() + 0.5 * (ridge * b * b).sum()

    now = loss(beta)
    for _ in range(steps):
        p = sigmoid(z @ beta)
        grad = z.T @ (w * (p - y)) + ridge * beta
        hess = (z * (w * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ z + np.diag(ridge)
        step = np.linalg.solve(hess, grad)
        rate = 1.0
        while rate > 1e-4 and loss(beta - rate * step) > now:
            rate /= 2
        beta, before = beta - rate * step, now
        now = loss(beta)
        if before - now < 1e-9 * max(abs(before), 1.0):
            break
    return beta


def fit_sparse_logistic(
    rows: list[np.ndarray], y: np.ndarray, d: int, weight: np.ndarray | None = None, l2: float = 1e-4, steps: int = 300
) -> np.ndarray:
    """The same for binary features given as index lists: accelerated gradient on flat arrays."""
    n = len(rows)
    lengths = np.array([len(r) for r in rows], dtype=np.int64)
    cols = np.concatenate(rows).astype(np.int64) if lengths.sum() else np.zeros(0, np.int64)
    owner = np.repeat(np.arange(n), lengths)
    w = np.full(n, 1 / max(n, 1)) if weight is None else weight / weight.sum()
    beta, ahead, bias, bias_ahead, t = np.zeros(d), np.zeros(d), 0.0, 0.0, 1.0
    rate = 4.0 / (1.0 + float((w * lengths).sum()))
    for _ in range(steps):
        m = np.bincount(owner, weights=ahead[cols], minlength=n) + bias_ahead
        r = w * (sigmoid(m) - y)
        grad = np.bincount(cols, weights=r[owner], minlength=d) + l2 * ahead
        new, new_bias = ahead - rate * grad, bias_ahead - rate * r.sum()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        mix = (t - 1) / t2
        ahead, bias_ahead = new + mix * (new - beta), new_bias + mix * (new_bias - bias)
        beta, bias, t = new, new_bias, t2
    return np.concatenate([beta, [bias]])


def auc(score: np.ndarray, label: np.ndarray) -> float:
    """Share of (1, 0) pairs in the right order, ties half; NaN without both classes."""
    order = np.argsort(score, kind="stable")
    s, l = score[order], label[order]
    first = np.searchsorted(s, s, side="left")
    last = np.searchsorted(s, s, side="right")
    rank = (first + last + 1) / 2
    n1, n0 = (l == 1).sum(), (l == 0).sum()
    return float((rank[l == 1].sum() - n1 * (n1 + 1) / 2) / (n1 * n0)) if n1 and n0 else float("nan")
