"""Logistic regression on sparse rows, binary with feature selection or weighted, calibrated, for bounded training sets."""

from __future__ import annotations

import numpy as np


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def select(rows: list[np.ndarray], labels: np.ndarray, least_df: int, most: int, least_g: float = 7.0, both_signs: bool = False) -> np.ndarray:
    """Features by log-likelihood ratio with the label: those that mark label 1, or either label, most telling first."""
    flat = np.concatenate(rows) if rows else np.zeros(0, np.int64)
    owner = np.repeat(labels, [len(r) for r in rows])
    names, inverse = np.unique(flat, return_inverse=True)
    one = np.bincount(inverse, weights=owner, minlength=len(names))
    zero = np.bincount(inverse, weights=1 - owner, minlength=len(names))
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    if not n1 or not n0:
        return names[:0]

    def part(k, n, p):
        return np.where(k > 0, k * np.log(np.maximum(k, 1) / np.maximum(n * p, 1e-12)), 0.0)

    p = (one + zero) / (n1 + n0)
    g = 2 * (part(one, n1, p) + part(n1 - one, n1, 1 - p) + part(zero, n0, p) + part(n0 - zero, n0, 1 - p))
    keep = ((one + zero) >= least_df) & (g > least_g) & ((one / n1 > zero / n0) | both_signs)
    order = np.flatnonzero(keep)
    return names[order[np.argsort(-g[order], kind="stable")][:most]]


def _csr(rows: list[np.ndarray], chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(chosen)
    names = chosen[order]
    at, who = [], []
    for i, row in enumerate(rows):
        if len(names):
            j = np.minimum(np.searchsorted(names, row), len(names) - 1)
            hit = order[j[names[j] == row]]
            at.append(hit)
            who.append(np.full(len(hit), i))
    none = np.zeros(0, np.int64)
    return (np.concatenate(who), np.concatenate(at)) if at else (none, none)


def fit(rows: list[np.ndarray], labels: np.ndarray, chosen: np.ndarray, l2: float = 1.0, steps: int = 300) -> tuple[np.ndarray, float]:
    """Weights of the chosen features and bias, by gradient descent with momentum."""
    who, at = _csr(rows, chosen)
    n, m = len(rows), len(chosen)
    w, b = np.zeros(m), float(np.log((labels.sum() + 1) / (n - labels.sum() + 1)))
    vw, vb = np.zeros(m), 0.0
    scale = np.maximum(1.0, np.bincount(at, minlength=m)) + l2  # a diagonal bound of the curvature
    width = max(1.0, np.bincount(who, minlength=n).mean() if n else 1.0)
    for _ in range(steps):
        score = b + np.bincount(who, weights=w[at], minlength=n)
        error = sigmoid(score) - labels
        gw = (np.bincount(at, weights=error[who], minlength=m) + l2 * w) / scale / np.sqrt(width)
        vw, vb = 0.9 * vw - gw, 0.9 * vb - error.mean()
        w, b = w + vw, b + vb
    return w, b


def decide(rows: list[np.ndarray], chosen: np.ndarray, w: np.ndarray, b: float) -> np.ndarray:
    who, at = _csr(rows, chosen)
    return b + np.bincount(who, weights=w[at], minlength=len(rows))


def calibrate(scores: np.ndarray, labels: np.ndarray, steps: int = 100) -> tuple[float, float]:
    """Slope and offset of the logistic that maps scores to probabilities (Newton steps with smoothed targets)."""
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    target = np.where(labels > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    x = np.stack([scores, np.ones_like(scores)], 1)
    theta = np.array([1.0, 0.0])
    for _ in range(steps):
        p = sigmoid(x @ theta)
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        step = np.linalg.solve(h, x.T @ (p - target) + 1e-3 * (theta - [1.0, 0.0]))
        theta = theta - np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-6:
            break
    return (float(theta[0]), float(theta[1])) if theta[0] > 0 else (1.0, 0.0)


def train(rows: list[np.ndarray], labels: np.ndarray, least_df: int, most: int, both_signs: bool = False, l2: float = 1.0):
    """(chosen, weights, bias) with the calibration folded in; scores for it come from two folds, each left out once."""
    labels = labels.astype(float)
    if not len(rows) or labels.min() == labels.max():
        return np.zeros(0, np.int64), np.zeros(0), float(8 * labels.mean() - 4) if len(rows) else 0.0
    fold, held = np.arange(len(rows)) % 2, np.zeros(len(rows))
    for k in (0, 1):
        inside = np.flatnonzero(fold != k)
        mine = [rows[i] for i in inside]
        chosen = select(mine, labels[inside], least_df, most, both_signs=both_signs)
        w, b = fit(mine, labels[inside], chosen, l2)
        out = np.flatnonzero(fold == k)
        held[out] = decide([rows[i] for i in out], chosen, w, b)
    slope, offset = calibrate(held, labels)
    chosen = select(rows, labels, least_df, most, both_signs=both_signs)
    w, b = fit(rows, labels, chosen, l2)
    return chosen, w * slope, b * slope + offset


def fit_weighted(who: np.ndarray, at: np.ndarray, values: np.ndarray, labels: np.ndarray, width: int, l2: float, steps: int) -> tuple[np.ndarray, float]:
    """Weights and bias for rows of weighted features (row who, feature at, value), by adaptive gradient steps."""
    n = len(labels)
    w, b = np.zeros(width), float(np.log((labels.sum() + 1) / (n - labels.sum() + 1)))
    seen, seen_b = np.full(width, 1e-6), 1e-6
    for _ in range(steps):
        error = sigmoid(b + np.bincount(who, weights=w[at] * values, minlength=n)) - labels
        g, gb = np.bincount(at, weights=values * error[who], minlength=width) + l2 * w, error.sum()
        seen, seen_b = seen + g * g, seen_b + gb * gb
        w, b = w - g / np.sqrt(seen), b - 0.2 * gb / np.sqrt(seen_b)
    return w, b


def train_weighted(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, width: int, l2: float = 0.5, steps: int = 60) -> tuple[np.ndarray, float]:
    """(weights, bias) over all ``width`` hashed features, calibrated on two folds, each left out once."""
    labels = labels.astype(float)
    if not len(rows) or labels.min() == labels.max():
        return np.zeros(width), float(8 * labels.mean() - 4) if len(rows) else 0.0
    sizes = np.array([len(at) for at, _ in rows])
    who, values = np.repeat(np.arange(len(rows)), sizes), np.concatenate([v for _, v in rows])
    used, at = np.unique(np.concatenate([a for a, _ in rows]), return_inverse=True)

    def learn(inside: np.ndarray) -> tuple[np.ndarray, float]:
        number = np.cumsum(inside) - 1
        mine = inside[who]
        return fit_weighted(number[who[mine]], at[mine], values[mine], labels[inside], len(used), l2, steps)

    fold, held = np.arange(len(rows)) % 2, np.zeros(len(rows))
    for k in (0, 1):
        w, b = learn(fold != k)
        scores = b + np.bincount(who, weights=w[at] * values, minlength=len(rows))
        held[fold == k] = scores[fold == k]
    slope, offset = calibrate(held, labels)
    w, b = learn(np.ones(len(rows), bool))
    weights = np.zeros(width)
    weights[used] = w * slope
    return weights, b * slope + offset
