"""Code distance should be proportional to input distance, near pairs weighing more."""

from __future__ import annotations

import numpy as np


def pair_index(n: int, pairing: str = "all", seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Which samples of a batch are paired: all, neighbours in order, or a random matching."""
    if pairing == "all":
        return np.triu_indices(n, 1)
    order = np.arange(n) if pairing == "consecutive" else np.random.default_rng(seed).permutation(n)
    if pairing not in ("consecutive", "random"):
        raise ValueError(pairing)
    m = n // 2 * 2
    return order[0:m:2], order[1:m:2]


def _terms(x: np.ndarray, lam: float, t: float, i: np.ndarray, j: np.ndarray):
    d = np.sqrt(np.maximum(((x[i] - x[j]) ** 2).sum(1), 0))
    weight = np.exp(-d / t) if np.isfinite(t) else np.ones_like(d)
    return lam * d, weight


def pair_loss(x: np.ndarray, codes: np.ndarray, lam: float, t: float, pairing: str = "all", seed: int = 0) -> float:
    """Mean loss over pairs; codes (or surrogate outputs) are rows of values in [-1, 1]."""
    i, j = pair_index(len(x), pairing, seed)
    if not len(i):
        return 0.0
    want, weight = _terms(x, lam, t, i, j)
    return float((np.abs(want - np.abs(codes[i] - codes[j]).sum(1)) * weight).mean())


def loss_gradient(x: np.ndarray, h: np.ndarray, lam: float, t: float, pairing: str = "all", seed: int = 0) -> tuple[np.ndarray, tuple[float, int]]:
    """(gradient with respect to the surrogate outputs, (mean loss, pairs))."""
    i, j = pair_index(len(x), pairing, seed)
    g = np.zeros_like(h)
    if not len(i):
        return g, (0.0, 0)
    want, weight = _terms(x, lam, t, i, j)
    diff = h[i] - h[j]
    error = want - np.abs(diff).sum(1)
    pull = (-np.sign(error) * weight / len(i))[:, None] * np.sign(diff)
    np.add.at(g, i, pull)
    np.add.at(g, j, -pull)
    return g, (float((np.abs(error) * weight).mean()), len(i))


def suggest_lambda(x: np.ndarray, bits: int, share: float = 0.95) -> float:
    """The lambda at which the given quantile of pair distances asks for opposite codes."""
    i, j = pair_index(len(x))
    d = np.sqrt(((x[i] - x[j]) ** 2).sum(1))
    return float(2 * bits / max(np.quantile(d, share), 1e-12))
