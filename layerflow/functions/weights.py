"""Layer weights: integers of a lattice, expressible in SQL as well, and seeded floats."""

from __future__ import annotations

import numpy as np


def lattice(layer: int, n_in: int, n_out: int) -> np.ndarray:
    """Small integers between -6 and 6 from a closed formula."""
    i, j = np.meshgrid(np.arange(n_in), np.arange(n_out), indexing="ij")
    return ((31 * i + 17 * j + 7 * layer) % 13 - 6).astype(np.int64)


def glorot(layer: int, n_in: int, n_out: int, seed: int = 0) -> np.ndarray:
    bound = np.sqrt(6 / (n_in + n_out))
    return np.random.default_rng([seed, layer]).uniform(-bound, bound, (n_in, n_out))


def ridge(x: np.ndarray, y: np.ndarray, classes: int, penalty: float = 1.0) -> np.ndarray:
    """Least-squares weights for one-hot classes; rows whose class is negative are left out."""
    keep = y >= 0
    x, t = x[keep], np.eye(classes)[y[keep]]
    return np.linalg.solve(x.T @ x + penalty * np.eye(x.shape[1]), x.T @ t)


def make_weights(layer: int, n_in: int, n_out: int, kind: str = "lattice", seed: int = 0) -> np.ndarray:
    if kind == "lattice":
        return lattice(layer, n_in, n_out)
    if kind == "glorot":
        return glorot(layer, n_in, n_out, seed)
    raise ValueError(f"no such weights: {kind}")
