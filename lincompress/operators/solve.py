"""Dense algebra of model size, on the driver."""

from __future__ import annotations

import numpy as np


def rank_report(gram: np.ndarray, tolerance: float = 1e-10) -> list[int]:
    """Columns that depend on earlier ones: their remainder after elimination is nothing beside their own size."""
    left, aliased = gram.astype(float).copy(), []
    size = np.diag(gram).astype(float)
    for j in range(len(gram)):
        if left[j, j] <= tolerance * max(size[j], np.finfo(float).tiny):
            aliased.append(j)
            left[j, :] = left[:, j] = 0
            continue
        left[j + 1 :, j + 1 :] -= np.outer(left[j + 1 :, j], left[j, j + 1 :]) / left[j, j]
    return aliased


class Aliased(ValueError):
    """The model has columns that others determine; ``columns`` are their places."""

    def __init__(self, columns: list[int]):
        super().__init__(f"aliased design columns: {columns}")
        self.columns = columns


def _lower_inverse(lower: np.ndarray) -> np.ndarray:
    """Inverse of a lower triangle by forward substitution, a row at a time."""
    out = np.zeros_like(lower)
    for i in range(len(lower)):
        out[i, :i] = -(lower[i, :i] @ out[:i, :i])
        out[i, i] = 1.0
        out[i, : i + 1] /= lower[i, i]
    return out


def inverse_spd(gram: np.ndarray, on_alias: str = "error") -> np.ndarray:
    """Inverse through a scaled Cholesky factor. on_alias: error, or drop (rows and columns of aliased ones stay zero)."""
    aliased = rank_report(gram)
    if aliased and on_alias == "error":
        raise Aliased(aliased)
    keep = [i for i in range(len(gram)) if i not in aliased]
    part = gram[np.ix_(keep, keep)]
    scale = 1 / np.sqrt(np.diag(part))
    factor = _lower_inverse(np.linalg.cholesky(part * np.outer(scale, scale))) * scale
    out = np.zeros_like(gram, float)
    out[np.ix_(keep, keep)] = factor.T @ factor
    return out


def solve_spd(gram: np.ndarray, b: np.ndarray, on_alias: str = "error") -> np.ndarray:
    """One refinement step after the product with the inverse."""
    inverse = inverse_spd(gram, on_alias)
    x = inverse @ b
    return x + inverse @ (b - gram @ x)
