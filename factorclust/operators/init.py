"""Initial factors on the domain; every draw depends on the row's id, the column and the seed alone."""

from __future__ import annotations

import numpy as np

from factorclust.functions import portable


def raw_factor(ids: np.ndarray, r: int, seed: int, how: str = "uniform") -> np.ndarray:
    """Unscaled nonnegative rows; the driver's first scale brings the squared norm to K."""
    cols = np.arange(r)
    if how == "uniform":
        return portable.uniform_np(ids[:, None], cols[None, :], seed)
    if how == "half_normal":
        return np.abs(portable.normal_np(ids[:, None], cols[None, :], seed))
    raise ValueError(f"unknown initial law {how!r}")


def warm_factor(ids: np.ndarray, labels: np.ndarray, k: int, r: int, seed: int, jitter: float = 0.05) -> np.ndarray:
    """Rows of the assignment factor of given labels, with some noise in all columns."""
    sizes = np.maximum(1, np.bincount(labels, minlength=k))
    f = jitter * portable.uniform_np(ids[:, None], np.arange(r)[None, :], seed) / np.sqrt(sizes[labels])[:, None]
    f[np.arange(len(ids)), labels] += 1 / np.sqrt(sizes[labels])
    return f
