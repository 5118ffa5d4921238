"""Distribution of the number of items of a row with independent items."""

from __future__ import annotations

import numpy as np


def size_distribution(probabilities: list[float] | np.ndarray) -> np.ndarray:
    """Probability of 0 to m items."""
    out = np.ones(1)
    for p in probabilities:
        out = np.append(out * (1 - p), 0.0) + np.append(0.0, out * p)
    return out


def without(sizes: np.ndarray, p: float) -> np.ndarray:
    """The distribution without one item of probability p: solved from the end where no error grows."""
    m = len(sizes) - 1
    out = np.zeros(m)
    if p <= 0.5:
        last = 0.0
        for j in range(m):
            last = (sizes[j] - last * p) / (1 - p)
            out[j] = last
    else:
        last = 0.0
        for j in range(m - 1, -1, -1):
            last = (sizes[j + 1] - last * (1 - p)) / p
            out[j] = last
    return out


def updated(sizes: np.ndarray, old: float, new: float) -> np.ndarray:
    """The distribution after one item's probability changes, in linear time."""
    rest = without(sizes, old)
    return np.append(rest * (1 - new), 0.0) + np.append(0.0, rest * new)


def given(sizes: np.ndarray, present: list[float]) -> np.ndarray:
    """The distribution if the items with these probabilities are in the row."""
    for p in present:
        sizes = without(sizes, p)
    return np.append(np.zeros(len(present)), sizes)
