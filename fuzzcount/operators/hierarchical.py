"""Agglomerative clustering of the filters of one cell: single, complete or average link.

Merges the closest two clusters until `k` are left or none is within `cut`; cubic at worst, so a cell has at
most `MOST_MERGED` rows (single link at a radius has a distributed form in `linkage.components`).
"""

from __future__ import annotations

import numpy as np

MOST_MERGED = 2_000


def labels(x: np.ndarray, link: str = "average", k: int = 1, cut: float | None = None) -> np.ndarray:
    """A label for each row of a 0/1 matrix, by Hamming distance; ties go to the earliest pair."""
    if link not in ("single", "complete", "average"):
        raise ValueError("link is single, complete or average")
    n = len(x)
    if n > MOST_MERGED:
        raise ValueError(f"more than {MOST_MERGED} rows: split into cells")
    if not n:
        return np.empty(0, np.int64)
    gap = (x[:, None] != x[None]).sum(2).astype(float)
    np.fill_diagonal(gap, np.inf)
    sizes, owner, left = np.ones(n), np.arange(n), n
    while left > k:
        i, j = sorted(np.unravel_index(int(gap.argmin()), gap.shape))
        if not np.isfinite(gap[i, j]) or (cut is not None and gap[i, j] > cut):
            break
        a, b = gap[i], gap[j]
        new = np.minimum(a, b) if link == "single" else np.maximum(a, b) if link == "complete" else (sizes[i] * a + sizes[j] * b) / (sizes[i] + sizes[j])
        gap[i], gap[:, i] = new, new
        gap[j], gap[:, j], gap[i, i] = np.inf, np.inf, np.inf
        sizes[i] += sizes[j]
        owner[owner == j] = i
        left -= 1
    return np.unique(owner, return_inverse=True)[1]
