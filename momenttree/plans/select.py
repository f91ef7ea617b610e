"""How many children, and which concentration."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from momenttree.functions import paths
from momenttree.functions import tensor as X
from momenttree.operators import moments


def suggest_width(values: np.ndarray, most: int = 10, rule: str = "gap", least_share: float = 0.05, least_ratio: float = 1.5) -> int:
    """From eigenvalues of E2, descending.

    gap: before the last fall by least_ratio or more, where the level tail of noise begins (the largest fall if none is
    so large); threshold: those above a share of the first.
    """
    values = values[values > 0][: most + 1]
    if len(values) < 2:
        return len(values)
    if rule == "threshold":
        return int((values[:most] >= least_share * values[0]).sum())
    falls = values[:-1] / values[1:]
    steep = np.flatnonzero(falls >= least_ratio)
    return int(steep[-1] if len(steep) else np.argmax(falls)) + 1


def suggest_alpha0(bags: DataFrame, v: int, k: int, grid: tuple[float, ...] = (0.01, 0.03, 0.1, 0.3, 1.0, 3.0), *, min_len: float = moments.MIN_LEN, seed: int = 0) -> tuple[float, list[tuple[float, float, float]]]:
    """The grid value whose shares sum best to 1 with least mass clipped; rows (alpha0, |sum - 1|, clipped).

    The corpus is projected once with the eigenvectors of E2; whiteners of all grid values are k x k turns of these.
    """
    root = moments.moments_of(bags, v, min_len=min_len)[paths.ROOT]
    sigma, u = X.largest_eigs(root.e2, k)
    parts = moments.project_third(bags, v, {paths.ROOT: u}, min_len=min_len)[paths.ROOT]
    third = (parts.p1 - X.three_ways(parts.p2) + 2 * np.einsum("x,xi,xj,xl->ijl", parts.g, u, u, u, optimize=True)) / parts.n_docs
    rows = []
    for alpha0 in grid:
        try:
            w = X.lean_whitener(u, sigma, root.m1, alpha0)
        except X.RankTooLow:
            continue
        turn = u.T @ w.w
        b = w.w.T @ root.m1
        core = 0.5 * (alpha0 + 1) * (alpha0 + 2) * X.multilinear(third, turn, turn, turn) - 0.5 * alpha0 * (alpha0 + 1) * X.u_terms(w.w, root.m1, alpha0) + alpha0**2 * X.outer(b, b, b)
        flat = X.recover(X.power_decompose(core, seed=seed), w, alpha0)
        rows.append((alpha0, abs(flat.share_sum - 1), float(flat.clipped.sum())))
    return min(rows, key=lambda r: r[1] + r[2])[0], rows
