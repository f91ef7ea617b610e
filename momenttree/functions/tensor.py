"""Small dense tensors: products, permutations, whitening, power iteration, recovery.  All on the driver, k is at most about ten."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

import numpy as np


def outer(*vectors: np.ndarray) -> np.ndarray:
    out = vectors[0]
    for v in vectors[1:]:
        out = np.multiply.outer(out, v)
    return out


def permute(a: np.ndarray, order: tuple[int, int, int]) -> np.ndarray:
    """out[i1, i2, i3] = a[i_order[0], i_order[1], i_order[2]], orders counted from 1."""
    place = [0, 0, 0]
    for axis, which in enumerate(order):
        place[which - 1] = axis
    return np.transpose(a, place)


def three_ways(a: np.ndarray) -> np.ndarray:
    """Sum of the three distinct placements of a tensor that is symmetric in its last two modes."""
    return a + permute(a, (2, 1, 3)) + permute(a, (3, 1, 2))


def multilinear(t: np.ndarray, *maps: np.ndarray) -> np.ndarray:
    """t with mode m contracted with the rows of maps[m]; vectors drop their mode."""
    out = t
    for axis in reversed(range(t.ndim)):
        out = np.moveaxis(np.tensordot(out, maps[axis], axes=([axis], [0])), -1, axis) if maps[axis].ndim == 2 else np.tensordot(out, maps[axis], axes=([axis], [0]))
    return out


def diagonal3(v: np.ndarray) -> np.ndarray:
    out = np.zeros((len(v),) * 3)
    at = np.arange(len(v))
    out[at, at, at] = v
    return out


#: Larger symmetric matrices get a few eigenpairs from a block Krylov basis instead of all of them.
WHOLE_SPECTRUM = 400


def largest_eigs(m: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k largest eigenpairs of a symmetric matrix, values descending."""
    m = (m + m.T) / 2
    if len(m) > WHOLE_SPECTRUM and 40 * k < len(m):
        random = np.random.default_rng(len(m))
        start = random.normal(size=(len(m), k + 6))
        for _ in range(4):
            blocks = [np.linalg.qr(start)[0]]
            for _ in range(8):
                blocks.append(np.linalg.qr(m @ blocks[-1])[0])
            basis = np.linalg.qr(np.hstack(blocks))[0]
            values, turn = np.linalg.eigh(basis.T @ m @ basis)
            order = np.argsort(values)[::-1][: k + 6]
            start = basis @ turn[:, order]
            values, vectors = values[order[:k]], start[:, :k]
            if np.linalg.norm(m @ vectors - vectors * values, axis=0).max() <= 1e-10 * max(abs(values[0]), 1e-300):
                return values, vectors
    values, vectors = np.linalg.eigh(m)
    order = np.argsort(values)[::-1][:k]
    return values[order], vectors[:, order]


class RankTooLow(ValueError):
    """Fewer positive eigenvalues than topics asked for."""

    def __init__(self, found: int, wanted: int):
        super().__init__(f"{found} positive eigenvalues, {wanted} topics asked for")
        self.found = found


@dataclass
class Whitener:
    """w whitens, back undoes it: w.T M w = I and back = pinv(w.T)."""

    w: np.ndarray
    back: np.ndarray
    values: np.ndarray


def whiten(vectors: np.ndarray, values: np.ndarray, tol: float = 1e-12) -> Whitener:
    good = int((values > tol * max(values.max(initial=0.0), 1e-300)).sum())
    if good < len(values):
        raise RankTooLow(good, len(values))
    root = np.sqrt(values)
    return Whitener(vectors / root, vectors * root, values)


def lean_whitener(u: np.ndarray, sigma: np.ndarray, m1: np.ndarray, alpha0: float) -> Whitener:
    """Whitener of (alpha0 + 1) E2 - alpha0 m1 m1' from the eigenpairs (u, sigma) of E2: a second step of size k only."""
    projected = u.T @ m1
    small = (alpha0 + 1) * np.diag(sigma) - alpha0 * np.outer(projected, projected)
    values, vectors = largest_eigs(small, len(sigma))
    return whiten(u @ vectors, values)


def u_terms(w: np.ndarray, m1: np.ndarray, alpha0: float, e2: np.ndarray | None = None) -> np.ndarray:
    """The sum of the three E2 x M1 terms projected by w; without e2 by the identity that whitening gives."""
    b = w.T @ m1
    a = w.T @ e2 @ w if e2 is not None else (np.eye(len(b)) + alpha0 * np.outer(b, b)) / (alpha0 + 1)
    return np.einsum("ij,l->ijl", a, b) + np.einsum("il,j->ijl", a, b) + np.einsum("jl,i->ijl", a, b)


def core_from(p1: np.ndarray, p2: np.ndarray, g: np.ndarray, w: np.ndarray, m1: np.ndarray, alpha0: float, n_docs: float, e2: np.ndarray | None = None) -> np.ndarray:
    """The k x k x k core of the centred third moment.

    p1: sum of y (x) y (x) y, p2: sum of y (x) W' diag(c) W, g: per-word sums, all over documents with their triple weights.
    """
    third = p1 - three_ways(p2) + 2 * np.einsum("x,xi,xj,xl->ijl", g, w, w, w, optimize=True)
    b = w.T @ m1
    core = 0.5 * (alpha0 + 1) * (alpha0 + 2) * third / n_docs - 0.5 * alpha0 * (alpha0 + 1) * u_terms(w, m1, alpha0, e2) + alpha0**2 * outer(b, b, b)
    return sum(np.transpose(core, p) for p in ((0, 1, 2), (0, 2, 1), (1, 0, 2), (1, 2, 0), (2, 0, 1), (2, 1, 0))) / 6


@dataclass
class Pairs:
    """Robust eigenpairs of a symmetric tensor with the trace of their iterations."""

    values: np.ndarray
    vectors: np.ndarray  # columns
    residual: float
    trace: list[list[float]] = field(default_factory=list)


def seed_of(*parts: object) -> int:
    """A seed that depends on its parts only, never on visiting order."""
    return int.from_bytes(hashlib.blake2b("|".join(map(str, parts)).encode(), digest_size=8).digest(), "little")


def power_decompose(t: np.ndarray, k: int | None = None, *, starts: int = 30, steps: int = 30, seed: int = 0, tol: float | None = None, trace: bool = False) -> Pairs:
    """k times: all starts iterate at once as columns, the one of the largest value wins and is deflated."""
    n = t.shape[0]
    k = n if k is None else k
    random = np.random.default_rng(seed)
    rest, values, vectors, traces = t.copy(), [], [], []
    for _ in range(k):
        v = random.normal(size=(n, starts))
        v /= np.linalg.norm(v, axis=0)
        moved = []
        for _ in range(steps):
            new = np.einsum("ijl,js,ls->is", rest, v, v, optimize=True)
            norm = np.linalg.norm(new, axis=0)
            new = np.where(norm > 0, new / np.where(norm > 0, norm, 1), v)
            change = float(np.abs(new - v).max())
            v = new
            moved.append(change)
            if tol is not None and change < tol:
                break
        gains = np.einsum("ijl,is,js,ls->s", rest, v, v, v, optimize=True)
        best = int(np.argmax(gains))
        values.append(float(gains[best]))
        vectors.append(v[:, best])
        rest = rest - gains[best] * outer(v[:, best], v[:, best], v[:, best])
        traces.append(moved)
    return Pairs(np.array(values), np.array(vectors).T, float(np.linalg.norm(rest)), traces if trace else [])


@dataclass
class Flat:
    """One level: topics in columns of phi, their shares, and how much had to be put right."""

    phi: np.ndarray
    shares: np.ndarray
    alpha: np.ndarray
    clipped: np.ndarray
    share_sum: float


def to_simplex(v: np.ndarray) -> tuple[np.ndarray, float]:
    """Negative entries cut off and the rest scaled to sum 1; the mass that was cut, relative to the sum."""
    total = v.sum()
    v = v if total >= 0 else -v
    positive = np.clip(v, 0, None)
    mass = positive.sum()
    return (positive / mass if mass > 0 else np.full_like(v, 1 / len(v))), float((positive.sum() - v.sum()) / max(abs(v.sum()), 1e-300))


def recover(pairs: Pairs, whitener: Whitener, alpha0: float) -> Flat:
    """Word distributions and weights from eigenpairs of the core: share = value^-2, word vector = value * back @ vector."""
    values = np.where(np.abs(pairs.values) > 1e-12, pairs.values, 1e-12)
    shares = 1 / values**2
    made = [to_simplex(value * (whitener.back @ pairs.vectors[:, z])) for z, value in enumerate(values)]
    phi, clipped = np.array([p for p, _ in made]).T, np.array([c for _, c in made])
    order = sorted(range(len(shares)), key=lambda z: (-round(shares[z], 9), int(np.argmax(phi[:, z]))))
    shares, phi, clipped = shares[order], phi[:, order], clipped[order]
    return Flat(phi, shares, alpha0 * shares, clipped, float(shares.sum()))


def population_moments(alpha: np.ndarray, phi: np.ndarray, order: int) -> np.ndarray:
    """E1, E2 or E3 of a node with Dirichlet weights alpha and children's words in columns of phi (drawing from an urn)."""
    a0, k = alpha.sum(), len(alpha)
    if order == 1:
        return phi @ alpha / a0
    q = np.multiply.outer(alpha, alpha) + np.diag(alpha)
    if order == 2:
        return phi @ (q / (a0 * (a0 + 1))) @ phi.T
    same = np.eye(k)
    q3 = q[:, :, None] * (alpha[None, None, :] + same[:, None, :] + same[None, :, :]) / (a0 * (a0 + 1) * (a0 + 2))
    return np.einsum("abc,xa,yb,zc->xyz", q3, phi, phi, phi, optimize=True)


def centred_moments(m1: np.ndarray, e2: np.ndarray, e3: np.ndarray, alpha0: float) -> tuple[np.ndarray, np.ndarray]:
    """Dense M2 and M3, which equal sums of shares times powers of the children's words."""
    m2 = (alpha0 + 1) * e2 - alpha0 * np.outer(m1, m1)
    u = np.einsum("ij,l->ijl", e2, m1)
    u = u + np.einsum("il,j->ijl", e2, m1) + np.einsum("jl,i->ijl", e2, m1)
    return m2, 0.5 * (alpha0 + 1) * (alpha0 + 2) * e3 - 0.5 * alpha0 * (alpha0 + 1) * u + alpha0**2 * outer(m1, m1, m1)


def best_matching(cost: np.ndarray) -> list[int]:
    """For each row its column in the assignment of least total cost; dynamic programme over column sets."""
    n, m = cost.shape
    best: dict[int, tuple[float, tuple[int, ...]]] = {0: (0.0, ())}
    for row in range(n):
        step: dict[int, tuple[float, tuple[int, ...]]] = {}
        for used, (total, chosen) in best.items():
            free = [c for c in range(m) if not used >> c & 1]
            for c in free or [-1]:
                key = used | 1 << c if c >= 0 else used
                new = total + (cost[row, c] if c >= 0 else 0.0)
                if key not in step or new < step[key][0]:
                    step[key] = new, (*chosen, c)
        best = step
    return list(min(best.values())[1])


def kl(p: np.ndarray, q: np.ndarray, eps: float = 1e-12) -> float:
    """Divergence of p from q, natural logarithm, both smoothed by eps and scaled to sum 1."""
    p, q = (p + eps) / (p + eps).sum(), (q + eps) / (q + eps).sum()
    return float((p * np.log(p / q)).sum())
