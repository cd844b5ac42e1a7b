"""Small dense linear algebra used inside tasks; nothing here is proportional to the rows of a table."""

from __future__ import annotations

import numpy as np


def positive_qr(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """QR with a non-negative diagonal of R, so that every node picks the same signs. Works on a stack
    of matrices too."""
    q, r = np.linalg.qr(v)
    sign = np.where(np.diagonal(r, axis1=-2, axis2=-1) < 0, -1.0, 1.0)
    return q * sign[..., None, :], r * sign[..., :, None]


def cholesky_qr(v: np.ndarray, passes: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """QR by the factor of the Gram matrix; the second pass repairs what conditioning costs."""
    q, total = v, np.eye(v.shape[1])
    for _ in range(passes):
        factor = factor_of(q.T @ q)
        q = np.linalg.solve(factor.T, q.T).T
        total = factor @ total
    return q, total


def factor_of(gram: np.ndarray) -> np.ndarray:
    """Upper triangular R with RᵀR = gram; a jitter stands in where the matrix is not definite."""
    gram = (gram + gram.T) / 2
    scale = max(np.trace(gram) / len(gram), np.finfo(float).tiny)
    for jitter in (0.0, 1e-14, 1e-12, 1e-10, 1e-8, 1e-4):
        try:
            return np.linalg.cholesky(gram + jitter * scale * np.eye(len(gram))).T
        except np.linalg.LinAlgError:
            continue
    raise np.linalg.LinAlgError("the columns are dependent")


def random_basis(d: int, r: int, seed: int) -> np.ndarray:
    """The orthonormal start that all nodes share."""
    if not 1 <= r <= d:
        raise ValueError("the rank must lie between 1 and the dimension")
    return positive_qr(np.random.default_rng(seed).standard_normal((d, r)))[0]


def leading(m: np.ndarray, r: int) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues in falling order and the basis of the first r eigenvectors."""
    values, vectors = np.linalg.eigh((m + m.T) / 2)
    return values[::-1], vectors[:, ::-1][:, :r]


def angle_error(q: np.ndarray, truth: np.ndarray) -> np.ndarray:
    """Mean squared sine of the principal angles between orthonormal bases; q may be a stack."""
    cross = np.swapaxes(q, -1, -2) @ truth
    return np.maximum(0.0, 1 - (cross**2).sum((-1, -2)) / truth.shape[1])


class Powers:
    """Powers of a mixing matrix, each computed once."""

    def __init__(self, w: np.ndarray):
        self.known = {0: np.eye(len(w)), 1: np.asarray(w, float)}

    def __getitem__(self, k: int) -> np.ndarray:
        if k not in self.known:
            below = max(j for j in self.known if j < k)
            if k - below == 1 or k % 2:
                self.known[k] = self[k - 1] @ self.known[1]
            else:
                self.known[k] = self[k // 2] @ self[k // 2]
        return self.known[k]


def anchor_scale(power: np.ndarray, how: str = "safe", floor: float = 1e-12) -> np.ndarray:
    """What a node multiplies its mixed average with to read a sum: one over its entry of the power's
    first column. ``safe`` takes the number of nodes where that entry is (nearly) zero, ``n`` takes it
    everywhere, ``none`` keeps the average; ``anchor`` divides whatever the entry is."""
    n, first = len(power), power[:, 0]
    if how == "none":
        return np.ones(n)
    if how == "n":
        return np.full(n, float(n))
    if how == "anchor":
        with np.errstate(divide="ignore"):
            return 1 / first
    if how != "safe":
        raise ValueError(f"unknown rescaling {how!r}")
    return np.where(first > floor, 1 / np.maximum(first, floor), float(n))
