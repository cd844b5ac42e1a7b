"""The iterations themselves, on node moments: row split, column split, and what they are compared with.

Node moments are stacked matrices or any kind of :mod:`meshspan.operators.nodes`: the loops ask for products alone.
Each loop yields, after every step, (inner rounds so far, node bases). Node bases are stacked (N, d, r);
a central method has N = 1. Column-split loops yield the stacked rows of all nodes as one basis.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np

from meshspan.functions.linalg import Powers, anchor_scale, factor_of, positive_qr
from meshspan.operators.nodes import as_nodes

Steps = Iterator[tuple[int, np.ndarray]]


def _mixed(power: np.ndarray, v: np.ndarray) -> np.ndarray:
    return np.tensordot(power.T, v, 1)


# ---------------------------------------------------------------- row split


def row_split(m, w: np.ndarray, rounds: Sequence[int], q0: np.ndarray, rescale: str = "safe") -> Steps:
    """Multiply with the own matrix, average with the neighbours, read the sum, re-orthonormalise."""
    m = as_nodes(m)
    powers, q, inner = Powers(w), np.broadcast_to(q0, (m.n, *q0.shape)), 0
    for k in rounds:
        power = powers[k]
        inner += k
        q, _ = positive_qr(_mixed(power, m.apply(q)) * anchor_scale(power, rescale)[:, None, None])
        yield inner, q


def central(m, outer: int, q0: np.ndarray) -> Steps:
    """Orthogonal iteration on the mean matrix; counts outer steps only."""
    m, q = as_nodes(m), q0
    for t in range(outer):
        q, _ = positive_qr(m.mean_apply(q))
        yield t + 1, q[None]


def central_sequential(m, per_vector: int, q0: np.ndarray) -> Steps:
    """One vector after the other by power steps, found ones projected out; the rest stay at the start."""
    m, q, t = as_nodes(m), q0.copy(), 0
    for k in range(q.shape[1]):
        x = q[:, k]
        for _ in range(per_vector):
            x = m.mean_apply(x[:, None])[:, 0]
            x = x - q[:, :k] @ (q[:, :k].T @ x)
            x /= np.linalg.norm(x)
            q[:, k] = x
            t += 1
            yield t, positive_qr(q)[0][None]


def sequential(m, w: np.ndarray, rounds: Sequence[int], per_vector: int, q0: np.ndarray, rescale: str = "safe") -> Steps:
    """The same with the product summed by averaging rounds."""
    m, powers, inner = as_nodes(m), Powers(w), 0
    q = np.repeat(q0[None], m.n, 0)
    for k in range(q.shape[2]):
        x = q[:, :, k]
        for t in range(per_vector):
            power = powers[rounds[min(t, len(rounds) - 1)]]
            inner += rounds[min(t, len(rounds) - 1)]
            x = _mixed(power, m.apply(x[:, :, None])[:, :, 0]) * anchor_scale(power, rescale)[:, None]
            found = q[:, :, :k]
            x = x - np.einsum("nik,nk->ni", found, np.einsum("nik,ni->nk", found, x))
            x = x / np.linalg.norm(x, axis=1)[:, None]
            q[:, :, k] = x
            yield inner, positive_qr(q)[0]


def hebbian(m, w: np.ndarray, outer: int, q0: np.ndarray, step: float = 0.1) -> Steps:
    """Average the bases, then a generalised Hebbian correction; no orthonormalisation."""
    m = as_nodes(m)
    q = np.repeat(q0[None], m.n, 0)
    for t in range(outer):
        mq = m.apply(q)
        q = _mixed(w, q) + step * (mq - q @ np.triu(np.swapaxes(q, 1, 2) @ mq))
        yield t + 1, positive_qr(q)[0]


def projected_gradient(m, w: np.ndarray, outer: int, q0: np.ndarray, step: float = 0.1) -> Steps:
    """Average the bases, a gradient step on the trace, back to orthonormal. The gradient's factor of two
    is part of the step."""
    m = as_nodes(m)
    q = np.repeat(q0[None], m.n, 0)
    for t in range(outer):
        q, _ = positive_qr(_mixed(w, q) + step * m.apply(q))
        yield t + 1, q


def tracking(m, w: np.ndarray, outer: int, q0: np.ndarray, rounds: int = 3, fast: bool = False) -> Steps:
    """Track the network's mean product: the mixed tracker plus the change of the own product."""
    from meshspan.operators.consensus import fast_power

    power = fast_power(w, rounds) if fast else Powers(w)[rounds]
    m = as_nodes(m)
    q = np.repeat(q0[None], m.n, 0)
    product = m.apply(q)
    tracker = product
    for t in range(outer):
        tracker = _mixed(power, tracker)
        q, _ = positive_qr(tracker)
        now = m.apply(q)
        tracker, product = tracker + now - product, now
        yield rounds * (t + 1), q


# ---------------------------------------------------------------- column split


def distributed_factor(grams: np.ndarray, power: np.ndarray | None) -> np.ndarray:
    """Every node's upper triangular factor of the summed Gram matrix, from mixed node Gram matrices
    (None: the exact sum)."""
    n = len(grams)
    sums = np.repeat(grams.sum(0)[None], n, 0) if power is None else _mixed(power, grams) * n
    return np.stack([factor_of(s) for s in sums])


def gram_qr(v: np.ndarray, blocks: Sequence[np.ndarray], power: np.ndarray | None, passes: int = 1) -> np.ndarray:
    """Orthonormal rows-by-node basis: each node solves its block with its own factor."""
    q = v.copy()
    for _ in range(passes):
        factors = distributed_factor(np.stack([q[b].T @ q[b] for b in blocks]), power)
        for b, f in zip(blocks, factors, strict=True):
            q[b] = np.linalg.solve(f.T, q[b].T).T
    return q


def modified_gram_schmidt(v: np.ndarray, blocks: Sequence[np.ndarray], power: np.ndarray | None) -> np.ndarray:
    """The same column by column: norms and inner products are averaged one phase after the other."""
    n, q = len(blocks), v.copy()

    def agreed(values: np.ndarray) -> np.ndarray:
        return np.repeat(values.sum(0)[None], n, 0) if power is None else _mixed(power, values) * n

    for k in range(q.shape[1]):
        norm = np.sqrt(np.maximum(agreed(np.array([[q[b, k] @ q[b, k]] for b in blocks]))[:, 0], 1e-300))
        for i, b in enumerate(blocks):
            q[b, k] /= norm[i]
        if k + 1 < q.shape[1]:
            inner = agreed(np.stack([q[b, k] @ q[b, k + 1 :] for b in blocks]))
            for i, b in enumerate(blocks):
                q[b, k + 1 :] -= np.outer(q[b, k], inner[i])
    return q


def column_split(c, blocks: Sequence[np.ndarray], w: np.ndarray, rounds: Sequence[int], q0: np.ndarray, qr: str = "gram", push_rounds: int | None = 50, rescale: str = "safe") -> Steps:
    """Scores averaged over the network, multiplied back by the own columns, orthonormalised by all. ``c``: the
    moments of all rows as one node."""
    c, powers, q, inner = as_nodes(c), Powers(w), q0, 0
    agree = None if push_rounds is None else powers[push_rounds]
    for k in rounds:
        inner += k
        v = c.column_product(blocks, powers[k], q, rescale)
        q = gram_qr(v, blocks, agree) if qr == "gram" else modified_gram_schmidt(v, blocks, agree)
        yield inner, q[None]


def column_sequential(c, blocks: Sequence[np.ndarray], w: np.ndarray, rounds: Sequence[int], per_vector: int, q0: np.ndarray, push_rounds: int | None = 50, rescale: str = "safe") -> Steps:
    """One vector after the other over split columns; inner products are averaged too."""
    c, powers, q, inner = as_nodes(c), Powers(w), q0.copy(), 0
    agree = None if push_rounds is None else powers[push_rounds]
    n = len(blocks)

    def summed(values: np.ndarray) -> np.ndarray:
        return np.repeat(values.sum(0)[None], n, 0) if agree is None else _mixed(agree, values) * n

    for k in range(q.shape[1]):
        for t in range(per_vector):
            rate = rounds[min(t, len(rounds) - 1)]
            inner += rate
            x = c.column_product(blocks, powers[rate], q[:, k : k + 1], rescale)[:, 0]
            if k:
                dots = summed(np.stack([q[b, :k].T @ x[b] for b in blocks]))
                x = x - np.concatenate([q[b, :k] @ dots[i] for i, b in enumerate(blocks)])[np.argsort(np.concatenate(blocks))]
            norms = np.sqrt(summed(np.array([[x[b] @ x[b]] for b in blocks]))[:, 0])
            for i, b in enumerate(blocks):
                x[b] /= norms[i]
            q[:, k] = x
            yield inner, positive_qr(q)[0][None]


def block_split(m, blocks: Sequence[np.ndarray], w_rows: np.ndarray, w_columns: np.ndarray, rounds: Sequence[int], q0: np.ndarray) -> Steps:
    """Rows and columns both split: products of every row node with every column holder's part are averaged over
    the row network, then over the holders, as the first row node reads them."""
    m, rows, columns, q, inner = as_nodes(m), Powers(w_rows), Powers(w_columns), q0, 0
    holders, r = len(blocks), q0.shape[1]
    for k in rounds:
        inner += k
        wide = np.zeros((len(q), holders * r))
        for j, b in enumerate(blocks):
            wide[b, j * r : (j + 1) * r] = q[b]
        parts = np.tensordot(rows[k][:, 0], m.apply(wide), 1).reshape(len(q), holders, r)
        share = columns[k].T * anchor_scale(columns[k], "safe")[:, None]
        v = np.empty_like(q)
        for i, b in enumerate(blocks):
            v[b] = np.einsum("j,djr->dr", share[i], parts[b]) / holders
        q = gram_qr(v, blocks, columns[max(k, 1)])
        yield inner, q[None]
