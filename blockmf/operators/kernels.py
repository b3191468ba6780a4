"""Lane kernels on numpy arrays, with one update rule for all.

A block is (rows, cols, vals): positions of the factor rows in p and q, and the ratings, in visit order. Kernels change p and q in place.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from blockmf.operators.params import MFParams


def _delta(p, q, err, params: MFParams):
    """Steps of row vectors and column vectors (both from the vectors given), for one rating or a batch."""
    g = params.gamma * params.grad_scale
    e = err[..., None] if np.ndim(err) else err
    dp = g * (e * q - params.lam_p * p)
    seen = p + dp if params.q_sees == "new_p" else p
    return dp, g * (e * seen - params.lam_q * q)


def _dots(pu, qv):
    """Inner products, summed from the first element on: the same bits for one pair and for many."""
    total = pu[..., 0] * qv[..., 0]
    for j in range(1, pu.shape[-1]):
        total = total + pu[..., j] * qv[..., j]
    return total


def narrow_kernel(rows, cols, vals, p, q, params: MFParams) -> None:
    """Ratings one by one, in order."""
    for u, v, r in zip(rows.tolist(), cols.tolist(), vals.tolist(), strict=True):
        pu, qv = p[u], q[v]
        dp, dq = _delta(pu, qv, r - float(_dots(pu, qv)), params)
        p[u] = pu + dp
        q[v] = qv + dq


def ordered_kernel(rows, cols, vals, p, q, params: MFParams) -> None:
    """The narrow kernel, bit for bit, in steps of ratings that share no vector: what shares one keeps its order."""
    for at in _parted(rows, cols):
        u, v = rows[at], cols[at]
        pu, qv = p[u], q[v]
        dp, dq = _delta(pu, qv, vals[at] - _dots(pu, qv), params)
        p[u], q[v] = pu + dp, qv + dq


def _parted(rows, cols) -> list[np.ndarray]:
    """Positions of a batch in sub-batches without a shared row or column; each keeps the order of what shares one."""
    if not len(rows):
        return []
    level_u, level_v, level = [0] * (int(rows.max()) + 1), [0] * (int(cols.max()) + 1), []
    for u, v in zip(rows.tolist(), cols.tolist(), strict=True):
        a, b = level_u[u], level_v[v]
        n = a if a > b else b
        level_u[u] = level_v[v] = n + 1
        level.append(n)
    level = np.array(level)
    order = np.argsort(level, kind="stable")
    return np.split(order, np.flatnonzero(np.diff(level[order])) + 1)


def wide_kernel(rows, cols, vals, p, q, params: MFParams) -> None:
    """Batches of batch_width ratings at once. collide: what becomes of several steps of one vector in a batch:
    'sum' adds them, 'mean' averages them, 'last' keeps the last (lock-free overwriting), 'split' runs
    sub-batches without shared vectors, which equals the narrow kernel."""
    width = max(1, params.batch_width)
    dots = _dots if width == 1 or params.collide == "split" else lambda a, b: np.einsum("ij,ij->i", a, b)
    for lo in range(0, len(vals), width):
        part = np.arange(lo, min(lo + width, len(vals)))
        for i in _parted(rows[part], cols[part]) if params.collide == "split" else (slice(None),):
            at = part[i]
            u, v = rows[at], cols[at]
            pu, qv = p[u], q[v]
            dp, dq = _delta(pu, qv, vals[at] - dots(pu, qv), params)
            if params.collide == "last":
                p[u], q[v] = pu + dp, qv + dq
            elif params.collide == "split":
                p[u], q[v] = pu + dp, qv + dq
            else:
                _add(p, u, dp, params.collide == "mean")
                _add(q, v, dq, params.collide == "mean")


def _add(m: np.ndarray, ids: np.ndarray, d: np.ndarray, mean: bool) -> None:
    """Add the sums (or means) of the steps of each vector: sorted by vector, and each run of one vector added up."""
    order = np.argsort(ids, kind="stable")
    ids = ids[order]
    first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
    total = np.add.reduceat(d[order], first, axis=0)
    m[ids[first]] += total / np.diff(np.append(first, len(ids)))[:, None] if mean else total


def run_block(kind: str, u, v, r, p_ids, p, q_ids, q, params: MFParams) -> None:
    """One visit: ids -> positions, then the lane's kernel. Ids of p and q are sorted."""
    rows, cols = np.searchsorted(p_ids, u), np.searchsorted(q_ids, v)
    {"narrow": ordered_kernel, "wide": wide_kernel}[kind](rows, cols, r, p, q, params)


def vectors(m: np.ndarray) -> pa.Array:
    """Rows of a matrix as an Arrow list column."""
    ends = np.arange(0, m.size + 1, max(1, m.shape[1]), dtype=np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.ascontiguousarray(m).ravel()))
