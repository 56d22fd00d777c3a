"""Cross approximation: pivot rows and columns that reproduce a matrix, with full or alternating pivoting."""

from __future__ import annotations

import numpy as np


def full(a: np.ndarray, eps: float, kmax: int | None = None) -> tuple[list[int], list[int]]:
    """Pivots by the largest entry of the rest; stops when it falls below eps times the first one."""
    rest = np.array(a, dtype=a.dtype, copy=True)
    at, to = np.arange(rest.shape[0]), np.arange(rest.shape[1])  # rows and columns that are left
    rows, cols, first, step = [], [], None, None
    for _ in range(min(a.shape) if kmax is None else min(kmax, *a.shape)):
        i, j, p = _largest(rest, step)
        first = abs(p) if first is None else first
        if abs(p) == 0 or abs(p) <= eps * first:
            break
        rows.append(int(at[i]))
        cols.append(int(to[j]))
        step = (rest[:, j] / p, rest[i].copy(), i, j)
        if len(rows) % 16 == 0:  # taken rows and columns are zero: they go now and then, the order of the others stays
            _largest(rest, step)
            left, free = ~np.isin(at, rows), ~np.isin(to, cols)
            rest, at, to, step = rest[np.ix_(left, free)], at[left], to[free], None
            if not rest.size:
                break
    return rows, cols


def _largest(rest: np.ndarray, step: tuple | None, most: int = 1 << 14):
    """(i, j, entry) of the largest entry after taking off a step (column, row, i, j), strip by strip so that each is passed in
    the caches."""
    high = max(1, most // rest.shape[1])
    room, best = np.empty((min(high, len(rest)), rest.shape[1]), rest.dtype), (-1.0, 0, 0)
    for r in range(0, len(rest), high):
        part = rest[r : r + high]
        z = room[: len(part)]
        if step is not None:
            part -= np.multiply(step[0][r : r + high, None], step[1], out=z)
            part[:, step[3]] = 0
            if r <= step[2] < r + high:
                part[step[2] - r] = 0
        size = np.abs(part) if np.iscomplexobj(part) else np.abs(part, out=z)
        k = int(size.argmax())
        if size.flat[k] > best[0]:
            best = (size.flat[k], r + k // rest.shape[1], k % rest.shape[1])
    return best[1], best[2], rest[best[1], best[2]]


def partial(entry_row, entry_col, shape: tuple[int, int], eps: float, kmax: int | None = None) -> tuple[list[int], list[int], np.ndarray, np.ndarray]:
    """Alternating pivoting on rows and columns produced on demand: pivots and factors with matrix about u @ v.T."""
    m, n = shape
    us, vs, rows, cols = [], [], [], []
    i, total = 0, 0.0
    left = set(range(m))
    while left and len(rows) < min(m, n, kmax or m):
        row = entry_row(i) - sum((u[i] * v for u, v in zip(us, vs, strict=True)), np.zeros(n))
        left.discard(i)
        j = int(np.argmax(np.abs(row)))
        if row[j] == 0:
            if not left:
                break
            i = min(left)
            continue
        col = (entry_col(j) - sum((v[j] * u for u, v in zip(us, vs, strict=True)), np.zeros(m))) / row[j]
        us.append(col)
        vs.append(row)
        rows.append(i)
        cols.append(j)
        step = np.linalg.norm(col) * np.linalg.norm(row)
        total = max(total, step)
        if step <= eps * total or not left:
            break
        rest = np.abs(col).copy()
        rest[list(set(range(m)) - left)] = -1
        i = int(np.argmax(rest))
    u = np.stack(us, 1) if us else np.zeros((m, 0))
    v = np.stack(vs, 1) if vs else np.zeros((n, 0))
    return rows, cols, u, v


def pivots(a: np.ndarray, eps: float, kmax: int | None = None, pivot: str = "full") -> tuple[list[int], list[int]]:
    if pivot == "full":
        return full(a, eps, kmax)
    rows, cols, _, _ = partial(lambda i: a[i], lambda j: a[:, j], a.shape, eps, kmax)
    return rows, cols


def interpolation(a: np.ndarray, rows: list[int], cols: list[int]) -> np.ndarray:
    """V = A(:, cols) A(rows, cols)^-1; its pivot rows are the identity."""
    if not rows:
        return np.zeros((len(a), 0))
    v = np.linalg.solve(a[np.ix_(rows, cols)].T, a[:, cols].T).T
    v[rows] = np.eye(len(rows))
    return v
