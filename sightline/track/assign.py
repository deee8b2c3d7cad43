"""Optimal one-to-one assignment by shortest augmenting paths."""

from __future__ import annotations

import numpy as np


def assign(score: np.ndarray, least: float) -> list[tuple[int, int]]:
    """Pairs (row, column) of the largest total score; pairs below ``least`` are not made. A feasible pair that is alone in its row and column is taken as it is;
    only the rows and columns of the others are searched."""
    if not score.size:
        return []
    fine = score >= least
    lone = fine & (fine.sum(0) == 1) & (fine.sum(1) == 1)[:, None]
    pairs = [(int(i), int(j)) for i, j in zip(*np.nonzero(lone))]
    left = fine & ~lone
    if left.any():
        rows, columns = np.flatnonzero(left.any(1)), np.flatnonzero(left.any(0))
        pairs += [(int(rows[i]), int(columns[j])) for i, j in _search(score[np.ix_(rows, columns)], least)]
        pairs.sort(key=lambda p: p[1])
    return pairs


def _search(score: np.ndarray, least: float) -> list[tuple[int, int]]:
    fine = score >= least
    n, m = score.shape
    # every row may also stay alone, at cost 0; gains are counted above the least score
    cost = np.concatenate([np.where(fine, -(score - least + 1e-9), 1e6), np.zeros((n, n))], 1)
    cols = m + n
    u, v = np.zeros(n + 1), np.zeros(cols + 1)
    owner, way = np.zeros(cols + 1, int), np.zeros(cols + 1, int)
    for i in range(1, n + 1):
        owner[0], j0 = i, 0
        low, used = np.full(cols + 1, np.inf), np.zeros(cols + 1, bool)
        while True:
            used[j0] = True
            i0 = owner[j0]
            reduced = cost[i0 - 1] - u[i0] - v[1:]
            free = ~used[1:]
            better = free & (reduced < low[1:])
            low[1:][better], way[1:][better] = reduced[better], j0
            j1 = int(np.argmin(np.where(free, low[1:], np.inf))) + 1
            delta = low[j1]
            u[owner[used]] += delta
            v[used] -= delta
            low[1:][free] -= delta
            j0 = j1
            if owner[j0] == 0:
                break
        while j0:
            j1 = way[j0]
            owner[j0], j0 = owner[j1], j1
    return [(int(owner[j]) - 1, j - 1) for j in range(1, m + 1) if owner[j] and fine[owner[j] - 1, j - 1]]
