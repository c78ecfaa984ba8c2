"""Maximum-weight bipartite matching of one bundle pair (numpy only).

Potentials and shortest augmenting paths over the smaller side; every row step is
vectorised over the columns.  Weights are non-negative, so the optimum of the
padded square problem is the optimum of the sparse one.
"""

from __future__ import annotations

from itertools import permutations

import numpy as np


def max_weight(weights: np.ndarray) -> tuple[int, list[tuple[int, int]]]:
    """(total, matched index pairs with positive weight) of a matrix of non-negative integers."""
    if not weights.size:
        return 0, []
    flip = weights.shape[0] > weights.shape[1]
    w = weights.T if flip else weights
    n, m = w.shape
    cost = (w.max() - w).astype(np.int64)
    u, v = np.zeros(n + 1, np.int64), np.zeros(m + 1, np.int64)
    owner, way = np.zeros(m + 1, np.int64), np.zeros(m + 1, np.int64)
    far = np.iinfo(np.int64).max // 4
    for i in range(1, n + 1):
        owner[0], j = i, 0
        least, used = np.full(m + 1, far), np.zeros(m + 1, bool)
        while True:
            used[j] = True
            row = owner[j]
            free = ~used[1:]
            reach = cost[row - 1] - u[row] - v[1:]
            better = free & (reach < least[1:])
            least[1:][better] = reach[better]
            way[1:][better] = j
            step_at = np.where(free, least[1:], far)
            nxt = int(step_at.argmin()) + 1
            step = least[nxt]
            u[owner[used]] += step
            v[used] -= step
            least[1:][free] -= step
            j = nxt
            if owner[j] == 0:
                break
        while j:
            owner[j] = owner[way[j]]
            j = int(way[j])
    pairs = [(int(owner[j]) - 1, j - 1) for j in range(1, m + 1) if owner[j] and w[owner[j] - 1, j - 1] > 0]
    return int(sum(w[a, b] for a, b in pairs)), [(b, a) if flip else (a, b) for a, b in pairs]


def greedy(weights: np.ndarray) -> tuple[int, list[tuple[int, int]]]:
    """Heaviest edge first; ties by index."""
    rows, cols = np.nonzero(weights)
    order = np.lexsort((cols, rows, -weights[rows, cols]))
    left: set[int] = set()
    right: set[int] = set()
    pairs = []
    for k in order:
        a, b = int(rows[k]), int(cols[k])
        if a not in left and b not in right:
            left.add(a)
            right.add(b)
            pairs.append((a, b))
    return int(sum(weights[a, b] for a, b in pairs)), pairs


def brute_force(weights: np.ndarray) -> int:
    """Best total over all injections; for tests on small matrices."""
    w = weights if weights.shape[0] <= weights.shape[1] else weights.T
    return max((int(sum(w[i, p[i]] for i in range(w.shape[0]))) for p in permutations(range(w.shape[1]), w.shape[0])), default=0)
