"""Tour improvements over the rows of a block, and the exact optimum of small blocks."""

from __future__ import annotations

from functools import lru_cache
from itertools import permutations

import numpy as np

from rowloom.operators.kernels.distance import matrix


#: Range of the numbers that keep the places of a linked path in order.
PLACES = 1 << 62


def adjacent_swap(codes: np.ndarray, max_passes: int | None = None) -> np.ndarray:
    """Swaps successive rows wherever that saves runs, in passes over the block until one changes nothing."""
    rows = codes.tolist()
    order = list(range(len(rows)))

    def d(i: int, j: int) -> int:
        return sum(x != y for x, y in zip(rows[order[i]], rows[order[j]], strict=True))

    passes = 0
    changed = len(rows) > 2
    while changed and (max_passes is None or passes < max_passes):
        changed = False
        passes += 1
        for i in range(len(order) - 1):
            gain = 0
            if i:
                gain += d(i - 1, i) - d(i - 1, i + 1)
            if i + 2 < len(order):
                gain += d(i + 1, i + 2) - d(i, i + 2)
            if gain > 0:
                order[i], order[i + 1] = order[i + 1], order[i]
                changed = True
    return np.array(order, "int64")


def window_swap(codes: np.ndarray, reach: int = 4) -> np.ndarray:
    """One pass that exchanges each row with the row at most `reach` after it that saves most runs."""
    rows = codes.tolist()
    n = len(rows)
    order = list(range(n))

    def d(a: int, b: int) -> int:
        if a < 0 or b >= n:
            return 0
        return sum(x != y for x, y in zip(rows[order[a]], rows[order[b]], strict=True))

    def around(i: int, j: int) -> int:
        places = {(i - 1, i), (i, i + 1), (j - 1, j), (j, j + 1)}
        return sum(d(a, b) for a, b in places)

    for i in range(n - 1):
        best, at = 0, -1
        for j in range(i + 1, min(n, i + reach + 1)):
            before = around(i, j)
            order[i], order[j] = order[j], order[i]
            gain = before - around(i, j)
            order[i], order[j] = order[j], order[i]
            if gain > best:
                best, at = gain, j
        if at >= 0:
            order[i], order[at] = order[at], order[i]
    return np.array(order, "int64")


def reinsertion(codes: np.ndarray) -> np.ndarray:
    """One pass: each row in turn is taken out and put where the path grows least (its own place wins ties,
    then the first place).

    Successive equal rows are one node of a linked path. A row of a longer one lies at no cost, and by
    the triangle inequality no row goes inside one, since the place before it comes first and costs no
    more. Only rows whose own place costs something look at all steps of the path: the steps of a column
    that has neither end's value cost 1, or 2 where the ends agree."""
    n, c = codes.shape
    if n < 3:
        return np.arange(n)
    first = np.flatnonzero(np.concatenate([[True], (codes[1:] != codes[:-1]).any(axis=1)]))
    m = len(first)
    if m < 2:
        return np.arange(n)
    lengths = np.diff(np.append(first, n))
    # narrow copies of the values, a column at a time; node m stands before the first and after the last
    ends = np.stack([np.append(np.unique(codes[first, j], return_inverse=True)[1], -1) for j in range(c)])
    ends = ends.astype("int16" if ends.max() < 1 << 15 else "int32")
    rows = [tuple(r) for r in ends.T.tolist()]
    nxt, prv = [*range(1, m + 1), 0], [m, *range(m)]
    left, right = ends, np.ascontiguousarray(ends[:, nxt])
    step = np.where(left == right, 2, 1).astype("uint8" if 2 * c < 255 else "int32")
    gap = max(1, PLACES // (m + 2))
    place = np.append(np.arange(m, dtype="int64") * gap + gap, 0)
    cost, part, most = np.empty(m + 1, step.dtype), np.empty(m + 1, step.dtype), np.iinfo(step.dtype).max
    miss, other = np.empty(m + 1, bool), np.empty(m + 1, bool)

    def join(u: int, v: int) -> None:
        nxt[u], prv[v] = v, u
        right[:, u] = left[:, v]
        step[:, u] = (left[:, u] == left[:, v]) + 1

    for x in np.flatnonzero(lengths == 1).tolist():
        p, q, here = prv[x], nxt[x], rows[x]
        own = sum(0 if h == a or h == b else 2 if a == b else 1 for h, a, b in zip(here, rows[p], rows[q], strict=True))
        if own == 0:
            continue
        join(p, q)
        cost.fill(0)
        for j in range(c):
            np.not_equal(left[j], here[j], out=miss)
            np.not_equal(right[j], here[j], out=other)
            miss &= other
            np.multiply(miss, step[j], out=part)
            cost += part
        cost[x] = most
        least = int(cost.min())
        u = p
        if least < own:
            found = np.flatnonzero(cost == least)
            u = int(found[place[found].argmin()])
        v = nxt[u]
        join(u, x)
        join(x, v)
        if u == p:
            continue
        after = int(place[v]) if v != m else int(place[u]) + 2 * gap
        place[x] = (int(place[u]) + after) // 2
        if place[x] == place[u] or after >= (1 << 63) - 1:
            at = m
            for k in range(m + 1):
                place[at] = k * gap
                at = nxt[at]
    order, at = [], nxt[m]
    while at != m:
        order.append(at)
        at = nxt[at]
    order = np.array(order)
    starts, sizes = first[order], lengths[order]
    return np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(n)


@lru_cache(maxsize=8)
def _inner(m: int) -> np.ndarray:
    return np.array(list(permutations(range(m))), "int64").reshape(-1, m)


def peephole(codes: np.ndarray, rows: int = 8) -> np.ndarray:
    """In successive groups of `rows` rows, the best order of the inner ones with both ends fixed."""
    order = np.arange(len(codes))
    for at in range(0, len(codes), rows):
        block = order[at : at + rows]
        m = len(block) - 2
        if m < 2:
            continue
        d = matrix(codes[block])
        inner = _inner(m) + 1
        cost = d[0, inner[:, 0]] + d[inner[:, -1], m + 1]
        for k in range(m - 1):
            cost = cost + d[inner[:, k], inner[:, k + 1]]
        best = inner[int(cost.argmin())]
        order[at + 1 : at + 1 + m] = block[best]
    return order


def optimal(codes: np.ndarray) -> np.ndarray:
    """A path with the fewest runs, by dynamic programming over subsets (12 rows at most)."""
    n = len(codes)
    if n > 12:
        raise ValueError("the exact optimum takes 12 rows at most")
    if n < 3:
        return np.arange(n)
    d = matrix(codes)
    best = np.full((1 << n, n), np.iinfo("int64").max // 2)
    back = np.full((1 << n, n), -1)
    for i in range(n):
        best[1 << i, i] = 0
    for mask in range(1, 1 << n):
        for i in range(n):
            if mask >> i & 1 and mask != 1 << i:
                rest = mask ^ 1 << i
                options = best[rest] + d[:, i]
                k = int(options.argmin())
                best[mask, i], back[mask, i] = options[k], k
    mask, at = (1 << n) - 1, int(best[-1].argmin())
    path = []
    while at >= 0:
        path.append(at)
        mask, at = mask ^ 1 << at, int(back[mask, at])
    return np.array(path[::-1], "int64")
