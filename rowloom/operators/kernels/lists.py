"""Greedy walks on a sparse graph of sorted lists."""

from __future__ import annotations

from itertools import permutations

import numpy as np


#: Columns from which on a step compares its neighbours as one array.
WIDE = 8


def list_orders(c: int, k: int | None = None, lists: str | list[list[int]] = "rotations") -> list[list[int]]:
    """Column orders of the lists: the first `k` rotations (all: c), all c! orders, or those given."""
    if not isinstance(lists, str):
        orders = [list(x) for x in lists]
    elif lists == "rotations":
        orders = [[(j - r) % c for j in range(c)] for r in range(c)]
    elif lists == "all":
        orders = [list(p) for p in permutations(range(c))]
    else:
        raise ValueError("lists is 'rotations', 'all' or a list of column orders")
    return orders if k is None else orders[:k]


def _digits(codes: np.ndarray, gray: bool) -> np.ndarray:
    """Sort digits of a column order: as they are, or turned over after an odd sum of earlier digits."""
    if not gray:
        return codes
    before = np.cumsum(codes, axis=1) - codes
    return np.where(before % 2 == 0, codes, -codes)


def sorted_lists(codes: np.ndarray, orders: list[list[int]], reuse: bool = True, gray: bool = False) -> np.ndarray:
    """Row numbers in each list's order, rows that tie in their given order.

    With `reuse`, a list whose order is the one before with its last column moved to the front is
    a stable sort of that list by that one column."""
    n = len(codes)
    out = np.empty((len(orders), n), "int64")
    for i, order in enumerate(orders):
        if reuse and not gray and i and order == [orders[i - 1][-1], *orders[i - 1][:-1]] and codes.shape[1] > 1:
            before = out[i - 1]
            # rows that tie everywhere keep the order of the list before, which is the given one
            out[i] = before[np.argsort(codes[before, order[0]], kind="stable")]
        else:
            digits = _digits(codes[:, order], gray)
            out[i] = np.lexsort(digits.T[::-1])
    return out


def walk(
    codes: np.ndarray, orders: list[list[int]] | None = None, start: int = 0, reuse: bool = True, gray: bool = False
) -> np.ndarray:
    """A path over all rows: each next row is the nearest of the last row's list neighbours.

    Neighbours are those before and after it in each list once visited rows are unlinked. Ties go
    to the lower list, the earlier neighbour first. Every unvisited row stays linked, so a step
    always has a neighbour until none is left."""
    n, c = codes.shape
    if n < 2:
        return np.arange(n)
    ranked = sorted_lists(codes, list_orders(c) if orders is None else orders, reuse, gray)
    rows = [tuple(r) for r in codes.tolist()]
    prev, nxt = [], []
    for order in ranked:
        p, q = np.full(n + 1, n), np.full(n + 1, n)
        p[order[1:]] = order[:-1]
        q[order[:-1]] = order[1:]
        prev.append(p.tolist())
        nxt.append(q.tolist())
    links = list(zip(prev, nxt, strict=True))
    path, at = [start], start
    append = path.append
    if c >= WIDE:
        narrow = np.ascontiguousarray(codes, dtype="int32") if codes.max(initial=0) < 1 << 31 else codes
        for _ in range(n - 1):
            near_rows = []
            for p, q in links:
                a, b = p[at], q[at]
                if a != n:
                    near_rows.append(a)
                if b != n:
                    near_rows.append(b)
                q[a], p[b] = b, a
            at = near_rows[(narrow.take(near_rows, axis=0) != narrow[at]).sum(axis=1).argmin()]
            append(at)
        return np.array(path, "int64")
    for _ in range(n - 1):
        here = rows[at]
        best, near = c + 1, n
        for p, q in links:
            a, b = p[at], q[at]
            if a != n:
                d = 0
                for x, y in zip(here, rows[a]):  # noqa: B905
                    d += x != y
                if d < best:
                    best, near = d, a
            if b != n:
                d = 0
                for x, y in zip(here, rows[b]):  # noqa: B905
                    d += x != y
                if d < best:
                    best, near = d, b
            q[a], p[b] = b, a
        at = near
        append(at)
    return np.array(path, "int64")


def walk_together(
    blocks: list[np.ndarray], orders: list[list[int]] | None = None, starts: list[int] | None = None, reuse: bool = True, gray: bool = False
) -> list[np.ndarray]:
    """The `walk` of each of several blocks with the same columns, a step of all of them at a time.

    The blocks are laid out one after another, each with a last row that stands for no neighbour
    and is farther from every row than any other."""
    c = blocks[0].shape[1]
    orders = list_orders(c) if orders is None else orders
    starts = [0] * len(blocks) if starts is None else starts
    turn = sorted((b for b in range(len(blocks)) if len(blocks[b])), key=lambda b: -len(blocks[b]))
    out = [np.empty(0, "int64") for _ in blocks]
    if not turn:
        return out
    lengths = [len(blocks[b]) for b in turn]
    bases = np.concatenate([[0], np.cumsum([n + 1 for n in lengths])])
    # rows are filled up to whole words, so that differing columns are counted eight at a time
    words = c // 8 + 1
    narrow = all(blocks[b].max(initial=0) < 1 << 31 and blocks[b].min(initial=0) > -(1 << 31) for b in turn)
    kind = np.dtype("int32" if narrow else "int64")
    codes = np.zeros((int(bases[-1]), 8 * words), kind)
    links = np.empty((int(bases[-1]), 2 * len(orders)), "int32" if bases[-1] < 1 << 31 else "int64")
    for k, b in enumerate(turn):
        lo, end = int(bases[k]), int(bases[k + 1]) - 1
        codes[lo:end, :c] = blocks[b]
        codes[end] = np.iinfo(kind).min
        links[end] = end
        for i, order in enumerate(sorted_lists(blocks[b], orders, reuse, gray)):
            before, after = links[lo:end, 2 * i], links[lo:end, 2 * i + 1]
            before[order[0]], after[order[-1]] = end, end
            before[order[1:]] = order[:-1] + lo
            after[order[:-1]] = order[1:] + lo
    flat, width = links.reshape(-1), links.shape[1]
    other = np.arange(width) ^ 1
    at = np.array([bases[k] + starts[b] for k, b in enumerate(turn)], "int64")
    paths = np.empty((lengths[0], len(turn)), "int64")
    paths[0] = at
    step, live = 1, len(turn)
    while live:
        upto = lengths[live - 1]
        at, each = at[:live], np.arange(live)
        for step in range(step, upto):
            near = links.take(at, axis=0)
            differs = codes.take(near, axis=0) != codes.take(at, axis=0)[:, None, :]
            counts = np.bitwise_count(differs.view("uint64"))
            far = counts[..., 0].astype("int32") if words > 31 else counts[..., 0]
            for x in range(1, words):
                far = far + counts[..., x]
            # the neighbours of a list become each other's
            flat[near.astype("int64") * width + other] = near[:, other]
            at = near[each, far.argmin(axis=1)]
            paths[step, :live] = at
        step = upto
        while live and lengths[live - 1] <= step:
            live -= 1
    for k, b in enumerate(turn):
        out[b] = paths[: lengths[k], k] - bases[k]
    return out
