"""Tour-construction heuristics over the rows of a block: paths as arrays of row numbers."""

from __future__ import annotations

import heapq

import numpy as np

from rowloom.operators.kernels.distance import matrix, to_one
from rowloom.operators.kernels.matching import least_matching


def nearest_neighbor(
    codes: np.ndarray, start: int = 0, ends: str = "one", history: int = 0, kind: str = "hamming",
    sizes: np.ndarray | None = None,
) -> np.ndarray:
    """Appends the unused row nearest to the last one (with `ends='both'`, to either end).

    Ties go to the lowest row number; with `history`, first to rows nearest to the row before the
    last, then to the one before that, up to `history` rows back."""
    n = len(codes)
    if n == 0:
        return np.arange(0)
    left = np.ones(n, bool)
    left[start] = False
    head, tail = [start], [start]
    far = np.iinfo("int64").max
    d_tail = to_one(codes, codes[start], kind, sizes)
    d_head = d_tail
    for _ in range(n - 1):
        a = np.where(left, d_tail, far)
        pick = int(a.argmin())
        if history:
            near = np.flatnonzero(a == a[pick])
            for back in tail[-2 : -2 - history : -1]:
                if len(near) < 2:
                    break
                d = to_one(codes[near], codes[back], kind, sizes)
                near = near[d == d.min()]
            pick = int(near[0])
        if ends == "both":
            b = np.where(left, d_head, far)
            other = int(b.argmin())
            if b[other] < a[pick]:
                head.append(other)
                left[other] = False
                d_head = to_one(codes, codes[other], kind, sizes)
                continue
        tail.append(pick)
        left[pick] = False
        d_tail = to_one(codes, codes[pick], kind, sizes)
    return np.array(head[:0:-1] + tail, "int64")


def _join(n: int, weight: list[np.ndarray], without: int = -1) -> np.ndarray:
    """A path from links in rising weight, ties by row numbers, wherever they keep all degrees under 3 and
    close no cycle; fragments left over follow each other. `weight[i]` has row i's links to the rows
    after it; row `without` takes none."""
    root = list(range(n))
    degree = np.zeros(n, "int8")
    near: list[list[int]] = [[] for _ in range(n)]

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    starts = np.concatenate([[0], np.cumsum([len(w) for w in weight])])
    order = np.argsort(np.concatenate(weight), kind="stable")
    if without >= 0:
        degree[without] = 2
    links = n - 1 if without < 0 else n - 2
    for at in range(0, len(order), 1 << 18):
        k = order[at : at + (1 << 18)]
        i = np.searchsorted(starts, k, "right") - 1
        j = k - starts[i] + i + 1
        open_ = (degree[i] < 2) & (degree[j] < 2)
        for a, b in zip(i[open_].tolist(), j[open_].tolist(), strict=True):
            if degree[a] < 2 and degree[b] < 2:
                ra, rb = find(a), find(b)
                if ra != rb:
                    root[ra] = rb
                    near[a].append(b)
                    near[b].append(a)
                    degree[a] += 1
                    degree[b] += 1
                    links -= 1
        if not links:
            break
    seen, path = [False] * n, []
    for s in range(n):
        if seen[s] or len(near[s]) == 2:
            continue
        at = s
        while at >= 0:
            seen[at] = True
            path.append(at)
            at = next((x for x in near[at] if not seen[x]), -1)
    return np.array(path, "int64")


def _after(codes: np.ndarray, kind: str, sizes: np.ndarray | None) -> list[np.ndarray]:
    """Each row's distances to the rows after it."""
    return [to_one(codes[i + 1 :], codes[i], kind, sizes).astype("int32") for i in range(len(codes))]


def _narrow(weight: list[np.ndarray]) -> list[np.ndarray]:
    """In 16 bits where they fit, which a stable sort takes digit by digit."""
    top = max((int(np.abs(w).max()) for w in weight if len(w)), default=0)
    return [w.astype("int16") for w in weight] if top < 1 << 15 else weight


def savings(
    codes: np.ndarray, depot: str | int = "first", seed: int = 0, kind: str = "hamming", sizes: np.ndarray | None = None
) -> np.ndarray:
    """Merges path ends by largest saving over going back to the depot row ('artificial': equally far from all)."""
    n = len(codes)
    if n < 3:
        return np.arange(n)
    d = _after(codes, kind, sizes)
    if depot == "artificial":
        return _join(n, _narrow(d))
    base = int(np.random.default_rng(seed).integers(n)) if depot == "random" else 0 if depot == "first" else int(depot)
    home = to_one(codes, codes[base], kind, sizes).astype("int32")
    path = _join(n, _narrow([d[i] - home[i] - home[i + 1 :] for i in range(n)]), base)
    # the depot closes the tour of the others; the path starts at it
    return np.concatenate([[base], path[path != base]])


def multiple_fragment(codes: np.ndarray, kind: str = "hamming", sizes: np.ndarray | None = None) -> np.ndarray:
    """Links the closest path ends first, ties by row numbers."""
    n = len(codes)
    if n < 2:
        return np.arange(n)
    return _join(n, _narrow(_after(codes, kind, sizes)))


def insertion(
    codes: np.ndarray, pick: str = "nearest", start: int = 0, seed: int = 0, kind: str = "hamming",
    sizes: np.ndarray | None = None,
) -> np.ndarray:
    """Inserts each picked row where the tour grows least. `pick`: nearest to or farthest from the tour, random, or cheapest.

    The tour is closed through an artificial row that is equally far from all rows, so the ends
    are open places at the row's full cost to one neighbour."""
    n = len(codes)
    if n < 3:
        return np.arange(n)
    d = matrix(codes, kind, sizes)
    far = int(d.max()) + 1
    full = np.full((n + 1, n + 1), far, "int32")
    full[:n, :n] = d
    # rows of the tour in the order of their insertion, and the row that follows each
    joined, after = np.zeros(n + 1, "int64"), np.zeros(n + 1, "int64")
    joined[:2] = n, start
    after[n], after[start] = start, n
    size = 2
    out = np.ones(n, bool)
    out[start] = False
    closest = d[start].copy()
    order = np.random.default_rng(seed).permutation(n)
    order = order[order != start]
    heap: list[tuple[int, int, int]] = []

    def cheapest_place(row: int) -> tuple[int, int]:
        a = joined[:size]
        b = after[a]
        cost = full[a, row] + full[row, b] - full[a, b]
        k = int(cost.argmin())
        return int(cost[k]), int(a[k])

    if pick == "cheapest":
        for r in np.flatnonzero(out):
            cost, place = cheapest_place(int(r))
            heapq.heappush(heap, (cost, int(r), place))
    for step in range(n - 1):
        if pick == "nearest":
            row = int(np.where(out, closest, far + 1).argmin())
            _, a = cheapest_place(row)
        elif pick == "farthest":
            row = int(np.where(out, closest, -1).argmax())
            _, a = cheapest_place(row)
        elif pick == "random":
            row = int(order[step])
            _, a = cheapest_place(row)
        elif pick == "cheapest":
            while True:
                cost, row, a = heapq.heappop(heap)
                if not out[row]:
                    continue
                now = cheapest_place(row)
                if now[0] <= cost:
                    a = now[1]
                    break
                heapq.heappush(heap, (now[0], row, now[1]))
        else:
            raise ValueError("pick is nearest, farthest, random or cheapest")
        b = int(after[a])
        after[a], after[row] = row, b
        joined[size] = row
        size += 1
        out[row] = False
        closest = np.minimum(closest, d[row])
        if pick == "cheapest":
            # only places beside the new row can have become cheaper
            rest = np.flatnonzero(out)
            for p, q in ((a, row), (row, b)):
                for cost, r in zip((full[p, rest] + full[rest, q] - full[p, q]).tolist(), rest.tolist(), strict=True):
                    heapq.heappush(heap, (cost, r, p))
    path, at = [], int(after[n])
    while at != n:
        path.append(at)
        at = int(after[at])
    return np.array(path, "int64")


#: Rows of the largest block that the methods by exact matchings take.
MATCHED_ROWS = 256


def iterated_matching(codes: np.ndarray) -> np.ndarray:
    """Joins groups of rows in pairs by a least-weight matching of their closest ends, until one group is left.

    Where their number is odd, the group whose leaving costs least waits for the next round."""
    if len(codes) > MATCHED_ROWS:
        raise ValueError(f"iterated_matching takes blocks of {MATCHED_ROWS} rows at most")
    groups = [[i] for i in range(len(codes))]
    while len(groups) > 1:
        heads, tails = codes[[g[0] for g in groups]], codes[[g[-1] for g in groups]]
        # distances of the ends that would meet, by whether the first and the second group is turned
        options = np.stack([matrix2(tails, heads), matrix2(tails, tails), matrix2(heads, heads), matrix2(heads, tails)])
        m = len(groups)
        cost = np.zeros((m + m % 2, m + m % 2), "int64")
        cost[:m, :m] = np.minimum(options.min(axis=0), options.min(axis=0).T)
        merged = []
        for a, b in least_matching(cost):
            if b == m:
                merged.append(groups[a])
                continue
            turn = int(options[:, a, b].argmin())
            merged.append((groups[a][::-1] if turn > 1 else groups[a]) + (groups[b][::-1] if turn % 2 else groups[b]))
        groups = merged
    return np.array(groups[0] if groups else [], "int64")


def matrix2(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Hamming distances of every row of `a` to every row of `b`."""
    return np.stack([(b != row).sum(axis=1) for row in a])


def christofides(codes: np.ndarray) -> np.ndarray:
    """Spanning tree, least-weight matching of its odd rows, and a shortcut Euler tour, cut at its longest step.

    The closed tour is at most 1.5 times the shortest one."""
    n = len(codes)
    if n > MATCHED_ROWS:
        raise ValueError(f"christofides takes blocks of {MATCHED_ROWS} rows at most")
    if n < 3:
        return np.arange(n)
    d = matrix(codes)
    inside, best, link = [0], d[0].copy(), np.zeros(n, "int64")
    edges: list[list[int]] = [[] for _ in range(n)]
    waiting = set(range(1, n))
    while waiting:
        x = min(waiting, key=lambda r: (best[r], r))
        waiting.remove(x)
        edges[x].append(int(link[x]))
        edges[int(link[x])].append(x)
        closer = d[x] < best
        best = np.where(closer, d[x], best)
        link = np.where(closer, x, link)
        inside.append(x)
    odd = [r for r in range(n) if len(edges[r]) % 2]
    for x, y in least_matching(d[np.ix_(odd, odd)]):
        a, b = odd[x], odd[y]
        edges[a].append(b)
        edges[b].append(a)
    stack, tour = [0], []
    while stack:
        at = stack[-1]
        if edges[at]:
            to = edges[at].pop()
            edges[to].remove(at)
            stack.append(to)
        else:
            tour.append(stack.pop())
    path = list(dict.fromkeys(tour))
    steps = [int(d[path[i], path[(i + 1) % n]]) for i in range(n)]
    cut = int(np.argmax(steps)) + 1
    return np.array(path[cut:] + path[:cut], "int64")
