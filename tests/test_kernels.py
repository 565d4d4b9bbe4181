from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rowloom.functions.keys import hilbert_index
from rowloom.operators.kernels import codecs, improve, lists, tours
from rowloom.operators.kernels import distance as D
from rowloom.plans.workloads import TOY_ROWS

TOY = np.array(TOY_ROWS)
TABLES = st.integers(1, 4).flatmap(lambda c: st.lists(st.lists(st.integers(0, 4), min_size=c, max_size=c), min_size=1, max_size=24)).map(lambda r: np.array(r, "int64"))
TOURS = {
    "nearest": tours.nearest_neighbor,
    "both ends": lambda x: tours.nearest_neighbor(x, ends="both"),
    "history": lambda x: tours.nearest_neighbor(x, history=3),
    "delta": lambda x: tours.nearest_neighbor(x, kind="delta_bits"),
    "lee": lambda x: tours.nearest_neighbor(x, kind="lee", sizes=np.full(x.shape[1], 5)),
    "savings": tours.savings,
    "savings artificial": lambda x: tours.savings(x, "artificial"),
    "fragment": tours.multiple_fragment,
    **{f"insertion {p}": (lambda x, p=p: tours.insertion(x, p)) for p in ("nearest", "farthest", "random", "cheapest")},
    "matching": tours.iterated_matching,
    "christofides": tours.christofides,
    "lists": lists.walk,
    "all lists": lambda x: lists.walk(x, lists.list_orders(x.shape[1], lists="all")),
}
BETTER = {
    "adjacent": improve.adjacent_swap, "window": improve.window_swap, "reinsertion": improve.reinsertion, "peephole": improve.peephole,
}


@settings(max_examples=60, deadline=None)
@given(TABLES)
def test_tours_are_permutations(table):
    for name, tour in TOURS.items():
        assert sorted(tour(table).tolist()) == list(range(len(table))), name


@settings(max_examples=60, deadline=None)
@given(TABLES)
def test_improvements_never_add_runs(table):
    for name, better in BETTER.items():
        order = better(table)
        assert sorted(order.tolist()) == list(range(len(table))), name
        assert D.runs(table[order]) <= D.runs(table), name


@settings(max_examples=40, deadline=None)
@given(TABLES.filter(lambda t: len(t) <= 9))
def test_the_optimum_bounds_everything(table):
    best = D.runs(table[improve.optimal(table)])
    distinct, c = len(np.unique(table, axis=0)), table.shape[1]
    assert best >= distinct + c - 1
    for name, tour in TOURS.items():
        assert D.runs(table[tour(table)]) >= best, name
    path = D.path_cost(table[tours.christofides(table)])
    # the tour is at most 1.5 times the least tour, which is at most twice the least path
    assert path <= 3 * max(best - c, 0) + 0


@settings(max_examples=60, deadline=None)
@given(TABLES)
def test_all_lists_step_to_a_nearest_row(table):
    codes = table[lists.walk(table, lists.list_orders(table.shape[1], lists="all"))]
    for i in range(len(codes) - 1):
        assert (codes[i + 1 :] != codes[i]).sum(axis=1).min() == (codes[i + 1] != codes[i]).sum()


@settings(max_examples=60, deadline=None)
@given(TABLES)
def test_sort_reuse_gives_the_same_lists(table):
    orders = lists.list_orders(table.shape[1])
    assert (lists.sorted_lists(table, orders, True) == lists.sorted_lists(table, orders, False)).all()


def test_worked_example():
    assert D.runs(TOY[lists.walk(TOY)]) == 14 == D.runs(TOY[improve.optimal(TOY)])
    assert D.runs(TOY) == 19
    assert D.to_one(np.array([[0, 1, 2]]), np.array([0, 3, 4]))[0] == 2


def test_fewer_and_more_lists():
    assert lists.list_orders(3) == [[0, 1, 2], [2, 0, 1], [1, 2, 0]]
    assert len(lists.list_orders(3, 2)) == 2 and len(lists.list_orders(3, lists="all")) == 6
    with pytest.raises(ValueError):
        lists.list_orders(3, lists="some")


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 9), max_size=300), st.sampled_from(codecs.KINDS))
def test_codecs_give_codes_back(values, kind):
    codes = np.array(values, "int64")
    assert (codecs.decode(codecs.encode(codes, kind, 10), kind) == codes).all()


@pytest.mark.parametrize("n", [0, 1, 127, 128, 129, 256, 257])
@pytest.mark.parametrize("kind", codecs.KINDS)
def test_short_last_blocks(n, kind):
    codes = np.sort(np.arange(n) % 7)
    assert (codecs.decode(codecs.encode(codes, kind, 7), kind) == codes).all()


@pytest.mark.parametrize(("c", "width"), [(2, 1), (2, 3), (3, 2), (4, 2)])
def test_hilbert_steps_are_unit_steps(c, width):
    grid = np.stack(np.meshgrid(*[np.arange(1 << width)] * c, indexing="ij"), -1).reshape(-1, c)
    order = np.lexsort(hilbert_index(grid, width).T[::-1])
    assert (np.abs(np.diff(grid[order], axis=0)).sum(axis=1) == 1).all()


def test_one_and_no_rows():
    for rows in (0, 1):
        table = np.zeros((rows, 2), "int64")
        for tour in [*TOURS.values(), *BETTER.values(), improve.optimal]:
            assert len(tour(table)) == rows


def test_least_matching_is_least():
    from functools import lru_cache

    from rowloom.operators.kernels.matching import least_matching

    def least(c):
        m = len(c)

        @lru_cache(None)
        def rest(mask):
            if mask == (1 << m) - 1:
                return 0
            i = next(k for k in range(m) if not mask >> k & 1)
            return min(int(c[i, j]) + rest(mask | 1 << i | 1 << j) for j in range(i + 1, m) if not mask >> j & 1)

        return rest(0)

    rng = np.random.default_rng(5)
    for _ in range(250):
        m, top = 2 * int(rng.integers(0, 7)), int(rng.choice([1, 3, 10, 1000]))
        c = np.triu(rng.integers(0, top + 1, (m, m)), 1)
        c = c + c.T
        pairs = least_matching(c) if m else []
        assert sorted(x for p in pairs for x in p) == list(range(m))
        assert sum(int(c[a, b]) for a, b in pairs) == (least(c) if m else 0)
    with pytest.raises(ValueError):
        least_matching(np.zeros((3, 3), int))


def test_christofides_keeps_its_bound():
    """At most one and a half times the shortest closed tour, found by dynamic programming over subsets."""
    from rowloom.operators.kernels import tours as C

    rng = np.random.default_rng(7)
    for _ in range(12):
        codes = rng.integers(0, 3, (10, 4))
        d = (codes[:, None, :] != codes[None, :, :]).sum(axis=2)
        best = {(1, 0): 0}
        for mask in range(1, 1 << 10):
            for last in range(10):
                if (mask, last) in best:
                    for x in range(10):
                        if not mask >> x & 1:
                            key, cost = (mask | 1 << x, x), best[mask, last] + int(d[last, x])
                            best[key] = min(best.get(key, cost), cost)
        shortest = min(best[(1 << 10) - 1, x] + int(d[x, 0]) for x in range(1, 10))
        path = C.christofides(codes)
        assert sorted(path.tolist()) == list(range(10))
        closed = sum(int(d[path[i], path[(i + 1) % 10]]) for i in range(10))
        assert closed <= 1.5 * shortest
    big = rng.integers(0, 4, (200, 5))
    for walk in (C.christofides, C.iterated_matching):
        assert sorted(walk(big).tolist()) == list(range(200))


def _reinsertion_by_all_places(codes):
    """Each row in turn against every place of the path."""
    order = list(range(len(codes)))
    d = lambda i, j: int((codes[i] != codes[j]).sum())
    for row in range(len(codes)):
        i = order.index(row)
        rest = order[:i] + order[i + 1 :]
        cost = [d(row, rest[0]), *(d(u, row) + d(row, v) - d(u, v) for u, v in zip(rest, rest[1:])), d(rest[-1], row)]
        order = rest.copy()
        order.insert(i if cost[i] == min(cost) else cost.index(min(cost)), row)
    return order


@pytest.mark.parametrize("places", [1 << 62, 1])
def test_reinsertion_takes_the_first_of_the_best_places(monkeypatch, places):
    monkeypatch.setattr(improve, "PLACES", places)
    rng = np.random.default_rng(8)
    for n, c, top in [(3, 1, 2), (30, 2, 4), (40, 4, 3), (60, 3, 6), (50, 5, 12)]:
        codes = rng.integers(0, top, (n, c))
        for given in (codes, codes[np.lexsort(codes.T[::-1])]):
            assert improve.reinsertion(given).tolist() == _reinsertion_by_all_places(given)


def test_reinsertion_takes_a_long_block(monkeypatch):
    """A step that looks at all rows costs more than rows by rows here: 12,000 rows, and copies of them."""
    import time

    rng = np.random.default_rng(9)
    codes = np.stack([rng.integers(0, k, 12_000) for k in (6, 25, 50, 64)], axis=1)
    codes = codes[np.lexsort(codes.T[::-1])]
    began = time.process_time()
    order = improve.reinsertion(codes)
    copies = improve.reinsertion(np.repeat(codes, 40, axis=0))
    assert time.process_time() - began < 4
    assert D.runs(codes[order]) < D.runs(codes) and len(np.unique(copies)) == 480_000
