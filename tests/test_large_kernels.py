"""Kernels on blocks whose matrix of distances would not fit a task, against the plain way on small ones."""

from itertools import combinations

import numpy as np
import pytest

from diversify.functions import kernels


@pytest.fixture
def no_large_matrix(monkeypatch):
    real = kernels.Block.matrix

    def matrix(self):
        assert len(self) <= 1000, "a matrix of all points"
        return real(self)

    monkeypatch.setattr(kernels.Block, "matrix", matrix)


def blocks(n, count, seed=0):
    rng = np.random.default_rng(seed)
    for _ in range(count):
        x = rng.integers(0, rng.choice([2, 6, 900]), (n, int(rng.integers(1, 4))))
        yield kernels.Block(rng.permutation(10 * n)[:n], x, str(rng.choice(["euclid", "manhattan", "chebyshev"])))


def large(n=6000):
    rng = np.random.default_rng(1)
    return kernels.Block(np.arange(n), np.column_stack([rng.integers(-1000, 10000, n), rng.integers(0, 25, n) * 400]))


def test_local_search_holds_rows_of_distances_only(no_large_matrix):
    b = large()
    found = kernels.local_search(b, 6)
    d = b.take(found).matrix()
    assert len(found) == 6 and kernels.clique(d) >= kernels.clique(b.take(kernels.heavy_matching(b, 6)).matrix())


def test_local_search_ends_where_no_swap_gains():
    for b in blocks(25, 20):
        found, d = kernels.local_search(b, 4), b.matrix()
        best = kernels.clique(d[np.ix_(found, found)])
        for a in found:
            for z in set(range(25)) - set(found):
                other = [z if i == a else i for i in found]
                assert kernels.clique(d[np.ix_(other, other)]) <= best + 1e-6


def test_matching_by_reach_takes_the_pairs_of_the_whole_list(monkeypatch):
    seen = []
    monkeypatch.setattr(kernels.Block, "keys", lambda self, i, real=kernels.Block.keys: seen.append(i) or real(self, i))
    for b in blocks(30, 40):
        free, want = set(range(30)), []
        for _ in range(3):
            pairs = sorted((-b.keys(i)[j], i, j) for i, j in combinations(sorted(free), 2))
            want += pairs[0][1:]
            free -= set(pairs[0][1:])
        assert kernels.heavy_matching(b, 6) == want
    seen.clear()
    assert len(kernels.heavy_matching(large(), 6)) == 6 and len(seen) < 100  # not every point's distances


@pytest.mark.parametrize("objective", ["edge", "clique", "star", "bipartition", "tree", "cycle"])
def test_best_of_boxes_is_the_first_best_triple(objective):
    for b in blocks(18, 30):
        d = b.matrix()
        want = max(combinations(range(18), 3), key=lambda t: (round(kernels.value(d[np.ix_(t, t)], objective), 9), tuple(-i for i in t)))
        assert kernels.brute_force(b, 3, objective)[0] == list(want)


@pytest.mark.parametrize("objective", ["edge", "clique", "star", "bipartition", "tree", "cycle"])
def test_best_of_boxes_needs_no_matrix(no_large_matrix, objective):
    b = large()
    at, best = kernels.brute_force(b, 3, objective)
    assert len(set(at)) == 3 and abs(kernels.value(b.take(at).matrix(), objective) - best) < 1e-6
    rng = np.random.default_rng(2)  # no random triple is better
    assert all(kernels.value(b.take(rng.choice(6000, 3, False)).matrix(), objective) <= best + 1e-6 for _ in range(200))
