"""Kernels on tiny inputs: worked values, ties, duplicates, short inputs, invariants and the solvers' factors."""

import itertools

import numpy as np
import pytest

from diversify.functions import kernels as f
from diversify.plans import params


def cloud(n, dims=2, seed=0, span=50):
    rng = np.random.default_rng(seed)
    return f.Block(np.arange(n), rng.integers(0, span, (n, dims)).astype(float))


LINE = f.Block([4, 2, 9, 7], [[0.0], [10.0], [10.0], [3.0]])


def test_farthest_first_takes_smallest_ids_on_ties():
    picks, owner, radii = f.farthest_first(LINE, 4)
    assert LINE.ids[picks].tolist() == [2, 4, 7, 9]
    assert radii.tolist() == [10.0, 3.0, 0.0, 0.0]
    assert LINE.ids[f.farthest_first(LINE, 99)[0]].tolist() == [2, 4, 7, 9]


def test_equal_points_are_still_returned():
    b = f.Block(range(5), [[1.0, 1.0]] * 5)
    assert b.ids[f.farthest_first(b, 3)[0]].tolist() == [0, 1, 2]
    assert len(f.heavy_matching(b, 3)) == 3 and f.edge(b.take([0, 1]).matrix()) == 0


def test_owners_go_to_the_earlier_anchor():
    b = f.Block(range(3), [[0.0], [10.0], [5.0]])
    picks, owner, _ = f.farthest_first(b, 2)
    assert owner.tolist() == [0, 1, 0]
    assert f.delegates(picks, owner, 2) == [(0, 0), (0, 2), (1, 1)]
    assert f.counts(picks, owner, 1).tolist() == [1, 1]


@pytest.mark.parametrize("seed", range(6))
def test_radius_is_at_most_separation_and_twice_the_best(seed):
    b = cloud(14, seed=seed)
    d = b.matrix()
    for k in (2, 3, 4):
        picks, _, radii = f.farthest_first(b, k)
        best = min(d[list(c)].min(0).max() for c in itertools.combinations(range(14), k))
        assert radii[-1] <= 2 * best + 1e-9
        assert radii[-1] <= f.edge(d[np.ix_(picks, picks)]) + 1e-9
        assert list(radii) == sorted(radii, reverse=True)


@pytest.mark.parametrize("objective", params.REGISTRY)
@pytest.mark.parametrize("k", (2, 3, 4, 5))
def test_solvers_keep_their_factors(objective, k):
    from diversify.operators.solvers import picks

    for seed in range(5):
        b = cloud(12, seed=seed)
        at = picks(b, k, objective)
        assert len(set(at)) == k
        best = f.brute_force(b, k, objective)[1]
        assert best <= params.REGISTRY[objective][2] * f.value(b.take(at).matrix(), objective) + 1e-6


def test_three_point_search_is_the_general_one():
    for objective in params.REGISTRY:
        b = cloud(9, seed=3)
        d = b.matrix()
        assert f.brute_force(b, 3, objective)[1] == max(round(f.value(d[np.ix_(c, c)], objective), 9) for c in itertools.combinations(range(9), 3))


def test_measures_of_two_and_four_points():
    d = cloud(2, seed=1).matrix()
    one = d[0, 1]
    assert [f.value(d, o) for o in ("edge", "clique", "star", "tree", "cycle", "bipartition")] == [one, one, one, one, 2 * one, one]
    d = cloud(4, seed=1).matrix()
    assert abs(f.value(d, "cycle") - f.value(d, "bipartition")) < 1e-9


def test_exact_measures_and_their_bounds():
    d = cloud(8, seed=5).matrix()
    tours = min(sum(d[a, b] for a, b in zip((0, *p), (*p, 0))) for p in itertools.permutations(range(1, 8)))
    assert abs(f.cycle(d)[0] - tours) < 1e-9
    upper, exact = f.cycle(d, exact_upto=4)
    assert not exact and tours - 1e-9 <= upper <= 2 * tours
    upper, exact = f.bipartition(d, exact_upto=4)
    assert not exact and upper >= f.bipartition(d)[0] - 1e-9


@pytest.mark.parametrize("kind", ("points", "delegates", "counts"))
@pytest.mark.parametrize("size", (1, 7, 1000))
def test_sketch_does_not_depend_on_batches(kind, size):
    b = cloud(600, 3, 7)
    whole = f.Sketch(4, 9, kind).update(b.ids, b.x)
    cut = f.Sketch(4, 9, kind)
    for i in range(0, 600, size):
        cut.update(b.ids[i : i + size], b.x[i : i + size])
    ids = lambda s: (s.ids, [[i for i, _ in h] for h in s.held], s.count, [i for i, _ in s.removed], s.square, s.log)
    assert ids(whole) == ids(cut)


@pytest.mark.parametrize("seed", range(4))
def test_sketch_covers_what_it_saw(seed):
    b = cloud(500, 2, seed, 400)
    for m in (5, 12, 40):
        s = f.Sketch(3, m).update(b.ids, b.x)
        kept = np.array(s.x)
        away = np.sqrt(((b.x[:, None] - kept[None]) ** 2).sum(2)).min(1).max()
        assert away <= 4 * s.threshold + 1e-9 and len(kept) <= m
        apart = [np.linalg.norm(p - q) for p, q in itertools.combinations(kept, 2)]
        assert min(apart, default=9e9) > 2 * s.threshold - 1e-9
        assert len(s.result()) >= 3


def test_sketch_with_copies_first_and_short_streams():
    x = np.array([[0.0]] * 6 + [[1.0], [5.0], [5.0], [9.0], [30.0]])
    s = f.Sketch(2, 3, "counts").update(range(len(x)), x)
    assert s.square > 0 and 1 <= len(s.ids) <= 3
    assert len(f.Sketch(2, 8).update([1, 2], [[0.0], [1.0]]).result()) == 2
    assert f.Sketch(2, 8).update([], np.zeros((0, 1))).result() == []
    assert f.Sketch(1, 2).update(range(50), np.zeros((50, 2))).ids == [0]


def test_a_merge_without_victims_doubles_again():
    s = f.Sketch(1, 2).update(range(3), [[0.0], [10.0], [1000.0]])
    assert len(s.ids) == 2 and any(gone == 0 for *_, gone, _ in s.log) is False
    s = f.Sketch(1, 2).update(range(4), [[0.0], [1.0], [100.0], [10000.0]])
    assert len(s.ids) <= 2


def test_delegate_lists_never_exceed_k():
    b = cloud(400, 2, 3, 60)
    for k in (2, 5):
        s = f.Sketch(k, 6, "delegates").update(b.ids, b.x)
        assert max(map(len, s.held)) <= k and sum(map(len, s.held)) >= min(400, k)
        assert all(h[0][0] == i for h, i in zip(s.held, s.ids))


def test_merged_sketches_cover_both_streams():
    b = cloud(400, 2, 9, 300)
    one, two = f.Sketch(3, 10).update(b.ids[:150], b.x[:150]), f.Sketch(3, 10).update(b.ids[150:], b.x[150:])
    bound = 4 * (one.threshold + two.threshold)
    s = one.merge(two)
    away = np.sqrt(((b.x[:, None] - np.array(s.x)[None]) ** 2).sum(2)).min(1).max()
    assert away <= 4 * s.threshold + bound and len(s.x) <= 10


def test_choices_with_counts():
    b = f.Block(range(3), [[0.0], [10.0], [4.0]])
    assert f.traversal_with_counts(b, [3, 1, 1], 5) == {0: 3, 1: 1, 2: 1}
    assert f.matching_with_counts(b, [1, 1, 4], 5) == {0: 1, 1: 1, 2: 3}
    assert f.matching_with_counts(b, [2, 2, 2], 4) == {0: 2, 1: 2}
    assert sum(f.matching_with_counts(b, [2, 2, 2], 5).values()) == 5
    one = f.Block([7], [[1.0]])
    assert f.matching_with_counts(one, [5], 4) == {0: 4} and f.traversal_with_counts(one, [5], 4) == {0: 4}


def test_other_metrics():
    a = f.Block(range(3), [{1, 2}, {2, 3}, set()], "jaccard")
    assert a.keys(0).tolist() == [0.0, pytest.approx(2 / 3), 1.0]
    v = f.Block(range(3), [[1.0, 0.0], [0.0, 2.0], [3.0, 0.0]], "angular")
    assert v.matrix()[0].round(6).tolist() == [0.0, round(np.pi / 2, 6), 0.0]
    s = f.Block(range(2), [([0, 3], [1, 2]), ([3], [5])], "sparse")
    assert abs(s.matrix()[0, 1] - np.arccos(2 / np.sqrt(5))) < 1e-6
    assert f.Block([0, 1], [[0.0, 0.0], [3.0, -4.0]], "manhattan").matrix()[0, 1] == 7
    assert f.Block([0, 1], [[0.0, 0.0], [3.0, -4.0]], "chebyshev").matrix()[0, 1] == 4


def test_planner_formulas():
    p = params.plan("mr2", "edge", 10**6, 4, eps=1.0, dim=1.0)
    assert p.eps_inner == pytest.approx(1 / 3) and p.k_prime == pytest.approx(96) and p.parts == int((10**6 / 96) ** 0.5)
    assert params.plan("mr2", "clique", 10**6, 4, dim=1.0).k_prime == pytest.approx(16 / (1 / 3) * 4)
    assert params.plan("stream1", "edge", 10**6, 1, dim=3.0).k_prime == pytest.approx(262144)
    assert params.plan("mr3", "edge", 10**6, 4) is None and params.plan("mr3", "tree", 10**6, 4).cap == 1


def test_local_search_ends_where_no_swap_gains(monkeypatch):
    b = f.Block(range(80), np.random.default_rng(3).standard_normal((80, 2)))
    monkeypatch.setattr(f, "heavy_matching", lambda b, k: np.argsort((b.x**2).sum(1))[:k].tolist())  # the innermost points
    d = b.matrix()
    at = f.local_search(b, 30)
    out = [z for z in range(80) if z not in at]
    assert len(at) == 30 and all(d[z, at].sum() - d[a, at].sum() - d[a, z] <= 1e-9 for a in at for z in out)


def test_counts_are_matched_as_their_copies_are():
    """The farthest pair of copies that are left, again and again, by brute force; and memory of one row of keys a point."""
    rng = np.random.default_rng(5)
    for _ in range(60):
        n = int(rng.integers(1, 7))
        b = f.Block(range(n), rng.choice(30, (n, 1), replace=False))
        mult, k = rng.integers(1, 5, n).tolist(), int(rng.integers(1, 12))
        left, want, need = list(mult), {}, min(k, sum(mult))
        while need:
            pairs = [(-abs(float(b.x[i, 0] - b.x[j, 0])), i, j) for i in range(n) for j in range(i + 1, n) if left[i] and left[j]]
            if need == 1 or not pairs:
                i = next(i for i in range(n) if left[i])
                used = [i]
            else:
                used = list(min(pairs)[1:])
            for i in used:
                left[i] -= 1
                want[i] = want.get(i, 0) + 1
            need -= len(used)
        assert f.matching_with_counts(b, mult, k) == want


def test_delegates_of_a_block_are_those_of_single_rows():
    rng = np.random.default_rng(6)
    x = rng.integers(0, 12, (400, 2)).astype(float)
    whole, single = f.Sketch(3, 6, "delegates").update(range(400), x), f.Sketch(3, 6, "delegates")
    for i in range(400):
        single.update([i], x[i : i + 1])
    ids = lambda s: [[i for i, _ in h] for h in s.held]
    assert (whole.ids, ids(whole), whole.count, whole.square) == (single.ids, ids(single), single.count, single.square)
