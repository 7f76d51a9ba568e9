import os

import numpy as np
import pytest

from diversify import queries
from diversify.functions import metrics
from diversify.operators import coresets, rounds
from diversify.queries import experiments


def counts(n):
    """Sparse vectors with a term in all of them, one in a third and one of their own; every seventh counts too much for single precision."""
    return {i: {0: 1 + i % 5 + (10_007 if i % 7 == 0 else 0), 1 + i % 3: 2, 10 + i: 3} for i in range(n)}


def table(spark, vectors):
    return spark.createDataFrame([(i, t, c) for i, v in vectors.items() for t, c in v.items()], "pid long, term int, cnt long")


def shuffled(spark):
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty(30_000)
    return sc.statusStore().executorSummary("driver").totalShuffleWrite()


def test_vectors_are_shuffled_once_whatever_the_number_of_blocks(spark):
    w = table(spark, counts(400)).cache()
    w.count()
    sent = []
    for block in (1000, 4):
        before = shuffled(spark)
        assert metrics.sparse_products(w, 400, block).count() == 400 * 399 // 2
        sent.append(shuffled(spark) - before)
    assert 0 < sent[1] < 3 * sent[0]


@pytest.mark.parametrize(("rows", "block"), [(7, 3), (4000, 1000)])
def test_angles_by_strips_are_those_of_pairs(spark, monkeypatch, rows, block):
    monkeypatch.setattr(metrics, "STRIP_ROWS", rows)
    vectors = counts(200) | {500: {9_000: 1}, 501: {9_000: 4}, 502: {9_001: 1}}
    got = {(r.i, r.j): (r.dot, r.d) for r in metrics.sparse_angles(table(spark, vectors), len(vectors), block).collect()}
    norm = {i: sum(c * c for c in v.values()) for i, v in vectors.items()}
    dots = {(i, j): sum(c * vectors[j].get(t, 0) for t, c in vectors[i].items()) for i in vectors for j in vectors if i < j}
    assert {p: x for p, (x, _) in got.items()} == {p: x for p, x in dots.items() if x}
    assert all(d == round(float(np.arccos(min(1, x / np.sqrt(float(norm[i] * norm[j]))))), 6) for (i, j), (x, d) in got.items())


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no test tables here")
def test_text_runs_take_both_rounds_each(spark, monkeypatch):
    runs, parts = [], []
    whole, first = rounds.two_round, coresets.traverse
    monkeypatch.setattr(rounds, "two_round", lambda s, k, kp, n, *a, **b: (runs.append((kp, n)), whole(s, k, kp, n, *a, **b))[1])
    monkeypatch.setattr(coresets, "traverse", lambda rows, m, n, *a, **b: (parts.append((m, *n)), first(rows, m, n, *a, **b))[1])
    found = {(r.k_prime, r.parts): r.value for r in queries.QUERIES["exp_mr_text"](spark, "/root/testdata/sf0.001").collect()}
    assert sorted(runs) == sorted(parts) == sorted(found) == [(8, 2), (8, 4), (16, 2), (16, 4)]
    s = experiments.texts(spark, "/root/testdata/sf0.001")
    assert found[8, 4] == round(whole(s, 8, 8, 4, "edge").first().value, 6)
