import numpy as np

from diversify.functions import metrics

XY = ("x", "y")


def test_audit_counts_each_triple_of_rows_once(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(i, int(a), int(b)) for i, (a, b) in enumerate(rng.integers(0, 3, (24, 2)))]
    monkeypatch.setitem(metrics.SCALAR, "lifted", lambda a, b: metrics.squared(a, b).cast("double") + 1.5 * (metrics.squared(a, b) < 2).cast("double"))
    d = lambda p, q: (s := (p[1] - q[1]) ** 2 + (p[2] - q[2]) ** 2) + 1.5 * (s < 2)
    want = sum(d(p, q) > d(p, r) + d(r, q) + 1e-9 for p in rows for q in rows if p[0] < q[0] for r in rows if r[0] not in (p[0], q[0]))
    found = metrics.audit(spark.createDataFrame(rows, "pid long, x long, y long"), list(XY), "lifted", block=4).first()
    assert (found.triples, found.violations) == (24 * 23 * 22 // 2, want) and want > 0
