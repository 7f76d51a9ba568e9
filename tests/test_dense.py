import numpy as np

from diversify.functions import metrics


def test_angles_by_blocks_are_those_of_pairs(spark):
    rng = np.random.default_rng(0)
    rows = [(i, [0.0] * 4 if i == 7 else rng.normal(size=4).tolist(), int(i % 3)) for i in range(60)]
    e = spark.createDataFrame(rows, "pid long, v array<double>, grp long")
    got = {(r.i, r.j): r.d for r in metrics.dense_angles(e, "grp", block=6).collect()}
    v = {p: np.array(x) for p, x, _ in rows}
    want = {(p, q): v[p] @ v[q] / (np.linalg.norm(v[p]) * np.linalg.norm(v[q])) if 7 not in (p, q) else None for p, _, g in rows for q, _, h in rows if p < q and g == h}
    assert got.keys() == want.keys()
    for k, c in want.items():
        assert got[k] is None if c is None else abs(got[k] - np.arccos(c)) < 1e-9
