"""Operators end to end: parts, instantiation, levels, spaces, streaming, and what the accuracy does with its parameters."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from diversify.functions import kernels, metrics
from diversify.operators import baselines, coresets, quality, relational, rounds, solvers
from diversify.operators.space import PointSpace, ranked
from diversify.plans import params, sqlapi
from diversify.sources import tables
from diversify.streaming import sketch as streaming

XY = ("x", "y")


def points(spark, n=400, seed=0, span=1000):
    rng = np.random.default_rng(seed)
    rows = [(i, int(a), int(b), i % 5) for i, (a, b) in enumerate(rng.integers(0, span, (n, 2)))]
    return PointSpace(spark.createDataFrame(rows, "pid long, x long, y long, grp long"), XY)


def block(space):
    rows = space.df.select("pid", "x", "y").collect()
    return kernels.Block([r.pid for r in rows], [[r.x, r.y] for r in rows])


def test_parts_smaller_than_the_kernel_come_whole(spark):
    s = points(spark, 10)
    found = coresets.build(s.with_parts(4), 50).collect()
    assert len(found) == 10 and all(r.radius >= 0 for r in found)
    assert coresets.build(s.with_parts(4), 50, "delegates", 3).count() == 10


@pytest.mark.parametrize("objective", params.REGISTRY)
def test_every_method_returns_k_points_and_their_value(spark, objective):
    s, k = points(spark), 5
    runs = [rounds.two_round(s, k, 8, 4, objective), rounds.multi_round(s, k, 6, 120, objective), rounds.one_pass(s.slim(), k, 8, objective), rounds.split_round(s, k, 8, objective)]
    if params.strict(objective):
        runs += [rounds.two_round_random(s, k, 8, 4, objective, 400), rounds.three_round(s, k, 8, 4, objective), rounds.two_pass(s.slim(), k, 8, objective)]
    b = block(s)
    for df in runs:
        rows = df.collect()
        ids = [r.pid for r in rows]
        assert len(set(ids)) == k and {r.value for r in rows} == {rows[0].value}
        at = np.searchsorted(b.ids, sorted(ids))
        assert rows[0].value == pytest.approx(kernels.value(b.take(at).matrix(), objective))


@pytest.mark.parametrize("objective", ["edge", "clique"])
@pytest.mark.parametrize("most", [rounds.LARGE_GROUPS, 0])
def test_groups_of_any_size(spark, monkeypatch, objective, most):
    monkeypatch.setattr(rounds, "LARGE_GROUPS", most)
    rng = np.random.default_rng(4)
    rows = [(i, int(a), int(b), None if i % 50 == 0 else 0 if i % 3 else i % 7) for i, (a, b) in enumerate(rng.integers(0, 1000, (1500, 2)))]
    s = PointSpace(spark.createDataFrame(rows, "pid long, x long, y long, grp long").repartition(3), XY)
    got = rounds.grouped_rounds(s, "grp", 4, 8, objective, 80).collect()
    whole = {r.grp: r.value for r in solvers.solve(s.slim("grp"), 4, objective, by="grp").collect()}
    of = {r[0]: r[3] for r in rows}
    assert len(got) == 4 * len(whole) and all(of[r.pid] == r.grp for r in got)
    small = {g for g in whole if sum(r[3] == g for r in rows) <= 80}
    assert None in small and 0 not in small
    assert all(r.value == whole[r.grp] if r.grp in small else r.value >= whole[r.grp] / 2 for r in got)
    with pytest.raises(ValueError):
        rounds.grouped_rounds(s, "grp", 4, 8, objective, 15)


def test_two_rounds_keep_the_factor_on_small_input(spark):
    s = points(spark, 24, 3)
    for objective, (_, _, alpha) in params.REGISTRY.items():
        best = kernels.brute_force(block(s), 3, objective)[1]
        value = rounds.two_round(s, 3, 8, 2, objective).first().value
        assert best <= (alpha + 1) * value + 1e-6


def test_three_rounds_lose_at_most_the_bound(spark):
    s, k = points(spark, 300, 4), 6
    found = coresets.build(s.with_parts(3), 8, "counts", k)
    for objective in ("clique", "star", "tree", "bipartition"):
        general = solvers.solve_with_counts(found, k, objective).first().value
        real = rounds.three_round(s, k, 8, 3, objective).first().value
        from diversify.operators.measures import term_count

        assert real >= general - 2 * found.agg(F.max("radius")).first()[0] * term_count(objective, k) - 1e-6


def test_multi_round_is_the_two_level_run(spark):
    s = points(spark, 300, 6)
    first = coresets.build(s.slim().withColumn("part_id", F.pmod("pid", F.lit(3)).cast("long")), 10)
    want = solvers.solve(first, 4, "edge").first().value
    assert rounds.multi_round(s, 4, 10, 100, "edge").first().value == want


def test_region_parts_are_even_and_ordered(spark):
    s = points(spark, 103)
    rows = s.with_parts(4, "region").collect()
    sizes = [sum(r.part_id == p for r in rows) for p in range(4)]
    assert sizes == [26, 26, 26, 25]
    tops = [max((r.v[0], r.v[1]) for r in rows if r.part_id == p) for p in range(4)]
    assert tops == sorted(tops)
    assert sorted(r._at for r in ranked(s.df, ("x",)).collect()) == list(range(103))


def test_guard_drops_what_has_no_place(spark):
    nan = float("nan")
    df = spark.createDataFrame([(1, 1.0, 2.0), (2, None, 1.0), (3, nan, 1.0), (None, 1.0, 1.0)], "pid long, x double, y double")
    assert [r.pid for r in PointSpace(df, XY).valid().df.collect()] == [1]
    v = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 0.0]), (3, None), (4, [nan, 1.0])], "pid long, v array<double>")
    assert [r.pid for r in PointSpace(v, ("v",), "angular").valid().df.collect()] == [1]


def test_pick_and_attach(spark):
    df = points(spark).df.withColumnRenamed("pid", "id").withColumn("name", F.concat(F.lit("n"), "id"))
    for method in ("auto", "sequential", "three", "splits", "multi", "stream"):
        got = rounds.pick(df, "id", XY, 4, "clique", method)
        assert got.count() == 4
    full = rounds.attach(got, df, "id").collect()
    assert len(full) == 4 and all(r.name == f"n{r.id}" for r in full)


def test_quota_and_strict_certificate(spark):
    s = points(spark, 60)
    rows = solvers.pick_with_quota(s.slim("grp"), 8, "grp", 2).collect()
    assert len(rows) == 8 and max([sum(r.pid % 5 == g for r in rows) for g in range(5)]) == 2
    assert solvers.pick_with_quota(s.slim("grp"), 50, "grp", 2).count() == 10
    c = quality.strict_certificate(solvers.solve(s.slim(), 4, "clique"), s.slim(), 0.0).first()
    assert (c.points, c.proxied) == (4, 4)


def test_range_join_is_the_plain_one(spark):
    s = points(spark, 200, 2, 300)
    got = {(r.i, r.j) for r in relational.range_join(s.df, s.df, 25, list(XY)).collect()}
    b = block(s)
    d = b.matrix()
    assert got == {(int(i), int(j)) for i, j in zip(*np.nonzero(d <= 25), strict=True) if i != j}


def test_ball_and_sphere(spark):
    rows = tables.ball_sphere(spark, 3000, 20, 1).collect()
    norm = [math.sqrt(r.x**2 + r.y**2 + r.z**2) for r in rows]
    assert all(abs(n - 1) < 1e-9 for n, r in zip(norm, rows, strict=True) if r.pid < 20)
    inner = [n for n, r in zip(norm, rows, strict=True) if r.pid >= 20]
    assert max(inner) <= 0.8 and abs(np.mean([(n / 0.8) ** 3 for n in inner]) - 0.5) < 0.03
    again = {r.pid: r.x for r in tables.ball_sphere(spark, 3000, 20, 1, 7).collect()}
    assert all(again[r.pid] == r.x for r in rows)


def test_audit_finds_a_broken_metric(spark, monkeypatch):
    s = points(spark, 12)
    assert metrics.audit(s.df, list(XY)).first().violations == 0
    monkeypatch.setitem(metrics.SCALAR, "square", lambda a, b: metrics.squared(a, b).cast("double"))
    assert metrics.audit(s.df, list(XY), "square").first().violations > 0


def test_accuracy_rises_with_the_kernel_and_falls_with_adversaries(spark):
    """Means over seeds on the hard cloud: more anchors do not hurt, and the loss of region parts stays small."""
    k, n = 16, 6000
    means = {}
    for mode, kp in (("hash", 16), ("hash", 64), ("region", 64)):
        values = []
        for seed in range(3):
            space = PointSpace(tables.ball_sphere(spark, n, k, seed), ("x", "y", "z"))
            values.append(rounds.two_round(space, k, kp, 4, "edge", mode, seed).first().value)
        means[mode, kp] = np.mean(values)
    assert means["hash", 64] >= 0.95 * means["hash", 16]
    assert means["region", 64] >= 0.85 * means["hash", 64]


def test_baselines_return_solutions(spark):
    s = points(spark, 120, 8)
    runs = [baselines.blocked_stream(s, 4, "edge", 120), baselines.size_k_coreset(s, 4, 3, "edge"), baselines.single_stream(s, 4, 64), baselines.adversarial(s, 4, 8, 3, "edge"), baselines.shuffled(s, 4, 8, 3, "edge", 5), baselines.local_search_coreset(s, 4, 3)]
    assert all(r.count() == 4 for r in runs)
    assert baselines.uniform_sample(s, 7).count() == 7
    best = baselines.sequential(s, 4, "clique").first().value
    assert baselines.local_search_coreset(s, 4, 3).first().value >= 0.5 * best


def test_plans_shuffle_no_more_than_needed(spark):
    s = points(spark)
    assert quality.exchanges(rounds.two_round(s, 4, 8, 4, "edge")) == 2
    assert quality.exchanges(rounds.split_round(s, 4, 8, "edge")) == 1
    assert quality.exchanges(coresets.sketch_splits(s, 4, 8)) == 0


def test_filters_and_columns_reach_the_scan(spark, tmp_path):
    points(spark).df.write.parquet(f"{tmp_path}/p")
    df = relational.within_ball(spark.read.parquet(f"{tmp_path}/p").select("pid", "x"), {"x": 100}, 50)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(x,50)" in plan.replace(".0", "") and "ReadSchema: struct<pid:bigint,x:bigint>" in plan


def test_table_functions(spark):
    sqlapi.register(spark)
    points(spark, 50).df.selectExpr("grp AS part", "pid", "array(double(x), double(y)) AS v").createOrReplaceTempView("some")
    assert spark.sql("SELECT * FROM diverse_pick(TABLE(SELECT * FROM some) PARTITION BY part ORDER BY (pid), 3, 'clique')").count() == 15
    assert spark.sql("SELECT * FROM coreset(TABLE(SELECT * FROM some) PARTITION BY part ORDER BY (pid), 4, 9)").agg(F.sum("mult")).first()[0] <= 50
    assert spark.sql("SELECT * FROM doubling(TABLE(SELECT * FROM some) PARTITION BY part ORDER BY (pid), 2, 4)").count() >= 10


def stream_of(spark, path, cuts):
    s = points(spark, 200, 11)
    rows = s.df.selectExpr("pid", "timestamp_seconds(pid * 60) AS at", "array(double(x), double(y)) AS v")
    for a, b in zip(cuts, cuts[1:]):
        rows.where((F.col("pid") >= a) & (F.col("pid") < b)).coalesce(1).write.mode("append").parquet(path)
    return s, spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


@pytest.mark.parametrize("cuts", ((0, 200), (0, 30, 31, 120, 200)))
def test_a_stream_is_its_replay(spark, tmp_path, cuts):
    s, live = stream_of(spark, f"{tmp_path}/in", cuts)
    q = streaming.sketch(live, 4, 9).writeStream.format("memory").queryName("live").outputMode("update").option("checkpointLocation", f"{tmp_path}/check").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = spark.table("live")
    last = got.where(f"seen = {got.agg(F.max('seen')).first()[0]}")
    want = coresets.sketch_stream(s.slim().withColumn("part_id", F.lit(0).cast("long")), 4, 9)
    assert sorted(r.pid for r in last.collect()) == sorted(r.pid for r in want.where("NOT is_filler OR is_filler").collect())
    assert streaming.finalise(got, 4, "edge").first().value == rounds.one_pass(s.slim(), 4, 9, "edge").first().value


def test_a_stream_goes_on_after_a_stop(spark, tmp_path):
    s, live = stream_of(spark, f"{tmp_path}/in", (0, 90))

    def run():
        out = streaming.sketch(live, 3, 6, "clique").writeStream.outputMode("update").option("checkpointLocation", f"{tmp_path}/check").trigger(availableNow=True)
        held = []
        q = out.foreachBatch(lambda df, _: held.append(df.collect())).start()
        q.awaitTermination(120)
        return held[-1]

    run()
    rows = s.df.selectExpr("pid", "timestamp_seconds(pid * 60) AS at", "array(double(x), double(y)) AS v")
    rows.where("pid >= 90").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    got = sorted(r.pid for r in run())
    whole = coresets.sketch_stream(s.slim().withColumn("part_id", F.lit(0).cast("long")), 3, 6, "delegates")
    assert got == sorted(r.pid for r in whole.collect())


def test_sketch_state_survives_text(spark, tmp_path):
    b = block(points(spark, 100))
    s = kernels.Sketch(3, 7, "delegates").update(b.ids[:60], b.x[:60])
    streaming.save_state({0: s}, spark, f"{tmp_path}/state")
    t = streaming.load_state(spark, f"{tmp_path}/state")[0]
    assert t.update(b.ids[60:], b.x[60:]).ids == s.update(b.ids[60:], b.x[60:]).ids


def test_late_and_repeated_rows_of_a_stream(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:01:00"), (2, "2024-01-01 02:00:00"), (4, "2024-01-01 02:01:00"), (3, "2024-01-01 00:00:30")]  # rows count as late one batch after the watermark has passed them
    for r in rows:
        spark.createDataFrame([r], "id long, ts string").selectExpr("id", "timestamp(ts) AS ts").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    live = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = streaming.dedupe_stream(live, ["id"], "ts", "10 minutes").writeStream.format("memory").queryName("once").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(r.id for r in spark.table("once").collect()) == [1, 2, 4]


def test_streams_meet_within_seconds(spark, tmp_path):
    spark.createDataFrame([(1, 0, "a"), (2, 100, "a"), (3, 40, "b")], "pid long, s long, u string").selectExpr("pid", "timestamp_seconds(s + 9999) AS ta", "u").coalesce(1).write.parquet(f"{tmp_path}/a")
    spark.createDataFrame([(7, 5, "a"), (8, 300, "a"), (9, 41, "b")], "oid long, s long, u string").selectExpr("oid", "timestamp_seconds(s + 9999) AS tb", "u").coalesce(1).write.parquet(f"{tmp_path}/b")
    a, b = spark.readStream.schema("pid long, ta timestamp, u string").parquet(f"{tmp_path}/a"), spark.readStream.schema("oid long, tb timestamp, u string").parquet(f"{tmp_path}/b")
    q = streaming.stream_pair(a, b, "u", 10, "1 minute").writeStream.format("memory").queryName("met").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted((r.pid, r.oid) for r in spark.table("met").collect()) == [(1, 7), (3, 9)]


def test_candidates_of_frozen_anchors(spark, tmp_path):
    s, live = stream_of(spark, f"{tmp_path}/in", (0, 200))
    anchors = solvers.solve(s.slim(), 3, "edge").selectExpr("pid AS anchor_pid", "v AS a")
    q = streaming.stream_candidates(live, anchors, 150.0).select("pid", "anchor_pid").writeStream.format("memory").queryName("near").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {(r.pid, r.anchor_pid) for r in spark.table("near").collect()}
    gap = metrics.euclid_arr(F.col("v"), F.col("a"))
    want = {(r.pid, r.anchor_pid) for r in s.slim().crossJoin(anchors).where(gap <= 150).collect()}
    assert got == want


@pytest.mark.parametrize("block", [4, 1000])
def test_sparse_products_keep_frequent_terms(spark, block):
    vectors = {i: {0: 2 + i % 3, 1 + i % 2: 1 + i, 10 + i: 5} for i in range(30)} | {40: {99: 1}}  # term 0 is in all but one
    w = spark.createDataFrame([(i, t, c) for i, v in vectors.items() for t, c in v.items()], "pid long, term int, cnt long")
    got = {(r.i, r.j): (r.dot, r.ni, r.nj) for r in metrics.sparse_products(w, len(vectors), block).collect()}
    norm = {i: sum(c * c for c in v.values()) for i, v in vectors.items()}
    want = {(i, j): (sum(c * vectors[j].get(t, 0) for t, c in vectors[i].items()), norm[i], norm[j]) for i in range(30) for j in range(i + 1, 30)}
    assert got == want


@pytest.mark.parametrize("how", ["parquet", "cached", "checkpointed", "shuffled", "no reuse"])
def test_places_are_right_on_any_plan(spark, tmp_path, how):
    n = 120_000
    df = spark.range(0, n, 1, 7).select(F.col("id").alias("pid"), F.pmod(F.xxhash64("id"), F.lit(500)).alias("x"), F.pmod(F.xxhash64("id", F.lit(1)), F.lit(3)).cast("int").alias("y"))
    if how == "parquet":
        df.write.parquet(f"{tmp_path}/p")
        df = spark.read.parquet(f"{tmp_path}/p")
    elif how == "cached":
        df = df.cache()
    elif how == "checkpointed":
        df = df.checkpoint()
    elif how == "shuffled":
        df = df.repartition(5)
    else:
        spark.conf.set("spark.sql.exchange.reuse", "false")
    try:
        got = ranked(df, ("x", "y")).select("pid", "_at", "_n").collect()
    finally:
        spark.conf.set("spark.sql.exchange.reuse", "true")
    order = {r.pid: k for k, r in enumerate(sorted(df.collect(), key=lambda r: (r.x, r.y, r.pid)))}
    assert {r.pid: r._at for r in got} == order and {r._n for r in got} == {n}


def test_places_of_few_rows_and_of_equal_ones(spark):
    df = spark.createDataFrame([(i, 1) for i in range(5)], "pid long, x long")
    assert {r.pid: r._at for r in ranked(df, ("x",)).collect()} == {i: i for i in range(5)}
    assert ranked(df.limit(0), ("x",)).collect() == []


def test_random_keys_need_fewer_delegates(spark):
    s = points(spark, 2000)
    assert coresets.random_cap(16, 2000, 4, 1.0) == 8
    few = rounds.core_set(s, 16, 16, 4, "clique", "keyed", 0, coresets.random_cap(16, 2000, 4, 1.0)).count()
    assert few <= 4 * 16 * 8 < rounds.core_set(s, 16, 16, 4, "clique", "keyed").count() <= 4 * 16 * 16
    assert rounds.two_round_random(s, 16, 16, 4, "clique", 2000, c=1.0).count() == 16


def test_levels_keep_their_bound(spark):
    s = points(spark, 3000)
    with pytest.raises(ValueError, match="twice"):
        rounds.multi_round(s, 4, 8, 15, "edge")
    assert rounds.multi_round(s, 4, 8, 16, "edge").count() == 4  # several levels
    same = PointSpace(s.df.withColumn("pid", F.col("pid") * 1000), XY)  # remainders of the ids are all alike
    assert rounds.multi_round(same, 4, 8, 100, "edge").count() == 4


def test_parts_follow_the_rows():
    assert params.part_count(1000, 32, 10**6) == 8 and params.part_count(10**12, 32, 10**6) >= 10**6
    n, size = 10**9, 256
    parts = params.part_count(n, size, 10**6)
    assert n / parts <= 10**6 and parts * size <= 10**6


def test_stream_by_angle_covers_its_points(spark):
    rng = np.random.default_rng(2)
    docs = [(i, [(int(t), int(c)) for t, c in zip(np.sort(rng.choice(60, 12, replace=False)), rng.integers(1, 6, 12), strict=True)]) for i in range(300)]
    space = PointSpace(spark.createDataFrame(docs, "pid long, v array<struct<term int, cnt int>>"), ("v",), "sparse")
    chosen = rounds.one_pass(space.slim(), 5, 12, "edge", metric="sparse", dims=60).collect()
    dense = np.zeros((300, 60))
    for i, v in docs:
        for t, c in v:
            dense[i, t] = c
    unit = dense / np.linalg.norm(dense, axis=1, keepdims=True)
    ids = [r.pid for r in chosen]
    angles = np.arccos(np.clip(unit[ids] @ unit[ids].T, -1, 1))
    assert len(set(ids)) == 5 and abs(angles[np.triu_indices(5, 1)].min() - chosen[0].value) < 1e-6
    s = kernels.Sketch(5, 12, "delegates", "angular").update(range(300), dense)
    kept = np.array(s.x) / np.linalg.norm(s.x, axis=1, keepdims=True)
    assert len(s.x) <= 12 and np.arccos(np.clip(unit @ kept.T, -1, 1)).min(1).max() <= 4 * s.threshold + 1e-9
    assert np.arccos(np.clip(kept @ kept.T, -1, 1))[np.triu_indices(len(kept), 1)].min(initial=9.0) > 0
    cut = kernels.Sketch(5, 12, "delegates", "angular")
    for a in range(0, 300, 7):
        cut.update(range(a, min(a + 7, 300)), dense[a : a + 7])
    assert cut.ids == s.ids and [[i for i, _ in h] for h in cut.held] == [[i for i, _ in h] for h in s.held]
    found = rounds.split_round(space, 5, 12, "edge")
    assert found.count() == 5 and set(found.schema["v"].dataType.typeName() for _ in [0]) == {"array"}
    assert streaming.restore(streaming.dump(s)).metric == "angular"


@pytest.mark.parametrize("together", [1, 3, 1000])
def test_traverse_picks_as_build_without_gathering_a_part(spark, monkeypatch, together):
    rng = np.random.default_rng(3)
    rows = [(int(i), [x for t in sorted(rng.choice(12, int(rng.integers(1, 4)), False).tolist()) for x in (t, int(rng.integers(1, 4)))]) for i in rng.permutation(120)]
    df = spark.createDataFrame(rows, "pid long, v array<long>").repartition(5)
    want = {}
    for n in (2, 3, 200):
        built = coresets.build(df.withColumn("part_id", F.col("pid") % n), 9, metric="sparse")
        want |= {(n, r.part_id, r.pick_rank): r.pid for r in built.collect()}
    monkeypatch.setattr(coresets, "NEXT", together)
    monkeypatch.setattr(coresets, "build", None)
    most = []
    monkeypatch.setattr(coresets, "_picked_on", lambda left, real=coresets._picked_on: most.append(left) or real(left))
    got = coresets.traverse(df, 9, [2, 3, 200], dims=12).collect()
    assert {(r.parts, r.part_id, r.pick_rank): r.pid for r in got} == want
    assert len(most) <= 9 and (together < 1000 or len(most) == 2)
