"""Certificates of core-sets, exact factors on small data, and the cost measures of a run."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.functions import kernels
from diversify.functions.metrics import to_set
from diversify.operators import measures, solvers
from diversify.operators.space import PointSpace, block_of


def loose_certificate(points: DataFrame, core: DataFrame, coords: list[str], sep: DataFrame) -> DataFrame:
    """(radius, separation, eps): every point has a core-set point within eps/2 of the separation. ``sep``: (objective, value) of a k-choice of the core-set."""
    r = measures.covering_radius(points, core, coords).select(F.col("value").alias("radius"))
    return r.crossJoin(F.broadcast(sep.select(F.col("value").alias("separation")))).select("radius", "separation", F.round(2 * F.col("radius") / F.col("separation"), 6).alias("eps"))


def strict_certificate(candidates: DataFrame, core: DataFrame, reach: float) -> DataFrame:
    """(points, proxied): how many of the candidates (pid, v) get proxies of their own among the core-set (pid, v) within reach; augmenting paths in one task."""
    gap = F.sqrt(F.aggregate(F.zip_with("v", "w", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    near = candidates.select("pid", "v").crossJoin(core.select(F.col("pid").alias("proxy"), F.col("v").alias("w"))).where(gap <= reach)

    def matched(t: pa.Table) -> pa.Table:
        options: dict[int, list[int]] = {}
        for a, b in zip(t.column("pid").to_pylist(), t.column("proxy").to_pylist(), strict=True):
            options.setdefault(a, []).append(b)
        of: dict[int, int] = {}

        def place(a: int, seen: set[int]) -> bool:
            for b in sorted(options[a]):
                if b not in seen:
                    seen.add(b)
                    if b not in of or place(of[b], seen):
                        of[b] = a
                        return True
            return False

        done = sum(place(a, set()) for a in sorted(options))
        return pa.table({"proxied": pa.array([done], pa.int64())})

    found = near.select("pid", "proxy", F.lit(0).alias("_all")).groupBy("_all").applyInArrow(lambda t: matched(t), "proxied long")
    return candidates.agg(F.count("*").alias("points")).crossJoin(found)


def beta(space: PointSpace, core: DataFrame, k: int, objective: str) -> DataFrame:
    """(objective, best, in_core, beta): the optimum of the input over that of the core-set, both by enumeration."""
    whole = solvers.solve(space.slim(), k, objective, space.metric, "brute").agg(F.max("value").alias("best"))
    inside = solvers.solve(core, k, objective, space.metric, "brute").agg(F.max("value").alias("in_core"))
    both = whole.crossJoin(inside)
    return both.select(F.lit(objective).alias("objective"), F.round("best", 6).alias("best"), F.round("in_core", 6).alias("in_core"), F.round(F.col("best") / F.col("in_core"), 6).alias("beta"))


def beta_of_counts(space: PointSpace, core: DataFrame, k: int, objective: str) -> DataFrame:
    """As ``beta`` for a core-set with counts: its optimum is over the expansion, copies at distance zero."""

    metric = space.metric

    def best(t: pa.Table) -> pa.Table:
        import numpy as np

        b = block_of(t, metric)
        of = dict(zip(t.column("pid").to_pylist(), t.column("mult").to_pylist(), strict=True))
        copies = [i for i, p in enumerate(b.ids.tolist()) for _ in range(min(of[p], k))]
        d = b.matrix()[np.ix_(copies, copies)]
        top = 0.0
        from itertools import combinations

        for some in combinations(range(len(copies)), k):
            top = max(top, kernels.value(d[np.ix_(some, some)], objective))
        return pa.table({"in_core": pa.array([top])})

    whole = solvers.solve(space.slim(), k, objective, space.metric, "brute").agg(F.max("value").alias("best"))
    inside = core.select("pid", "v", "mult", F.lit(0).alias("_all")).groupBy("_all").applyInArrow(lambda t: best(t), "in_core double")
    return whole.crossJoin(inside).select(F.lit(objective).alias("objective"), F.round("best", 6).alias("best"), F.round("in_core", 6).alias("in_core"), F.round(F.col("best") / F.col("in_core"), 6).alias("beta"))


def ratio(found: DataFrame, by: list[str]) -> DataFrame:
    """Reference over value, at least 1: the reference is the best of all runs of ``found`` (…, value)."""
    best = found.agg(F.max("value").alias("reference"))
    return found.crossJoin(F.broadcast(best)).groupBy(*by).agg(
        F.round(F.avg(F.col("reference") / F.col("value")), 6).alias("mean_ratio"), F.round(F.min(F.col("reference") / F.col("value")), 6).alias("best_ratio"),
        F.round(F.max(F.col("reference") / F.col("value")), 6).alias("worst_ratio"), F.count("*").alias("runs"),
    )


def local_memory(parted: DataFrame, core: DataFrame) -> DataFrame:
    """(role, largest, total): rows that reducers hold, in the parts and in the union."""
    parts = parted.groupBy("part_id").count().agg(F.max("count").alias("largest"), F.sum("count").alias("total")).select(F.lit("part").alias("role"), "largest", "total")
    return parts.unionByName(core.agg(F.count("*").alias("largest"), F.count("*").alias("total")).select(F.lit("union").alias("role"), "largest", "total"))


def work(parted: DataFrame, m: int) -> DataFrame:
    """(part_id, rows, evaluations): distances that a part's traversal computes."""
    return parted.groupBy("part_id").agg(F.count("*").alias("rows")).select("part_id", "rows", (F.col("rows") * F.least(F.lit(m), F.col("rows"))).alias("evaluations"))


def doubling_estimate(trace: DataFrame) -> DataFrame:
    """Slope of the number of anchors against the shrinking radius, both as logarithms."""
    t = trace.where("radius > 0").select(F.log(F.col("pick_rank") + 1).alias("y"), (-F.log("radius")).alias("x"))
    return t.agg(F.round(F.regr_slope("y", "x"), 6).alias("dimension"), F.count("*").alias("steps"))


def exchanges(df: DataFrame) -> int:
    """Shuffles in the plan, a method's number of rounds."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ")


def assignment(points: DataFrame, anchors: DataFrame, coords: list[str]) -> DataFrame:
    return to_set(points, anchors, coords)
