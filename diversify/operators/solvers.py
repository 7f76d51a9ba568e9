"""Sequential solvers over a gathered core-set, which is bounded by parts times kernel size, in one task."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.functions import kernels
from diversify.operators.space import block_of, v_of
from diversify.plans.params import REGISTRY


def picks(b: kernels.Block, k: int, objective: str) -> list[int]:
    if REGISTRY[objective][1] == "traversal":
        return kernels.farthest_first(b, k)[0].tolist()
    return kernels.heavy_matching(b, k)


def _chosen(b: kernels.Block, at: list[int], objective: str) -> float:
    return kernels.value(b.take(at).matrix(), objective)


def solve(gathered: DataFrame, k: int, objective: str, metric: str = "euclid", how: str = "solver", by: str | None = None) -> DataFrame:
    """(pid, pick_rank, v, value) of the solution among (pid, v), for each value of ``by`` if given.

    how: 'solver' (the objective's approximation), 'brute' (the optimum), 'search' (swaps for the sum of distances).
    """

    def made(t: pa.Table) -> pa.Table:
        b = block_of(t, metric)
        if how == "brute":
            at = kernels.brute_force(b, k, objective)[0]
        elif how == "search":
            at = kernels.local_search(b, k)
        else:
            at = picks(b, k, objective)
        value = _chosen(b, at, objective)
        ids = b.ids[at]
        cols = {by: pa.array([t.column(by)[0].as_py()] * len(at), t.schema.field(by).type)} if by else {}
        cols |= {"pid": pa.array(ids), "pick_rank": pa.array(range(len(at)), pa.int64()), "v": v_of(t, ids), "value": pa.array([value] * len(at), pa.float64())}
        return pa.table(cols)

    v = gathered.schema["v"].dataType.simpleString()
    first = f"{by} {gathered.schema[by].dataType.simpleString()}, " if by else ""
    rows = gathered.select(*([by] if by else []), "pid", "v")
    groups = rows.groupBy(by) if by else rows.withColumn("_all", F.lit(0)).groupBy("_all")
    return groups.applyInArrow(made if by else lambda t: made(t.drop_columns(["_all"])), f"{first}pid long, pick_rank long, v {v}, value double")


def solve_with_counts(gathered: DataFrame, k: int, objective: str, metric: str = "euclid") -> DataFrame:
    """(pid, v, mult, value): a coherent choice of total k among (pid, v, mult); value of its expansion, copies at distance zero."""

    def made(t: pa.Table) -> pa.Table:
        b = block_of(t, metric)
        of = dict(zip(t.column("pid").to_pylist(), t.column("mult").to_pylist(), strict=True))
        mult = [of[i] for i in b.ids.tolist()]
        choose = kernels.traversal_with_counts if REGISTRY[objective][1] == "traversal" else kernels.matching_with_counts
        chosen = choose(b, mult, k)
        at = sorted(chosen)
        copies = [i for i in at for _ in range(chosen[i])]
        whole = b.matrix()
        value = kernels.value(whole[copies][:, copies], objective)
        ids = b.ids[at]
        return pa.table({"pid": pa.array(ids), "v": v_of(t, ids), "mult": pa.array([chosen[i] for i in at], pa.int64()), "value": pa.array([value] * len(at), pa.float64())})

    v = gathered.schema["v"].dataType.simpleString()
    return gathered.select("pid", "v", "mult", F.lit(0).alias("_all")).groupBy("_all").applyInArrow(made, f"pid long, v {v}, mult long, value double")


def pick_with_quota(gathered: DataFrame, k: int, group: str, quota: int, metric: str = "euclid") -> DataFrame:
    """(pid, pick_rank): farthest-first that takes at most ``quota`` rows of a group."""

    def made(t: pa.Table) -> pa.Table:
        import numpy as np

        b = block_of(t, metric)
        of = dict(zip(t.column("pid").to_pylist(), t.column(group).to_pylist(), strict=True))
        groups = [of[i] for i in b.ids.tolist()]
        used: dict = {}
        near, out = np.full(len(b), np.inf), []
        free = np.ones(len(b), bool)
        while len(out) < k and free.any():
            at = int(np.argmax(np.where(free, near, -1.0)))
            out.append(at)
            near = np.minimum(near, b.keys(at))
            free[at] = False
            used[groups[at]] = used.get(groups[at], 0) + 1
            if used[groups[at]] >= quota:
                free &= np.array([g != groups[at] for g in groups])
        return pa.table({"pid": pa.array(b.ids[out]), "pick_rank": pa.array(range(len(out)), pa.int64())})

    return gathered.select("pid", "v", group, F.lit(0).alias("_all")).groupBy("_all").applyInArrow(made, "pid long, pick_rank long")
