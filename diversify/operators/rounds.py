"""The methods end to end: in two, three or more rounds over parts, and in one or two passes over a stream."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from diversify.functions import kernels
from diversify.operators import coresets, solvers
from diversify.operators.space import PointSpace, block_of, checkpoint, v_of
from diversify.plans.params import part_count, strict

#: Rows of a part that a task is to hold in ``pick``.
TASK_ROWS = 1_000_000
#: Most large groups that ``grouped_rounds`` broadcasts; more are joined by a shuffle.
LARGE_GROUPS = 100_000


def core_set(space: PointSpace, k: int, k_prime: int, parts: int, objective: str, mode: str = "mod", seed: int = 0, cap: int | None = None, axes: tuple[str, ...] = (), scans: bool = False) -> DataFrame:
    """The union of the parts' core-sets, with delegates where the objective needs distinct proxies.

    ``scans``: of sparse vectors in parts by remainder, whose space is ``kept``; the same picks by scans of the rows, so that no part is gathered in a task.
    """
    if scans:
        if space.metric != "sparse" or mode != "mod" or strict(objective):
            raise ValueError("scans pick anchors of sparse vectors in parts by remainder")
        return coresets.traverse(space.slim(), k_prime, [parts], kept=True)
    parted = space.with_parts(parts, mode, seed, axes)
    kind = "delegates" if strict(objective) else "anchors"
    return coresets.build(parted, k_prime, kind, cap or k, space.metric)


def two_round(space: PointSpace, k: int, k_prime: int, parts: int, objective: str, mode: str = "mod", seed: int = 0, axes: tuple[str, ...] = (), scans: bool = False) -> DataFrame:
    """Core-sets of the parts, then the solver on their union."""
    return solvers.solve(core_set(space, k, k_prime, parts, objective, mode, seed, None, axes, scans), k, objective, space.metric)


def two_round_random(space: PointSpace, k: int, k_prime: int, parts: int, objective: str, n: int, seed: int = 0, mode: str = "hash", c: float = 2.0) -> DataFrame:
    """As ``two_round`` with random keys, which let an anchor do with fewer delegates: c times the larger of log n and its share of k."""
    cap = coresets.random_cap(k, n, parts, c)
    return solvers.solve(core_set(space, k, k_prime, parts, objective, mode, seed, cap), k, objective, space.metric)


def split_round(space: PointSpace, k: int, k_prime: int, objective: str) -> DataFrame:
    """Sketches of the input splits instead of parts: points are not shuffled at all."""
    return solvers.solve(coresets.sketch_splits(space, k, k_prime, "delegates" if strict(objective) else "points"), k, objective, space.metric)


def three_round(space: PointSpace, k: int, k_prime: int, parts: int, objective: str, mode: str = "mod") -> DataFrame:
    """(pid, value, gap): counts instead of delegates leave the parts; the chosen anchors go back to their parts and take members of their own clusters.

    gap: the most that replacing copies by members can have cost, twice the radius for each distance counted.
    """
    parted = space.with_parts(parts, mode)
    found = coresets.build(parted, k_prime, "counts", k, space.metric)
    chosen = solvers.solve_with_counts(found.select("pid", "v", "mult"), k, objective, space.metric).select("pid", F.col("mult").alias("take"))
    anchors = found.select("part_id", F.col("pid").alias("anchor_pid"), "v", "pick_rank").join(F.broadcast(chosen.withColumnRenamed("pid", "anchor_pid")), "anchor_pid", "left")
    members = instantiate(parted, anchors, space.metric)
    return with_value(members, k, objective, space.metric)


def instantiate(parted: DataFrame, anchors: DataFrame, metric: str) -> DataFrame:
    """(pid, v): for every chosen anchor itself and its next members by id, from its own cluster; clusters are disjoint, so no point serves two anchors."""

    def made(key, left: pa.Table, right: pa.Table) -> pa.Table:
        ranks = sorted(zip(right.column("pick_rank").to_pylist(), right.column("anchor_pid").to_pylist(), right.column("take").to_pylist(), strict=True))
        if not any(t for _, _, t in ranks) or not left.num_rows:
            return pa.table({"pid": pa.array([], pa.int64()), "v": v_of(left, np.zeros(0, np.int64))})
        b = block_of(left, metric)
        where = {p: i for i, p in enumerate(b.ids.tolist())}
        near, owner = np.full(len(b), np.inf), np.zeros(len(b), np.int64)
        for r, (_, pid, _) in enumerate(ranks):
            keys = b.keys(where[pid])
            better = keys < near
            near[better], owner[better] = keys[better], r
            near[where[pid]], owner[where[pid]] = -1.0, r
        out = []
        for r, (_, pid, take) in enumerate(ranks):
            if take:
                members = b.ids[owner == r]
                out += [pid, *members[members != pid][: take - 1].tolist()]
        return pa.table({"pid": pa.array(out, pa.int64()), "v": v_of(left, np.array(out, np.int64))})

    v = parted.schema["v"].dataType.simpleString()
    return parted.groupBy("part_id").cogroup(anchors.groupBy("part_id")).applyInArrow(made, f"pid long, v {v}")


def with_value(chosen: DataFrame, k: int, objective: str, metric: str = "euclid") -> DataFrame:
    """(pid, pick_rank, v, value) of at most k rows (pid, v)."""

    def made(t: pa.Table) -> pa.Table:
        b = block_of(t, metric)
        value = kernels.value(b.matrix(), objective)
        return pa.table({"pid": pa.array(b.ids), "pick_rank": pa.array(range(len(b)), pa.int64()), "v": v_of(t, b.ids), "value": pa.array([value] * len(b), pa.float64())})

    v = chosen.schema["v"].dataType.simpleString()
    return chosen.select("pid", "v", F.lit(0).alias("_all")).groupBy("_all").applyInArrow(made, f"pid long, pick_rank long, v {v}, value double")


def multi_round(space: PointSpace, k: int, k_prime: int, max_rows: int, objective: str, mode: str = "mod") -> DataFrame:
    """Core-sets of core-sets until at most ``max_rows`` rows are left, which must be twice a core-set at least, so that each level shrinks.

    A part has about ``max_rows`` rows, so neither a part nor the final union is larger than a task is given. Each level is written to the
    shared checkpoint folder; the driver reads row counts only. The first level's keys may be unequal parts, later ones are dealt by hash
    (after remainders by MD5, which other engines have too).
    """
    kind, size = ("delegates", k_prime * k) if strict(objective) else ("anchors", k_prime)
    if max_rows < 2 * size:
        raise ValueError(f"max_rows must be at least {2 * size}, twice the core-set of a part")
    rows, level = space.slim(), 0
    n = rows.count()
    while n > max_rows:
        parts = -(-n // max_rows)
        by = "hash" if mode != "mod" else "keyed" if level else "mod"
        parted = PointSpace(rows, ("v",)).with_parts(parts, by, level)
        rows = checkpoint(coresets.build(parted, k_prime, kind, k, space.metric).select("pid", "v"))
        left, level = rows.count(), level + 1
        if left >= n and level > 1:
            raise RuntimeError(f"{n} rows do not shrink: ids repeat in too few parts")
        n = left
    return solvers.solve(rows, k, objective, space.metric)


def grouped_rounds(space: PointSpace, by: str, k: int, k_prime: int, objective: str, max_rows: int = TASK_ROWS, mode: str = "hash", levels: int | None = None) -> DataFrame:
    """(by, pid, pick_rank, v, value): k diverse rows of each group, however unequal the groups are. A null is a group too.

    A group of at most ``max_rows`` rows is solved as it is. Larger ones are split in parts of about so many rows and replaced by their parts' core-sets,
    until they fit; ``max_rows`` must be twice a core-set at least, so that each level shrinks them. The driver reads numbers of groups only.
    With ``levels`` there are at most so many of them, and a group's solver gets all that the last one left.
    """
    kind, size = ("delegates", k_prime * k) if strict(objective) else ("anchors", k_prime)
    if max_rows < 2 * size:
        raise ValueError(f"max_rows must be at least {2 * size}, twice the core-set of a part")
    rows, fit, level = space.slim(by), [], 0
    while levels is None or level < levels:
        large = rows.groupBy(F.col(by).alias("_by")).agg(F.ceil(F.count("*") / max_rows).alias("_parts")).where("_parts > 1")
        known = large.limit(LARGE_GROUPS + 1).count()
        if not known:
            break
        of = F.col(by).eqNullSafe(F.col("_by"))
        listed = F.broadcast(large) if known <= LARGE_GROUPS else large
        key = F.col("pid") if mode == "mod" else F.xxhash64("pid", F.lit(level))
        parted = rows.join(listed, of).select(by, "pid", "v", F.pmod(key, F.col("_parts")).cast("long").alias("part_id"))
        fit.append(rows.join(listed, of, "left_anti"))
        rows = checkpoint(coresets.build(parted, k_prime, kind, k, space.metric, by).select("pid", "v", by))
        level += 1
    for part in fit:
        rows = rows.unionByName(part)
    return solvers.solve(rows, k, objective, space.metric, by=by)


def one_pass(ordered: DataFrame, k: int, k_prime: int, objective: str, order: tuple[str, ...] = ("pid",), metric: str = "euclid", dims: int = 5000) -> DataFrame:
    """One pass over (pid, v and order columns) as one stream: the sketch, with delegates where needed, then the solver."""
    stream = ordered.withColumn("part_id", F.lit(0).cast("long"))
    sketch = coresets.sketch_stream(stream, k, k_prime, "delegates" if strict(objective) else "points", order=order, metric=metric, dims=dims)
    return solvers.solve(sketch, k, objective, metric)


def two_pass(ordered: DataFrame, k: int, k_prime: int, objective: str, order: tuple[str, ...] = ("pid",)) -> DataFrame:
    """The first pass counts, the solver chooses anchors with copies, the second pass finds members within reach of them.

    Reach is four thresholds, which covers every counted point. A streamed point may serve several anchors: each keeps its first k candidates and augmenting
    paths assign them.
    """
    stream = ordered.withColumn("part_id", F.lit(0).cast("long"))
    sketch = coresets.sketch_stream(stream, k, k_prime, "counts", order=order)
    chosen = solvers.solve_with_counts(sketch.select("pid", "v", "mult"), k, objective).select(F.col("pid").alias("anchor_pid"), F.col("v").alias("a"), "mult")
    reach = sketch.agg(F.max("threshold").alias("thr"))
    anchors = chosen.crossJoin(F.broadcast(reach))  # one row
    gap = F.aggregate(F.zip_with("v", "a", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    near = ordered.crossJoin(F.broadcast(anchors)).where(gap <= 16 * F.col("thr") * F.col("thr"))  # at most k anchors
    # Of an anchor's candidates only the first k in the stream's order are kept; groups of (anchor, hash) first keep k each.
    shard = F.pmod(F.xxhash64("pid"), F.lit(32))
    by = [F.col("pid") == F.col("anchor_pid")]
    local = Window.partitionBy("anchor_pid", "_s").orderBy(by[0].desc(), *order)
    whole = Window.partitionBy("anchor_pid").orderBy(by[0].desc(), *order)
    first = near.withColumn("_s", shard).withColumn("_r", F.row_number().over(local)).where(F.col("_r") <= k)
    kept = first.withColumn("_r", F.row_number().over(whole)).where(F.col("_r") <= k).select("anchor_pid", "mult", "pid", "v", "_r")

    def assigned(t: pa.Table) -> pa.Table:
        rows = t.to_pylist()
        anchors_ = {r["anchor_pid"]: r["mult"] for r in rows}
        options: dict[int, list[int]] = {}
        for r in sorted(rows, key=lambda r: (r["anchor_pid"], r["_r"])):
            options.setdefault(r["anchor_pid"], []).append(r["pid"])
        owner: dict[int, tuple[int, int]] = {a: (a, 0) for a in anchors_}  # anchors stand for themselves
        slots = [(a, s) for a in sorted(anchors_) for s in range(1, anchors_[a])]

        def place(slot: tuple[int, int], seen: set[int]) -> bool:
            for p in options[slot[0]]:
                if p in seen or p in anchors_:
                    continue
                seen.add(p)
                if p not in owner or place(owner[p], seen):
                    owner[p] = slot
                    return True
            return False

        for s in slots:
            place(s, set())
        v = {r["pid"]: r["v"] for r in rows}
        ids = sorted(p for p in owner if p in v)
        return pa.table({"pid": pa.array(ids, pa.int64()), "v": pa.array([v[p] for p in ids], pa.list_(pa.float64()))})

    done = kept.withColumn("_all", F.lit(0)).groupBy("_all").applyInArrow(assigned, "pid long, v array<double>")
    return with_value(done, k, objective)


def pick(
    df: DataFrame, id_col: str, coords: tuple[str, ...], k: int, objective: str = "edge", method: str = "auto", k_prime: int | None = None, parts: int | None = None,
    metric: str = "euclid", mode: str = "mod",
) -> DataFrame:
    """A diverse choice of k rows: (pid, pick_rank, v, value).

    Parts follow from the number of rows, so that neither a part nor the union of the core-sets exceeds what a task holds. 'auto' takes two
    rounds, three where delegates would be many, and several where no number of parts keeps both bounds.
    """
    space = PointSpace(df.withColumnRenamed(id_col, "pid"), coords, metric).valid()
    k_prime = k_prime or 2 * k
    if method == "sequential":
        return solvers.solve(space.slim(), k, objective, metric)
    if method == "splits":
        return split_round(space, k, k_prime, objective)
    if method == "stream":
        return one_pass(space.slim(), k, k_prime, objective, metric=metric)
    size = k_prime * (k if strict(objective) else 1)
    if method == "multi":
        return multi_round(space, k, k_prime, max(TASK_ROWS, 2 * size), objective, mode)
    if parts is None:
        n = space.df.count()
        if method == "auto" and strict(objective) and k >= 16:
            method, size = "three", k_prime
        parts = part_count(n, size, TASK_ROWS)
        if method == "auto" and parts * size > 4 * TASK_ROWS:
            return multi_round(space, k, k_prime, max(TASK_ROWS, 2 * size), objective, mode)
    if method == "three" or method == "auto" and strict(objective) and k >= 16:
        return three_round(space, k, k_prime, parts, objective, mode)
    return two_round(space, k, k_prime, parts, objective, mode)


def attach(chosen: DataFrame, df: DataFrame, id_col: str) -> DataFrame:
    """The payload of the chosen rows: at most k rows are broadcast."""
    return df.join(F.broadcast(chosen.select(F.col("pid").alias(id_col), "pick_rank", "value")), id_col)
