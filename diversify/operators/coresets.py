"""Core-sets of parts. A part is one group of rows; what leaves it is bounded by the kernel size, whatever the part's size.

``build`` takes given parts (one shuffle of pid and coordinates). ``sketch_splits`` takes the input splits as they are read: no shuffle of
points, a task's memory follows the sketch; any partition composes, so the union is a core-set as well.
"""

from __future__ import annotations

import math
from bisect import bisect_right

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from diversify.functions import kernels
from diversify.operators.space import PointSpace, block_of, checkpoint, v_of


def schema(v: str) -> str:
    return f"part_id long, pid long, v {v}, anchor_pid long, pick_rank long, mult long, radius double"


def build(parted: DataFrame, m: int, kind: str = "anchors", cap: int = 1, metric: str = "euclid", by: str | None = None) -> DataFrame:
    """Core-set of each part of (pid, v, part_id): kind 'anchors', 'delegates' (up to ``cap`` rows an anchor) or 'counts' (mult up to ``cap``).

    With ``by`` a part is one of (by, part_id), and the column is kept.
    """

    def made(t: pa.Table) -> pa.Table:
        b = block_of(t, metric)
        picks, owner, radii = kernels.farthest_first(b, m)
        last = float(radii[-1]) if len(radii) else 0.0
        mult = kernels.counts(picks, owner, cap) if kind == "counts" else np.ones(len(picks), np.int64)
        pairs = kernels.delegates(picks, owner, cap) if kind == "delegates" else [(int(p), int(p)) for p in picks]
        rank = {int(p): r for r, p in enumerate(picks)}
        ids, anchors = b.ids[[x for _, x in pairs]], b.ids[[a for a, _ in pairs]]
        v = v_of(t, ids)
        part = t.column("part_id")[0].as_py()
        ranks = [rank[a] for a, _ in pairs]
        own = {by: pa.array([t.column(by)[0].as_py()] * len(pairs), t.schema.field(by).type)} if by else {}
        return pa.table(own | {
            "part_id": pa.array([part] * len(pairs), pa.int64()), "pid": pa.array(ids), "v": v, "anchor_pid": pa.array(anchors), "pick_rank": pa.array(ranks, pa.int64()),
            "mult": pa.array([int(mult[r]) for r in ranks], pa.int64()), "radius": pa.array([last if kind != "anchors" else float(radii[r]) for r in ranks], pa.float64()),
        })

    first = f"{by} {parted.schema[by].dataType.simpleString()}, " if by else ""
    return parted.groupBy(*([by] if by else []), "part_id").applyInArrow(made, first + schema(parted.schema["v"].dataType.simpleString()))


#: Rows of a part that ``traverse`` compares with each other in one task after a scan.
NEXT = 1000


def traverse(rows: DataFrame, m: int, parts: list[int], dims: int = 5000, kept: bool = False) -> DataFrame:
    """(parts, part_id, pick_rank, pid, v): the farthest-first picks of each part of sparse vectors (pid, v), for several numbers of parts by remainder.

    The picks are those of ``build``, but no part is gathered. A scan finds each row's distance to the picks so far. Of a part the ``NEXT`` farthest rows
    meet in a task, which picks on as long as the farthest of them comes before all rows that are not there: those only come nearer. At least one
    pick is made a scan. The driver holds the picks, m for each part. Rows that are ``kept`` in the checkpoint folder are scanned as they are.
    """
    rows = rows.where("pid IS NOT NULL").select("pid", F.col("v").cast("array<int>").alias("v"), F.array(*(F.pmod("pid", F.lit(n)).cast("long") + sum(parts[:i]) for i, n in enumerate(parts))).alias("own"))
    rows = rows if kept else checkpoint(rows)
    owns = rows.select("pid", F.explode("own").alias("part"))
    first = owns.groupBy("part").agg(F.min("pid").alias("pid"))
    picks: dict[int, list] = {}
    found = rows.select("pid", "v").join(F.broadcast(first), "pid").collect()  # a row for each part
    while found:
        for r in sorted(found, key=lambda r: r["pick_rank"] if "pick_rank" in r else 0):
            picks.setdefault(r["part"], []).append((r["pid"], r["v"]))
        left = {p: m - len(at) for p, at in picks.items() if len(at) < m}
        far = _farthest(rows, {p: picks[p] for p in left}, dims)
        order = F.desc("near"), "pid"
        local = F.row_number().over(Window.partitionBy("part", F.pmod(F.xxhash64("pid"), F.lit(32))).orderBy(*order))  # so that few rows of a part meet in the last window
        whole = F.row_number().over(Window.partitionBy("part").orderBy(*order))
        some = far.withColumn("at", local).where(F.col("at") <= NEXT).withColumn("at", whole).where(F.col("at") <= NEXT)
        found = rows.select("pid", "v").join(F.broadcast(some), "pid").groupBy("part").applyInArrow(_picked_on(left), "part long, pick_rank long, pid long, v array<int>").collect() if left else []
    ends = [sum(parts[: i + 1]) for i in range(len(parts))]
    out = [(parts[(i := bisect_right(ends, p))], p - ends[i] + parts[i], rank, pid, v) for p, at in sorted(picks.items()) for rank, (pid, v) in enumerate(at)]
    return rows.sparkSession.createDataFrame(out, "parts long, part_id long, pick_rank long, pid long, v array<long>")


def _farthest(rows: DataFrame, picks: dict[int, list], dims: int, block: int = 256) -> DataFrame:
    """(part, pid, near) of the rows (pid, v, own) that are in a part of ``picks`` and not picked there: the key of the distance to its nearest pick."""
    taken = {p: np.array([pid for pid, _ in at], np.int64) for p, at in picks.items()}
    slots, columns = {}, []
    for p, at in picks.items():
        slots[p] = slice(len(columns), len(columns) + len(at))
        columns += [np.asarray(v, np.int64) for _, v in at]

    def made(batches):
        to = np.zeros((dims, len(columns)))
        for c, v in enumerate(columns):
            to[v[::2], c] = v[1::2]
        norms = (to * to).sum(0)
        for batch in batches:
            for at in range(0, batch.num_rows, block):
                piece = batch.slice(at, block)
                pid, v = piece.column("pid").to_numpy(), _points(piece.column("v"), "sparse", dims)
                keys = 1 - np.round((v @ to) / np.sqrt((v * v).sum(1)[:, None] * norms), 12)
                own = np.asarray(piece.column("own").flatten()).reshape(len(pid), -1)
                for p, slot in slots.items():
                    here = np.flatnonzero((own == p).any(1) & ~np.isin(pid, taken[p]))
                    if len(here):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(here), p)), pa.array(pid[here]), pa.array(keys[here, slot].min(1))], ["part", "pid", "near"])

    return rows.mapInArrow(made, "part long, pid long, near double")


def _picked_on(left: dict[int, int]):
    """The next picks of a part's farthest rows (part, pid, v, near, at): up to its number in ``left``, while no row elsewhere may come first."""

    def made(t: pa.Table) -> pa.Table:
        part = t.column("part")[0].as_py()
        b = block_of(t, "sparse")
        near = t.column("near").to_numpy()[np.argsort(t.column("pid").to_numpy(), kind="stable")].copy()
        last = max(zip(-near, b.ids, strict=True)) if len(b) >= NEXT else (np.inf, 0)
        out, free = [], np.ones(len(b), bool)
        while len(out) < left[part] and free.any():
            i = int(np.argmax(np.where(free, near, -1.0)))
            if (-near[i], b.ids[i]) > last:
                break
            out.append(i)
            free[i] = False
            near = np.minimum(near, b.keys(i))
        ids = b.ids[out]
        return pa.table({"part": pa.array([part] * len(out), pa.int64()), "pick_rank": pa.array(range(len(out)), pa.int64()), "pid": pa.array(ids), "v": v_of(t, ids)})

    return made


def random_cap(k: int, n: int, parts: int, c: float = 2.0) -> int:
    """Delegates an anchor needs when keys are random."""
    return min(k, math.ceil(c * max(math.log(max(n, 2)), k / parts)))


def stream_metric(metric: str) -> str:
    """The sketch's metric: word counts are laid out as rows of the vocabulary and compared by angle."""
    if metric not in ("euclid", "angular", "sparse"):
        raise ValueError(f"no sketch for {metric}")
    return "euclid" if metric == "euclid" else "angular"


def _points(column: pa.Array, metric: str, dims: int) -> np.ndarray:
    """Rows of coordinates; (term, count) lists become rows over ``dims`` terms."""
    flat = np.asarray(column.flatten(), float)
    if metric != "sparse":
        return flat.reshape(len(column), -1)
    out = np.zeros((len(column), dims))
    size = np.asarray(pc.list_value_length(column), np.int64) // 2
    out[np.repeat(np.arange(len(column)), size), flat[::2].astype(np.int64)] = flat[1::2]
    return out


def _listed(points: list[np.ndarray], metric: str) -> pa.Array:
    """Points as they came: coordinates, or terms and counts in turn."""
    if metric == "sparse":
        at = [np.flatnonzero(p) for p in points]
        return pa.array([np.column_stack((t, p[t])).ravel().tolist() for t, p in zip(at, points, strict=True)], pa.list_(pa.float64()))
    return pa.array([p.tolist() for p in points], pa.list_(pa.float64()))


def sketch_splits(space: PointSpace, k: int, m: int, kind: str = "points", dims: int = 5000) -> DataFrame:
    """(pid, v, mult): a doubling sketch of each input split, without a shuffle, for euclid, angular and sparse spaces."""
    metric, own = space.metric, stream_metric(space.metric)

    def made(batches):
        s = kernels.Sketch(k, m, kind, own)
        for batch in batches:
            s.update(batch.column("pid").to_numpy(), _points(batch.column("v"), metric, dims))
        if kind == "delegates":
            rows = [(i, p, 1) for held in s.held for i, p in held]
        else:
            rows = [(i, p, c) for (i, p, _), c in zip(s.result(), [*s.count, *[1] * len(s.removed)], strict=False)]
        if rows:
            ids, points, mult = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), _listed(points, metric), pa.array([int(c) for c in mult], pa.int64())], ["pid", "v", "mult"])

    return space.slim().mapInArrow(made, "pid long, v array<double>, mult long")


def sketch_stream(
    ordered: DataFrame, k: int, m: int, kind: str = "points", part: str = "part_id", order: tuple[str, ...] = ("pid",), metric: str = "euclid", dims: int = 5000
) -> DataFrame:
    """Batch replay of one stream for each value of ``part``, in the order of ``order``: (part_id, anchor_pid, pid, v, mult, is_filler, threshold, phase, kept, removed).

    Rows arrive sorted and are folded batch by batch; a stream never stands in memory.
    """
    own = stream_metric(metric)

    def made(batches):
        held: dict[int, kernels.Sketch] = {}
        now = None
        for batch in batches:
            parts = np.asarray(batch.column(part))
            edges = np.concatenate(([0], np.flatnonzero(parts[1:] != parts[:-1]) + 1, [len(parts)])) if len(parts) else np.zeros(1, int)
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if now is not None and now != parts[a]:
                    yield _sketch_rows(now, held.pop(now), metric)
                now = parts[a]
                s = held.setdefault(now, kernels.Sketch(k, m, kind, own))
                step = int(b - a) if metric != "sparse" else 1024  # laid out rows are long
                for first in range(int(a), int(b), step):
                    piece = batch.slice(first, min(step, int(b) - first))
                    s.update(piece.column("pid").to_numpy(), _points(piece.column("v"), metric, dims))
        if now is not None:
            yield _sketch_rows(now, held.pop(now), metric)

    out = "part_id long, anchor_pid long, pid long, v array<double>, mult long, is_filler boolean, threshold double, phase long"
    return ordered.repartition(F.col(part)).sortWithinPartitions(part, *order).mapInArrow(made, out)


def _sketch_rows(part: int, s: kernels.Sketch, metric: str = "euclid") -> pa.RecordBatch:
    if s.kind == "delegates":
        rows = [(a, i, p, 1, False) for a, held in zip(s.ids, s.held, strict=True) for i, p in held]
    else:
        rows = [(i, i, p, s.count[n] if n < len(s.count) else 1, f) for n, (i, p, f) in enumerate(s.result())]
    cols = list(zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([
        pa.array([int(part)] * len(rows), pa.int64()), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), _listed(cols[2], metric),
        pa.array([int(c) for c in cols[3]], pa.int64()), pa.array(cols[4], pa.bool_()), pa.array([s.threshold] * len(rows)), pa.array([s.phase] * len(rows), pa.int64()),
    ], ["part_id", "anchor_pid", "pid", "v", "mult", "is_filler", "threshold", "phase"])


def phase_log(ordered: DataFrame, k: int, m: int, order: tuple[str, ...] = ("pid",)) -> DataFrame:
    """(phase, threshold, kept, removed, seen) of each merge of one stream."""

    def made(batches):
        s = kernels.Sketch(k, m)
        for batch in batches:
            x = np.asarray(batch.column("v").flatten(), float).reshape(batch.num_rows, -1) if batch.num_rows else np.zeros((0, 1))
            s.update(batch.column("pid").to_numpy(), x)
        if s.log:
            phase, square, kept, removed, seen = zip(*s.log, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(phase, pa.int64()), pa.array(np.sqrt(square)), pa.array(kept, pa.int64()), pa.array(removed, pa.int64()), pa.array(seen, pa.int64())], ["phase", "threshold", "kept", "removed", "seen"])

    return ordered.repartition(1).sortWithinPartitions(*order).mapInArrow(made, "phase long, threshold double, kept long, removed long, seen long")


def farthest_first_frame(space: PointSpace, m: int, checkpoint_every: int = 16) -> DataFrame:
    """(pick_rank, pid, radius) of the traversal over the whole frame, without parts: one scan and one row to the driver for each pick.

    The distance so far is a column of literals of the anchors, so the scan stays in generated code; the frame is cut by a
    checkpoint in the shared folder when many anchors have gathered.
    """
    coords = list(space.coords)
    points = space.df.select("pid", *coords)
    spark = points.sparkSession
    first = points.agg(F.min(F.struct("pid", *coords)).alias("p")).first().p
    found, near, batch = [], F.lit(None).cast("double"), 0
    anchor = first
    for rank in range(m):
        key = sum(((F.col(c) - F.lit(anchor[c])) * (F.col(c) - F.lit(anchor[c])) for c in coords[1:]), (F.col(coords[0]) - F.lit(anchor[coords[0]])) * (F.col(coords[0]) - F.lit(anchor[coords[0]]))).cast("double")
        near = key if rank == 0 else F.least(near, key)
        taken = [f["pid"] for f in found] + [anchor["pid"]]
        best = points.select("pid", *coords, near.alias("near")).agg(F.max("near").alias("radius"), F.max(F.when(~F.col("pid").isin(taken), F.struct("near", (-F.col("pid")).alias("low"), "pid", *coords))).alias("p")).first()
        found.append({"pick_rank": rank, "pid": anchor["pid"], "radius": math.sqrt(best.radius)})
        if best.p is None:
            break
        anchor = best.p
        batch += 1
        if batch == checkpoint_every and rank + 1 < m and spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
            points = points.withColumn("_near", near).checkpoint()
            near, batch = F.col("_near"), 0
            coords = [c for c in coords if c != "_near"]
    return spark.createDataFrame([(f["pick_rank"], f["pid"], f["radius"]) for f in found], "pick_rank long, pid long, radius double")
