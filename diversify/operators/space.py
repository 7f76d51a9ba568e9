"""Points with a metric, and the numpy block a task makes of them."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType

from diversify.functions.kernels import Block


@dataclass(frozen=True)
class PointSpace:
    """``df`` has pid and either scalar columns ``coords``, or one array column: of doubles, of tokens (jaccard), or of (term, cnt) structs (sparse; flat, terms and counts in turn, once ``kept``)."""

    df: DataFrame
    coords: tuple[str, ...]
    metric: str = "euclid"

    @property
    def arrays(self) -> bool:
        return len(self.coords) == 1 and self.df.schema[self.coords[0]].dataType.typeName() == "array"

    def slim(self, *more: str) -> DataFrame:
        """pid, v and ``more``: what the kernels read. Everything else stays out of the shuffle; join it back by pid."""
        v = F.col(self.coords[0]) if self.arrays else F.array(*(F.col(c).cast("double") for c in self.coords))
        if self.metric == "sparse" and self.df.schema[self.coords[0]].dataType.elementType.typeName() == "struct":  # terms and counts in turn: a flat array crosses to the kernels as it is
            v = F.flatten(F.transform(v, lambda x: F.array(x["term"].cast("long"), x["cnt"].cast("long"))))
        return self.df.select(F.col("pid").cast("long").alias("pid"), v.alias("v"), *more)

    def kept(self) -> PointSpace:
        """The space of ``slim``, computed once for several runs; word counts as flat integers, the smallest that crosses to the kernels."""
        rows = self.slim()
        return replace(self, df=checkpoint(rows.withColumn("v", F.col("v").cast("array<int>")) if self.metric == "sparse" else rows), coords=("v",))

    def valid(self) -> PointSpace:
        """Without rows whose id or coordinates are null, NaN or, for angles, all zero."""
        if not self.arrays:
            ok: Column = F.col("pid").isNotNull()
            for c in self.coords:
                ok = ok & F.col(c).isNotNull() & ~F.isnan(F.col(c).cast("double"))
            return replace(self, df=self.df.where(ok))
        v = F.col(self.coords[0])
        ok = F.col("pid").isNotNull() & v.isNotNull()
        if self.metric in ("euclid", "manhattan", "chebyshev", "angular"):
            ok = ok & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")))
        if self.metric == "angular":
            ok = ok & F.exists(v, lambda x: x != 0)
        if self.metric == "sparse":
            ok = ok & (F.size(v) > 0)
        return replace(self, df=self.df.where(ok))

    def with_parts(self, parts: int, mode: str = "mod", seed: int = 0, axes: tuple[str, ...] = ()) -> DataFrame:
        """``slim`` with part_id: by remainder of the id, by its hash ('keyed': by its MD5, which other engines have too), or by region (equal runs in the order of ``axes``, the adversary's parts)."""
        if mode == "mod":
            part = F.pmod(F.col("pid"), F.lit(parts))
        elif mode == "hash":
            part = F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(parts))
        elif mode == "keyed":
            part = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("pid").cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("long") % parts
        else:
            return region_parts(self.df, parts, axes or self.coords).select(F.col("pid").cast("long").alias("pid"), F.array(*(F.col(c).cast("double") for c in self.coords)).alias("v"), "part_id")
        return self.slim().withColumn("part_id", part.cast("long"))


def checkpoint(df: DataFrame) -> DataFrame:
    """``df`` computed once and written to the shared checkpoint folder of the session, so a lost executor costs a read, not the lineage."""
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        # Unset only in local runs and tests, where the warehouse is a folder that driver and executors share.
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None) or f"{df.sparkSession.conf.get('spark.sql.warehouse.dir')}/_checkpoints"
        context.setCheckpointDir(folder)
    return df.checkpoint()


#: Rows of the sample from which ``ranked`` takes a bound, for each bound.
BOUND_SAMPLE = 64


def ranked(df: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    """``df`` with _at, the row's place in the order of ``axes`` and pid, and _n, the number of rows.

    The order is cut at bounds that a sample gives (those rows whose hashes are least, so it is the same in every run); a row's bucket follows
    from its own values and the bounds, whatever the partitioning, and its place from the buckets' sizes: nothing is sorted in one task.
    """
    names = list(dict.fromkeys((*axes, "pid")))
    buckets = max(8, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    some = df.select(*names).orderBy(F.xxhash64(*names), *names).limit(BOUND_SAMPLE * buckets).select(F.struct(*names).alias("b"))
    bounds = [r.b for r in some.orderBy("b").collect()][BOUND_SAMPLE - 1 :: BOUND_SAMPLE]
    kind = df.select(F.struct(*names).alias("b")).schema["b"].dataType
    cuts = F.array(*(F.struct(*(F.lit(v).cast(f.dataType).alias(f.name) for v, f in zip(b, kind.fields, strict=True))) for b in bounds)).cast(ArrayType(kind))
    own = F.struct(*names)
    bucketed = df.withColumn("_p", F.size(F.filter(cuts, lambda b: b < own)))
    local = bucketed.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(*names)))
    every = Window.partitionBy(F.lit(0))  # a row for each bucket
    sizes = bucketed.groupBy("_p").count().select("_p", (F.sum("count").over(every.orderBy("_p")) - F.col("count")).alias("_before"), F.sum("count").over(every).alias("_n"))
    return local.join(F.broadcast(sizes), "_p").withColumn("_at", F.col("_before") + F.col("_r") - 1).drop("_p", "_r", "_before")


def region_parts(df: DataFrame, parts: int, axes: tuple[str, ...]) -> DataFrame:
    """part_id in runs along ``axes`` whose sizes differ by one at most, the longer ones first, as ntile has them."""
    at = ranked(df, axes)
    short, extra = F.floor(F.col("_n") / parts), F.col("_n") % parts
    head = extra * (short + 1)
    part = F.when(F.col("_at") < head, F.floor(F.col("_at") / (short + 1))).otherwise(extra + F.floor((F.col("_at") - head) / F.greatest(short, F.lit(1))))
    return at.withColumn("part_id", part.cast("long")).drop("_n", "_at")


def block_of(t: pa.Table | pa.RecordBatch, metric: str) -> Block:
    """The block of a table with pid and v."""
    ids, v = t.column("pid").to_numpy(), t.column("v")
    if metric == "jaccard":
        return Block(ids, v.to_pylist(), metric)
    if metric == "sparse":
        return Block(ids, [(r[::2], r[1::2]) for r in v.to_pylist()], metric)
    flat = v.combine_chunks().flatten() if isinstance(v, pa.ChunkedArray) else v.flatten()
    return Block(ids, np.asarray(flat, float).reshape(len(ids), -1) if len(ids) else np.zeros((0, 1)), metric)


def rows_of(t: pa.Table, pids: np.ndarray) -> list[int]:
    """Row numbers of some ids."""
    where = {p: i for i, p in enumerate(t.column("pid").to_pylist())}
    return [where[p] for p in pids.tolist()]


def v_of(t: pa.Table, ids: np.ndarray) -> pa.Array:
    """The coordinates of some ids, with elements that may be null, as a schema's text declares them."""
    v = t.column("v").combine_chunks().take(pa.array(rows_of(t, ids), pa.int64()))
    return v.cast(pa.list_(v.type.value_type))
