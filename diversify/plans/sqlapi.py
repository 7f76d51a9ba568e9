"""Table functions for SQL: a diverse choice, a core-set and a doubling sketch of each partition of a table (part, pid, v)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from diversify.functions import kernels
from diversify.operators.solvers import picks


class _Gathered:
    """Rows of one partition; the arguments after the table are the same on each."""

    def __init__(self) -> None:
        self.rows: list = []
        self.args: tuple = ()

    def eval(self, row, *args):
        self.rows.append((row["part"], row["pid"], row["v"]))
        self.args = args

    def block(self) -> kernels.Block:
        return kernels.Block([r[1] for r in self.rows], np.array([r[2] for r in self.rows], float))


@udtf(returnType="part string, pid long, pick_rank long, value double")
class DiversePick(_Gathered):
    def terminate(self):
        if self.rows:
            k, objective = self.args
            b = self.block()
            at = picks(b, k, objective)
            value = kernels.value(b.take(at).matrix(), objective)
            for rank, i in enumerate(at):
                yield str(self.rows[0][0]), int(b.ids[i]), rank, value


@udtf(returnType="part string, pid long, mult long, radius double")
class CoreSet(_Gathered):
    def terminate(self):
        if self.rows:
            m, cap = self.args
            b = self.block()
            at, owner, radii = kernels.farthest_first(b, m)
            for i, n in zip(at, kernels.counts(at, owner, cap), strict=True):
                yield str(self.rows[0][0]), int(b.ids[i]), int(n), float(radii[-1])


@udtf(returnType="part string, pid long, is_filler boolean, threshold double")
class Doubling:
    """A true one-pass table function: rows are folded as they come."""

    def __init__(self) -> None:
        self.sketch: kernels.Sketch | None = None

    def eval(self, row, k: int, m: int):
        self.sketch = self.sketch or kernels.Sketch(k, m)
        self.part = str(row["part"])
        self.sketch.update([row["pid"]], [row["v"]])

    def terminate(self):
        if self.sketch:
            for pid, _, filler in self.sketch.result():
                yield self.part, int(pid), filler, self.sketch.threshold


def register(spark: SparkSession) -> None:
    """diverse_pick(TABLE(..), k, objective), coreset(TABLE(..), m, cap), doubling(TABLE(..), k, m)."""
    spark.udtf.register("diverse_pick", DiversePick)
    spark.udtf.register("coreset", CoreSet)
    spark.udtf.register("doubling", Doubling)
