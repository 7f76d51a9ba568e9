"""Measures of a chosen set (pid and coordinates, at most some thousands of rows) and of how it covers the input."""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from diversify.functions import kernels
from diversify.functions.metrics import SCALAR, to_set


def pairs(sel: DataFrame, coords: list[str], metric: str = "euclid", of: str = "i < j") -> DataFrame:
    """(i, j, d) of the pairs of rows, each once."""
    a, b = (sel.select(F.col("pid").alias(n), *(F.col(c).alias(f"{n}_{c}") for c in coords)) for n in "ij")
    d = SCALAR[metric]([F.col(f"i_{c}") for c in coords], [F.col(f"j_{c}") for c in coords])
    return a.join(b, F.expr(of)).select("i", "j", d.alias("d"))


#: Rows of a strip of ``strip_pairs``.
STRIP = 2000


def strip_pairs(rows: DataFrame, coords: list[str], metric: str = "euclid") -> DataFrame:
    """(i, j, d) of the pairs i < j of rows: dealt to strips of about ``STRIP`` rows by a hash of pid, a task compares two strips.

    A strip moves once for each other one, a thousandth of what their pairs are; no task grows with the rows.
    """
    n = max(1, -(-rows.count() // STRIP))
    point = F.struct("pid", *coords)
    strips = rows.groupBy(F.pmod(F.xxhash64("pid"), F.lit(n)).alias("own")).agg(F.collect_list(point).alias("rows"))
    left, right = (strips.select(F.col("own").alias(s), F.col("rows").alias(f"rows_{s}")) for s in "xy")
    both = left.join(right, F.col("x") <= F.col("y")).repartition(n * (n + 1) // 2)
    # The filter keeps the first explode out of generated code, which would hold all pairs of two strips before the first one leaves.
    ones = F.explode(F.filter("rows_x", lambda p: p["pid"].isNotNull()))
    each = both.select("x", "y", ones.alias("p"), "rows_y").select("x", "y", "p", F.explode("rows_y").alias("q")).where("x < y OR p.pid < q.pid")
    d = SCALAR[metric]([F.col("p")[c] for c in coords], [F.col("q")[c] for c in coords])
    return each.select(F.least("p.pid", "q.pid").alias("i"), F.greatest("p.pid", "q.pid").alias("j"), d.alias("d"))


def class_pairs(df: DataFrame, coords: list[str], metric: str = "euclid") -> DataFrame:
    """(i, j, d): the pairs i < j of the first rows at each position, and each other row with the first one at its position, at distance zero.

    What the copies' pairs would add follows from these rows. A row without a position is a class of its own.
    """
    unplaced = F.greatest(*(F.col(c).isNull() for c in coords), F.lit(False))
    own = Window.partitionBy(*coords, F.when(unplaced, F.col("pid")))
    rows = df.select("pid", *coords).withColumn("_first", F.min("pid").over(own))
    firsts = rows.where("pid = _first").drop("_first")
    return strip_pairs(firsts, coords, metric).unionByName(rows.where("pid <> _first").select(F.col("_first").alias("i"), F.col("pid").alias("j"), F.lit(0.0).alias("d")))


def _one(df: DataFrame, objective: str, value: Column) -> DataFrame:
    return df.agg(F.round(F.coalesce(value, F.lit(0.0)), 6).alias("value")).select(F.lit(objective).alias("objective"), "value")


def remote_edge(sel: DataFrame, coords: list[str]) -> DataFrame:
    return _one(pairs(sel, coords), "edge", F.min("d"))


def remote_clique(sel: DataFrame, coords: list[str]) -> DataFrame:
    return _one(pairs(sel, coords), "clique", F.sum("d"))


def remote_star(sel: DataFrame, coords: list[str]) -> DataFrame:
    return _one(pairs(sel, coords, of="i <> j").groupBy("i").agg(F.sum("d").alias("s")), "star", F.min("s"))


def remote_bipartition(sel: DataFrame, coords: list[str], k: int) -> DataFrame:
    """All halves as bit masks over the ranks of at most 16 points; above, the kernel's upper bound."""
    if k > 16:
        return by_kernel(sel, coords, "bipartition")
    at = sel.select("pid").withColumn("at", (F.expr("row_number() OVER (ORDER BY pid)") - 1).cast("int"))
    e = pairs(sel, coords).join(at.withColumnsRenamed({"pid": "i", "at": "ai"}), "i").join(at.withColumnsRenamed({"pid": "j", "at": "aj"}), "j")
    masks = sel.sparkSession.range(1 << k).where(F.bit_count("id") == k // 2)
    cut = masks.crossJoin(F.broadcast(e)).where(F.expr("shiftright(id, ai) & 1 <> shiftright(id, aj) & 1"))
    return _one(cut.groupBy("id").agg(F.sum("d").alias("s")), "bipartition", F.min("s"))


def by_kernel(sel: DataFrame, coords: list[str], objective: str) -> DataFrame:
    """Tree, cycle and large bipartitions: one task over the chosen rows."""

    def made(t: pa.Table) -> pa.Table:
        import numpy as np

        b = kernels.Block(t.column("pid").to_numpy(), np.column_stack([t.column(c).to_numpy() for c in coords]))
        return pa.table({"objective": pa.array([objective]), "value": pa.array([round(kernels.value(b.matrix(), objective), 6)])})

    rows = sel.select("pid", *(F.col(c).cast("double").alias(c) for c in coords), F.lit(0).alias("_all"))
    return rows.groupBy("_all").applyInArrow(lambda t: made(t), "objective string, value double")


def remote_tree(sel: DataFrame, coords: list[str]) -> DataFrame:
    return by_kernel(sel, coords, "tree")


def remote_cycle(sel: DataFrame, coords: list[str]) -> DataFrame:
    return by_kernel(sel, coords, "cycle")


def covering_radius(points: DataFrame, sel: DataFrame, coords: list[str]) -> DataFrame:
    return _one(to_set(points, sel, coords), "radius", F.max("dist"))


def separation(sel: DataFrame, coords: list[str]) -> DataFrame:
    """Smallest distance of a chosen point to the rest."""
    return _one(pairs(sel, coords, of="i <> j").groupBy("i").agg(F.min("d").alias("n")), "separation", F.min("n"))


def expansion(sel: DataFrame, coords: list[str]) -> DataFrame:
    """Each row ``mult`` times, with ids of its own."""
    return sel.select(F.explode(F.sequence(F.lit(1), F.col("mult").cast("int"))).alias("copy"), "*").select((F.col("pid") * 1000 + F.col("copy")).alias("pid"), *coords)


def generalized(sel: DataFrame, coords: list[str], objective: str, k: int) -> DataFrame:
    """A measure of the multiset that counts describe, copies at distance zero. The sum of distances needs no expansion."""
    if objective == "clique":
        a, b = (sel.select(F.col("pid").alias(n), F.col("mult").alias(f"m{n}"), *(F.col(c).alias(f"{n}_{c}") for c in coords)) for n in "ij")
        d = SCALAR["euclid"]([F.col(f"i_{c}") for c in coords], [F.col(f"j_{c}") for c in coords])
        return _one(a.join(b, F.expr("i < j")).select((F.col("mi") * F.col("mj") * d).alias("d")), "clique", F.sum("d"))
    whole = expansion(sel, coords)
    return {"star": remote_star, "tree": remote_tree}[objective](whole, coords) if objective in ("star", "tree") else remote_bipartition(whole, coords, k)


def term_count(objective: str, k: int) -> int:
    """Number of distances that the measure adds."""
    return {"edge": 1, "cycle": k, "clique": k * (k - 1) // 2, "star": k - 1, "tree": k - 1, "bipartition": (k // 2) * (k - k // 2)}[objective]


def mean_term(objective: str, k: int, value: float) -> float:
    return value / term_count(objective, k)


def term_table(sizes: DataFrame) -> DataFrame:
    """(objective, k, terms) for each size k (a column of longs): ``term_count`` in columns."""
    terms = {"clique": "k * (k - 1) div 2", "star": "k - 1", "tree": "k - 1", "bipartition": "(k div 2) * (k - k div 2)"}
    each = F.explode(F.array(*(F.struct(F.lit(o).alias("objective"), F.expr(e).alias("terms")) for o, e in terms.items())))
    return sizes.select("k", each.alias("t")).select("t.objective", "k", "t.terms")


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)
