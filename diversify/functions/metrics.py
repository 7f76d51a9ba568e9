"""Distances as columns. All are metrics; angular is the angle between vectors."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from diversify.operators.space import checkpoint


def _sum(columns: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, columns)


def squared(a: list[Column], b: list[Column]) -> Column:
    """Squared Euclid over scalar columns: exact on integers, within whole-stage code."""
    return _sum([(x - y) * (x - y) for x, y in zip(a, b, strict=True)])


def euclid(a: list[Column], b: list[Column]) -> Column:
    return F.sqrt(squared(a, b).cast("double"))


def manhattan(a: list[Column], b: list[Column]) -> Column:
    return _sum([F.abs(x - y) for x, y in zip(a, b, strict=True)]).cast("double")


def chebyshev(a: list[Column], b: list[Column]) -> Column:
    gaps = [F.abs(x - y) for x, y in zip(a, b, strict=True)]
    return (gaps[0] if len(gaps) == 1 else F.greatest(*gaps)).cast("double")


def micro(d: Column) -> Column:
    """A distance, zero to 9e12, to six digits as other engines round it; ``round`` goes through the text of each number."""
    return F.floor(d * 1e6 + 0.5).cast("double") / 1e6


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def euclid_arr(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def angle(cosine: Column) -> Column:
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cosine)))


def angular(a: Column, b: Column) -> Column:
    """The angle between dense arrays; null where one of them is zero."""
    norms = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(norms > 0, angle(dot(a, b) / norms))


def jaccard(a: Column, b: Column) -> Column:
    """1 - shared over all for arrays of distinct elements; two empty sets are equal."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, 0.0).otherwise(1 - F.size(F.array_intersect(a, b)) / union)


def sparse_dots(a: DataFrame, b: DataFrame) -> DataFrame:
    """(i, j, dot) of sparse vectors (pid, term, cnt) that share a term, by an inverted index."""
    left, right = (df.select(F.col("pid").alias(n), "term", F.col("cnt").alias(f"c{n}")) for df, n in ((a, "i"), (b, "j")))
    return left.join(right, "term").groupBy("i", "j").agg(F.sum(F.col("ci") * F.col("cj")).alias("dot"))


#: Strips into which sparse vectors are dealt, so that pairs of them keep several tasks busy; more where a strip had over ``STRIP_ROWS`` vectors.
STRIPS, STRIP_ROWS = 24, 4000


def _strips(w: DataFrame, vectors: int, block: int) -> DataFrame:
    """(own, pids, sizes, terms, cnts): the sparse vectors (pid, term, cnt) dealt by a hash of pid, a row for each strip, kept in the checkpoint folder."""
    n = max(1, min(-(-vectors // block), STRIPS), -(-vectors // STRIP_ROWS))
    dealt = w.where("pid IS NOT NULL").select(F.pmod(F.xxhash64("pid"), F.lit(n)).alias("own"), F.col("pid").cast("long").alias("pid"), F.col("term").cast("int").alias("term"), F.col("cnt").cast("int").alias("cnt"))

    def packed(t: pa.Table) -> pa.Table:
        pid, term, cnt = (t.column(c).to_numpy() for c in ("pid", "term", "cnt"))
        by = np.argsort(pid, kind="stable")
        pids, sizes = np.unique(pid, return_counts=True)
        return pa.table({"own": t.column("own")[:1], "pids": pa.array([pids]), "sizes": pa.array([sizes.astype(np.int32)]), "terms": pa.array([term[by]]), "cnts": pa.array([cnt[by]])})

    return checkpoint(dealt.groupBy("own").applyInArrow(packed, "own long, pids array<long>, sizes array<int>, terms array<int>, cnts array<int>")).coalesce(n)


def _sparse_pairs(w: DataFrame, vectors: int, block: int, finish: Callable[..., dict[str, np.ndarray]], columns: str) -> DataFrame:
    """(i, j) and ``columns``, which ``finish`` makes of dot products and squared norms, of all pairs i < j of sparse vectors that share a term.

    A task takes a strip and another one from the checkpoint folder, so each vector is written once, whatever the number of strips. Each pair of
    their blocks is one matrix product, so terms in every vector cost no more than others. Both the work and the result grow with the squared number.
    """
    strips = _strips(w, vectors, block)
    names = ("pids", "sizes", "terms", "cnts")
    left, right = (strips.select(F.col("own").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in names)) for s in "xy")

    few = max(1, block // 4)  # rows of the second side, as what a product takes along is several times its size

    def laid(side: tuple, at: int, most: int, used: np.ndarray, kind: type) -> np.ndarray:
        """A block's vectors as rows over the terms in use."""
        pids, starts, row, terms, cnts, _ = side
        some = slice(starts[at], starts[min(at + most, len(pids))])
        to = np.minimum(np.searchsorted(used, terms[some]), len(used) - 1)
        both = used[to] == terms[some]
        m = np.zeros((min(most, len(pids) - at), len(used)), kind)
        m[row[some][both] - at, to[both]] = cnts[some][both]
        return m

    def products(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            for r in range(t.num_rows):
                sides = []
                for s in "xy":
                    pids, sizes, terms, cnts = (t.column(f"{c}_{s}")[r].values.to_numpy() for c in names)
                    row = np.repeat(np.arange(len(pids)), sizes)
                    sides.append((pids, np.concatenate(([0], np.cumsum(sizes))), row, terms, cnts, np.bincount(row, cnts.astype(float) ** 2)))
                one, two = sides
                p, q, norms = one[0], two[0], (one[-1], two[-1])
                used = np.intersect1d(one[3], two[3])
                if not len(used):
                    continue
                # No part of a dot product exceeds the larger squared norm, and single precision holds integers to 2^24.
                kind = np.float32 if max(n.max() for n in norms) < 1 << 24 else np.float64
                same = t.column("x")[r] == t.column("y")[r]
                for a in range(0, len(p), block):
                    m = laid(one, a, block, used, kind)
                    for b in range(a if same else 0, len(q), few):
                        dot = m @ laid(two, b, few, used, kind).T
                        i, j = np.nonzero(np.triu(dot, a - b + 1) if same and b < a + block else dot)
                        dot, i, j = dot[i, j].astype(np.int64), i + a, j + b
                        i, j, ni, nj = p[i], q[j], norms[0][i], norms[1][j]
                        if not same:
                            turn = i > j
                            i, j, ni, nj = np.where(turn, j, i), np.where(turn, i, j), np.where(turn, nj, ni), np.where(turn, ni, nj)
                        yield pa.RecordBatch.from_pydict({"i": i, "j": j} | finish(dot, ni, nj))

    return left.join(right.hint("shuffle_replicate_nl"), F.col("x") <= F.col("y")).mapInArrow(products, f"i long, j long, {columns}")


def sparse_products(w: DataFrame, vectors: int, block: int = 1000) -> DataFrame:
    """(i, j, dot, ni, nj): dot products and squared norms of all pairs i < j of sparse vectors (pid, term, cnt) that share a term.

    ``vectors``, their number, sets the number of strips; a product is of ``block`` rows by a quarter of that. Sums of integers are exact below 2^53.
    """
    return _sparse_pairs(w, vectors, block, lambda dot, ni, nj: {"dot": dot, "ni": ni.astype(np.int64), "nj": nj.astype(np.int64)}, "dot long, ni long, nj long")


def sparse_angles(w: DataFrame, vectors: int, block: int = 1000) -> DataFrame:
    """(i, j, dot, d): as ``sparse_products``, with the angle to six digits in place of the norms."""
    return _sparse_pairs(w, vectors, block, lambda dot, ni, nj: {"dot": dot, "d": np.floor(np.arccos(np.minimum(1, dot / np.sqrt(ni * nj))) * 1e6 + 0.5) / 1e6}, "dot long, d double")


def dense_angles(e: DataFrame, by: str, block: int = 1000) -> DataFrame:
    """(i, j, d): the angle of each pair i < j of dense vectors (pid, v, ``by``) with the same ``by``; null where one is zero.

    A group is dealt in blocks of about ``block`` rows and each pair of blocks is one matrix product. The result grows with a group's squared size.
    """
    sizes = e.groupBy(F.col(by).alias("_by")).agg(F.ceil(F.count("*") / block).cast("int").alias("n"))
    own = e.join(sizes, F.col(by) == F.col("_by")).select(by, "pid", "v", "n", F.pmod(F.xxhash64("pid"), F.col("n")).cast("int").alias("own"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n") - 1))).select(by, F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own", "pid", "v")

    def angles(t: pa.Table) -> pa.Table:
        own, pid = t.column("own").to_numpy(), t.column("pid").to_numpy()
        v = np.asarray(t.column("v").combine_chunks().flatten(), float).reshape(len(pid), -1)
        norm = np.sqrt((v * v).sum(1))
        x, y = t.column("x")[0].as_py(), t.column("y")[0].as_py()
        a, b = np.flatnonzero(own == x), np.flatnonzero(own == y)
        if x == y:
            i, j = np.nonzero(pid[a][:, None] < pid[b])
        else:
            i, j = (m.ravel() for m in np.indices((len(a), len(b))))
        with np.errstate(divide="ignore", invalid="ignore"):
            d = np.arccos(np.clip((v[a] @ v[b].T)[i, j] / (norm[a][i] * norm[b][j]), -1, 1))
        i, j = a[i], b[j]
        none = (norm[i] == 0) | (norm[j] == 0)
        return pa.table({"i": np.minimum(pid[i], pid[j]), "j": np.maximum(pid[i], pid[j]), "d": pa.array(d, mask=none)})

    return dealt.groupBy(by, "x", "y").applyInArrow(angles, "i long, j long, d double")


def custom(fn: Callable[[np.ndarray, np.ndarray], float]) -> Callable[[Column, Column], Column]:
    """A user's metric over two array columns, in Arrow batches. It must be a metric; ``audit`` looks for broken triangles."""

    @F.pandas_udf("double")
    def distance(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(fn(np.asarray(x, float), np.asarray(y, float))) for x, y in zip(a, b, strict=True)])

    return distance


SCALAR = {"euclid": euclid, "manhattan": manhattan, "chebyshev": chebyshev}


def to_set(points: DataFrame, chosen: DataFrame, coords: list[str], metric: str = "euclid") -> DataFrame:
    """(pid, anchor_pid, dist): each point's nearest chosen one (ties to the smaller id). ``chosen`` is a solution or core-set, so it is broadcast."""
    own = chosen.select(F.col("pid").alias("anchor_pid"), *(F.col(c).alias(f"a_{c}") for c in coords))
    d = SCALAR[metric]([F.col(c) for c in coords], [F.col(f"a_{c}") for c in coords])
    near = points.crossJoin(F.broadcast(own)).groupBy("pid").agg(F.min(F.struct(d.alias("dist"), "anchor_pid")).alias("m"))
    return near.select("pid", "m.anchor_pid", "m.dist")


def audit(points: DataFrame, coords: list[str], metric: str = "euclid", block: int = 500) -> DataFrame:
    """(triples, violations) of the triangle inequality over all triples of distinct ids.

    Distances follow from positions, so each triple of positions is compared once and counts as often as there are rows at them. A group holds the
    distances of two blocks of positions to all; the work grows with the third power of the positions, not of the rows.
    """
    rows = points.where("pid IS NOT NULL")
    places = rows.groupBy(*coords).agg(F.min("pid").cast("long").alias("id"), F.count("*").alias("w"))
    blocks = max(1, -(-places.count() // block))
    a, b = (places.select(F.col("id").alias(m), F.col("w").alias(f"w{m}"), *(F.col(x).alias(f"{m}_{x}") for x in coords)) for m in "ab")
    d = SCALAR[metric]([F.col(f"a_{x}") for x in coords], [F.col(f"b_{x}") for x in coords])
    to = a.crossJoin(b).select("a", "wa", F.struct("b", "wb", d.cast("double").alias("d")).alias("e")).groupBy("a", "wa").agg(F.sort_array(F.collect_list("e")).alias("e"))
    own = to.select(F.pmod(F.xxhash64("a"), F.lit(blocks)).alias("own"), "a", "wa", F.col("e.b").alias("ids"), F.col("e.wb").alias("ws"), F.transform("e.d", lambda x: F.coalesce(x, F.lit(float("nan")))).alias("ds"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own", "a", "wa", "ids", "ws", "ds")

    def broken(t: pa.Table) -> pa.Table:
        x, y = t.column("x")[0].as_py(), t.column("y")[0].as_py()
        part, w = t.column("own").to_numpy(), t.column("wa").to_numpy()
        ids, ws = (np.asarray(t.column(c)[0].values) for c in ("ids", "ws"))
        far = np.asarray(t.column("ds").combine_chunks().flatten()).reshape(len(w), -1)
        at = np.searchsorted(ids, t.column("a").to_numpy())
        first, second = np.flatnonzero(part == x), np.flatnonzero(part == y)
        found = 0
        for i in first:
            some = second[at[second] >= at[i]] if x == y else second
            over = far[i, at[some], None] > far[i] + far[some] + 1e-9
            for j, c in zip(*np.nonzero(over), strict=True):
                b = some[j]
                pairs = int(w[i]) * (int(w[i]) - 1) // 2 if b == i else int(w[i]) * int(w[b])
                found += pairs * (int(ws[c]) - int(c == at[i]) - int(c == at[b]))
        return pa.table({"violations": pa.array([found], pa.int64())})

    count = rows.agg(F.expr("count(*) * (count(*) - 1) div 2 * (count(*) - 2)").alias("triples"))
    return count.crossJoin(dealt.groupBy("x", "y").applyInArrow(broken, "violations long").agg(F.coalesce(F.sum("violations"), F.lit(0)).cast("long").alias("violations")))
