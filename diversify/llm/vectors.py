"""Near copies among embeddings: a forest of random-projection trees with spill, exact cosines within the leaves.

A tree asks one random direction a level. A node splits at the median of its rows' projections; rows near the split go to both sides.
Node medians come from a bounded sample (SAMPLE rows by a hash of the id, fewer if they exceed SAMPLE_BYTES); where a node holds too few
sample rows, the level's overall median is its split. Every row is indexed. The number of levels follows the number of rows, the number of trees the loss that the
levels allow, so that a pair at the limit of 0.9 is found with probability RECALL at any size.

Equal vectors are one class and are compared once. A pair of classes that meets in several leaves is counted in the first of them only:
each row carries its leaves of all trees, so no pair is ever emitted. Leaves with too many classes are compared block against block.

Defined cases: null vectors, zero vectors and those with null or non-finite components link with nothing (also not with equal ones);
vectors of other lengths than most are compared with their own length only; repeated rows get a row each and count as that id once; other columns, the label among
them, are ignored. A null id is a row without links and without component.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint, table
from diversify.llm.links import components, local_components

LIMIT, RECALL = 0.9, 0.995
#: Rows of a leaf, share of the spread that spills, rows of the sample, least sample rows of a node with its own median, classes of a block.
LEAF, SPILL, SAMPLE, OWN_MEDIAN, BLOCK = 400, 0.16, 100_000, 32, 2000
#: Most bytes of the sample on the driver.
SAMPLE_BYTES = 64_000_000


def forest_shape(rows: int, dims: int, limit: float = LIMIT) -> tuple[int, int]:
    """(levels, trees). A split loses a pair at the limit if its projections lie beyond the spill on both sides."""
    levels = max(0, math.ceil(math.log2(max(rows, 1) / LEAF)))
    gap = math.sqrt(2 * (1 - limit))  # length of the difference; its projection has this over the spread of the data as deviation
    z = 2 * SPILL / gap
    beyond = gap * 2 * (math.exp(-z * z / 2) / math.sqrt(2 * math.pi) - z * 0.5 * math.erfc(z / math.sqrt(2)))
    kept = max(1e-3, 1 - beyond * 0.3989) ** levels
    return levels, 1 if levels == 0 else math.ceil(math.log(1 - RECALL) / math.log(1 - kept))


class Forest:
    """Directions and splits; ``leaves`` gives each row's leaf numbers over all trees."""

    def __init__(self, sample: np.ndarray, levels: int, trees: int, seed: int = 7):
        self.levels, self.trees = levels, trees
        dims = sample.shape[1]
        # A direction is the difference of two random sample rows, so that splits follow the data.
        rng = np.random.default_rng(seed)
        a, b = rng.integers(0, max(len(sample), 1), (2, levels * trees)) if len(sample) else (np.zeros(0, int),) * 2
        way = sample[a] - sample[b] if len(sample) else np.zeros((levels * trees, dims))
        way += 1e-3 * rng.standard_normal((levels * trees, dims)) + (np.abs(way).sum(1, keepdims=True) < 1e-9) * rng.standard_normal((levels * trees, dims))
        self.way = (way / np.linalg.norm(way, axis=1, keepdims=True)).T if levels else np.zeros((dims, 0))
        self.splits: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}  # by tree and level: nodes and their medians
        at = sample @ self.way
        self.spread = at.std(0) + 1e-12 if len(sample) else np.ones(levels * trees)
        self.middle = np.median(at, axis=0) if len(sample) else np.zeros(levels * trees)
        for t in range(trees):
            node = np.zeros(len(sample), np.int64)
            for level in range(levels):
                p = at[:, t * levels + level]
                order = np.lexsort((p, node))
                nodes, first, count = np.unique(node[order], return_index=True, return_counts=True)
                own = count >= OWN_MEDIAN
                self.splits[t, level] = nodes[own], p[order][first[own] + count[own] // 2]
                split = self._split(t, level, node)
                node = node * 2 + (p > split)

    def _split(self, t: int, level: int, node: np.ndarray) -> np.ndarray:
        nodes, medians = self.splits[t, level]
        split = np.full(len(node), self.middle[t * self.levels + level])
        if len(nodes):
            at = np.minimum(np.searchsorted(nodes, node), len(nodes) - 1)
            split = np.where(nodes[at] == node, medians[at], split)
        return split

    def leaves(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf); leaf numbers are unique over the trees."""
        at, rows, found = x @ self.way, [], []
        for t in range(self.trees):
            row, node = np.arange(len(x)), np.zeros(len(x), np.int64)
            for level in range(self.levels):
                k = t * self.levels + level
                p = at[row, k]
                split = self._split(t, level, node)
                spill = SPILL * self.spread[k]
                left, right = p <= split + spill, p > split - spill
                row, node = np.concatenate((row[left], row[right])), np.concatenate((node[left] * 2, node[right] * 2 + 1))
            rows.append(row)
            found.append(node + (t << self.levels))
        return np.concatenate(rows), np.concatenate(found)


def _matrix(column: pa.Array) -> np.ndarray:
    """Rows of a list column of equal lengths as doubles."""
    return np.asarray(column.flatten(), float).reshape(len(column), -1)


def classes(vectors: DataFrame) -> DataFrame:
    """(v, rep, n): the distinct comparable vectors, their smallest id and how many ids have them."""
    v = F.col("embedding").cast("array<double>")
    usable = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = vectors.where(F.col("vec_id").isNotNull() & usable).select("vec_id", F.transform(v, lambda x: F.when(x == 0, F.lit(0.0)).otherwise(x)).alias("v"))
    return rows.groupBy("v").agg(F.min("vec_id").alias("rep"), F.count_distinct("vec_id").alias("n"))


def _compare(ids: np.ndarray, n: np.ndarray, unit: np.ndarray, leaves: list[np.ndarray], leaf: int, block: tuple[np.ndarray, np.ndarray] | None):
    """Links of one leaf (or of two of its blocks): (id, linked vectors, id of the first of its component here)."""
    size = len(ids)
    root, links = np.arange(size), np.zeros(size, np.int64)
    # Leaves of both rows before this one: there the pair was counted. A matrix of earlier leaves makes the test a product.
    earlier = [x[x < leaf] for x in leaves]
    kinds, at = np.unique(np.concatenate([*earlier, np.zeros(0, np.int64)]), return_inverse=True)
    row = np.repeat(np.arange(size), [len(x) for x in earlier])
    for a in range(0, size, 512):
        part = slice(a, min(a + 512, size))
        close = unit[part] @ unit.T >= LIMIT
        close[np.arange(part.stop - a), np.arange(a, part.stop)] = False
        if block is not None:
            close &= block[0][part, None] != block[0][None, :] if block[1] else True
        i, j = np.nonzero(close)
        i += a
        differ = root[i] != root[j]
        if differ.any():
            root = local_components(size, root[i[differ]], root[j[differ]])[root]
        if len(kinds):
            seen = np.zeros(len(i), bool)
            inside = np.zeros((part.stop - a, len(kinds)), bool)
            mine = (row >= a) & (row < part.stop)
            inside[row[mine] - a, at[mine]] = True
            offset = np.concatenate(([0], np.cumsum([len(x) for x in earlier])))
            for k in range(max((len(x) for x in earlier), default=0)):
                has = offset[j] + k < offset[j + 1]
                seen[has] |= inside[i[has] - a, at[offset[j[has]] + k]]
            i, j = i[~seen], j[~seen]
        links += np.bincount(i, weights=n[j], minlength=size).astype(np.int64)
    return links, root


def near_vectors(vectors: DataFrame) -> DataFrame:
    """(vec_id, n_links, component_id) of every row of ``vectors`` (vec_id, embedding)."""
    found = checkpoint(classes(vectors))
    by_dims = {r.dims: r["count"] for r in found.groupBy(F.size("v").alias("dims")).count().collect()}
    edges, counts = [], []
    for dims in sorted(by_dims):  # usually one; a table has as many lengths as models made it
        e, c = _linked(found.where(F.size("v") == dims), by_dims[dims], dims)
        edges.append(e)
        counts.append(c)
    if not by_dims:
        return vectors.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    link = edges[0]
    count = counts[0]
    for e, c in zip(edges[1:], counts[1:], strict=True):
        link, count = link.unionByName(e), count.unionByName(c)
    part = components(link, "a", "b").withColumnRenamed("node", "rep")
    per_class = found.join(count.groupBy("rep").agg(F.sum("links").alias("links")), "rep", "left").join(part, "rep", "left")
    per_class = per_class.select("v", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).cast("long").alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    v = F.transform(F.col("embedding").cast("array<double>"), lambda x: F.when(x == 0, F.lit(0.0)).otherwise(x)).alias("v")
    rows = vectors.select("vec_id", v).join(per_class, "v", "left")
    linked = F.col("n_links").isNotNull() & F.col("vec_id").isNotNull()
    return rows.select("vec_id", F.when(linked, F.col("n_links")).otherwise(0).alias("n_links"), F.when(linked, F.col("component_id")).otherwise(F.col("vec_id")).alias("component_id"))


def _linked(found: DataFrame, rows: int, dims: int) -> tuple[DataFrame, DataFrame]:
    """Links between representatives and, by representative, the number of linked vectors of other classes."""
    levels, trees = forest_shape(rows, dims)
    x = np.zeros((0, dims))
    if levels:
        few = min(SAMPLE, SAMPLE_BYTES // (8 * dims) + 1)
        sample = found.where(F.pmod(F.xxhash64("rep"), F.lit(max(1, rows // (2 * few)))) == 0).orderBy(F.xxhash64("rep"), "rep").limit(few).select("v").toArrow()
        x = np.asarray(sample.column("v").combine_chunks().flatten(), float).reshape(-1, dims)
    forest = Forest(x / np.linalg.norm(x, axis=1, keepdims=True) if len(x) else x, levels, trees)

    def routed(batches):
        for batch in batches:
            x = _matrix(batch.column("v"))
            unit = x / np.linalg.norm(x, axis=1, keepdims=True)
            row, leaf = forest.leaves(unit)
            order = np.argsort(row, kind="stable")
            row, leaf = row[order], leaf[order]
            lists = pa.ListArray.from_arrays(np.searchsorted(row, np.arange(len(x) + 1)).astype(np.int32), pa.array(leaf))
            yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("n"), pa.array([r.tobytes() for r in unit], pa.binary()), lists], ["rep", "n", "unit", "leaves"])

    rep = dict(found.dtypes)["rep"]
    dealt = found.select("rep", "n", "v").mapInArrow(routed, f"rep {rep}, n long, unit binary, leaves array<long>").select("*", F.explode("leaves").alias("leaf"))
    sizes = dealt.groupBy("leaf").agg(F.count("*").alias("rows")).where(F.col("rows") > BLOCK)
    many = dealt.join(sizes, "leaf", "left")  # at most one row for every BLOCK rows; broadcast only if small
    blocks = F.ceil(F.coalesce("rows", F.lit(1)) / BLOCK).cast("int")
    own = F.pmod(F.xxhash64(F.lit("block"), "rep"), blocks).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda other: F.struct(F.least(F.col("own"), other).alias("low"), F.greatest(F.col("own"), other).alias("high")))
    tasks = many.withColumn("blocks", blocks).withColumn("own", own).select("rep", "n", "unit", "leaves", "leaf", "own", F.explode(pairs).alias("pair"))

    def compared(t: pa.Table) -> pa.Table:
        ids, n = t.column("rep").to_numpy(), t.column("n").to_numpy()
        unit = np.frombuffer(b"".join(t.column("unit").to_pylist()), float).reshape(len(ids), -1)
        order = np.argsort(ids, kind="stable")
        leaves = [np.asarray(x, np.int64) for x in t.column("leaves").to_pylist()]
        pair, own = t.column("pair")[0].as_py(), t.column("own").to_numpy()[order]
        links, root = _compare(ids[order], n[order], unit[order], [leaves[i] for i in order], t.column("leaf")[0].as_py(), (own, pair["low"] != pair["high"]))
        ids = ids[order]
        used = (links > 0) | (root != np.arange(len(ids)))
        return pa.table({"rep": ids[used], "first": ids[root[used]], "links": links[used]})

    kind = f"rep {rep}, first {rep}, links long"
    out = checkpoint(tasks.groupBy("leaf", "pair").applyInArrow(compared, kind))
    return out.where("rep <> first").select(F.col("rep").alias("a"), F.col("first").alias("b")), out.select("rep", "links")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_vectors(table(spark, sf_dir, "embeddings"))
    return found.select("vec_id", "n_links", "component_id", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)).alias("kept"))


QUERIES = {"op6_projection_forest": embeddings}
SQL: dict[str, str] = {}
