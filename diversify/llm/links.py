"""Connected components of a graph that no machine can hold: alternating stars, with a checkpoint after each round."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint


def components(edges: DataFrame, a: str, b: str) -> DataFrame:
    """(node, component): for every node of ``edges`` the smallest node that its links reach.

    Each round points every node at the smallest node near it, first from the larger neighbours, then among the smaller ones; the number
    of rounds follows the logarithm of the longest chain. Only minima by node are aggregated, with partial sums before the
    shuffle, so a hub with a third of all links needs no task that holds them together.
    """
    now = checkpoint(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct())
    before = None
    while (mark := now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()) != before:
        before = mark
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("w"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("w").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("w"))
        small = large.join(least, "u")
        stars = small.where("v <> w").select(F.col("v").alias("u"), F.col("w").alias("v")).unionByName(least.select("u", F.col("w").alias("v")))
        now = checkpoint(stars.distinct())
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)


def local_components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For 0..n-1 the smallest index that the links a-b reach; in one task."""
    root = np.arange(n)
    while len(a):
        ra, rb = root[a], root[b]
        low, high = np.minimum(ra, rb), np.maximum(ra, rb)
        np.minimum.at(root, high, low)
        while not np.array_equal(up := root[root], root):
            root = up
        differ = root[a] != root[b]
        a, b = a[differ], b[differ]
    return root
