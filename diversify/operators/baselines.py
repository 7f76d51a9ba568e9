"""What the methods are compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.operators import coresets, measures, rounds, solvers
from diversify.operators.space import PointSpace, ranked


def blocked_stream(space: PointSpace, k: int, objective: str, n: int) -> DataFrame:
    """The earlier scheme: the stream in blocks of sqrt(k n) rows, a core-set of k rows of each, the solver on their union."""
    size = max(1, math.ceil(math.sqrt(k * n)))
    blocks = ranked(space.slim(), ("pid",)).withColumn("part_id", F.floor(F.col("_at") / size).cast("long")).select("pid", "v", "part_id")
    return solvers.solve(coresets.build(blocks, k, metric=space.metric), k, objective, space.metric)


def size_k_coreset(space: PointSpace, k: int, parts: int, objective: str) -> DataFrame:
    """Kernel size k, as for general metrics."""
    return rounds.two_round(space, k, k, parts, objective)


def sequential(space: PointSpace, k: int, objective: str) -> DataFrame:
    """The solver on everything, in one task."""
    return solvers.solve(space.slim(), k, objective, space.metric)


def best_known(space: PointSpace, k: int, objective: str, grid: list[tuple[int, int]]) -> DataFrame:
    """(parts, k_prime, value) of many large runs; the best is the numerator of ratios."""
    runs = [rounds.two_round(space, k, kp, parts, objective).agg(F.max("value").alias("value")).select(F.lit(parts).cast("long").alias("parts"), F.lit(kp).cast("long").alias("k_prime"), F.round("value", 6).alias("value")) for parts, kp in grid]
    return measures.union_all(runs)


def single_stream(space: PointSpace, k: int, k_prime: int = 2048, objective: str = "edge") -> DataFrame:
    return rounds.one_pass(space.slim(), k, k_prime, objective)


def adversarial(space: PointSpace, k: int, k_prime: int, parts: int, objective: str) -> DataFrame:
    """Each part is a region, so that no part sees the whole."""
    return rounds.two_round(space, k, k_prime, parts, objective, "region")


def shuffled(space: PointSpace, k: int, k_prime: int, parts: int, objective: str, seed: int = 0, mode: str = "keyed") -> DataFrame:
    """Parts by a random hash first."""
    return rounds.two_round(space, k, k_prime, parts, objective, mode, seed)


def uniform_sample(space: PointSpace, k: int) -> DataFrame:
    """(pid): k rows in the order of an arithmetic hash of the id."""
    return space.df.select("pid").orderBy((F.col("pid") * 2654435761) % 1000003, "pid").limit(k)


def local_search_coreset(space: PointSpace, k: int, parts: int) -> DataFrame:
    """For the sum of distances: local search in each part, then on the union."""
    own = solvers.solve(space.with_parts(parts), k, "clique", space.metric, "search", "part_id").select("pid", "v")
    return solvers.solve(own, k, "clique", space.metric, "search")


