"""The relational operators that surround a selection. Everything is declared; Catalyst picks the physical plan, hints only say which strategy is meant."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from diversify.functions.metrics import SCALAR, squared

# Projections and filters.


def scale(df: DataFrame, cols: list[str], how: str = "unit") -> DataFrame:
    """Columns as shares of their range ('unit') or in deviations from their mean ('z')."""
    aggs = [f for c in cols for f in (F.min(c).alias(f"_lo_{c}"), F.max(c).alias(f"_hi_{c}"), F.avg(c).alias(f"_mean_{c}"), F.stddev_pop(c).alias(f"_dev_{c}"))]
    both = df.crossJoin(F.broadcast(df.agg(*aggs)))  # one row

    def scaled(c: str) -> Column:
        if how == "unit":
            return F.when(F.col(f"_hi_{c}") > F.col(f"_lo_{c}"), (F.col(c) - F.col(f"_lo_{c}")) / (F.col(f"_hi_{c}") - F.col(f"_lo_{c}"))).otherwise(0.0)
        return F.when(F.col(f"_dev_{c}") > 0, (F.col(c) - F.col(f"_mean_{c}")) / F.col(f"_dev_{c}")).otherwise(0.0)

    return both.select(*(scaled(c).alias(c) if c in cols else F.col(c) for c in df.columns))


def lattice(df: DataFrame, factors: dict[str, float]) -> DataFrame:
    return df.select(*(F.round(F.col(c) * factors[c]).cast("long").alias(c) if c in factors else F.col(c) for c in df.columns))


def collapse_duplicates(df: DataFrame, cols: list[str], id_col: str = "pid") -> DataFrame:
    return df.groupBy(*cols).agg(F.min(id_col).alias(id_col), F.count("*").alias("mult"))


def within_ball(df: DataFrame, center: dict[str, float], r: float) -> DataFrame:
    """Rows within r of a centre. The box around the ball is a filter on plain columns, which reaches the file scan."""
    box = F.lit(True)
    for c, x in center.items():
        box = box & F.col(c).between(x - r, x + r)
    return df.where(box).where(squared([F.col(c) for c in center], [F.lit(x) for x in center.values()]) <= r * r)


def min_words(counts: DataFrame, w: int = 10) -> DataFrame:
    return counts.groupBy("pid").agg(F.count("*").alias("words")).where(F.col("words") >= w)


def only_relevant(df: DataFrame, labels: DataFrame, on: str, cond: str) -> DataFrame:
    return df.join(labels.where(cond).select(on), on, "left_semi")


def json_filter(df: DataFrame, col: str, path: str, low: int) -> DataFrame:
    return df.where(F.get_json_object(col, path).try_cast("long") >= low)


# Joins.


def equi_join(a: DataFrame, b: DataFrame, on: str, how: str = "inner", strategy: str | None = None) -> DataFrame:
    """strategy: shuffle_hash, merge or broadcast; none leaves the choice to the optimizer."""
    return a.join(b.hint(strategy) if strategy else b, on, how)


def range_join(a: DataFrame, b: DataFrame, r: int, coords: list[str]) -> DataFrame:
    """(i, j, d) within r: cells of side r, each left row also looks into the neighbouring cells."""
    cell = lambda c: F.floor(F.col(c) / r).cast("long")
    left, right = a.select(F.col("pid").alias("i"), *(F.col(c).alias(f"i_{c}") for c in coords), *(cell(c).alias(f"_c{n}") for n, c in enumerate(coords))), b.select(F.col("pid").alias("j"), *(F.col(c).alias(f"j_{c}") for c in coords), *(cell(c).alias(f"_c{n}") for n, c in enumerate(coords)))
    for n in range(len(coords)):
        left = left.withColumn(f"_c{n}", F.explode(F.array(*(F.col(f"_c{n}") + s for s in (-1, 0, 1)))))
    q = squared([F.col(f"i_{c}") for c in coords], [F.col(f"j_{c}") for c in coords])
    return left.join(right, [f"_c{n}" for n in range(len(coords))]).where((q <= r * r) & (F.col("i") != F.col("j"))).select("i", "j", F.sqrt(q.cast("double")).alias("d"))


def members(df: DataFrame, sel: DataFrame, on: str = "pid") -> DataFrame:
    return df.join(sel.select(on), on, "left_semi")


def rest(df: DataFrame, sel: DataFrame, on: str = "pid") -> DataFrame:
    return df.join(sel.select(on), on, "left_anti")


def k_nearest(points: DataFrame, anchors: DataFrame, m: int, coords: list[str]) -> DataFrame:
    """(pid, anchor_pid, rank, dist) of each point's m nearest anchors. The anchors are a bounded selection: one array beside every point, no shuffle of points."""
    folded = anchors.agg(F.sort_array(F.collect_list(F.struct("pid", *coords))).alias("_anchors"))
    d = lambda a: SCALAR["euclid"]([F.col(c) for c in coords], [a[c] for c in coords])
    ranked = F.slice(F.array_sort(F.transform("_anchors", lambda a: F.struct(d(a).alias("dist"), a["pid"].alias("anchor_pid")))), 1, m)
    near = points.crossJoin(F.broadcast(folded)).select("pid", F.posexplode(ranked).alias("rank", "n"))  # one row
    return near.select("pid", "n.anchor_pid", F.col("rank").cast("long").alias("rank"), "n.dist")


def as_of(left: DataFrame, right: DataFrame, time: str, by: str, value: str) -> DataFrame:
    """``left`` with the value of ``right`` at the latest time up to each row's, by one pass over the union of both.

    Of several values at one time the largest counts, nulls only where there is no other; rows without a time or ``by`` match nothing.
    """
    latest = right.where(F.col(time).isNotNull() & F.col(by).isNotNull()).groupBy(time, by).agg(F.struct(F.max(value).alias("v")).alias("_v"))
    both = left.withColumn("_v", F.lit(None).cast(latest.schema["_v"].dataType)).withColumn("_r", F.lit(1)).unionByName(latest.withColumn("_r", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(time, "_r").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(w)["v"]).where("_r = 1").drop("_v", "_r")


def interval_join(a: DataFrame, b: DataFrame, seconds: int, by: str) -> DataFrame:
    """Pairs (i, j) of one ``by`` whose seconds ``s`` differ by at most ``seconds``, through buckets of that width."""
    left = a.select(F.col("pid").alias("i"), by, F.col("s").alias("si"), F.explode(F.array(*((F.floor(F.col("s") / seconds) + k).cast("long") for k in (-1, 0, 1)))).alias("_b"))
    right = b.select(F.col("pid").alias("j"), by, F.col("s").alias("sj"), F.floor(F.col("s") / seconds).cast("long").alias("_b"))
    return left.join(right, [by, "_b"]).where(F.abs(F.col("si") - F.col("sj")) <= seconds).select("i", "j", by)


# Aggregates, windows, order.


def distance_quantiles(pairs: DataFrame, qs: list[float]) -> DataFrame:
    return pairs.agg(F.percentile("d", qs).alias("v")).select(F.posexplode("v").alias("n", "value")).select(F.element_at(F.array(*map(F.lit, qs)), F.col("n") + 1).alias("q"), F.round("value", 6).alias("value"))


def cluster_histogram(assign: DataFrame, low: float, high: float, buckets: int) -> DataFrame:
    size = assign.groupBy("anchor_pid").agg(F.count("*").alias("n"))
    return size.groupBy(F.width_bucket("n", F.lit(low), F.lit(high), F.lit(buckets)).alias("bucket")).agg(F.count("*").alias("clusters"))


def cap_delegates(assign: DataFrame, cap: int) -> DataFrame:
    w = Window.partitionBy("anchor_pid").orderBy((F.col("pid") == F.col("anchor_pid")).desc(), "pid")
    return assign.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= cap)


def top_per_group(df: DataFrame, group: str, by: list[Column], n: int) -> DataFrame:
    return df.withColumn("rn", F.row_number().over(Window.partitionBy(group).orderBy(*by)).cast("long")).where(F.col("rn") <= n)
