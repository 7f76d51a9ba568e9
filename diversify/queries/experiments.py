"""Cost and accuracy measures, the experiment workloads on the given tables, and the motivating uses."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.operators import baselines, coresets, measures, quality, relational, rounds, solvers
from diversify.operators.space import PointSpace
from diversify.queries import sqltext as q
from diversify.queries.methods import K, OBJECTIVES, WORDS, local_search_sql, solution
from diversify.queries.sqltext import LATTICE, PARTS, SUPPLIERS, XY, XYZ
from diversify.sources import tables

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


def run_value(df: DataFrame, **labels: int | str) -> DataFrame:
    """One row of a grid: the labels and the value of a solution."""
    names = [F.lit(v).cast("long").alias(n) if isinstance(v, int) else F.lit(v).alias(n) for n, v in labels.items()]
    return df.agg(F.round(F.max("value"), 6).alias("value")).select(*names, "value")


def with_ratio(grid: DataFrame, by: str | None = None) -> DataFrame:
    """The grid with reference, its best value (per ``by``), and the ratio of reference to value."""
    best = grid.groupBy(by).agg(F.max("value").alias("reference")) if by else grid.agg(F.max("value").alias("reference"))
    joined = grid.join(F.broadcast(best), by) if by else grid.crossJoin(F.broadcast(best))  # a row for each run at most
    return joined.withColumn("ratio", F.round(F.col("reference") / F.col("value"), 6))


def grid_sql(runs: list[tuple[str, list[str], str]], by: str = "") -> str:
    """runs: name of the value expression, its expressions, labels as SQL."""
    rows = " UNION ALL ".join(f"SELECT {labels}, round(value, 6) AS value FROM {name}" for name, _, labels in runs)
    over = f"OVER (PARTITION BY {by})" if by else "OVER ()"
    return q.query([*(c for _, ctes, _ in runs for c in ctes), q.cte("g", rows)], f"SELECT *, max(value) {over} AS reference, round(max(value) {over} / value, 6) AS ratio FROM g")


# Measures.
add("mem_points", lambda spark, d: coresets.sketch_stream(tables.parts(spark, d).slim().withColumn("part_id", F.lit(0).cast("long")), 1, 16).agg(F.count("*").alias("points_held"), F.max("phase").alias("phase")), q.query(q.sketch("sk", PARTS, 16), "SELECT len(kept)::BIGINT AS points_held, phase FROM sk"))
add("mem_local", lambda spark, d: quality.local_memory(tables.lattice(spark, d).with_parts(8), coresets.build(tables.lattice(spark, d).with_parts(8), 16)), f"WITH p AS ({LATTICE}), n AS (SELECT pid % 8 AS part, count(*) AS n FROM p GROUP BY 1) SELECT 'part' AS role, max(n) AS largest, sum(n)::BIGINT AS total FROM n UNION ALL SELECT 'union', sum(least(n, 16))::BIGINT, sum(least(n, 16))::BIGINT FROM n")
add("coreset_size", lambda spark, d: coresets.build(tables.parts(spark, d).with_parts(4), 8, "counts", 20).groupBy("part_id").agg(F.count("*").alias("size"), F.sum("mult").alias("expanded")), q.query([q.parted("pts", PARTS, 4), q.farthest("ff", "pts", 8)], f"SELECT part_id::BIGINT AS part_id, count(*) AS size, sum(least(n, 20))::BIGINT AS expanded FROM (SELECT part_id, owner, count(*) AS n FROM ({q.last('ff')}) GROUP BY part_id, owner) GROUP BY part_id"))
add("work_per_part", lambda spark, d: quality.work(tables.lattice(spark, d).with_parts(8), 16), f"SELECT pid % 8 AS part_id, count(*) AS rows, count(*) * least(16, count(*)) AS evaluations FROM ({LATTICE}) GROUP BY 1")

# Parallel runs on the lattice.
PARALLEL = [(kp, parts) for kp in (16, 32) for parts in (2, 4, 8)]


def parallel_runs(space: PointSpace, k: int, grid: list[tuple[int, int]], mode: str = "mod") -> DataFrame:
    return measures.union_all([run_value(rounds.two_round(space, k, kp, parts, "edge", mode), k_prime=kp, parts=parts) for kp, parts in grid])


def _parallel_sql(grid: list[tuple[int, int]], k: int = 16) -> str:
    return grid_sql([(f"r{kp}_{p}_v", q.two_round(f"r{kp}_{p}", "edge", LATTICE, k, kp, p, XYZ), f"{kp}::BIGINT AS k_prime, {p}::BIGINT AS parts") for kp, p in grid])


add("exp_mr_r3", lambda spark, d: with_ratio(parallel_runs(tables.lattice(spark, d), 16, PARALLEL)), _parallel_sql(PARALLEL))
BUDGET = [(64, 2), (32, 4), (16, 8)]
add("exp_mr_budget", lambda spark, d: with_ratio(parallel_runs(tables.lattice(spark, d), 16, BUDGET)), _parallel_sql(BUDGET))


def seeds(spark, d) -> DataFrame:
    """Ten partitions of the lattice, each a run for two kernel sizes; mean, best and worst ratio by kernel size."""
    rows, out = tables.lattice(spark, d).slim(), []
    for kp in (8, 16):
        for seed in range(10):
            parted = rows.withColumn("part_id", F.pmod(F.floor(F.col("pid") / (seed + 1)), F.lit(4)).cast("long"))
            out.append(run_value(solvers.solve(coresets.build(parted, kp), K, "edge"), k_prime=kp, seed=seed))
    return measures.union_all(out)


_SEEDS = [(f"s{kp}_{s}", q.two_round(f"s{kp}_{s}", "edge", LATTICE, K, kp, 4, XYZ, f"floor(pid / {s + 1})::BIGINT % 4"), kp, s) for kp in (8, 16) for s in range(10)]
_SEED_ROWS = " UNION ALL ".join(f"SELECT {kp}::BIGINT AS k_prime, {s}::BIGINT AS seed, round(value, 6) AS value FROM {n}_v" for n, _, kp, s in _SEEDS)
_SEED_CTES = [c for _, ctes, _, _ in _SEEDS for c in ctes]
add("exp_seeds", lambda spark, d: with_ratio(seeds(spark, d)), q.query([*_SEED_CTES, q.cte("g", _SEED_ROWS)], "SELECT *, max(value) OVER () AS reference, round(max(value) OVER () / value, 6) AS ratio FROM g"))
add("ratio_grid", lambda spark, d: quality.ratio(seeds(spark, d), ["k_prime"]), q.query([*_SEED_CTES, q.cte("g", _SEED_ROWS), q.cte("h", "SELECT k_prime, max(value) OVER () / value AS r FROM g")], "SELECT k_prime, round(avg(r), 6) AS mean_ratio, round(min(r), 6) AS best_ratio, round(max(r), 6) AS worst_ratio, count(*) AS runs FROM h GROUP BY k_prime"))


def adversarial(spark, d) -> DataFrame:
    s = tables.lattice(spark, d)
    return measures.union_all([run_value(rounds.two_round(s, 16, kp, 4, "edge", m), layout=m, k_prime=kp) for m in ("mod", "region") for kp in (16, 32)])


add("exp_adversarial", lambda spark, d: with_ratio(adversarial(spark, d)), grid_sql([(f"a{m}{kp}_v", q.two_round(f"a{m}{kp}", "edge", LATTICE, 16, kp, 4, XYZ, None if m == "mod" else "ntile(4) OVER (ORDER BY x, y, z, pid)"), f"'{m}' AS layout, {kp}::BIGINT AS k_prime") for m in ("mod", "region") for kp in (16, 32)]))
add("exp_all_objectives", lambda spark, d: measures.union_all([run_value(rounds.two_round(tables.parts(spark, d), k, 8, 4, o), objective=o, k=k) for o in OBJECTIVES for k in (4, 8)]), q.query(
    [c for o in OBJECTIVES for k in (4, 8) for c in q.two_round(f"{o}{k}", o, PARTS, k, 8, 4)], " UNION ALL ".join(f"SELECT '{o}' AS objective, {k}::BIGINT AS k, round(value, 6) AS value FROM {o}{k}_v" for o in OBJECTIVES for k in (4, 8))))


def stream_r3(spark, d) -> DataFrame:
    """One pass over the lattice, k' linear in k."""
    rows = tables.lattice(spark, d).slim()
    runs = [run_value(rounds.one_pass(rows, k, kp, "edge"), k=k, k_prime=kp) for k in (8, 32) for kp in (k, k + k // 2, 2 * k, 2 * k + k // 2)]
    return with_ratio(measures.union_all(runs), "k")


add("exp_stream_r3", stream_r3)


# Customers as points of the unit ball: SEEDS clouds by remainder of the id, a run on each for every size.
FAR, SEEDS = 128, 10


def clouds(spark, d) -> DataFrame:
    """(seed, pid, v): ids differ between the clouds, so that they can be run side by side."""
    return tables.customer_ball(spark, d).select(F.pmod("pid", F.lit(SEEDS)).alias("seed"), "pid", F.array("x", "y", "z").alias("v"))


def by_seed(core: DataFrame) -> DataFrame:
    """(seed, value) of the solver on each seed's core-set."""
    return solvers.solve(core.select("seed", "pid", "v"), FAR, "edge", by="seed").groupBy("seed").agg(F.max("value").alias("value"))


def ratios(runs: list[DataFrame], by: list[str]) -> DataFrame:
    """Mean, best and worst ratio of the best value of a cloud to those of the runs on it."""
    every = measures.union_all(runs)
    best = every.groupBy("seed").agg(F.max("value").alias("reference"))
    each = every.join(F.broadcast(best), "seed").withColumn("r", F.col("reference") / F.col("value"))  # SEEDS rows
    return each.groupBy(*by).agg(F.round(F.avg("r"), 6).alias("mean_ratio"), F.round(F.min("r"), 6).alias("best_ratio"), F.round(F.max("r"), 6).alias("worst_ratio"), F.count("*").alias("runs"))


def labelled(df: DataFrame, **labels: int | str) -> DataFrame:
    return df.withColumns({n: F.lit(v).cast("long") if isinstance(v, int) else F.lit(v) for n, v in labels.items()})


def stream_cloud(spark, d) -> DataFrame:
    """One pass over each cloud, k' linear in k."""
    rows = clouds(spark, d)
    runs = [labelled(by_seed(coresets.sketch_stream(rows, FAR, kp, part="seed").withColumnRenamed("part_id", "seed")), k_prime=kp) for kp in (128, 192, 256, 320)]
    return ratios(runs, ["k_prime"])


def parted_cloud(spark, d, parts: int, kp: int, layout: str = "random") -> DataFrame:
    """Two rounds over each cloud; regions are sectors around an axis, so no part sees the whole."""
    rows = clouds(spark, d)
    turn = (F.atan2(F.col("v")[1], F.col("v")[0]) + F.lit(math.pi)) / F.lit(2 * math.pi)
    part = F.pmod(F.xxhash64("pid"), F.lit(parts)) if layout == "random" else F.least(F.floor(turn * parts), F.lit(parts - 1))
    core = coresets.build(rows.withColumn("part_id", F.col("seed") * parts + part.cast("long")), kp)
    return by_seed(core.withColumn("seed", F.floor(F.col("part_id") / parts)))


def parallel_cloud(spark, d) -> DataFrame:
    return ratios([labelled(parted_cloud(spark, d, p, kp), k_prime=kp, parts=p) for kp in (128, 256, 512) for p in (2, 8)], ["k_prime", "parts"])


def adversarial_cloud(spark, d) -> DataFrame:
    return ratios([labelled(parted_cloud(spark, d, 4, kp, layout), layout=layout, k_prime=kp) for layout in ("random", "region") for kp in (128, 256)], ["layout", "k_prime"])


add("exp_stream_cloud", stream_cloud)
add("exp_mr_cloud", parallel_cloud)
add("exp_adversarial_cloud", adversarial_cloud)


def texts(spark, d) -> PointSpace:
    return tables.word_vectors(tables.read(spark, d, "documents"))


def parallel_text(spark, d) -> DataFrame:
    """Two rounds over word vectors by angle, a run of both rounds for each size and number of parts."""
    s = texts(spark, d).kept()
    return with_ratio(measures.union_all([run_value(rounds.two_round(s, 8, kp, parts, "edge", scans=True), k_prime=kp, parts=parts) for kp in (8, 16) for parts in (2, 4)]))


_TEXT = [(kp, p) for kp in (8, 16) for p in (2, 4)]
_TEXT_ROWS = " UNION ALL ".join(f"SELECT {kp}::BIGINT AS k_prime, {p}::BIGINT AS parts, round(value, 6) AS value FROM t{kp}_{p}_v" for kp, p in _TEXT)
add("exp_mr_text", parallel_text, q.query(
    [*q.angle_keys(WORDS), *(c for kp, p in _TEXT for c in q.two_round_by_keys(f"t{kp}_{p}", 8, kp, p)), q.cte("g", _TEXT_ROWS)],
    "SELECT *, max(value) OVER () AS reference, round(max(value) OVER () / value, 6) AS ratio FROM g"))


def stream_text(spark, d) -> DataFrame:
    """One pass over word vectors by angle in the order of ids, k' geometric in k."""
    rows = texts(spark, d).slim()
    runs = [run_value(rounds.one_pass(rows, k, k * f, "edge", metric="sparse"), k=k, k_prime=k * f) for k in (8, 16) for f in (1, 2, 4)]
    return with_ratio(measures.union_all(runs), "k")


add("exp_stream_text", stream_text)


def compared(spark, d) -> DataFrame:
    """The sum of distances by the baselines and the methods."""
    s = tables.suppliers(spark, d)
    n = s.df.count()
    out = []
    for k in (4, 6, 8):
        out += [
            run_value(baselines.sequential(s, k, "clique"), method="sequential", k=k), run_value(baselines.blocked_stream(s, k, "clique", n), method="blocked", k=k),
            run_value(baselines.size_k_coreset(s, k, 2, "clique"), method="kprime_k", k=k), run_value(baselines.local_search_coreset(s, k, 2), method="local_search", k=k),
            run_value(rounds.two_round(s, k, 2 * k, 2, "clique"), method="two_round", k=k), run_value(rounds.three_round(s, k, 2 * k, 2, "clique"), method="three_round", k=k),
        ]
    return with_ratio(measures.union_all(out), "k")


_BLOCK = lambda k: f"SELECT *, floor((row_number() OVER (ORDER BY pid) - 1) / ceil(sqrt({k} * count(*) OVER ())))::BIGINT AS blk FROM ({SUPPLIERS})"
_COMPARED = [
    (f"{m}{k}_v", ctes, f"'{label}' AS method, {k}::BIGINT AS k") for k in (4, 6, 8) for m, label, ctes in (
        ("sq", "sequential", [q.parted(f"sq{k}_p", SUPPLIERS, 1), *q.solved(f"sq{k}", "clique", f"sq{k}_p", k)]),
        ("bl", "blocked", [q.cte(f"bl{k}_p", f"SELECT *, blk AS part_id FROM ({_BLOCK(k)})"), q.farthest(f"bl{k}_f", f"bl{k}_p", k), q.chosen(f"bl{k}_u", f"bl{k}_f"), *q.solved(f"bl{k}", "clique", f"bl{k}_u", k)]),
        ("kk", "kprime_k", q.two_round(f"kk{k}", "clique", SUPPLIERS, k, k, 2)), ("ls", "local_search", local_search_sql(f"ls{k}", k, 2)),
        ("tw", "two_round", q.two_round(f"tw{k}", "clique", SUPPLIERS, k, 2 * k, 2)), ("th", "three_round", q.three_round(f"th{k}", "clique", SUPPLIERS, k, 2 * k, 2)),
    )
]
add("exp_baselines", compared, grid_sql(_COMPARED, "k"))


# Uses.
def search(spark, d) -> DataFrame:
    """Good documents, the 200 nearest to the benchmark's words, of these ten far apart."""
    docs = tables.read(spark, d, "documents")
    good = relational.only_relevant(docs, tables.read(spark, d, "labels"), "doc_id", "quality = 1")
    counts = tables.word_counts(docs)
    wanted = tables.read(spark, d, "benchmark").select(F.explode_outer(tables.letter_runs("text")).alias("word")).groupBy("word").agg(F.count("*").alias("w"))
    terms = wanted.join(F.broadcast(tables.vocabulary(docs)), "word").select("term", "w")  # at most the vocabulary's size
    score = counts.join(F.broadcast(terms), "term").join(good.select(F.col("doc_id").alias("pid")), "pid", "left_semi").groupBy("pid").agg(F.sum(F.col("cnt") * F.col("w")).alias("score"))
    top = score.orderBy(F.desc("score"), "pid").limit(200)
    vectors = tables.word_vectors(docs).df.join(top, "pid", "left_semi")
    return solution(solvers.solve(PointSpace(vectors, ("v",), "sparse").slim(), 10, "edge", "sparse"), "edge")


add("app_search", search, q.query([
    *q.angle_keys(WORDS), q.cte("wanted", "SELECT term, count(*) AS weight FROM (SELECT unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')) AS word FROM benchmark) JOIN vocab USING (word) GROUP BY term"),
    q.cte("top", "SELECT pid, sum(cnt * weight) AS score FROM wc JOIN wanted USING (term) WHERE pid IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY pid ORDER BY score DESC, pid LIMIT 200"),
    q.cte("pts", "SELECT 0 AS part_id, pid FROM top JOIN vec USING (pid)"), q.farthest_by_keys("ff", "pts", 10), q.cte("sel", f"SELECT pid FROM ({q.last('ff')}) WHERE picked"), q.edge_by_keys("sel_v", "sel"),
], q.solution("sel", "sel_v", "edge")))
add("app_products", lambda spark, d: solution(rounds.two_round(PointSpace(tables.parts(spark, d).df.where("y BETWEEN 200 AND 1500"), XY), 10, 16, 4, "edge"), "edge"), q.query(q.two_round("r", "edge", f"SELECT * FROM ({PARTS}) WHERE y BETWEEN 200 AND 1500", 10, 16, 4), q.solution("r", "r_v", "edge")))


def sites(spark, d) -> DataFrame:
    """Three sites of each region, as far apart as farthest-first finds them."""
    n = tables.read(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("grp"), F.col("n_regionkey").cast("long").alias("region"))
    s = tables.suppliers(spark, d).df.join(F.broadcast(n), "grp")  # nations
    return solvers.solve(PointSpace(s, XY).slim("region"), 3, "edge", by="region").select("region", "pid", F.round("value", 6).alias("value"))


add("app_sites", sites, q.query(
    [q.cte("pts", f"SELECT s.*, n_regionkey::BIGINT AS part_id FROM ({SUPPLIERS}) s JOIN nation ON n_nationkey = grp"), q.farthest("ff", "pts", 3), q.cte("c", f"SELECT part_id AS region, pid, x, y FROM ({q.last('ff')}) WHERE picked"),
     q.cte("v", f"SELECT a.region, min(sqrt(({q.square('a', 'b', XY)})::DOUBLE)) AS value FROM c a JOIN c b ON a.region = b.region AND a.pid < b.pid GROUP BY 1")],
    "SELECT region, pid, round(coalesce(value, 0), 6) AS value FROM c LEFT JOIN v USING (region)"))
