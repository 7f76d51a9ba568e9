"""Objectives, distances, kernels, solvers, methods and baselines on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from diversify.functions import metrics
from diversify.operators import baselines, coresets, measures, quality, rounds, solvers
from diversify.plans import params
from diversify.queries import sqltext as q
from diversify.queries.sqltext import LATTICE, PARTS, SUPPLIERS, XY, XYZ
from diversify.sources import tables

QUERIES: dict = {}
SQL: dict[str, str] = {}
K, M, L = 8, 16, 4
OBJECTIVES = ("edge", "clique", "star", "bipartition", "tree", "cycle")
SHORT = {"bipartition": "bip"}


def add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


def solution(df: DataFrame, objective: str) -> DataFrame:
    return df.select("pid", F.lit(objective).alias("objective"), F.round("value", 6).alias("value"))


def scalars(df: DataFrame, coords: tuple[str, ...]) -> DataFrame:
    """Rows (pid, v) with their coordinates as integer columns again."""
    return df.select("pid", *(F.col("v")[i].cast("long").alias(c) for i, c in enumerate(coords)))


def selection(spark, d, space=tables.parts, k: int = K) -> DataFrame:
    """The farthest-first choice of k points of a whole table."""
    s = space(spark, d)
    return scalars(solvers.solve(s.slim(), k, "edge"), s.coords)


PICKED = [q.parted("pts", PARTS, 1), q.farthest("ff", "pts", K), q.chosen("sel", "ff")]

# Measures of a choice, and of a choice with copies.
_MEASURES = {
    "edge": lambda s: measures.remote_edge(s, list(XY)), "clique": lambda s: measures.remote_clique(s, list(XY)), "star": lambda s: measures.remote_star(s, list(XY)),
    "bipartition": lambda s: measures.remote_bipartition(s, list(XY), K), "tree": lambda s: measures.remote_tree(s, list(XY)), "cycle": lambda s: measures.remote_cycle(s, list(XY)),
}
for _o in OBJECTIVES:
    add(f"m_{_o}", lambda spark, d, o=_o: _MEASURES[o](selection(spark, d)), q.query([*PICKED, *q.measure("v", _o, "sel", XY, K)], f"SELECT '{_o}' AS objective, round(value, 6) AS value FROM v"))
add("m_separation", lambda spark, d: measures.separation(selection(spark, d), list(XY)), q.query([*PICKED, *q.measure("v", "edge", "sel", XY, K)], "SELECT 'separation' AS objective, round(value, 6) AS value FROM v"))
add("m_radius", lambda spark, d: measures.covering_radius(tables.parts(spark, d).df, selection(spark, d), list(XY)), q.query(PICKED, "SELECT 'radius' AS objective, round(sqrt(max(near)::DOUBLE), 6) AS value FROM (" + q.last("ff") + ")"))
add("m_terms", lambda spark, d: measures.term_table(tables.read(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("k")).select("k").distinct()), """
SELECT o AS objective, k::BIGINT AS k, (CASE o WHEN 'clique' THEN k * (k - 1) // 2 WHEN 'bipartition' THEN (k // 2) * (k - k // 2) ELSE k - 1 END)::BIGINT AS terms
FROM (SELECT unnest(['clique', 'star', 'tree', 'bipartition']) AS o), (SELECT DISTINCT count(*) AS k FROM orders GROUP BY o_custkey)""")  # fmt: skip


def counted(spark, d, cap: int = 3) -> DataFrame:
    """The four anchors of the suppliers with counts up to ``cap``: (pid, x, y, mult)."""
    s = tables.suppliers(spark, d)
    c = coresets.build(s.with_parts(1), 4, "counts", cap)
    return c.select("pid", F.col("v")[0].cast("long").alias("x"), F.col("v")[1].cast("long").alias("y"), "mult")


COUNTED = [
    q.parted("pts", SUPPLIERS, 1), q.farthest("ff", "pts", 4),
    q.cte("cnt", f"SELECT a.pid, a.x, a.y, least(n, 3) AS mult FROM ({q.last('ff')}) a JOIN (SELECT owner, count(*) AS n FROM ({q.last('ff')}) GROUP BY owner) USING (owner) WHERE picked"),
    q.cte("sel", "SELECT pid * 1000 + unnest(range(1, mult + 1)) AS pid, x, y FROM cnt"),
]
for _o in ("clique", "star", "tree", "bipartition"):
    add(f"m_gen_{SHORT.get(_o, _o)}", lambda spark, d, o=_o: measures.generalized(counted(spark, d), list(XY), o, 12), q.query([*COUNTED, *q.measure("v", _o, "sel", XY, 12)], f"SELECT '{_o}' AS objective, round(value, 6) AS value FROM v"))

# Distances.
_SCALAR_SQL = {"euclid": "sqrt(((a.x - b.x) ** 2 + (a.y - b.y) ** 2)::DOUBLE)", "manhattan": "(abs(a.x - b.x) + abs(a.y - b.y))::DOUBLE", "chebyshev": "greatest(abs(a.x - b.x), abs(a.y - b.y))::DOUBLE"}
# Rows at one position are a class: pairs between the first rows of the classes, and each other row with its first one at distance zero.
_CLASSES = "c AS (SELECT *, min(pid) OVER (PARTITION BY x, y, CASE WHEN x IS NULL OR y IS NULL THEN pid END) AS first FROM p)"
for _n, _sql in _SCALAR_SQL.items():
    add(f"d_{_n}", lambda spark, d, n=_n: measures.class_pairs(tables.suppliers(spark, d).df, list(XY), n).select("i", "j", metrics.micro(F.col("d")).alias("d")), f"WITH p AS ({SUPPLIERS}), {_CLASSES}, f AS (SELECT * FROM c WHERE pid = first) SELECT a.pid AS i, b.pid AS j, round({_sql}, 6) AS d FROM f a JOIN f b ON a.pid < b.pid UNION ALL SELECT first, pid, 0 FROM c WHERE pid <> first")


def _dense_pairs(spark, d, distance) -> DataFrame:
    """Each label's vectors in pairs."""
    e = tables.embeddings(spark, d).df
    a, b = e.select(F.col("pid").alias("i"), F.col("v").alias("a"), "grp"), e.select(F.col("pid").alias("j"), F.col("v").alias("b"), "grp")
    return a.join(b, "grp").where("i < j").select("i", "j", F.round(distance(F.col("a"), F.col("b")), 6).alias("d"))


def _dense_angles(spark, d) -> DataFrame:
    """Each label's vectors in pairs, by matrix products where the vectors are whole and of one length."""
    e = tables.embeddings(spark, d).df
    odd = F.col("pid").isNull() | F.col("v").isNull() | F.coalesce(F.exists("v", lambda x: x.isNull()), F.lit(False))
    if e.agg((F.count_distinct(F.size("v")) <= 1) & (F.count_if(odd) == 0)).first()[0]:
        return metrics.dense_angles(e, "grp").select("i", "j", F.round("d", 6).alias("d"))
    return _dense_pairs(spark, d, metrics.angular)


_DENSE = "FROM (SELECT a.vec_id AS i, b.vec_id AS j, a.embedding::DOUBLE[] AS a, b.embedding::DOUBLE[] AS b FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id)"
add("d_euclid_arr", lambda spark, d: _dense_pairs(spark, d, metrics.euclid_arr), f"SELECT i, j, round(list_distance(a, b), 6) AS d {_DENSE}")
add("d_angular_dense", lambda spark, d: _dense_angles(spark, d), f"SELECT i, j, round(acos(greatest(-1, least(1, list_cosine_similarity(a, b)))), 6) AS d {_DENSE}")
add("d_custom", lambda spark, d: _dense_pairs(spark, d, metrics.custom(lambda x, y: float(abs(x - y).sum()))), f"SELECT i, j, round(list_sum(list_transform(list_zip(a, b), lambda z: abs(z[1] - z[2]))), 6) AS d {_DENSE}")


def _sets(spark, d) -> DataFrame:
    """Customers' nations as sets of market segments."""
    return tables.read(spark, d, "customer").groupBy(F.col("c_nationkey").cast("long").alias("pid")).agg(F.sort_array(F.collect_set(F.concat_ws("/", "c_mktsegment", F.floor(F.col("c_acctbal") / 500).cast("int").cast("string")))).alias("v"))


def jaccard(spark, d) -> DataFrame:
    s = _sets(spark, d)
    a, b = s.select(F.col("pid").alias("i"), F.col("v").alias("a")), s.select(F.col("pid").alias("j"), F.col("v").alias("b"))
    return a.join(b, F.expr("i < j")).select("i", "j", F.round(metrics.jaccard(F.col("a"), F.col("b")), 6).alias("d"))


add("d_jaccard", jaccard, """
WITH s AS (SELECT DISTINCT c_nationkey::BIGINT AS p, c_mktsegment || '/' || floor(c_acctbal / 500)::INT AS t FROM customer), n AS (SELECT p, count(*) AS n FROM s GROUP BY p),
shared AS (SELECT a.p AS i, b.p AS j, count(*) AS c FROM s a JOIN s b ON a.t = b.t AND a.p < b.p GROUP BY 1, 2)
SELECT a.p AS i, b.p AS j, round(1 - coalesce(c.c, 0)::DOUBLE / (a.n + b.n - coalesce(c.c, 0)), 6) AS d FROM n a JOIN n b ON a.p < b.p LEFT JOIN shared c ON c.i = a.p AND c.j = b.p""")  # fmt: skip


def sparse_angles(spark, d) -> DataFrame:
    """The dot product and the angle of pairs of documents over their words of document frequency 2 to 20 alone, as the SQL has it; ``whole_angles`` takes all words."""
    w = tables.word_counts(tables.read(spark, d, "documents"))
    rare = w.join(w.groupBy("term").agg(F.count("*").alias("df")).where("df BETWEEN 2 AND 20"), "term").select("pid", "term", "cnt")
    norm = rare.groupBy("pid").agg(F.sum(F.col("cnt") * F.col("cnt")).alias("n"))
    dots = metrics.sparse_dots(rare, rare).where("i < j")
    both = dots.join(norm.withColumnsRenamed({"pid": "i", "n": "ni"}), "i").join(norm.withColumnsRenamed({"pid": "j", "n": "nj"}), "j")
    return both.select("i", "j", "dot", F.round(metrics.angle(F.col("dot") / F.sqrt((F.col("ni") * F.col("nj")).cast("double"))), 6).alias("d"))


WORDS = "w AS (SELECT doc_id AS pid, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')) AS word FROM documents), vocab AS (SELECT word, count(*) AS n, row_number() OVER (ORDER BY count(*) DESC, word) - 1 AS term FROM w GROUP BY word QUALIFY term < 5000), wc AS (SELECT pid, term, count(*) AS cnt FROM w JOIN vocab USING (word) GROUP BY pid, term)"
add("d_angular_sparse", sparse_angles, f"""
WITH {WORDS}, r AS (SELECT pid, term, cnt FROM wc JOIN (SELECT term FROM wc GROUP BY term HAVING count(*) BETWEEN 2 AND 20) USING (term)), n AS (SELECT pid, sum(cnt * cnt) AS n FROM r GROUP BY pid),
dots AS (SELECT a.pid AS i, b.pid AS j, sum(a.cnt * b.cnt)::BIGINT AS dot FROM r a JOIN r b ON a.term = b.term AND a.pid < b.pid GROUP BY 1, 2)
SELECT i, j, dot, round(acos(least(1, dot / sqrt((a.n * b.n)::DOUBLE))), 6) AS d FROM dots JOIN n a ON a.pid = i JOIN n b ON b.pid = j""")  # fmt: skip


def whole_angles(spark, d) -> DataFrame:
    """The dot product and the angle of all pairs of documents that share a word, over all words of the vocabulary."""
    docs = tables.read(spark, d, "documents")
    return metrics.sparse_angles(tables.word_counts(docs), docs.count())


add("d_angular_sparse_whole", whole_angles, f"""
WITH {WORDS}, n AS (SELECT pid, sum(cnt * cnt) AS n FROM wc GROUP BY pid),
dots AS (SELECT a.pid AS i, b.pid AS j, sum(a.cnt * b.cnt)::BIGINT AS dot FROM wc a JOIN wc b ON a.term = b.term AND a.pid < b.pid GROUP BY 1, 2)
SELECT i, j, dot, round(acos(least(1, dot / sqrt((a.n * b.n)::DOUBLE))), 6) AS d FROM dots JOIN n a ON a.pid = i JOIN n b ON b.pid = j""")  # fmt: skip
add("d_to_set", lambda spark, d: metrics.to_set(tables.parts(spark, d).df, selection(spark, d), list(XY)).select("pid", "anchor_pid", F.round("dist", 6).alias("dist")), q.query(PICKED, f"SELECT p.pid, s.pid AS anchor_pid, round(sqrt(({q.square('p', 's', XY)})::DOUBLE), 6) AS dist FROM pts p, sel s QUALIFY row_number() OVER (PARTITION BY p.pid ORDER BY {q.square('p', 's', XY)}, s.pid) = 1"))
add("d_audit", lambda spark, d: metrics.audit(tables.suppliers(spark, d).df, list(XY)), f"WITH p AS ({SUPPLIERS}), e AS (SELECT a.pid AS a, b.pid AS b, {_SCALAR_SQL['euclid']} AS d FROM p a, p b WHERE a.pid <> b.pid) SELECT count(*) AS triples, count(*) FILTER (WHERE x.d > y.d + z.d + 1e-9) AS violations FROM e x JOIN e y ON y.a = x.a JOIN e z ON z.a = y.b AND z.b = x.b WHERE x.a < x.b")

# Kernels.
PARTS4 = [q.parted("pts", PARTS, 4), q.farthest("ff", "pts", 8)]


def _built(spark, d, kind: str, m: int = 8, cap: int = 1, parts: int = 4) -> DataFrame:
    return coresets.build(tables.parts(spark, d).with_parts(parts), m, kind, cap)


add("farthest_first_part", lambda spark, d: _built(spark, d, "anchors").select("part_id", "pick_rank", "pid", F.round("radius", 6).alias("radius")), q.query(PARTS4, "SELECT part_id::BIGINT AS part_id, step::BIGINT AS pick_rank, any_value(pick) AS pid, round(sqrt(max(near)::DOUBLE), 6) AS radius FROM ff GROUP BY part_id, step"))
_LATTICE_TRACE = [q.parted("pts", LATTICE, 1), q.farthest("ff", "pts", M, XYZ)]
_TRACE_SQL = q.query(_LATTICE_TRACE, "SELECT step::BIGINT AS pick_rank, any_value(pick) AS pid, round(sqrt(max(near)::DOUBLE), 6) AS radius FROM ff GROUP BY step")
add("farthest_first_global", lambda spark, d: coresets.farthest_first_frame(tables.lattice(spark, d), M).select("pick_rank", "pid", F.round("radius", 6).alias("radius")), _TRACE_SQL)
add("farthest_first_trace", lambda spark, d: coresets.build(tables.lattice(spark, d).with_parts(1), M).select("pick_rank", "pid", F.round("radius", 6).alias("radius")), _TRACE_SQL)
add("anchors_delegates", lambda spark, d: _built(spark, d, "delegates", 8, 5).select("part_id", "anchor_pid", "pid"), q.query([*PARTS4, q.with_delegates("dl", "ff", 5)], "SELECT own_part::BIGINT AS part_id, anchor AS anchor_pid, pid FROM dl"))
add("anchors_counts", lambda spark, d: _built(spark, d, "counts", 8, 20).select("part_id", "pid", "mult"), q.query(PARTS4, f"SELECT a.part_id::BIGINT AS part_id, a.pid, least(n, 20)::BIGINT AS mult FROM ({q.last('ff')}) a JOIN (SELECT part_id, owner, count(*) AS n FROM ({q.last('ff')}) GROUP BY part_id, owner) USING (part_id, owner) WHERE picked"))


def random_capped(spark, d) -> DataFrame:
    s = tables.parts(spark, d)
    return coresets.build(s.with_parts(4), 8, "delegates", coresets.random_cap(64, s.df.count(), 4)).select("part_id", "anchor_pid", "pid")


add("anchors_randcap", random_capped, q.query([*PARTS4, q.with_delegates("dl", "ff", 64), q.cte("cap", f"SELECT least(64, ceil(2 * greatest(ln(count(*)), 16))) AS c FROM ({PARTS})")], "SELECT own_part::BIGINT AS part_id, anchor AS anchor_pid, pid FROM (SELECT *, row_number() OVER (PARTITION BY own_part, anchor ORDER BY pid <> anchor, pid) AS rn FROM dl), cap WHERE rn <= c"))


def _stream(spark, d) -> DataFrame:
    return tables.parts(spark, d).slim().withColumn("part_id", F.lit(0).cast("long"))


add("doubling_sketch", lambda spark, d: coresets.sketch_stream(_stream(spark, d), 1, 8).select("pid", "is_filler", F.round("threshold", 6).alias("threshold")), q.query(q.sketch("sk", PARTS, 8), "SELECT unnest(list_transform(kept, lambda e: e.pid)) AS pid, false AS is_filler, round(sqrt(q::DOUBLE), 6) AS threshold FROM sk"))
add("doubling_filler", lambda spark, d: coresets.sketch_stream(_stream(spark, d), 8, 8).select("pid", "is_filler", F.round("threshold", 6).alias("threshold")), q.query(q.sketch("sk", PARTS, 8, 8), "SELECT unnest(list_transform(kept, lambda e: e.pid)) AS pid, false AS is_filler, round(sqrt(q::DOUBLE), 6) AS threshold FROM sk UNION ALL SELECT unnest(list_transform(gone[:greatest(8 - len(kept), 0)], lambda e: e.pid)), true, round(sqrt(q::DOUBLE), 6) FROM sk"))
add("doubling_phases", lambda spark, d: coresets.phase_log(_stream(spark, d), 1, 8).select("phase", F.round("threshold", 6).alias("threshold"), "kept", "removed"), q.query(q.sketch("sk", PARTS, 8), "SELECT phase - (len(kept) = was_kept)::BIGINT AS phase, round(sqrt((CASE WHEN len(kept) = was_kept THEN q / 4 ELSE q END)::DOUBLE), 6) AS threshold, len(kept)::BIGINT AS kept, was_kept - len(kept) AS removed FROM sk_s WHERE was_kept IS NOT NULL"))
add("doubling_delegates", lambda spark, d: coresets.sketch_stream(_stream(spark, d), 4, 8, "delegates").select("anchor_pid", "pid"), q.query(q.sketch_with_hosts("sk", PARTS, 8, 4), "SELECT anchor AS anchor_pid, pid FROM sk_h"))
add("doubling_counts", lambda spark, d: coresets.sketch_stream(_stream(spark, d), 20, 20, "counts").select("part_id", "pid", "mult"), q.query(q.sketch_with_hosts("sk", PARTS, 20, 20), "SELECT 0::BIGINT AS part_id, anchor AS pid, count(*) AS mult FROM sk_h GROUP BY anchor"))
add("sketch_partitions", lambda spark, d: coresets.sketch_splits(tables.lattice(spark, d), K, M).select("pid", "mult"))

# Solvers on a core-set of four parts, with and without counts; optima of each nation's suppliers.
UNION = [*PARTS4, q.chosen("u", "ff")]
for _o in OBJECTIVES:
    _n = SHORT.get(_o, _o)
    for _k in (4, 5) if _o == "clique" else (4,):
        add(f"solve_{_n}" + ("_odd" if _k % 2 else ""), lambda spark, d, o=_o, k=_k: solution(solvers.solve(_built(spark, d, "anchors"), k, o), o), q.query([*UNION, *q.solved("s", _o, "u", _k)], q.solution("s", "s_v", _o)))
    add(f"brute_{_n}", lambda spark, d, o=_o: solvers.solve(tables.suppliers(spark, d).slim("grp"), 3, o, how="brute", by="grp").groupBy("grp").agg(F.round(F.max("value"), 6).alias("value")).where("value IS NOT NULL"), None)
_BRUTE = {"edge": "least(ab, ac, bc)", "clique": "ab + ac + bc", "tree": "ab + ac + bc - greatest(ab, ac, bc)", "star": "least(ab + ac, ab + bc, ac + bc)", "cycle": "ab + ac + bc", "bipartition": "least(ab + ac, ab + bc, ac + bc)"}
for _o, _e in _BRUTE.items():
    _small = {"edge": "ab", "clique": "ab", "tree": "ab", "star": "ab", "cycle": "2 * ab", "bipartition": "ab"}[_o]
    SQL[f"brute_{SHORT.get(_o, _o)}"] = f"""
WITH p AS ({SUPPLIERS}), e AS (SELECT a.grp, a.pid AS i, b.pid AS j, {_SCALAR_SQL['euclid']} AS d FROM p a JOIN p b ON a.grp = b.grp AND a.pid < b.pid),
three AS (SELECT x.grp, x.d AS ab, y.d AS ac, z.d AS bc FROM e x JOIN e y ON y.i = x.i AND y.j > x.j JOIN e z ON z.i = x.j AND z.j = y.j),
two AS (SELECT grp, {_small} AS v FROM (SELECT grp, max(d) AS ab, count(*) AS n FROM e GROUP BY grp) WHERE n = 1), one AS (SELECT grp, 0.0::DOUBLE AS v FROM p GROUP BY grp HAVING count(*) = 1)
SELECT grp, round(max(v), 6) AS value FROM (SELECT grp, {_e} AS v FROM three UNION ALL SELECT * FROM two UNION ALL SELECT * FROM one) GROUP BY grp"""
for _o in ("tree", "clique", "star", "bipartition"):
    add(f"solve_mult_{SHORT.get(_o, _o)}", lambda spark, d, o=_o: solvers.solve_with_counts(_built(spark, d, "counts", 3, 4, 1), 8, o).select("pid", "mult", F.round("value", 6).alias("value")), q.query(
        [q.parted("pts", PARTS, 1), q.farthest("ff", "pts", 3), q.counted("n", "ff", 4), *q.solved_counts("s", _o, "n", 8)], "SELECT pid, take AS mult, round(value, 6) AS value FROM s, s_v"))
add("local_search", lambda spark, d: solution(solvers.solve(_built(spark, d, "anchors"), 6, "clique", how="search"), "clique"), q.query([*UNION, *q.searched("s", "u", 6)], q.solution("s", "s_v", "clique")))


def solver_table(spark, d) -> DataFrame:
    """The registry, with what each solver finds on the core-set of four parts and the most that an optimum of the core-set can be."""
    found = measures.union_all([solvers.solve(_built(spark, d, "anchors"), 4, o).agg(F.max("value").alias("value")).select(F.lit(o).alias("objective"), F.lit(f).alias("family"), F.lit(s).alias("solver"), F.lit(a).cast("long").alias("alpha"), "value") for o, (f, s, a) in params.REGISTRY.items()])
    return found.select("objective", "family", "solver", "alpha", F.round("value", 6).alias("value"), F.round(F.col("alpha") * F.col("value"), 6).alias("bound"))


add("solver_table", solver_table, q.query(
    [*UNION, *(c for o in OBJECTIVES for c in q.solved(f"s_{o}", o, "u", 4)), q.cte("found", " UNION ALL ".join(f"SELECT '{o}' AS objective, value FROM s_{o}_v" for o in OBJECTIVES))],
    "SELECT objective, family, solver, alpha, round(value, 6) AS value, round(alpha * value, 6) AS bound FROM (VALUES ('edge', 'loose', 'traversal', 2::BIGINT), ('cycle', 'loose', 'traversal', 3), ('clique', 'strict', 'matching', 2), ('star', 'strict', 'matching', 2), ('bipartition', 'strict', 'matching', 3), ('tree', 'strict', 'traversal', 4)) t(objective, family, solver, alpha) JOIN found USING (objective)"))

# Methods. With random keys and 16 points to choose, ln n delegates an anchor do, fewer than 16.
KEYED = f"('0x' || substr(md5(pid || ':0'), 1, 8))::BIGINT % {L}"
RANDOM_CAP = f"(SELECT least(16, ceil(greatest(ln(count(*)), 16 / {L})))::BIGINT FROM ({PARTS}))"


def random_rounds(space, objective: str) -> DataFrame:
    return rounds.two_round_random(space, 16, 16, L, objective, space.df.count(), mode="keyed", c=1.0)


for _o in OBJECTIVES:
    _n = SHORT.get(_o, _o)
    _space, _source, _coords = (tables.lattice, LATTICE, XYZ) if _o in ("edge", "cycle") else (tables.parts, PARTS, XY)
    add(f"mr2_{_n}", lambda spark, d, o=_o, s=_space: solution(rounds.two_round(s(spark, d), K, M if o in ("edge", "cycle") else 8, L, o), o), q.query(q.two_round("r", _o, _source, K, M if _o in ("edge", "cycle") else 8, L, _coords), q.solution("r", "r_v", _o)))
    add(f"stream1_{_n}", lambda spark, d, o=_o: solution(rounds.one_pass(tables.events(spark, d).slim("ts"), K, M, o, ("ts", "pid")), o))
    if params.strict(_o):
        SQL[f"stream1_{_n}"] = q.query([*q.sketch_with_hosts("sk", q.EVENTS, M, K, "ts, pid"), q.cte("u", "SELECT 0 AS part_id, pid, x, y FROM sk_h"), *q.solved("s", _o, "u", K)], q.solution("s", "s_v", _o))
        add(f"mr2r_{_n}", lambda spark, d, o=_o: solution(random_rounds(tables.parts(spark, d), o), o), q.query(q.two_round("r", _o, PARTS, 16, 16, L, XY, KEYED, RANDOM_CAP), q.solution("r", "r_v", _o)))
        add(f"mr3_{_n}", lambda spark, d, o=_o: solution(rounds.three_round(tables.parts(spark, d), K, 8, L, o), o), q.query(q.three_round("r", _o, PARTS, K, 8, L), q.solution("r", "r_v", _o)))
        add(f"stream2_{_n}", lambda spark, d, o=_o: solution(rounds.two_pass(tables.events(spark, d).slim("ts"), K, M, o, ("ts", "pid")), o))
for _o in ("edge", "cycle"):
    SQL[f"stream1_{_o}"] = q.query([*q.sketch("sk", q.EVENTS, M, K, "ts, pid"), q.cte("u", f"SELECT 0 AS part_id, e.pid, e.x, e.y FROM (SELECT unnest(list_concat(kept, gone[:greatest({K} - len(kept), 0)])) AS e FROM sk)"), *q.solved("s", _o, "u", K)], q.solution("s", "s_v", _o))
add("mr_splits_edge", lambda spark, d: solution(rounds.split_round(tables.lattice(spark, d), K, M, "edge"), "edge"))

# Levels of core-sets: the lattice's first level always fits, the parts take as many as they need; a table that fits has no level at all.
_LEVEL = lambda source, rows: f"pid % (SELECT greatest(1, ceil(count(*) / {rows}.0))::BIGINT FROM ({source}))"
add("mr_multi_edge", lambda spark, d: solution(rounds.multi_round(tables.lattice(spark, d), K, M, 600, "edge"), "edge"), q.query(q.two_round("r", "edge", LATTICE, K, M, 1, XYZ, _LEVEL(LATTICE, 600)), q.solution("r", "r_v", "edge")))
add("mr_multi_clique", lambda spark, d: solution(rounds.multi_round(tables.parts(spark, d), 4, 8, 800, "clique"), "clique"), q.query(
    [*q.levels("u", PARTS, 8, 4, 800), *q.solved("s", "clique", "u", 4)], q.solution("s", "s_v", "clique")))
_PLAN = "method string, objective string, alpha long, eps_inner double, k_prime double, parts long, cap long, local_rows double"
_LINES = "l_quantity IS NOT NULL AND l_discount IS NOT NULL AND l_tax IS NOT NULL"


def plan_table(spark, d) -> DataFrame:
    """The advised sizes of every method for the lines with a position."""
    n = tables.read(spark, d, "lineitem").where(_LINES).count()
    return spark.createDataFrame([tuple(r.values()) for r in params.table(n, 16)], _PLAN).withColumns({c: F.round(c, 3) for c in ("eps_inner", "k_prime", "local_rows")})


add("plan_table", plan_table, f"""
WITH objectives AS (SELECT * FROM (VALUES ('edge', false, 2::BIGINT), ('cycle', false, 3), ('clique', true, 2), ('star', true, 2), ('bipartition', true, 3), ('tree', true, 4)) t(objective, strict, alpha)),
methods AS (SELECT * FROM (VALUES ('stream1', 32, 64, false), ('stream2', NULL, 64, true), ('mr2', 8, 16, false), ('mr2r', 8, 16, false), ('mr3', NULL, 16, true), ('multi', 8, 16, false)) t(method, loose, tight, scaled)),
sizes AS (
    SELECT *, (CASE WHEN strict THEN tight ELSE loose END * CASE WHEN scaled THEN alpha ELSE 1 END / inner_) ** 3 * 16 AS kp, (SELECT count(*) FROM lineitem WHERE {_LINES})::DOUBLE AS n, CASE WHEN strict AND method IN ('mr2', 'multi', 'stream1') THEN 16 ELSE 1 END AS c0
    FROM (SELECT *, CASE method WHEN 'stream1' THEN 0.5::DOUBLE WHEN 'mr2' THEN 1 - 1 / (1 + 1.0::DOUBLE / alpha) WHEN 'mr2r' THEN 1 - 1 / (1 + 1.0::DOUBLE / alpha) WHEN 'multi' THEN 1 - 1 / (1 + 1.0::DOUBLE / (alpha * 3)) ELSE 1.0::DOUBLE / (alpha + 1) END AS inner_ FROM methods, objectives)
    WHERE strict OR loose IS NOT NULL
),
dealt AS (
    SELECT *, CASE WHEN starts_with(method, 'stream') THEN 1 WHEN method = 'mr2r' THEN greatest(1, floor(least(sqrt(n / (kp * ln(n))), n / (16 * kp)))) WHEN method = 'multi' THEN greatest(1, ceil(n / greatest(n ** (1 / 3.0::DOUBLE) * kp, 1)))
        ELSE greatest(1, floor(sqrt(n / (kp * CASE WHEN method = 'mr2' AND strict THEN 16 ELSE 1 END)))) END::BIGINT AS l FROM sizes
),
capped AS (SELECT *, CASE WHEN method = 'mr2r' AND strict THEN ceil(greatest(ln(n), 16.0 / l))::BIGINT ELSE c0::BIGINT END AS c FROM dealt)
SELECT method, objective, alpha, round(inner_, 3) AS eps_inner, round(kp, 3) AS k_prime, l AS parts, c AS cap,
       round(CASE WHEN starts_with(method, 'stream') THEN kp * c ELSE greatest(n / l, l * least(kp, n / l) * c) END, 3) AS local_rows
FROM capped""")

# Certificates.
add("cert_loose", lambda spark, d: quality.loose_certificate(tables.parts(spark, d).df, scalars(_built(spark, d, "anchors"), XY), list(XY), measures.remote_edge(scalars(solvers.solve(_built(spark, d, "anchors"), 4, "edge"), XY), list(XY))), q.query(
    [*UNION, *q.solved("s", "edge", "u", 4), q.cte("r", f"SELECT max(n) AS q FROM (SELECT p.pid, min({q.square('p', 'c', XY)}) AS n FROM pts p, u c GROUP BY p.pid)")],
    "SELECT round(sqrt(q::DOUBLE), 6) AS radius, round(value, 6) AS separation, round(2 * round(sqrt(q::DOUBLE), 6) / round(value, 6), 6) AS eps FROM r, s_v"))
add("cert_strict", lambda spark, d: quality.strict_certificate(solvers.solve(tables.suppliers(spark, d).slim(), K, "clique"), coresets.build(tables.suppliers(spark, d).with_parts(2), 8, "delegates", K), 4000.0))


def _enumerated(union: str, objective: str) -> str:
    return f"SELECT max({_BRUTE[objective]}) FROM (SELECT x.d AS ab, y.d AS ac, z.d AS bc FROM {union} x JOIN {union} y ON y.i = x.i AND y.j > x.j JOIN {union} z ON z.i = x.j AND z.j = y.j)"


add("beta_generalized", lambda spark, d: quality.beta_of_counts(tables.suppliers(spark, d), coresets.build(tables.suppliers(spark, d).with_parts(3), 4, "counts", 3), 3, "clique"), q.query(
    [q.parted("pts", SUPPLIERS, 3), q.farthest("ff", "pts", 4), q.pairs("all_", "pts"),
     q.cte("cnt", f"SELECT a.pid, a.x, a.y, least(n, 3) AS mult FROM ({q.last('ff')}) a JOIN (SELECT part_id, owner, count(*) AS n FROM ({q.last('ff')}) GROUP BY part_id, owner) USING (part_id, owner) WHERE picked"),
     q.cte("u", "SELECT pid * 1000 + unnest(range(1, mult + 1)) AS pid, x, y FROM cnt"), q.pairs("some_", "u")],
    f"SELECT 'clique' AS objective, round(a, 6) AS best, round(b, 6) AS in_core, round(a / b, 6) AS beta FROM (SELECT ({_enumerated('all_', 'clique')}) AS a, ({_enumerated('some_', 'clique')}) AS b)"))


def instantiation_gap(spark, d) -> DataFrame:
    """(objective, generalized, value, bound): what choosing members for copies costs, and the most it may."""
    s = tables.parts(spark, d)
    found = coresets.build(s.with_parts(1), 8, "counts", K)
    out = []
    for o in ("clique", "star", "tree", "bipartition"):
        general = solvers.solve_with_counts(found, K, o).agg(F.max("value").alias("g"))
        real = rounds.three_round(s, K, 8, 1, o).agg(F.max("value").alias("v"))
        reach = found.agg((2 * F.max("radius") * measures.term_count(o, K)).alias("bound"))
        out.append(general.crossJoin(real).crossJoin(reach).select(F.lit(o).alias("objective"), F.round("g", 6).alias("generalized"), F.round("v", 6).alias("value"), F.round("bound", 6).alias("bound"), (F.col("v") >= F.col("g") - F.col("bound")).alias("holds")))
    return measures.union_all(out)


_STRICT = ("clique", "star", "tree", "bipartition")
add("inst_gap", instantiation_gap, q.query(
    [c for o in _STRICT for c in q.three_round(o, o, PARTS, K, 8, 1)],
    " UNION ALL ".join(f"SELECT '{o}' AS objective, round(g.value, 6) AS generalized, round(v.value, 6) AS value, round(b, 6) AS bound, v.value >= g.value - b AS holds FROM {o}_g_v g, {o}_v v, "
        f"(SELECT 2 * sqrt(max(near)::DOUBLE) * {measures.term_count(o, K)} AS b FROM ({q.last(f'{o}_ff')}))" for o in _STRICT)))  # fmt: skip
add("dim_estimate", lambda spark, d: quality.doubling_estimate(coresets.build(tables.lattice(spark, d).with_parts(1), M)), q.query(_LATTICE_TRACE, "SELECT round(regr_slope(ln(step + 1), -ln(r)), 6) AS dimension, count(*) AS steps FROM (SELECT step, sqrt(max(near)::DOUBLE) AS r FROM ff GROUP BY step) WHERE r > 0"))
for _name, _parts in (("beta_exact", 1), ("beta_composable", 3)):
    add(_name, lambda spark, d, p=_parts: quality.beta(tables.suppliers(spark, d), coresets.build(tables.suppliers(spark, d).with_parts(p), 6), 3, "edge"), q.query(
        [q.parted("pts", SUPPLIERS, _parts), q.farthest("ff", "pts", 6), q.chosen("u", "ff"), q.pairs("all_", "pts"), q.pairs("some_", "u")],
        f"SELECT 'edge' AS objective, round(a, 6) AS best, round(b, 6) AS in_core, round(a / b, 6) AS beta FROM (SELECT ({_enumerated('all_', 'edge')}) AS a, ({_enumerated('some_', 'edge')}) AS b)"))


# Baselines.
def blocked(spark, d) -> DataFrame:
    s = tables.parts(spark, d)
    return solution(baselines.blocked_stream(s, 4, "edge", s.df.count()), "edge")


add("base_blocked", blocked, q.query(q.two_round("r", "edge", f"SELECT *, floor((row_number() OVER (ORDER BY pid) - 1) / ceil(sqrt(4 * count(*) OVER ())))::BIGINT AS blk FROM ({PARTS})", 4, 4, 1, XY, "blk"), q.solution("r", "r_v", "edge")))
add("base_kprime_eq_k", lambda spark, d: solution(baselines.size_k_coreset(tables.lattice(spark, d), K, L, "edge"), "edge"), q.query(q.two_round("r", "edge", LATTICE, K, K, L, XYZ), q.solution("r", "r_v", "edge")))
add("base_sequential_edge", lambda spark, d: solution(baselines.sequential(tables.lattice(spark, d), K, "edge"), "edge"), q.query([q.parted("pts", LATTICE, 1), *q.solved("s", "edge", "pts", K, XYZ)], q.solution("s", "s_v", "edge")))
add("base_sequential_clique", lambda spark, d: solution(baselines.sequential(tables.suppliers(spark, d), 6, "clique"), "clique"), q.query([q.parted("pts", SUPPLIERS, 1), *q.solved("s", "clique", "pts", 6)], q.solution("s", "s_v", "clique")))
GRID = [(2, 8), (4, 16), (8, 16), (16, 32)]
add("base_reference", lambda spark, d: baselines.best_known(tables.lattice(spark, d), K, "edge", GRID), q.query([c for p, m in GRID for c in q.two_round(f"r{p}", "edge", LATTICE, K, m, p, XYZ)], " UNION ALL ".join(f"SELECT {p}::BIGINT AS parts, {m}::BIGINT AS k_prime, round(value, 6) AS value FROM r{p}_v" for p, m in GRID)))
add("base_single_stream", lambda spark, d: solution(baselines.single_stream(tables.lattice(spark, d), K, 2048), "edge"))
add("base_adversarial", lambda spark, d: solution(baselines.adversarial(tables.lattice(spark, d), K, M, L, "edge"), "edge"), q.query(q.two_round("r", "edge", LATTICE, K, M, L, XYZ, f"ntile({L}) OVER (ORDER BY x, y, z, pid)"), q.solution("r", "r_v", "edge")))
add("base_shuffled", lambda spark, d: solution(baselines.shuffled(tables.lattice(spark, d), K, M, L, "edge"), "edge"), q.query(q.two_round("r", "edge", LATTICE, K, M, L, XYZ, KEYED), q.solution("r", "r_v", "edge")))
add("base_random", lambda spark, d: baselines.uniform_sample(tables.parts(spark, d), K), f"SELECT p_partkey AS pid FROM part ORDER BY (p_partkey * 2654435761) % 1000003, p_partkey LIMIT {K}")


def local_search_sql(name: str, k: int, parts: int) -> list[str]:
    """Local search in each part of the suppliers, then on the union."""
    own = [c for p in range(parts) for c in (q.cte(f"{name}_p{p}", f"SELECT 0 AS part_id, pid, x, y FROM ({SUPPLIERS}) WHERE pid % {parts} = {p}"), *q.searched(f"{name}_l{p}", f"{name}_p{p}", k))]
    return [*own, q.cte(f"{name}_u", " UNION ALL ".join(f"SELECT * FROM {name}_l{p}" for p in range(parts))), *q.searched(name, f"{name}_u", k)]


add("base_local_search", lambda spark, d: solution(baselines.local_search_coreset(tables.suppliers(spark, d), 6, 2), "clique"), q.query(local_search_sql("s", 6, 2), q.solution("s", "s_v", "clique")))
