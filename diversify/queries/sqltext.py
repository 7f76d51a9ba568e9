"""Oracle SQL for DuckDB, put together from common table expressions. It derives every answer anew from the tables."""

from __future__ import annotations

SUPPLIERS = "SELECT s_suppkey AS pid, round(s_acctbal)::BIGINT AS x, s_nationkey::BIGINT * 400 AS y, s_nationkey::BIGINT AS grp FROM supplier"
LATTICE = "SELECT DISTINCT round(l_quantity)::BIGINT * 10000 + round(l_discount * 100)::BIGINT * 100 + round(l_tax * 100)::BIGINT AS pid, round(l_quantity)::BIGINT AS x, 5 * round(l_discount * 100)::BIGINT AS y, 6 * round(l_tax * 100)::BIGINT AS z FROM lineitem"
PARTS = "SELECT p_partkey AS pid, p_size::BIGINT AS x, (round(p_retailprice * 10) - 9000)::BIGINT AS y, p_brand AS grp FROM part"
CUSTOMERS = "SELECT c_custkey AS pid, round(c_acctbal)::BIGINT AS x, c_nationkey::BIGINT AS grp FROM customer"
ORDERS = "SELECT o_orderkey AS pid, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::BIGINT AS x, round(o_totalprice / 100)::BIGINT AS y FROM orders"
EVENTS = "SELECT event_id AS pid, ts, floor((epoch_us(ts) - 1704067200000000) / 60000000)::BIGINT AS x, round(value * 10)::BIGINT AS y, event_type AS grp, user_id FROM events"
XY, XYZ = ("x", "y"), ("x", "y", "z")


def square(a: str, b: str, coords: tuple[str, ...]) -> str:
    return " + ".join(f"({a}.{c} - {b}.{c}) * ({a}.{c} - {b}.{c})" for c in coords)


def query(ctes: list[str], final: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + final


def cte(name: str, body: str) -> str:
    return f"{name} AS ({body})"


def parted(name: str, source: str, parts: int) -> str:
    return cte(name, f"SELECT *, pid % {parts} AS part_id FROM ({source})")


def farthest(name: str, points: str, m: int, coords: tuple[str, ...] = XY) -> str:
    """All points of ``points`` (part_id, pid, coords) at each step with the squared distance to, and the rank of, the nearest pick so far."""
    c = ", ".join(coords)
    fc = ", ".join(f"f.{x}" for x in coords)
    return f"""{name} AS (
    SELECT 0 AS step, p.part_id, p.pid, {", ".join("p." + x for x in coords)}, {square("p", "s", coords)} AS near, 0 AS owner, p.pid = s.pid AS picked, s.pid AS pick
    FROM {points} p JOIN (SELECT * FROM {points} QUALIFY row_number() OVER (PARTITION BY part_id ORDER BY pid) = 1) s ON s.part_id = p.part_id
    UNION ALL
    SELECT f.step + 1, f.part_id, f.pid, {fc}, least(f.near, {square("f", "c", coords)}),
           CASE WHEN f.pid = c.pid OR {square("f", "c", coords)} < f.near THEN f.step + 1 ELSE f.owner END, f.picked OR f.pid = c.pid, c.pid
    FROM {name} f JOIN (
        SELECT part_id, pid, {c} FROM (SELECT *, row_number() OVER (PARTITION BY part_id ORDER BY picked, near DESC, pid) AS rn FROM {name}) WHERE rn = 1 AND NOT picked
    ) c ON c.part_id = f.part_id
    WHERE f.step + 1 < {m}
)"""


def last(name: str) -> str:
    """The points of a traversal after its last pick."""
    return f"SELECT * FROM {name} QUALIFY step = max(step) OVER (PARTITION BY part_id)"


def chosen(name: str, traversal: str, coords: tuple[str, ...] = XY) -> str:
    """The picks of a traversal, with part_id 0."""
    return cte(name, f"SELECT 0 AS part_id, pid, {', '.join(coords)} FROM ({last(traversal)}) WHERE picked")


def with_delegates(name: str, traversal: str, cap: int, coords: tuple[str, ...] = XY) -> str:
    """Anchors and up to cap-1 members of each cluster by id, with part_id 0, anchor and own_part."""
    return cte(
        name,
        f"SELECT 0 AS part_id, own_part, anchor, pid, {', '.join(coords)} FROM (SELECT l.*, l.part_id AS own_part, a.pid AS anchor, row_number() OVER (PARTITION BY l.part_id, l.owner ORDER BY l.picked DESC, l.pid) AS rn "
        f"FROM ({last(traversal)}) l JOIN (SELECT part_id, owner, pid FROM ({last(traversal)}) WHERE picked) a ON a.part_id = l.part_id AND a.owner = l.owner) WHERE rn <= {cap}",
    )


def pairs(name: str, points: str, coords: tuple[str, ...] = XY) -> str:
    return cte(name, f"SELECT a.pid AS i, b.pid AS j, {square('a', 'b', coords)} AS q, sqrt(({square('a', 'b', coords)})::DOUBLE) AS d FROM {points} a JOIN {points} b ON a.pid < b.pid")


def matching(name: str, pair: str, points: str, k: int) -> str:
    """Ids of the heavy matching, as (pid)."""
    odd = f" UNION ALL SELECT min(pid) FROM {points}, (SELECT used FROM {name}_m ORDER BY step DESC LIMIT 1) WHERE NOT list_contains(used, pid)" if k % 2 else ""
    return f"""{name}_m AS (
    SELECT 0 AS step, []::BIGINT[] AS used
    UNION ALL
    SELECT step + 1, list_concat(used, [i, j]) FROM (
        SELECT m.step, m.used, p.i, p.j, row_number() OVER (ORDER BY p.q DESC, p.i, p.j) AS rn
        FROM {name}_m m JOIN {pair} p ON NOT list_contains(m.used, p.i) AND NOT list_contains(m.used, p.j) WHERE m.step < {k // 2}
    ) WHERE rn = 1
), {name}_ids AS (SELECT unnest(used) AS pid FROM (SELECT used FROM {name}_m ORDER BY step DESC LIMIT 1){odd}), {name} AS (SELECT p.* FROM {points} p JOIN {name}_ids USING (pid))"""


def measure(name: str, objective: str, sel: str, coords: tuple[str, ...] = XY, k: int = 8) -> list[str]:
    """Expressions whose last, ``name``, has the one value of a set ``sel`` (pid, coords) of k points."""
    p = f"{name}_p"
    out = [pairs(p, sel, coords)]
    both = f"(SELECT i, j, d FROM {p} UNION ALL SELECT j, i, d FROM {p})"
    if objective == "edge":
        return [*out, cte(name, f"SELECT coalesce(min(d), 0)::DOUBLE AS value FROM {p}")]
    if objective == "clique":
        return [*out, cte(name, f"SELECT coalesce(sum(d), 0)::DOUBLE AS value FROM {p}")]
    if objective == "star":
        return [*out, cte(name, f"SELECT coalesce(min(s), 0)::DOUBLE AS value FROM (SELECT i, sum(d) AS s FROM {both} GROUP BY i)")]
    rank = cte(f"{name}_r", f"SELECT pid, row_number() OVER (ORDER BY pid) - 1 AS r FROM {sel}")
    dist = cte(f"{name}_d", f"SELECT a.r AS a, b.r AS b, d FROM {both} e JOIN {name}_r a ON a.pid = e.i JOIN {name}_r b ON b.pid = e.j")
    out += [rank, dist]
    if objective == "bipartition":
        cut = f"SELECT m, sum(d) AS s FROM range({1 << k}) t(m), {name}_d WHERE bit_count(m) = {k // 2} AND a < b AND (m >> a) & 1 <> (m >> b) & 1 GROUP BY m"
        return [*out, cte(name, f"SELECT coalesce(min(s), 0)::DOUBLE AS value FROM ({cut})")]
    if objective == "tree":
        grow = f"""{name}_t AS (
    SELECT 1::BIGINT AS mask, 0::DOUBLE AS w, 1 AS n
    UNION ALL
    SELECT mask | (1::BIGINT << b), w + d, n + 1 FROM (
        SELECT t.mask, t.w, t.n, e.b, e.d, row_number() OVER (ORDER BY e.d, e.b) AS rn FROM {name}_t t JOIN {name}_d e ON (t.mask >> e.a) & 1 = 1 AND (t.mask >> e.b) & 1 = 0
    ) WHERE rn = 1
)"""
        return [*out, grow, cte(name, f"SELECT coalesce(max(w), 0)::DOUBLE AS value FROM {name}_t")]
    walk = f"""{name}_w AS (
    SELECT 1::BIGINT AS mask, 0::BIGINT AS here, 0::DOUBLE AS w
    UNION ALL
    SELECT mask | (1::BIGINT << b), b, w + d FROM {name}_w JOIN {name}_d ON a = here AND (mask >> b) & 1 = 0
)"""
    return [*out, walk, cte(name, f"SELECT coalesce(min(w + d), 0)::DOUBLE AS value FROM {name}_w JOIN {name}_d ON a = here AND b = 0 WHERE bit_count(mask) = (SELECT count(*) FROM {sel})")]


def solution(sel: str, value: str, objective: str) -> str:
    return f"SELECT pid, '{objective}' AS objective, round(value, 6) AS value FROM {sel}, {value}"


def counted(name: str, traversal: str, cap: int, coords: tuple[str, ...] = XY) -> str:
    """Anchors of all parts with the sizes of their clusters up to cap: (part_id 0, own_part, owner, pid, coords, mult)."""
    sizes = f"SELECT part_id, owner, count(*) AS n FROM ({last(traversal)}) GROUP BY part_id, owner"
    return cte(name, f"SELECT 0 AS part_id, a.part_id AS own_part, a.owner, a.pid, {', '.join('a.' + c for c in coords)}, least(n, {cap}) AS mult FROM ({last(traversal)}) a JOIN ({sizes}) s ON s.part_id = a.part_id AND s.owner = a.owner WHERE picked")


def solved_counts(name: str, objective: str, counts: str, k: int, coords: tuple[str, ...] = XY) -> list[str]:
    """A choice with copies: ``name`` (pid, take), ``name``_x its expansion, ``name``_v the value. Copies are points of their own at one place."""
    c = ", ".join(coords)
    if traversal_objective(objective):
        ranks = f"SELECT pid, min(step) AS r FROM {name}_f WHERE pid = pick GROUP BY pid"
        out = [
            farthest(f"{name}_f", counts, k, coords),
            cte(name, f"""SELECT pid, 1 + greatest(0, least(mult - 1, {k} - count(*) OVER () - coalesce(sum(mult - 1) OVER (ORDER BY r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)))::BIGINT AS take
    FROM {counts} JOIN ({ranks}) USING (pid)"""),
        ]
    else:
        out = [
            cte(f"{name}_c", f"SELECT pid * 1000 + unnest(range(1, mult + 1)) AS pid, {c} FROM {counts}"), pairs(f"{name}_q", f"{name}_c", coords),
            matching(f"{name}_s", f"{name}_q", f"{name}_c", k), cte(name, f"SELECT pid // 1000 AS pid, count(*) AS take FROM {name}_s GROUP BY 1"),
        ]
    out.append(cte(f"{name}_x", f"SELECT pid * 1000 + unnest(range(1, take + 1)) AS pid, {c} FROM {name} JOIN {counts} USING (pid)"))
    return [*out, *measure(f"{name}_v", objective, f"{name}_x", coords, k)]


def three_round(name: str, objective: str, source: str, k: int, m: int, parts: int, coords: tuple[str, ...] = XY) -> list[str]:
    """Counts from the parts, a choice with copies, members of the chosen anchors' own clusters: ``name`` and ``name``_v; ``name``_g_v has the value with copies."""
    ranked = (
        f"SELECT l.*, a.pid AS anchor, row_number() OVER (PARTITION BY l.part_id, l.owner ORDER BY l.picked DESC, l.pid) AS rn "
        f"FROM ({last(f'{name}_ff')}) l JOIN {name}_n a ON a.own_part = l.part_id AND a.owner = l.owner"
    )
    return [
        parted(f"{name}_pts", source, parts), farthest(f"{name}_ff", f"{name}_pts", m, coords), counted(f"{name}_n", f"{name}_ff", k, coords),
        *solved_counts(f"{name}_g", objective, f"{name}_n", k, coords),
        cte(name, f"SELECT 0 AS part_id, r.pid, {', '.join('r.' + c for c in coords)} FROM ({ranked}) r JOIN {name}_g g ON g.pid = r.anchor WHERE rn <= take"),
        *measure(f"{name}_v", objective, name, coords, k),
    ]


def searched(name: str, points: str, k: int, coords: tuple[str, ...] = XY) -> list[str]:
    """Local search for the sum of distances from the heavy matching: the best swap while it gains; ``name`` and ``name``_v."""
    both = f"SELECT i AS a, j AS b, d FROM {name}_q UNION ALL SELECT j, i, d FROM {name}_q"
    walk = f"""{name}_w AS (
    SELECT 0 AS step, (SELECT list(pid) FROM {name}_m0) AS chosen
    UNION ALL
    SELECT step + 1, list_append(list_filter(chosen, lambda p: p <> a), z) FROM (
        SELECT step, chosen, a, z, gain, row_number() OVER (ORDER BY gain DESC, a, z) AS rn FROM (
            SELECT w.step, w.chosen, o.a, o.z, n.total - c.total - o.d AS gain
            FROM {name}_w w
            JOIN (SELECT a, b AS z, d FROM ({both})) o ON list_contains(w.chosen, o.a) AND NOT list_contains(w.chosen, o.z)
            JOIN (SELECT e.a AS p, sum(e.d) AS total FROM ({both}) e, {name}_w w2 WHERE list_contains(w2.chosen, e.b) GROUP BY e.a) n ON n.p = o.z
            JOIN (SELECT e.a AS p, sum(e.d) AS total FROM ({both}) e, {name}_w w3 WHERE list_contains(w3.chosen, e.b) GROUP BY e.a) c ON c.p = o.a
        )
    ) WHERE rn = 1 AND gain > 1e-9
)"""
    found = f"SELECT p.* FROM {points} p JOIN (SELECT unnest(chosen) AS pid FROM (SELECT chosen FROM {name}_w ORDER BY step DESC LIMIT 1)) USING (pid)"
    return [pairs(f"{name}_q", points, coords), matching(f"{name}_m0", f"{name}_q", points, k), walk, cte(name, found), *measure(f"{name}_v", "clique", name, coords, k)]


def traversal_objective(objective: str) -> bool:
    return objective in ("edge", "tree", "cycle")


def solved(name: str, objective: str, union: str, k: int, coords: tuple[str, ...] = XY) -> list[str]:
    """The solver of an objective on ``union`` (part_id 0, pid, coords): expressions ``name`` and ``name``_v with the value."""
    if traversal_objective(objective):
        out = [farthest(f"{name}_f", union, k, coords), chosen(name, f"{name}_f", coords)]
    else:
        out = [pairs(f"{name}_q", union, coords), matching(name, f"{name}_q", union, k)]
    return [*out, *measure(f"{name}_v", objective, name, coords, k)]


def two_round(name: str, objective: str, source: str, k: int, m: int, parts: int, coords: tuple[str, ...] = XY, part: str | None = None, cap: int | None = None) -> list[str]:
    """Core-sets of parts and the solver on their union."""
    points = cte(f"{name}_pts", f"SELECT *, {part or f'pid % {parts}'} AS part_id FROM ({source})")
    out = [points, farthest(f"{name}_ff", f"{name}_pts", m, coords)]
    if objective in ("edge", "cycle"):
        out.append(chosen(f"{name}_u", f"{name}_ff", coords))
    else:
        out.append(with_delegates(f"{name}_u", f"{name}_ff", cap or k, coords))
    return [*out, *solved(name, objective, f"{name}_u", k, coords)]


def levels(name: str, source: str, m: int, cap: int, rows: int, coords: tuple[str, ...] = XY) -> list[str]:
    """Core-sets with delegates of core-sets until at most ``rows`` rows are left: ``name`` (part_id 0, pid, coords).

    One step makes a pick in each part, or after the last one deals the parts' anchors and delegates to the parts of the next level.
    """
    c, far = ", ".join(coords), square("f", "c", coords)
    start = f"-1 AS step, pid, {c}, 9223372036854775807 AS near, 0 AS owner, false AS picked"
    parts = f"greatest(1, ceil(n / {rows}.0))::BIGINT"
    md5 = "('0x' || substr(md5(pid::VARCHAR || ':' || (level + 1)::VARCHAR), 1, 8))::BIGINT"
    steps = f"""{name}_l AS (
    SELECT 0 AS level, pid % {parts} AS part_id, {start}, n <= {rows} AS final FROM (SELECT *, count(*) OVER () AS n FROM ({source}))
    UNION ALL
    SELECT * FROM (
        SELECT f.level, f.part_id, f.step + 1, f.pid, {", ".join("f." + x for x in coords)}, least(f.near, {far}),
               CASE WHEN f.pid = c.pid OR {far} < f.near THEN f.step + 1 ELSE f.owner END, f.picked OR coalesce(f.pid = c.pid, false), false
        FROM {name}_l f LEFT JOIN (
            SELECT part_id, pid, {c} FROM (SELECT *, row_number() OVER (PARTITION BY part_id ORDER BY picked, near DESC, pid) AS rn FROM {name}_l) WHERE rn = 1 AND NOT picked
        ) c ON c.part_id = f.part_id
        WHERE NOT f.final AND f.step + 1 < {m}
        UNION ALL
        SELECT level + 1, {md5} % {parts}, {start}, n <= {rows} FROM (
            SELECT *, count(*) OVER () AS n FROM (
                SELECT *, row_number() OVER (PARTITION BY part_id, owner ORDER BY picked DESC, pid) AS rn FROM {name}_l WHERE NOT final AND step + 1 = {m}
            ) WHERE rn <= {cap}
        )
    )
)"""
    return [steps, cte(name, f"SELECT 0 AS part_id, pid, {c} FROM {name}_l WHERE final")]


def sketch(name: str, source: str, m: int, k: int = 1, order: str = "pid") -> list[str]:
    """A fold of the doubling sketch over the points (pid, x, y) of ``source`` in their order; ``name`` is its last state.

    One step reads a point or merges. Kept points carry their host count; a merge folds the kept list into survivors and victims.
    """
    far = lambda a, b: f"({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y)"
    init = f"SELECT *, row_number() OVER (ORDER BY {order}) AS pos FROM ({source})"
    survivors = f"list_reduce(kept, lambda acc, e: CASE WHEN list_bool_or(list_transform(acc, lambda s: {far('s', 'e')} <= 4 * q)) THEN acc ELSE list_append(acc, e) END, []::STRUCT(pid BIGINT, x BIGINT, y BIGINT)[])"
    return [
        cte(f"{name}_in", init),
        f"""{name}_s AS (
    SELECT 0::BIGINT AS pos, 0::BIGINT AS phase, NULL::BIGINT AS q, []::STRUCT(pid BIGINT, x BIGINT, y BIGINT)[] AS kept, []::STRUCT(pid BIGINT, x BIGINT, y BIGINT)[] AS gone, false AS merging, NULL::BIGINT AS was_kept
    UNION ALL
    SELECT CASE WHEN merging THEN pos ELSE pos + 1 END,
           CASE WHEN merging AND len(left_) = len(kept) THEN phase + 1 WHEN NOT merging AND full_ THEN phase + 1 ELSE phase END,
           CASE WHEN merging AND len(left_) = len(kept) THEN 4 * q WHEN NOT merging AND full_ THEN CASE WHEN q IS NULL THEN first_q ELSE 4 * q END ELSE q END,
           CASE WHEN merging THEN left_ ELSE next_ END,
           CASE WHEN merging AND len(left_) < len(kept) THEN list_filter(kept, lambda e: NOT list_contains(list_transform(left_, lambda s: s.pid), e.pid)) ELSE gone END,
           CASE WHEN merging THEN len(left_) = len(kept) ELSE full_ END,
           CASE WHEN merging THEN len(kept) END
    FROM (
        SELECT *, len(next_) = {max(m, k) + 1} AND len(next_) > len(kept) AS full_,
               list_min(list_transform(range(1, len(next_)), lambda a: list_min(list_transform(range(a + 1, len(next_) + 1), lambda b: {far('next_[a]', 'next_[b]')})))) AS first_q
        FROM (
            SELECT s.*, CASE WHEN s.merging THEN {survivors} ELSE kept END AS left_,
                   CASE WHEN s.merging OR coalesce(list_min(list_transform(kept, lambda e: {far('e', 'p')})) <= 16 * coalesce(q, 0), false) THEN kept ELSE list_append(kept, {{'pid': p.pid, 'x': p.x, 'y': p.y}}) END AS next_
            FROM {name}_s s JOIN {name}_in p ON p.pos = CASE WHEN s.merging THEN 1 ELSE s.pos + 1 END
        )
    )
)""",
        cte(name, f"SELECT * FROM {name}_s WHERE NOT merging QUALIFY row_number() OVER (ORDER BY pos DESC, phase DESC, was_kept DESC NULLS LAST) = 1"),
    ]


def sketch_with_hosts(name: str, source: str, m: int, k: int, order: str = "pid") -> list[str]:
    """As ``sketch``, but kept points hold up to k points of their own, the first ones that joined them; ``name`` is the last state."""
    far = lambda a, b: f"({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y)"
    point = "STRUCT(pid BIGINT, x BIGINT, y BIGINT)"
    kept = f"STRUCT(pid BIGINT, x BIGINT, y BIGINT, held {point}[])"
    me = "{'pid': p.pid, 'x': p.x, 'y': p.y}"
    survivors = f"list_reduce(kept, lambda acc, e: CASE WHEN list_bool_or(list_transform(acc, lambda s: {far('s', 'e')} <= 4 * q)) THEN acc ELSE list_append(acc, e) END, []::{kept}[])"
    nearest = f"list_position(list_transform(left_, lambda s: {far('s', 'v')}), list_min(list_transform(left_, lambda s: {far('s', 'v')})))"
    gathered = f"flatten(list_transform(list_filter(gone_, lambda v: {nearest} = i), lambda v: v.held))"
    joined = f"list_transform(left_, lambda t, i: {{'pid': t.pid, 'x': t.x, 'y': t.y, 'held': list_concat(t.held, {gathered})[:{k}]}})"
    held = f"list_transform(kept, lambda e, i: CASE WHEN i = host AND len(e.held) < {k} THEN {{'pid': e.pid, 'x': e.x, 'y': e.y, 'held': list_append(e.held, {me})}} ELSE e END)"
    return [
        cte(f"{name}_in", f"SELECT *, row_number() OVER (ORDER BY {order}) AS pos FROM ({source})"),
        f"""{name}_s AS (
    SELECT 0::BIGINT AS pos, 0::BIGINT AS phase, NULL::BIGINT AS q, []::{kept}[] AS kept, false AS merging
    UNION ALL
    SELECT CASE WHEN merging THEN pos ELSE pos + 1 END,
           CASE WHEN merging AND len(left_) = len(kept) OR NOT merging AND full_ THEN phase + 1 ELSE phase END,
           CASE WHEN merging AND len(left_) = len(kept) THEN 4 * q WHEN NOT merging AND full_ THEN CASE WHEN q IS NULL THEN first_q ELSE 4 * q END ELSE q END,
           CASE WHEN NOT merging THEN next_ WHEN len(left_) = len(kept) THEN kept ELSE {joined} END,
           CASE WHEN merging THEN len(left_) = len(kept) ELSE full_ END
    FROM (
        SELECT *, len(next_) = {max(m, k) + 1} AND len(next_) > len(kept) AS full_, list_filter(kept, lambda e: NOT list_contains(list_transform(left_, lambda s: s.pid), e.pid)) AS gone_,
               CASE WHEN q IS NULL AND len(next_) = {max(m, k) + 1} THEN list_min(list_transform(range(1, len(next_)), lambda a: list_min(list_transform(range(a + 1, len(next_) + 1), lambda b: {far('next_[a]', 'next_[b]')})))) END AS first_q
        FROM (
            SELECT *, CASE WHEN merging THEN {survivors} ELSE kept END AS left_,
                   CASE WHEN merging THEN kept WHEN near IS NULL OR near > 16 * coalesce(q, 0) THEN list_append(kept, {{'pid': p.pid, 'x': p.x, 'y': p.y, 'held': [{me}]}}) ELSE {held} END AS next_
            FROM (
                SELECT *, list_position(list_transform(kept, lambda e: {far('e', 'p')}), near) AS host
                FROM (
                    SELECT s.*, {{'pid': i.pid, 'x': i.x, 'y': i.y}} AS p, list_min(list_transform(kept, lambda e: (e.x - i.x) * (e.x - i.x) + (e.y - i.y) * (e.y - i.y))) AS near
                    FROM {name}_s s JOIN {name}_in i ON i.pos = CASE WHEN s.merging THEN 1 ELSE s.pos + 1 END
                )
            )
        )
    )
)""",
        cte(name, f"SELECT * FROM {name}_s WHERE NOT merging QUALIFY row_number() OVER (ORDER BY pos DESC, phase DESC) = 1"),
        cte(f"{name}_h", f"SELECT anchor, h.pid AS pid, h.x AS x, h.y AS y FROM (SELECT e.pid AS anchor, unnest(e.held) AS h FROM (SELECT unnest(kept) AS e FROM {name}))"),
    ]


def angle_keys(words: str) -> list[str]:
    """From word counts wc (pid, term, cnt): vectors of ten words at least, and for each two that share a word one less the cosine, to 12 places."""
    return [
        words, cte("vec", "SELECT pid, sum(cnt * cnt) AS n FROM wc GROUP BY pid HAVING count(*) >= 10"), cte("big", "SELECT wc.* FROM wc JOIN vec USING (pid)"),
        "keys AS MATERIALIZED (SELECT i, j, 1 - round(dot / sqrt((a.n * b.n)::DOUBLE), 12) AS key FROM (SELECT a.pid AS i, b.pid AS j, sum(a.cnt * b.cnt)::BIGINT AS dot FROM big a JOIN big b ON a.term = b.term GROUP BY 1, 2) JOIN vec a ON a.pid = i JOIN vec b ON b.pid = j)",
    ]


def farthest_by_keys(name: str, points: str, m: int) -> str:
    """As ``farthest`` for points (part_id, pid) whose distances are in keys; what shares no word is at key 1."""
    return f"""{name} AS (
    SELECT 0 AS step, p.part_id, p.pid, coalesce(k.key, 1) AS near, p.pid = s.pid AS picked
    FROM {points} p JOIN (SELECT part_id, min(pid) AS pid FROM {points} GROUP BY 1) s ON s.part_id = p.part_id LEFT JOIN keys k ON k.i = s.pid AND k.j = p.pid
    UNION ALL
    SELECT f.step + 1, f.part_id, f.pid, least(f.near, coalesce(k.key, 1)), f.picked OR f.pid = c.pid
    FROM {name} f JOIN (
        SELECT part_id, pid FROM (SELECT *, row_number() OVER (PARTITION BY part_id ORDER BY picked, near DESC, pid) AS rn FROM {name}) WHERE rn = 1 AND NOT picked
    ) c ON c.part_id = f.part_id LEFT JOIN keys k ON k.i = c.pid AND k.j = f.pid
    WHERE f.step + 1 < {m}
)"""


def edge_by_keys(name: str, sel: str) -> str:
    return cte(name, f"SELECT min(acos(greatest(-1, least(1, 1 - coalesce(key, 1))))) AS value FROM {sel} a JOIN {sel} b ON a.pid < b.pid LEFT JOIN keys ON i = a.pid AND j = b.pid")


def two_round_by_keys(name: str, k: int, m: int, parts: int) -> list[str]:
    return [
        cte(f"{name}_pts", f"SELECT pid, pid % {parts} AS part_id FROM vec"), farthest_by_keys(f"{name}_ff", f"{name}_pts", m),
        cte(f"{name}_u", f"SELECT 0 AS part_id, pid FROM ({last(f'{name}_ff')}) WHERE picked"), farthest_by_keys(f"{name}_f", f"{name}_u", k),
        cte(name, f"SELECT pid FROM ({last(f'{name}_f')}) WHERE picked"), edge_by_keys(f"{name}_v", name),
    ]
