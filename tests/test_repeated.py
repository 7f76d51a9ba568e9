"""Queries against their oracles on tables that are larger or less regular than the given ones: repeated with shifted keys, with ties."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from diversify import queries
from diversify.functions import metrics
from diversify.operators import measures, rounds, solvers
from diversify.queries import sqltext
from diversify.sources import tables

DIR = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test tables here")


def view(con, folder):
    for t in os.listdir(folder):
        con.execute(f"CREATE OR REPLACE VIEW {t[:-8]} AS SELECT * FROM '{folder}/{t}'")
    return con


def folder(tmp_path, **made):
    """The given tables, those in ``made`` replaced by what their SQL gives."""
    con = view(duckdb.connect(), DIR)
    for t in os.listdir(DIR):
        if t[:-8] in made:
            con.execute(f"COPY ({made[t[:-8]]}) TO '{tmp_path}/{t}' (FORMAT parquet)")
        else:
            os.symlink(f"{DIR}/{t}", f"{tmp_path}/{t}")
    return str(tmp_path)


def times(table, key, n, **more):
    """SQL of a table ``n`` times with shifted keys; ``more`` replaces columns, with r for the turn."""
    other = "".join(f", {e} AS {c}" for c, e in more.items())
    return f"SELECT * REPLACE ({key} + r * (SELECT max({key}) + 1 FROM {table}) AS {key}{other}) FROM {table}, range({n}) t(r)"


def plain(x):
    return round(x, 6) if isinstance(x, float) else x


def agree(spark, name, where):
    found = queries.QUERIES[name](spark, where)
    columns = sorted(found.columns)
    rel = view(duckdb.connect(), where).execute(queries.SQL[name])
    names = [c[0] for c in rel.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    want = sorted(repr(tuple(plain(r[i]) for i in at)) for r in rel.fetchall())
    assert sorted(repr(tuple(plain(r[c]) for c in columns)) for r in found.collect()) == want


def test_groups_that_do_not_fit_after_two_levels(spark, tmp_path):
    agree(spark, "a_group_rounds", folder(tmp_path, customer="SELECT * REPLACE (c_custkey + r * 1000 AS c_custkey, c_nationkey % 2 AS c_nationkey, c_acctbal + r * 7.0 AS c_acctbal) FROM customer, range(24) t(r)"))


def test_levels_of_a_strict_objective_follow_the_oracle(spark, tmp_path):
    agree(spark, "mr_multi_clique", folder(tmp_path, part=times("part", "p_partkey", 130)))


def test_levels_go_on_until_the_union_fits(spark, tmp_path, monkeypatch):
    where, solved, solve = folder(tmp_path, part=times("part", "p_partkey", 130)), [], solvers.solve
    monkeypatch.setattr(solvers, "solve", lambda rows, *a, **b: (solved.append(rows.count()), solve(rows, *a, **b))[1])
    agree(spark, "mr_multi_clique", where)
    assert len(solved) == 1 and solved[0] <= 800 < 26_000 / 800 * 32


@pytest.mark.parametrize("n", [2, 13])
def test_many_levels_follow_the_oracle(spark, tmp_path, n):
    where = folder(tmp_path, part=times("part", "p_partkey", n))
    sql = sqltext.query([*sqltext.levels("u", sqltext.PARTS, 8, 4, 70), *sqltext.solved("s", "clique", "u", 4)], sqltext.solution("s", "s_v", "clique"))
    want = view(duckdb.connect(), where).execute(sql).fetchall()
    found = rounds.multi_round(tables.parts(spark, where), 4, 8, 70, "clique").collect()
    assert sorted((r.pid, round(r.value, 6)) for r in found) == sorted((pid, value) for pid, _, value in want)


def test_as_of_takes_the_largest_of_one_second_and_keeps_nulls(spark, tmp_path):
    made = """SELECT event_id * 8 + r AS event_id, to_timestamp(1704067200 + (event_id % 40) * 10)::TIMESTAMP AS ts, CASE WHEN event_id % 9 = 0 THEN NULL ELSE event_id % 5 END AS user_id,
        event_type, CASE WHEN event_id % 40 % 7 = 3 THEN NULL ELSE value + (r * 37 + event_id * 11) % 100 END AS value, props FROM events, range(8) t(r)"""
    agree(spark, "j_asof", folder(tmp_path, events=made))


def test_audit_of_copies(spark, tmp_path):
    agree(spark, "d_audit", folder(tmp_path, supplier=times("supplier", "s_suppkey", 6)))


@pytest.mark.parametrize("name", ["d_euclid", "d_manhattan", "d_chebyshev"])
def test_copies_are_members_of_a_class(spark, tmp_path, name):
    where = folder(tmp_path, supplier=times("supplier", "s_suppkey", 5))
    agree(spark, name, where)
    n = spark.read.parquet(f"{where}/supplier.parquet").select("s_suppkey").count() // 5
    assert queries.QUERIES[name](spark, where).count() <= n * (n - 1) // 2 + 4 * n


def test_pairs_of_many_positions_are_dealt_to_tasks(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(measures, "STRIP", 5)
    where = folder(tmp_path, supplier=times("supplier", "s_suppkey", 6, s_acctbal="CASE WHEN s_suppkey = 3 THEN NULL ELSE s_acctbal + r % 5 END"))
    for name in ("d_euclid", "d_manhattan", "d_chebyshev"):
        agree(spark, name, where)
    rows = tables.suppliers(spark, where).df.where("x IS NOT NULL")
    assert len({r.t for r in measures.strip_pairs(rows, ["x", "y"]).select(F.spark_partition_id().alias("t")).collect()}) > 20


def test_six_digits_as_in_the_oracle(spark):
    roots = range(1, 300_000, 7)
    found = spark.createDataFrame([(i,) for i in roots], "i long").select("i", metrics.micro(F.sqrt(F.col("i").cast("double"))).alias("d")).collect()
    want = duckdb.sql("SELECT i, round(sqrt(i::DOUBLE), 6) FROM range(1, 300000, 7) t(i)").fetchall()
    assert sorted(map(tuple, found)) == sorted(want)
