"""Queries that once made their data up read the given tables."""

import os

import pytest
from test_repeated import DIR, agree, folder

from diversify import queries

pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test tables here")


@pytest.mark.parametrize("name", ["src_ball_sphere", "exp_stream_cloud", "exp_mr_cloud", "exp_adversarial_cloud", "m_terms", "solver_table"])
def test_files_are_read(spark, name):
    assert queries.QUERIES[name](spark, DIR).inputFiles()


def test_plans_follow_the_lines(spark, tmp_path):
    where = folder(tmp_path, lineitem="SELECT * FROM lineitem WHERE l_orderkey % 3 = 0")
    agree(spark, "plan_table", where)
    assert queries.QUERIES["plan_table"](spark, where).collect() != queries.QUERIES["plan_table"](spark, DIR).collect()
