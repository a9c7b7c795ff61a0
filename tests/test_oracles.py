"""Every graph and relational query with SQL, against DuckDB on the smallest tables."""

from __future__ import annotations

import pytest
from conftest import SF, same

import __spark_entry__ as entry
from tidegraph.plans import method_queries, relational_queries, stream_queries

#: Covered by smaller tests, and by the driver on the larger tables.
SLOW = {
    "bfs_level_order_chain", "bfs_relaxed_page_path", "bfs_relaxed_order_part", "bfs_relaxed_order_part_window", "bfs_relaxed_urand_dense", "bfs_relaxed_uncombined", "bfs_hops_order_part_window", "urand_bfs", "urand_rank",
    "rank_split_part_next", "rank_pull_part_next", "rank_push_host_path", "rank_push_user_next", "rank_salted_part_next", "rank_prejoined_part_next", "rank_push_uncombined", "rank_dag_leak",
}
NAMES = [n for m in (method_queries, relational_queries, stream_queries) for n in m.SQL if n not in SLOW]


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, duck, name):
    same(entry.queries()[name](spark, SF).toPandas(), duck.sql(entry.oracle_sql()[name]).df())


def test_entry(spark):
    sizes = {r["level"]: r["count"] for r in entry.entry(spark).groupBy("level").count().collect()}
    assert [sizes[i] for i in range(6)] == [1, 36, 100, 1260, 99, 177]


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
