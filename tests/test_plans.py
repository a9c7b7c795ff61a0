"""Exchanges of one step, counted in the plans that are written, with broadcasts off."""

from __future__ import annotations

import pytest

from tidegraph.functions import adaptive
from tidegraph.model import EDGES, Graph
from tidegraph.operators import bfs, rank
from tidegraph.plans.scratch import Scratch

CHAIN = [(i, (i * 7 + 3) % 200) for i in range(200)] + [(i, (i + 1) % 200) for i in range(200)]


@pytest.fixture
def plans(spark, monkeypatch):
    """name: exchanges of the plan that wrote it; buckets as on large data."""
    found, save = {}, Scratch.save_bucketed

    def watched(self, df, name, *args, **kw):
        found[name] = df._jdf.queryExecution().executedPlan().toString()
        return save(self, df, name, *args, **kw)

    monkeypatch.setattr(Scratch, "save_bucketed", watched)
    monkeypatch.setattr(Scratch, "buckets", lambda self, df: int(spark.conf.get("spark.sql.shuffle.partitions")))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield lambda name: found[name].count("Exchange hashpartitioning")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_relaxed_round_moves_claims_only(spark, plans):
    got = bfs.bfs_relaxed(Graph(spark.createDataFrame(CHAIN, EDGES)), 0, how="cyclic", blocks=4)
    assert got.rounds > 2
    assert plans("round-2") == 0 and plans("claims-1") == 1 and plans("claims-2") == 1


@pytest.mark.parametrize("rows", [0, 500_000])
def test_level_moves_claims_only(spark, plans, monkeypatch, rows):
    """Whether or not the frontier is broadcast."""
    monkeypatch.setattr(bfs, "small", lambda df, n: adaptive.small(df, n, rows))
    got = bfs.bfs_level(Graph(spark.createDataFrame(CHAIN, EDGES)), 0)
    assert got.rounds > 2 and got.state.count() == 200
    assert plans("state") == 1


@pytest.mark.parametrize(("search", "rows", "moved"), [(lambda g: bfs.bfs_multi(g, [0, 5]), 500_000, 1), (lambda g: bfs.bfs_multi(g, [0, 5]), 0, 2), (lambda g: bfs.spmv_bfs(g, 0).state, 0, 1)])
def test_reached_vertices_stay(spark, plans, monkeypatch, search, rows, moved):
    """Claims move in a level, and a large frontier of many roots; edges and reached vertices do not."""
    monkeypatch.setattr(bfs, "small", lambda df, n: adaptive.small(df, n, rows))
    assert search(Graph(spark.createDataFrame(CHAIN, EDGES))).count() in (200, 400)
    assert plans("state") == moved


@pytest.mark.parametrize(("how", "most"), [({}, 1), ({"mode": "prejoined"}, 1), ({"mode": "split", "how": "cyclic", "blocks": 4}, 1), ({"combine": False}, 1)])
def test_rank_iteration_moves_sums_only(spark, plans, how, most):
    rank.rank(Graph(spark.createDataFrame(CHAIN, EDGES)), tol=None, max_iter=2, **how)
    assert plans("2") == most


def test_local_sums_move_nothing(spark, plans, monkeypatch):
    """With one block all edges are inside; the plan's one exchange carries no row."""
    found = rank.rank(Graph(spark.createDataFrame(CHAIN, EDGES)), tol=None, max_iter=2, mode="split", blocks=1)
    want = rank.rank(Graph(spark.createDataFrame(CHAIN, EDGES)), tol=None, max_iter=2)
    a, b = ({r["id"]: round(r["rank"], 12) for r in x.ranks.collect()} for x in (found, want))
    assert a == b and plans("2") <= 1


def test_compared_searches_are_in_flight_together(spark, monkeypatch):
    from threading import Barrier

    from tidegraph.plans import method_queries

    met = Barrier(4, timeout=20)  # breaks if they come one by one
    log = [{"remote": 2, "corrections": 1}] * 3
    monkeypatch.setattr(method_queries, "held", lambda spark, d, w: w)
    monkeypatch.setattr(method_queries, "chained", lambda spark, d: ("order_chain", 4, None, 9))
    for name in ("bfs_level", "bfs_relaxed"):
        monkeypatch.setattr(bfs, name, lambda g, root, **how: (met.wait(), bfs.Traversal(None, log))[1])
    got = method_queries.QUERIES["rounds_compare"](spark, "")
    assert [tuple(r) for r in got.collect()] == [(w, 3, 3, 6, 3) for w in ("part_supplier", "order_part_window", "urand_dense", "order_chain")]
