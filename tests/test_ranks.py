"""Ranks: hand cases, equality of modes, mass, errors."""

from __future__ import annotations

import numpy as np
import pytest

from tidegraph.functions import adaptive, measures
from tidegraph.model import EDGES, Graph
from tidegraph.operators import analytics, rank


def make(spark, pairs) -> Graph:
    return Graph(spark.createDataFrame(pairs, EDGES))


def got(r):
    return {x["id"]: x["rank"] for x in r.ranks.collect()}


PAIRS = [(0, 1), (0, 2), (1, 2), (2, 0), (3, 2), (3, 4)]


@pytest.mark.parametrize("how", [{}, {"combine": False}, {"mode": "split", "how": "cyclic", "blocks": 2}, {"mode": "split", "how": "block", "blocks": 2, "combine": False}, {"mode": "pull"}, {"mode": "prejoined", "hubs": 1}])
@pytest.mark.parametrize("dangling", rank.DANGLING)
def test_modes_equal_the_sequential_one(spark, how, dangling):
    s, d = (np.array([p[i] for p in PAIRS]) for i in (0, 1))
    want, errors = rank.rank_seq(s, d, np.arange(5), tol=None, max_iter=3, dangling=dangling)
    found = rank.rank(make(spark, PAIRS), tol=None, max_iter=3, dangling=dangling, **how)
    assert np.allclose([got(found)[i] for i in range(5)], want, atol=1e-12)
    assert np.allclose([x["l1_error"] for x in found.log], errors, atol=1e-12)
    mass = found.log[-1]["mass"]
    assert mass == pytest.approx(1) if dangling != "leak" else mass < 1


@pytest.mark.parametrize("window", [3, 1 << 21])
@pytest.mark.parametrize("dangling", rank.DANGLING)
def test_spooled_edges_rank_as_arrays(monkeypatch, window, dangling):
    from tidegraph.operators import oneprocess

    monkeypatch.setattr(oneprocess, "WINDOW", window)
    s, d = (np.array([p[i] * 10**12 for p in PAIRS]) for i in (0, 1))
    held = oneprocess.Spool()
    for at in (slice(0, 2), slice(2, 5), slice(5, 6)):
        held.add(s[at], d[at])
    held.close()
    want = rank.rank_seq(s, d, held.ids, tol=None, max_iter=3, dangling=dangling)
    found = rank._iterate(held.degrees(), held.gained, 0.85, None, 3, dangling)
    assert held.ids.tolist() == [i * 10**12 for i in range(5)] and np.allclose(found[0], want[0], atol=1e-12) and np.allclose(found[1], want[1], atol=1e-12)


def test_sequential_rank_brings_no_edges_to_the_driver(spark, monkeypatch):
    import __spark_entry__ as entry

    monkeypatch.setattr(type(spark.range(0)), "toArrow", lambda self: pytest.fail("edges on the driver"))
    assert entry.queries()["rank_sequential"](spark, "/root/testdata/sf0.001").count() == 200
    assert rank.rank_one_task(make(spark, [])).count() == 0


def test_uniform_and_errors(spark):
    full = make(spark, [(a, b) for a in range(4) for b in range(4) if a != b])
    assert all(x == pytest.approx(0.25) for x in got(rank.rank(full)).values())
    assert all(x == pytest.approx(0.2) for x in got(rank.rank(make(spark, PAIRS), alpha=0.0)).values())
    log = rank.rank(make(spark, PAIRS), tol=1e-6).log
    assert log[-1]["l1_error"] < 1e-6
    assert all(b["l1_error"] <= 0.85 * a["l1_error"] + 1e-12 for a, b in zip(log[:-1], log[1:], strict=True))
    with pytest.raises(ValueError):
        rank.rank(full, alpha=1.0)
    assert rank.rank(make(spark, [])).ranks.count() == 0


def test_vertex_delta_restart_weight(spark):
    g = make(spark, PAIRS)
    exact = rank.rank(g, tol=1e-13, max_iter=200)
    c = measures.compare_ranks(rank.rank_delta(g, 1e-10).ranks, exact.ranks, 3).first()
    assert c["largest"] < 1e-8 and c["agree"] == 3
    a, b = got(rank.rank_vertex(g, iterations=3)), got(rank.rank(g, tol=None, max_iter=3))
    assert all(a[i] == pytest.approx(b[i]) for i in b)
    only = got(rank.rank(g, tol=None, max_iter=5, restart=spark.createDataFrame([(3, 1.0)], "id bigint, p double"), dangling="redistribute"))
    assert sum(only.values()) == pytest.approx(1) and only[3] >= 0.15
    heavy = Graph(spark.createDataFrame([(0, 1, 3.0), (0, 2, 1.0)], "src bigint, dst bigint, w double"))
    w = got(rank.rank(heavy, tol=None, max_iter=1, weight="w"))
    assert (w[1] - 0.05) == pytest.approx(3 * (w[2] - 0.05))


def test_analytics(spark):
    g = make(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4)])
    assert analytics.triangles(g).count() == 1
    assert sorted(r["id"] for r in analytics.k_core(g, 2).collect()) == [0, 1, 2]
    assert tuple(analytics.motif_counts(make(spark, [(0, 1), (1, 2), (2, 3), (3, 0)])).first()) == (4, 0, 1)
    line = make(spark, [(0, 1), (1, 0), (1, 2), (2, 1)])
    assert {r["id"]: r["score"] for r in analytics.betweenness(line, [0, 1, 2]).collect()} == {1: 2.0}
    w = Graph(spark.createDataFrame([(0, 1, 5.0), (0, 2, 1.0), (2, 1, 1.0)], "src bigint, dst bigint, w double"))
    assert {r["id"]: r["dist"] for r in analytics.sssp(w, 0).collect()} == {0: 0.0, 1: 2.0, 2: 1.0}
    with pytest.raises(ValueError):
        analytics.sssp(Graph(spark.createDataFrame([(0, 1, -1.0)], "src bigint, dst bigint, w double")), 0)


def test_measures(spark):
    runs = spark.createDataFrame([("g", "one", 1, 2.0, True), ("g", "other", 1, 4.0, True), ("g", "relaxed", 4, 1.0, False)], "graph string, method string, workers int, seconds double, sequential boolean")
    got = {r["method"]: (r["speedup"], r["efficiency"]) for r in measures.speedup(runs).collect()}
    assert got["relaxed"] == (2.0, 0.5) and got["other"] == (0.5, 0.5)
    g = make(spark, PAIRS)
    from tidegraph.operators.bfs import bfs_level

    assert measures.teps(bfs_level(g, 0).state, g, 2.0) == 2.0  # four edges leave 0, 1 and 2


def test_hash_owner_is_the_published_hash(spark):
    import struct

    import xxhash
    from pyspark.sql import functions as F

    from tidegraph.model import owner

    for r in spark.range(50).select("id", owner(F.col("id"), "hash", 7).alias("x")).collect():
        h = xxhash.xxh64(struct.pack("<q", r["id"]), seed=42).intdigest()
        assert r["x"] == (h - (1 << 64) if h >> 63 else h) % 7


def test_adaptive():
    assert adaptive.choose_blocks(10, 8) == 1 and adaptive.choose_blocks(1_000_000, 8) == 20 and adaptive.choose_blocks(1 << 40, 8) == 1 << 16
    assert adaptive.choose_schedule(0.1) == "relaxed" and adaptive.choose_schedule(0.9) == "level"
    assert adaptive.choose_parallelism(10, 8) == 1
    assert adaptive.choose_parallelism(20_000_000, 8) == 24
    assert adaptive.run_all([lambda: 1, lambda: 2]) == [1, 2]
    with pytest.raises(ZeroDivisionError):
        adaptive.run_all([lambda: 1 // 0])
    assert measures.timed(lambda: 5, 2)["result"] == 5


def test_edges_stay_where_they_are(spark):
    """With edges bucketed by the join key, a join moves the other side only."""
    from pyspark.sql import functions as F

    from tidegraph.plans.scratch import Scratch

    scratch = Scratch(spark, "plan")
    edges = scratch.save_bucketed(spark.createDataFrame([(i, i + 1) for i in range(50)], EDGES), "edges", "src")
    ranks = scratch.save(spark.range(50).select(F.col("id").alias("src"), F.lit(1.0).alias("rank")), "ranks")
    plan = edges.join(ranks.hint("merge"), "src")._jdf.queryExecution().executedPlan().toString()
    scratch.drop_table("edges")
    assert plan.count("Exchange") == 1


@pytest.mark.parametrize("block_edges", [40, 1 << 23])
def test_triangles_counted_without_wedges(spark, block_edges):
    rng = np.random.default_rng(5)
    pairs = [(int(a) * 10**11, int(b) * 10**11) for a, b in rng.integers(0, 90, (500, 2))] + [(0, i * 10**11) for i in range(90)]  # loops, repeats, a hub
    near = {}
    for a, b in pairs:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    want = sum(len(near[a] & near[b]) for a in near for b in near[a]) // 6
    assert analytics.triangle_count(make(spark, pairs), block_edges) == want
    assert analytics.triangle_count(make(spark, []), block_edges) == 0


def test_triangle_query_joins_no_wedges(spark, monkeypatch):
    import __spark_entry__ as entry

    monkeypatch.setattr(analytics, "oriented", lambda g: pytest.fail("wedges are joined"))
    assert entry.queries()["triangle_count"](spark, "/root/testdata/sf0.001").first()["triangles"] > 0
