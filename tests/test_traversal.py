"""Searches: hand-sized graphs, invariants, equality of variants, plans."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from tidegraph.model import EDGES, Graph, dense_ids, owner, split_edges
from tidegraph.operators import bfs
from tidegraph.operators.components import connected_components
from tidegraph.plans.scratch import Scratch


def make(spark, pairs) -> Graph:
    return Graph(spark.createDataFrame(pairs, EDGES))


def rows(state):
    return sorted((r["id"], r["parent"], r["level"]) for r in state.collect())


def plain(pairs, root):
    near = {}
    for s, d in pairs:
        near.setdefault(s, set()).add(d)
    level, front, depth, parent = {root: 0}, [root], 0, {root: root}
    while front:
        depth += 1
        new = {}
        for u in sorted(front):
            for v in near.get(u, ()):
                if v not in level:
                    new.setdefault(v, u)
        level |= dict.fromkeys(new, depth)
        parent |= new
        front = list(new)
    return sorted((v, parent[v], level[v]) for v in level)


HAND = {
    "cycle of two": ([(0, 1), (1, 0)], 0),
    "path": ([(0, 1), (1, 2), (2, 3)], 0),
    "star out": ([(0, i) for i in range(1, 6)], 0),
    "star in": ([(i, 0) for i in range(1, 6)], 0),
    "diamond": ([(0, 2), (0, 1), (2, 3), (1, 3)], 0),
    "apart": ([(0, 1), (5, 6)], 0),
    "loop": ([(0, 0)], 0),
    "complete": ([(a, b) for a in range(4) for b in range(4) if a != b], 2),
    # with cyclic blocks of two, 0-2-4-6-8 stays inside; 0-1-8 is shorter and crosses
    "shortcut": ([(0, 2), (2, 4), (4, 6), (6, 8), (8, 10), (0, 1), (1, 8)], 0),
    "repeats": ([(0, 1), (0, 1), (1, 1), (1, 2)], 0),
}


@pytest.mark.parametrize("name", HAND)
def test_variants_agree(spark, name):
    pairs, root = HAND[name]
    g, want = make(spark, pairs), plain(pairs, root)
    assert rows(bfs.bfs_level(g, root).state) == want
    assert rows(bfs.bfs_relaxed(g, root, how="cyclic", blocks=2).state) == want
    if name in ("shortcut", "diamond", "apart"):
        for other in (bfs.bfs_hops(g, root, 2, "cyclic", 2), bfs.bfs_vertex(g, root), bfs.spmv_bfs(g, root), bfs.bfs_dropin(g, root), bfs.bfs_level(g, root, direction="auto"), bfs.bfs_relaxed(g, root, how="hash", blocks=1)):
            assert rows(other.state) == want


def test_shortcut_is_corrected_or_wrong(spark):
    g = make(spark, HAND["shortcut"][0])
    exact = bfs.bfs_relaxed(g, 0, how="cyclic", blocks=2)
    assert sum(x["corrections"] for x in exact.log) > 0
    loose = {r[0]: r[2] for r in rows(bfs.bfs_relaxed(g, 0, how="cyclic", blocks=2, claim="first").state)}
    true = {r[0]: r[2] for r in rows(exact.state)}
    assert set(loose) == set(true) and all(loose[v] >= true[v] for v in true) and loose[8] > true[8]


@given(st.lists(st.tuples(st.integers(0, 14), st.integers(0, 14)), max_size=50), st.integers(1, 5))
@settings(max_examples=60, deadline=None)
def test_drain_rounds_reach_plain_levels(pairs, blocks):
    """The block step alone, handed claims by hand, against a plain search."""
    src, dst = (np.array([p[i] for p in pairs], np.int64) for i in (0, 1))
    state, claims = {}, {0: (0, 0)}
    for _ in range(60):
        sent = {}
        for b in range(blocks):
            mine = [v for v in {*state, *claims} if v % blocks == b]
            if not any(v in claims for v in mine):
                continue
            known = [(v, *state[v][::-1], False) for v in mine if v in state] + [(v, claims[v][1], claims[v][0], True) for v in mine if v in claims]
            k = {n: np.array([x[i] for x in known]) for i, n in enumerate(("id", "parent", "level", "fresh"))}
            use = src % blocks == b
            got = bfs.drain(k, src[use], dst[use], dst[use] % blocks, b)
            for v, p, lv in zip(got["id"], got["parent"], got["level"], strict=True):
                state[int(v)] = (int(lv), int(p))
            for v, p, lv in zip(got["out_id"], got["out_parent"], got["out_level"], strict=True):
                sent[int(v)] = min(sent.get(int(v), (99, 99)), (int(lv), int(p)))
        claims = {v: c for v, c in sent.items() if v not in state or c[0] < state[v][0]}
        if not claims:
            break
    assert {v: s[0] for v, s in state.items()} == {v: lv for v, _, lv in plain(pairs, 0)}


@given(st.lists(st.tuples(st.integers(0, 12), st.integers(0, 12)), max_size=40))
@settings(max_examples=60, deadline=None)
def test_sequential(pairs):
    src, dst = (np.array([p[i] for p in pairs], np.int64) for i in (0, 1))
    ids, parents, levels = bfs.bfs_seq(src, dst, 0)
    assert sorted(zip(ids.tolist(), parents.tolist(), levels.tolist(), strict=True)) == plain(pairs, 0)
    assert sorted(zip(*(x.tolist() for x in bfs.bfs_sweep(src, dst, 0)), strict=True)) == plain(pairs, 0)


@given(st.lists(st.tuples(st.integers(0, 12), st.integers(0, 12)), max_size=40), st.integers(1, 9), st.integers(1, 50))
@settings(max_examples=60, deadline=None)
def test_spooled_edges_are_searched_as_arrays(pairs, batch, window):
    from tidegraph.operators import oneprocess

    before, oneprocess.WINDOW = oneprocess.WINDOW, window
    try:
        held = oneprocess.Spool(also=(0,))
        for i in range(0, len(pairs), batch):
            held.add(*(np.array([p[k] for p in pairs[i : i + batch]], np.int64) for k in (0, 1)))
        assert sorted(zip(*(x.tolist() for x in held.close().search(0)), strict=True)) == plain(pairs, 0)
    finally:
        oneprocess.WINDOW = before


def test_sequential_searches_refuse_no_size(spark, monkeypatch):
    """One task holds the vertices; arrays of all edges, and their limit, are not met."""
    import __spark_entry__ as entry

    # defaults of bfs_seq: no edge fits
    monkeypatch.setattr(bfs.bfs_seq, "__defaults__", (0,))
    monkeypatch.setattr(type(spark.range(0)), "toArrow", lambda self: pytest.fail("edges on the driver"))
    g = make(spark, HAND["shortcut"][0])
    assert rows(bfs.bfs_dropin(g, 0).state) == plain(*HAND["shortcut"])
    assert rows(bfs.bfs_dropin(make(spark, []), 3).state) == [(3, 3, 0)]
    assert entry.queries()["bfs_sequential"](spark, "/root/testdata/sf0.001").count() > 1


def test_ownership_by_chain_needs_one_round(spark):
    pairs = [(i, i + 1) for i in range(40) if i % 10 != 9]
    g = make(spark, pairs)
    assert bfs.bfs_relaxed(g, 0, how="block", blocks=4, n=40).rounds == 1
    assert bfs.bfs_level(g, 0).rounds == 10
    assert bfs.bfs_relaxed(g, 0, how="cyclic", blocks=4).rounds == 10


def test_blocks_beyond_the_vertices_hubs_and_no_edges(spark):
    pairs = [(0, i) for i in range(1, 30)] + [(i, i + 1) for i in range(29)] + [(29, 40), (40, 0)]
    g, want = make(spark, pairs), plain(pairs, 0)
    assert rows(bfs.bfs_relaxed(g, 0, how="cyclic", blocks=50).state) == want
    assert rows(bfs.bfs_relaxed(g, 0, how="cyclic", blocks=2, hub_edges=5).state) == want  # 0 is followed by a join
    assert rows(bfs.bfs_relaxed(g, 0, how="cyclic", blocks=1, block_edges=10).state) == want  # blocks are doubled
    lone = make(spark, [])
    assert rows(bfs.bfs_relaxed(lone, 3).state) == rows(bfs.bfs_level(lone, 3).state) == [(3, 3, 0)]
    with pytest.raises(RuntimeError):
        bfs.bfs_relaxed(g, 0, how="cyclic", blocks=50, max_rounds=1)


def test_depth_first_order_by_recursion(spark):
    from tidegraph.plans.method_queries import held
    from tidegraph.plans.workloads import OFFSETS

    g = held(spark, "/root/testdata/sf0.001", "page_path")
    near = {}
    for r in g.edges.collect():
        near.setdefault(r["src"], []).append(r["dst"])
    want, seen = [], set()

    def visit(v, parent, level):
        seen.add(v)
        want.append((len(want), v, parent, level))
        for w in sorted(near.get(v, [])):
            if w not in seen:
                visit(w, v, level + 1)

    visit(OFFSETS["page"], OFFSETS["page"], 0)
    assert sorted(map(tuple, bfs.dfs_range(g, OFFSETS["page"]).select("ord", "id", "parent", "level").collect())) == want


def test_rounds_of_the_blueprint(spark):
    from tidegraph.plans.method_queries import held

    got = bfs.bfs_relaxed(held(spark, "/root/testdata/sf0.01", "part_supplier"), 0, how="cyclic", blocks=8)
    total = {k: sum(x[k] for x in got.log) for k in ("remote", "corrections", "accepted", "rejected", "combined")}
    assert got.rounds == 3 and (total["remote"], total["corrections"]) == (97312, 761)
    assert total["accepted"] + total["rejected"] == total["combined"]


def test_limits_and_views(spark):
    g = make(spark, HAND["path"][0])
    assert rows(bfs.bfs_level(g, 0, max_level=1).state) == [(0, 0, 0), (1, 0, 1)]
    assert rows(bfs.bfs_level(g, 99).state) == [(99, 99, 0)]  # a root without edges
    assert bfs.bfs_level(g, 0, targets=spark.createDataFrame([(1,)], "id bigint")).rounds == 1
    assert [r["id"] for r in bfs.dfs_range(make(spark, [(0, 3), (0, 1), (1, 2), (2, 3)]), 0).orderBy("ord").collect()] == [0, 1, 2, 3]
    assert sorted(map(tuple, bfs.path_to(bfs.bfs_level(g, 0).state, spark.createDataFrame([(2,)], "id bigint")).select("id", "step", "vertex").collect())) == [(2, 0, 2), (2, 1, 1), (2, 2, 0)]
    with pytest.raises(ValueError):
        bfs.bfs_seq(np.zeros(5, int), np.zeros(5, int), 0, most=4)


def test_many_roots_and_level_order(spark):
    pairs = [(i, (i * 5 + 1) % 90) for i in range(90)] + [(i, i + 1) for i in range(0, 89, 3)] + [(200, 201)]
    g = make(spark, pairs)
    alone = {r: {(s["id"], s["parent"], s["level"]) for s in bfs.bfs_level(g, r).state.collect()} for r in (0, 200, 999)}
    for roots in ([0, 200, 0, 999], []):  # a repeated root counts once, one without edges reaches itself
        got = [tuple(r) for r in bfs.bfs_multi(g, roots).select("root", "id", "parent", "level").collect()]
        assert sorted(got) == sorted((r, *s) for r in set(roots) for s in alone[r])
    ranged = [tuple(r) for r in bfs.bfs_range(g, 0).select("ord", "id", "parent", "level").collect()]
    assert sorted(ranged) == [(k, *s) for k, s in enumerate(sorted(alone[0], key=lambda s: (s[2], s[0])))]


def test_paths_of_all_deepest_vertices(spark, tmp_path):
    import duckdb

    import __spark_entry__ as entry
    from tidegraph.model import OFFSETS

    # part 0, order 1, part 1, then orders 2, 5000 and 60000
    lines = [(1, 0), (1, 1), (2, 1), (5000, 1), (60000, 1)]
    spark.createDataFrame(lines, "l_orderkey bigint, l_partkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    first = OFFSETS["order"] + 1
    want = sorted(x for k in (2, 5000, 60000) for o in [OFFSETS["order"] + k] for x in ((o, 0, o), (o, 1, 1), (o, 2, first), (o, 3, 0)))
    assert sorted((r["id"], r["step"], r["vertex"]) for r in entry.queries()["bfs_paths"](spark, str(tmp_path)).collect()) == want
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{tmp_path}/lineitem.parquet/*.parquet'")
    assert sorted(con.sql(entry.oracle_sql()["bfs_paths"]).fetchall()) == want


def test_model(spark):
    with pytest.raises(TypeError):
        Graph(spark.createDataFrame([("a", "b")], "src string, dst string"))
    keyed = dense_ids(spark.createDataFrame([("b",), ("a",), (None,), ("b",)], "k string"), "k")
    assert sorted(map(tuple, keyed.collect())) == [("a", 0), ("b", 1)]
    inside, between = split_edges(make(spark, [(0, 2), (0, 1)]), "cyclic", 2)
    assert (inside.count(), between.count()) == (1, 1)
    with pytest.raises(ValueError):
        owner(keyed["id"], "nearest", 2)
    cut = make(spark, [(0, i) for i in range(100)]).adjacency(chunk=10)
    assert cut.count() > 5 and Graph.from_adjacency(cut).edges.count() == 100


def test_components(spark):
    pairs = [(i, i + 1) for i in range(60)] + [(100, 101), (7, 7)]
    found = connected_components(spark.createDataFrame(pairs, "a bigint, b bigint"), Scratch(spark))
    assert {r["id"]: r["component"] for r in found.collect()} == {**dict.fromkeys(range(61), 0), 100: 100, 101: 100}
    assert connected_components(spark.createDataFrame([], "a bigint, b bigint"), Scratch(spark)).count() == 0


def test_bucketed_edges_are_not_shuffled_again(spark):
    from tidegraph.sources.files import save_bucketed

    table = save_bucketed(make(spark, [(i, i + 1) for i in range(50)]).edges, "tide_plan_test", 4)
    plan = table.groupBy("blk").count()._jdf.queryExecution().executedPlan().toString()
    spark.sql("drop table tide_plan_test")
    assert "Exchange" not in plan


def test_scan_prunes_and_pushes(spark):
    import __spark_entry__ as entry

    plan = entry.queries()["scan_parquet_pruned"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate), GreaterThanOrEqual" in plan and "l_tax" not in plan.split("== Physical Plan ==")[1]


@pytest.mark.parametrize(("most", "tile"), [(1 << 16, 1024), (40, 7), (1000, 16)])
def test_nearest_do_not_depend_on_blocks_or_tiles(spark, tmp_path, most, tile):
    from tidegraph.plans import workloads

    rng = np.random.default_rng(3)
    x = rng.integers(-3, 4, (150, 4)).astype(float)  # many ties, repeated rows
    x[(x == 0).all(axis=1), 0] = 1
    spark.createDataFrame([(i * 3, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    c = np.round((x @ x.T) / np.outer(*[np.linalg.norm(x, axis=1)] * 2), 9)
    want = {(i * 3, j * 3) for i in range(150) for j in sorted((j for j in range(150) if j != i), key=lambda j: (-c[i, j], j))[:5]}
    assert {tuple(r) for r in workloads.knn(spark, str(tmp_path), most=most, tile=tile).collect()} == want


def test_random_source_draws_for_the_rows_of_a_table(spark, tmp_path):
    """And the data source, read by itself, draws the same for the same numbers."""
    import hashlib

    import __spark_entry__ as entry
    from tidegraph.sources.urand import UrandSource

    end = lambda c, i: int(hashlib.md5(f"42:{c}:{i}".encode()).hexdigest()[:15], 16) % 1024
    spark.createDataFrame([(5, 1), (5, 2), (10**12, 7), (None, 1)], "l_orderkey bigint, l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert sorted(map(tuple, entry.queries()["source_urand"](spark, str(tmp_path)).collect())) == sorted((end("a", i), end("b", i)) for i in (41, 42, 8 * 10**12 + 7))
    spark.dataSource.register(UrandSource)
    got = spark.read.format("urand").option("k", 10).option("degree", 16).load()
    assert sorted(map(tuple, got.collect())) == sorted((end("a", i), end("b", i)) for i in range(8192))


def test_recursion_goes_down_to_the_orders(spark, tmp_path):
    import duckdb

    import __spark_entry__ as entry

    whole = entry.queries()["rcte_hierarchy"](spark, "/root/testdata/sf0.01")
    assert [r["count"] for r in whole.groupBy("level").count().orderBy("level").collect()] == [1, 5, 286, 2883]
    assert len(whole.inputFiles()) > 1  # not all by one task
    assert spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled") == "true"
    small = {
        "nation": ("n_nationkey int, n_regionkey int", [(0, 0), (1, 1), (2, 0), (None, 0)]),
        "customer": ("c_custkey bigint, c_nationkey int", [(10, 0), (10, 0), (11, 1), (12, 2), (13, None), (None, 2), (0, 2)]),
        "orders": ("o_orderkey bigint, o_custkey bigint", [(0, 10), (100, 10), (101, 11), (102, 12), (103, None), (104, 99), (105, 13)]),
    }
    con = duckdb.connect()
    for table, (columns, held) in small.items():
        spark.createDataFrame(held, columns).write.parquet(f"{tmp_path}/{table}.parquet")
        con.execute(f"create view {table} as select * from '{tmp_path}/{table}.parquet/*.parquet'")
    want = [(0, 0, "r"), (0, 1, "n"), (2, 1, "n"), (None, 1, "n"), (10, 2, "c"), (10, 2, "c"), (12, 2, "c"), (None, 2, "c"), (0, 2, "c"), *[(0, 3, "o"), (100, 3, "o")] * 2, (102, 3, "o")]
    spark.conf.set("spark.sql.cteRecursionRowLimit", "3")
    try:
        got = entry.queries()["rcte_hierarchy"](spark, str(tmp_path)).collect()
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))
    assert sorted(map(str, con.execute(entry.oracle_sql()["rcte_hierarchy"]).fetchall())) == sorted(map(str, want))
