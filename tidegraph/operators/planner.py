"""One search for all graphs: counts choose blocks and schedule."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from tidegraph.functions.adaptive import choose_blocks, choose_schedule
from tidegraph.model import Graph, owner
from tidegraph.operators.bfs import Traversal, bfs_level, bfs_relaxed


@dataclass(frozen=True)
class Plan:
    """What was counted and chosen: cut is the number of edges between blocks."""

    edges: int
    blocks: int
    cut: int
    schedule: str


def plan(g: Graph, how: str = "hash", n: int | None = None, cores: int | None = None, block_edges: int = 1 << 24) -> Plan:
    """Two passes over the edges, one number each. cores: the session's, unless given."""
    edges = g.edges.count()
    blocks = choose_blocks(edges, cores or g.edges.sparkSession.sparkContext.defaultParallelism, block_edges)
    crosses = owner(F.col("src"), how, blocks, n) != owner(F.col("dst"), how, blocks, n)
    cut = g.edges.agg(F.count(F.when(crosses, 1))).first()[0] if blocks > 1 else 0
    return Plan(edges, blocks, cut, choose_schedule(cut / max(edges, 1)))


def search(g: Graph, root: int, how: str = "hash", n: int | None = None) -> tuple[Traversal, Plan]:
    """Exact levels and smallest parents by the schedule that fits the graph; and what was chosen."""
    chosen = plan(g, how, n)
    if chosen.schedule == "relaxed":
        return bfs_relaxed(g, root, how, chosen.blocks, n), chosen
    return bfs_level(g, root), chosen
