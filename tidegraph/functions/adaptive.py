"""Choices made from counts: broadcast or shuffle, and how many partitions."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import InheritableThread
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Counted rows up to which a narrow side may be broadcast.
BROADCAST_ROWS = 500_000


def small(df: DataFrame, rows: int, most: int = BROADCAST_ROWS) -> DataFrame:
    """Hints a broadcast while the counted rows keep within the bound."""
    return F.broadcast(df) if rows <= most else df


def choose_parallelism(active_edges: int, cores: int, target_rows: int = 1_000_000) -> int:
    """Partitions for a step: enough that none exceeds target_rows, in whole waves of the cores, and one for little work."""
    if active_edges <= target_rows // 10:
        return 1
    waves = -(-active_edges // (target_rows * cores))
    return max(1, waves) * cores


def choose_blocks(edges: int, cores: int, block_edges: int = 1 << 24) -> int:
    """Blocks of a graph: none over block_edges on average, and for smaller graphs four a core, but none of so few
    edges that starting its task costs more than following them."""
    return max(1, -(-edges // block_edges), min(4 * cores, -(-edges // 50_000)))


def choose_schedule(cut_share: float, threshold: float = 0.5) -> str:
    """relaxed where most edges stay inside blocks, so that whole rounds are saved; level where they cross."""
    return "relaxed" if cut_share < threshold else "level"


def run_all(calls: list[Callable], pool: int = 4) -> list:
    """Independent jobs in flight together; results in order, the first failure raised."""

    def inherit(call: Callable):
        out: list = []

        def body() -> None:
            try:
                out.append((True, call()))
            except BaseException as e:  # handed to the caller below
                out.append((False, e))

        t = InheritableThread(target=body)
        t.start()
        t.join()
        return out[0]

    with ThreadPoolExecutor(pool) as workers:
        found = list(workers.map(inherit, calls))
    for fine, x in found:
        if not fine:
            raise x
    return [x for _, x in found]
