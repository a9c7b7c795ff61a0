"""Edges for methods of one process: what grows with the vertices is in memory, what grows with the edges in a file.

The method runs in one task and reads the edges once, as Arrow batches; nothing passes through the driver.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from tidegraph.plans.scratch import Scratch

#: Edges worked on at a time, and rows of a batch of results.
WINDOW, BATCH = 1 << 21, 1 << 16


class Spool:
    """Edges with dense codes for their ends, codes in order of the ids.

    A run is a stretch of edges of one source. Of runs the source, first edge and length are in memory, of edges the
    target's code in a temporary file, so edges should come with equal sources together (they need not).
    """

    def __init__(self, also: tuple[int, ...] = ()):
        self._raw = tempfile.TemporaryFile()
        self._sources: list[np.ndarray] = []
        self._counts: list[np.ndarray] = []
        self._new: list[np.ndarray] = []
        self._waiting = 0
        self.ids, self.edges = np.unique(np.array(also, np.int64)), 0

    def add(self, src: np.ndarray, dst: np.ndarray) -> None:
        if not len(src):
            return
        src, dst = src.astype(np.int64), dst.astype(np.int64)
        cuts = np.flatnonzero(np.concatenate(([True], src[1:] != src[:-1])))
        self._sources.append(src[cuts])
        self._counts.append(np.diff(np.append(cuts, len(src))))
        self._raw.write(dst.tobytes())
        self.edges += len(src)
        self._new += [src[cuts], np.unique(dst)]
        self._waiting += len(self._new[-1]) + len(cuts)
        if self._waiting > max(WINDOW, len(self.ids)):
            self._merge()

    def _merge(self) -> None:
        self.ids = np.unique(np.concatenate((self.ids, *self._new)))
        self._new, self._waiting = [], 0

    def close(self) -> Spool:
        """All edges have come: codes the targets."""
        self._merge()
        none = np.zeros(0, np.int64)
        self.source, self.count = np.searchsorted(self.ids, np.concatenate((none, *self._sources))), np.concatenate((none, *self._counts))
        self._sources, self._counts = [], []
        self.first = np.cumsum(self.count) - self.count
        self._raw.flush()
        raw, self._raw = self._raw, None
        self.kind = np.dtype(np.int32 if len(self.ids) < 1 << 31 else np.int64)
        self._coded = tempfile.TemporaryFile()
        raw.seek(0)
        while len(part := np.frombuffer(raw.read(WINDOW * 8), np.int64)):
            self._coded.write(np.searchsorted(self.ids, part).astype(self.kind).tobytes())
        raw.close()
        self._coded.flush()
        self.target = np.memmap(self._coded, self.kind, "r") if self.edges else np.zeros(0, self.kind)
        return self

    def degrees(self) -> np.ndarray:
        """Out-degree by code."""
        return np.bincount(self.source, weights=self.count, minlength=len(self.ids)).astype(np.int64)

    def windows(self, runs: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Sources and targets of the edges of the given runs, in that order, so many at a time."""
        count = self.count[runs]
        last = np.cumsum(count)
        for lo in range(0, int(last[-1]) if len(last) else 0, WINDOW):
            at = np.arange(lo, min(lo + WINDOW, int(last[-1])))
            run = np.searchsorted(last, at, side="right")
            yield self.source[runs[run]], np.asarray(self.target[self.first[runs[run]] + at - (last[run] - count[run])])

    def search(self, root: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """As bfs_seq: ids, parents and levels of what root reaches; each edge is followed once."""
        n = len(self.ids)
        order = np.argsort(self.source, kind="stable")
        begin = np.searchsorted(self.source[order], np.arange(n + 1))
        parent, level = np.full(n, -1, np.int64), np.full(n, -1, np.int32)
        front = np.searchsorted(self.ids, [root])
        parent[front], level[front], depth = front, 0, 0
        while len(front):
            depth += 1
            runs = begin[front + 1] - begin[front]
            mine = order[np.repeat(begin[front] - (np.cumsum(runs) - runs), runs) + np.arange(runs.sum())]
            found = [np.zeros(0, np.int64)]
            for via, near in self.windows(mine):
                new = parent[near] < 0
                # sources ascend within and over windows, so the first to name a vertex is its smallest parent
                near, at = np.unique(near[new], return_index=True)
                parent[near], level[near] = via[new][at], depth
                found.append(near)
            front = np.sort(np.concatenate(found))
        got = np.flatnonzero(level >= 0)
        return self.ids[got], self.ids[parent[got]], level[got]

    def gained(self, share: np.ndarray) -> np.ndarray:
        """What each code gets if every edge brings its source's share."""
        out, every = np.zeros(len(self.ids)), np.arange(len(self.source))
        for via, near in self.windows(every):
            out += np.bincount(near, weights=share[via], minlength=len(out))
        return out


def in_one_task(edges: DataFrame, method: Callable[[Spool], tuple[np.ndarray, ...]], schema: str, also: tuple[int, ...] = ()) -> DataFrame:
    """The columns that method makes of all edges, in one task. also: ids that are there without edges.

    Sources are brought together by all tasks before, in a table that the one task streams. Edges without an end are left out.
    """
    scratch = Scratch(edges.sparkSession, "one-process")
    near = scratch.save(edges.select("src", "dst").where("src is not null and dst is not null").repartition("src").sortWithinPartitions("src"), "edges")

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = Spool(also)
        for b in batches:
            held.add(b.column(0).to_numpy(), b.column(1).to_numpy())
        columns = method(held.close())
        for lo in range(0, len(columns[0]), BATCH):
            yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + BATCH]) for c in columns], names=[x.split()[0] for x in schema.split(", ")])

    return near.coalesce(1).mapInArrow(one, schema)
