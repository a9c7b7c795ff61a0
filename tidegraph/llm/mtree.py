"""Exact top-k by inner product: M-trees searched best first.

An inner product becomes a distance when each vector gets one more coordinate, sqrt(m - |v|^2) with
m the largest squared norm, and each query a 0: then d(q, v)^2 = |q|^2 + m - 2 q.v, so the nearest
vectors have the largest products. Vectors are integers; products are exact, and the metric only
rules out what cannot matter, with slack for rounding.

Distribution: routing vectors from a bounded sample split the vectors into cells; a cell is cut by a
hash of the row into chunks of a bounded number of rows, and each chunk carries an M-tree of its own,
built where it is searched: paged leaves under directory nodes, every node with a routing vector, a
covering radius and its distance to the parent's routing vector. A query is sent to the chunks of those
cells that its bound admits. The bound starts from the k-th best product among the sample, a true lower
limit, so most of a tree is never opened. A task reads a chunk's vectors, makes the tree, and streams the
chunk's queries through it, so no vector is copied for them; only a chunk with more than slice_rows queries
is built again for each further slice, to keep tasks short. Each chunk yields k rows a query at most, and
those are ranked.

Cases: vectors that are null or hold null, NaN or infinite components (or ones that leave 64 bits)
take no part; shorter vectors count as filled up with zeros; rows of one id are rows of their own: each is
a candidate of the others, and each that asks has its own ranks; ties go to smaller ids; fewer than k candidates
are all returned; a table without vectors gives an empty result; further columns are not looked at.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tidegraph.llm.common import bounded_rows
from tidegraph.llm.textblocks import mix64
from tidegraph.plans.scratch import Scratch


@dataclass(frozen=True)
class MTreeSearch:
    k: int = 20
    page: int = 128
    fanout: int = 8
    cells: int = 48
    sample_rows: int = 4096
    chunk_rows: int = 16384
    slice_rows: int = 1 << 18


def integers(embedding: str = "embedding", scale: int = 64) -> Column:
    """floor(scale * x) of each component as a double; null if the vector takes no part."""
    c = F.col(embedding)
    made = F.transform(c, lambda x: F.floor(x.cast("double") * scale).try_cast("bigint"))
    fine = ~F.exists(c, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) >= 2.0**56))
    return F.when(c.isNotNull() & F.coalesce(fine, F.lit(False)), made)


def _matrix(column, width: int) -> np.ndarray:
    """Lists as rows of int64, filled up with zeros."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.diff(column.offsets.to_numpy())
    out = np.zeros((len(column), width), np.int64)
    flat = column.flatten().to_numpy()
    if len(flat) == len(column) * width and (sizes == width).all():
        return flat.reshape(len(column), width)
    rows = np.repeat(np.arange(len(column)), sizes)
    out[rows, np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = flat
    return out


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact inner products of int64 rows; through floating point where that is exact."""
    if not a.size or not b.size:
        return np.zeros((len(a), len(b)), np.int64)
    if float(np.abs(a).max()) * float(np.abs(b).max()) * a.shape[1] < 2**53:
        return (a.astype(float) @ b.T.astype(float)).astype(np.int64)
    return a @ b.T


def lifted(v: np.ndarray, most: float) -> np.ndarray:
    """Vectors with the coordinate that gives all the squared norm `most`."""
    x = v.astype(float)
    return np.concatenate([x, np.sqrt(np.maximum(most - (x**2).sum(axis=1), 0))[:, None]], axis=1)


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    square = (a**2).sum(axis=1)[:, None] + (b**2).sum(axis=1)[None, :] - 2 * (a @ b.T)
    return np.sqrt(np.maximum(square, 0))


def spread(points: np.ndarray, count: int) -> np.ndarray:
    """Positions of up to `count` points, each far from those before it."""
    first = [0]
    near = _distances(points[:1], points)[0]
    while len(first) < min(count, len(points)) and near.max() > 1e-9:
        first.append(int(near.argmax()))
        near = np.minimum(near, _distances(points[first[-1:]], points)[0])
    return np.array(first)


class MTree:
    """Two routing levels over pages of vectors; page rows keep their distance to the page's routing vector."""

    def __init__(self, rows: np.ndarray, ids: np.ndarray, vectors: np.ndarray, most: float, how: MTreeSearch):
        self.how, self.most = how, most
        points = lifted(vectors, most)
        self.slack = 1e-6 * (np.sqrt(most) + 1)
        order, self.directory, self.pages = [], [], []
        done = 0
        for members in self._split(np.arange(len(ids)), points, max(1, -(-len(ids) // (how.page * how.fanout)))):
            routing = points[members].mean(axis=0)
            pages = []
            for page in self._split(members, points, max(1, -(-len(members) // how.page))):
                centre = points[page].mean(axis=0)
                out = _distances(centre[None], points[page])[0]
                page, out = page[np.argsort(out, kind="stable")], np.sort(out)
                pages.append((centre, out[-1], float(_distances(routing[None], centre[None])[0, 0]), done, done + len(page), out))
                order.append(page)
                done += len(page)
            reach = float(_distances(routing[None], points[members])[0].max())
            self.directory.append((routing, reach, len(self.pages), len(self.pages) + len(pages)))
            self.pages += pages
        order = np.concatenate(order)
        self.rows, self.ids, self.vectors = rows[order], ids[order], vectors[order]

    def _split(self, members: np.ndarray, points: np.ndarray, parts: int) -> list[np.ndarray]:
        """By nearest of spread-out members; equal points are cut by position, so no part exceeds its share by far."""
        if parts <= 1:
            return [members]
        own = points[members]
        step = max(1, len(members) // 512)
        chosen = own[::step][spread(own[::step], parts)]
        nearest = _distances(own, chosen).argmin(axis=1)
        limit = max(1, 2 * -(-len(members) // parts))
        out = []
        for c in range(len(chosen)):
            part = members[nearest == c]
            out += [part[i : i + limit] for i in range(0, len(part), limit)]
        return out

    def search(self, query_rows: np.ndarray, queries: np.ndarray, floor: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Per query the k best rows but its own, as flat arrays (query position, id, product).

        floor: a product that each query's k-th best is known to reach.
        """
        k, n = self.how.k, len(queries)
        best = np.full((n, k), np.iinfo(np.int64).min)
        best_id = np.full((n, k), np.iinfo(np.int64).max)
        limit = floor.copy()
        norms = (queries.astype(float) ** 2).sum(axis=1)
        points = np.concatenate([queries.astype(float), np.zeros((n, 1))], axis=1)

        def ceiling(distance: np.ndarray, norm: np.ndarray) -> np.ndarray:
            """The largest product at a distance of at least this."""
            return (norm + self.most - np.maximum(distance - self.slack, 0) ** 2) / 2 + 1e-6 * (norm + self.most)

        to_directory = _distances(points, np.array([d[0] for d in self.directory]))
        reach = np.array([d[1] for d in self.directory])
        # pages by the triangle inequality over the stored distance to the parent, before any is measured
        parent = np.repeat(np.arange(len(self.directory)), [d[3] - d[2] for d in self.directory])
        centres, radius = np.array([p[0] for p in self.pages]), np.array([p[1] for p in self.pages])
        up = np.array([p[2] for p in self.pages])
        rough = np.maximum(np.abs(to_directory[:, parent] - up) - radius, (to_directory - reach)[:, parent])
        open_ = ceiling(rough, norms[:, None]) >= limit[:, None]
        far = np.full(open_.shape, np.inf)
        for p in np.flatnonzero(open_.any(axis=0)):
            at = np.flatnonzero(open_[:, p])
            far[at, p] = _distances(points[at], centres[p : p + 1])[:, 0]
        bound = far - radius
        turn = np.argsort(bound, axis=1, kind="stable")  # nearest page first
        todo = np.arange(n)
        for step in range(len(self.pages)):
            page = turn[todo, step]
            can = ceiling(bound[todo, page], norms[todo]) >= limit[todo]
            todo, page = todo[can], page[can]  # later pages of a query are farther still
            if not len(todo):
                break
            for p in np.unique(page):
                at = todo[page == p]
                lo, hi, out = self.pages[p][3:]
                # rows by their stored distance to the routing vector: none with |d(q, c) - d(v, c)| too large
                room = np.sqrt(np.maximum(norms[at] + self.most - 2.0 * (limit[at].astype(float) - 1), 0)) + 2 * self.slack
                a = lo + np.searchsorted(out, (far[at, p] - room).min() - self.slack)
                b = lo + np.searchsorted(out, (far[at, p] + room).max() + self.slack, side="right")
                if a >= b:
                    continue
                got = products(queries[at], self.vectors[a:b])
                ids = np.broadcast_to(self.ids[a:b], got.shape)
                own = self.rows[a:b][None, :] == query_rows[at][:, None]
                got = np.where(own, np.iinfo(np.int64).min, got)
                ids = np.where(own, np.iinfo(np.int64).max, ids)
                both, names = np.concatenate([best[at], got], axis=1), np.concatenate([best_id[at], ids], axis=1)
                rank = np.lexsort((names, -both.astype(float)), axis=1)[:, :k] if np.abs(both).max() < 2**53 else np.lexsort((names, ~both), axis=1)[:, :k]
                best[at], best_id[at] = np.take_along_axis(both, rank, 1), np.take_along_axis(names, rank, 1)
                limit[at] = np.maximum(limit[at], best[at][:, -1])
        q, r = np.nonzero((best_id != np.iinfo(np.int64).max) | (best != np.iinfo(np.int64).min))
        return q, best_id[q, r], best[q, r]


def top_k(vectors: DataFrame, queries: Column, how: MTreeSearch = MTreeSearch()) -> DataFrame:
    """vectors: id bigint, v array<bigint> (nulls take no part); queries: which rows ask.

    Returns query_id, rank, id, score: each asking row's k best other rows.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "mtree")
    # rows are numbered once, in the written table, so that a row stays itself when a task runs again
    vectors = scratch.save(vectors.select("id", "v", queries.alias("asks")).where("id is not null and v is not null").withColumn("row", F.monotonically_increasing_id()), "vectors")
    norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x)
    rows, most, width = vectors.agg(F.count(F.lit(1)), F.coalesce(F.max(norm), F.lit(0.0)), F.coalesce(F.max(F.size("v")), F.lit(0))).first()
    empty = "query_id bigint, rank int, id bigint, score bigint"
    if not rows:
        return spark.createDataFrame([], empty)
    drawn = bounded_rows(vectors, "row", how.sample_rows).orderBy("id", "v").toArrow()
    known, known_rows = _matrix(drawn["v"], width), drawn["row"].to_numpy()
    routing = lifted(known, most)
    routing = routing[spread(routing, how.cells)] if len(routing) else np.zeros((1, width + 1))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                far = _distances(lifted(_matrix(batch.column(2), width), most), routing)
                cell = far.argmin(axis=1)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell.astype(np.int32)), pa.array(far[np.arange(len(cell)), cell])], names=["row", "id", "v", "cell", "out"])

    placed = scratch.save(vectors.select("row", "id", "v").mapInArrow(place, "row bigint, id bigint, v array<bigint>, cell int, out double"), "placed")
    cells = placed.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("out").alias("reach")).toArrow()
    chunks = {c: (-(-n // how.chunk_rows), r) for c, n, r in zip(*(cells[x].to_pylist() for x in ("cell", "n", "reach")), strict=True)}
    asked = vectors.where("asks").select("row", "id", "v")
    slices = max(1, -(-asked.count() // how.slice_rows))
    centres = np.array([routing[c] for c in chunks])
    reach, parts, names = np.array([r for _, r in chunks.values()]), np.array([p for p, _ in chunks.values()]), np.array(list(chunks))
    slack = 1e-6 * (np.sqrt(most) + 1)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row for each chunk that may hold one of the query's k best."""
        for batch in batches:
            if not batch.num_rows:
                continue
            own_rows, ids, q = batch.column(0).to_numpy(), batch.column(1).to_numpy(), _matrix(batch.column(2), width)
            for lo in range(0, len(q), 256):
                part, own = q[lo : lo + 256], own_rows[lo : lo + 256]
                got = products(part, known)
                got[own[:, None] == known_rows[None, :]] = np.iinfo(np.int64).min
                low = np.partition(got, -how.k, axis=1)[:, -how.k] if got.shape[1] >= how.k else np.full(len(part), np.iinfo(np.int64).min)
                far = _distances(np.concatenate([part.astype(float), np.zeros((len(part), 1))], axis=1), centres)
                square = (part.astype(float) ** 2).sum(axis=1)[:, None]
                fits = (square + most - np.maximum(far - reach - slack, 0) ** 2) / 2 + 1e-6 * (square + most) >= low[:, None]
                r, c = np.nonzero(fits)
                times = parts[c]
                r, c = np.repeat(r, times), np.repeat(c, times)
                salt = np.arange(len(r)) - np.repeat(np.cumsum(times) - times, times)
                cut = (mix64(own.astype(np.uint64)) % np.uint64(slices)).astype(np.int32)
                wide = pa.array(np.ascontiguousarray(part[r]).reshape(-1))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(r) + 1, dtype=np.int32) * width), wide)
                columns = names[c].astype(np.int32), salt.astype(np.int32), cut[r], own[r], ids[lo : lo + 256][r], lists, low[r]
                yield pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in columns], names=["cell", "salt", "cut", "row", "id", "v", "low"])

    salts = F.create_map(*[x for c, (p, _) in chunks.items() for x in (F.lit(c), F.lit(p))])
    salt = F.pmod(F.xxhash64("row"), salts[F.col("cell")]).cast("int").alias("salt")
    data = placed.select("cell", salt, F.explode(F.sequence(F.lit(0), F.lit(slices - 1))).alias("cut"), "row", "id", "v", F.lit(None).cast("bigint").alias("low"))
    wanted = asked.mapInArrow(ask, "cell int, salt int, cut int, row bigint, id bigint, v array<bigint>, low bigint")

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come by (cell, salt, cut), vectors (without low) first: those make a tree, then queries pass through it."""
        here, held, tree = None, [], None
        for batch in batches:
            keys = np.stack([batch.column(i).to_numpy() for i in range(3)] + [np.array(batch.column(6).is_valid(), bool)], axis=1) if batch.num_rows else np.zeros((0, 4))
            cuts = np.concatenate(([0], np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1, [len(keys)])) if len(keys) else [0]
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                part = batch.slice(lo, hi - lo)
                if here != (now := tuple(keys[lo, :3].tolist())):
                    here, held, tree = now, [], None
                if not keys[lo, 3]:
                    held.append((part.column(3).to_numpy(), part.column(4).to_numpy(), _matrix(part.column(5), width)))
                    continue
                if tree is None and held:
                    tree, held = MTree(*map(np.concatenate, zip(*held, strict=True)), most, how), []
                if tree is None:
                    continue
                asking, ids, low, wide = part.column(3).to_numpy(), part.column(4).to_numpy(), part.column(6).to_numpy(), _matrix(part.column(5), width)
                for at in range(0, len(ids), 512):
                    q, found, score = tree.search(asking[at : at + 512], wide[at : at + 512], low[at : at + 512])
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (asking[at + q], ids[at + q], found, score)], names=["row", "query_id", "id", "score"])

    keys = ("cell", "salt", "cut")
    both = data.unionByName(wanted).repartition(*keys).sortWithinPartitions(*keys, F.col("low").isNotNull())
    near = both.mapInArrow(meet, "row bigint, query_id bigint, id bigint, score bigint")
    ranked = near.withColumn("rank", F.row_number().over(Window.partitionBy("row").orderBy(F.desc("score"), "id")))
    return ranked.where(F.col("rank") <= how.k).select("query_id", "rank", "id", "score")
