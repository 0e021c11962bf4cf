"""Distances on the road network.

Worker engines hold the road in compressed rows: its size is checked against ``ROAD_LIMIT`` before it is
broadcast. It is packed by Spark's tasks, partition by partition, so that the driver only passes the packed bytes
on. ``relaxed`` is the way beyond that limit, which ``from_sources`` and ``between`` take by themselves,
and the test of equality; ``labels`` answers pairs by a join on shared hubs, and is built within that limit.
Lengths that are positive integers are searched from many sources at once, a bucket of equal distances a step;
other lengths by a heap, source by source.

A plan takes the output of a search to be as small as its input. What comes from one is hinted to be merged in joins,
or it would be broadcast through the driver, whole.
"""

from __future__ import annotations

import heapq
import pickle
import zlib
from collections.abc import Iterator
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import keep

#: Directed edges of a road that may be broadcast (a few bytes each while packed, 8 or 12 in a worker).
ROAD_LIMIT = 20_000_000
#: Cells of a table of distances by source and vertex that a worker fills at once.
CELLS = 4_000_000


class Rows:
    """Adjacency in compressed rows over arbitrary vertex ids."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, length: np.ndarray):
        self.ids = np.unique(np.concatenate([src, dst])) if len(src) else np.zeros(0, np.int64)
        s, d = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        order = np.argsort(s, kind="stable")
        self.first = np.searchsorted(s[order], np.arange(len(self.ids) + 1))
        self.to, self.len = d[order].astype(np.int32), length[order]
        self._near: list | None = None
        #: lengths suit a search by buckets: whole, and so short that many vertices share a distance; distances fit in 32 bits
        most = int(length.max()) if len(length) else 0
        self.stepped = self.len.dtype.kind in "iu" and (not len(length) or length.min() > 0 and 16 * most <= len(self.ids) and most * (len(self.ids) + 1) < 1 << 31)
        if self.stepped:
            self.len = self.len.astype(np.int32)

    def neighbours(self) -> list[list[tuple[int, float]]]:
        if self._near is None:
            to, length = self.to.tolist(), self.len.tolist()
            self._near = [list(zip(to[a:b], length[a:b], strict=True)) for a, b in zip(self.first[:-1].tolist(), self.first[1:].tolist(), strict=True)]
        return self._near

    def cells(self) -> tuple[memoryview, memoryview, memoryview]:
        """first, to and len for a step at a time: lists of all neighbours take 400 bytes a vertex."""
        return memoryview(self.first), memoryview(self.to), memoryview(self.len)

    def index(self, v: int) -> int | None:
        i = int(np.searchsorted(self.ids, v))
        return i if i < len(self.ids) and self.ids[i] == v else None

    def places(self, v: np.ndarray) -> np.ndarray:
        """The index of each vertex, -1 for those not on the road."""
        if not len(self.ids):
            return np.full(len(v), -1)
        i = np.minimum(np.searchsorted(self.ids, v), len(self.ids) - 1)
        return np.where(self.ids[i] == v, i, -1)

    def out(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Head, length and place in ``v`` of every edge that leaves one of ``v``."""
        lo = self.first[v]
        size = self.first[v + 1] - lo
        which = np.repeat(np.arange(len(v)), size)
        e = np.arange(len(which)) + np.repeat(lo - (np.cumsum(size) - size), size)
        return self.to[e], self.len[e], which

    def distances(self, starts: np.ndarray, wanted: list[np.ndarray] | None = None, within: float | None = None) -> np.ndarray:
        """dist[i, v] from each start, -1 where no way leads (or, with ``wanted``, perhaps where none is wanted; or farther than ``within``).

        All starts go on together, one step a distance. A start with ``wanted`` vertices leaves off once these are reached.
        """
        n, m, none = len(self.ids), len(starts), np.iinfo(np.int32).max
        dist, mark = np.full(m * n, none, np.int32), np.empty(m * n, np.int32)
        keys = np.arange(m) * n + starts
        dist[keys] = 0
        buckets, heap, check, going = {0: [keys]}, [0], 8, None
        while heap:
            d = heapq.heappop(heap)
            if wanted is not None and d > check:
                # what is nearer than d is final
                going = np.array([bool((dist[i * n + w] >= d).any()) for i, w in enumerate(wanted)])
                check = d + max(8, d // 4)
            keys = np.concatenate(buckets.pop(d))
            keys = keys[dist[keys] == d]
            if going is not None:
                keys = keys[going[keys // n]]
            nth = np.arange(len(keys), dtype=np.int32)
            mark[keys] = nth
            keys = keys[mark[keys] == nth]
            v = keys % n
            to, length, which = self.out(v)
            at, new = (keys - v)[which] + to, d + length
            good = new < dist[at] if within is None else (new < dist[at]) & (new <= within)
            at, new = at[good], new[good]
            order = np.argsort(new - d if len(new) and new.max() - d > 255 else (new - d).astype(np.uint8), kind="stable")[::-1]
            at, new = at[order], new[order]
            dist[at] = new  # the last one written, the least, stays
            good = dist[at] == new
            at, new = at[good], new[good]
            cuts = np.flatnonzero(np.diff(new)) + 1
            for piece, x in zip(np.split(at, cuts), new[np.r_[0, cuts]].tolist() if len(new) else [], strict=False):
                if x not in buckets:
                    buckets[x] = []
                    heapq.heappush(heap, x)
                buckets[x].append(piece)
        dist[dist == none] = -1
        return dist.reshape(m, n)


class Cells:
    """The road in cells, nested in the given groups of its vertices, so that a way is put together from pieces that cross one cell each.

    Groups are halved in turn by column and by row of the square layout until a cell has ``cap`` vertices on average. A border is a vertex with an
    edge to or from another cell; those of a cell are numbered together, cells of a group too.
    """

    #: Farther than any distance; the sum of three fits in 32 bits.
    NONE = 1 << 29

    def __init__(self, rows: Rows, group: np.ndarray, cap: int):
        self.rows, n = rows, len(rows.ids)
        side = ceil(n**0.5)
        x, y = rows.ids % max(side, 1), rows.ids // max(side, 1)
        cell = np.unique(group, return_inverse=True)[1]
        while n > cap * (cell.max(initial=0) + 1):
            for first, second in ((x, y), (y, x)):
                order, size = np.lexsort((second, first, cell)), np.bincount(cell)
                nth = np.empty(n, np.int64)
                nth[order] = np.arange(n) - (np.cumsum(size) - size)[cell[order]]
                cell = np.unique(2 * cell + (2 * nth >= size[cell]), return_inverse=True)[1]
        self.cell, self.count = cell, int(cell.max(initial=-1)) + 1
        self.order = np.argsort(cell, kind="stable")
        self.begin = np.searchsorted(cell[self.order], np.arange(self.count + 1))
        src = np.repeat(np.arange(n), np.diff(rows.first))
        over = cell[src] != cell[rows.to]
        src, dst, length = src[over], rows.to[over].astype(np.int64), rows.len[over]
        ends = np.unique(np.r_[src, dst])
        self.border = ends[np.argsort(cell[ends], kind="stable")]
        self.of = cell[self.border]
        self.first = np.searchsorted(self.of, np.arange(self.count + 1))
        self.nth, self._at = np.full(n, -1), np.empty(n, np.int32)
        self.nth[self.border] = np.arange(len(self.border))
        # edges between cells by the cell they leave; heads sorted, so that the least of each is taken at once
        by = np.lexsort((dst, cell[src]))
        self.over = self.nth[src[by]], self.nth[dst[by]], length[by], np.searchsorted(cell[src[by]], np.arange(self.count + 1))

    def own(self, c: int) -> np.ndarray:
        return self.order[self.begin[c] : self.begin[c + 1]]

    def inside(self, c: int) -> np.ndarray:
        """dist[i, j] from each border of a cell to each of its vertices, ``own``, by ways inside it, ``NONE`` without one."""
        own = self.own(c)
        to, length, which = self.rows.out(own)
        good = self.cell[to] == c
        at = self._at
        at[own] = np.arange(len(own))
        # a loop at each vertex: those without an edge inside count, too
        some = Rows(np.r_[which[good], np.arange(len(own))], np.r_[at[to[good]], np.arange(len(own))], np.r_[length[good], np.ones(len(own), length.dtype)])
        dist = some.distances(at[self.border[self.first[c] : self.first[c + 1]]])
        dist[dist < 0] = self.NONE
        return dist

    def between(self, tables: list[np.ndarray], starts: np.ndarray, lo: int, hi: int) -> np.ndarray:
        """dist[i, j] from the start j, a border, to the border i of the cells ``lo`` to ``hi``; of others no more than an upper bound.

        ``tables`` has the distances between the borders of each cell by ways inside it. A cell whose borders have come nearer passes this on, the
        nearest cells first; what is no nearer than all that is asked for is not passed on.
        """
        tail, head, length, edge = self.over
        dist = np.full((len(self.border), len(starts)), self.NONE, np.int32)
        dist[self.nth[starts], np.arange(len(starts))] = 0
        fresh = np.zeros(len(self.border), bool)
        fresh[self.nth[starts]] = True
        due = np.full(self.count, self.NONE, np.int64)
        due[self.of[self.nth[starts]]] = 0
        asked, steps, last = slice(self.first[lo], self.first[hi]), 0, np.full(len(starts), self.NONE, np.int32)
        while due[c := int(due.argmin())] < self.NONE:
            due[c] = self.NONE
            if steps % 32 == 0:
                last = dist[asked].max(0)
            steps += 1
            a, b = self.first[c], self.first[c + 1]
            own, table, old = dist[a:b], tables[c], dist[a:b].copy()
            from_, buffer = np.flatnonzero(fresh[a:b]), np.empty_like(own)
            fresh[a:b] = False
            for i in from_.tolist():
                np.add(table[i][:, None], old[i][None, :], out=buffer)
                np.minimum(own, buffer, out=own)
            moved = (own < old).any(1)
            moved[from_] = True
            e = np.arange(edge[c], edge[c + 1])
            e = e[moved[tail[e] - a]]
            if not len(e):
                continue
            new = dist[tail[e]] + length[e][:, None]
            heads = np.flatnonzero(np.r_[True, np.diff(head[e]) != 0])
            new, to = np.minimum.reduceat(new, heads, axis=0), head[e][heads]
            now = dist[to]
            nearer = new < np.minimum(now, last)
            if not nearer.any():
                continue
            dist[to] = np.where(nearer, new, now)
            any_ = nearer.any(1)
            fresh[to[any_]] = True
            np.minimum.at(due, self.of[to[any_]], np.where(nearer, new, self.NONE)[any_].min(1))
        return dist


def _less(c: np.ndarray) -> tuple[bool, str, bytes]:
    """A column as steps of few bytes (of integers), compressed."""
    if whole := c.dtype.kind in "iu":
        c = np.diff(c.astype(np.int64), prepend=0)
        c = c.astype(np.promote_types(np.min_scalar_type(c.min()), np.min_scalar_type(c.max()))) if len(c) else c
    return whole, c.dtype.str, zlib.compress(np.ascontiguousarray(c), 6)


def _whole(whole: bool, kind: str, data: bytes) -> np.ndarray:
    c = np.frombuffer(zlib.decompress(data), kind)
    return np.cumsum(c, dtype=np.int64) if whole else c


class Packed:
    """Columns of a table in pieces of compressed bytes; unpacked once in each worker that asks."""

    def __init__(self, parts: list[bytes], kind: type | None):
        self.parts, self.kind, self._made = parts, kind, None

    def made(self):
        if self._made is None:
            # a column at a time: all pieces together take twice the space
            rows = [pickle.loads(p) for p in self.parts]
            columns = [np.concatenate([_whole(*c) for c in pieces]) for pieces in zip(*rows, strict=True)]
            rows = None
            self._made = columns if self.kind is None else self.kind(*columns)
        return self._made

    def __getstate__(self):
        return self.parts, self.kind

    def __setstate__(self, state):
        self.__init__(*state)


class Shared:
    """A broadcast ``Packed``: ``value`` is what it unpacks to."""

    def __init__(self, packed):
        self.packed = packed

    @property
    def value(self):
        return self.packed.value.made()


def share(df: DataFrame, kind: type | None = None) -> Shared:
    """Numeric columns without nulls, packed in Spark's tasks and broadcast; their order of rows is open. The caller checks the size."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = list(batches)
        if sum(len(b) for b in batches):
            columns = [c.to_numpy() for c in pa.Table.from_batches(batches).columns]
            order = np.lexsort(columns[::-1])
            yield pa.RecordBatch.from_pydict({"data": pa.array([packed(*(c[order] for c in columns))], pa.binary())})

    return gathered(df.mapInArrow(pack, "data binary"), kind, packed(*(np.zeros(0, np.float64 if t == "double" else np.int64) for _, t in df.dtypes)))


def packed(*columns: np.ndarray) -> bytes:
    return pickle.dumps([_less(c) for c in columns])


def gathered(pieces: DataFrame, kind: type | None, empty: bytes | None = None) -> Shared:
    """Pieces (data) made by ``packed``, broadcast."""
    rows = pieces.collect()
    return Shared(pieces.sparkSession.sparkContext.broadcast(Packed([bytes(r["data"]) for r in rows] or [empty], kind)))


def whole(road: DataFrame, vertices: int) -> bool:
    """Lengths are positive integers, and ways over all vertices are nearer than ``Cells.NONE``."""
    if dict(road.dtypes)["len"] not in ("tinyint", "smallint", "int", "bigint"):
        return False
    ends = road.agg(F.min("len").alias("lo"), F.max("len").alias("hi")).first()
    return ends["lo"] is not None and ends["lo"] > 0 and ends["hi"] * (vertices + 1) < Cells.NONE


def tasks(df: DataFrame) -> int:
    """Tasks for rows that are few and cost much each: a number that is not lowered for their few bytes."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


class Search:
    """A shortest-path search that can be carried on: settled distances grow with the radius asked for."""

    def __init__(self, rows: Rows, source: int):
        self.cells, self.settled = rows.cells(), {}
        start = rows.index(source)
        self.heap = [] if start is None else [(0, start)]

    def until(self, radius: float) -> bool:
        """Settle all within ``radius``; False when nothing is left beyond."""
        heap, settled, (first, heads, lengths) = self.heap, self.settled, self.cells
        while heap and heap[0][0] <= radius:
            d, v = heapq.heappop(heap)
            if v in settled:
                continue
            settled[v] = d
            a, b = first[v], first[v + 1]
            for to, length in zip(heads[a:b].tolist(), lengths[a:b].tolist(), strict=True):
                if to not in settled:
                    heapq.heappush(heap, (d + length, to))
        return bool(heap)


def broadcast_rows(road: DataFrame):
    """The road as a broadcast ``Rows``, or an error if it is larger than may be broadcast. A kept road is packed and passed on once."""
    n = edges(road)
    if n > ROAD_LIMIT:
        raise ValueError(f"a road of {n} edges is too large to broadcast; use relaxed()")
    shared = getattr(road, "_shared", None) or share(road.select("src", "dst", "len"), Rows)
    if getattr(road, "_kept", False):
        road._shared = shared
    return shared


def edges(road: DataFrame) -> int:
    """Rows of a road; those of a kept one are counted once."""
    n = getattr(road, "_edges", None)
    n = road.count() if n is None else n
    if getattr(road, "_kept", False):
        road._edges = n
    return n


def _runs(batches: Iterator[pa.RecordBatch], by: str, most: int) -> Iterator[pa.Table]:
    """Tables of whole runs of equal ``by`` (sorted batches), of ``most`` different values at most."""
    held: list[pa.Table] = []

    def ends(table: pa.Table) -> np.ndarray:
        return np.r_[0, np.flatnonzero(np.diff(table[by].to_numpy())) + 1, len(table)]

    def cut(table: pa.Table, last: bool):
        at = ends(table)
        whole = len(at) - 1 if last else (len(at) - 2) // most * most
        for i in range(0, whole, most):
            yield table.slice(int(at[i]), int(at[min(i + most, whole)] - at[i]))
        return table.slice(int(at[whole]))

    for batch in batches:
        if not len(batch):
            continue
        held.append(pa.Table.from_batches([batch]))
        if sum(map(len, held)) >= CELLS // 4 or len(held) % 16 == 0:
            held = [(yield from cut(pa.concat_tables(held), False))]
    if sum(map(len, held)):
        yield from cut(pa.concat_tables(held), True)


def from_sources(road: DataFrame, sources: DataFrame, within: float | None = None) -> DataFrame:
    """src, v, dist: shortest distance from every ``v`` of sources to every vertex that it reaches, or that lies ``within`` a distance."""
    road = keep(road, "road")
    if edges(road) > ROAD_LIMIT:
        return relaxed(road, _on_road(road, sources.select("v")), within)
    shared, kind = broadcast_rows(road), dict(road.dtypes)["len"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        every = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
        if not sum(map(len, every)):
            return
        rows = shared.value
        starts = rows.places(np.concatenate(every))
        starts = starts[starts >= 0]
        each = max(1, CELLS // max(1, len(rows.ids))) if rows.stepped else 1
        for i in range(0, len(starts), each):
            few = starts[i : i + each]
            if rows.stepped:
                found = [(np.flatnonzero(d >= 0), d[d >= 0]) for d in rows.distances(few, within=within)]
            else:
                search = Search(rows, int(rows.ids[few[0]]))
                search.until(float("inf") if within is None else within)
                found = [(np.fromiter(search.settled.keys(), np.int64, len(search.settled)), np.fromiter(search.settled.values(), np.float64, len(search.settled)))]
            for s, (at, dist) in zip(few.tolist(), found, strict=True):
                yield pa.RecordBatch.from_pydict({"src": np.full(len(at), rows.ids[s]), "v": rows.ids[at], "dist": dist.astype(np.float64)})

    return sources.select("v").where("v is not null").distinct().repartition(tasks(road), "v").mapInArrow(work, "src long, v long, dist double").withColumn("dist", F.col("dist").cast(kind)).hint("merge")


def between(road: DataFrame, pairs: DataFrame) -> DataFrame:
    """a, b, dist of (a, b) pairs: the search from a ends when all its b are settled, so near pairs are cheap."""
    road = keep(road, "road")
    if edges(road) > ROAD_LIMIT:
        rows = pairs.select("a", "b").distinct()
        reach = relaxed(road, _on_road(road, rows.select(F.col("a").alias("v"))))
        return rows.join(reach.select(F.col("src").alias("a"), F.col("v").alias("b"), "dist"), ["a", "b"]).select("a", "b", "dist")
    shared, kind = broadcast_rows(road), dict(road.dtypes)["len"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = None
        for table in _runs(batches, "a", max(1, CELLS // max(1, len((rows := shared.value).ids)))):
            a, b = table["a"].to_numpy(), table["b"].to_numpy()
            i, j = rows.places(a), rows.places(b)
            good = (i >= 0) & (j >= 0)
            a, b, i, j = a[good], b[good], i[good], j[good]
            starts, nth = np.unique(i, return_inverse=True)
            wanted = [j[nth == x] for x in range(len(starts))] if len(starts) < 9 else np.split(j[(order := np.argsort(nth, kind="stable"))], np.flatnonzero(np.diff(nth[order])) + 1)
            if rows.stepped:
                dist = rows.distances(starts, wanted)[nth, j].astype(np.float64) if len(starts) else np.zeros(0)
            else:
                dist = np.full(len(a), -1.0)
                for x, ends in enumerate(wanted):
                    search, radius, more = Search(rows, int(rows.ids[starts[x]])), 8.0, True
                    while more and not all(e in search.settled for e in ends.tolist()):
                        more = search.until(radius)
                        radius *= 2
                    dist[nth == x] = [search.settled.get(e, -1.0) for e in j[nth == x].tolist()]
            known = dist >= 0
            yield pa.RecordBatch.from_pydict({"a": a[known], "b": b[known], "dist": dist[known]})

    rows = pairs.select("a", "b").where("a is not null and b is not null").distinct().repartition(tasks(road), "a").sortWithinPartitions("a")
    return rows.mapInArrow(work, "a long, b long, dist double").withColumn("dist", F.col("dist").cast(kind)).hint("merge")


def _on_road(road: DataFrame, vertices: DataFrame) -> DataFrame:
    return vertices.distinct().join(road.select(F.col("src").alias("v")).union(road.select("dst")).distinct(), "v", "left_semi")


def relaxed(road: DataFrame, sources: DataFrame, within: float | None = None) -> DataFrame:
    """The same by rounds of joins: only vertices that got nearer in a round are carried to the next."""
    found = keep(sources.select(F.col("v").alias("src"), "v").distinct().withColumn("dist", F.lit(0).cast(dict(road.dtypes)["len"])), "dist")
    ways, front = road.select(F.col("src").alias("v"), "dst", "len"), found
    while True:
        step = front.join(ways, "v").groupBy("src", F.col("dst").alias("v")).agg(F.min(F.col("dist") + F.col("len")).alias("new"))
        step = step if within is None else step.where(F.col("new") <= within)
        better = keep(step.join(found, ["src", "v"], "left").where("dist is null or new < dist").select("src", "v", F.col("new").alias("dist")), "front")
        if better.isEmpty():
            return found
        found = keep(found.join(better.select("src", "v"), ["src", "v"], "left_anti").union(better), "dist")
        front = better


def labels(road: DataFrame) -> DataFrame:
    """label(v, hub, dist) by pruned searches from the best-connected vertices first; built in one task."""
    shared = broadcast_rows(road)

    def build(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if not len(frame):
                continue
            rows = shared.value
            near, n = rows.neighbours(), len(rows.ids)
            label: list[dict[int, float]] = [{} for _ in range(n)]
            # recursive halving of the id range puts separators of a row-by-row layout first
            order, spans = [], [(0, n)]
            for lo, hi in spans:
                if lo < hi:
                    mid = (lo + hi) // 2
                    order.append(mid)
                    spans += [(lo, mid), (mid + 1, hi)]
            for hub in order:
                own, heap, done = label[hub], [(0, hub)], set()
                while heap:
                    d, v = heapq.heappop(heap)
                    if v in done:
                        continue
                    done.add(v)
                    small, large = (own, label[v]) if len(own) < len(label[v]) else (label[v], own)
                    if any(h in large and x + large[h] <= d for h, x in small.items()):
                        continue
                    label[v][hub] = d
                    for to, length in near[v]:
                        if to not in done:
                            heapq.heappush(heap, (d + length, to))
            yield pd.DataFrame([(int(rows.ids[v]), int(rows.ids[h]), float(d)) for v in range(n) for h, d in label[v].items()], columns=["v", "hub", "dist"])

    one = road.sparkSession.range(1, numPartitions=1)
    return one.mapInPandas(build, "v long, hub long, dist double").withColumn("dist", F.col("dist").cast(dict(road.dtypes)["len"])).hint("merge")


def label_distances(label: DataFrame, pairs: DataFrame) -> DataFrame:
    """a, b, dist of (a, b) pairs: the best shared hub."""
    left = label.select(F.col("v").alias("a"), "hub", F.col("dist").alias("d1"))
    right = label.select(F.col("v").alias("b"), "hub", F.col("dist").alias("d2"))
    return pairs.select("a", "b").distinct().join(left, "a").join(right, ["b", "hub"]).groupBy("a", "b").agg(F.min(F.col("d1") + F.col("d2")).alias("dist"))


def site_distances(city, candidates: DataFrame, within: float | None = None) -> DataFrame:
    """poi, usr, dist: road distance between candidates and users, with the offsets of both; ``within`` a distance, if one is given."""
    sites = city.sites.join(candidates.select("poi"), "poi").select("poi", "v", "dis")
    # the way on the road is no longer than the whole, but for offsets below zero
    below = [df.agg(F.min("dis").alias("dis")).first()["dis"] or 0 for df in (sites, city.users)] if within is not None else []
    reach = from_sources(city.road, sites, None if within is None else within - sum(min(0, d) for d in below))
    out = F.broadcast(sites).join(reach, sites["v"] == reach["src"]).select("poi", sites["dis"].alias("d1"), reach["v"].alias("at"), "dist")
    # all users: no broadcast, which would pass through the driver
    every = out.join(city.users.hint("merge"), out["at"] == city.users["v"]).select("poi", "usr", (F.col("d1") + F.col("dist") + F.col("dis")).alias("dist"))
    return every if within is None else every.where(F.col("dist") <= within)
