"""The keyword-Voronoi tree: a road partition, inverted files of its nodes, and nearest places by keyword.

A node is the path of its splits ("" is the root, "03" a child of "0"), so ancestors are prefixes and every
level comes out of the leaf paths by ``substring``.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, replace
from math import ceil, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import City
from ..sources import keep
from . import roads

FANOUT = 4
#: Keywords of a user up to which all their subsets are indexed.
KEYS = 4
#: Levels from the leaves up on which distances between borders and users are indexed.
NEAR_LEVELS = 2
#: Vertices of a cell of the road, on average: ways to nodes of many cells are put together from ways inside cells.
CELL = 900
#: Borders whose ways to a node are put together at once.
TOGETHER = 128
#: The relations of an index beside the members of its nodes.
PARTS = frozenset({"border", "terms", "nearest", "postings", "sets", "holders", "ranges"})


@dataclass(frozen=True)
class Tree:
    """member(v, leaf); border(node, v); terms(node, term, n_users, n_pois); nearest(term, v, poi, dist) of frequent
    keywords at borders; postings(term, poi, w_m) of the others; sets(node, parent, cls, n_users): keyword sets that some user of
    the node holds (with others, perhaps); holders(leaf, cls, usr, key); ranges(node, b, lo, hi): how far users are from a border."""

    depth: int
    member: DataFrame
    border: DataFrame
    terms: DataFrame
    nearest: DataFrame
    postings: DataFrame
    sets: DataFrame
    holders: DataFrame
    ranges: DataFrame


def depth_of(vertices: int, leaf_cap: int) -> int:
    return max(1, ceil(log(max(vertices / leaf_cap, 1.0001), FANOUT)))


def partition(road: DataFrame, leaf_cap: int = 100, depth: int | None = None) -> tuple[DataFrame, int]:
    """member(v, leaf) and the depth: each node is halved by column, then each half by row, of the square layout.

    Without a ``depth``, as many levels as leaves of ``leaf_cap`` vertices need.
    """
    v = road.select(F.col("src").alias("v")).distinct()
    n = v.count()
    side = ceil(n**0.5)
    depth = depth or depth_of(n, leaf_cap)
    out = v.select("v", (F.col("v") % side).alias("x"), F.floor(F.col("v") / side).alias("y"), F.lit("").alias("leaf"))
    for _ in range(depth):
        out = out.withColumn("half", F.ntile(2).over(Window.partitionBy("leaf").orderBy("x", "v")) - 1)
        out = out.withColumn("rest", F.ntile(2).over(Window.partitionBy("leaf", "half").orderBy("y", "v")) - 1)
        out = out.withColumn("leaf", F.concat("leaf", (2 * F.col("half") + F.col("rest")).cast("string")))
    return out.select("v", "leaf"), depth


def _levels(depth: int):
    return F.explode(F.sequence(F.lit(1), F.lit(depth)))


def borders(road: DataFrame, member: DataFrame, depth: int) -> DataFrame:
    """node, v: vertices with an edge that leaves their node, at every level."""
    ends = road.join(member.withColumnRenamed("v", "src").withColumnRenamed("leaf", "from"), "src").join(member.withColumnRenamed("v", "dst").withColumnRenamed("leaf", "to"), "dst").where("from <> to")
    every = ends.select(F.col("src").alias("v"), "from", "to", _levels(depth).alias("level"))
    return every.where(F.expr("substring(from, 1, level) <> substring(to, 1, level)")).select(F.expr("substring(from, 1, level)").alias("node"), "v").distinct()


def node_terms(city: City, member: DataFrame, depth: int) -> DataFrame:
    """node, term, n_users, n_pois for the root and every level below it."""
    users = city.users.join(member, "v").join(city.user_terms, "usr").select("leaf", "term", F.lit(1).alias("u"), F.lit(0).alias("p"))
    sites = city.sites.join(member, "v").join(city.site_terms.select("poi", "term"), "poi").select("leaf", "term", F.lit(0).alias("u"), F.lit(1).alias("p"))
    at = users.union(sites).groupBy("leaf", "term").agg(F.sum("u").alias("u"), F.sum("p").alias("p"))
    levels = at.select("term", "u", "p", "leaf", F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("level"))
    return levels.groupBy(F.expr("substring(leaf, 1, level)").alias("node"), "term").agg(F.sum("u").alias("n_users"), F.sum("p").alias("n_pois"))


def _nearest(rows: roads.Rows, v: np.ndarray, poi: np.ndarray, dis: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """size[v], and place and distance (a row of k a vertex) of the k nearest different places, from sources (v, poi, dis); ties: smaller poi.

    A step takes all that arrives at one distance. What a full vertex turns away is no farther from anything behind it.
    """
    n = len(rows.ids)
    names, p = np.unique(poi, return_inverse=True)
    size, got, far, m = np.zeros(n, np.int32), np.full((n, k), -1, np.int32), np.zeros((n, k), np.int32), len(names)
    buckets: dict[int, list[np.ndarray]] = {}
    heap: list[int] = []

    def put(keys: np.ndarray, dist: np.ndarray) -> None:
        order = np.argsort(dist, kind="stable")
        keys, dist = keys[order], dist[order]
        cuts = np.flatnonzero(np.diff(dist)) + 1
        for piece, x in zip(np.split(keys, cuts), dist[np.r_[0, cuts]].tolist() if len(dist) else [], strict=False):
            if x not in buckets:
                buckets[x] = []
                heapq.heappush(heap, x)
            buckets[x].append(piece)

    put(v.astype(np.int64) * m + p, dis)
    while heap:
        d = heapq.heappop(heap)
        keys = np.concatenate(buckets.pop(d))
        keys = np.unique(keys[size[keys // m] < k])
        at, q = keys // m, (keys % m).astype(np.int32)
        new = ~(got[at] == q[:, None]).any(1)
        at, q = at[new], q[new]
        head = np.r_[True, at[1:] != at[:-1]] if len(at) else np.zeros(0, bool)
        nth = np.arange(len(at)) - np.flatnonzero(head)[np.cumsum(head) - 1] + size[at]
        fit = nth < k
        at, q, nth = at[fit], q[fit], nth[fit]
        got[at, nth], far[at, nth] = q, d
        np.maximum.at(size, at, nth.astype(np.int32) + 1)
        to, length, which = rows.out(at)
        open_ = size[to] < k
        put(to[open_].astype(np.int64) * m + q[which[open_]], d + length[open_])
    return size, names[got] if len(names) else got, far


def k_nearest(city: City, k: int, min_df: int = 0, at: DataFrame | None = None) -> DataFrame:
    """term, v, poi, dist: the k nearest places of each keyword from each vertex, offset of the place included.

    One search a keyword, with all its places as sources; a vertex takes the first k different ones that
    reach it (ties: smaller id). k = 1 gives the keyword's Voronoi diagram. With ``at`` (term, v), only the
    rows of these are given out.
    """
    road = keep(city.road, "road")
    shared, asked = roads.broadcast_rows(road), at is not None

    def by_heap(rows: roads.Rows, v: np.ndarray, poi: np.ndarray, dis: np.ndarray):
        near, n = rows.neighbours(), len(rows.ids)
        heap = list(zip(dis.tolist(), poi.tolist(), v.tolist(), strict=True))
        heapq.heapify(heap)
        taken: list[dict[int, float]] = [{} for _ in range(n)]
        while heap:
            d, p, i = heapq.heappop(heap)
            got = taken[i]
            if p in got or len(got) >= k:
                continue
            got[p] = d
            for to, length in near[i]:
                other = taken[to]
                if len(other) < k and p not in other:
                    heapq.heappush(heap, (d + length, p, to))
        size = np.array([len(t) for t in taken], np.int32)
        full = [[*t.items(), *[(0, 0)] * (k - len(t))] for t in taken]
        return size, np.array([[p for p, _ in t] for t in full], np.int64).reshape(n, k), np.array([[d for _, d in t] for t in full]).reshape(n, k)

    def told(term: str, v: np.ndarray, poi: np.ndarray, dis: np.ndarray, only: np.ndarray) -> Iterator[pa.RecordBatch]:
        rows = shared.value
        i = rows.places(v)
        whole = rows.stepped and dis.dtype.kind in "iu" and (not len(dis) or dis.min() >= 0)
        size, got, far = (_nearest if whole else lambda *x: by_heap(*x[:-1]))(rows, i[i >= 0], poi[i >= 0], dis[i >= 0], k)
        out = rows.places(np.unique(only)) if asked else np.arange(len(rows.ids))
        out = out[out >= 0]
        for lo in range(0, len(out), 1 + (1 << 20) // k):
            some = out[lo : lo + 1 + (1 << 20) // k]
            held = np.arange(k) < size[some][:, None]
            yield pa.RecordBatch.from_pydict({"term": pa.repeat(term, int(held.sum())), "v": np.repeat(rows.ids[some], size[some]), "poi": got[some][held].astype(np.int64), "dist": far[some][held].astype(np.float64)})

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        term, held = None, []
        for batch in (*batches, None):
            names = batch["term"].dictionary_encode() if batch is not None else None
            code = names.indices.to_numpy(zero_copy_only=False) if names is not None else np.zeros(0, int)
            ends = np.r_[0, np.flatnonzero(np.diff(code)) + 1, len(code)] if len(code) else [0]
            for lo, hi in zip(ends[:-1], ends[1:], strict=True):
                word = names.dictionary[int(code[lo])].as_py()
                if word != term and held:
                    yield from finish(term, held)
                    held = []
                term = word
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from finish(term, held)

    def finish(term: str, held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v, poi, dis, source = (pa.Table.from_batches(held)[c].to_numpy() for c in ("v", "poi", "dis", "source"))
        yield from told(term, v[source], poi[source], dis[source], v[~source])

    terms = city.site_terms.select("term", "poi")
    if min_df > 1:
        terms = terms.join(split_terms(city.site_terms, min_df)[0], "term", "left_semi")
    group = terms.join(city.sites.where("v is not null").hint("merge"), "poi").select("term", "v", "poi", "dis", F.lit(True).alias("source"))
    if asked:
        zero = F.lit(0).cast(dict(city.sites.dtypes)["dis"])
        group = group.union(at.select("term", "v", F.lit(0).cast("long"), zero, F.lit(False)).where("v is not null").distinct())
    sorted_ = group.repartition(roads.tasks(road), "term").sortWithinPartitions("term")
    return sorted_.mapInArrow(work, "term string, v long, poi long, dist double").withColumn("dist", F.col("dist").cast("long")).hint("merge")


def split_terms(site_terms: DataFrame, min_df: int) -> tuple[DataFrame, DataFrame]:
    """(frequent terms, postings term/poi/w_m of the others): only frequent keywords get a diagram."""
    df = site_terms.groupBy("term").agg(F.count("*").alias("df"))
    frequent = df.where(F.col("df") >= min_df).select("term")
    return frequent, site_terms.join(frequent, "term", "left_anti").select("term", "poi", "w_m")


def owners(city: City) -> DataFrame:
    """term, v, poi, dist: the cells of all keyword Voronoi diagrams."""
    return k_nearest(city, 1)


def adjacency(road: DataFrame, owner: DataFrame, sites: DataFrame, site_terms: DataFrame) -> DataFrame:
    """term, poi_a < poi_b: cells that touch over an edge, and places of one keyword at one vertex."""
    a = owner.select("term", F.col("v").alias("src"), F.col("poi").alias("p"))
    b = owner.select("term", F.col("v").alias("dst"), F.col("poi").alias("q"))
    touch = road.select("src", "dst").join(a, "src").join(b, ["term", "dst"]).where("p <> q").select("term", F.least("p", "q").alias("poi_a"), F.greatest("p", "q").alias("poi_b"))
    at = site_terms.select("term", "poi").join(sites.select("poi", "v"), "poi")
    same = at.alias("x").join(at.alias("y"), (F.col("x.term") == F.col("y.term")) & (F.col("x.v") == F.col("y.v"))).where("x.poi < y.poi").select(F.col("x.term").alias("term"), F.col("x.poi").alias("poi_a"), F.col("y.poi").alias("poi_b"))
    return touch.union(same).distinct()


def compressed(owner: DataFrame, member: DataFrame, depth: int) -> tuple[DataFrame, DataFrame]:
    """(runs term/node/poi: largest nodes with one owner, exceptions term/v/poi: vertices that no run covers)."""
    at = owner.select("term", "v", "poi").join(member, "v")
    nodes = at.select("term", "poi", "leaf", F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("level")).groupBy("term", F.expr("substring(leaf, 1, level)").alias("node")).agg(F.min("poi").alias("poi"), F.max("poi").alias("hi")).where("poi = hi").select("term", "node", "poi")
    up = nodes.select("term", F.col("node").alias("parent"))
    runs = nodes.withColumn("parent", F.expr("substring(node, 1, greatest(length(node) - 1, 0))")).withColumn("root", F.length("node") == 0)
    runs = runs.where("root").select("term", "node", "poi").union(runs.where("not root").join(up, ["term", "parent"], "left_anti").select("term", "node", "poi"))
    whole = nodes.where(F.length("node") == depth).select("term", F.col("node").alias("leaf"))
    return runs, at.join(whole, ["term", "leaf"], "left_anti").select("term", "v", "poi")


def border_owner(border: DataFrame, nearest: DataFrame) -> DataFrame:
    """node, term, v, poi, dist, nth: the nearest places of each keyword from the borders of every node, nearest first."""
    order = Window.partitionBy("node", "term", "v").orderBy("dist", "poi")
    return border.join(nearest.hint("merge"), "v").withColumn("nth", F.row_number().over(order)).select("node", "term", "v", "poi", "dist", "nth")


def key_sets(city: City) -> DataFrame:
    """usr, key: the sorted keywords of each user."""
    return city.user_terms.groupBy("usr").agg(F.sort_array(F.collect_set("term")).alias("key"))


def holders(city: City, member: DataFrame, words: DataFrame | None = None) -> DataFrame:
    """leaf, cls, usr, key: every set of keywords, of ``words`` (term) if given, that a located user of at most ``KEYS`` keywords holds."""
    keys = key_sets(city).withColumn("told", F.col("key"))
    if words is not None:
        named = city.user_terms.join(F.broadcast(words.withColumn("named", F.lit(True))), "term", "left")
        keys = named.groupBy("usr").agg(F.sort_array(F.collect_set("term")).alias("key"), F.sort_array(F.collect_set(F.when(F.col("named"), F.col("term")))).alias("told")).where(F.size("told") > 0)
    users = city.users.select("usr", "v").join(keys, "usr").join(member, "v").where(F.size("key") <= KEYS)
    some = F.transform(F.sequence(F.lit(1), F.call_function("shiftleft", F.lit(1), F.size("told")) - 1), lambda m: F.filter("told", lambda t, i: F.get(F.array(*((m.bitwiseAND(1 << j)) for j in range(KEYS))), i) > 0))
    return users.select("leaf", F.explode(some).alias("cls"), "usr", "key")


def class_sets(held: DataFrame, depth: int) -> DataFrame:
    """node, parent, cls, n_users for the root (whose parent is null) and every level below it."""
    at = held.groupBy("leaf", "cls").agg(F.count("*").alias("n"))
    levels = at.select("cls", "n", "leaf", F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("level"))
    each = levels.groupBy(F.expr("substring(leaf, 1, level)").alias("node"), "cls").agg(F.sum("n").alias("n_users"))
    return each.select("node", F.when(F.length("node") > 0, F.expr("substring(node, 1, length(node) - 1)")).alias("parent"), "cls", "n_users")


class _Spots:
    """Users' vertices by leaf, from rows (code of the leaf, v, near, far): those of a node are one slice."""

    def __init__(self, leaf: np.ndarray, v: np.ndarray, near: np.ndarray, far: np.ndarray):
        order = np.argsort(leaf, kind="stable")
        self.leaf, self.v, self.near, self.far = leaf[order], v[order], near[order], far[order]
        self.at = None

    def on(self, rows: roads.Rows) -> _Spots:
        if self.at is None:
            self.at = rows.places(self.v).astype(np.int32)
        return self

    def of(self, code: int, below: int) -> slice:
        """The vertices of a node ``below`` levels above the leaves."""
        return slice(*np.searchsorted(self.leaf, [code * FANOUT**below, (code + 1) * FANOUT**below]).tolist())


class _Leaves:
    """The road in cells nested in the leaves, from rows (code of the leaf, v)."""

    def __init__(self, leaf: np.ndarray, v: np.ndarray):
        order = np.argsort(v, kind="stable")
        self.leaf, self.v, self.cells = leaf[order], v[order], None

    def on(self, rows: roads.Rows, spots: _Spots, cap: int) -> _Leaves:
        if self.cells is None:
            i = np.minimum(np.searchsorted(self.v, rows.ids), max(len(self.v) - 1, 0))
            code = np.where(self.v[i] == rows.ids, self.leaf[i], -1)
            cells = roads.Cells(rows, code, cap)
            self.code = code[cells.order[cells.begin[:-1]]]
            good = spots.at >= 0
            self.near, self.far, self.held = np.zeros(len(rows.ids)), np.zeros(len(rows.ids)), np.zeros(len(rows.ids), bool)
            self.near[spots.at[good]], self.far[spots.at[good]], self.held[spots.at[good]] = spots.near[good], spots.far[good], True
            self.users: dict[int, tuple] = {}
            self.cells = cells
        return self

    def table(self, c: int) -> tuple[np.ndarray, ...]:
        """Distances between the borders of a cell inside it, and the least and largest to its users, offsets included."""
        dist, own = self.cells.inside(c), self.cells.own(c)
        at = np.searchsorted(own, self.cells.border[self.cells.first[c] : self.cells.first[c + 1]])
        some = self.held[own]
        far = dist[:, some]
        return dist[:, at], (far + self.near[own[some]]).min(1, initial=self.cells.NONE), (far + self.far[own[some]]).max(1, initial=-self.cells.NONE)

    def to_users(self, c: int) -> tuple[np.ndarray, np.ndarray]:
        """Distances inside a cell from its borders to its users' vertices, and their largest offsets; the last few are held."""
        if c not in self.users:
            own = self.cells.own(c)
            some = self.held[own]
            if len(self.users) >= 64:
                del self.users[next(iter(self.users))]
            self.users[c] = np.ascontiguousarray(self.cells.inside(c)[:, some].T), self.far[own[some]]
        return self.users[c]

    def extremes(self, tables: _Tables, starts: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
        """Least and largest distance, offsets included, from each of ``starts`` to the users that it reaches in the cells ``lo`` to ``hi``; lo > hi without any.

        The largest one of a cell is looked for only if a bound, by the farthest user from each border, allows more than is found already.
        """
        cells, none = self.cells, self.cells.NONE
        dist = cells.between(tables.made, starts, lo, hi)
        rows = slice(cells.first[lo], cells.first[hi])
        least = (dist[rows] + tables.near[rows][:, None]).min(0, initial=none)
        some = np.flatnonzero(np.diff(cells.first[lo : hi + 1])) + lo
        most = np.full(len(starts), -np.inf)
        if len(some):
            bound = np.minimum.reduceat(dist[rows] + tables.far[rows][:, None], cells.first[some] - cells.first[lo], axis=0)
            for i in np.argsort(-bound.max(1), kind="stable").tolist():
                asked = np.flatnonzero(bound[i] > most)
                if not len(asked):
                    continue
                way, far = self.to_users(some[i])
                got, own = np.full((len(far), len(asked)), none, np.int32), dist[cells.first[some[i]] : cells.first[some[i] + 1]][:, asked]
                for j in range(len(own)):
                    np.minimum(got, way[:, j][:, None] + own[j][None, :], out=got)
                most[asked] = np.maximum(most[asked], np.where(got < none, got + far[:, None], -np.inf).max(0, initial=-np.inf))
        return least, most


class _Tables:
    """What is known of each cell, by its number: distances between its borders, least and largest ones to its users by border."""

    def __init__(self, cell: np.ndarray, size: np.ndarray, dist: np.ndarray, near: np.ndarray, far: np.ndarray):
        order = np.argsort(cell, kind="stable")
        at, border = np.cumsum(size**2) - size**2, np.cumsum(size) - size
        self.made = [dist[at[i] : at[i] + size[i] ** 2].reshape(size[i], size[i]).astype(np.int32) for i in order.tolist()]
        self.near, self.far = (np.concatenate([x[border[i] : border[i] + size[i]] for i in order.tolist()] or [x]) for x in (near, far))


def ranges(city: City, member: DataFrame, border: DataFrame, depth: int, levels: int = NEAR_LEVELS) -> DataFrame:
    """node, b, lo, hi: least and largest distance, offset included, of the node's users to a border; the lowest ``levels`` only.

    A worker searches from a border until the users' vertices of its nodes are reached, and gives out their extremes only. For nodes of many cells
    the ways of many borders are put together from ways inside cells, where lengths are positive integers.
    """
    least = max(1, depth - levels + 1)
    if roads.edges(city.road) > roads.ROAD_LIMIT:
        nodes = F.explode(F.sequence(F.lit(least), F.lit(depth)))
        users = city.users.join(member, "v").select("leaf", "v", "dis", nodes.alias("level")).groupBy(F.expr("substring(leaf, 1, level)").alias("node"), "v").agg(F.min("dis").alias("near"), F.max("dis").alias("far"))
        pairs = keep(border.select("node", F.col("v").alias("b")).join(users, "node"), "border_users")
        dist = roads.between(city.road, pairs.select(F.col("b").alias("a"), F.col("v").alias("b")))
        return pairs.join(dist.select(F.col("a").alias("b"), F.col("b").alias("v"), "dist"), ["b", "v"]).groupBy("node", "b").agg(F.min(F.col("dist") + F.col("near")).alias("lo"), F.max(F.col("dist") + F.col("far")).alias("hi"))
    code = lambda node: F.conv(node, FANOUT, 10).cast("long")
    users = city.users.join(member, "v").groupBy("leaf", "v").agg(F.min("dis").alias("near"), F.max("dis").alias("far")).select(code("leaf").alias("leaf"), "v", "near", "far")
    held = getattr(member, "_spots", None)
    spots = held[1] if held is not None and held[0] is city.users else roads.share(users, _Spots)
    if getattr(city.users, "_kept", False) and getattr(member, "_kept", False):
        member._spots = city.users, spots
    road, kind = roads.broadcast_rows(city.road), dict(city.users.dtypes)["dis"]

    def given(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_pydict({n: pa.array(c, t) for n, c, t in zip(("node", "b", "lo", "hi"), zip(*out, strict=True) if out else [[]] * 4, (pa.string(), pa.int64(), pa.float64(), pa.float64()), strict=True)})

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked = [r for batch in batches for r in batch.to_pylist()]
        if not asked:
            return
        rows = road.value
        near = spots.value.on(rows)
        at = rows.places(np.array([r["b"] for r in asked]))
        each = max(1, 2 * roads.CELLS // max(1, len(rows.ids))) if rows.stepped else 1
        out = []
        for i in range(0, len(asked), each):
            few = [(r, int(x)) for r, x in zip(asked[i : i + each], at[i : i + each].tolist(), strict=True) if x >= 0]
            slices = [[near.of(c, depth - n) for c, n in zip(r["codes"], r["sizes"], strict=True)] for r, _ in few]
            if rows.stepped and few:
                # the nodes of a border are nested
                dist = rows.distances(np.array([x for _, x in few]), [near.at[max(s, key=lambda x: x.stop - x.start)] for s in slices])
            for nth, ((r, x), own) in enumerate(zip(few, slices, strict=True)):
                if rows.stepped:
                    found = dist[nth]
                else:
                    search, found = roads.Search(rows, r["b"]), np.full(len(rows.ids), -1.0)
                    search.until(float("inf"))
                    found[list(search.settled.keys())] = list(search.settled.values())
                for node, s in zip(r["nodes"], own, strict=True):
                    d = found[near.at[s]]
                    if (good := d >= 0).any():
                        out.append((node, r["b"], float((d + near.near[s])[good].min()), float((d + near.far[s])[good].max())))
        yield given(out)

    def by_cells(low: DataFrame) -> DataFrame:
        leaves, n, many = roads.share(member.select(code("leaf").alias("leaf"), "v"), _Leaves), 4 * roads.tasks(city.road), TOGETHER

        def tables(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            mine = [i for batch in batches for i in batch["id"].to_pylist()]
            rows = road.value
            all_ = leaves.value.on(rows, spots.value.on(rows), cap)
            for c in (c for i in mine for c in range(i, all_.cells.count, n)):
                dist, near, far = all_.table(c)
                yield pa.RecordBatch.from_pydict({"data": pa.array([roads.packed(np.array([c]), np.array([len(dist)]), dist.ravel().astype(np.int64), near, far)], pa.binary())})

        made = roads.gathered(city.road.sparkSession.range(n, numPartitions=n).mapInArrow(tables, "data binary"), _Tables)

        def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for r in (r for batch in batches for r in batch.to_pylist()):
                rows = road.value
                all_, out = leaves.value.on(rows, spots.value.on(rows), cap), []
                b = rows.places(np.array(r["b"]))
                b = b[b >= 0]
                # borders of a part are next to each other
                b = b[np.lexsort((b, all_.cells.cell[b]))][many * r["part"] : many * (r["part"] + 1)]
                below = FANOUT ** (depth - r["size"])
                lo, hi = np.searchsorted(all_.code, [r["code"] * below, (r["code"] + 1) * below]).tolist()
                for x, first, last in zip(rows.ids[b].tolist(), *(x.tolist() for x in all_.extremes(made.value, b, lo, hi)), strict=True):
                    if last > -np.inf:
                        out.append((r["node"], x, float(first), float(last)))
                yield given(out)

        parts = F.explode(F.expr(f"sequence(0L, cast((size(b) - 1) div {many} as bigint))"))
        some = keep(low.groupBy("node", "code", "size").agg(F.collect_set("b").alias("b")).select("node", "code", "size", "b", parts.alias("part")), "parts")
        # a task a part: few rows that cost much each
        return some.coalesce(1).repartition(max(1, some.count())).mapInArrow(told, "node string, b long, lo double, hi double")

    low = border.where((F.length("node") >= least) & (F.length("node") <= depth)).select(F.col("v").alias("b"), "node", code("node").alias("code"), F.length("node").alias("size"))
    vertices, cap = roads.edges(member), CELL
    large, told = F.lit(vertices) > 4 * cap * F.pow(F.lit(float(FANOUT)), F.col("size")), None
    # the table of a cell costs about as much as a few searches
    if vertices > 4 * cap * FANOUT**least and low.where(large).count() > vertices / cap and roads.whole(city.road, vertices):
        told, low = by_cells(low.where(large)), low.where(~large)
    some = low.groupBy("b").agg(F.collect_list(F.struct("node", "code", "size")).alias("of")).select("b", F.col("of.node").alias("nodes"), F.col("of.code").alias("codes"), F.col("of.size").alias("sizes"))
    each = some.repartition(roads.tasks(city.road), "b").mapInArrow(work, "node string, b long, lo double, hi double")
    told = each if told is None else told.union(each)
    return told.select("node", "b", *(F.col(c).cast(_wider(dict(city.road.dtypes)["len"], kind)).alias(c) for c in ("lo", "hi"))).hint("merge")


def _wider(*kinds: str) -> str:
    """The type of a sum of lengths and offsets."""
    return "double" if {"double", "float"} & set(kinds) else "bigint"


def build(city: City, k: int, leaf_cap: int = 100, min_df: int = 0, only: frozenset = PARTS, words: DataFrame | None = None) -> tuple[City, Tree]:
    """The city and its index, each relation kept as a table; keywords of fewer than ``min_df`` places get postings only.

    ``nearest`` tells of border vertices, where classes are tested, and holds k + 1 places, as one of them may be the candidate itself.
    Of the relations beside ``member``, those in ``only`` are built; the others are None. ``words`` (term): the keywords, all that will be
    asked for, of which ``nearest``, ``sets`` and ``holders`` tell.
    """
    city = city.kept(keep)
    member, depth = partition(city.road, leaf_cap)
    member = keep(member, "member")
    border = keep(borders(city.road, member, depth), "border") if only & {"border", "nearest", "ranges"} else None
    held = keep(holders(city, member, words), "holders") if only & {"holders", "sets"} else None

    def nearest() -> DataFrame:
        told = city if words is None else replace(city, site_terms=keep(city.site_terms.join(F.broadcast(words), "term", "left_semi"), "told_terms"))
        at_border = border.select("v").distinct().crossJoin(F.broadcast(told.site_terms.select("term").distinct()))  # one row a word
        if min_df > 1:
            at_border = at_border.join(F.broadcast(split_terms(told.site_terms, min_df)[0]), "term", "left_semi")
        return k_nearest(told, k + 1, min_df, at_border)

    parts = {"terms": lambda: node_terms(city, member, depth), "nearest": nearest, "postings": lambda: split_terms(city.site_terms, min_df)[1], "sets": lambda: class_sets(held, depth), "ranges": lambda: ranges(city, member, border, depth)}
    return city, Tree(depth=depth, member=member, border=border, holders=held, **{name: keep(make(), name) if name in only else None for name, make in parts.items()})
