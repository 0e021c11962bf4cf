"""Influence of sets of users under the independent-cascade process.

Weights are 1 / in-degree of the head (``indeg`` of the social relation), or a given ``w``. Coins are 32-bit
integers from md5, so that a run, a reverse sample or an edge has the same fate in every engine and plan.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import coin
from ..sources import keep
from . import roads

#: Social edges, users and audience pairs together that may be broadcast to the walkers; beyond it, walks go by joins.
EDGE_LIMIT = 20_000_000
#: Rows up to which one task may number them; beyond, they are numbered range by range.
NUMBER_LIMIT = 2_000_000
#: Edges of a graph whose possible worlds are enumerated.
WORLD_EDGES = 16


def weights(edges: DataFrame, mode: str = "cascade", constant: float = 0.1) -> DataFrame:
    """src, dst, w: weighted cascade (1 / in-degree), one constant, or the ``w`` that is given."""
    if mode == "cascade":
        return edges.select("src", "dst", (1.0 / F.count("*").over(Window.partitionBy("dst"))).alias("w"))
    if mode == "constant":
        return edges.select("src", "dst", F.lit(float(constant)).alias("w"))
    if mode != "given":
        raise ValueError("mode must be cascade, constant or given")
    return edges.select("src", "dst", "w")


def _w(social: DataFrame) -> DataFrame:
    return social.select("src", "dst", "w") if "w" in social.columns else social.select("src", "dst", (1.0 / F.col("indeg")).alias("w"))


def two_hop(social: DataFrame, seeds: DataFrame) -> DataFrame:
    """set_id, influence: exact expected number of users within two hops, for (set_id, usr) seeds.

    A user is reached within one hop with p1 = 1 - product(1 - w) over the seeds before it, and within two
    with 1 - product(1 - p1 * w) over all before it: different in-edges are independent.
    """
    w = _w(social)
    first = seeds.select("set_id", F.col("usr").alias("x")).distinct()
    hop = first.join(w, first["x"] == w["src"]).groupBy("set_id", F.col("dst").alias("x")).agg((1 - F.product(1 - F.col("w"))).alias("p1"))
    hop = hop.join(first, ["set_id", "x"], "left_anti")
    near = first.withColumn("p1", F.lit(1.0)).union(hop)
    reach = near.join(w, near["x"] == w["src"]).groupBy("set_id", F.col("dst").alias("x")).agg((1 - F.product(1 - F.col("p1") * F.col("w"))).alias("p2"))
    beyond = reach.join(first, ["set_id", "x"], "left_anti").groupBy("set_id").agg(F.sum("p2").alias("more"))
    own = first.groupBy("set_id").agg(F.count("*").alias("own"))
    return own.join(beyond, "set_id", "left").select("set_id", (F.col("own") + F.coalesce("more", F.lit(0.0))).alias("influence"))


def reachable(social: DataFrame, seeds: DataFrame) -> DataFrame:
    """usr: everyone that the seeds reach if every edge is live (the case w = 1)."""
    found = keep(seeds.select("usr").distinct(), "reach")
    front, edges = found, social.select("src", "dst")
    while True:
        front = keep(front.join(edges, front["usr"] == edges["src"]).select(F.col("dst").alias("usr")).distinct().join(found, "usr", "left_anti"), "front")
        if front.isEmpty():
            return found
        found = found.union(front)


def cascades(social: DataFrame, seeds: DataFrame, runs: int, seed: int = 1, depth: int | None = None) -> DataFrame:
    """run, usr, hop: who is activated in each simulated run (``depth`` caps the hops).

    An edge's coin is fixed for the run, so the order in which hops are computed does not matter.
    """
    spark = social.sparkSession
    edges = social.select("src", "dst", "indeg")
    found = keep(spark.range(runs).select(F.col("id").alias("run")).crossJoin(F.broadcast(seeds.select("usr").distinct())).withColumn("hop", F.lit(0)), "cascade")
    front, hop = found, 0
    while depth is None or hop < depth:
        hop += 1
        live = front.join(edges, front["usr"] == edges["src"]).where(coin(F.col("run"), F.col("src"), F.col("dst"), F.lit(seed)) * F.col("indeg") < F.lit(1 << 32))
        front = keep(live.select("run", F.col("dst").alias("usr")).distinct().join(found, ["run", "usr"], "left_anti").withColumn("hop", F.lit(hop)), "front")
        if front.isEmpty():
            break
        found = found.union(front)
    return found


def simulated(social: DataFrame, seeds: DataFrame, runs: int, seed: int = 1, depth: int | None = None) -> float:
    return cascades(social, seeds, runs, seed, depth).count() / runs


def worlds_exact(edges: DataFrame, seeds: DataFrame) -> DataFrame:
    """influence: the sum over all possible worlds of a small graph (src, dst, w) of probability times users reached."""
    n = edges.count()
    if n > WORLD_EDGES:
        raise ValueError(f"{n} edges have too many possible worlds")
    spark = edges.sparkSession
    numbered = edges.withColumn("bit", F.row_number().over(Window.orderBy("src", "dst")) - 1)
    worlds = spark.range(1 << n).select(F.col("id").alias("world"))
    state = worlds.crossJoin(F.broadcast(numbered)).withColumn("live", (F.expr("shiftright(world, bit)") % 2) == 1)
    state = keep(state, "worlds")
    prob = state.groupBy("world").agg(F.product(F.when(F.col("live"), F.col("w")).otherwise(1 - F.col("w"))).alias("prob"))
    live = state.where("live").select("world", "src", "dst")
    found = keep(worlds.crossJoin(F.broadcast(seeds.select("usr").distinct())), "worlds")
    front = found
    while True:
        front = keep(front.join(live, (front["world"] == live["world"]) & (front["usr"] == live["src"])).select(live["world"], F.col("dst").alias("usr")).distinct().join(found, ["world", "usr"], "left_anti"), "front")
        if front.isEmpty():
            break
        found = found.union(front)
    size = found.groupBy("world").agg(F.count("*").alias("n"))
    return prob.join(size, "world").agg(F.sum(F.col("prob") * F.col("n")).alias("influence"))


def reached_part(social: DataFrame, audience: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The heterogeneous graph without what no candidate reaches: (social edges between reachable users, these users)."""
    users = keep(reachable(social, audience.select("usr")), "universe")
    inside = social.join(users.select(F.col("usr").alias("src")), "src", "left_semi").join(users.select(F.col("usr").alias("dst")), "dst", "left_semi")
    return inside.select("src", "dst", "indeg"), users


def _draw(*parts) -> int:
    return int(md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16)


def numbered(df: DataFrame, key: str, ranges: int = 200) -> DataFrame:
    """``df`` with ``at``: 0, 1, ... by ascending key (unique). Many rows are numbered within ranges of the key, whose sizes add up."""
    if df.count() <= NUMBER_LIMIT:
        return df.withColumn("at", (F.row_number().over(Window.orderBy(key)) - 1).cast("long"))
    edges = df.agg(F.percentile_approx(key, [i / ranges for i in range(1, ranges)], 10_000).alias("q")).first()["q"]
    part = F.size(F.filter(F.array(*map(F.lit, sorted(set(edges)))), lambda e: e < F.col(key)))
    rows = df.withColumn("part", part)
    # one row a range
    before = rows.groupBy("part").agg(F.count("*").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("part", "base")
    nth = F.row_number().over(Window.partitionBy("part").orderBy(key)) - 1
    return rows.withColumn("nth", nth).join(F.broadcast(before), "part").withColumn("at", (F.col("base") + F.col("nth")).cast("long")).drop("part", "nth", "base")


class Walker:
    """Draws reverse samples of one graph: its parts are checked, and broadcast or kept, once for all ranges of samples."""

    def __init__(self, social: DataFrame, audience: DataFrame, universe: DataFrame, seed: int = 1, hops: int = 2, coins: str = "mix"):
        self.social, self.audience, self.universe = social, audience, universe.select("usr").distinct()
        self.seed, self.hops, self.coins = seed, hops, coins
        users = self.universe.count()
        self.empty, self.small = not users, social.count() + users + audience.count() <= EDGE_LIMIT
        self.shared = _broadcast_graph(social, audience, self.universe) if self.small else None

    def draw(self, first: int, count: int) -> DataFrame:
        """rid, target, near, far of the samples first, ..., first + count - 1."""
        if self.small:
            return _walk(self.social.sparkSession, self.shared, self.empty, first, count, self.seed, self.hops, self.coins)
        return reverse_samples_shuffled(self.social, self.audience, self.universe, first, count, self.seed, self.hops)


def reverse_samples(social: DataFrame, audience: DataFrame, universe: DataFrame, first: int, count: int, seed: int = 1, hops: int = 2, coins: str = "mix") -> DataFrame:
    """rid, target, near, far for ``count`` samples from id ``first`` on.

    A sample walks the live edges backwards from a uniform target of the universe. A candidate is near if a
    user of its audience stands at most ``hops`` edges before the target, far if one stands further away
    only. ``coins``: ``md5`` for coins shared with SQL, ``mix`` for the fast ones of production; graphs too
    large to broadcast are walked by joins, with md5 coins.
    """
    return Walker(social, audience, universe, seed, hops, coins).draw(first, count)


class _Graph:
    """In-edges by head, users and audience in compressed rows, from rows (kind, a, b, c): edges dst, src, indeg (0), users (1), audience usr, poi (2)."""

    def __init__(self, kind: np.ndarray, a: np.ndarray, b: np.ndarray, c: np.ndarray):
        edge, fan = kind == 0, kind == 2
        self.ids = np.sort(a[kind == 1])
        order = np.lexsort((b[edge], a[edge]))
        self.heads, self.cut = np.unique(a[edge][order], return_index=True)
        self.cut = np.append(self.cut, len(order))
        self.src, self.indeg = b[edge][order], c[edge][order]
        order = np.lexsort((b[fan], a[fan]))
        self.users, self.of = np.unique(a[fan][order], return_index=True)
        self.of = np.append(self.of, len(order))
        self.pois = b[fan][order]

    def back(self, v: int) -> tuple[int, int]:
        """Where the in-edges of a user begin and end."""
        return self._span(self.heads, self.cut, v)

    def fans(self, u: int) -> list[int]:
        lo, hi = self._span(self.users, self.of, u)
        return self.pois[lo:hi].tolist()

    @staticmethod
    def _span(keys: np.ndarray, cut: np.ndarray, key: int) -> tuple[int, int]:
        i = int(np.searchsorted(keys, key))
        return (int(cut[i]), int(cut[i + 1])) if i < len(keys) and keys[i] == key else (0, 0)


def _broadcast_graph(social: DataFrame, audience: DataFrame, universe: DataFrame):
    """The graph, packed in Spark's tasks: only compressed bytes pass through the driver."""
    row = lambda kind, *c: [F.lit(kind).cast("long").alias("kind"), *(x.cast("long").alias(n) for n, x in zip("abc", c, strict=True))]
    none = F.lit(0)
    edges = social.select(*row(0, F.col("dst"), F.col("src"), F.col("indeg")))
    users = universe.select(*row(1, F.col("usr"), none, none))
    aud = audience.select("poi", "usr").distinct().select(*row(2, F.col("usr"), F.col("poi"), none))
    return roads.share(edges.union(users).union(aud), _Graph)


def _walk(spark, shared, empty: bool, first: int, count: int, seed: int, hops: int, coins: str) -> DataFrame:
    def hits(rid: int, target: int, graph: _Graph) -> tuple[list[int], list[int]]:
        src, indeg = graph.src, graph.indeg
        seen, layer, depth, at = {target}, [target], 0, {}
        rng = np.random.default_rng((seed, rid)) if coins == "mix" else None
        while layer:
            for u in layer:
                for p in graph.fans(u):
                    at.setdefault(p, depth)
            following = []
            for v in layer:
                lo, hi = graph.back(v)
                if lo == hi:
                    continue
                if rng is not None:
                    live = np.flatnonzero(rng.random(hi - lo) * indeg[lo:hi] < 1.0) + lo
                else:
                    live = [i for i in range(lo, hi) if _draw(rid, src[i], v, seed) * int(indeg[i]) < 1 << 32]
                for u in src[live].tolist() if len(live) else ():
                    if u not in seen:
                        seen.add(u)
                        following.append(u)
            layer, depth = following, depth + 1
        return sorted(p for p, d in at.items() if d <= hops), sorted(p for p, d in at.items() if d > hops)

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        graph = shared.value
        ids = graph.ids
        for frame in frames:
            out = []
            for rid in frame["id"].tolist():
                target = int(ids[_draw(rid, "t", seed) % len(ids)])
                out.append((rid, target, *hits(rid, target, graph)))
            yield pd.DataFrame(out, columns=["rid", "target", "near", "far"])

    if empty:
        return spark.createDataFrame([], "rid long, target long, near array<long>, far array<long>")
    return spark.range(first, first + count).mapInPandas(work, "rid long, target long, near array<long>, far array<long>")


def reverse_samples_shuffled(social: DataFrame, audience: DataFrame, universe: DataFrame, first: int, count: int, seed: int = 1, hops: int = 2) -> DataFrame:
    """The same samples (md5 coins) when the graph is too large for a worker: one join a hop, live edges only."""
    spark = social.sparkSession
    placed = keep(numbered(universe.select("usr").distinct(), "usr"), "universe")
    size = placed.agg(F.count("*").alias("n"))
    draws = spark.range(first, first + count).select(F.col("id").alias("rid")).crossJoin(F.broadcast(size)).select("rid", (coin(F.col("rid"), F.lit("t"), F.lit(seed)) % F.col("n")).alias("at"))
    found = keep(draws.join(placed, "at").select("rid", F.col("usr").alias("target"), "usr", F.lit(0).alias("depth")), "samples")
    front, depth, edges = found, 0, social.select("src", "dst", "indeg")
    while True:
        depth += 1
        live = front.join(edges, front["usr"] == edges["dst"]).where(coin(F.col("rid"), F.col("src"), F.col("dst"), F.lit(seed)) * F.col("indeg") < F.lit(1 << 32))
        front = keep(live.select("rid", "target", F.col("src").alias("usr")).distinct().join(found, ["rid", "target", "usr"], "left_anti").withColumn("depth", F.lit(depth)), "front")
        if front.isEmpty():
            break
        found = found.union(front)
    hit = found.join(audience.select("poi", "usr"), "usr").groupBy("rid", "poi").agg(F.min("depth").alias("depth"))
    lists = hit.groupBy("rid").agg(F.sort_array(F.collect_list(F.when(F.col("depth") <= hops, F.col("poi")))).alias("near"), F.sort_array(F.collect_list(F.when(F.col("depth") > hops, F.col("poi")))).alias("far"))
    none = F.array().cast("array<bigint>")
    return found.where("depth = 0").select("rid", "target").join(lists, "rid", "left").select("rid", "target", F.coalesce("near", none).alias("near"), F.coalesce("far", none).alias("far"))


def hit_rows(samples: DataFrame) -> DataFrame:
    """rid, poi, far: one row for each candidate that a sample meets."""
    return samples.select("rid", F.explode("near").alias("poi"), F.lit(False).alias("far")).union(samples.select("rid", F.explode("far").alias("poi"), F.lit(True).alias("far")))


def coverage(samples: DataFrame, sites: list[int], mode: str = "any") -> int:
    """Samples that the set covers: ``any``; ``exclusive`` far (far from some, near to none); ``inclusive`` far."""
    chosen = F.array(*(F.lit(s).cast("long") for s in sites)) if sites else F.array().cast("array<bigint>")
    near, far = F.arrays_overlap("near", chosen), F.arrays_overlap("far", chosen)
    return samples.where({"any": near | far, "exclusive": far & ~near, "inclusive": far}[mode]).count()


def hybrid_estimate(local: float, covered: int, universe: int, samples: int) -> float:
    return local + covered * universe / samples
