"""Choosing b sites: exhaustive, greedy and certified solvers.

After the samples are drawn, coverage needs only which of the (at most a few hundred) candidates each
sample meets. ``Matrix`` holds that as one bitmap a candidate, so a greedy step is a few counts of bits;
its size is checked, and ``greedy_cover`` does the same in DataFrame rounds beyond it.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import combinations
from math import ceil
from time import perf_counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import City
from ..sources import keep
from . import audience as audience_ops
from . import certificates as cert
from . import influence

#: Bytes of bitmaps that the driver may hold.
MATRIX_BYTES = 256 << 20
#: First sample ids of the two independent collections.
SAMPLE_RANGES = (1 << 40, 1 << 41)


@dataclass
class Result:
    method: str
    sites: list[int]
    influence: float = 0.0
    certified: float | None = None
    certified_by: str | None = None
    samples: int = 0
    retrieval_s: float = 0.0
    selection_s: float = 0.0
    counters: dict = field(default_factory=dict)


# ---------------------------------------------------------------- local influence
def local_influence(social: DataFrame, audience: DataFrame, sets: list[list[int]]) -> list[float]:
    """Exact two-hop influence of many site sets in one job."""
    spark = audience.sparkSession
    members = spark.createDataFrame([(i, p) for i, s in enumerate(sets) for p in s] or [(0, -1)], "set_id int, poi long")
    seeds = audience.join(F.broadcast(members), "poi").select("set_id", "usr")
    found = {r["set_id"]: r["influence"] for r in influence.two_hop(social, seeds).collect()}
    return [found.get(i, 0.0) for i in range(len(sets))]


def greedy_local(social: DataFrame, audience: DataFrame, candidates: list[int], b: int) -> tuple[list[int], float]:
    """b rounds; each evaluates every extension in one job. Ties go to the smaller id."""
    chosen, value = [], 0.0
    for _ in range(min(b, len(candidates))):
        rest = [p for p in sorted(candidates) if p not in chosen]
        values = local_influence(social, audience, [[*chosen, p] for p in rest])
        best = max(range(len(rest)), key=lambda i: (round(values[i], 9), -rest[i]))
        chosen, value = [*chosen, rest[best]], values[best]
    return chosen, value


def exhaustive(candidates: list[int], b: int, value: Callable[[list[list[int]]], list[float]]) -> tuple[list[int], float]:
    """The best of all sets of b candidates (ties: the smallest ids)."""
    sets = [list(s) for s in combinations(sorted(candidates), min(b, len(candidates)))]
    values = value(sets)
    best = max(range(len(sets)), key=lambda i: (round(values[i], 9), [-p for p in sets[i]]))
    return sets[best], values[best]


# ---------------------------------------------------------------- coverage
def matrix_bytes(candidates: int, samples: int) -> int:
    return 2 * candidates * samples // 8


class Matrix:
    """near[c], far[c]: bitmaps over the samples, which may be extended by further ranges."""

    def __init__(self, samples: DataFrame, candidates: list[int], first: int, count: int):
        self.candidates, self.count = sorted(candidates), 0
        self.near, self.far = (np.zeros((len(candidates), 0), np.uint8) for _ in range(2))
        self.extend(samples, first, count)

    def extend(self, samples: DataFrame, first: int, count: int) -> None:
        """Append the samples first, ..., first + count - 1. One row a candidate comes back: the ids of its samples, packed to bits here."""
        if matrix_bytes(len(self.candidates), self.count + count) > MATRIX_BYTES:
            raise ValueError("too many samples for bitmaps on the driver; use Counted")
        at = {p: i for i, p in enumerate(self.candidates)}
        new = np.zeros((2, len(at), -(-count // 8)), np.uint8)
        for r in influence.hit_rows(samples).groupBy("poi", "far").agg(F.collect_list(F.col("rid") - first).alias("rids")).collect():
            if r["poi"] in at:
                bits = np.zeros(count, bool)
                bits[np.asarray(r["rids"], np.int64)] = True
                new[int(r["far"]), at[r["poi"]]] = np.packbits(bits)
        # ranges begin at whole bytes; the bits between them stay 0
        self.near, self.far = np.hstack([self.near, new[0]]), np.hstack([self.far, new[1]])
        self.count += count

    def rows(self, sites: list[int]) -> list[int]:
        return [self.candidates.index(p) for p in sites]

    def masks(self, sites: list[int]) -> tuple[np.ndarray, np.ndarray]:
        i = self.rows(sites)
        empty = np.zeros(self.near.shape[1], np.uint8)
        return (np.bitwise_or.reduce(self.near[i]), np.bitwise_or.reduce(self.far[i])) if i else (empty, empty)

    def covered(self, sites: list[int], mode: str = "any") -> int:
        near, far = self.masks(sites)
        bits = {"any": near | far, "exclusive": far & ~near, "inclusive": far}[mode]
        return int(np.bitwise_count(bits).sum())

    def gains(self, sites: list[int], mode: str) -> list[float]:
        base = self.covered(sites, mode)
        return [float(self.covered([*sites, p], mode) - base) for p in self.candidates if p not in sites]


class Counted:
    """The same answers by counts over rows, where bitmaps would exceed ``MATRIX_BYTES``."""

    def __init__(self, samples: DataFrame, candidates: list[int], first: int, count: int):
        self.candidates, self.count, self.hits = sorted(candidates), 0, None
        self.extend(samples, first, count)

    def extend(self, samples: DataFrame, first: int, count: int) -> None:
        new = keep(influence.hit_rows(samples).distinct(), "hits")
        self.hits = new if self.hits is None else self.hits.union(new)
        self.count += count

    def _met(self, sites: list[int], mode: str) -> DataFrame:
        at = self.hits.where(F.col("poi").isin(sites)).groupBy("rid").agg(F.max("far").alias("far"), F.max(~F.col("far")).alias("near"))
        return at.where({"any": F.lit(True), "exclusive": F.col("far") & ~F.col("near"), "inclusive": F.col("far")}[mode]).select("rid")

    def covered(self, sites: list[int], mode: str = "any") -> int:
        return self._met(sites, mode).count()

    def gains(self, sites: list[int], mode: str = "any") -> list[float]:
        if mode == "exclusive":  # gains may be negative there
            base = self.covered(sites, mode)
            return [float(self.covered([*sites, p], mode) - base) for p in self.candidates if p not in sites]
        rows = self.hits if mode == "any" else self.hits.where("far")
        found = rows.select("rid", "poi").distinct().join(self._met(sites, mode), "rid", "left_anti").groupBy("poi").agg(F.count("*").alias("n")).collect()
        n = {r["poi"]: r["n"] for r in found}
        return [float(n.get(p, 0)) for p in self.candidates if p not in sites]


class Collection:
    """A growing collection of samples: bitmaps while they fit, then counts over rows. Earlier samples are kept, never drawn again."""

    def __init__(self, walker: influence.Walker, candidates: list[int], first: int, count: int):
        self.walker, self.candidates, self.first = walker, candidates, first
        self.found = coverage_of(walker.draw(first, count), candidates, first, count)

    def double(self) -> None:
        old = self.found.count
        new = self.walker.draw(self.first + old, old)
        if isinstance(self.found, Matrix) and matrix_bytes(len(self.candidates), 2 * old) > MATRIX_BYTES:
            self.found = Counted(self.walker.draw(self.first, 2 * old), self.candidates, self.first, 2 * old)
        else:
            self.found.extend(new, self.first + old, old)


def coverage_of(samples: DataFrame, candidates: list[int], first: int, count: int) -> Matrix | Counted:
    kind = Counted if matrix_bytes(len(candidates), count) > MATRIX_BYTES else Matrix
    return kind(samples, candidates, first, count)


def greedy_matrix(m: Matrix | Counted, b: int, mode: str = "any") -> tuple[list[int], list[float], list[list[float]]]:
    """Choices, coverages of the prefixes and the gains seen after each: lazily, as gains only fall for ``any``."""
    chosen, prefixes, gains = [], [0.0], []
    for _ in range(min(b, len(m.candidates))):
        seen = m.gains(chosen, mode)
        gains.append(seen)
        rest = [p for p in m.candidates if p not in chosen]
        best = max(range(len(rest)), key=lambda i: (seen[i], -rest[i]))
        chosen.append(rest[best])
        prefixes.append(float(m.covered(chosen, mode)))
    gains.append(m.gains(chosen, mode))
    return chosen, prefixes, gains


def greedy_cover(hits: DataFrame, b: int) -> list[int]:
    """Greedy maximum coverage of (rid, poi) rows without bitmaps: one count and one anti-join a round."""
    rest, chosen = hits.select("rid", "poi").distinct(), []
    for _ in range(b):
        top = rest.groupBy("poi").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "poi").limit(1).collect()
        if not top:
            break
        chosen.append(top[0]["poi"])
        rest = keep(rest.join(rest.where(F.col("poi") == chosen[-1]).select("rid"), "rid", "left_anti"), "cover")
    return chosen


def lazy_cover(m: Matrix, b: int) -> list[int]:
    """The same choice with stale gains on a heap: a gain is counted again only when it comes first."""
    import heapq

    heap = [(-float(m.covered([p])), p, 0) for p in m.candidates]
    heapq.heapify(heap)
    chosen: list[int] = []
    while heap and len(chosen) < b:
        gain, p, when = heapq.heappop(heap)
        if when == len(chosen):
            chosen.append(p)
        else:
            heapq.heappush(heap, (-float(m.covered([*chosen, p]) - m.covered(chosen)), p, len(chosen)))
    return chosen


def greedy_hybrid(social: DataFrame, audience: DataFrame, m: Matrix | Counted, universe: int, b: int, mode: str = "exclusive") -> tuple[list[int], float]:
    """Greedy on exact local influence plus sampled remote influence."""
    chosen, value = [], 0.0
    for _ in range(min(b, len(m.candidates))):
        rest = [p for p in m.candidates if p not in chosen]
        sets = [[*chosen, p] for p in rest]
        local = local_influence(social, audience, sets)
        total = [x + m.covered(s, mode) * universe / m.count for x, s in zip(local, sets, strict=True)]
        best = max(range(len(rest)), key=lambda i: (round(total[i], 9), -rest[i]))
        chosen, value = sets[best], total[best]
    return chosen, value


# ---------------------------------------------------------------- solvers
def _pois(candidates: DataFrame) -> list[int]:
    return sorted(r["poi"] for r in candidates.select("poi").distinct().collect())


def _setup(city: City, candidates: DataFrame, retrieve: Callable[[], DataFrame], result: Result):
    began = perf_counter()
    aud = keep(retrieve(), "audience")
    result.retrieval_s = perf_counter() - began
    social, users = influence.reached_part(city.social, aud)
    return aud, keep(social, "social"), users, users.count()


def sampling_baseline(city: City, candidates: DataFrame, b: int = 5, k: int = 20, alpha: float = 0.6, eps: float = 0.1, delta: float | None = None, retrieval: str = "combined", split: str = "union", cap: str = "marginal", seed: int = 1, most: int | None = None, coins: str = "mix", start: int = 64, retrieve: Callable[[], DataFrame] | None = None, one_by_one: bool = True) -> Result:
    """Site by site retrieval, then reverse samples doubled until the greedy choice is certified, or ``most`` of them, if given, are drawn."""
    out, pois = Result("sampling_baseline", []), _pois(candidates)
    get = retrieve or ((lambda: audience_ops.combined(city, candidates, k, alpha, one_by_one=one_by_one)[0]) if retrieval == "combined" else (lambda: audience_ops.batch(city, candidates, k, alpha)[0]))
    aud, social, users, n = _setup(city, candidates, get, out)
    delta, began = delta or 1 / max(n, 2), perf_counter()
    if not n:
        out.sites = pois[:b]
        return out
    size, rounds, walker = start, 0, influence.Walker(social, aud, users, seed, coins=coins)
    r1, r2 = (Collection(walker, pois, first, size) for first in SAMPLE_RANGES)
    while True:
        rounds += 1
        each = delta / 2 if split == "half" else delta / 2 / (rounds * (rounds + 1))
        m1, m2 = r1.found, r2.found
        chosen, prefixes, gains = greedy_matrix(m1, b)
        lo = cert.lower(m2.covered(chosen), n, size, each)
        hi = cert.upper(min(cert.coverage_cap(prefixes, gains, b, cap), size), n, size, each)
        out.sites, out.influence, out.samples, out.certified = chosen, n * m2.covered(chosen) / size, 2 * size, lo / hi
        if lo / hi >= cert.GREEDY - eps or (most and 2 * size >= most):
            out.certified_by = "ratio" if lo / hi >= cert.GREEDY - eps else "limit"
            break
        size *= 2
        r1.double()
        r2.double()
    out.selection_s = perf_counter() - began
    return out


def hybrid_approx(city: City, candidates: DataFrame, b: int = 5, k: int = 20, alpha: float = 0.6, eps: float = 0.1, delta: float | None = None, mode: str = "exclusive", seed: int = 1, retrieve: Callable[[], DataFrame] | None = None, coins: str = "mix") -> Result:
    """Batch retrieval, exact two hops plus sampled rest, certified with both parts."""
    out, pois = Result("hybrid_approx", []), _pois(candidates)
    aud, social, users, n = _setup(city, candidates, retrieve or (lambda: audience_ops.batch(city, candidates, k, alpha)[0]), out)
    delta, began = delta or 1 / max(n, 2), perf_counter()
    b = min(b, len(pois))
    local_set, psi = greedy_local(social, aud, pois, b)
    if not n or psi <= 0 or len(pois) <= b:
        out.sites, out.influence = sorted(pois[:b] if not psi else local_set), psi
        return out
    todo = cert.plan(n, len(pois), b, eps, delta, psi)
    each, size = delta / (3 * todo.rounds), max(1, ceil(todo.theta_0))
    walker = influence.Walker(social, aud, users, seed, coins=coins)
    r1, r2 = (Collection(walker, pois, first, size) for first in SAMPLE_RANGES)
    for step in range(todo.rounds + 1):
        m1, m2 = r1.found, r2.found
        chosen, _ = greedy_hybrid(social, aud, m1, n, b, mode)
        local = local_influence(social, aud, [chosen])[0]
        _, prefixes, gains = greedy_matrix(m1, b, "inclusive")
        lo = cert.hybrid_lower(local, m2.covered(chosen, "exclusive"), n, size, each)
        hi = cert.hybrid_upper(psi, min(cert.coverage_cap(prefixes, gains, b), size), n, size, each)
        out.sites, out.samples, out.certified = chosen, 2 * size, lo / hi
        out.influence = influence.hybrid_estimate(local, m2.covered(chosen, "exclusive"), n, size)
        if lo / hi >= cert.GREEDY - eps or step == todo.rounds or size >= todo.theta_max:
            out.certified_by = "ratio" if lo / hi >= cert.GREEDY - eps else "theta_max"
            break
        size *= 2
        r1.double()
        r2.double()
    out.selection_s = perf_counter() - began
    return out


def local_heuristic(city: City, candidates: DataFrame, b: int = 5, k: int = 20, alpha: float = 0.6, batches: int = 4, aggressive: bool = True, priority: bool = True, early_stop: bool = True) -> Result:
    """Two-hop greedy on users verified so far, most promising first, until the rest cannot matter much."""
    out, pois = Result("local_heuristic", []), _pois(candidates)
    began = perf_counter()
    maybe = keep(audience_ops.candidates_of(city, candidates, k, alpha, drop_rare_user_terms=2 if aggressive else 0)[0], "maybe")
    degree = city.friends.groupBy("usr").agg(F.count("*").alias("n_friends"))
    worth = maybe.groupBy("usr").agg(F.count("*").alias("n_sites")).join(degree, "usr", "left").withColumn("worth", F.col("n_sites") * F.coalesce("n_friends", F.lit(0)))
    # batches by quantiles of the priority (without it, of a hash), so no task has to rank all users
    ranked = worth.select("usr", (-F.col("worth")).cast("long").alias("by") if priority else F.xxhash64("usr").alias("by"))
    edges = ranked.agg(F.percentile_approx("by", [i / batches for i in range(1, batches)] or [0.5], 10_000).alias("q")).first()["q"] or []
    bounds = F.array(*map(F.lit, sorted(set(edges)))).cast("array<bigint>")
    staged = keep(ranked.select("usr", F.size(F.filter(bounds, lambda e: e < F.col("by"))).alias("stage")), "stages")
    batches = len(set(edges))
    social, done, out.retrieval_s = keep(city.social.select("src", "dst", "indeg"), "social"), None, perf_counter() - began
    for stage in range(batches + 1):
        began = perf_counter()
        users = staged.where(F.col("stage") == stage).select("usr")
        found = keep(audience_ops.verify(city, maybe.join(users, "usr", "left_semi"), k, alpha), "verified")
        done = found if done is None else done.union(found)
        rest = maybe.join(staged.where(F.col("stage") > stage), "usr", "left_semi").select("poi", "usr")
        out.retrieval_s += perf_counter() - began
        began = perf_counter()
        chosen, value = greedy_local(social, done, pois, b)
        last = stage == batches
        ceiling = value if last else greedy_local(social, done.union(rest), pois, b)[1]
        out.selection_s += perf_counter() - began
        out.sites, out.influence, out.counters = chosen, value, {"stages": stage + 1}
        out.certified = value / ceiling if ceiling else 1.0
        if last or (early_stop and out.certified >= cert.GREEDY):
            break
    out.certified_by = "stop"
    return out
