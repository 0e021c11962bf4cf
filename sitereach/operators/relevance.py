"""Relevance of places to users, top-k lists and audiences (the exact side)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from itertools import islice

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import gain, linear_score
from ..functions.score import MILLION, _share
from ..model import City
from ..sources import keep
from . import roads

#: Keywords up to which the best weights of two at one place are tabled.
PAIR_CODES = 1024
#: Places and their keywords (rows of both) that may be broadcast (a few bytes each while packed, about 30 in a worker).
PLACE_LIMIT = 20_000_000
SOCIAL_MODES = ("friend_share", "visitor_share", "jaccard", "any_friend")


def text_similarity(user_terms: DataFrame, site_terms: DataFrame) -> DataFrame:
    """usr, poi, text_m: summed weights (millionths) of the shared terms."""
    return user_terms.join(site_terms.select("term", "poi", "w_m"), "term").groupBy("usr", "poi").agg(F.sum("w_m").alias("text_m"))


def friend_visits(friends: DataFrame, checkins: DataFrame) -> DataFrame:
    """usr, poi, visits: how many friends of the user have visited the place."""
    seen = checkins.select("poi", F.col("usr").alias("friend"))
    return friends.join(seen, "friend").groupBy("usr", "poi").agg(F.count("*").alias("visits"))


def social_relevance(friends: DataFrame, checkins: DataFrame, mode: str = "friend_share") -> DataFrame:
    """usr, poi, social in [0, 1]; pairs without a visiting friend have no row."""
    if mode not in SOCIAL_MODES:
        raise ValueError(f"mode must be one of {SOCIAL_MODES}")
    pairs = friend_visits(friends, checkins)
    if mode == "any_friend":
        return pairs.select("usr", "poi", F.lit(1.0).alias("social"))
    n_friends = friends.groupBy("usr").agg(F.count("*").alias("n_friends"))
    n_visitors = checkins.groupBy("poi").agg(F.count("*").alias("n_visitors"))
    if mode == "friend_share":
        return pairs.join(n_friends, "usr").select("usr", "poi", (F.col("visits") / F.col("n_friends")).alias("social"))
    if mode == "visitor_share":
        return pairs.join(n_visitors, "poi").select("usr", "poi", (F.col("visits") / F.col("n_visitors")).alias("social"))
    both = pairs.join(n_friends, "usr").join(n_visitors, "poi")
    return both.select("usr", "poi", (F.col("visits") / (F.col("n_friends") + F.col("n_visitors") - F.col("visits"))).alias("social"))


def relevant_pairs(city: City, alpha: float, mode: str = "friend_share") -> DataFrame:
    """usr, poi, gain > 0: the numerator of the score. One aggregation over both sources of relevance."""
    text = text_similarity(city.user_terms, city.site_terms).select("usr", "poi", F.lit(0.0).alias("social"), "text_m")
    social = social_relevance(city.friends, city.checkins, mode).select("usr", "poi", "social", F.lit(0).cast("long").alias("text_m"))
    both = text.union(social).groupBy("usr", "poi").agg(F.max("social").alias("social"), F.max("text_m").alias("text_m"))
    return both.select("usr", "poi", gain(F.col("social"), F.col("text_m"), alpha).alias("gain")).where("gain > 0")


def located(city: City, pairs: DataFrame) -> DataFrame:
    users = city.users.select("usr", F.col("v").alias("uv"), F.col("dis").alias("ud"))
    sites = city.sites.select("poi", F.col("v").alias("pv"), F.col("dis").alias("pd"))
    return pairs.join(users, "usr").join(sites, "poi").where("uv is not null and pv is not null")


def ranked(city: City, pairs: DataFrame, k: int) -> DataFrame:
    """usr, poi, score, rnk: the k best places of each user of (usr, poi, gain) pairs, score then smaller id.

    Users of a vertex share one search that grows ring by ring. It ends as soon as nothing beyond the ring
    could still reach the k-th score of any of them, so far places cost nothing however many there are.
    """
    shared = roads.broadcast_rows(city.road)

    def best(search: roads.Search, rows: roads.Rows, user: pd.DataFrame, radius: float, more: bool):
        at, gain = user["at"].to_numpy(), user["gain"].to_numpy()
        settled = search.settled
        road = np.array([settled.get(i, -1) for i in at.tolist()], float)
        near = road >= 0
        offset = user["ud"].to_numpy()[0]
        dist = road[near] + offset + user["pd"].to_numpy()[near]
        score = gain[near] / np.maximum(dist, 1.0)
        poi = user["poi"].to_numpy()[near]
        order = np.lexsort((poi, -score))[:k]
        rest = gain[~near]
        done = not more or not len(rest) or (len(order) == k and rest.max() / max(radius + offset, 1.0) < score[order[-1]])
        return done, poi[order], score[order]

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows = shared.value
        held = pd.DataFrame()
        for frame in (*frames, None):
            if frame is not None:
                frame = pd.concat([held, frame]) if len(held) else frame
                # the last vertex of a frame may go on in the next one
                last = frame["uv"].to_numpy()[-1] if len(frame) else None
                held, frame = frame[frame["uv"] == last], frame[frame["uv"] != last]
            else:
                frame = held
            for v, group in frame.groupby("uv", sort=False):
                where = np.searchsorted(rows.ids, group["pv"].to_numpy())
                where = np.minimum(where, max(len(rows.ids) - 1, 0))
                known = rows.ids[where] == group["pv"].to_numpy() if len(rows.ids) else np.zeros(len(group), bool)
                group = group.assign(at=np.where(known, where, -1))
                search, radius = roads.Search(rows, int(v)), 8.0
                waiting = {u: g for u, g in group.groupby("usr", sort=False)}
                while waiting:
                    more = search.until(radius)
                    for u in list(waiting):
                        done, poi, score = best(search, rows, waiting[u], radius, more)
                        if done:
                            del waiting[u]
                            yield pd.DataFrame({"usr": int(u), "poi": poi, "score": score, "rnk": np.arange(1, len(poi) + 1, dtype=np.int32)})
                    radius *= 2

    rows = located(city, pairs).select("usr", "uv", "ud", "poi", "pv", "pd", "gain")
    return rows.repartition("uv").sortWithinPartitions("uv", "usr").mapInPandas(work, "usr long, poi long, score double, rnk int")


class Places:
    """Places with their keywords by number, from rows (poi, -1, v, dis) of places and (poi, code, weight, 0) of keywords."""

    def __init__(self, poi: np.ndarray, code: np.ndarray, x: np.ndarray, dis: np.ndarray):
        site = code < 0
        order = np.argsort(poi[site], kind="stable")
        self.poi, self.v, self.dis = poi[site][order], x[site][order], dis[site][order]
        poi, code, x = poi[~site], code[~site].astype(np.int32), x[~site]
        at = np.minimum(np.searchsorted(self.poi, poi), max(len(self.poi) - 1, 0))
        known = self.poi[at] == poi if len(self.poi) else np.zeros(len(poi), bool)
        at, code, x = at[known].astype(np.int32), code[known], x[known]
        order = np.argsort(at, kind="stable")
        self.code, self.weight = code[order], x[order]
        self.first = np.searchsorted(at[order], np.arange(len(self.poi) + 1))
        self._rows = self._whole = None

    def at_vertices(self, rows: roads.Rows) -> np.ndarray:
        """Sorted by vertex of the road; the vertex of each place, -1 for those not on the road."""
        v = rows.places(self.v)
        order = np.argsort(v, kind="stable")
        self.at = order[v[order] >= 0]
        self.begin = np.searchsorted(v[self.at], np.arange(len(rows.ids) + 1))
        self.least = self.dis[v >= 0].min() if len(self.at) else 0
        return v

    def on(self, rows: roads.Rows) -> Places:
        """Sorted by vertex of the road; ``holders`` and ``top`` of each keyword are of places on the road."""
        if self._whole is not rows:
            v = self.at_vertices(rows)
            on = np.repeat(v >= 0, np.diff(self.first))
            codes = int(self.code.max()) + 1 if len(self.code) else 0
            self.holders = np.bincount(self.code[on], minlength=codes)
            self.top = np.zeros(codes, np.int64)
            np.maximum.at(self.top, self.code[on], self.weight[on])
            self.two = self._pairs(on, codes) if codes <= PAIR_CODES else None
            self._rows = self._whole = rows
        return self

    def near(self, rows: roads.Rows) -> Places:
        """Sorted by vertex, and ``holders`` of each keyword: what the nearest places by keyword need, without the best weights."""
        if self._rows is not rows:
            on = np.repeat(self.at_vertices(rows) >= 0, np.diff(self.first))
            self.holders = np.bincount(self.code[on], minlength=int(self.code.max()) + 1 if len(self.code) else 0)
            self._rows = rows
        return self

    def _pairs(self, on: np.ndarray, codes: int) -> np.ndarray:
        """two[a, b]: the most that two keywords weigh together at one place on the road."""
        two = np.maximum.outer(self.top, self.top)
        at = np.repeat(np.arange(len(self.poi), dtype=np.int32), np.diff(self.first))
        for j in range(1, int(np.diff(self.first).max(initial=0))):
            i = np.flatnonzero((at[j:] == at[:-j]) & on[j:])
            w = self.weight[i] + self.weight[i + j]
            np.maximum.at(two.reshape(-1), self.code[i].astype(np.int64) * codes + self.code[i + j], w)
        return np.maximum(two, two.T)

    def most(self, codes: np.ndarray) -> int:
        """No place weighs more under these keywords: neither than their best weights, nor than those of all their pairs, each keyword being in n - 1."""
        n, most = len(codes), int(self.top[codes].sum())
        if n < 2 or self.two is None:
            return most
        pairs = self.two[np.ix_(codes, codes)]
        return min(most, int(pairs.sum() - pairs.trace()) // 2 // (n - 1))

    def around(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The places at vertices, and where in ``v`` each has its vertex."""
        i, which = _spread(self.begin, v)
        return self.at[i], which


def _spread(first: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The entries of the rows ``at`` of a compressed table, and which row each is of."""
    lo = first[at]
    size = first[at + 1] - lo
    which = np.repeat(np.arange(len(at)), size)
    return np.arange(len(which)) + np.repeat(lo - (np.cumsum(size) - size), size), which


class _List:
    """The k best places of one user while a search from its vertex grows.

    What is not yet met is farther than the radius, and gains no more than the best weights of the user's
    keywords give, or, known by name, what a place visited by friends gives. Once no such gain reaches the k-th score, or
    all that is relevant has been met, the list is final. Rounded sums and quotients grow with what goes in, so bounds hold.
    """

    def __init__(self, places: Places, hit: np.ndarray, codes: np.ndarray, poi: np.ndarray, social: np.ndarray, ud, k: int, share: tuple[float, float], floor: float | None = None):
        self.places, self.k, self.ud, self.share = places, k, ud, share
        # a margin for scores that were summed in another order
        self.floor = np.inf if floor is None else floor * (1 + 1e-9)
        self.codes = codes = codes[codes < len(places.top)] if share[1] > 0 else codes[:0]
        self.left = int(places.holders[codes].sum())
        self.most = self.gain(0.0, places.most(codes))
        at = np.minimum(np.searchsorted(places.poi, poi), max(len(places.poi) - 1, 0))
        known = (places.poi[at] == poi) & (social > 0) if len(places.poi) and share[0] > 0 else np.zeros(len(poi), bool)
        order = np.argsort(at[known])
        self.at, self.social = at[known][order], social[known][order]
        self.open = np.ones(len(self.at), bool)
        self.known = self.gain(self.social, self.text(self.at, hit))
        self.poi, self.score = np.zeros(0, np.int64), np.zeros(0)

    def gain(self, social, text):
        return self.share[0] * social + self.share[1] * (text / float(MILLION))

    def text(self, at: np.ndarray, hit: np.ndarray) -> np.ndarray:
        """Summed weights (whole numbers) of the user's keywords, those set in ``hit``, at places."""
        hit[self.codes] = True
        i, which = _spread(self.places.first, at)
        good = hit[self.places.code[i]]
        hit[self.codes] = False
        self.held = int(good.sum())
        return np.bincount(which[good], weights=self.places.weight[i[good]], minlength=len(at))

    def meet(self, at: np.ndarray, road: np.ndarray, hit: np.ndarray) -> None:
        """Places, not met before, at their distances on the road."""
        text, social = self.text(at, hit), np.zeros(len(at))
        self.left -= self.held
        if len(self.at):
            i = np.minimum(np.searchsorted(self.at, at), len(self.at) - 1)
            seen = self.at[i] == at
            social[seen] = self.social[i[seen]]
            self.open[i[seen]] = False
        gained = self.gain(social, text)
        good = gained > 0
        dist = road[good] + self.ud + self.places.dis[at[good]]
        poi = np.concatenate([self.poi, self.places.poi[at[good]]])
        score = np.concatenate([self.score, gained[good] / np.maximum(dist, 1.0)])
        best = np.lexsort((poi, -score))[: self.k]
        self.poi, self.score = poi[best], score[best]

    def ahead(self) -> float:
        """The most that a place not yet met can gain."""
        return max(self.most if self.left else 0.0, float(self.known[self.open].max()) if self.open.any() else 0.0)

    def done(self, radius: float) -> bool:
        if len(self.score) == self.k and self.score[-1] > self.floor:
            return True
        most = self.ahead()
        return most <= 0 or (len(self.score) == self.k and most / max(radius + self.ud + self.places.least, 1.0) < self.score[-1])

    def next(self, radius: float) -> float:
        """A larger radius, but hardly larger than the one at which the list as it is would be final."""
        if len(self.score) < self.k:
            return 1.5 * radius
        last = self.ahead() / self.score[-1] - self.ud - self.places.least
        return min(1.5 * radius, max(last * (1 + 1e-9) + 1e-9, 1.02 * radius))


def _relevances(city: City, alpha: float, mode: str, users: DataFrame | None) -> City:
    """The city with the keywords and friendships of some users only."""
    if users is None:
        return city
    few = users.select("usr").distinct()
    return replace(city, user_terms=city.user_terms.join(few, "usr", "left_semi"), friends=city.friends.join(few, "usr", "left_semi"))


def too_large(city: City) -> bool:
    """The road or the places are too many to broadcast."""
    return roads.edges(city.road) > roads.ROAD_LIMIT or city.site_terms.count() + city.sites.count() > PLACE_LIMIT


def _coded(city: City) -> DataFrame:
    """term, code: one row a word."""
    codes = city.site_terms.select("term").where("term is not null").distinct().withColumn("code", F.row_number().over(Window.orderBy("term")) - 1)
    return F.broadcast(keep(codes, "codes"))


def _placed(city: City) -> tuple[DataFrame, roads.Shared]:
    """The codes of the words, and the places; those of kept tables are packed and passed on once."""
    held = getattr(city.site_terms, "_placed", None)
    if held is not None and held[0] is city.sites:
        return held[1:]
    codes = _coded(city)
    site = city.sites.where("poi is not null and v is not null").select("poi", F.lit(-1).alias("code"), F.col("v").cast("long").alias("x"), "dis")
    named = city.site_terms.join(codes, "term").select("poi", "code", F.col("w_m").cast("long"), F.lit(0).cast(dict(city.sites.dtypes)["dis"]).alias("dis")).where("poi is not null and w_m is not null")
    shared = roads.share(site.union(named), Places)
    if getattr(city.sites, "_kept", False) and getattr(city.site_terms, "_kept", False):
        city.site_terms._placed = city.sites, codes, shared
    return codes, shared


class _Nearest:
    """The nearest places of each keyword of one user while a search from its vertex grows; of ``whole`` keywords all places."""

    def __init__(self, places: Places, slot: np.ndarray, codes: np.ndarray, whole: np.ndarray, each: int):
        self.places, self.slot, self.each = places, slot, each
        good = codes < len(places.holders)
        self.codes, whole = codes[good], whole[good]
        holders = places.holders[self.codes]
        self.wanted = np.where(whole, holders, np.minimum(holders, each))
        self.whole, self.rings = whole, []

    def meet(self, at: np.ndarray, road: np.ndarray) -> None:
        """Places, not met before, at their distances on the road."""
        self.slot[self.codes] = np.arange(len(self.codes))
        i, which = _spread(self.places.first, at)
        key = self.slot[self.places.code[i]]
        self.slot[self.codes] = -1
        good = key >= 0
        at, which = at[which[good]], which[good]
        self.rings.append((key[good], at, self.places.weight[i[good]], road[which] + self.places.dis[at]))

    def all(self) -> tuple[np.ndarray, ...]:
        if len(self.rings) > 1:
            self.rings = [tuple(np.concatenate(c) for c in zip(*self.rings, strict=True))]
        return self.rings[0]

    def done(self, radius: float) -> bool:
        """What is not yet met is farther than the radius and the least offset of a place."""
        key, _, _, dist = self.all()
        held = np.bincount(key, minlength=len(self.codes))
        if (held < self.wanted).any():
            return False
        final = np.bincount(key[dist <= radius + self.places.least], minlength=len(self.codes))
        return bool(((final >= self.wanted) | (held >= self.places.holders[self.codes])).all())

    def kth(self, k: int, ud, share: tuple[float, float]) -> float:
        """The k-th best score, friends left out, among the nearest places; 0 with fewer."""
        key, at, weight, dist = self.all()
        order = np.lexsort((self.places.poi[at], dist, key))
        nth = np.empty(len(key), np.int64)
        nth[order] = np.arange(len(key)) - np.searchsorted(key[order], np.arange(len(self.codes)))[key[order]]
        names, of = np.unique(at, return_inverse=True)
        text = np.bincount(of, weights=weight, minlength=len(names))
        far = np.zeros(len(names))
        far[of] = dist
        near = np.zeros(len(names), bool)
        near[of[(nth < self.each) | self.whole[key]]] = True
        if near.sum() < k:
            return 0.0
        gained = share[0] * 0.0 + share[1] * (text[near] / float(MILLION))
        return float(np.sort(gained / np.maximum(far[near] + ud, 1.0))[-k])


class Around:
    """The nearest places by keyword around single vertices, met ring by ring."""

    def __init__(self, rows: roads.Rows, places: Places):
        self.rows, self.places, self.guess = rows, places.near(rows), 12.0
        self.slot = np.full(len(self.places.holders), -1, np.int64)

    def nearest(self, v: int, codes: np.ndarray, k: int) -> tuple[np.ndarray, ...]:
        """Of the places that are among the ``k`` nearest (ties: smaller id) of a keyword: poi, distance, weight[i, code] of all the keywords, and listed[i, code]."""
        mine, search, radius, seen, more = _Nearest(self.places, self.slot, codes, np.zeros(len(codes), bool), k), roads.Search(self.rows, v), self.guess, 0, True
        while True:
            more = search.until(radius)
            got = list(islice(search.settled.items(), seen, None))
            seen += len(got)
            at, which = self.places.around(np.array([x for x, _ in got], np.int64))
            mine.meet(at, np.array([d for _, d in got], float)[which] if len(got) else np.zeros(0))
            if not more or mine.done(radius):
                break
            radius *= 1.5
        self.guess = 0.9 * self.guess + 0.1 * 0.9 * radius
        key, at, weight, dist = mine.all()
        order = np.lexsort((self.places.poi[at], dist, key))
        nth = np.empty(len(key), np.int64)
        nth[order] = np.arange(len(key)) - np.searchsorted(key[order], np.arange(len(mine.codes)))[key[order]]
        names = np.unique(at[nth < k])
        some = np.isin(at, names)
        key, of, weight, dist, near = key[some], np.searchsorted(names, at[some]), weight[some], dist[some], nth[some] < k
        out, listed, far = np.zeros((len(names), len(codes))), np.zeros((len(names), len(codes))), np.zeros(len(names))
        # keywords that no place holds have no slot
        column = np.flatnonzero(codes < len(self.places.holders))[key]
        out[of, column], listed[of, column], far[of] = weight, near, dist
        return self.places.poi[names], far, out, listed


def nearest_bounds(city: City, users: DataFrame, k: int, alpha: float, each: int, min_df: int = 0) -> DataFrame:
    """usr, s_k: the k-th best score, friends left out, among the ``each`` nearest places of each of the user's keywords.

    Of keywords of fewer than ``min_df`` places all count. Places are met around each user's vertex, ring by ring, so
    neither the nearest places of other vertices nor rows of users and places are listed. 0 with fewer than k places.
    """
    (codes, places), least = _placed(city), min_df if min_df > 1 else 0
    road, share = roads.broadcast_rows(city.road), _share(alpha)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = at = None
        guess = 12.0
        for batch in batches:
            if not len(batch):
                continue
            if rows is None:
                rows = road.value
                near = places.value.near(rows)
                slot = np.full(len(near.holders), -1, np.int64)
            bounds = []
            for r in batch.to_pylist():
                if r["uv"] != at:
                    at, search, rings, reach, more = r["uv"], None if r["uv"] is None else roads.Search(rows, r["uv"]), [], [], r["uv"] is not None
                mine, nth = _Nearest(near, slot, np.array(r["codes"], np.int64), np.array(r["rare"], bool), each), 0
                while not (nth and mine.done(reach[nth - 1])):
                    if nth == len(rings):
                        if not more:
                            break
                        seen = len(search.settled)
                        reach.append(1.5 * reach[-1] if reach else guess)
                        more = search.until(reach[-1])
                        got = list(islice(search.settled.items(), seen, None))
                        spots, which = near.around(np.array([x for x, _ in got], np.int64))
                        rings.append((spots, np.array([d for _, d in got], float)[which] if len(got) else np.zeros(0)))
                    mine.meet(*rings[nth])
                    nth += 1
                if nth:
                    guess = 0.9 * guess + 0.1 * 0.9 * reach[nth - 1]
                bounds.append(mine.kth(k, r["ud"], share) if nth else 0.0)
            yield pa.RecordBatch.from_pydict({"usr": batch["usr"], "s_k": pa.array(bounds, pa.float64())})

    rare = city.site_terms.groupBy("term").agg((F.count("*") < least).alias("rare"))
    few = city.user_terms.join(users.select("usr").distinct(), "usr", "left_semi").join(codes, "term").join(F.broadcast(rare), "term")  # one row a word
    words = few.groupBy("usr").agg(F.collect_set(F.struct("code", "rare")).alias("w"))
    asked = city.users.join(users.select("usr").distinct(), "usr", "left_semi").join(words, "usr", "left")
    asked = asked.select("usr", F.col("v").alias("uv"), F.col("dis").alias("ud"), F.coalesce("w.code", F.array().cast("array<int>")).alias("codes"), F.coalesce("w.rare", F.array().cast("array<boolean>")).alias("rare"))
    return asked.repartition(roads.tasks(city.road), "uv").sortWithinPartitions("uv").mapInArrow(work, "usr long, s_k double").hint("merge")


def top_k(city: City, k: int, alpha: float, mode: str = "friend_share", users: DataFrame | None = None) -> DataFrame:
    """usr, poi, score, rnk: the top-k list of every user, or of ``users``: min(k, places of positive score) rows.

    Places are met around each user's vertex, ring by ring, so no pairs of users and places are listed but those of
    visits by friends. A road or places too many to broadcast are ranked by those pairs (``ranked``).
    ``users`` may have a ``floor``: a user whose k-th place is known to score more is done, with a list that holds other places
    than the final one perhaps, but only such as score more than the floor.
    """
    own = _relevances(city, alpha, mode, users)
    if too_large(city):
        return ranked(city, relevant_pairs(own, alpha, mode), k)
    codes, places = _placed(city)
    road, share = roads.broadcast_rows(city.road), _share(alpha)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = hit = search = at = None
        for batch in batches:
            if not len(batch):
                continue
            if rows is None:
                rows = road.value
                near = places.value.on(rows)
                hit = np.zeros(len(near.top), bool)
            out: list[tuple] = []
            for r in batch.to_pylist():
                if r["uv"] != at:
                    at, search, rings, reach = r["uv"], roads.Search(rows, r["uv"]), [], []
                    more = True
                mine = _List(near, hit, np.array(r["codes"], np.int64), np.array(r["pois"], np.int64), np.array(r["social"], float), r["ud"], k, share, r.get("floor"))
                nth = 0
                while not (nth and mine.done(reach[nth - 1])):
                    if nth == len(rings):
                        if not more:
                            break
                        seen = len(search.settled)
                        reach.append(mine.next(reach[-1]) if reach else 12.0)
                        more = search.until(reach[-1])
                        got = list(islice(search.settled.items(), seen, None))
                        v = np.array([x for x, _ in got], np.int64)
                        spots, which = near.around(v)
                        rings.append((spots, np.array([d for _, d in got], float)[which] if len(got) else np.zeros(0)))
                    mine.meet(*rings[nth], hit)
                    nth += 1
                if len(mine.poi):
                    out.append((np.full(len(mine.poi), r["usr"]), mine.poi, mine.score, np.arange(1, len(mine.poi) + 1, dtype=np.int32)))
            if out:
                yield pa.RecordBatch.from_pydict(dict(zip(("usr", "poi", "score", "rnk"), (np.concatenate(c) for c in zip(*out, strict=True)), strict=True)))

    words = own.user_terms.join(codes, "term").groupBy("usr").agg(F.collect_set("code").alias("codes"))
    seen = social_relevance(own.friends, city.checkins, mode).groupBy("usr").agg(F.collect_list(F.struct("poi", "social")).alias("seen"))
    asked = city.users.where("v is not null").select("usr", F.col("v").alias("uv"), F.col("dis").alias("ud"))
    asked = asked.join(words.join(seen, "usr", "full"), "usr").select("usr", "uv", "ud", F.coalesce("codes", F.array().cast("array<int>")).alias("codes"), F.coalesce("seen.poi", F.array().cast("array<long>")).alias("pois"), F.coalesce("seen.social", F.array().cast("array<double>")).alias("social"))
    if users is not None and "floor" in users.columns:
        asked = asked.join(users.groupBy("usr").agg(F.max("floor").alias("floor")).hint("merge"), "usr")
    return asked.repartition(roads.tasks(city.road), "uv").sortWithinPartitions("uv").mapInArrow(work, "usr long, poi long, score double, rnk int").hint("merge")


def top_k_linear(city: City, k: int, alpha: float, beta: float) -> DataFrame:
    """Top-k lists under the linear score; distances are needed for all relevant pairs."""
    pairs = located(city, relevant_pairs(city, alpha))
    reach = roads.from_sources(city.road, city.sites.select("v"))
    dist = pairs.join(reach, (F.col("pv") == F.col("src")) & (F.col("uv") == F.col("v"))).select("usr", "poi", "gain", (F.col("ud") + F.col("dist") + F.col("pd")).alias("distance"))
    far = dist.agg(F.max("distance").alias("farthest"))
    score = linear_score(F.col("gain"), F.col("distance"), beta, F.col("farthest"))
    order = Window.partitionBy("usr").orderBy(F.desc("score"), "poi")
    return dist.crossJoin(F.broadcast(far)).withColumn("score", score).withColumn("rnk", F.row_number().over(order)).where(F.col("rnk") <= k).select("usr", "poi", "score", "rnk")


def audiences(lists: DataFrame, candidates: DataFrame) -> DataFrame:
    """poi, usr for the candidates: users who have the place in their list."""
    return lists.join(candidates.select("poi").distinct(), "poi", "left_semi").select("poi", "usr")


def audience_union(audience: DataFrame, sites: DataFrame) -> DataFrame:
    return audience.join(sites.select("poi").distinct(), "poi", "left_semi").select("usr").distinct()
