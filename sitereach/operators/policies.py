"""Simple selection policies that the experiments compare with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import City
from ..sources import keep
from . import audience, influence, relevance, roads, selection


def random_sites(candidates: DataFrame, b: int, seed: int = 1) -> list[int]:
    order = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("poi").cast("string")))
    return [r["poi"] for r in candidates.select("poi").distinct().orderBy(order, "poi").limit(b).collect()]


def cardinality(aud: DataFrame, b: int) -> list[int]:
    """Greedy on the size of the united audience."""
    return selection.greedy_cover(aud.select(F.col("usr").alias("rid"), "poi"), b)


def cardinality_plain(aud: DataFrame, b: int) -> list[int]:
    """The b largest audiences."""
    return [r["poi"] for r in aud.groupBy("poi").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "poi").limit(b).collect()]


def near_relevant(city: City, candidates: DataFrame, radius: float) -> DataFrame:
    """poi, usr: users within the radius who share a keyword with the place or have a friend who visited it."""
    close = keep(roads.site_distances(city, candidates.select("poi").distinct(), radius).select("poi", "usr"), "close")
    text = close.join(city.user_terms, "usr").join(city.site_terms.select("poi", "term"), ["poi", "term"]).select("poi", "usr")
    visited = city.checkins.select("poi", F.col("usr").alias("friend"))
    social = close.join(city.friends, "usr").join(visited, ["poi", "friend"]).select("poi", "usr")
    return text.union(social).distinct()


def most_relevant(city: City, candidates: DataFrame, b: int, radius: float = 40.0) -> list[int]:
    return cardinality(near_relevant(city, candidates, radius), b)


def influencers(city: City, candidates: DataFrame, b: int, k: int, alpha: float, x: int = 200, samples: int = 4096, seed: int = 1) -> list[int]:
    """Sites by how many of the x most influential relevant users have them in their lists."""
    few = candidates.select("poi").distinct()
    words = city.site_terms.join(few, "poi", "left_semi").select("term").distinct()
    text = city.user_terms.join(F.broadcast(words), "term", "left_semi").select("usr")  # one row a word
    visitors = city.checkins.join(F.broadcast(few), "poi", "left_semi").select(F.col("usr").alias("friend")).distinct()
    social = city.friends.join(visitors, "friend", "left_semi").select("usr")
    users = keep(text.union(social).distinct(), "relevant")
    # every relevant user is a candidate of its own
    walks = influence.reverse_samples(city.social, users.select(F.col("usr").alias("poi"), "usr"), city.users.select("usr"), 0, samples, seed)
    hits = influence.hit_rows(walks).select("rid", "poi")
    top = _seeds(hits, x)
    lists = audience.verify(city, users.sparkSession.createDataFrame([(u,) for u in top], "usr long").crossJoin(F.broadcast(few)), k, alpha)
    return cardinality_plain(lists, b)


def _seeds(hits: DataFrame, x: int) -> list[int]:
    """Lazy greedy over the samples; the walks are bounded by their number, so the driver may hold them."""
    import heapq

    rows = hits.groupBy("poi").agg(F.collect_set("rid").alias("rids")).collect()
    sets = {r["poi"]: set(r["rids"]) for r in rows}
    heap = [(-len(s), u) for u, s in sets.items()]
    heapq.heapify(heap)
    covered, out = set(), []
    while heap and len(out) < x:
        n, u = heapq.heappop(heap)
        gain = len(sets[u] - covered)
        if gain == -n:
            out.append(u)
            covered |= sets[u]
        elif gain:
            heapq.heappush(heap, (-gain, u))
    return out
