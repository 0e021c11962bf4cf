"""Query sets and parameter grids of the experiments."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import City

#: Defaults and the values that each experiment varies.
DEFAULTS = {"k": 20, "n": 60, "b": 5, "alpha": 0.6, "eps": 0.1}
GRID = {"b": [1, 3, 5, 7, 9], "n": [20, 40, 60, 80, 100], "k": [10, 15, 20, 25, 30], "alpha": [0.0, 0.2, 0.4, 0.6, 0.8], "share": [0.6, 0.7, 0.8, 0.9, 1.0]}


def drawn_sites(city: City, n: int, seed: str = "c") -> DataFrame:
    """poi: n places by the order of their md5, the same in every engine."""
    return city.sites.select("poi").orderBy(F.md5(F.concat(F.lit(f"{seed}|"), F.col("poi").cast("string"))), "poi").limit(n)


def query_sets(city: City, n: int = 60, min_df: int = 100, seed: str = "q") -> DataFrame:
    """set_id (1..4), poi: two drawn frequent keywords, each with popular and unpopular places, n of each at most.

    Popular means more visits than the mean; places without a visit are left out. A keyword's popular and
    unpopular places make sets 1 and 2, the other's 3 and 4.
    """
    frequent = city.site_terms.groupBy("term").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    order = F.md5(F.concat(F.lit(f"{seed}|"), F.col("term")))
    two = frequent.withColumn("nth", F.row_number().over(Window.orderBy(order, "term"))).where("nth <= 2").select("term", "nth")
    visits = city.checkins.groupBy("poi").agg(F.count("*").alias("n"))
    mean = visits.agg(F.avg("n").alias("mean"))
    at = city.site_terms.join(F.broadcast(two), "term").join(visits, "poi").crossJoin(F.broadcast(mean))
    sets = at.select("poi", (2 * F.col("nth") - F.when(F.col("n") > F.col("mean"), 1).otherwise(0)).cast("int").alias("set_id"))
    draw = F.row_number().over(Window.partitionBy("set_id").orderBy(F.md5(F.concat(F.lit(f"{seed}|"), F.col("poi").cast("string"))), "poi"))
    return sets.withColumn("nth", draw).where(F.col("nth") <= n).select("set_id", "poi")


def shared_users(city: City, share: float, seed: str = "u") -> City:
    """The city with a share of its users, chosen by hash, so that larger shares contain smaller ones."""
    from dataclasses import replace

    keep = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.col("usr").cast("string"))), 1, 6), 16, 10).cast("long") < int(share * (1 << 24))
    return replace(city, users=city.users.where(keep))


def shared_sites(city: City, share: float, always: DataFrame, seed: str = "s") -> City:
    """The city with a share of its places; the candidates always stay."""
    from dataclasses import replace

    keep = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.col("poi").cast("string"))), 1, 6), 16, 10).cast("long") < int(share * (1 << 24))
    sites = city.sites.where(keep).select("poi").union(always.select("poi")).distinct()
    return replace(city, sites=city.sites.join(sites, "poi", "left_semi"), site_terms=city.site_terms.join(sites, "poi", "left_semi"))
