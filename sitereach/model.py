"""The data model: a city of places and users on a road network, with keywords, visits and friendships.

``parts_city`` derives one from the order tables: customers live on a street grid, parts are the places,
purchases are visits, and buying an item soon after someone else makes one a follower. Joins whose sides grow with the
city are hinted to merge: a broadcast of either would pass through the driver. ``events_city``
derives a text-rich one from documents, conversations, events and embeddings. Both are plain logical
plans over Parquet scans; nothing is collected.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import weight_millionths
from .sources import table


#: Rows of a relation from which on joins do not broadcast it through the driver.
MERGE_ROWS = 500_000


@dataclass(frozen=True)
class City:
    """road(src, dst, len) both ways; sites(poi, v, dis); site_terms(poi, term, tf, idf_m, w_m); users(usr, v, dis);
    user_terms(usr, term); checkins(poi, usr); friends(usr, friend) both ways; social(src, dst, indeg), w = 1 / indeg."""

    road: DataFrame
    sites: DataFrame
    site_terms: DataFrame
    users: DataFrame
    user_terms: DataFrame
    checkins: DataFrame
    friends: DataFrame
    social: DataFrame

    def kept(self, write, *only: str) -> City:
        """Every relation, or ``only`` those named, passed through ``write(df, name)``, e.g. to a table that later jobs read."""
        return replace(self, **{k: _merged(write(getattr(self, k), k)) for k in only or self.__dataclass_fields__})


def _merged(df: DataFrame) -> DataFrame:
    """``df``, hinted to be merged in joins if it has many rows: their compressed files look small enough for a broadcast."""
    if getattr(df, "_sized", False):
        return df
    out = df.hint("merge") if df.count() > MERGE_ROWS else df
    out._kept, out._sized = getattr(df, "_kept", False), True
    return out


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """usr bought poi at time d; o, ln order purchases of the same time; rf is the return flag."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_returnflag", "l_shipdate")
    order = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = line.join(order.hint("merge"), line["l_orderkey"] == order["o_orderkey"])
    return joined.select(F.col("o_custkey").alias("usr"), F.col("l_partkey").alias("poi"), F.col("l_shipdate").alias("d"), F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("ln"), F.col("l_returnflag").alias("rf"))


def street_grid(customers: DataFrame) -> DataFrame:
    """road(src, dst, len), both directions, over customer keys laid out row by row on a square."""
    size = customers.agg(F.ceil(F.sqrt(F.count("*"))).cast("long").alias("side"))
    at = customers.select(F.col("c_custkey").alias("v"), F.col("c_acctbal").alias("bal")).crossJoin(F.broadcast(size))  # one row
    right = at.where(F.col("v") % F.col("side") != F.col("side") - 1).select("v", "bal", (F.col("v") + 1).alias("to"))
    down = at.where((F.col("v") % F.col("side") == 0) | (F.col("v") % 4 != 3)).select("v", "bal", (F.col("v") + F.col("side")).alias("to"))
    other = customers.select(F.col("c_custkey").alias("to"), F.col("c_acctbal").alias("other"))
    one = right.union(down).join(other.hint("merge"), "to").select(F.col("v").alias("src"), F.col("to").alias("dst"), (F.lit(1) + F.floor(F.abs(F.col("bal") - F.col("other")) / 500)).cast("long").alias("len"))
    return one.union(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "len"))


def term_weights(raw: DataFrame) -> DataFrame:
    """poi, term, tf, idf_m, w_m from (poi, term, tf): idf in integer thousandths, weights in millionths."""
    n = raw.agg(F.countDistinct("poi").alias("n_sites"))
    df = raw.groupBy("term").agg(F.count("*").alias("df")).crossJoin(F.broadcast(n))  # one row
    idf = df.select("term", F.round(1000 * F.log(1 + F.col("n_sites") / F.col("df"))).cast("long").alias("idf_m"))
    rows = raw.join(F.broadcast(idf), "term")  # one row a word
    norm = rows.groupBy("poi").agg(F.sum((F.col("tf") * F.col("idf_m")) * (F.col("tf") * F.col("idf_m"))).alias("norm2"))
    return rows.join(norm.hint("merge"), "poi").select("poi", "term", "tf", "idf_m", weight_millionths(F.col("tf"), F.col("idf_m"), F.col("norm2")).alias("w_m"))


def follower_edges(bought: DataFrame, customers: DataFrame) -> DataFrame:
    """social(src, dst, indeg): dst bought an item next after src, within a gap that grows with the balance of src."""
    order = Window.partitionBy("poi").orderBy("d", "o", "ln", "usr")
    following = bought.select("usr", F.lead("usr").over(order).alias("dst"), F.datediff(F.lead("d").over(order), "d").alias("gap"))
    gap = F.when(F.col("c_acctbal") >= 9500, 365).when(F.col("c_acctbal") >= 8000, 90).otherwise(7)
    linked = following.where("dst is not null and dst <> usr").join(customers.select("c_custkey", "c_acctbal").hint("merge"), F.col("usr") == F.col("c_custkey")).where(F.col("gap") <= gap)
    edges = linked.select(F.col("usr").alias("src"), "dst").distinct()
    return edges.withColumn("indeg", F.count("*").over(Window.partitionBy("dst")))


def parts_city(spark: SparkSession, sf_dir: str, write=lambda df, name: df) -> City:
    """``write(df, name)`` may keep, as a table, what several relations are made of."""
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_type", "p_brand", "p_size")
    bought = write(purchases(spark, sf_dir), "purchases")
    first = bought.groupBy("poi").agg(F.min(F.struct("d", "o", "ln", "usr")).alias("f")).select("poi", F.col("f.usr").alias("v"))
    sites = parts.join(first.hint("merge"), parts["p_partkey"] == first["poi"]).select("poi", "v", (1 + F.col("p_size") % 5).cast("long").alias("dis"))
    words = parts.select(F.col("p_partkey").alias("poi"), F.explode(F.concat(F.split("p_name", " "), F.array(F.lower("p_type"), F.lower("p_brand")))).alias("term"))
    site_terms = write(term_weights(words.groupBy("poi", "term").agg(F.count("*").alias("tf"))), "site_terms")
    rank = Window.partitionBy("usr").orderBy(F.desc("fame"), "term")
    fame = bought.select("usr", "poi").join(site_terms.select("poi", "term", "tf", "idf_m").hint("merge"), "poi").groupBy("usr", "term").agg((F.sum("tf") * F.first("idf_m") * F.first("idf_m")).alias("fame"))
    user_terms = fame.withColumn("nth", F.row_number().over(rank)).where("nth <= 3").select("usr", "term")
    social = write(follower_edges(bought, customers), "social")
    pair = social.select("src", "dst")
    friends = pair.union(pair.select("dst", "src")).toDF("usr", "friend").distinct()
    users = customers.select(F.col("c_custkey").alias("usr"), F.col("c_custkey").alias("v"), (1 + F.col("c_nationkey") % 3).cast("long").alias("dis"))
    return City(street_grid(customers), sites, site_terms, users, user_terms, bought.where("rf = 'R'").select("poi", "usr").distinct(), friends, social)


def events_city(spark: SparkSession, sf_dir: str, neighbours: int = 4) -> City:
    """Users of the event stream, documents 0..99 as places with their words, and a road of nearest vectors.

    Lengths are distances of the vectors in hundredths, rounded up, so that they stay integers.
    """
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    docs = table(spark, sf_dir, "documents").where("doc_id < 100").select("doc_id", "text")
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    n_vec = vectors.agg(F.count("*").alias("n_vec"))
    said = table(spark, sf_dir, "conversations").where("role = 'user'").select("conv_id", "text")
    n_conv = table(spark, sf_dir, "conversations").agg((F.max("conv_id") + 1).alias("n_conv"))
    words = lambda df, key: df.select(key, F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("term"))
    users = events.select(F.col("user_id").alias("usr")).distinct()
    placed = users.crossJoin(F.broadcast(n_vec)).select("usr", (F.col("usr") % F.col("n_vec")).alias("v"), F.lit(1).cast("long").alias("dis"))
    sites = docs.crossJoin(F.broadcast(n_vec)).select(F.col("doc_id").alias("poi"), (F.col("doc_id") % F.col("n_vec")).alias("v"), F.lit(1).cast("long").alias("dis"))
    site_terms = term_weights(words(docs, "doc_id").groupBy(F.col("doc_id").alias("poi"), "term").agg(F.count("*").alias("tf")))
    conv = users.crossJoin(F.broadcast(n_conv)).select("usr", (F.col("usr") % F.col("n_conv")).alias("conv_id"))
    user_terms = conv.join(words(said, "conv_id"), "conv_id").select("usr", "term").distinct()
    # vectors of the road are a bounded table (one per street corner), compared in blocks against themselves
    x, y = vectors.select(F.col("vec_id").alias("src"), F.col("embedding").alias("a")), vectors.select(F.col("vec_id").alias("dst"), F.col("embedding").alias("b"))
    gap = F.sqrt(F.aggregate(F.zip_with("a", "b", lambda p, q: ((p - q) * (p - q)).cast("double")), F.lit(0.0), lambda s, z: s + z))
    near = x.join(F.broadcast(y), F.col("src") != F.col("dst")).select("src", "dst", gap.alias("gap")).withColumn("nth", F.row_number().over(Window.partitionBy("src").orderBy("gap", "dst"))).where((F.col("nth") <= neighbours) | (F.col("dst") == F.col("src") + 1))
    one = near.select("src", "dst", F.ceil(100 * F.col("gap")).cast("long").alias("len"))
    road = one.union(one.select("dst", "src", "len")).groupBy("src", "dst").agg(F.min("len").alias("len"))
    checkins = events.where("event_type = 'purchase'").select(F.col("k").alias("poi"), F.col("user_id").alias("usr")).distinct()
    span = events.agg(F.count("*").alias("n_events"))
    order = Window.partitionBy("k").orderBy("ts", "event_id")
    following = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(order).alias("dst"), (F.lead("ts").over(order).cast("timestamp").cast("double") - F.col("ts").cast("timestamp").cast("double")).alias("gap")).crossJoin(F.broadcast(span))
    edges = following.where("dst is not null and dst <> src").where(F.col("gap") <= 3600 * F.lit(10000.0) / F.col("n_events")).select("src", "dst").distinct()
    social = edges.withColumn("indeg", F.count("*").over(Window.partitionBy("dst")))
    friends = edges.union(edges.select("dst", "src")).toDF("usr", "friend").distinct()
    return City(road, sites, site_terms, placed, user_terms, checkins, friends, social)
