"""Check-ins as a stream: windows, sessions and state over the events, and audiences kept up to date."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model import City
from ..operators.audience import batch, verify
from ..sources import keep, store_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
#: How long late events are waited for.
LATE = "1 hour"


def parsed(events: DataFrame) -> DataFrame:
    """event_id, ts (UTC), user_id, event_type, k."""
    ts = F.to_utc_timestamp(F.col("ts").cast("timestamp"), F.current_timezone())
    return events.select("event_id", ts.alias("ts"), "user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))


def stream_of(spark: SparkSession, sf_dir: str, event_type: str) -> DataFrame:
    """The events of a type as a stream; its source is the folder of the events table."""
    events = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", 8).parquet(sf_dir)
    return parsed(events).where(F.col("event_type") == event_type).withWatermark("ts", LATE)


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream of check-ins."""
    return stream_of(spark, sf_dir, "purchase")


def _start(window: str = "window"):
    return F.unix_seconds(F.col(f"{window}.start")).alias("start")


def tumbling(stream: DataFrame) -> DataFrame:
    return stream.groupBy("k", F.window("ts", "1 hour")).agg(F.count("*").alias("visits")).select("k", _start(), "visits")


def sliding(stream: DataFrame) -> DataFrame:
    return stream.groupBy("k", F.window("ts", "1 hour", "15 minutes")).agg(F.count("*").alias("visits")).select("k", _start(), "visits")


def sessions(stream: DataFrame, gap: str = "1 hour") -> DataFrame:
    return stream.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("visits")).select("user_id", _start("session_window"), "visits")


def visitors(stream: DataFrame) -> DataFrame:
    """k, visitors after each batch; the state of a place is the sorted list of its visitors."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0]) if state.exists else set()
        for frame in frames:
            seen.update(frame["user_id"].tolist())
        state.update((sorted(seen),))
        yield pd.DataFrame({"k": [key[0]], "visitors": [len(seen)]})

    return stream.groupBy("k").applyInPandasWithState(update, "k long, visitors long", "seen array<long>", "update", GroupStateTimeout.NoTimeout)


def without_repeats(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def changed_social(stream: DataFrame, friends: DataFrame) -> DataFrame:
    """usr, poi whose social relevance a check-in changes: the friends of the visitor (stream-static join)."""
    return stream.join(friends, stream["user_id"] == friends["friend"]).select(F.col("usr"), F.col("k").alias("poi"), "ts")


def view_to_purchase(views: DataFrame, bought: DataFrame) -> DataFrame:
    """Views followed by a purchase of the same place within an hour (stream-stream interval join)."""
    v, p = views.select(F.col("k").alias("vk"), F.col("ts").alias("seen"), F.col("user_id").alias("viewer")), bought.select("k", "ts", "user_id")
    return v.join(p, F.expr("vk = k and ts >= seen and ts <= seen + interval 1 hour")).select("viewer", "user_id", "k", "seen", "ts")


def drain(spark: SparkSession, out: DataFrame, mode: str) -> DataFrame:
    """Run a streaming query over what is there and return its table. Batches are written idempotently, by their id."""
    folder = f"{store_dir(spark)}/stream-{uuid.uuid4().hex}"
    schema = out.schema

    def write(rows: DataFrame, number: int) -> None:
        # in complete mode every batch holds the whole result, so the last one replaces the others
        rows.write.mode("overwrite").parquet(f"{folder}/table" if mode == "complete" else f"{folder}/table/batch={number}")

    out.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema).parquet(f"{folder}/table").select(*schema.names)


def drained(spark: SparkSession, sf_dir: str, plan: Callable[[DataFrame], DataFrame], mode: str = "complete") -> DataFrame:
    """The same of a plan over the stream of check-ins."""
    return drain(spark, plan(purchases(spark, sf_dir)), mode)


def refreshed(city: City, audience: DataFrame, new: DataFrame, candidates: DataFrame, k: int, alpha: float) -> tuple[City, DataFrame]:
    """The city with further check-ins (poi, usr), and its audiences, from those before.

    A check-in changes the social relevance of its place to the friends of the visitor, and nothing else: the lists of
    these users alone are made again, by the verification of batch retrieval.
    """
    added = new.select("poi", "usr").join(city.sites.select("poi"), "poi", "left_semi").distinct().join(city.checkins, ["poi", "usr"], "left_anti")
    added = keep(added, "new_checkins")
    if added.isEmpty():
        return city, audience
    touched = keep(added.join(city.friends, added["usr"] == city.friends["friend"]).select(city.friends["usr"]).distinct(), "touched_users")
    city = replace(city, checkins=keep(city.checkins.union(added), "checkins"))
    pairs = touched.crossJoin(F.broadcast(candidates.select("poi").distinct()))  # candidates are a bounded query set
    again = verify(city, pairs, k, alpha)
    return city, keep(audience.select("poi", "usr").join(touched, "usr", "left_anti").select("poi", "usr").union(again), "audience")


def kept_up(spark: SparkSession, city: City, stream: DataFrame, candidates: DataFrame, k: int, alpha: float) -> DataFrame:
    """Audiences after a stream of check-ins (k: the place, user_id: the visitor), brought up to date batch by batch.

    A batch that is run again finds its check-ins in the city already and changes nothing.
    """
    state = {"city": city, "audience": keep(batch(city, candidates, k, alpha)[0], "audience")}

    def update(rows: DataFrame, _: int) -> None:
        new = rows.select(F.col("k").alias("poi"), F.col("user_id").alias("usr"))
        state["city"], state["audience"] = refreshed(state["city"], state["audience"], new, candidates, k, alpha)

    folder = f"{store_dir(spark)}/stream-{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(update).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()
    return state["audience"]
