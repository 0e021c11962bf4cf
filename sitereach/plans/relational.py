"""Relational and streaming queries around the methods: reports, time windows, as-of joins, sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import model
from ..operators import workloads
from ..sources import keep, table
from ..streaming import checkins
from . import oracles as sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


def _visits(spark, sf_dir: str) -> DataFrame:
    """usr, poi, day of every purchase that counts as a visit."""
    return model.purchases(spark, sf_dir).where("rf = 'R'").select("usr", "poi", F.to_date("d").alias("day"))


_VISITS = sql.CITY + ", visit as (select usr, poi, d::DATE as day from buy where rf = 'R')\n"
_WHERE = ", home as (select c_custkey as usr, n_name as nation, r_name as region, c_mktsegment as segment from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)\n"


def _homes(spark, sf_dir: str) -> DataFrame:
    c, n, r = (table(spark, sf_dir, x) for x in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"]).select(F.col("c_custkey").alias("usr"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"), F.col("c_mktsegment").alias("segment"))


@query(_VISITS + _WHERE + "select region, nation, count(*)::BIGINT as visits, count(distinct usr)::BIGINT as visitors from visit join home using (usr) group by rollup (region, nation)")
def ops_rollup(spark, sf_dir):
    return _visits(spark, sf_dir).join(_homes(spark, sf_dir), "usr").rollup("region", "nation").agg(F.count("*").alias("visits"), F.count_distinct("usr").alias("visitors"))


@query(_VISITS + _WHERE + "select region, segment, count(*)::BIGINT as visits from visit join home using (usr) group by cube (region, segment)")
def ops_cube(spark, sf_dir):
    return _visits(spark, sf_dir).join(_homes(spark, sf_dir), "usr").cube("region", "segment").agg(F.count("*").alias("visits"))


@query(
    _VISITS + _WHERE + """select region, (count(*) filter (segment = 'BUILDING'))::BIGINT as building, (count(*) filter (segment = 'MACHINERY'))::BIGINT as machinery
    from visit join home using (usr) group by region having count(*) > 10"""
)
def ops_pivot(spark, sf_dir):
    return _visits(spark, sf_dir).join(_homes(spark, sf_dir), "usr").groupBy("region").agg(F.count("*").alias("n"), F.count_if(F.col("segment") == "BUILDING").alias("building"), F.count_if(F.col("segment") == "MACHINERY").alias("machinery")).where("n > 10").drop("n")


@query(
    _VISITS + """, a as (select poi, day, count(*)::BIGINT as n from visit group by poi, day)
    select poi, day::VARCHAR as day, n, (sum(n) over (partition by poi order by day rows between unbounded preceding and current row))::BIGINT as so_far,
    (sum(n) over (partition by poi order by day range between interval 30 days preceding and current row))::BIGINT as last_month,
    (rank() over (partition by day order by n desc, poi))::INT as place, coalesce(date_diff('day', lag(day) over (partition by poi order by day), day), -1)::INT as gap from a"""
)
def ops_windows(spark, sf_dir):
    daily = _visits(spark, sf_dir).groupBy("poi", "day").agg(F.count("*").alias("n")).withColumn("nr", F.datediff("day", F.lit("1970-01-01")))
    run = Window.partitionBy("poi").orderBy("day")
    return daily.select(
        "poi", F.col("day").cast("string").alias("day"), "n",
        F.sum("n").over(run.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"),
        F.sum("n").over(Window.partitionBy("poi").orderBy("nr").rangeBetween(-30, 0)).alias("last_month"),
        F.rank().over(Window.partitionBy("day").orderBy(F.desc("n"), "poi")).alias("place"),
        F.coalesce(F.datediff("day", F.lag("day").over(run)), F.lit(-1)).alias("gap"),
    )


@query(
    """with e as (select event_id, ts, user_id, event_type, json_extract(props, '$.k')::BIGINT as k from events)
    select v.event_id, v.user_id, v.k, coalesce((select max(struct_pack(ts := p.ts, event_id := p.event_id)).event_id from e p where p.event_type = 'purchase' and p.user_id = v.user_id and p.ts < v.ts), -1) as last_purchase
    from e v where v.event_type = 'view'"""
)
def ops_asof(spark, sf_dir):
    """The last purchase of a user before each view: one pass over the union, no join."""
    e = checkins.parsed(table(spark, sf_dir, "events"))
    before = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    both = e.where("event_type in ('view', 'purchase')").withColumn("ts", F.unix_micros("ts"))
    last = F.max(F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))).over(before)
    return both.withColumn("last_purchase", F.coalesce(last["event_id"], F.lit(-1))).where("event_type = 'view'").select("event_id", "user_id", "k", "last_purchase")


@query(
    """with e as (select event_id, ts, user_id, event_type, json_extract(props, '$.k')::BIGINT as k from events)
    select v.event_id as view_id, p.event_id as purchase_id from e v join e p on v.k = p.k and p.ts > v.ts and p.ts <= v.ts + interval 1 hour where v.event_type = 'view' and p.event_type = 'purchase'"""
)
def ops_interval_join(spark, sf_dir):
    """Purchases within an hour of a view of the same place: an equi-join on place and hour, the view also put into the next hour."""
    e = checkins.parsed(table(spark, sf_dir, "events")).withColumn("at", F.unix_micros("ts")).withColumn("hour", F.floor(F.col("at") / 3_600_000_000))
    view = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "k", F.col("at").alias("seen"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    buy = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "k", "at", "hour")
    return view.join(buy, ["k", "hour"]).where((F.col("at") > F.col("seen")) & (F.col("at") <= F.col("seen") + 3_600_000_000)).select("view_id", "purchase_id")


@query(sql.CITY + ", a as (select distinct usr from checkins), b as (select distinct usr from friends) select 'both' as part, count(*)::BIGINT as n from (select * from a intersect select * from b) union all select 'visits only', count(*) from (select * from a except select * from b) union all select 'either', count(*) from (select * from a union select * from b)")
def ops_sets(spark, sf_dir):
    c = model.parts_city(spark, sf_dir)
    a, b = c.checkins.select("usr").distinct(), c.friends.select("usr").distinct()
    count = lambda df, part: df.agg(F.count("*").alias("n")).select(F.lit(part).alias("part"), "n")
    return count(a.intersect(b), "both").union(count(a.exceptAll(b), "visits only")).union(count(a.union(b).distinct(), "either"))


@query("select page_id, length(regexp_replace(html, '<[^>]*>', ' ', 'g'))::INT as n_text, len(regexp_extract_all(html, '<[^>]*>'))::INT as n_tags, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages")
def ops_pages(spark, sf_dir):
    p = table(spark, sf_dir, "pages")
    return p.select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", " ")).alias("n_text"), F.size(F.regexp_extract_all("html", F.lit("<[^>]*>"), F.lit(0))).alias("n_tags"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))


_EVENTS = "with e as (select event_id, ts, user_id, json_extract(props, '$.k')::BIGINT as k from events where event_type = 'purchase')\n"


@query(_EVENTS + "select k, epoch(date_trunc('hour', ts))::BIGINT as start, count(*)::BIGINT as visits from e group by 1, 2")
def stream_checkins_tumbling(spark, sf_dir):
    return checkins.drained(spark, sf_dir, checkins.tumbling)


@query(_EVENTS + ", w as (select k, unnest([0, 1, 2, 3]) as i, floor(epoch(ts))::BIGINT as t from e) select k, ((t // 900 - i) * 900)::BIGINT as start, count(*)::BIGINT as visits from w group by 1, 2")
def stream_checkins_sliding(spark, sf_dir):
    return checkins.drained(spark, sf_dir, checkins.sliding)


@query(
    _EVENTS + """, g as (select user_id, ts, case when ts >= lag(ts) over w + interval 1 hour or lag(ts) over w is null then 1 else 0 end as opens from e window w as (partition by user_id order by ts, event_id)),
    s as (select user_id, ts, sum(opens) over (partition by user_id order by ts rows unbounded preceding) as nr from g)
    select user_id, floor(epoch(min(ts)))::BIGINT as start, count(*)::BIGINT as visits from s group by user_id, nr"""
)
def stream_checkins_session(spark, sf_dir):
    return checkins.drained(spark, sf_dir, checkins.sessions)


@query(_EVENTS + "select k, count(distinct user_id)::BIGINT as visitors from e group by k")
def stream_visitors(spark, sf_dir):
    """Different visitors of each place, kept up to date by a stateful operator."""
    return checkins.drained(spark, sf_dir, checkins.visitors, "update").groupBy("k").agg(F.max("visitors").alias("visitors"))


@query(_EVENTS + "select event_id, user_id, k from e")
def stream_without_repeats(spark, sf_dir):
    return checkins.drained(spark, sf_dir, lambda s: checkins.without_repeats(s).select("event_id", "user_id", "k"), "append")


@query(
    """with e as (select ts, user_id, event_type, json_extract(props, '$.k')::BIGINT as k from events)
    select v.user_id as viewer, p.user_id, v.k, epoch_us(v.ts)::BIGINT as seen, epoch_us(p.ts)::BIGINT as ts from e v join e p on v.k = p.k and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour where v.event_type = 'view' and p.event_type = 'purchase'"""
)
def stream_view_to_purchase(spark, sf_dir):
    """Two streams joined by place and interval."""
    out = checkins.view_to_purchase(checkins.stream_of(spark, sf_dir, "view"), checkins.purchases(spark, sf_dir))
    return checkins.drain(spark, out, "append").select("viewer", "user_id", "k", F.unix_micros("seen").alias("seen"), F.unix_micros("ts").alias("ts"))


_DYNAMIC = sql.CITY.replace("checkins as (select distinct poi, usr from buy where rf = 'R')", "checkins as (select distinct poi, usr from buy where rf = 'R' union select k, user_id from (select json_extract(props, '$.k')::BIGINT as k, user_id from events where event_type = 'purchase') where k in (select poi from sites))")


@query(sql.CITY + ", e as (select user_id, json_extract(props, '$.k')::BIGINT as k from events where event_type = 'purchase') select f.usr, k as poi, count(*)::BIGINT as n from e join friends f on f.friend = user_id group by f.usr, k")
def stream_changed_social(spark, sf_dir):
    """Pairs whose social relevance the check-ins of the stream touch, and how often."""
    city = model.parts_city(spark, sf_dir)
    friends = keep(city.friends, "friends")
    return checkins.drained(spark, sf_dir, lambda s: checkins.changed_social(s, friends), "append").groupBy("usr", "poi").agg(F.count("*").alias("n"))


@query(_DYNAMIC + sql.GAIN.format(a=0.6, b=1 - 0.6) + sql.DIST.format(sources="sites") + sql.TOPK.format(k=10) + sql.CAND.format(n=20) + "select poi, usr from topk where poi in (select poi from cand)")
def stream_audiences(spark, sf_dir):
    """Audiences kept up to date while check-ins of the event stream come in."""
    city = model.parts_city(spark, sf_dir).kept(keep)
    cand = keep(workloads.drawn_sites(city, 20), "cand")
    return checkins.kept_up(spark, city, checkins.purchases(spark, sf_dir), cand, 10, 0.6).select("poi", "usr")


def queries() -> dict:
    return QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES
