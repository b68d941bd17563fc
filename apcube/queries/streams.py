"""Streaming queries: each drains the event stream and gives what the batch gives."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from apcube.operators.boxtree import Nodes
from apcube.operators.index import assign
from apcube.plans.spec import Tiling
from apcube.queries.methods import BOXES
from apcube.queries.registry import query
from apcube.queries.surroundings import scratch
from apcube.sources.tables import cents, load
from apcube.streaming import ingest

W = np.array([57600.0, 57600.0])
_A = np.array(BOXES)
_MAX = "select max(ts) - interval 1 hour as mark from events"


def _events(spark, sf_dir):
    return ingest.read_stream(spark, sf_dir)


def _points(spark, sf_dir):
    """Value and user as a plane: lead() needs the whole stream, so the second axis is the user."""
    return _events(spark, sf_dir).select("event_id", "ts", cents("value").alias("x"), (F.col("user_id") * 97 % 57600).alias("y"), F.lit(None).cast("bigint").alias("m"))


def _nodes() -> Nodes:
    return Nodes.of_boxes(_A[:, 1:3], _A[:, 3:5], np.zeros(64, int))


query("src_stream_parquet", "select count(*) as n, sum(event_id)::bigint as s from events")(lambda s, d: ingest.drain(_events(s, d).select("event_id"), scratch(s, "stream")).agg(F.count("*").alias("n"), F.sum("event_id").alias("s")))


@query("str_ingest_cells", "select (round(value * 100)::bigint // 7200)::bigint as t1, ((user_id * 97 % 57600) // 7200)::bigint as t2, count(*) as value from events group by all")
def _(spark, sf_dir):
    per = np.full((64, 2), 1800, np.int64)
    cells = ingest.ingest_cells(_points(spark, sf_dir), scratch(spark, "ingest"), ["x", "y"], _nodes(), W, per)
    from apcube.operators.index import Index

    n = _nodes()
    ix = Index(["x", "y"], W, n, n.leaves, per, cells, 1 << 16, True, 1)
    return ix.chart(Tiling({"x": 7200, "y": 7200}))


_SUM = "count(*) as n, sum(round(value * 100)::bigint)::bigint as s"
query("str_tumbling", f"select floor(epoch(time_bucket(interval 1 day, ts)))::bigint as start, {_SUM} from events group by all having max(time_bucket(interval 1 day, ts)) + interval 1 day <= ({_MAX})")(lambda s, d: _closed(ingest.drain(ingest.windows(_events(s, d), "1 day"), scratch(s, "tumbling"))))
query(
    "str_sliding",
    f"with e as (select *, unnest([0, 6, 12, 18]) as back from events), w as (select time_bucket(interval 6 hour, ts) - to_hours(back) as start, value from e) select floor(epoch(start))::bigint as start, {_SUM} from w group by w.start having w.start + interval 1 day <= ({_MAX})",
)(lambda s, d: _closed(ingest.drain(ingest.windows(_events(s, d), "1 day", "6 hours"), scratch(s, "sliding"))))


def _closed(df):
    return df.select(F.unix_timestamp("start").alias("start"), "n", "s")


@query(
    "str_session",
    f"""with g as (select *, case when ts - lag(ts) over w < interval 12 hour then 0 else 1 end as new from events window w as (partition by user_id order by ts, event_id)),
k as (select *, sum(new) over (partition by user_id order by ts, event_id) as k from g)
select user_id, floor(epoch(min(ts)))::bigint as start, count(*) as n from k group by user_id, k having max(ts) + interval 12 hour <= ({_MAX})""",
)
def _(spark, sf_dir):
    got = ingest.drain(ingest.sessions(_events(spark, sf_dir), "12 hours"), scratch(spark, "session"))
    return got.select("user_id", F.unix_timestamp("start").alias("start"), "n")


@query("str_watermark_late", f"select count(*) as late from events where time_bucket(interval 1 day, ts) + interval 1 day > ({_MAX})")
def _(spark, sf_dir):
    """Records in windows that the watermark hasn't closed: all records less those delivered."""
    got = ingest.drain(ingest.windows(_events(spark, sf_dir), "1 day"), scratch(spark, "late")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("done"))
    return load(spark, sf_dir, "events").agg(F.count("*").alias("every")).crossJoin(got).select((F.col("every") - F.col("done")).cast("long").alias("late"))  # one row each


@query("str_dedup", "select count(distinct (user_id, event_type)) as n from events")
def _(spark, sf_dir):
    e = _events(spark, sf_dir).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return ingest.drain(e.select("user_id", "event_type"), scratch(spark, "dedup")).agg(F.count("*").alias("n"))


@query("str_stateful", "select count(*) as n, min(round(value * 100)::bigint) as lo, max(round(value * 100)::bigint) as hi from events")
def _(spark, sf_dir):
    placed = assign(_points(spark, sf_dir).select("x", "y"), ["x", "y"], _nodes(), _nodes().leaves, W).withColumn("leaf", F.col("leaf").cast("long"))
    path, grown = scratch(spark, "state"), ingest.growing_boxes(placed)
    ingest.drain_batches(grown, path, lambda b, i: b.withColumn("batch", F.lit(i)).write.mode("overwrite").parquet(f"{path}/out/run={i}"), "update")
    last = spark.read.parquet(f"{path}/out").groupBy("leaf").agg(F.max_by(F.struct("n", "lo_x", "hi_x"), "batch").alias("v"))
    return last.agg(F.sum("v.n").cast("long").alias("n"), F.min("v.lo_x").alias("lo"), F.max("v.hi_x").alias("hi"))


@query("str_stream_static_join", "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by all")
def _(spark, sf_dir):
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    e = _events(spark, sf_dir)
    return ingest.drain(e.join(c, e.user_id == c.c_custkey).select("c_mktsegment"), scratch(spark, "static")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("str_stream_stream_join", "select count(*) as pairs from events v join events p on v.user_id = p.user_id and p.ts between v.ts and v.ts + interval 1 hour where v.event_type = 'view' and p.event_type = 'purchase'")
def _(spark, sf_dir):
    """Views followed by a purchase of the same user within an hour."""
    e = _events(spark, sf_dir).withWatermark("ts", "2 hours")
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("vt"))
    p = _events(spark, sf_dir).withWatermark("ts", "2 hours").where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"))
    joined = v.join(p, F.expr("u = user_id and pt >= vt and pt <= vt + interval 1 hour"))
    return ingest.drain(joined.select("u"), scratch(spark, "both")).agg(F.count("*").alias("pairs"))
