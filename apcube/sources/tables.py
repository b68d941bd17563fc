"""The given tables as DataFrames, and the point views of the experiments, each with its SQL.

A view is a set of records on integer scales: cents, days, seconds or counts, so that the edges of cells and bins never
depend on binary fractions. ``VIEWS`` has, per name, a function (spark, sf_dir) and the SQL of the same rows.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table; time stamps without zone become time stamps in UTC."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    naive = [f.name for f in df.schema if f.dataType.typeName() == "timestamp_ntz"]
    return df.withColumns({c: F.to_timestamp(F.col(c)) for c in naive}) if naive else df


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


#: Raw columns behind dimensions: a coordinate in [lo, hi) lies in [(lo - slack) / scale, (hi + slack) / scale] of the column.
RAW = {
    "splom": {"qty": ("l_quantity", 1.0, 0.5), "price": ("l_extendedprice", 1.0, 0.01), "disc": ("l_discount", 100.0, 0.51), "tax": ("l_tax", 100.0, 0.51)},
    "hail": {"price": ("o_totalprice", 1.0, 0.01), "cust": ("o_custkey", 1.0, 0.0)},
}


def narrowed(df: DataFrame, name: str, where: dict[str, tuple[int, int]] | None) -> DataFrame:
    """``df`` under predicates on raw columns that a view's ranges imply: unlike those on scaled coordinates they reach the
    Parquet reader. They only leave out what the ranges leave out, so both are applied."""
    for dim, (lo, hi) in (where or {}).items():
        if dim in RAW.get(name, {}):
            column, scale, slack = RAW[name][dim]
            df = df.where((F.col(column) >= (lo - slack) / scale) & (F.col(column) <= (hi + slack) / scale))
    return df


def days(c: str, origin: str):
    return F.datediff(F.col(c), F.lit(origin).cast("date")).cast("long")


@dataclass(frozen=True)
class View:
    """``widths``: scales of each dimension's domain [0, width); ``id``: columns that order rows."""

    make: Callable[..., DataFrame]
    sql: str
    widths: dict[str, int]
    key: tuple[str, ...]


def _plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts", "props", cents("value").alias("x"))
    e = e.withColumn("y", F.lead("x").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("y is not null")
    seconds = F.unix_timestamp("ts") - 1704067200
    return e.select("event_id", "event_type", "user_id", "x", "y", F.weekday("ts").cast("long").alias("wd"), F.hour("ts").cast("long").alias("hr"), seconds.cast("long").alias("t"), F.get_json_object("props", "$.k").cast("long").alias("k"), (F.col("user_id") % 360).alias("dir"))


PLANE = """select event_id, event_type, user_id, x, y, isodow(ts) - 1 as wd, hour(ts) as hr, floor(epoch(ts))::bigint - 1704067200 as t,
  json_extract_string(props, '$.k')::bigint as k, user_id % 360 as dir
  from (select *, round(value * 100)::bigint as x, lead(round(value * 100)::bigint) over (partition by user_id order by ts, event_id) as y from events) where y is not null"""


def _splom(spark: SparkSession, sf_dir: str, where: dict | None = None) -> DataFrame:
    li = narrowed(load(spark, sf_dir, "lineitem"), "splom", where)
    return li.select("l_orderkey", "l_linenumber", "l_partkey", "l_returnflag", "l_linestatus", F.round("l_quantity").cast("long").alias("qty"), F.expr("cast(round(l_extendedprice * 100) as bigint) div 100").alias("price"), cents("l_discount").alias("disc"), cents("l_tax").alias("tax"), days("l_shipdate", "1995-01-01").alias("day"), cents("l_extendedprice").alias("ext"))


SPLOM = """select l_orderkey, l_linenumber, l_partkey, l_returnflag, l_linestatus, round(l_quantity)::bigint as qty, round(l_extendedprice * 100)::bigint // 100 as price,
  round(l_discount * 100)::bigint as disc, round(l_tax * 100)::bigint as tax, datediff('day', date '1995-01-01', l_shipdate::date) as day, round(l_extendedprice * 100)::bigint as ext from lineitem"""


def _delay(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    j = li.join(o, li.l_orderkey == o.o_orderkey)
    return j.select("l_orderkey", "l_linenumber", "l_partkey", "o_orderpriority", F.expr("cast(round(l_extendedprice * 100) as bigint) div 100").alias("price"), cents("l_discount").alias("disc"), cents("l_tax").alias("tax"), (F.year("l_shipdate") - 1995).cast("long").alias("year"), (F.month("l_shipdate") - 1).cast("long").alias("month"), F.weekday("l_shipdate").cast("long").alias("wd"), F.round("l_quantity").cast("long").alias("qty"), cents("o_totalprice").alias("total"), cents("l_extendedprice").alias("ext"))


DELAY = """select l_orderkey, l_linenumber, l_partkey, o_orderpriority, round(l_extendedprice * 100)::bigint // 100 as price, round(l_discount * 100)::bigint as disc, round(l_tax * 100)::bigint as tax,
  year(l_shipdate) - 1995 as year, month(l_shipdate) - 1 as month, isodow(l_shipdate) - 1 as wd, round(l_quantity)::bigint as qty, round(o_totalprice * 100)::bigint as total, round(l_extendedprice * 100)::bigint as ext
  from lineitem join orders on l_orderkey = o_orderkey"""


def _hail(spark: SparkSession, sf_dir: str, where: dict | None = None) -> DataFrame:
    o = narrowed(load(spark, sf_dir, "orders"), "hail", where)
    return o.select("o_orderkey", "o_orderstatus", "o_orderpriority", F.expr("cast(round(o_totalprice * 100) as bigint) div 100").alias("price"), F.col("o_custkey").alias("cust"), (F.month("o_orderdate") - 1).cast("long").alias("month"), (F.dayofmonth("o_orderdate") - 1).cast("long").alias("dom"), days("o_orderdate", "1995-01-01").alias("day"), cents("o_totalprice").alias("total"))


HAIL = """select o_orderkey, o_orderstatus, o_orderpriority, round(o_totalprice * 100)::bigint // 100 as price, o_custkey as cust, month(o_orderdate) - 1 as month, day(o_orderdate) - 1 as dom,
  datediff('day', date '1995-01-01', o_orderdate::date) as day, round(o_totalprice * 100)::bigint as total from orders"""


def _vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "embeddings")
    return e.select("vec_id", "label", *((F.round(F.element_at("embedding", i + 1).cast("double") * 1000) + 1000).cast("long").alias(f"e{i}") for i in range(16)))


VEC = "select vec_id, label, " + ", ".join(f"(round(embedding[{i + 1}]::double * 1000) + 1000)::bigint as e{i}" for i in range(16)) + " from embeddings"


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lb = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    return d.join(lb, "doc_id", "left").select("doc_id", "lang", "source", "quality", "toxic", F.col("n_chars").cast("long").alias("chars"), F.size(F.split("text", " ")).cast("long").alias("tokens"))


DOCS = "select doc_id, lang, source, quality, toxic, n_chars::bigint as chars, len(string_split(text, ' ')) as tokens from documents left join labels using (doc_id)"


def _geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c, n, r = (load(spark, sf_dir, t) for t in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return j.select("o_orderkey", F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"), F.expr("cast(round(o_totalprice * 100) as bigint) div 100").alias("price"), cents("o_totalprice").alias("total"))


GEO = """select o_orderkey, r_name as region, n_name as nation, c_mktsegment as segment, round(o_totalprice * 100)::bigint // 100 as price, round(o_totalprice * 100)::bigint as total
  from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"""

SIDE = 57600
VIEWS: dict[str, View] = {
    "plane": View(_plane, PLANE, {"x": SIDE, "y": SIDE}, ("event_id",)),
    "checkin": View(_plane, PLANE, {"x": SIDE, "y": SIDE, "wd": 7, "hr": 24, "t": 2592000}, ("event_id",)),
    "gps": View(_plane, PLANE, {"x": SIDE, "y": SIDE, "t": 2592000, "k": 100, "dir": 360}, ("event_id",)),
    "splom": View(_splom, SPLOM, {"qty": 60, "price": 108000, "disc": 12, "tax": 10, "day": 2500}, ("l_orderkey", "l_linenumber", "l_partkey", "ext")),
    "delay": View(_delay, DELAY, {"price": 108000, "disc": 12, "tax": 10, "year": 8, "month": 12, "wd": 7}, ("l_orderkey", "l_linenumber", "l_partkey", "ext")),
    "hail": View(_hail, HAIL, {"price": 500000, "cust": 15000, "month": 12, "dom": 31, "day": 2430}, ("o_orderkey",)),
    "vec": View(_vec, VEC, {f"e{i}": 2000 for i in range(16)}, ("vec_id",)),
    "docs": View(_docs, DOCS, {"chars": 144000, "tokens": 20000}, ("doc_id",)),
    "geo": View(_geo, GEO, {"price": 500000}, ("o_orderkey",)),
}


def view(spark: SparkSession, sf_dir: str, name: str, where: dict[str, tuple[int, int]] | None = None) -> DataFrame:
    """The view's rows; with ``where`` its scan skips what those ranges exclude, where raw columns allow (``RAW``)."""
    return VIEWS[name].make(spark, sf_dir, where) if where and name in RAW else VIEWS[name].make(spark, sf_dir)
