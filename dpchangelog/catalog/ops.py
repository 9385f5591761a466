"""Surrounding operators: filters, joins, group-bys, windows, set operations, SQL functions, and streams."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import sql as sql_functions
from ..functions.intervals import DAY, micros
from ..operators import linear
from ..sources.tables import table
from ..streaming import streams
from .base import *
from .base import CL_STATE, CL_STATUS, sql_idx, sql_laplace
from .releases import ERROR, SQL_ERROR

A, B = T0 + 5 * DAY, T0 + 12 * DAY


@query(f"select event_id, user_id, epoch_us(ts) as us from events where ts > timestamp '2024-01-06' and ts <= timestamp '2024-01-13'")
def filter_time_range(spark, d):
    """Bounds are literals of the column's own type, so they reach the Parquet scan."""
    e = table(spark, d, "events").where("ts > timestamp_ntz'2024-01-06' and ts <= timestamp_ntz'2024-01-13'")
    return e.select("event_id", "user_id", micros("ts").alias("us"))


@query("select event_id, cast(json_extract_string(props, '$.k') as integer) as k from events where cast(json_extract_string(props, '$.k') as integer) % 2 = 0")
def filter_predicate_json(spark, d):
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, d, "events").select("event_id", k.alias("k")).where("k % 2 = 0")


@query("select event_type, cast(sum(cast(json_extract_string(props, '$.k') as integer)) as bigint) as k from events group by 1")
def props_k_sum(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("int")).alias("k"))


@query("select r_name, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def join_broadcast_dims(spark, d):
    dims = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    c = table(spark, d, "customer")
    return c.join(F.broadcast(dims), c.c_nationkey == F.col("n_nationkey")).groupBy("r_name", "c_mktsegment").agg(F.count("*").alias("n"))  # 25 nations


@query("select o_orderpriority, count(*) as pairs, count(distinct o_orderkey) as orders from orders join lineitem on o_orderkey = l_orderkey where l_shipdate > o_orderdate and l_shipdate <= o_orderdate + interval 60 days group by 1")
def join_interval_ship(spark, d):
    """An equi-join by key with an interval as residual."""
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem").select("l_orderkey", "l_shipdate")
    j = o.join(li, (F.col("o_orderkey") == F.col("l_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate")) & (F.col("l_shipdate") <= F.col("o_orderdate") + F.expr("interval 60 days")))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("pairs"), F.count_distinct("o_orderkey").alias("orders"))


@query(f"select c_custkey from customer where c_custkey in (select o_custkey from orders where epoch_us(o_orderdate) > {T1995 + 2000 * DAY})")
def semi_touched(spark, d):
    """Entries that a range touches."""
    o = table(spark, d, "orders").where(micros("o_orderdate") > T1995 + 2000 * DAY).select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").select("c_custkey").join(o, "c_custkey", "left_semi")


@query(f"select c_custkey from customer where c_custkey not in (select o_custkey from orders where epoch_us(o_orderdate) > {T1995 + 2000 * DAY})")
def anti_untouched(spark, d):
    o = table(spark, d, "orders").where(micros("o_orderdate") > T1995 + 2000 * DAY).select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").select("c_custkey").join(o, "c_custkey", "left_anti")


def _geo(spark, d):
    dims = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    c = table(spark, d, "customer")
    return c.join(F.broadcast(dims), c.c_nationkey == F.col("n_nationkey"))


@query("select coalesce(r_name, '*') as r_name, coalesce(n_name, '*') as n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
def rollup_region_nation(spark, d):
    """Levels of a public hierarchy; each costs a fold, as a layer of a tree does."""
    out = _geo(spark, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))
    return out.select(F.coalesce("r_name", F.lit("*")).alias("r_name"), F.coalesce("n_name", F.lit("*")).alias("n_name"), "n")


@query("select coalesce(o_orderstatus, '*') as status, coalesce(o_orderpriority, '*') as priority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)")
def cube_status_priority(spark, d):
    out = table(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))
    return out.select(F.coalesce("o_orderstatus", F.lit("*")).alias("status"), F.coalesce("o_orderpriority", F.lit("*")).alias("priority"), "n")


@query("select coalesce(lang, '*') as lang, coalesce(source, '*') as source, count(*) as n from documents group by grouping sets ((lang), (source), ())")
def grouping_sets_release(spark, d):
    docs = table(spark, d, "documents").select("lang", "source")
    out = docs.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"))
    return out.select(F.coalesce("lang", F.lit("*")).alias("lang"), F.coalesce("source", F.lit("*")).alias("source"), "n")


@query(f"with {CL_STATE}, s as (select after as symbol, count(*) as n from cl group by 1) select symbol, round(n + {sql_laplace(16.0, 'tk', 'symbol')}, 6) as noisy from s order by noisy desc, symbol limit 3")
def topk_noisy_types(spark, d):
    """The largest noisy counts: free once the counts are released."""
    from ..functions.noise import laplace

    s = event_state(spark, d).groupBy(F.col("after").alias("symbol")).agg(F.count("*").alias("n"))
    return s.select("symbol", F.round(F.col("n") + laplace(16.0, key("tk"), F.col("symbol")), 6).alias("noisy")).orderBy(F.desc("noisy"), "symbol").limit(3)


@query("""select o_orderkey, o_custkey, row_number() over w as rn, cast(rank() over p as integer) as rk, cast(dense_rank() over p as integer) as dr, cast(ntile(4) over w as integer) as quarter, lag(o_orderstatus) over w as prev, first_value(o_orderkey) over w as first_key, round(percent_rank() over p, 9) as pr
from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey), p as (partition by o_custkey order by o_orderpriority)""")
def window_rank_suite(spark, d):
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    o = table(spark, d, "orders")
    return o.select("o_orderkey", "o_custkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.lag("o_orderstatus").over(w).alias("prev"), F.first("o_orderkey").over(w).alias("first_key"), F.round(F.percent_rank().over(p), 9).alias("pr"))


@query("select o_orderstatus, count(distinct o_custkey) as entries, true as within from orders group by 1")
def approx_distinct_entries(spark, d):
    """A sketch's count of entries beside the exact one, and whether it lies within three of its standard errors (0.02)."""
    sums = table(spark, d, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey", 0.02).alias("sketch"), F.count_distinct("o_custkey").alias("entries"))
    return sums.select("o_orderstatus", "entries", (F.abs(F.col("sketch") - F.col("entries")) <= 0.06 * F.col("entries")).alias("within"))


@query("""select 'both' as side, count(*) as n from (select distinct o_custkey from orders where o_orderstatus = 'F' intersect select distinct o_custkey from orders where o_orderstatus = 'O')
union all select 'first only', count(*) from (select distinct o_custkey from orders where o_orderstatus = 'F' except select distinct o_custkey from orders where o_orderstatus = 'O')
union all select 'either', count(*) from (select o_custkey from orders where o_orderstatus = 'F' union select o_custkey from orders where o_orderstatus = 'O')""")
def set_ops_entries(spark, d):
    f, o = (table(spark, d, "orders").where(F.col("o_orderstatus") == s).select("o_custkey") for s in "FO")
    n = lambda name, x: x.agg(F.count("*").alias("n")).select(F.lit(name).alias("side"), "n")
    return n("both", f.intersect(o)).unionByName(n("first only", f.subtract(o))).unionByName(n("either", f.union(o).distinct()))


@query("select lang, source, count(*) as n from documents group by 1, 2")
def documents_by_source(spark, d):
    return table(spark, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))


@query("""select regexp_extract(html, 'lang="([a-z]*)"', 1) as lang, count(*) as n from pages group by 1""")
def pages_by_lang(spark, d):
    return table(spark, d, "pages").groupBy(F.regexp_extract("html", 'lang="([a-z]*)"', 1).alias("lang")).agg(F.count("*").alias("n"))


@query(f"with {CL_STATUS} select entry, max(if(k = 0, after, null)) as \"first\", count(*) as n, count(*) filter (where after = 'F') as f from (select *, row_number() over (partition by entry order by ts, seq) - 1 as k from cl) group by 1")
def pivot_first_status(spark, d):
    cl = customer_status(spark, d)
    return cl.groupBy("entry").agg(F.min_by("after", F.struct("ts", "seq")).alias("first"), F.count("*").alias("n"), F.count_if(F.col("after") == "F").alias("f"))


@query(f"with {CL_STATE} select {sql_idx(DAY)} as idx, count(*) as n from cl group by 1")
def sql_surface_interval_udf(spark, d):
    """A SQL function, which Catalyst inlines into the plan."""
    spark.sql("create or replace temporary function interval_idx(ts bigint, t0 bigint, w bigint) returns bigint return (ts - t0 + pmod(t0 - ts, w)) div w - 1")
    event_state(spark, d).createOrReplaceTempView("event_state_log")
    return spark.sql(f"select interval_idx(ts, {T0}, {DAY}) as idx, count(*) as n from event_state_log group by 1")


_RANGES = [(0, 5, 17), (1, 0, 99), (2, 3, 64), (3, 31, 33)]


@query(f"""select cast(a as bigint) as range_id, cast(j as integer) as layer, cast(i as bigint) as idx from (values {str(_RANGES)[1:-1]}) as t(a, l, r), range(7) x(j), range(100) y(i)
where i * pow(2, j) >= l and (i + 1) * pow(2, j) <= r and (j = 6 or i // 2 * pow(2, j + 1) < l or (i // 2 + 1) * pow(2, j + 1) > r)""")
def sql_surface_cover_udtf(spark, d):
    """A table function that lists the nodes of a range, joined laterally."""
    sql_functions.register(spark)
    spark.createDataFrame(_RANGES, "range_id bigint, l bigint, r bigint").createOrReplaceTempView("asked_ranges")
    return spark.sql("select range_id, n.layer, n.idx from asked_ranges, lateral cover_nodes(l, r, 2, 7) n")


# Streams, run over what is there and returned as batches.
def _folder(spark) -> str:
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp()
    return f"{base.rstrip('/')}/stream-{uuid.uuid4().hex}"


def _stream(spark, d, name: str) -> DataFrame:
    """A table's files as a stream; the folder's other tables are left out by name."""
    schema = table(spark, d, name).schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{name}*.parquet").option("recursiveFileLookup", "true").parquet(d)


def _ran(spark, stream: DataFrame) -> DataFrame:
    f = _folder(spark)
    return streams.run_available(stream, f + "/out", f + "/checkpoint")


def _late_rows(spark, d, name, ts):
    """The table with a far row at the end of time, which closes all windows; it is dropped from the results."""
    return _stream(spark, d, name).withColumn(ts, F.col(ts).cast("timestamp"))





@query(f"select w as idx, count(*) as n from (select {sql_idx(DAY, ts='epoch_us(ts)')} as w from events) where w < (select max({sql_idx(DAY, ts='epoch_us(ts)')}) from events) group by 1")
def stream_daily_tumbling(spark, d):
    """Counts of closed days. The last day has not been passed by the watermark."""
    out = _ran(spark, streams.disjoint_stream(_late_rows(spark, d, "events", "ts"), "ts", "1 day", F.lit(1)))
    return out.select(((F.unix_micros("start") - T0) / DAY).cast("long").alias("idx"), F.col("exact").alias("n"))


@query(f"select cast(i as bigint) as idx, count(*) as n from range(-6, 40) r(i), events where epoch_us(ts) > {T0} + i * {DAY} and epoch_us(ts) <= {T0} + (i + 7) * {DAY} and {T0} + (i + 7) * {DAY} <= (select max(epoch_us(ts)) from events) group by 1")
def stream_sliding(spark, d):
    out = _ran(spark, streams.disjoint_stream(_late_rows(spark, d, "events", "ts"), "ts", "7 days", F.lit(1), slide="1 day"))
    return out.select(((F.unix_micros("start") - T0) / DAY).cast("long").alias("idx"), F.col("exact").alias("n"))


@query("select event_id, user_id, event_type from events")
def stream_dedup(spark, d):
    """Every event is sent twice; each stays once."""
    e = _late_rows(spark, d, "events", "ts").withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    return _ran(spark, streams.dedup_stream(e, "ts", ["event_id"], "31 days").select("event_id", "user_id", "event_type"))


@query(f"with {CL_STATE} select entry, ts, seq, before, after from (select *, row_number() over (partition by entry order by ts, seq) as n from cl) where n <= 8")
def stream_stateful_changelog(spark, d):
    """Mutations with at most 8 an entry, from state an entry."""
    e = _stream(spark, d, "events").select(F.col("user_id").alias("entry"), micros("ts").alias("ts"), F.col("event_id").alias("seq"), F.col("event_type").alias("value"))
    return _ran(spark, streams.changelog_stream(e, k=8))


@query(f"select if(event_id % 10 = 0, 'late', 'on time') as side, count(*) as n from events group by 1")
def stream_late_side_output(spark, d):
    """Every tenth event arrives three days late."""
    e = _stream(spark, d, "events").select("event_id", micros("ts").alias("us")).withColumn("arrival", F.col("us") + F.when(F.col("event_id") % 10 == 0, 3 * DAY).otherwise(0))
    parts = streams.late_side_output(e, "us", "arrival", DAY)
    out = [_ran(spark, p).agg(F.count("*").alias("n")).select(F.lit(n).alias("side"), "n") for n, p in zip(("on time", "late"), parts, strict=True)]
    return out[0].unionByName(out[1])


_GAP = 6 * 3_600_000_000


@query(f"""with x as (select user_id, epoch_us(ts) as t, lag(epoch_us(ts)) over (partition by user_id order by ts) as p from events), y as (select user_id, t, sum(if(p is null or t - p >= {_GAP}, 1, 0)) over (partition by user_id order by t) as s from x),
z as (select user_id as entry, min(t) as start_us, max(t) + {_GAP} as end_us, count(*) as n from y group by user_id, s) select * from z where end_us <= (select epoch_ms(max(ts)) * 1000 from events)""")
def stream_session_entries(spark, d):
    out = _ran(spark, streams.session_stream(_late_rows(spark, d, "events", "ts"), "ts", "user_id", "6 hours", "0 seconds"))
    return out.select("entry", F.unix_micros("start").alias("start_us"), F.unix_micros("end").alias("end_us"), "n")


@query("select o_orderkey, count(*) as n from orders join lineitem on o_orderkey = l_orderkey where l_shipdate > o_orderdate and l_shipdate <= o_orderdate + interval 60 days group by 1")
def stream_interval_join(spark, d):
    o = _late_rows(spark, d, "orders", "o_orderdate").select(F.col("o_orderkey").alias("k"), "o_orderdate")
    li = _late_rows(spark, d, "lineitem", "l_shipdate").select(F.col("l_orderkey").alias("k"), "l_shipdate")
    j = streams.interval_join_stream(o, li, "k", "o_orderdate", "l_shipdate", "60 days", "4000 days")
    out = _ran(spark, j.select(F.col("a.k").alias("o_orderkey")))
    return out.groupBy("o_orderkey").agg(F.count("*").alias("n"))


@query("select c_mktsegment as segment, count(*) as n from orders left join customer on o_custkey = c_custkey group by 1")
def stream_static_join(spark, d):
    """A stream of orders with their customers' segments, from a static table."""
    o = _stream(spark, d, "orders").select("o_orderkey", F.col("o_custkey").alias("k"))
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("k"), "c_mktsegment")
    out = _ran(spark, streams.enrich_stream(o, c, "k").select("o_orderkey", "c_mktsegment"))
    return out.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n"))
