"""Fixtures of the query catalogue, as DataFrames and as SQL, and the registry."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.intervals import DAY, IntervalGrid, gcd_int, micros
from ..functions.noise import Key
from ..operators import changelog
from ..sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: 2024-01-01 and 1995-01-01 in microseconds.
T0, T1995 = 1_704_067_200_000_000, 788_918_400_000_000
EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]
STATUSES, ROLES = ["F", "O", "P"], ["assistant", "system", "user"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
LANGS = ["de", "en", "es", "fr"]
DAILY = IntervalGrid.regular(T0, DAY, 30)
#: Month ends 1995-01 to 2001-08, as days since 1970.
MONTHS = [f"{y}-{m:02d}-01" for y in range(1995, 2002) for m in range(1, 13)][:81]


def query(sql: str | None = None):
    """Register a function under its name, with its SQL."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def key(release: str) -> Key:
    return Key("test", release, public=True)


def month_ends() -> list[int]:
    from datetime import datetime, timezone

    return [int(datetime.fromisoformat(m).replace(tzinfo=timezone.utc).timestamp()) * 1_000_000 for m in MONTHS]


# DataFrames.
def events(spark, d) -> DataFrame:
    return table(spark, d, "events").withColumn("us", micros("ts"))


def event_state(spark, d) -> DataFrame:
    return changelog.from_history(events(spark, d).select("user_id", "us", "event_id", "event_type"), "user_id", "us", "event_type", "event_id")


def event_value(spark, d) -> DataFrame:
    e = events(spark, d).select("user_id", "us", "event_id", F.round(F.col("value") * 100).cast("long").alias("cents"))
    return changelog.from_history(e, "user_id", "us", "cents", "event_id")


def order_ship(spark, d) -> DataFrame:
    """Orders enter with 0 cents; each later ship day adds what it ships. Orders and lines are each shuffled once, by order."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), micros("o_orderdate").alias("t0"))
    li = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), micros("l_shipdate").alias("t"), F.round(F.col("l_extendedprice") * 100).cast("long").alias("c"))
    later = F.col("t") > F.col("t0")
    days = o.join(li, "k", "left").groupBy("k", "t0", F.when(later, F.col("t")).alias("ts")).agg(F.sum(F.when(later, F.col("c")).otherwise(0)).alias("c"))
    w = Window.partitionBy("k").orderBy(F.col("ts").asc_nulls_first())
    total = F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, 0))
    zero, none = F.lit(0).cast("long"), F.lit(None).cast("long")
    enter = F.when(F.row_number().over(w) == 1, F.struct(F.col("t0").alias("ts"), none.alias("before"), zero.alias("after")))
    ship = F.when(F.col("ts").isNotNull() & (F.col("c") != 0), F.struct(F.col("ts").alias("ts"), (F.col("total") - F.col("c")).alias("before"), F.col("total").alias("after")))
    rows = days.withColumns({"total": total, "enter": enter}).select(F.col("k").alias("entry"), F.explode(F.array("enter", ship)).alias("m")).where("m is not null")
    kind = F.when(F.col("m.before").isNull(), "insert").otherwise("update")
    return rows.select("entry", "m.ts", zero.alias("seq"), kind.alias("kind"), "m.before", "m.after")


def customer_status(spark, d) -> DataFrame:
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_orderstatus", micros("o_orderdate").alias("us"))
    return changelog.from_history(o, "o_custkey", "us", "o_orderstatus", "o_orderkey")


def conversation_role(spark, d) -> DataFrame:
    return changelog.from_history(table(spark, d, "conversations").select("conv_id", F.col("turn").cast("long").alias("turn"), "role"), "conv_id", "turn", "role")


def order_limits(spark, d) -> DataFrame:
    """(entry, k, b): how many orders a customer has, and the whole days from the first to the last."""
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("entry"), F.to_date("o_orderdate").alias("day"))
    return o.groupBy("entry").agg(F.count("*").alias("k"), F.datediff(F.max("day"), F.min("day")).cast("long").alias("b"))


def order_windows(spark, d) -> DataFrame:
    """(w, p, entries, g): windows as long as a customer's history, moved by the mean time between orders, in whole days, how
    many customers have them, and their common divisor."""
    some = order_limits(spark, d).where("k >= 2 and b >= 1")
    pairs = some.groupBy(F.col("b").alias("w"), F.greatest(F.lit(1).cast("long"), F.call_function("div", F.col("b"), F.col("k") - 1)).alias("p")).agg(F.count("*").alias("entries"))
    return pairs.withColumn("g", gcd_int(F.col("w"), F.col("p")))


# The same as SQL: a CTE named cl.
def _lag(table_sql: str, entry: str, ts: str, seq: str, value: str, name: str = "cl") -> str:
    return f"""{name} as (select entry, ts, seq, case when before is null then 'insert' when after is null then 'delete' else 'update' end as kind, before, after from (
      select {entry} as entry, {ts} as ts, cast({seq} as bigint) as seq, {value} as after, lag({value}) over (partition by {entry} order by {ts}, {seq}) as before from {table_sql})
      where before is distinct from after)"""


CL_STATE = _lag("events", "user_id", "epoch_us(ts)", "event_id", "event_type")
CL_VALUE = _lag("events", "user_id", "epoch_us(ts)", "event_id", "cast(round(value * 100) as bigint)")
CL_STATUS = _lag("orders", "o_custkey", "epoch_us(o_orderdate)", "o_orderkey", "o_orderstatus")
CL_ROLE = _lag("conversations", "conv_id", "cast(turn as bigint)", "0", "role")
CL_SHIP = (
    """ship0 as (select o_orderkey as k, epoch_us(o_orderdate) as ts, cast(0 as bigint) as c from orders union all
      select l_orderkey, epoch_us(l_shipdate), cast(sum(cast(round(l_extendedprice * 100) as bigint)) as bigint) from lineitem join orders on l_orderkey = o_orderkey
      where l_shipdate > o_orderdate group by 1, 2),
    ship as (select k, ts, cast(sum(c) over (partition by k order by ts) as bigint) as cents from ship0),
    """
    + _lag("ship", "k", "ts", "0", "cents")
)

LIMITS = "lim as (select o_custkey as entry, count(*) as k, cast(max(o_orderdate)::date - min(o_orderdate)::date as bigint) as b from orders group by 1)"


def sql_idx(width: int, start: int = T0, ts: str = "ts") -> str:
    """ceil((ts - start) / width) - 1"""
    a = f"({ts} - {start})"
    return f"(({a} + ((-{a}) % {width} + {width}) % {width}) // {width} - 1)"


def sql_u(release: str, *parts: str, salt: str = "") -> str:
    """The keyed uniform of functions.noise."""
    text = ", ".join(["'test'", f"'{release}'", *[f"cast({p} as varchar)" for p in parts], f"'{salt}'"])
    return f"(((('0x' || substr(md5(concat_ws('|', {text})), 1, 13))::bigint) + 0.5) / 4503599627370496.0)"


def sql_laplace(scale, release: str, *parts: str) -> str:
    u = f"({sql_u(release, *parts)} - 0.5)"
    return f"(-({scale}) * sign({u}) * ln(1 - 2 * abs({u})))"
