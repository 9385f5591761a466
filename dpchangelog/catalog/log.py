"""Changelogs and constraints."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.intervals import DAY, IntervalGrid, micros
from ..operators import changelog, constraints
from ..sources.tables import table
from .base import *
from .base import CL_ROLE, CL_SHIP, CL_STATE, CL_STATUS, CL_VALUE, _lag

T_JAN15, T_FEB = T0 + 14 * DAY, T0 + 31 * DAY
T98, T99 = T1995 + 1096 * DAY, T1995 + 1461 * DAY


#: Values as text, as a column of whole numbers and nulls isn't one type to every reader.
AS_TEXT = " select entry, ts, seq, kind, cast(before as varchar) as before, cast(after as varchar) as after from cl"


def as_text(cl):
    return cl.withColumns({c: F.col(c).cast("string") for c in ("before", "after")})


@query(f"with {CL_STATE} select * from cl")
def changelog_event_state(spark, d):
    return event_state(spark, d)


@query(f"with {CL_VALUE} {AS_TEXT}")
def changelog_value_state(spark, d):
    return as_text(event_value(spark, d))


@query(f"with {CL_SHIP} {AS_TEXT}")
def changelog_order_ship(spark, d):
    return as_text(order_ship(spark, d))


@query(f"with {CL_STATUS} select * from cl")
def changelog_customer_status(spark, d):
    return customer_status(spark, d)


@query(f"with {CL_ROLE} select * from cl")
def changelog_conversation(spark, d):
    return conversation_role(spark, d)


@query("select doc_id as entry, doc_id as ts, cast(0 as bigint) as seq, case when source is null then 'delete' else 'insert' end as kind, cast(null as varchar) as before, source as after from documents")
def changelog_insert_only(spark, d):
    out = changelog.from_inserts(table(spark, d, "documents").select("doc_id", "source"), "doc_id", "doc_id", "source")
    return out


@query(f"""with {CL_STATE}, last as (select entry, max(ts) as ts from cl group by entry)
select * from cl union all select c.entry, c.ts + {7 * DAY}, c.seq + 1, 'delete', c.after, null from cl c join last l on c.entry = l.entry and c.ts = l.ts""")
def changelog_with_deletes(spark, d):
    return changelog.with_deletes(event_state(spark, d), ttl=7 * DAY)


@query(f"with {CL_STATE} select * from cl")
def changelog_new_value_to_change(spark, d):
    return changelog.to_value_change(changelog.to_new_value(event_state(spark, d)))


@query(f"""with src as (select user_id, ts, event_id, case when event_type <> 'error' then event_type end as v from events), {_lag("src", "user_id", "epoch_us(ts)", "event_id", "v")} select * from cl""")
def changelog_terminal_state(spark, d):
    return changelog.with_deletes(event_state(spark, d), terminal_values=["error"])


@query(f"with {CL_STATE} select entry, value from (select entry, arg_max(after, (ts, seq)) as value from cl where ts <= {T_JAN15} group by entry) where value is not null")
def snapshot_at_time(spark, d):
    return changelog.snapshot_at(event_state(spark, d), T_JAN15)


@query(f"""with {CL_STATE}, times as (select cast({T0} + i * {5 * DAY} as bigint) as t from range(1, 6) r(i)), e as (select distinct entry from cl)
select e.entry, t.t, (select arg_max(c.after, (c.ts, c.seq)) from cl c where c.entry = e.entry and c.ts <= t.t) as value from e, times t""")
def snapshot_asof_many(spark, d):
    grid = IntervalGrid.regular(T0, 5 * DAY, 5)
    out = changelog.states_at(event_state(spark, d), grid)
    return out.select("entry", (F.lit(grid.start) + (F.col("idx") + 1) * grid.width).alias("t"), "value")


def _snap(t):
    return f"(select entry as k, value as v from (select entry, arg_max(after, (ts, seq)) as value from cl where ts <= {t} group by entry) where value is not null)"


@query(f"""with {CL_STATUS}, a as {_snap(T98)}, b as {_snap(T99)}
select coalesce(a.k, b.k) as entry, cast({T99} as bigint) as ts, cast(0 as bigint) as seq, case when a.v is null then 'insert' when b.v is null then 'delete' else 'update' end as kind, a.v as before, b.v as after
from a full join b on a.k = b.k where a.v is distinct from b.v""")
def snapshot_diff_full_outer(spark, d):
    cl = customer_status(spark, d)
    return changelog.from_snapshots(changelog.snapshot_at(cl, T98), changelog.snapshot_at(cl, T99), "entry", "value", T99)


@query(f"""with {CL_STATUS}, a as {_snap(T98)}, b as {_snap(T99)}
select k as entry, v as value, 1 as sign from (select * from b except all select * from a) union all select k, v, -1 from (select * from a except all select * from b)""")
def snapshot_diff_setops(spark, d):
    cl = customer_status(spark, d)
    return changelog.snapshot_diff(changelog.snapshot_at(cl, T98), changelog.snapshot_at(cl, T99))


@query(f"""with {CL_STATUS}, a as {_snap(T98)}, b as {_snap(T99)}
select k as entry, cast({T98} as bigint) as ts, cast(0 as bigint) as seq, 'insert' as kind, cast(null as varchar) as before, v as after from a union all
select coalesce(a.k, b.k), {T99}, 0, case when a.v is null then 'insert' when b.v is null then 'delete' else 'update' end, a.v, b.v from a full join b on a.k = b.k where a.v is distinct from b.v""")
def changelog_snapshot_series(spark, d):
    cl = customer_status(spark, d)
    return changelog.from_snapshot_series([(T98, changelog.snapshot_at(cl, T98)), (T99, changelog.snapshot_at(cl, T99))], "entry", "value")


NET = f"net as (select entry, idx, before, after from (select entry, {sql_idx(DAY)} as idx, arg_min(before, (ts, seq)) as before, arg_max(after, (ts, seq)) as after from (select entry, ts, seq, coalesce(before, '~') as before, coalesce(after, '~') as after from cl) group by 1, 2) where before <> after and idx between 0 and 29)"


@query(f"with {CL_STATE}, {NET} select entry, idx, nullif(before, '~') as before, nullif(after, '~') as after from net")
def net_change_daily(spark, d):
    return changelog.net_change(DAILY.assign(event_state(spark, d)))


@query(f"""with {CL_STATE}, broken as (select * from cl where seq % 7 <> 0) select entry, ts, seq, before, expected from (
select *, lag(after) over (partition by entry order by ts, seq) as expected from broken) where before is distinct from expected""")
def chain_violations(spark, d):
    """A changelog with mutations missing."""
    return changelog.chain_violations(event_state(spark, d).where("seq % 7 <> 0"))


@query(f"with {CL_STATE} select * from cl where entry <> 7")
def neighbour_changelog(spark, d):
    return changelog.without_entry(event_state(spark, d), 7)


@query("""with src as (select user_id, ts, event_id, cast(round(value * 100) as bigint) as v, epoch_us(ts) as us from events),
f as (select user_id, us as t, cast(0 as bigint) as o, event_id, v from src union all select user_id, ((us // 86400000000) + 1) * 86400000000, 1, event_id, (v + 50) // 100 * 100 from src),
""" + _lag("f", "event_id", "t", "o", "v") + AS_TEXT)
def overwrite_batch_1d(spark, d):
    """Each event enters with its value and is overwritten by a corrected one at the end of its day."""
    e = events(spark, d).select("event_id", "us", F.round(F.col("value") * 100).cast("long").alias("v"))
    fast = e.select("event_id", F.col("us").alias("t"), F.lit(0).cast("long").alias("o"), "v")
    end = (F.floor(F.col("us") / DAY).cast("long") + 1) * DAY
    fixed = e.select("event_id", end.alias("t"), F.lit(1).cast("long").alias("o"), (F.floor((F.col("v") + 50) / 100) * 100).cast("long").alias("v"))
    return as_text(changelog.from_history(fast.unionByName(fixed), "event_id", "t", "v", "o"))


# Constraints.
@query(f"with {CL_STATE} select entry, count(*) as mutations from cl group by entry")
def mutation_counts(spark, d):
    return constraints.counts(event_state(spark, d))


@query(f"with {CL_STATE} select entry, max(ts) - min(ts) as lifespan from cl group by entry")
def lifespan_per_entry(spark, d):
    return constraints.lifespans(event_state(spark, d))


@query(f"with {CL_STATE} select entry, count(*) as observed, cast(50 as bigint) as \"limit\" from cl group by entry having count(*) > 50")
def violators_k(spark, d):
    return constraints.violators(event_state(spark, d), k=50)


@query(f"with {CL_STATE} select entry, max(ts) - min(ts) as observed, cast({28 * DAY} as bigint) as \"limit\" from cl group by entry having max(ts) - min(ts) > {28 * DAY}")
def violators_b(spark, d):
    return constraints.violators(event_state(spark, d), b=28 * DAY)


@query(f"with {CL_STATE} select * exclude n from (select *, row_number() over (partition by entry order by ts, seq) as n from cl) where n <= 8")
def enforce_k(spark, d):
    return constraints.enforce_k(event_state(spark, d), 8)


@query(f"with {CL_STATE} select * exclude f from (select *, min(ts) over (partition by entry) as f from cl) where ts <= f + {7 * DAY}")
def enforce_b(spark, d):
    return constraints.enforce_b(event_state(spark, d), 7 * DAY)


HYBRID = f"hy as (select * exclude (n, f) from (select *, if(entry % 2 = 0, 'rides', 'pass') as constraint_id, row_number() over (partition by entry order by ts, seq) as n, min(ts) over (partition by entry) as f from cl) where (constraint_id = 'rides' and n <= 10) or (constraint_id = 'pass' and ts <= f + {10 * DAY}))"


def hybrid(spark, d):
    cl = event_state(spark, d).withColumn("constraint_id", F.when(F.col("entry") % 2 == 0, "rides").otherwise("pass"))
    return constraints.enforce_hybrid(cl, {"rides": {"k": 10}, "pass": {"b": 10 * DAY}})


@query(f"with {CL_STATE}, {HYBRID} select * from hy")
def enforce_hybrid(spark, d):
    return hybrid(spark, d)


@query(f"with {CL_ROLE} select before, after, count(*) as n from cl group by 1, 2")
def transition_edges(spark, d):
    return constraints.transitions(conversation_role(spark, d))


#: Edges of three graphs; the longest path over strongly connected components, all by recursive closure.
GRAPH = f"""with recursive cl1 as (with {CL_ROLE} select 'role' as g, coalesce(before, '~') as a, coalesce(after, '~') as b from cl), cl2 as (with {CL_STATE} select 'event_type' as g, coalesce(before, '~') as a, coalesce(after, '~') as b from cl),
cl3 as (with src as (select o_custkey, o_orderdate, o_orderkey, least(2, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey)) as v from orders), {_lag("src", "o_custkey", "epoch_us(o_orderdate)", "o_orderkey", "v")} select 'counter' as g, coalesce(before::varchar, '~') as a, coalesce(after::varchar, '~') as b from cl),
e as (select distinct * from (select * from cl1 union all select * from cl2 union all select * from cl3)), v as (select g, a as x from e union select g, b from e),
reach as (select g, x as a, x as b from v union select r.g, r.a, e.b from reach r join e on e.g = r.g and e.a = r.b),
comp as (select r.g, r.a as x, min(r.b) as c from reach r join reach s on s.g = r.g and s.a = r.b and s.b = r.a group by 1, 2),
dag as (select distinct e.g, p.c as a, q.c as b from e join comp p on p.g = e.g and p.x = e.a join comp q on q.g = e.g and q.x = e.b where p.c <> q.c),
walk as (select g, c as at, 0 as n from comp where x = '~' union select w.g, d.b, w.n + 1 from walk w join dag d on d.g = w.g and d.a = w.at)
select g as graph, cast(max(n) as bigint) as k from walk group by 1"""
#: Pairs of states that one changelog's graph may have, at most: states are public and few, or grouped before (M22).
MOST_EDGES = 100_000


def _edges(cl):
    rows = constraints.transitions(cl).select("before", "after").limit(MOST_EDGES + 1).collect()
    if len(rows) > MOST_EDGES:
        raise ValueError("too many states for a graph; group them first")
    return [(r.before, r.after) for r in rows]


@query(GRAPH)
def state_graph_bound(spark, d):
    """(graph, k): longest path over components, for three graphs."""
    rows = [(name, constraints.mutation_bound(_edges(cl))[0]) for name, cl in (("role", conversation_role(spark, d)), ("event_type", event_state(spark, d)), ("counter", counter_bucket_changelog(spark, d)))]
    return spark.createDataFrame(rows, "graph string, k long")


@query("with src as (select conv_id, turn, if(role = 'system', 'system', 'assistant') as v from conversations), " + _lag("src", "conv_id", "cast(turn as bigint)", "0", "v") + " select * from cl")
def composite_state_changelog(spark, d):
    cl = conversation_role(spark, d)
    return constraints.composite_states(cl, constraints.mutation_bound(_edges(cl))[1])


@query("""with src as (select o_custkey, o_orderdate, o_orderkey, least(2, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey)) as v from orders), """ + _lag("src", "o_custkey", "epoch_us(o_orderdate)", "o_orderkey", "v") + AS_TEXT)
def counter_bucket_changelog(spark, d):
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", micros("o_orderdate").alias("us"))
    n = F.row_number().over(Window.partitionBy("o_custkey").orderBy("us", "o_orderkey"))
    return as_text(changelog.from_history(o.withColumn("v", constraints.bucketed(n, [1, 2])), "o_custkey", "us", "v", "o_orderkey"))
