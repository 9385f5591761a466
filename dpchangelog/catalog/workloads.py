"""Settings of the reference re-expressed on the tables: logical clocks, hybrid limits, batch overwrites, surveys by group."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import sql as sql_functions
from ..functions.intervals import DAY, IntervalGrid, micros
from ..functions.noise import Noise, laplace
from ..operators import changelog, hierarchy, linear, release, responses, sliding
from ..plans import accounting as A
from ..plans.planner import prefix_nodes
from ..sources.tables import table
from .base import *
from .base import CL_ROLE, CL_STATE, LIMITS, _lag, sql_idx, sql_laplace, sql_u
from .local_rr import sql_code, sql_respond
from .log import HYBRID, hybrid, overwrite_batch_1d
from .releases import ERROR, GRID, HOURLY, S14, SQL_ERROR, daily_sql, rounded, window_sql

TURNS = IntervalGrid.regular(-1, 2, 4)


@query(f"""with {CL_ROLE}, pm as (select {sql_idx(2, -1)} as idx, after as symbol, 1 as n from cl where after is not null union all select {sql_idx(2, -1)}, before, -1 from cl where before is not null),
s as (select idx, symbol, cast(sum(n) as bigint) as exact from pm group by 1, 2), a as (select unnest({ROLES!r}) as symbol)
select cast(i as bigint) as idx, a.symbol, round(coalesce(exact, 0) + {sql_laplace(4.0, 'cr', chr(39) + '0' + chr(39), 'i', 'a.symbol')}, 6) as noisy, 0.5::double as eps, 32.0::double as sigma2 from range(4) r(i), a left join s on s.idx = i and s.symbol = a.symbol""")
def conversation_roles_by_turn(spark, d):
    """A logical clock: intervals of two turns."""
    symbols = spark.createDataFrame([(s,) for s in ROLES], "symbol string")
    return rounded(release.histogram(conversation_role(spark, d), TURNS, symbols, Noise("laplace", 0.5), key("cr")))


#: Rides: 10 folds. Passes: spans of 10 days on a daily grid. The release spends the larger.
HYBRID_FOLDS = max(A.folds_disjoint_k(10), A.folds_disjoint_b_regular(10 * DAY, DAY))
#: The same by hand, for SQL: 10 rides, or 10 days and one more interval.
_FOLDS = "greatest(10, ceil(10 * 1.0) + 1)"


@query(f"with {CL_STATE}, {HYBRID}, {daily_sql(SQL_ERROR, 'hy')} select idx, round(exact + {sql_laplace(_FOLDS, 'hy', chr(39) + '0' + chr(39), 'idx')}, 6) as noisy, round(1.0 / {_FOLDS}, 9) as eps, round(2.0 * {_FOLDS} * {_FOLDS}, 6) as sigma2 from b")
def hybrid_release_daily(spark, d):
    """Two kinds of tickets under one release at a total of 1."""
    out = release.disjoint(hybrid(spark, d), DAILY, ERROR, Noise("laplace", 1.0 / HYBRID_FOLDS), key("hy"))
    return rounded(out).withColumns({"eps": F.round("eps", 9), "sigma2": F.round("sigma2", 6)})


@query("""with v as (select vec_id // 100 as idx, embedding::double[] as e, greatest(1.0, sqrt(list_sum([x * x for x in embedding::double[]]))) as len from embeddings),
u as (select idx, unnest(range(64)) as coord, unnest(e) / len as x from v), s as (select cast(idx as bigint) as idx, cast(coord as integer) as coord, sum(x) as x from u group by 1, 2)
select idx, coord, round(x + """ + f"sqrt(-2 * ln({sql_u('ve', 'idx', 'coord')})) * cos(2 * pi() * {sql_u('ve', 'idx', 'coord', salt='b')})" + ", 5) as noisy from s")
def vector_sum_noisy(spark, d):
    """Sums of clipped vectors with Gaussian noise at rho = 1/2: the L2 sensitivity is the clip."""
    cl = changelog.from_inserts(table(spark, d, "embeddings"), "vec_id", "vec_id", "embedding").withColumn("idx", F.floor(F.col("ts") / 100).cast("long"))
    n = Noise("gaussian", rho=0.5)
    out = linear.vector_change(cl, 64, 1.0)
    return out.select("idx", "coord", (F.round(F.col("exact") + n.draw(1, 1, key("ve"), F.col("idx"), F.col("coord")), 5) + 0.0).alias("noisy"))


@query("""with src as (select user_id, ts, event_id, cast(round(value * 100) as bigint) as v, epoch_us(ts) as us from events),
f as (select user_id, us as t, cast(0 as bigint) as o, event_id, v from src union all select user_id, ((us // 86400000000) + 1) * 86400000000, 1, event_id, (v + 50) // 100 * 100 from src),
""" + _lag("f", "event_id", "t", "o", "v") + f", {daily_sql('coalesce(after, 0) - coalesce(before, 0)')} select idx, round(exact + {sql_laplace(50_000 / 0.5, 'ow', chr(39) + '0' + chr(39), 'idx')}, 5) as noisy from b")
def overwrite_release_daily(spark, d):
    """A fast layer overwritten at the end of the day: all changes of an entry lie within a day, so it touches two intervals."""
    cl = overwrite_batch_1d(spark, d).withColumns({c: F.col(c).cast("long") for c in ("before", "after")})
    folds = A.folds_disjoint_b_regular(DAY, DAY)
    out = release.disjoint(cl, DAILY, linear.clipped_sum(0, 50_000), Noise("laplace", 1.0 / folds), key("ow"))
    return out.select("idx", (F.round("noisy", 5) + 0.0).alias("noisy"))


PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
CL_PRIORITY = _lag("orders", "o_custkey", "epoch_us(o_orderdate)", "o_orderkey", "o_orderpriority")
YEARLY = IntervalGrid.regular(T1995 - 1, 365 * DAY, 7)


@query(f"""with {CL_PRIORITY}, net as (select entry, {sql_idx(365 * DAY, T1995 - 1)} as idx, arg_min(coalesce(before, '~'), (ts, seq)) as b, arg_max(after, (ts, seq)) as a from cl group by 1, 2),
d as (select c_custkey as entry, cast(i as bigint) as idx, if(net.a is distinct from nullif(net.b, '~'), {sql_code("nullif(net.b, '~')", PRIORITIES)}, null) as b, if(net.a is distinct from nullif(net.b, '~'), {sql_code('net.a', PRIORITIES)}, null) as a from customer cross join range(7) r(i) left join net on net.entry = c_custkey and net.idx = i),
o as (select idx, cast({sql_respond('(coalesce(b + 1, 0) * 6 + coalesce(a + 1, 0))', 36, 2.0, 'rp', 'entry', 'idx')} as integer) as out_code from d) select idx, out_code, count(*) as n from o group by 1, 2""")
def rr_continual_priority(spark, d):
    """Customers report how their last order's priority changed over each year; customers without orders report too."""
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_orderpriority", micros("o_orderdate").alias("us"))
    cl = changelog.from_history(o, "o_custkey", "us", "o_orderpriority", "o_orderkey")
    entries = table(spark, d, "customer").select(F.col("c_custkey").alias("entry"))
    return responses.mutation_counts(cl, entries, YEARLY, PRIORITIES, 2.0, key("rp"))


LABEL_PAIRS = ["00", "01", "10", "11"]


@query(f"with o as (select {sql_respond(sql_code('cast(quality as varchar) || cast(toxic as varchar)', LABEL_PAIRS), 4, 1.0, 'rq', 'doc_id')} as out_code from labels), c as (select cast(i as integer) as out_code, count(o.out_code) as n from range(4) r(i) left join o on o.out_code = i group by 1) select * from c")
def rr_label_pairs(spark, d):
    lab = table(spark, d, "labels").select("doc_id", F.concat(F.col("quality").cast("string"), F.col("toxic").cast("string")).alias("v"))
    return responses.static_counts(lab, "doc_id", "v", LABEL_PAIRS, 1.0, key("rq"))


@query(f"""with {LIMITS}, s as (select c_mktsegment as segment, max(k) as k, max(b) as b from lim join customer on c_custkey = entry group by 1)
select 'local' as model, segment, c as "constraint", cast(bound as bigint) as bound, r as release, cast(2 * f as bigint) as folds from (
  select segment, 'k' as c, k as bound, 'disjoint' as r, k as f from s union all select segment, 'B', b, 'disjoint', ceil(b / 1.0) + 1 from s union all select segment, 'k', k, 'tree h=3', 3 * k from s
  union all select segment, 'B', b, 'tree h=3 c=2', sum(ceil(b / pow(2, j)) + 1) from s, range(3) t(j) group by segment, b union all select segment, 'k', k, 'sliding 14/1', k * ceil(14 / 1.0) from s union all select segment, 'B', b, 'sliding 14/1', ceil((b + 14) / 1.0) from s)""")
def local_folds_table(spark, d):
    """What a local release by segment has to count, with the limits that the segment's customers keep: k orders, or B days."""
    k, b, f = F.col("k"), F.col("b"), A.local_folds
    rows = [("k", k, "disjoint", f(A.folds_disjoint_k(k))), ("B", b, "disjoint", f(A.folds_disjoint_b_regular(b, 1))), ("k", k, "tree h=3", f(A.folds_tree_k(3, k))), ("B", b, "tree h=3 c=2", f(A.folds_tree_b(3, 2, b, 1))), ("k", k, "sliding 14/1", f(A.folds_sliding_k(k, 14, 1))), ("B", b, "sliding 14/1", f(A.folds_sliding_b(b, 14, 1)))]
    each = F.array(*[F.struct(F.lit(c).alias("constraint"), x.cast("long").alias("bound"), F.lit(r).alias("release"), n.cast("long").alias("folds")) for c, x, r, n in rows])
    customers = table(spark, d, "customer").select(F.col("c_custkey").alias("entry"), F.col("c_mktsegment").alias("segment"))
    most = order_limits(spark, d).join(customers, "entry").groupBy("segment").agg(F.max("k").alias("k"), F.max("b").alias("b"))
    return most.select(F.lit("local").alias("model"), "segment", F.explode(each).alias("r")).select("model", "segment", "r.*")


@query(f"""with {CL_STATE}, s as (select {sql_idx(3_600_000_000)} + 1 as r, count(*) as n from cl where {sql_idx(3_600_000_000)} between 0 and 719 group by 1),
c as (select cast(c as integer) as c, cast((select min(j) from range(1, 12) t(j) where pow(c, j) >= 720) as integer) as h from range(2, 65) a(c)),
k as (select c, h, r, n, r - (c - 1) * sum(if(j < h, r // cast(pow(c, j) as bigint), 0)) as nodes from c, s, range(1, 11) x(j) group by 1, 2, 3, 4)
select c, h, cast(max(nodes) as integer) as nodes, cast(h * h * max(nodes) as double) as cost, cast(sum(n) as bigint) as mutations, round(h * h * sum(nodes * n) / sum(n), 6) as mean_cost from k group by 1, 2""")
def base_fanout_sweep(spark, d):
    """Fan-outs of a tree over 720 hours: height, most nodes of a prefix that ends in an hour with mutations, the variance of that
    at one total budget, and the mean variance of the prefixes that end with each mutation."""
    hours = HOURLY.assign(event_state(spark, d)).groupBy((F.col("idx") + 1).alias("r")).agg(F.count("*").alias("n"))
    trees = [(c, A.height_for(720, c)) for c in range(2, 65)]
    sweep = F.array(*[F.struct(F.lit(c).alias("c"), F.lit(h).alias("h"), prefix_nodes(F.col("r"), c, h).alias("nodes")) for c, h in trees])
    each = hours.select("r", "n", F.explode(sweep).alias("t")).select("n", "t.*").groupBy("c", "h")
    sums = each.agg(F.max("nodes").cast("int").alias("nodes"), F.sum("n").alias("mutations"), F.sum(F.col("nodes") * F.col("n")).alias("s"))
    square = F.col("h") * F.col("h")
    return sums.select("c", "h", "nodes", (square * F.col("nodes")).cast("double").alias("cost"), "mutations", F.round(square * F.col("s") / F.col("mutations"), 6).alias("mean_cost"))


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx, round(exact + {sql_laplace(2.0, 'sq', 'idx')}, 6) as noisy from b")
def sql_surface_noise(spark, d):
    """Noise and grids from SQL alone."""
    sql_functions.register(spark)
    event_state(spark, d).createOrReplaceTempView("event_state_log")
    return spark.sql(f"""with s as (select interval_idx(ts, {T0}, {DAY}) as idx, sum(if(after <=> 'error', 1, 0) - if(before <=> 'error', 1, 0)) as x from event_state_log group by 1)
      select g.idx, round(coalesce(x, 0) + lap_noise(concat_ws('|', 'test', 'sq', g.idx, ''), 2.0D), 6) + 0.0D as noisy from interval_grid({T0}, {DAY}, 30) g left join s on g.idx = s.idx""")


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)}, n as (select idx, 15 + exact + {sql_laplace(2.0, 'pp', chr(39) + '0' + chr(39), 'idx')} as x from b) select idx, round(greatest(0, x), 6) as estimate from n")
def post_processed(spark, d):
    """Clipping at zero after the release costs no privacy, and no longer has zero bias."""
    out = release.disjoint(event_state(spark, d), DAILY, ERROR, Noise("laplace", 0.5), key("pp"))
    return out.select("idx", (F.round(F.greatest(F.lit(0.0), F.col("noisy") + 15), 6) + 0.0).alias("estimate"))


# Hybrid limits of trees and sliding windows: the release spends the larger of what either kind of ticket can touch.
TREE_H = 4
HYBRID_TREE = max(A.folds_tree_k(TREE_H, 10), A.folds_tree_b(TREE_H, 2, 10, 1))
HYBRID_SLIDING = max(A.folds_sliding_k(10, 14, 1), A.folds_sliding_b(10, 14, 1))
_TREE_FOLDS = "(select greatest(4 * 10, sum(ceil(10 / pow(2, j)) + 1)) from range(4) f(j))"
_SLIDING_FOLDS = "greatest(10 * ceil(14 * 1.0), ceil((10 + 14) * 1.0))"


@query(f"""with {CL_STATE}, {HYBRID}, s as (select {sql_idx(DAY)} as i, sum({SQL_ERROR}) as x from hy group by 1), f as (select {_TREE_FOLDS} as k), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact from range(30) r(i) cross join range(4) l(j) left join s on s.i = r.i group by 1, 2)
select layer, idx, round(exact + {sql_laplace('k', 'hyt', 'layer', 'idx')}, 6) as noisy, round(1.0 / k, 9) as eps, round(2.0 * k * k, 6) as sigma2 from t, f""")
def hybrid_tree_daily(spark, d):
    out = hierarchy.hierarchy(hybrid(spark, d), DAILY, 2, TREE_H, ERROR, Noise("laplace", 1.0 / HYBRID_TREE), key("hyt"))
    return rounded(out).withColumns({"eps": F.round("eps", 9), "sigma2": F.round("sigma2", 6)})


@query(f"with {CL_STATE}, {HYBRID}, {window_sql(S14).replace('join cl', 'join hy')}, f as (select {_SLIDING_FOLDS} as k) select idx, round(exact + {sql_laplace('k', 'hys', chr(39) + '0' + chr(39), 'idx')}, 6) as noisy, round(1.0 / k, 9) as eps, round(2.0 * k * k, 6) as sigma2 from w, f")
def hybrid_sliding_windows(spark, d):
    out = sliding.direct(hybrid(spark, d), S14, ERROR, Noise("laplace", 1.0 / HYBRID_SLIDING), key("hys"))
    return rounded(out).withColumns({"eps": F.round("eps", 9), "sigma2": F.round("sigma2", 6)})


@query(f"""with {CL_PRIORITY}, net as (select entry, {sql_idx(365 * DAY, T1995 - 1)} as idx, arg_min(coalesce(before, '~'), (ts, seq)) as b, arg_max(after, (ts, seq)) as a from cl group by 1, 2),
d as (select c_custkey as entry, cast(i as bigint) as idx, if(net.a is distinct from nullif(net.b, '~'), {sql_code("nullif(net.b, '~')", PRIORITIES)}, null) as b, if(net.a is distinct from nullif(net.b, '~'), {sql_code('net.a', PRIORITIES)}, null) as a from customer cross join range(7) r(i) left join net on net.entry = c_custkey and net.idx = i),
o as (select idx, cast({sql_respond('(coalesce(b + 1, 0) * 6 + coalesce(a + 1, 0))', 36, 2.0, 'rp', 'entry', 'idx')} as integer) as out_code from d), c as (select idx, out_code, count(*) as n from o group by 1, 2), sy as (select unnest({PRIORITIES!r}) as symbol, unnest(range(1, 6)) as code),
e as (select idx, symbol, sum(if(out_code % 6 = code, n, 0) - if(out_code // 6 = code, n, 0)) / ((exp(2.0) - 1) / (35 + exp(2.0))) as x from c, sy group by 1, 2) select idx, symbol, round(sum(x) over (partition by symbol order by idx), 6) as estimate from e""")
def rr_priority_histogram(spark, d):
    """How many customers' last order has each priority, after every year, as running sums of estimated changes."""
    changes = responses.estimate_change(rr_continual_priority(spark, d), PRIORITIES, 2.0)
    return responses.continual_histogram(changes).withColumn("estimate", F.round("estimate", 6) + 0.0)
