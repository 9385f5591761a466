"""Linear changes, disjoint, hierarchical and sliding releases."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.intervals import DAY, HOUR, IntervalGrid, micros
from ..functions.noise import Noise, laplace_variance, sigma_classic
from ..operators import changelog, hierarchy, linear, release, sliding
from ..plans import accounting as A
from ..plans.accounting import height_for
from ..sources.tables import table
from .base import *
from .base import CL_STATE, CL_STATUS, CL_VALUE, sql_idx, sql_laplace, sql_u

ERROR = linear.count_if(lambda v: v == "error")
CENTS = linear.clipped_sum(0, 30_000)
SQL_ERROR = "(if(after = 'error', 1, 0) - if(before = 'error', 1, 0))"
GRID = "g as (select cast(i as bigint) as idx from range(30) r(i))"


def daily_sql(change: str, cl: str = "cl", first: str = "idx") -> str:
    """b as (idx, exact) over the daily grid, dense."""
    idx = sql_idx(DAY)
    return f"s as (select {idx if first == 'idx' else f'greatest(0, {idx})'} as idx, cast(sum({change}) as bigint) as exact from {cl} group by 1), {GRID}, b as (select g.idx, coalesce(s.exact, 0) as exact from g left join s on g.idx = s.idx)"


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select * from b")
def change_count_daily(spark, d):
    return release.dense(DAILY, linear.change(DAILY.assign(event_state(spark, d)), ERROR))


def _month_cl(spark, d):
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", micros("o_orderdate").alias("us"), F.round(F.col("o_totalprice") * 100).cast("long").alias("c"))
    return changelog.from_history(o, "o_custkey", "us", "c", "o_orderkey")


CL_PRICE = None
from .base import _lag  # noqa: E402

CL_PRICE = _lag("orders", "o_custkey", "epoch_us(o_orderdate)", "o_orderkey", "cast(round(o_totalprice * 100) as bigint)")
ENDS = "e as (select epoch_us(make_timestamp(1995 + i // 12, i % 12 + 1, 1, 0, 0, 0)) as t, i from range(81) r(i)), g as (select cast(a.i as bigint) as idx, a.t as lo, b.t as hi from e a join e b on b.i = a.i + 1)"
HIGH = 50_000_000
CLIP = lambda c: f"greatest(0, least({HIGH}, coalesce({c}, 0)))"


def _monthly_sql(f):
    return f"with {CL_PRICE}, {ENDS} select g.idx, cast(coalesce(sum({f('after')} - {f('before')}), 0) as {{}}) as exact from g left join cl on cl.ts > g.lo and cl.ts <= g.hi group by g.idx"


@query(_monthly_sql(CLIP).format("bigint"))
def change_sum_monthly(spark, d):
    grid = IntervalGrid.explicit(month_ends())
    return release.dense(grid, linear.change(grid.assign(_month_cl(spark, d)), linear.clipped_sum(0, HIGH)))


@query(_monthly_sql(lambda c: f"cast({CLIP(c)} // 100 as bigint) * ({CLIP(c)} // 100)").format("bigint"))
def change_second_moment_monthly(spark, d):
    """In whole currency units, so that squares stay exact."""
    grid, q = IntervalGrid.explicit(month_ends()), linear.custom(lambda v: F.call_function("div", F.greatest(F.lit(0), F.least(F.lit(HIGH), v)), F.lit(100)) * F.call_function("div", F.greatest(F.lit(0), F.least(F.lit(HIGH), v)), F.lit(100)), 0, (HIGH // 100) ** 2)
    return release.dense(grid, linear.change(grid.assign(_month_cl(spark, d)), q))


PM = f"pm as (select {sql_idx(DAY)} as idx, after as symbol, 1 as n from cl where after is not null union all select {sql_idx(DAY)}, before, -1 from cl where before is not null)"


@query(f"with {CL_STATE}, {PM} select idx, symbol, cast(sum(n) as bigint) as exact from pm where idx between 0 and 29 group by 1, 2")
def change_histogram_daily(spark, d):
    return linear.histogram_change(DAILY.assign(event_state(spark, d)))


@query("""with v as (select vec_id // 100 as idx, embedding::double[] as e, greatest(1.0, sqrt(list_sum([x * x for x in embedding::double[]]))) as len from embeddings),
u as (select idx, unnest(range(64)) as coord, unnest(e) / len as x from v) select cast(idx as bigint) as idx, cast(coord as integer) as coord, round(sum(x), 6) as exact from u group by 1, 2""")
def change_vector_embedding(spark, d):
    cl = changelog.from_inserts(table(spark, d, "embeddings"), "vec_id", "vec_id", "embedding").withColumn("idx", F.floor(F.col("ts") / 100).cast("long"))
    return linear.vector_change(cl, 64, 1.0).withColumn("exact", F.round("exact", 6))


SQL_CENTS = "least(30000, coalesce(after, 0)) - least(30000, coalesce(before, 0))"


@query(f"with {CL_VALUE}, {daily_sql(SQL_CENTS)} select * from b")
def change_clipped(spark, d):
    return release.dense(DAILY, linear.change(DAILY.assign(event_value(spark, d)), CENTS))


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx // 10 as part, cast(sum(exact) as bigint) as exact from b group by 1")
def range_additivity(spark, d):
    """Ten-day answers from daily ones."""
    return linear.combine(change_count_daily(spark, d).withColumn("part", F.floor(F.col("idx") / 10).cast("long")), "exact", ("part",))


@query(f"with {CL_STATE} select {sql_idx(DAY)} as idx, count(*) as mutations, count(distinct entry) as entries from cl where {sql_idx(DAY)} between 0 and 29 group by 1")
def mechanism_mutation_count(spark, d):
    return DAILY.assign(event_state(spark, d)).groupBy("idx").agg(F.count("*").alias("mutations"), F.count_distinct("entry").alias("entries"))


@query(f"""with {CL_VALUE}, s as (select {sql_idx(DAY)} as idx, cast(sum(if(after is null, 0, 1) - if(before is null, 0, 1)) as bigint) as n, cast(sum(coalesce(after, 0) - coalesce(before, 0)) as bigint) as total from cl group by 1)
select idx, cast(sum(n) over (order by idx) as bigint) as n, cast(sum(total) over (order by idx) as bigint) as total, round(sum(total) over (order by idx) * 1.0 / sum(n) over (order by idx), 6) as mean from s where idx between 0 and 29""")
def mean_from_parts(spark, d):
    """A mean as post-processing of a count and a sum, both aggregatable."""
    from pyspark.sql import Window

    rows, w = DAILY.assign(event_value(spark, d)), Window.orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    parts = linear.COUNT.partials(rows, ("idx",)).join(linear.SUM.partials(rows, ("idx",)), "idx")
    parts = parts.select("idx", F.sum("count").over(w).alias("n"), F.sum("sum").over(w).alias("total"))
    mean, _ = linear.mean_and_variance(F.col("n"), F.col("total"), F.col("total"))
    return parts.select("idx", "n", "total", F.round(mean, 6).alias("mean"))


# Disjoint.
@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx, cast(exact as double) as noisy, 0.0::double as eps, 0.0::double as sigma2 from b")
def disjoint_exact_regular(spark, d):
    return release.disjoint(event_state(spark, d), DAILY, ERROR, Noise("off"), key("dx"))


@query(f"with {CL_STATUS}, {ENDS}, f as (select idx, lo, hi from g) select f.idx, cast(coalesce(sum(if(after = 'F', 1, 0) - if(before = 'F', 1, 0)), 0) as double) as noisy, 0.0::double as eps, 0.0::double as sigma2 from f left join cl on cl.ts > f.lo and cl.ts <= f.hi group by f.idx")
def disjoint_exact_irregular(spark, d):
    return release.disjoint(customer_status(spark, d), IntervalGrid.explicit(month_ends()), linear.count_if(lambda v: v == "F"), Noise("off"), key("di"))


LATE = T0 + 10 * DAY


@query(f"with {CL_STATE}, s as (select greatest(0, {sql_idx(DAY, LATE)}) as idx, cast(sum({SQL_ERROR}) as bigint) as exact from cl group by 1) select cast(i as bigint) as idx, cast(coalesce(exact, 0) as double) as noisy, 0.0::double as eps, 0.0::double as sigma2 from range(20) r(i) left join s on s.idx = i")
def disjoint_initial_interval(spark, d):
    """The first interval reaches back to the beginning."""
    return release.disjoint(event_state(spark, d), IntervalGrid.regular(LATE, DAY, 20), ERROR, Noise("off"), key("d0"), from_beginning=True)


LAP = Noise("laplace", 0.5)


def noisy_sql(rel: str, scale: float, var: float, eps: float, cl: str = CL_STATE, change: str = SQL_ERROR) -> str:
    return f"with {cl}, {daily_sql(change)} select idx, round(exact + {sql_laplace(scale, rel, chr(39) + '0' + chr(39), 'idx')}, 6) as noisy, {eps}::double as eps, {var!r}::double as sigma2 from b"


def rounded(df):
    return df.withColumn("noisy", F.round("noisy", 6) + 0.0)


@query(noisy_sql("dl", 2.0, laplace_variance(2.0), 0.5))
def disjoint_noisy_laplace(spark, d):
    return rounded(release.disjoint(event_state(spark, d), DAILY, ERROR, LAP, key("dl")))


def _geo(rel, scale):
    one = lambda s: f"floor(ln({sql_u(rel, chr(39) + '0' + chr(39), 'idx', salt=s)}) / ({-1 / scale!r}))"
    return f"({one('')} - {one('b')})"


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx, cast(exact + {_geo('dg', 2.0)} as double) as noisy, 0.5::double as eps, round(2 * exp(-0.5) / pow(1 - exp(-0.5), 2), 9) as sigma2 from b")
def disjoint_noisy_geometric(spark, d):
    return rounded(release.disjoint(event_state(spark, d), DAILY, ERROR, Noise("geometric", 0.5), key("dg"))).withColumn("sigma2", F.round("sigma2", 9))


_SIGMA = "(sqrt(2 * ln(1.25 / 1e-6)) / 0.5)"


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx, round(exact + {_SIGMA} * sqrt(-2 * ln({sql_u('dn', chr(39) + '0' + chr(39), 'idx')})) * cos(2 * pi() * {sql_u('dn', chr(39) + '0' + chr(39), 'idx', salt='b')}), 6) as noisy, 0.5::double as eps, round({_SIGMA} * {_SIGMA}, 6) as sigma2 from b")
def disjoint_noisy_gaussian(spark, d):
    return rounded(release.disjoint(event_state(spark, d), DAILY, ERROR, Noise("gaussian", 0.5, 1e-6), key("dn"))).withColumn("sigma2", F.round("sigma2", 6))


@query(f"with {CL_STATE}, {GRID}, {PM}, s as (select idx, symbol, cast(sum(n) as bigint) as exact from pm group by 1, 2), a as (select unnest({EVENT_TYPES!r}) as symbol) select g.idx, a.symbol, round(coalesce(s.exact, 0) + {sql_laplace(4.0, 'hd', chr(39) + '0' + chr(39), 'g.idx', 'a.symbol')}, 6) as noisy, 0.5::double as eps, 32.0::double as sigma2 from g, a left join s on s.idx = g.idx and s.symbol = a.symbol")
def histogram_release_daily(spark, d):
    symbols = spark.createDataFrame([(s,) for s in EVENT_TYPES], "symbol string")
    return rounded(release.histogram(event_state(spark, d), DAILY, symbols, LAP, key("hd")))


YEARS = IntervalGrid.regular(T1995 - 1, 365 * DAY, 7)


@query(f"""with {CL_STATUS}, h as (select c.*, r_name as group_key from cl c join customer on c_custkey = entry join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey),
s as (select {sql_idx(365 * DAY, T1995 - 1)} as idx, group_key, cast(sum(if(after = 'O', 1, 0) - if(before = 'O', 1, 0)) as bigint) as exact from h group by 1, 2)
select cast(i as bigint) as idx, r_name as group_key, round(coalesce(exact, 0) + {sql_laplace(2.0, 'dr', chr(39) + '0' + chr(39), 'i', 'r_name')}, 6) as noisy, 0.5::double as eps, 8.0::double as sigma2
from range(7) y(i), region left join s on s.idx = i and s.group_key = r_name""")
def disjoint_by_region(spark, d):
    """Regions are disjoint predicates on entries, so they share one budget."""
    cl, regions = _by_region(spark, d)
    return rounded(release.disjoint(cl, YEARS, linear.count_if(lambda v: v == "O"), LAP, key("dr"), regions, "group_key"))


@query(f"select idx, round(sum(noisy) over (order by idx), 6) as total, sum(sigma2) over (order by idx) as var from ({noisy_sql('dl', 2.0, laplace_variance(2.0), 0.5).replace('round(exact', '(exact').replace(', 6) as noisy', ') as noisy')})")
def running_total_noisy(spark, d):
    out = release.running_total(release.disjoint(event_state(spark, d), DAILY, ERROR, LAP, key("dl")))
    return out.withColumn("total", F.round("total", 6) + 0.0)


@query(f"""with {CL_VALUE}, s as (select {sql_idx(DAY)} as idx, cast(sum({SQL_CENTS}) as bigint) as a, cast(sum(if(after is not null, 1, 0) - if(before is not null, 1, 0)) as bigint) as b from cl group by 1), {GRID}
select 'sum' as mechanism, g.idx, round(coalesce(a, 0) + {sql_laplace(30000.0, 'ht/sum', chr(39) + '0' + chr(39), 'g.idx')}, 6) as noisy, 1.0::double as eps, 1800000000.0::double as sigma2 from g left join s on s.idx = g.idx union all
select 'count', g.idx, round(coalesce(b, 0) + {sql_laplace(4.0, 'ht/count', chr(39) + '0' + chr(39), 'g.idx')}, 6), 0.25, 32.0 from g left join s on s.idx = g.idx""")
def disjoint_heterogeneous(spark, d):
    q = [("sum", CENTS, Noise("laplace", 1.0)), ("count", linear.count_if(lambda v: v.isNotNull()), Noise("laplace", 0.25))]
    return rounded(release.heterogeneous(event_value(spark, d), DAILY, q, key("ht")))


# Trees: 720 hours, fan-out 2, height 10.
HOURLY = IntervalGrid.regular(T0, HOUR, 720)
TREE = Noise("laplace", 0.1)


def hourly_sql() -> str:
    return f"s as (select greatest(0, {sql_idx(HOUR)}) as i, cast(sum({SQL_ERROR}) as bigint) as x from cl where {sql_idx(HOUR)} <= 719 group by 1), b as (select cast(r.i as bigint) as i, coalesce(x, 0) as x from range(720) r(i) left join s on s.i = r.i)"


def tree_sql(h: int = 10, c: int = 2) -> str:
    return f"{hourly_sql()}, t as (select cast(j as integer) as layer, b.i // cast(pow({c}, j) as bigint) as idx, cast(sum(x) as bigint) as exact from b, range({h}) l(j) group by 1, 2)"


def tree_noisy(rel: str = "tn") -> str:
    return f"{tree_sql()}, n as (select layer, idx, exact + {sql_laplace(10.0, rel, 'layer', 'idx')} as noisy, 0.1::double as eps, 200.0::double as sigma2 from t)"


@query(f"with {CL_STATE}, {tree_sql()} select * from t")
def tree_nodes_exact(spark, d):
    return hierarchy.exact_nodes(linear.change(HOURLY.assign(event_state(spark, d), from_beginning=True), ERROR), 720, 2, 10)


def tree_nodes(spark, d):
    return hierarchy.hierarchy(event_state(spark, d), HOURLY, 2, 10, ERROR, TREE, key("tn"), from_beginning=True)


@query(f"with {CL_STATE}, {tree_noisy()} select layer, idx, round(noisy, 6) as noisy, eps, sigma2 from n")
def tree_nodes_noisy(spark, d):
    return rounded(tree_nodes(spark, d))


def ranges(spark):
    """Every 45th start, seven lengths."""
    i = F.col("id")
    length = F.element_at(F.array(*[F.lit(x) for x in (1, 7, 24, 48, 100, 168, 240)]), (i % 7 + 1).cast("int"))
    return spark.range(70).select(i.alias("range_id"), (F.floor(i / 7) * 45).cast("long").alias("l"), (F.floor(i / 7) * 45 + length).cast("long").alias("r"))


RANGES = "q as (select cast(i as bigint) as range_id, cast(i // 7 * 45 as bigint) as l, cast(i // 7 * 45 + [1, 7, 24, 48, 100, 168, 240][i % 7 + 1] as bigint) as r from range(70) z(i))"
#: Nodes within the range whose parent is not (or is above the top).
COVER = "k as (select range_id, layer, idx from q, n where idx * pow(2, layer) >= l and (idx + 1) * pow(2, layer) <= r and (layer = 9 or idx // 2 * pow(2, layer + 1) < l or (idx // 2 + 1) * pow(2, layer + 1) > r))"


def user_ranges(spark, d):
    """(range_id, l, r): the hours of the grid from each user's first event to the last."""
    hours = HOURLY.assign(events(spark, d).select("user_id", F.col("us").alias("ts"), F.col("value"))).groupBy(F.col("user_id").alias("range_id"))
    return hours.agg(F.min("idx").alias("l"), (F.max("idx") + 1).alias("r"))


USER_RANGES = f"q as (select user_id as range_id, min(i) as l, max(i) + 1 as r from (select user_id, {sql_idx(3_600_000_000, ts='epoch_us(ts)')} as i from events) where i between 0 and 719 group by 1)"


@query(f"with {USER_RANGES}, n as (select cast(j as integer) as layer, cast(i as bigint) as idx from range(10) a(j), range(1440) b(i)), {COVER} select * from k")
def cover_nodes_ranges(spark, d):
    """The nodes that make up the hours in which each user was active."""
    return hierarchy.cover_df(user_ranges(spark, d), 2, 10)


@query(f"""with s as (select {sql_idx(DAY, T1995 - 1, 'epoch_us(o_orderdate)')} as i, count(*) as n, cast(sum(cast(round(o_totalprice * 100) as bigint)) as bigint) as c from orders group by 1),
k as (select cast(0 as bigint) as range_id, cast(z.i // 9 as integer) as layer, cast(if(z.i < 9, 90 + z.i, z.i - 9) as bigint) as idx from range(18) z(i))
select range_id, layer, idx, cast(coalesce(sum(n), 0) as bigint) as orders, cast(coalesce(sum(c), 0) as bigint) as cents from k left join s on s.i // cast(pow(10, layer) as bigint) = idx and s.i >= 0 group by 1, 2, 3""")
def cover_worked_example(spark, d):
    """(0, 99] at fan-out 10 and height 2: nine nodes of either layer, with the orders of the first 99 days of 1995 in each."""
    cover = hierarchy.cover_df(spark.range(1).select(F.col("id").alias("range_id"), F.lit(0).cast("long").alias("l"), F.lit(99).cast("long").alias("r")), 10, 2)
    days = IntervalGrid.regular(T1995 - 1, DAY, 100)  # a day's midnight lies within it
    o = table(spark, d, "orders").select(micros("o_orderdate").alias("ts"), F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    daily = days.assign(o).groupBy("idx").agg(F.count("*").alias("orders"), F.sum("cents").alias("cents"))
    each = daily.select("idx", F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.col(m).alias("exact")) for m in ("orders", "cents")])).alias("m")).select("idx", "m.*")
    nodes = hierarchy.exact_nodes(each, 100, 10, 2, spark.createDataFrame([("orders",), ("cents",)], "measure string"))
    of = lambda m: F.sum(F.when(F.col("measure") == m, F.col("exact"))).alias(m)
    return cover.join(nodes, ["layer", "idx"]).groupBy("range_id", "layer", "idx").agg(of("orders"), of("cents"))


@query(f"with {CL_STATE}, {tree_noisy()}, {RANGES}, {COVER} select range_id, round(sum(noisy), 6) as estimate, count(*) as n_nodes, sum(sigma2) as var from k join n using (layer, idx) group by 1")
def range_from_tree(spark, d):
    return hierarchy.range_query(tree_nodes(spark, d), ranges(spark), 2, 10).withColumn("estimate", F.round("estimate", 6) + 0.0)


@query(f"with {CL_STATE}, {tree_noisy()}, q as (select cast(i as bigint) as range_id, 0 as l, i + 1 as r from range(720) z(i)), {COVER} select range_id as idx, round(sum(noisy), 6) as estimate, sum(sigma2) as var from k join n using (layer, idx) group by 1")
def prefix_from_tree(spark, d):
    return hierarchy.prefix_series(tree_nodes(spark, d), 720, 2, 10).withColumn("estimate", F.round("estimate", 6) + 0.0)


def _consistency_sql(h: int = 6) -> str:
    """Up, a layer at a time: a node's own answer and its children's sum, weighted by their variances; down: a node takes half of
    what its parent has beyond the two children."""
    ctes = [f"n as (select cast(j as integer) as layer, b.i // cast(pow(2, j) as bigint) as idx, sum(x) + any_value(0) as exact from (select cast(r.i as bigint) as i, coalesce(x, 0) as x from range(32) r(i) left join s on s.i = r.i) b, range({h}) l(j) group by 1, 2)",
            f"y as (select layer, idx, exact + {sql_laplace(10.0, 'tc', 'layer', 'idx')} as noisy from n)", "z0 as (select idx, noisy as z from y where layer = 0)"]
    for j in range(1, h):
        own = f"((pow(2, {j + 1}) - pow(2, {j})) / (pow(2, {j + 1}) - 1))"
        ctes.append(f"z{j} as (select y.idx, {own} * any_value(noisy) + (1 - {own}) * sum(c.z) as z from y join z{j - 1} c on c.idx // 2 = y.idx where layer = {j} group by 1)")
    ctes.append(f"u{h - 1} as (select idx, z as u from z{h - 1})")
    for j in range(h - 2, -1, -1):
        ctes.append(f"u{j} as (select c.idx, c.z + (p.u - sum(c.z) over (partition by c.idx // 2)) / 2 as u from z{j} c join u{j + 1} p on p.idx = c.idx // 2)")
    return ", ".join(ctes) + " " + " union all ".join(f"select cast({j} as integer) as layer, idx, round(u, 6) as consistent from u{j}" for j in range(h))


@query(f"with {CL_STATE}, s as (select {sql_idx(DAY)} as i, sum({SQL_ERROR}) as x from cl where {sql_idx(DAY)} between 0 and 31 group by 1), {_consistency_sql()}")
def tree_consistency(spark, d):
    grid = IntervalGrid.regular(T0, DAY, 32)
    nodes = hierarchy.hierarchy(event_state(spark, d), grid, 2, 6, ERROR, TREE, key("tc"))
    return hierarchy.make_consistent(nodes, 32, 2, 6).withColumn("consistent", F.round("consistent", 6) + 0.0)


@query(f"with {RANGES}, n as (select cast(j as integer) as layer, cast(i as bigint) as idx from range(10) a(j), range(1440) b(i)), {COVER} select range_id, count(*) as n_nodes, count(*) * 200.0::double as var from k group by 1")
def tree_variance_by_range(spark, d):
    return hierarchy.cover_df(ranges(spark), 2, 10).groupBy("range_id").agg(F.count("*").alias("n_nodes"), (F.count("*") * 200.0).alias("var"))


# Sliding.
S14 = sliding.SlidingSpec(T0 + 14 * DAY, 14 * DAY, DAY, 17)
S36 = sliding.SlidingSpec(T0 + 36 * HOUR, 36 * HOUR, 24 * HOUR, 28)
TUMBLE = sliding.SlidingSpec(T0 + DAY, DAY, DAY, 30)
GAP = sliding.SlidingSpec(T0 + 6 * HOUR, 6 * HOUR, 12 * HOUR, 60)


def window_sql(s: sliding.SlidingSpec, noise: str = "0") -> str:
    return f"w as (select cast(i as bigint) as idx, cast(coalesce(sum({SQL_ERROR}), 0) as bigint) as exact from range({s.n}) r(i) left join cl on ts > {s.t1 - s.w} + i * {s.p} and ts <= {s.t1} + i * {s.p} group by 1)"


def _exact_sql(s):
    return f"with {CL_STATE}, {window_sql(s)} select * from w"


@query(_exact_sql(S14))
def sliding_direct_exact(spark, d):
    return sliding.direct_exact(event_state(spark, d), S14, ERROR)


@query(f"with {CL_STATE}, {window_sql(S14)} select idx, round(exact + {sql_laplace(2.0, 'sd', chr(39) + '0' + chr(39), 'idx')}, 6) as noisy, 0.5::double as eps, 8.0::double as sigma2 from w")
def sliding_direct_noisy(spark, d):
    return rounded(sliding.direct(event_state(spark, d), S14, ERROR, LAP, key("sd")))


@query(_exact_sql(GAP))
def sliding_gap(spark, d):
    return sliding.direct_exact(event_state(spark, d), GAP, ERROR)


@query(_exact_sql(TUMBLE))
def sliding_tumbling(spark, d):
    return sliding.direct_exact(event_state(spark, d), TUMBLE, ERROR)


@query(_exact_sql(S36))
def sliding_non_divisible(spark, d):
    return sliding.direct_exact(event_state(spark, d), S36, ERROR)


#: Nodes within window w = [w, w + 14) of a binary tree of four layers: whole, and not under a whole parent.
_WINDOW_COVER = "k as (select w, layer, idx from range(17) a(w), t where idx * pow(2, layer) >= w and (idx + 1) * pow(2, layer) <= w + 14 and (layer = 3 or idx // 2 * pow(2, layer + 1) < w or (idx // 2 + 1) * pow(2, layer + 1) > w + 14))"


def _tree_window_sql(noise: str, var: float) -> str:
    return f"""with {CL_STATE}, s as (select {sql_idx(DAY)} as i, cast(sum({SQL_ERROR}) as bigint) as x from cl group by 1), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact from range(30) r(i) cross join range(4) l(j) left join s on s.i = r.i group by 1, 2),
    {_WINDOW_COVER} select cast(w as bigint) as idx, round(sum(exact + {noise}), 6) as estimate, count(*) as n_nodes, count(*) * {var}::double as var from k join t using (layer, idx) group by 1"""


@query(_tree_window_sql("0.0", 0.0))
def sliding_from_tree_exact(spark, d):
    return sliding.from_hierarchy(event_state(spark, d), S14, ERROR, Noise("off"), key("st"), 2)


@query(_tree_window_sql(sql_laplace(10.0, "st", "layer", "idx"), 200.0))
def sliding_from_tree_noisy(spark, d):
    return sliding.from_hierarchy(event_state(spark, d), S14, ERROR, TREE, key("st"), 2).withColumn("estimate", F.round("estimate", 6) + 0.0)


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)}, n as (select idx, exact + {sql_laplace(2.0, 'sf', chr(39) + '0' + chr(39), 'idx')} as noisy from b) select cast(i as bigint) as idx, round(sum(noisy), 6) as estimate, cast(14 as bigint) as n_nodes, 112.0::double as var from range(17) r(i) join n on n.idx >= i and n.idx < i + 14 group by 1")
def sliding_from_flat(spark, d):
    return sliding.from_flat(event_state(spark, d), S14, ERROR, LAP, key("sf")).withColumn("estimate", F.round("estimate", 6) + 0.0)


# Trees and windows of histograms, groups and vectors.
def _alphabet(spark, symbols=EVENT_TYPES):
    return spark.createDataFrame([(s,) for s in symbols], "symbol string")


_HIST_TREE = f"""pm0 as (select greatest(0, {sql_idx(DAY, LATE)}) as i, after as symbol, 1 as n from cl where after is not null and {sql_idx(DAY, LATE)} < 16 union all select greatest(0, {sql_idx(DAY, LATE)}), before, -1 from cl where before is not null and {sql_idx(DAY, LATE)} < 16),
hs as (select i, symbol, sum(n) as x from pm0 group by 1, 2), al as (select unnest({EVENT_TYPES!r}) as symbol),
ht as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, al.symbol, cast(sum(coalesce(x, 0)) as bigint) as exact from range(16) r(i) cross join range(4) l(j) cross join al left join hs on hs.i = r.i and hs.symbol = al.symbol group by 1, 2, 3),
hn as (select layer, idx, symbol, exact + {sql_laplace(20.0, 'th', 'layer', 'idx', 'symbol')} as noisy from ht)"""
LATE_GRID = IntervalGrid.regular(LATE, DAY, 16)


def _histogram_tree(spark, d):
    return hierarchy.hierarchy_histogram(event_state(spark, d), LATE_GRID, 2, 4, _alphabet(spark), TREE, key("th"), from_beginning=True)


@query(f"with {CL_STATE}, {_HIST_TREE} select layer, idx, symbol, round(noisy, 6) as noisy, 0.1::double as eps, 800.0::double as sigma2 from hn")
def tree_histogram(spark, d):
    """A tree of histograms whose first interval reaches back to the beginning."""
    return rounded(_histogram_tree(spark, d))


@query(f"""with {CL_STATE}, {_HIST_TREE} select cast(r.i as bigint) as idx, symbol, round(sum(noisy), 6) as estimate, count(*) * 800.0::double as var from range(16) r(i) join hn on (hn.idx + 1) * pow(2, layer) <= r.i + 1
  and (layer = 3 or (hn.idx // 2 + 1) * pow(2, layer + 1) > r.i + 1) group by 1, 2""")
def tree_histogram_prefix(spark, d):
    """The histogram of states after every day, from few nodes each."""
    return hierarchy.prefix_series(_histogram_tree(spark, d), 16, 2, 4).withColumn("estimate", F.round("estimate", 6) + 0.0)


_REGION_SQL = f"""h as (select c.*, r_name as group_key from cl c join customer on c_custkey = entry join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey),
s as (select {sql_idx(365 * DAY, T1995 - 1)} as i, group_key, sum(if(after = 'O', 1, 0) - if(before = 'O', 1, 0)) as x from h group by 1, 2)"""


def _by_region(spark, d):
    r, n = table(spark, d, "region"), table(spark, d, "nation")
    c = table(spark, d, "customer").select("c_custkey", "c_nationkey")
    where = c.join(n.join(r, n.n_regionkey == r.r_regionkey), c.c_nationkey == n.n_nationkey).select(F.col("c_custkey").alias("entry"), F.col("r_name").alias("group_key"))
    return customer_status(spark, d).join(where, "entry"), r.select(F.col("r_name").alias("group_key"))


@query(f"""with {CL_STATUS}, {_REGION_SQL} select cast(j as integer) as layer, cast(y.i // cast(pow(2, j) as bigint) as bigint) as idx, r_name as group_key, round(cast(sum(coalesce(x, 0)) as bigint) + {sql_laplace(10.0, 'tg', 'j', 'y.i // cast(pow(2, j) as bigint)', 'r_name')}, 6) as noisy, 0.1::double as eps, 200.0::double as sigma2
from range(7) y(i) cross join range(3) l(j) cross join region left join s on s.i = y.i and s.group_key = r_name group by j, y.i // cast(pow(2, j) as bigint), r_name""")
def tree_by_region(spark, d):
    """A tree for each region; regions are disjoint predicates on entries, so the trees share one budget."""
    cl, regions = _by_region(spark, d)
    return rounded(hierarchy.hierarchy(cl, YEARS, 2, 3, linear.count_if(lambda v: v == "O"), TREE, key("tg"), regions, "group_key"))


@query("""with v as (select vec_id // 100 as i, embedding::double[] as e, greatest(1.0, sqrt(list_sum([x * x for x in embedding::double[]]))) as len from embeddings where vec_id // 100 < 4),
u as (select i, unnest(range(64)) as coord, unnest(e) / len as x from v), n as (select cast(j as integer) as layer, cast(i // cast(pow(2, j) as bigint) as bigint) as idx, cast(coord as integer) as coord, sum(x) as x from u, range(3) l(j) group by 1, 2, 3),
g as (select cast(j as integer) as layer, cast(i as bigint) as idx, cast(k as integer) as coord from range(3) l(j), range(4) y(i), range(64) c(k) where i < 4 // cast(pow(2, j) as bigint))
select layer, idx, coord, round(coalesce(x, 0) + """ + f"2 * sqrt(-2 * ln({sql_u('tv', 'layer', 'idx', 'coord')})) * cos(2 * pi() * {sql_u('tv', 'layer', 'idx', 'coord', salt='b')})" + ", 5) as noisy, 4.0::double as sigma2 from g left join n using (layer, idx, coord)")
def tree_vector_sums(spark, d):
    """A tree of sums of clipped vectors over their ids as a logical clock, with Gaussian noise at rho = 1/2 a node."""
    cl = changelog.from_inserts(table(spark, d, "embeddings"), "vec_id", "vec_id", "embedding")
    nodes = hierarchy.hierarchy_vector(cl, IntervalGrid.regular(-1, 100, 4), 2, 3, 64, 1.0, Noise("gaussian", rho=0.5), key("tv"))
    return nodes.select("layer", "idx", "coord", (F.round("noisy", 5) + 0.0).alias("noisy"), "sigma2")


LAYERS = [0.2, 0.1, 0.05, 0.05]


@query(f"with {CL_STATE}, s as (select {sql_idx(DAY)} as i, sum({SQL_ERROR}) as x from cl group by 1), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact, [0.2, 0.1, 0.05, 0.05][j + 1]::double as eps from range(16) r(i) cross join range(4) l(j) left join s on s.i = r.i group by 1, 2, 4) select layer, idx, round(exact + {sql_laplace('1 / eps', 'tl', 'layer', 'idx')}, 6) as noisy, eps, round(2 / (eps * eps), 6) as sigma2 from t")
def tree_layer_budgets(spark, d):
    """Layers with budgets of their own: the base gets half of the total of 0.4."""
    out = hierarchy.hierarchy(event_state(spark, d), IntervalGrid.regular(T0, DAY, 16), 2, 4, ERROR, [Noise("laplace", e) for e in LAYERS], key("tl"))
    return rounded(out).withColumn("sigma2", F.round("sigma2", 6))


_HIST_WINDOWS = f"pw as (select ts, after as symbol, 1 as n from cl where after is not null union all select ts, before, -1 from cl where before is not null), al as (select unnest({EVENT_TYPES!r}) as symbol)"


@query(f"with {CL_STATE}, {_HIST_WINDOWS}, w as (select cast(i as bigint) as idx, al.symbol, cast(coalesce(sum(n), 0) as bigint) as exact from range(17) r(i) cross join al left join pw on pw.symbol = al.symbol and ts > {S14.t1 - S14.w} + i * {S14.p} and ts <= {S14.t1} + i * {S14.p} group by 1, 2) select idx, symbol, round(exact + {sql_laplace(4.0, 'sh', chr(39) + '0' + chr(39), 'idx', 'symbol')}, 6) as noisy, 0.5::double as eps, 32.0::double as sigma2 from w")
def sliding_histogram(spark, d):
    return rounded(sliding.direct_histogram(event_state(spark, d), S14, _alphabet(spark), LAP, key("sh")))


@query(f"""with {CL_STATE}, {_HIST_WINDOWS}, s as (select {sql_idx(DAY)} as i, symbol, sum(n) as x from pw group by 1, 2), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, al.symbol, cast(sum(coalesce(x, 0)) as bigint) as exact from range(30) r(i) cross join range(4) l(j) cross join al left join s on s.i = r.i and s.symbol = al.symbol group by 1, 2, 3),
{_WINDOW_COVER.replace('select w, layer, idx from', 'select distinct w, layer, idx from')} select cast(w as bigint) as idx, symbol, round(sum(exact + {sql_laplace(20.0, 'sw', 'layer', 'idx', 'symbol')}), 6) as estimate, count(*) as n_nodes, count(*) * 800.0::double as var from k join t using (layer, idx) group by 1, 2""")
def sliding_histogram_from_tree(spark, d):
    return sliding.histogram_from_hierarchy(event_state(spark, d), S14, _alphabet(spark), TREE, key("sw"), 2).withColumn("estimate", F.round("estimate", 6) + 0.0)


# One total budget of 1 for at most one mutation an entry: 14-day windows every day, by three plans, over 100 keys.
RUNS, MATCHED_H = 100, 2


def _matched_sql() -> str:
    lap = lambda scale, *parts: sql_laplace(scale, "mb", *parts)
    return f"""b as (select cast(i as bigint) as idx from range(30) r(i)), w as (select cast(i as bigint) as w from range(17) r(i)), run as (select cast(i as bigint) as run from range({RUNS}) r(i)),
    t as (select cast(0 as integer) as layer, idx from b union all select cast(1 as integer), cast(i as bigint) from range(8) r(i)),
    k as (select w, layer, idx from w, t where idx * pow(4, layer) >= w and (idx + 1) * pow(4, layer) <= w + 14 and (layer = 1 or idx // 4 * 4 < w or (idx // 4 + 1) * 4 > w + 14)),
    e as (select 'direct' as plan, w, run, {lap(14.0, chr(39) + 'd' + chr(39), 'w', 'run')} as e from w, run
      union all select 'flat', w, run, sum({lap(1.0, chr(39) + 'f' + chr(39), 'idx', 'run')}) from w join b on idx >= w and idx < w + 14 cross join run group by 2, 3
      union all select 'tree', w, run, sum({lap(2.0, 'layer', 'idx', 'run')}) from k cross join run group by 2, 3),
    n as (select 'direct' as plan, w, 1 as nodes, 2 * 14.0 * 14 as var from w union all select 'flat', w, 14, 28.0 from w union all select 'tree', w, count(*), count(*) * 8.0 from k group by w)
    select plan, cast(e.w as bigint) as idx, cast(any_value(nodes) as bigint) as n_nodes, cast(any_value(n.var) as double) as var, round(avg(e), 6) as bias, round(var_samp(e), 6) as measured from e join n using (plan, w) group by 1, 2"""


@query(f"with {_matched_sql()}")
def sliding_matched_budget(spark, d):
    """(plan, idx, n_nodes, var, bias, measured): the variance that direct, flat and tree releases of one total budget have by
    their formulas and measured over many keys, window by window."""
    from ..operators import metrics

    spec, runs = S14, RUNS
    base = sliding.base_sums(event_state(spark, d), spec, ERROR)
    windows, k = spec.ranges(spark), key("mb")
    direct = metrics.monte_carlo(sliding.rolled(base, spec, [], exact="exact"), Noise("laplace", 1 / A.folds_sliding_k(1, spec.w, spec.p)), 1, 1, runs, k, "d")
    one = base.select(F.lit(0).alias("layer"), "idx", "exact")
    flat = metrics.cover_monte_carlo(one, windows, 2, 1, Noise("laplace", 1.0), 1, 1, runs, k, "f")
    tree = metrics.cover_monte_carlo(hierarchy.exact_nodes(base, 30, 4, MATCHED_H), windows, 4, MATCHED_H, Noise("laplace", 1 / A.folds_tree_k(MATCHED_H, 1)), 1, 1, runs, k)
    nodes = hierarchy.cover_df(windows, 4, MATCHED_H).groupBy(F.col("range_id").alias("idx")).agg(F.count("*").alias("n_nodes"))
    each = windows.select(F.col("range_id").alias("idx"))
    out = direct.join(each.select("idx", F.lit(1).cast("long").alias("n_nodes")), "idx").select(F.lit("direct").alias("plan"), "*", (F.lit(2.0 * A.folds_sliding_k(1, spec.w, spec.p) ** 2)).alias("formula"))
    out = out.unionByName(flat.join(each.select("idx", F.lit(14).cast("long").alias("n_nodes")), "idx").select(F.lit("flat").alias("plan"), "*", F.lit(28.0).alias("formula")))
    out = out.unionByName(tree.join(nodes, "idx").select(F.lit("tree").alias("plan"), "*", (F.col("n_nodes") * 2.0 * MATCHED_H**2).alias("formula")))
    return out.select("plan", "idx", "n_nodes", F.col("formula").alias("var"), (F.round("bias", 6) + 0.0).alias("bias"), F.round("var", 6).alias("measured"))


# A secret key: the same digests by DuckDB's own SHA-256, from the pads that HMAC prescribes.
SECRET = b"a secret of the tests"


def sql_secret_u(release: str, *parts: str, salt: str = "") -> str:
    """The keyed uniform under SECRET: two rounds of SHA-256 with the pads that HMAC prescribes, the key from Python's hmac."""
    import hashlib
    import hmac

    own = hmac.new(SECRET, f"test|{release}".encode(), hashlib.sha256).digest() + bytes(32)
    pad = lambda x: "from_hex('" + bytes(b ^ x for b in own).hex() + "')"
    text = ", ".join(["'test'", f"'{release}'", *[f"cast({p} as varchar)" for p in parts], f"'{salt}'"])
    digest = f"sha256({pad(0x5C)} || from_hex(sha256({pad(0x36)} || encode(concat_ws('|', {text})))))"
    return f"(((('0x' || substr({digest}, 1, 13))::bigint) + 0.5) / 4503599627370496.0)"


_U = f"({sql_secret_u('ds', chr(39) + '0' + chr(39), 'idx')} - 0.5)"


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)} select idx, round(exact - 2.0 * sign({_U}) * ln(1 - 2 * abs({_U})), 6) as noisy, 0.5::double as eps, 8.0::double as sigma2 from b")
def disjoint_noisy_secret(spark, d):
    """Noise under a secret key, from Spark's sha2 alone."""
    from ..functions.noise import Key

    return rounded(release.disjoint(event_state(spark, d), DAILY, ERROR, LAP, Key("test", "ds", SECRET)))


# Lineitem days: fan-out 10.
LINE_DAYS = IntervalGrid.regular(T1995 - 1, DAY, 2500)


@query(f"""with s as (select {sql_idx(DAY, T1995 - 1, 'epoch_us(l_shipdate)')} as i, count(*) as x from lineitem group by 1), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(10, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact from range(2500) r(i) cross join range(4) l(j) left join s on s.i = r.i group by 1, 2)
select layer, idx, round(exact + {sql_laplace(4.0, 'tl10', 'layer', 'idx')}, 6) as noisy, 0.25::double as eps, 32.0::double as sigma2 from t""")
def tree_lineitem_days(spark, d):
    """Shipped lines over 2,500 days, each line an entry: a tree of fan-out 10 and height 4."""
    li = table(spark, d, "lineitem").select(micros("l_shipdate").alias("ts"), F.lit(1).alias("entry"), F.lit(None).cast("string").alias("before"), F.lit("1").alias("after"))
    return rounded(hierarchy.hierarchy(li, LINE_DAYS, 10, 4, linear.count_if(lambda v: v.isNotNull()), Noise("laplace", 0.25), key("tl10")))


NOW = T0 + 10 * DAY + 5 * HOUR


@query(f"with {CL_STATE}, {tree_noisy()} select layer, idx, round(noisy, 6) as noisy, eps, sigma2 from n where {T0} + (idx + 1) * {HOUR} * cast(pow(2, layer) as bigint) <= {NOW}")
def tree_released_by(spark, d):
    """What a live release has published at a time: the nodes whose intervals have ended, and no padded one."""
    return rounded(hierarchy.released_by(tree_nodes(spark, d), HOURLY, 2, NOW))
