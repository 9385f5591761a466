"""Budgets, fold counts, touched queries, crossovers, and measures."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.intervals import DAY, ceil_int, div_int, interval_span
from ..functions.noise import Noise, laplace_variance
from ..operators import hierarchy, linear, metrics, release, sliding
from ..plans import accounting as A
from ..plans.filters import Filter, by_group, filtered_budget
from ..plans.planner import choose_sliding_plan
from .base import *
from .base import CL_SHIP, CL_STATE, CL_STATUS, CL_VALUE, LIMITS, sql_idx, sql_laplace
from .log import HYBRID, hybrid
from .releases import ERROR, GRID, HOURLY, S14, daily_sql, SQL_ERROR

CASES = [("a", [1, 2, 3], 100), ("b", [0, 10, 11, 12, 13], 5), ("c", list(range(0, 50, 5)), 12), ("d", [0, 1, 2, 3], 0), ("e", list(range(0, 300, 7)), 50)]
_VALUES = ", ".join(f"('{n}', {t}, {b})" for n, e, b in CASES for t in e)


@query(f"""with v(grid, t, b) as (values {_VALUES}), r as (select *, row_number() over (partition by grid order by t) as i, max(t) over (partition by grid) as last from v),
j as (select x.grid, x.i, min(y.i) as j from r x join r y on x.grid = y.grid and y.i >= x.i and (y.t >= x.t + x.b or y.t = y.last) group by 1, 2)
select grid, cast(max(j - i + 1) as bigint) as span from j group by 1""")
def span_grid(spark, d):
    return spark.createDataFrame([(n, interval_span(e, b)) for n, e, b in CASES], "grid string, span long")


#: Width, period (days), fan-out and height of releases.
SHAPES = [(w, p, c, h) for w, p in ((14, 1), (28, 7), (36, 24), (6, 12)) for c, h in ((2, 4), (4, 2))]
_CEIL = lambda a, b: f"cast(ceil(({a}) * 1.0 / ({b})) as bigint)"


@query(f"""with {LIMITS}, kb as (select k, b, count(*) as entries from lim group by 1, 2), gr(w, p, c, h) as (values {', '.join(map(str, SHAPES))}),
t as (select kb.*, gr.*, cast(sum(ceil(b * 1.0 / (w * pow(c, j))) + 1) as bigint) as tb from kb, gr, range(4) r(j) where j < h group by all)
select k, b, entries, w, p, c, h, model, cast(m * dk as bigint) as disjoint_k, cast(m * db as bigint) as disjoint_b, cast(m * h * k as bigint) as tree_k, cast(m * tb as bigint) as tree_b, cast(m * sk as bigint) as sliding_k, cast(m * sb as bigint) as sliding_b
from (select *, k as dk, {_CEIL('b', 'w')} + 1 as db, k * {_CEIL('w', 'p')} as sk, {_CEIL('b + w', 'p')} as sb from t), (values ('global', 1), ('local', 2)) as x(model, m)""")
def folds_table(spark, d):
    """Folds that customers with k orders within b days may touch of releases of every shape, and how many such customers there are."""
    k, b, rows = F.col("k"), F.col("b"), []
    names = ["disjoint_k", "disjoint_b", "tree_k", "tree_b", "sliding_k", "sliding_b"]
    for w, p, c, h in SHAPES:
        folds = (A.folds_disjoint_k(k), A.folds_disjoint_b_regular(b, w), A.folds_tree_k(h, k), A.folds_tree_b(h, c, b, w), A.folds_sliding_k(k, w, p), A.folds_sliding_b(b, w, p))
        shape = [F.lit(x).alias(n) for x, n in zip((w, p, c, h), "wpch", strict=True)]
        for model, counts in (("global", folds), ("local", map(A.local_folds, folds))):
            rows.append(F.struct(*shape, F.lit(model).alias("model"), *[x.cast("long").alias(n) for x, n in zip(counts, names, strict=True)]))
    kinds = order_limits(spark, d).groupBy("k", "b").agg(F.count("*").alias("entries"))
    return kinds.select("k", "b", "entries", F.explode(F.array(*rows)).alias("r")).select("k", "b", "entries", "r.*")


_EPS_K = f"{CL_STATE}, kk as (select k, count(*) as entries from (select count(*) as k from cl group by entry) group by 1), x as (select e as eps, k, entries from kk, (values (0.01::double), (0.1), (0.5)) a(e))"
ORDERS_R = (1.5, 2, 3, 4, 6, 8, 12, 16, 24, 32, 64, 128)


@query(f"""with {_EPS_K}, i as (select eps, k, i, (k - 2 * i) * eps as e from (select x.*, unnest(range(k // 2 + 1)) as i from x)),
t as (select eps, k, e, coalesce(sum(exp(lgamma(k + 1) - lgamma(j + 1) - lgamma(k - j + 1) - k * ln(1 + exp(eps)) + (k - j) * eps) - exp(lgamma(k + 1) - lgamma(j + 1) - lgamma(k - j + 1) - k * ln(1 + exp(eps)) + (k - 2 * i + j) * eps)) filter (where j < i), 0) as d
  from (select i.*, unnest(range(i + 1)) as j from i) group by eps, k, i, e),
f as (select eps, k, min(e) as optimal from t where d <= 1e-6 group by 1, 2),
y as (select eps, k, min(k / (a - 1) * ln(a / (2 * a - 1) * exp((a - 1) * eps) + (a - 1) / (2 * a - 1) * exp(-a * eps)) + ln(1e6) / (a - 1)) as renyi from x, (values {', '.join(f'({a}::double)' for a in ORDERS_R)}) o(a) group by 1, 2)
select eps, k, entries, round(k * eps, 6) as basic, round(sqrt(2 * k * ln(1e6)) * eps + k * eps * (exp(eps) - 1), 6) as advanced, round(optimal, 6) as optimal, round(k * eps * eps / 2 + 2 * sqrt(k * eps * eps / 2 * ln(1e6)), 6) as zcdp, round(renyi, 6) as renyi
from x join f using (eps, k) join y using (eps, k)""")
def composition_table(spark, d):
    """eps of the k queries that a user's k changes touch, by four ways of counting and by the optimal frontier at delta 1e-6, and how
    many users change so often. The frontier is summed over outcomes in log space, from logarithms of factorials."""
    kinds = event_state(spark, d).groupBy("entry").agg(F.count("*").alias("k")).groupBy("k").agg(F.count("*").alias("entries"))
    log_fact = F.expr("aggregate(sequence(1L, k), array(0D), (a, x) -> concat(a, array(element_at(a, -1) + ln(x))))")
    x = kinds.withColumn("lf", log_fact).withColumn("eps", F.explode(F.array(*[F.lit(e) for e in (0.01, 0.1, 0.5)])))
    outcome = "lf[k] - lf[j] - lf[k - j] - k * ln(1 + exp(eps))"
    delta = F.expr(f"if(i = 0, 0D, aggregate(sequence(0L, greatest(0L, i - 1)), 0D, (a, j) -> a + exp({outcome} + (k - j) * eps) - exp({outcome} + (k - 2 * i + j) * eps)))")
    ways = x.withColumn("i", F.explode(F.expr("sequence(0L, k div 2)"))).where(delta <= 1e-6).groupBy("eps", "k", "entries").agg(F.min((F.col("k") - 2 * F.col("i")) * F.col("eps")).alias("optimal"))
    k, eps, log = F.col("k"), F.col("eps"), math.log(1e6)
    renyi = [k / (a - 1) * F.log(a / (2 * a - 1) * F.exp((a - 1) * eps) + (a - 1) / (2 * a - 1) * F.exp(-a * eps)) + log / (a - 1) for a in ORDERS_R]
    rho = k * eps * eps / 2
    found = {"basic": k * eps, "advanced": F.sqrt(2 * k * log) * eps + k * eps * F.expm1(eps), "optimal": F.col("optimal"), "zcdp": rho + 2 * F.sqrt(rho * log), "renyi": F.least(*renyi)}
    return ways.select("eps", "k", "entries", *[F.round(c, 6).alias(n) for n, c in found.items()])


CROSS_FANOUTS = (2, 3, 4, 16)


WINDOWS = f"{LIMITS}, ow as (select b as w, greatest(1, b // (k - 1)) as p, count(*) as entries from lim where k >= 2 and b >= 1 group by 1, 2)"
_OWN_SQL = f"""{WINDOWS}, x as (select w, p, entries, c, w // gcd(w, p) as n from ow, (values (2), (3), (4), (16)) f(c)),
y as (select x.*, (select min(j) from range(1, 62) t(j) where pow(c, j) >= n) as h, cast(ceil(w * 1.0 / p) as bigint) as r from x)"""


def _by_fanout(windows, columns, fanouts=CROSS_FANOUTS):
    """A row for each fan-out c: columns gives those beside c, from c and the height that holds a window."""
    rows = F.array(*[F.struct(F.lit(c).alias("c"), *columns(c, F.col(f"h{c}"))) for c in fanouts])
    windows = windows.withColumns({f"h{c}": A.height_for(div_int(F.col("w"), F.col("g")), c) for c in fanouts})
    return windows.select("w", "p", "entries", F.explode(rows).alias("r")).select("w", "p", "entries", "r.*")


@query(f"with {_OWN_SQL} select w, p, entries, cast(c as integer) as c, cast(h as integer) as h, cast(2 * (c - 1) * h * h * h as double) as lhs, cast(r * r as double) as rhs, 2 * (c - 1) * h * h * h < r * r as tree_wins from y")
def crossover_grid_k(spark, d):
    """Where a tree has the smaller variance bound at one total budget, for at most k mutations an entry: over the windows of the
    customers' own histories."""
    w, p = F.col("w"), F.col("p")

    def columns(c, h):
        lhs, rhs, wins = A.prefer_tree_k(w, p, c, h)
        return h.cast("int").alias("h"), lhs.cast("double").alias("lhs"), rhs.cast("double").alias("rhs"), wins.alias("tree_wins")

    return _by_fanout(order_windows(spark, d), columns)


BOUNDS_B = (1, 7, 30)


@query(f"""with {_OWN_SQL}, z as (select w, p, entries, b, c, h, n, gcd(w, p) as g from y, (values (1), (7), (30)) bb(b) where c in (2, 4)),
s as (select z.*, ceil((b + w) * 1.0 / p) as r, (select sum(ceil(b / (g * pow(c, j))) + 1) from range(62) t(j) where j < h) as safe, (pow(c, h) - 1) / (pow(c, h) - pow(c, h - 1)) * ceil(b * 1.0 / g) + h as pub from z)
select w, p, entries, cast(c as integer) as c, cast(b as integer) as b, round(2 * (c - 1) * h * pub * pub, 3) as published, round(cast(2 * (c - 1) * h * safe * safe as double), 3) as safe, cast(r * r as double) as rhs, 2 * (c - 1) * h * pub * pub < r * r as published_wins, 2 * (c - 1) * h * safe * safe < r * r as safe_wins from s""")
def crossover_grid_b(spark, d):
    """The same where all mutations of an entry lie within b, by the published and by the safe count of folds."""
    w, p = F.col("w"), F.col("p")

    def columns(c, h):
        rows = []
        for b in BOUNDS_B:
            pub, rhs, first = A.prefer_tree_b(w, p, b, c, "published", F.col("g"), h)
            safe, _, second = A.prefer_tree_b(w, p, b, c, "safe", F.col("g"), h)
            rows.append(F.struct(F.lit(b).alias("b"), F.round(pub, 3).alias("published"), F.round(safe.cast("double"), 3).alias("safe"), rhs.cast("double").alias("rhs"), first.alias("published_wins"), second.alias("safe_wins")))
        return (F.array(*rows).alias("rows"),)

    return _by_fanout(order_windows(spark, d), columns, (2, 4)).select("w", "p", "entries", "c", F.explode("rows").alias("r")).select("w", "p", "entries", "c", "r.*")


@query(f"""with {CL_STATE}, {HYBRID}, t as (select constraint_id, entry, count(distinct {sql_idx(DAY)}) as n from hy where {sql_idx(DAY)} between 0 and 29 group by 1, 2), m as (select constraint_id, max(n) as touched from t group by 1)
select constraint_id, if(constraint_id = 'rides', 10, cast(ceil(10 * 1.0) + 1 as bigint)) as folds, touched, if(constraint_id = 'rides', 10, ceil(10 * 1.0) + 1) * 0.125 as eps, greatest(10, ceil(10 * 1.0) + 1) * 0.125 as release_eps from m""")
def hybrid_budget(spark, d):
    """Tickets limited by rides (at most 10) and by time (10 days): the folds each kind may touch, the most that one does touch,
    and the release's budget, the larger of both, at 0.125 a query."""
    rules = [("rides", A.folds_disjoint_k(10)), ("pass", A.folds_disjoint_b_regular(10, 1))]
    total = A.hybrid_bound([A.fold(f, A.Budget(0.125)) for _, f in rules]).eps
    cl = hybrid(spark, d)
    touched = DAILY.assign(cl).select("constraint_id", "entry", "idx").distinct().groupBy("constraint_id", "entry").agg(F.count("*").alias("n")).groupBy("constraint_id").agg(F.max("n").alias("touched"))
    table_ = spark.createDataFrame([(n, f, f * 0.125, total) for n, f in rules], "constraint_id string, folds long, eps double, release_eps double")
    return table_.join(touched, "constraint_id").select("constraint_id", "folds", "touched", "eps", "release_eps")


@query(f"with {_OWN_SQL} select w, p, entries, cast(c as integer) as c, round(r * 0.5 / h, 9) as eps_node from y")
def matched_epsilon(spark, d):
    """Budget of a tree's node that spends what the direct release of a customer's window spends at 0.5 a query."""
    w, p = F.col("w"), F.col("p")
    return _by_fanout(order_windows(spark, d), lambda c, h: [F.round(A.matched_epsilon_k(w, p, h, 0.5), 9).alias("eps_node")])


PLAN_LENGTHS = (2, 7, 14, 28, 90, 365, 720, 4096, 4097, 8760)


@query(f"""with n as (select cast(r as bigint) as r from (values {', '.join(f'({r})' for r in PLAN_LENGTHS)}) v(r)), t as (select r, c, h from n, range(2, 65) a(c), range(2, 16) b(h) where pow(c, h - 1) < r),
o as (select t.*, unnest(range(cast(pow(c, h - 1) as bigint))) as l from t), k as (select r, c, h, l, r - (c - 1) * sum(greatest(0, (l + r) // cast(pow(c, j) as bigint) - (l + cast(pow(c, j) as bigint) - 1) // cast(pow(c, j) as bigint))) as nodes from o, range(1, 15) x(j) where j < h group by 1, 2, 3, 4),
p as (select r, 'tree' as kind, c, h, max(nodes) * h * h as cost, c * 100 + h as place from k group by 1, 2, 3, 4 union all select r, 'direct', 1, 1, r * r, 0 from n union all select r, 'flat', 2, 1, r, 1 from n),
b as (select *, row_number() over (partition by r order by cost, place) as rank from p) select cast(r as integer) as r, kind, cast(c as integer) as c, cast(h as integer) as h, round(cost * 1.0 / (r * r), 12) as ratio from b where rank = 1""")
def sliding_plan_choice(spark, d):
    """The planner's choice over window lengths: direct, flat or a tree, with the variance relative to direct. The SQL counts the
    nodes of every tree at every offset."""
    rows = []
    for r in PLAN_LENGTHS:
        p = choose_sliding_plan(r, 1, 1.0, k=1)
        rows.append((r, p.kind, p.c, p.h, round(p.worst_variance / (2 * r * r), 12)))
    return spark.createDataFrame(rows, "r int, kind string, c int, h int, ratio double")


@query(f"with {CL_STATE} select entry, count(distinct {sql_idx(DAY)}) as touched from cl where {sql_idx(DAY)} between 0 and 29 group by 1")
def touch_counts_disjoint(spark, d):
    return metrics.touch_counts(metrics.touched_disjoint(event_state(spark, d), DAILY))


@query(f"with {CL_STATE}, x as (select distinct entry, j, {sql_idx(3_600_000_000)} // cast(pow(2, j) as bigint) as i from cl, range(10) r(j) where {sql_idx(3_600_000_000)} between 0 and 719) select entry, count(*) as touched from x group by 1")
def touch_counts_tree(spark, d):
    return metrics.touch_counts(metrics.touched_tree(event_state(spark, d), HOURLY, 2, 10))


@query(f"with {CL_STATE} select entry, count(distinct i) as touched from cl, range(17) r(i) where ts > {S14.t1 - S14.w} + i * {S14.p} and ts <= {S14.t1} + i * {S14.p} group by 1")
def touch_counts_sliding(spark, d):
    return metrics.touch_counts(metrics.touched_sliding(event_state(spark, d), S14))


@query(f"with {CL_SHIP} select entry, count(distinct {sql_idx(30 * DAY, T1995)}) as touched from cl where {sql_idx(30 * DAY, T1995)} between 0 and 99 group by 1")
def touch_counts_orders(spark, d):
    from ..functions.intervals import IntervalGrid

    return metrics.touch_counts(metrics.touched_disjoint(order_ship(spark, d), IntervalGrid.regular(T1995, 30 * DAY, 100)))


@query(f"with {CL_STATE}, x as (select distinct entry, {sql_idx(DAY)} as i from cl where {sql_idx(DAY)} between 0 and 29) select entry, sum(0.125 * (1 + i % 2)) as eps, sum(1e-9) * 0 as delta from x group by 1")
def parallel_bound_by_entry(spark, d):
    budgets = spark.range(30).select(F.col("id").alias("idx"), (F.lit(0.125) * (1 + F.col("id") % 2)).alias("eps"), F.lit(0.0).alias("delta"))
    return metrics.parallel_bound(metrics.touched_disjoint(event_state(spark, d), DAILY), budgets)


@query("select cast(i + 1 as bigint) as r, (i + 1) * 200.0::double as plain, bit_count(i + 1) * 200.0::double as tree from range(720) t(i)")
def variance_growth(spark, d):
    """Variance of the total after r releases: a running sum grows in proportion, a prefix from a tree with log r."""
    covers = hierarchy.cover_df(spark.range(720).select(F.col("id").alias("range_id"), F.lit(0).cast("long").alias("l"), (F.col("id") + 1).alias("r")), 2, 10)
    return covers.groupBy((F.col("range_id") + 1).alias("r")).agg(F.count("*").alias("n")).select("r", (F.col("r") * 200.0).alias("plain"), (F.col("n") * 200.0).alias("tree"))


_RATIO = [(r, c) for c in (2, 3, 4) for r in (7, 14, 28, 90, 365)]


@query(f"with x(r, c) as (values {', '.join(map(str, _RATIO))}), y as (select r, c, (select min(j) from range(1, 12) t(j) where pow(c, j) >= r) as h from x), o as (select y.*, unnest(range(cast(pow(c, h - 1) as bigint))) as l from y), k as (select r, c, h, l, r - (c - 1) * coalesce(sum(greatest(0, (l + r) // cast(pow(c, j) as bigint) - (l + cast(pow(c, j) as bigint) - 1) // cast(pow(c, j) as bigint))) filter (where j < h), 0) as nodes from o, range(1, 12) z(j) group by 1, 2, 3, 4) select r, c, round(2.0 * (c - 1) * h * h * h / (r * r), 9) as tree_bound, round(max(nodes) * 1.0 * h * h / (r * r), 9) as tree_exact, round(1.0 / r, 9) as flat from k group by r, c, h")
def matched_variance_ratio(spark, d):
    """Variance over that of a direct release of the same total budget: of trees by the bound and by their worst cover, and flat."""
    rows = []
    for r, c in _RATIO:
        x = metrics.matched_ratio(r, 1, c)
        rows.append((r, c, *(round(x[k], 9) for k in ("tree_bound", "tree_exact", "flat"))))
    return spark.createDataFrame(rows, "r int, c int, tree_bound double, tree_exact double, flat double")


@query("""with t(c, h) as (values (2, 8), (3, 5), (10, 2)), x as (select c, h, unnest(range(1, cast(pow(c, h) as bigint))) as n from t), o as (select *, unnest(range(cast(pow(c, h - 1) as bigint))) as l from x),
k as (select c, h, n, l, n - (c - 1) * sum(greatest(0, (l + n) // cast(pow(c, j) as bigint) - (l + cast(pow(c, j) as bigint) - 1) // cast(pow(c, j) as bigint))) as nodes from o, range(1, 8) z(j) where j < h group by 1, 2, 3, 4),
s as (select l, r, count(*) as times from (select lag(day) over (partition by o_custkey order by day) as l, day as r from (select o_custkey, cast(o_orderdate::date - date '1970-01-01' as bigint) as day from orders)) where l < r group by 1, 2),
q as (select c, h, l, r, times, r - l - (c - 1) * sum(greatest(0, r // cast(pow(c, j) as bigint) - (l + cast(pow(c, j) as bigint) - 1) // cast(pow(c, j) as bigint))) as nodes from s, t, range(1, 8) z(j) where j < h group by c, h, l, r, times),
m as (select c, h, r - l as n, max(nodes) as most, sum(times) as ranges from q group by 1, 2, 3)
select cast(w.c as integer) as c, cast(w.h as integer) as h, cast(w.n as integer) as length, worst, cast(if(w.n = 1, 1, 2 * (w.c - 1) * (select min(j) from range(1, 12) z(j) where pow(w.c, j) >= w.n)) as integer) as bound, cast(coalesce(most, 0) as bigint) as most, cast(coalesce(ranges, 0) as bigint) as ranges
from (select c, h, n, cast(max(nodes) as integer) as worst from k group by c, h, n) w left join m on m.c = w.c and m.h = w.h and m.n = w.n""")
def cover_slack(spark, d):
    """Most nodes a range takes, against the bound: over all offsets, and over the days between a customer's orders."""
    shapes = ((2, 8), (3, 5), (10, 2))
    rows = [(c, h, n, worst, bound) for c, h in shapes for n, worst, bound in metrics.cover_statistics(c, h, range(1, c**h))]
    lengths = spark.createDataFrame(rows, "c int, h int, length int, worst int, bound int")
    o = table(spark, d, "orders").select("o_custkey", F.unix_date(F.to_date("o_orderdate")).cast("long").alias("r"))
    seen = o.select(F.lag("r").over(Window.partitionBy("o_custkey").orderBy("r")).alias("l"), "r").where("l < r").groupBy("l", "r").agg(F.count("*").alias("times"))
    l, r = F.col("l"), F.col("r")
    nodes = lambda c, h: r - l - (c - 1) * sum(F.greatest(F.lit(0).cast("long"), div_int(r, c**j) - ceil_int(l, c**j)) for j in range(1, h))
    each = F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.lit(h).alias("h"), nodes(c, h).alias("nodes")) for c, h in shapes]))
    most = seen.select((r - l).cast("int").alias("length"), "times", each.alias("x")).groupBy("x.c", "x.h", "length").agg(F.max("x.nodes").alias("most"), F.sum("times").alias("ranges"))
    none = F.lit(0).cast("long")
    return lengths.join(most, ["c", "h", "length"], "left").withColumns({"most": F.coalesce("most", none), "ranges": F.coalesce("ranges", none)})


@query(f"with e as (select i, {sql_laplace(2.0, 'mc', chr(39) + '0' + chr(39), 'i', 'j')} as e from range(30) a(i), range(200) b(j)) select cast(i as bigint) as idx, round(avg(e), 6) as bias, round(var_samp(e), 6) as var from e group by 1")
def bias_over_keys(spark, d):
    exact = release.dense(DAILY, linear.change(DAILY.assign(event_state(spark, d)), ERROR))
    return metrics.monte_carlo(exact, Noise("laplace", 0.5), 1, 1, 200, key("mc")).select("idx", (F.round("bias", 6) + 0.0).alias("bias"), F.round("var", 6).alias("var"))


@query(f"with {CL_STATE}, {daily_sql(SQL_ERROR)}, e as (select abs({sql_laplace(2.0, 'dl', chr(39) + '0' + chr(39), 'idx')}) as e, abs(exact) as x from b) select round(avg(e), 6) as mae, round(sqrt(avg(e * e)), 6) as rmse, round(max(e), 6) as max_err, round(sum(e) / sum(x), 6) as rel_err, round(sum(e), 6) as l1, round(sqrt(sum(e * e)), 6) as l2 from e")
def error_summary(spark, d):
    cl = event_state(spark, d)
    noisy = release.disjoint(cl, DAILY, ERROR, Noise("laplace", 0.5), key("dl"))
    exact = release.dense(DAILY, linear.change(DAILY.assign(cl), ERROR))
    out = metrics.errors(noisy.join(exact, "idx"))
    return out.select(*[F.round(c, 6).alias(c) for c in out.columns])


CLIPS = [5_000, 10_000, 20_000, 40_000]


@query("with v as (select cast(round(value * 100) as bigint) as v from events) select cast(c as bigint) as clip, cast(sum(greatest(v - c, 0)) as bigint) as lost, cast(sum(if(v > c, 1, 0)) as bigint) as clipped_rows from v, (values (5000), (10000), (20000), (40000)) as t(c) group by 1")
def truncation_loss(spark, d):
    rows = events(spark, d).select(F.round(F.col("value") * 100).cast("long").alias("v"))
    return metrics.truncation(rows, "v", CLIPS)


_SIDE = lambda name, where: f"select '{name}' as side, floor((x + {sql_laplace(2.0, 'nr' + name, chr(39) + '0' + chr(39), 'run')}) / 4) as bin from (select sum({SQL_ERROR}) as x from cl where {sql_idx(DAY)} between 0 and 29 {where}), range(4000) r(run)"


@query(f"""with {CL_STATE}, o as ({_SIDE('with', '')} union all {_SIDE('without', 'and entry <> 7')}), c as (select cast(bin as bigint) as bin, count(*) filter (where side = 'with') as a, count(*) filter (where side = 'without') as b from o group by 1)
select bin, a as n_with, b as n_without, round(ln(a * 1.0 / b), 6) as log_ratio, abs(ln(a * 1.0 / b)) <= 0.5 + 4 * sqrt(1.0 / a + 1.0 / b) as within from c where a >= 100 and b >= 100""")
def neighbour_output_ratio(spark, d):
    """Log ratios of answer frequencies on a changelog and on one without an entry, over 4,000 keys. All of an entry's mutations
    move the answer by one at most (they telescope), so the ratio stays below eps = 0.5, here with four standard errors of the
    sampled frequencies."""
    from ..functions.noise import laplace
    from ..operators.changelog import without_entry

    cl, out = event_state(spark, d), []
    for name, x in (("with", cl), ("without", without_entry(cl, 7))):
        exact = linear.change(DAILY.assign(x), ERROR, ()).crossJoin(spark.range(4000).select(F.col("id").alias("run")))  # one row times keys
        out.append(exact.select(F.lit(name).alias("side"), F.floor((F.col("exact") + laplace(2.0, key("nr" + name), "0", F.col("run"))) / 4).alias("bin")))
    c = out[0].unionByName(out[1]).groupBy("bin").agg(F.count_if(F.col("side") == "with").alias("a"), F.count_if(F.col("side") == "without").alias("b")).where("a >= 100 and b >= 100")
    ratio = F.log(F.col("a") / F.col("b"))
    return c.select("bin", F.col("a").alias("n_with"), F.col("b").alias("n_without"), F.round(ratio, 6).alias("log_ratio"), (F.abs(ratio) <= 0.5 + 4 * F.sqrt(1 / F.col("a") + 1 / F.col("b"))).alias("within"))


YEAR = 365 * DAY


@query(f"""with {CL_STATUS}, y as (select entry, count(distinct i) * 0.5 as paid from cl, range(4) r(i) where ts > {T1995} + i * {YEAR} and ts <= {T1995} + (i + 1) * {YEAR} group by 1),
c as (select if(r_name in ('AFRICA', 'AMERICA', 'ASIA'), 0.5, 0) as g, if(c_mktsegment = 'BUILDING', 0.5, 0) as s from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)
select 'disjoint times, one entry' as releases, 2.0::double as eps, cast(count(*) as bigint) as entries, cast(max(paid) as double) as paid from y
union all select 'regions kept for good', 0.5, count(*) filter (where g > 0), max(g) from c union all select 'regions and one segment', 1.0, count(*) filter (where g + s > 0), max(g + s) from c
union all select 'statuses that change', 1.0, count(distinct entry), max(if(before in ('F', 'O', 'P'), 0.5, 0) + if(after in ('F', 'O', 'P'), 0.5, 0)) from cl where before in ('F', 'O', 'P') or after in ('F', 'O', 'P')""")
def filtered_budgets(spark, d):
    """Budgets of releases by their filters, with the customers they hold and the most that one of these pays (one mutation, where
    statuses change): disjoint times don't help an entry that changes in all of them, fixed groups do."""
    one = A.Budget(0.5)
    years = [(Filter.time(T1995 + i * YEAR, T1995 + (i + 1) * YEAR), one) for i in range(4)]
    regions = [(Filter.among("r_name", [r], fixed=True), one) for r in ("AFRICA", "AMERICA", "ASIA")]
    segment = [(Filter.among("c_mktsegment", ["BUILDING"], fixed=True), one)]
    cl = customer_status(spark, d)
    nations = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    customers = table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("entry"), "r_name", "c_mktsegment")
    spent = lambda releases: sum(F.when(F.max(f.column()), b.eps).otherwise(0.0) for f, b in releases)
    in_status = lambda c: F.when(Filter.among(c, STATUSES).column(), one.eps).otherwise(0.0)
    by_status = cl.groupBy("entry").agg(F.max(in_status("before") + in_status("after")).alias("paid"))
    parts = [("disjoint times, one entry", filtered_budget(years), cl.groupBy("entry").agg(spent(years).alias("paid")))]
    parts += [(name, filtered_budget(x), customers.groupBy("entry").agg(spent(x).alias("paid"))) for name, x in (("regions kept for good", regions), ("regions and one segment", regions + segment))]
    parts.append(("statuses that change", by_group("status", STATUSES, one, fixed=False), by_status))
    rows = [p.where("paid > 0").agg(F.count("*").alias("entries"), F.max("paid").alias("paid")).select(F.lit(name).alias("releases"), F.lit(b.eps).alias("eps"), "entries", "paid") for name, b, p in parts]
    return rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3])


@query(f"with {CL_STATE} select * from cl where ts > {T0 + 2 * DAY} and ts <= {T0 + 9 * DAY} and after in ('click', 'error') and kind = 'update'")
def filter_composed(spark, d):
    """A time range and two sets of values, composed."""
    f = Filter.time(T0, T0 + 9 * DAY).and_(Filter.time(T0 + 2 * DAY, None)).and_(Filter.among("after", ["click", "error", "view"])).and_(Filter.among("after", ["error", "click"])).and_(Filter.among("kind", ["update"]))
    return f.apply(event_state(spark, d))
