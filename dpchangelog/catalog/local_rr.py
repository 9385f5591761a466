"""The local model, randomized responses, and baselines."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.intervals import DAY, IntervalGrid
from ..functions.noise import laplace_variance
from ..operators import baselines, changelog, linear, local, metrics, release, responses
from ..sources.tables import table
from .base import *
from .base import CL_STATE, CL_VALUE, sql_idx, sql_laplace, sql_u
from .log import NET
from .releases import ERROR, GRID, HOURLY, S14, SQL_ERROR, daily_sql

ENTRIES = "en as (select distinct user_id as entry from events)"


def entries(spark, d):
    return table(spark, d, "events").select(F.col("user_id").alias("entry")).distinct()


_TOUCHED = f"x as (select distinct entry, {sql_idx(DAY)} as i from cl where {sql_idx(DAY)} between 0 and 29), n as (select entry, count(*) as n from x group by 1)"


@query(f"with {CL_STATE}, {_TOUCHED}, top as (select entry as other from n order by n desc, entry limit 1) select p.entry as one, top.other, count(distinct x.i) as queries from n p cross join top join x on x.entry in (p.entry, top.other) group by 1, 2")
def local_touch_pairs(spark, d):
    """Queries that each entry and the most-touching one touch between them."""
    touched = metrics.touched_disjoint(event_state(spark, d), DAILY)
    return local.touch_pairs(touched, local.most_touching(touched))


@query(f"with {CL_STATE}, {_TOUCHED}, t as (select n from n order by n desc limit 2) select max(n) as most, cast(sum(n) - max(n) as bigint) as second, cast(sum(n) as bigint) as bound from t")
def local_touch_supremum(spark, d):
    """A bound over all pairs of entries, beside which the formula's twice the one-sided folds stands."""
    return local.touch_supremum(metrics.touched_disjoint(event_state(spark, d), DAILY))


@query(f"""with {CL_STATE}, {ENTRIES}, c as (select entry, {sql_idx(DAY)} as idx, list_sort(list({{'t': ts, 'b': before, 'a': after}})) as m from cl where {sql_idx(DAY)} between 0 and 29 group by 1, 2),
g as (select en.entry, i as idx from en, range(30) r(i)) select g.entry, cast(count(*) filter (where x.m is distinct from y.m) as bigint) as queries from g left join c x on x.entry = g.entry and x.idx = g.idx left join c y on y.entry = 5 and y.idx = g.idx group by 1""")
def local_separating_queries(spark, d):
    """How many days tell each entry from entry 5: those on which their mutations differ."""
    return local.separations(event_state(spark, d), entries(spark, d), DAILY, 5)


@query(f"with {CL_STATE}, {ENTRIES}, {GRID}, s as (select entry, {sql_idx(DAY)} as idx, sum({SQL_ERROR}) as x from cl group by 1, 2), r as (select g.idx, coalesce(x, 0) + {sql_laplace(4.0, 'll', chr(39) + '0' + chr(39), 'g.idx', 'en.entry')} as r from en cross join g left join s on s.entry = en.entry and s.idx = g.idx) select idx, round(sum(r), 6) as estimate, count(*) * 32.0::double as var from r group by 1")
def local_linear_change_daily(spark, d):
    out = local.linear_change(event_state(spark, d), entries(spark, d), DAILY, ERROR, 0.5, key("ll"))
    return out.withColumn("estimate", F.round("estimate", 6) + 0.0)


_LOCAL_NODES = f"""b as (select entry, {sql_idx(DAY)} as i, sum({SQL_ERROR}) as x from cl where {sql_idx(DAY)} between 0 and 29 group by 1, 2), s as (select entry, cast(j as integer) as layer, i // cast(pow(2, j) as bigint) as idx, sum(x) as x from b, range(3) l(j) group by 1, 2, 3),
nd as (select cast(j as integer) as layer, cast(i as bigint) as idx from range(3) l(j), range(30) r(i) where i < ceil(30 / pow(2, j)))"""


@query(f"with {CL_STATE}, {ENTRIES}, {_LOCAL_NODES}, r as (select nd.layer, nd.idx, coalesce(x, 0) + {sql_laplace(4.0, 'lt', 'nd.layer', 'nd.idx', 'en.entry')} as r from en cross join nd left join s on s.entry = en.entry and s.layer = nd.layer and s.idx = nd.idx) select layer, idx, round(sum(r), 6) as noisy, count(*) * 32.0::double as sigma2 from r group by 1, 2")
def local_tree_daily(spark, d):
    """A tree of local reports: every entry answers at every node, with noise of its own."""
    out = local.tree(event_state(spark, d), entries(spark, d), DAILY, 2, 3, ERROR, 0.5, key("lt"))
    return out.withColumn("noisy", F.round("noisy", 6) + 0.0)


@query(f"""with {CL_STATE}, {ENTRIES}, w as (select cast(i as bigint) as idx from range({S14.n}) r(i)), s as (select w.idx, entry, sum({SQL_ERROR}) as x from w join cl on ts > {S14.t1 - S14.w} + idx * {S14.p} and ts <= {S14.t1} + idx * {S14.p} group by 1, 2),
r as (select w.idx, coalesce(x, 0) + {sql_laplace(4.0, 'ls', chr(39) + '0' + chr(39), 'w.idx', 'en.entry')} as r from en cross join w left join s on s.entry = en.entry and s.idx = w.idx) select idx, round(sum(r), 6) as estimate, count(*) * 32.0::double as var from r group by 1""")
def local_sliding_windows(spark, d):
    """Sliding windows of local reports."""
    out = local.sliding(event_state(spark, d), entries(spark, d), S14, ERROR, 0.5, key("ls"))
    return out.withColumn("estimate", F.round("estimate", 6) + 0.0)


@query(f"""with {CL_STATE}, {ENTRIES}, {GRID}, s as (select entry, {sql_idx(DAY)} as idx, sum({SQL_ERROR}) as x from cl group by 1, 2), k as (select (exp(1.0) + 1) / (exp(1.0) - 1) as b),
r as (select g.idx, if({sql_u('lb', chr(39) + '0' + chr(39), 'g.idx', 'en.entry')} < 0.5 + coalesce(x, 0) / (2 * b), b, -b) as r, b from en cross join g cross join k left join s on s.entry = en.entry and s.idx = g.idx) select idx, round(sum(r), 6) as estimate, round(count(*) * any_value(b * b), 6) as var from r group by 1""")
def local_one_bit_daily(spark, d):
    """The local release with another randomizer: one bit an entry and day."""
    out = local.linear_change(event_state(spark, d), entries(spark, d), DAILY, ERROR, 1.0, key("lb"), local.sign_reports(ERROR, 1.0))
    return out.select("idx", (F.round("estimate", 6) + 0.0).alias("estimate"), F.round("var", 6).alias("var"))


# Randomized responses.
def sql_respond(code: str, z: int, eps: float, rel: str, *parts: str) -> str:
    keep = f"((exp({float(eps)}) - 1) / ({z} - 1 + exp({float(eps)})))"  # p - q
    return f"(case when {code} is not null and {sql_u(rel, *parts)} < {keep} then {code} else cast(floor({sql_u(rel, *parts, salt='b')} * {z}) as integer) end)"


def sql_code(c: str, symbols: list) -> str:
    return f"(nullif(coalesce(list_position({symbols!r}, {c}), 0), 0) - 1)"


@query("select cast(z as integer) as z, e as eps, round(exp(e) / (z - 1 + exp(e)), 9) as p, round(1 / (z - 1 + exp(e)), 9) as q from (values (2), (3), (5), (10), (36)) a(z), (values (0.5::double), (1.0), (2.0)) b(e)")
def rr_matrix(spark, d):
    rows = [(z, e, *(round(x, 9) for x in responses.optimal_matrix(z, e))) for z in (2, 3, 5, 10, 36) for e in (0.5, 1.0, 2.0)]
    return spark.createDataFrame(rows, "z int, eps double, p double, q double")


def _static_sql(tab, entry, col, symbols, eps, rel):
    z = len(symbols)
    return f"o as (select {sql_respond(sql_code(col, symbols), z, eps, rel, entry)} as out_code from {tab}), c as (select cast(i as integer) as out_code, count(o.out_code) as n from range({z}) r(i) left join o on o.out_code = i group by 1)"


def _estimate_sql(symbols, eps):
    base = f"({len(symbols)} - 1 + exp({float(eps)}))"  # q is one over it
    return f"select {symbols!r}[out_code + 1] as symbol, round((n - sum(n) over () / {base}) / ((exp({float(eps)}) - 1) / {base}), 6) as estimate from c"


@query(f"with {_static_sql('customer', 'c_custkey', 'c_mktsegment', SEGMENTS, 1.0, 'rs')} select * from c")
def rr_static_counts(spark, d):
    return responses.static_counts(table(spark, d, "customer"), "c_custkey", "c_mktsegment", SEGMENTS, 1.0, key("rs"))


def _rounded(df):
    return df.withColumn("estimate", F.round("estimate", 6) + 0.0)


@query(f"with {_static_sql('customer', 'c_custkey', 'c_mktsegment', SEGMENTS, 1.0, 'rs')} {_estimate_sql(SEGMENTS, 1.0)}")
def rr_static_estimate(spark, d):
    return _rounded(responses.estimate_histogram(rr_static_counts(spark, d), SEGMENTS, 1.0))


@query(f"with {_static_sql('documents', 'doc_id', 'lang', LANGS, 1.0, 'rd')} {_estimate_sql(LANGS, 1.0)}")
def rr_documents_lang(spark, d):
    return _rounded(responses.estimate_histogram(responses.static_counts(table(spark, d, "documents"), "doc_id", "lang", LANGS, 1.0, key("rd")), LANGS, 1.0))


DIGITS = [str(i) for i in range(10)]


@query(f"with {_static_sql('embeddings', 'vec_id', 'cast(label as varchar)', DIGITS, 2.0, 're')} {_estimate_sql(DIGITS, 2.0)}")
def rr_embedding_label(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("label").cast("string").alias("label"))
    return _rounded(responses.estimate_histogram(responses.static_counts(e, "vec_id", "label", DIGITS, 2.0, key("re")), DIGITS, 2.0))


EPS, Z = 2.0, 5
_B, _A = sql_code("before", EVENT_TYPES), sql_code("after", EVENT_TYPES)


def _net_sql(width=DAY, n=30):
    """d as (entry, idx, b, a) for every entry and interval, codes or null."""
    return f"""net as (select entry, idx, nullif(before, '~') as before, nullif(after, '~') as after from (select entry, {sql_idx(width)} as idx, arg_min(before, (ts, seq)) as before, arg_max(after, (ts, seq)) as after from (select entry, ts, seq, coalesce(before, '~') as before, coalesce(after, '~') as after from cl) group by 1, 2) where before <> after),
    {ENTRIES}, d as (select en.entry, cast(i as bigint) as idx, {_B} as b, {_A} as a from en cross join range({n}) r(i) left join net on net.entry = en.entry and net.idx = i)"""


_FULL = f"(coalesce(b + 1, 0) * {Z + 1} + coalesce(a + 1, 0))"
_COMPACT = f"(case when coalesce(a + 1, 0) = coalesce(b + 1, 0) then 0 else 1 + coalesce(b + 1, 0) * {Z} + coalesce(a + 1, 0) - if(coalesce(a + 1, 0) > coalesce(b + 1, 0), 1, 0) end)"


def _counts_sql(code=_FULL, z2=(Z + 1) ** 2, rel="rm", width=DAY, n=30):
    return f"{_net_sql(width, n)}, o as (select idx, cast({sql_respond(code, z2, EPS, rel, 'entry', 'idx')} as integer) as out_code from d), c as (select idx, out_code, count(*) as n from o group by 1, 2)"


#: What each answer code says: (code, before, after), 0 for null; written out here, not taken from the library.
_PAIRS_FULL = f"pairs as (select b * {Z + 1} + a as out_code, b, a from range({Z + 1}) x(b), range({Z + 1}) y(a))"
_PAIRS_COMPACT = f"pairs as (select row_number() over (order by b, a) as out_code, b, a from range({Z + 1}) x(b), range({Z + 1}) y(a) where a <> b)"
_GAP36 = f"((exp({EPS}) - 1) / (35 + exp({EPS})))"


def _change_sql(compact=False, by="idx"):
    """e: estimates from c. Answers that end in a symbol less answers that start there, over p - q."""
    size = Z * Z + Z + 1 if compact else (Z + 1) ** 2
    return f"""{_PAIRS_COMPACT if compact else _PAIRS_FULL}, sy as (select unnest({EVENT_TYPES!r}) as symbol, unnest(range(1, {Z + 1})) as code),
    e as (select {by}, symbol, sum(if(a = code, n, 0) - if(b = code, n, 0)) / ((exp({EPS}) - 1) / ({size} - 1 + exp({EPS}))) as estimate from c cross join sy left join pairs using (out_code) group by {by}, symbol)"""


@query(f"with {CL_STATE}, {_counts_sql()} select * from c")
def rr_mutation_counts(spark, d):
    return responses.mutation_counts(event_state(spark, d), entries(spark, d), DAILY, EVENT_TYPES, EPS, key("rm"))


@query(f"with {CL_STATE}, {_counts_sql()}, {_change_sql()} select idx, symbol, round(estimate, 6) as estimate from e")
def rr_mutation_estimate(spark, d):
    return _rounded(responses.estimate_change(rr_mutation_counts(spark, d), EVENT_TYPES, EPS))


@query(f"with {CL_STATE}, {_counts_sql(_COMPACT, Z * Z + Z + 1, 'rc')}, {_change_sql(True)} select idx, symbol, round(estimate, 6) as estimate from e")
def rr_compact_alphabet(spark, d):
    c = responses.mutation_counts(event_state(spark, d), entries(spark, d), DAILY, EVENT_TYPES, EPS, key("rc"), compact=True)
    return _rounded(responses.estimate_change(c, EVENT_TYPES, EPS, compact=True))


@query(f"with {CL_STATE}, {_counts_sql()}, {_change_sql()} select idx, symbol, round(sum(estimate) over (partition by symbol order by idx), 6) as estimate from e")
def rr_running_histogram(spark, d):
    return _rounded(responses.continual_histogram(responses.estimate_change(rr_mutation_counts(spark, d), EVENT_TYPES, EPS)))


_TREE_COUNTS = f"""ld as (select cast(j as integer) as layer, cast(pow(2, j) as bigint) as w from range(3) l(j)),
net as (select entry, layer, idx, nullif(before, '~') as before, nullif(after, '~') as after from (select entry, layer, {sql_idx(DAY)} // w as idx, arg_min(coalesce(before, '~'), (ts, seq)) as before, arg_max(coalesce(after, '~'), (ts, seq)) as after from cl, ld where {sql_idx(DAY)} between 0 and 29 group by 1, 2, 3) where before <> after),
{ENTRIES}, nd as (select layer, cast(i as bigint) as idx from ld, range(30) r(i) where i * w < 30), d as (select en.entry, nd.layer, nd.idx, {_B} as b, {_A} as a from en cross join nd left join net on net.entry = en.entry and net.layer = nd.layer and net.idx = nd.idx),
c as (select layer, idx, out_code, count(*) as n from (select layer, idx, cast({sql_respond(_FULL, 36, EPS, 'rt', 'layer', 'entry', 'idx')} as integer) as out_code from d) group by 1, 2, 3)"""
#: Most that one report adds to a variance: a report whose pair touches the symbol.
_WORST = f"((2 * {Z} / (35 + exp({EPS})) + {_GAP36} - {_GAP36} * {_GAP36}) / ({_GAP36} * {_GAP36}))"
_TREE_NODES = f"{_TREE_COUNTS}, {_change_sql(by='layer, idx')}, nn as (select layer, idx, sum(n) as reports from c group by 1, 2), nodes as (select layer, idx, symbol, estimate, reports * {_WORST} as var from e join nn using (layer, idx))"


def _response_tree(spark, d):
    return responses.tree_reports(event_state(spark, d), entries(spark, d), DAILY, EVENT_TYPES, 2, 3, EPS, key("rt"))


@query(f"with {CL_STATE}, {_TREE_NODES} select layer, idx, symbol, round(estimate, 6) as estimate, round(var, 4) as var from nodes")
def rr_tree_nodes(spark, d):
    return _rounded(_response_tree(spark, d)).withColumn("var", F.round("var", 4))


@query(f"""with {CL_STATE}, {_TREE_NODES} select cast(r.i as bigint) as idx, symbol, round(sum(estimate), 6) as estimate, count(*) as n_nodes, round(sum(var), 4) as var from range(30) r(i) join nodes t on (t.idx + 1) * pow(2, layer) <= r.i + 1
  and (layer = 2 or (t.idx // 2 + 1) * pow(2, layer + 1) > r.i + 1) group by 1, 2""")
def rr_prefix_from_tree(spark, d):
    """The histogram after every day from the nodes of a response tree: few surveys each, where running sums add up all days."""
    return _rounded(responses.prefix_histogram(_response_tree(spark, d), 30, 2, 3)).withColumn("var", F.round("var", 4))


@query(f"""with {CL_STATE}, {_net_sql()}, t as (select d.idx, s.symbol, count(*) as n, sum(if((b is not null and {EVENT_TYPES!r}[b + 1] = symbol) <> (a is not null and {EVENT_TYPES!r}[a + 1] = symbol), 1, 0)) as k from d, (select unnest({EVENT_TYPES!r}) as symbol) s group by 1, 2)
select idx, symbol, round((n * 2 * {Z} / (35 + exp({EPS})) + k * ({_GAP36} - {_GAP36} * {_GAP36})) / ({_GAP36} * {_GAP36}), 6) as var from t""")
def rr_variance_exact(spark, d):
    """Exact variance of each day's estimate: from the number of entries and of those whose pair touches the symbol."""
    dense = responses.dense_pairs(event_state(spark, d), entries(spark, d), DAILY, EVENT_TYPES)
    p, q = responses.optimal_matrix(36, EPS)
    gap = p - q
    touch = [F.sum((F.coalesce(F.col("b") == i, F.lit(False)) != F.coalesce(F.col("a") == i, F.lit(False))).cast("long")).alias(f"k{i}") for i in range(Z)]
    sums = dense.groupBy("idx").agg(F.count("*").alias("n"), *touch)
    rows = F.array(*[F.struct(F.lit(s).alias("symbol"), ((F.col("n") * (2 * Z * q) + F.col(f"k{i}") * (gap - gap * gap)) / gap**2).alias("var")) for i, s in enumerate(EVENT_TYPES)])
    return sums.select("idx", F.explode(rows).alias("r")).select("idx", "r.symbol", F.round("r.var", 6).alias("var"))


_M = f"{_PAIRS_FULL}, m as (select symbol, out_code, if(a = code, 1, 0) - if(b = code, 1, 0) as v from pairs, (select unnest({EVENT_TYPES!r}) as symbol, unnest(range(1, {Z + 1})) as code))"


@query(f"""with {CL_STATE}, {_counts_sql()}, {_M}, s as (select c.idx, x.symbol as one, y.symbol as other, sum(x.v * n) as a, sum(y.v * n) as b, sum(x.v * y.v * n) as ab, sum(n) as total from c join m x using (out_code) join m y using (out_code) group by 1, 2, 3)
select idx, one, other, round((ab - a * 1.0 * b / total) / ({_GAP36} * {_GAP36}), 6) as cov from s""")
def rr_covariance_plugin(spark, d):
    """The whole plug-in covariance of each day's estimates, from answer counts alone."""
    return metrics.plug_in_covariance(rr_mutation_counts(spark, d), EVENT_TYPES, EPS).withColumn("cov", F.round("cov", 6) + 0.0)


@query(f"""with {CL_STATE}, {_counts_sql()}, {_M}, s as (select c.idx, symbol, sum(v * n) as a, sum(v * v * n) as b from c join m using (out_code) group by 1, 2), t as (select idx, sum(n) as total from c group by 1)
select s.idx, symbol, round((b - a * a * 1.0 / total) / ({_GAP36} * {_GAP36}), 6) as var from s join t using (idx)""")
def rr_variance_plugin(spark, d):
    """Diagonal of the plug-in covariance."""
    out = metrics.plug_in_covariance(rr_mutation_counts(spark, d), EVENT_TYPES, EPS)
    return out.where("one = other").select("idx", F.col("one").alias("symbol"), F.round("cov", 6).alias("var"))


BIAS_RUNS = 20


@query(f"""with {CL_STATE}, {_net_sql()}, runs as (select cast(i as bigint) as run from range({BIAS_RUNS}) r(i)), c as (select idx, run, out_code, count(*) as n from (select idx, run, cast({sql_respond(_FULL, 36, EPS, 'rb', 'entry', 'idx', 'run')} as integer) as out_code from d, runs) group by 1, 2, 3),
{_change_sql(by='idx, run')}, x as (select idx, symbol, sum(if(a.a = code - 1, 1, 0) - if(a.b = code - 1, 1, 0)) as exact from d a cross join sy group by 1, 2)
select symbol, round(avg(estimate - exact), 6) as bias, round(sqrt(var_samp(estimate - exact) / count(*)), 6) as standard_error, count(*) as n from e join x using (idx, symbol) group by 1""")
def rr_bias_over_keys(spark, d):
    """Estimated less true change of each symbol, over all days and many keys: no more than a few standard errors from 0."""
    pairs = responses.dense_pairs(event_state(spark, d), entries(spark, d), DAILY, EVENT_TYPES)
    truth = F.array(*[F.struct(F.lit(s).alias("symbol"), ((F.coalesce(F.col("a") == i, F.lit(False))).cast("long") - (F.coalesce(F.col("b") == i, F.lit(False))).cast("long")).alias("v")) for i, s in enumerate(EVENT_TYPES)])
    exact = pairs.select("idx", F.explode(truth).alias("t")).groupBy("idx", "t.symbol").agg(F.sum("t.v").alias("exact"))
    runs = pairs.withColumn("run", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(BIAS_RUNS - 1).cast("long"))))
    code = responses.pair_code(F.col("b"), F.col("a"), Z)
    counts = runs.select("idx", "run", responses.respond(code, 36, EPS, key("rb"), F.col("entry"), F.col("idx"), F.col("run")).alias("out_code")).groupBy("idx", "run", "out_code").agg(F.count("*").alias("n"))
    error = responses.estimate_change(counts, EVENT_TYPES, EPS, by=("idx", "run")).join(exact, ["idx", "symbol"]).select("symbol", (F.col("estimate") - F.col("exact")).alias("e"))
    return error.groupBy("symbol").agg((F.round(F.avg("e"), 6) + 0.0).alias("bias"), F.round(F.sqrt(F.var_samp("e") / F.count("*")), 6).alias("standard_error"), F.count("*").alias("n"))


FEW = ["BUILDING", "FURNITURE", "MACHINERY"]


@query(f"with {_static_sql('customer', 'c_custkey', 'c_mktsegment', FEW, 1.0, 'rf')} select out_code, n, (select count(*) from customer) as rows, cast(sum(n) over () as bigint) as answers from c")
def rr_foreign_values(spark, d):
    """Two segments are outside the alphabet: their rows answer at random, so answers add up to rows."""
    c = table(spark, d, "customer")
    counts = responses.static_counts(c, "c_custkey", "c_mktsegment", FEW, 1.0, key("rf"))
    total = counts.agg(F.sum("n").alias("answers"))
    return counts.crossJoin(c.agg(F.count("*").alias("rows"))).crossJoin(total).select("out_code", "n", "rows", "answers")  # one row each


#: Columns are truths F, O, P; each adds up to 1.
GENERAL = [[0.6, 0.2, 0.1], [0.3, 0.6, 0.2], [0.1, 0.2, 0.7]]


@query(f"""with r as (select list_position({STATUSES!r}, o_orderstatus) as t, {sql_u('rg', 'o_orderkey')} as u from orders), o as (select case t when 1 then if(u < 0.6, 0, if(u < 0.9, 1, 2)) when 2 then if(u < 0.2, 0, if(u < 0.8, 1, 2)) else if(u < 0.1, 0, if(u < 0.3, 1, 2)) end as c from r),
n as (select count(*) filter (where c = 0) as x, count(*) filter (where c = 1) as y, count(*) filter (where c = 2) as z from o), det as (select 0.6 * (0.6 * 0.7 - 0.2 * 0.2) - 0.2 * (0.3 * 0.7 - 0.2 * 0.1) + 0.1 * (0.3 * 0.2 - 0.6 * 0.1) as d),
i as (select 'F' as symbol, ((0.6 * 0.7 - 0.2 * 0.2) * x - (0.2 * 0.7 - 0.1 * 0.2) * y + (0.2 * 0.2 - 0.1 * 0.6) * z) / d as e from n, det union all select 'O', (-(0.3 * 0.7 - 0.2 * 0.1) * x + (0.6 * 0.7 - 0.1 * 0.1) * y - (0.6 * 0.2 - 0.1 * 0.3) * z) / d from n, det union all select 'P', ((0.3 * 0.2 - 0.6 * 0.1) * x - (0.6 * 0.2 - 0.2 * 0.1) * y + (0.6 * 0.6 - 0.2 * 0.3) * z) / d from n, det)
select symbol, round(cast(e as double), 5) as estimate, round(ln(greatest(0.6 / 0.1, 0.6 / 0.2, 0.7 / 0.1)), 6) as eps from i""")
def rr_general_matrix(spark, d):
    """A matrix other than the optimal one: its eps, and an estimate by its inverse."""
    m = responses.ResponseMatrix(GENERAL)
    o = table(spark, d, "orders")
    out = o.select(m.respond(responses.code_of("o_orderstatus", STATUSES), key("rg"), F.col("o_orderkey")).alias("c")).groupBy("c").count()
    n = {r.c: r["count"] for r in out.collect()}  # three counts
    est = m.estimate([n.get(i, 0) for i in range(3)])
    return spark.createDataFrame([(s, float(round(x, 5)) + 0.0, float(round(m.epsilon(), 6))) for s, x in zip(STATUSES, est, strict=True)], "symbol string, estimate double, eps double")


# Baselines.
@query(f"""with {CL_STATE}, {GRID}, en as (select distinct entry from cl), st as (select g.idx, (select arg_max(c.after, (c.ts, c.seq)) from cl c where c.entry = en.entry and c.ts <= {T0} + (g.idx + 1) * {DAY}) as v from g, en)
select idx, round(sum(if(v = 'error', 1, 0)) + {sql_laplace(60.0, 'b4', chr(39) + '0' + chr(39), 'idx')}, 6) as noisy, round(0.5 / 30, 9) as eps, 7200.0::double as sigma2 from st group by 1""")
def base_resnapshot(spark, d):
    out = baselines.resnapshot_series(event_state(spark, d), DAILY, ERROR, 0.5, key("b4"))
    return out.withColumns({"noisy": F.round("noisy", 6) + 0.0, "eps": F.round("eps", 9)})


@query(f"""with {CL_STATE}, {daily_sql(SQL_ERROR)}, n as (select idx, exact, exact + {sql_laplace(2.0, 'dl', chr(39) + '0' + chr(39), 'idx')} as noisy from b)
select idx, cast(sum(exact) over w as bigint) as exact, round(sum(noisy) over w, 6) as total, (idx + 1) * {laplace_variance(2.0)}::double as var from n window w as (order by idx)""")
def base_running_sum_variance(spark, d):
    """The running sum of noisy daily changes beside the true one, with its variance, which grows in proportion."""
    from .releases import running_total_noisy

    w = Window.orderBy("idx")  # over intervals
    exact = release.dense(DAILY, linear.change(DAILY.assign(event_state(spark, d)), ERROR)).select("idx", F.sum("exact").over(w).alias("exact"))
    return exact.join(running_total_noisy(spark, d), "idx").select("idx", "exact", "total", "var")


@query(f"""with s as (select {sql_idx(3_600_000_000, ts='epoch_us(ts)')} as i, count(*) as x from events group by 1), t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact from range(720) r(i) cross join range(10) l(j) left join s on s.i = r.i group by 1, 2)
select layer, idx, round(exact + {sql_laplace(10.0, 'b6', 'layer', 'idx')}, 6) as noisy, 0.1::double as eps, 200.0::double as sigma2 from t""")
def base_event_level_tree(spark, d):
    e = events(spark, d).select("event_id", "us")
    out = baselines.event_level_tree(e, "us", "event_id", HOURLY, 2, 10, 0.1, key("b6"))
    return out.withColumn("noisy", F.round("noisy", 6) + 0.0)


@query(f"""with {CL_STATE}, kk as (select * exclude n from (select *, row_number() over (partition by entry order by ts, seq) as n from cl) where n <= 8), s as (select {sql_idx(3_600_000_000)} as i, sum({SQL_ERROR}) as x from kk group by 1),
t as (select cast(j as integer) as layer, cast(r.i // cast(pow(2, j) as bigint) as bigint) as idx, cast(sum(coalesce(x, 0)) as bigint) as exact from range(720) r(i) cross join range(10) l(j) left join s on s.i = r.i group by 1, 2)
select layer, idx, round(exact + {sql_laplace(20.0, 'b9', 'layer', 'idx')}, 6) as noisy, 0.05::double as eps, 800.0::double as sigma2 from t""")
def base_bounded_user_tree(spark, d):
    out = baselines.bounded_user_tree(event_state(spark, d), 8, HOURLY, 2, 10, ERROR, 4.0, key("b9"))
    return out.withColumn("noisy", F.round("noisy", 6) + 0.0)


@query(f"with {CL_VALUE}, x as (select * from cl where {sql_idx(DAY)} between 0 and 29) select cast(c as bigint) as clip, cast(sum(coalesce(after, 0) - coalesce(before, 0)) - sum(least(coalesce(after, 0), c) - least(coalesce(before, 0), c)) as bigint) as bias, 8.0 * c * c as sigma2 from x, (values (5000), (10000), (20000), (40000)) as t(c) group by c")
def base_truncation_sweep(spark, d):
    return baselines.truncation_sweep(event_value(spark, d), DAILY, [5_000, 10_000, 20_000, 40_000], 0.5)


@query(f"""with s as (select {sql_idx(DAY, ts='epoch_us(ts)')} as idx, count(*) as n from events group by 1), t as (select idx, cast(sum(n) over (order by idx) as bigint) as total from s), u as (select *, cast(floor(log2(total)) as integer) as step from t),
f as (select step, arg_min(total, idx) as total, min(idx) as idx from u group by 1) select idx, step, round(total + {sql_laplace('1 / (0.5 * pow(0.9, step))', 'bg', chr(39) + '0' + chr(39), 'step')}, 6) as noisy, round(0.5 * pow(0.9, step), 9) as eps from f""")
def base_growing_budget(spark, d):
    daily = DAILY.assign(events(spark, d), "us").groupBy("idx").agg(F.count("*").alias("n"))
    out = baselines.growing_budget(daily, 0.5, 0.9, key("bg"))
    return out.withColumns({"noisy": F.round("noisy", 6) + 0.0, "eps": F.round("eps", 9)})


@query(f"with s as (select {sql_idx(DAY, ts='epoch_us(ts)')} as idx, count(*) as n from events group by 1), {GRID} select g.idx, round(coalesce(n, 0) + {sql_laplace(2.0, 'bb', chr(39) + '0' + chr(39), 'g.idx')}, 6) as noisy, 0.5::double as eps, 8.0::double as sigma2 from g left join s on s.idx = g.idx")
def base_block_budget(spark, d):
    out = baselines.block_budget(events(spark, d), DAILY, "us", 0.5, key("bb"))
    return out.withColumn("noisy", F.round("noisy", 6) + 0.0)


STATES = f"{GRID}, en as (select distinct entry from cl), st as (select entry, idx, value from (select en.entry, g.idx, (select arg_max(c.after, (c.ts, c.seq)) from cl c where c.entry = en.entry and c.ts <= {T0} + (g.idx + 1) * {DAY}) as value from g, en) where value is not null)"


def states(spark, d):
    return changelog.states_at(event_state(spark, d), DAILY).where("value is not null")


_MEMO = f"m as (select entry, idx, value, cast({sql_respond(sql_code('value', EVENT_TYPES), 5, 1.0, 'bm', 'entry', 'value')} as integer) as out_code from st)"


@query(f"with {CL_STATE}, {STATES}, {_MEMO} select * from m")
def base_memoised_local(spark, d):
    return baselines.memoised_local(states(spark, d), EVENT_TYPES, 1.0, key("bm"))


@query(f"with {CL_STATE}, {STATES}, {_MEMO}, p as (select value, out_code, lag(value) over w as v, lag(out_code) over w as o from m window w as (partition by entry order by idx)) select count(*) as changes, cast(sum(if(o <> out_code, 1, 0)) as bigint) as seen from p where v is not null and v <> value")
def base_memo_leak(spark, d):
    return baselines.memo_leak(base_memoised_local(spark, d))


_VOTES = f"""vt as (select d.idx, sum(if({sql_u('bv', 'd.entry', 'd.idx', salt='v')} < exp(1.0) / (1 + exp(1.0)), if(net.entry is null, 0, 1), if(net.entry is null, 1, 0))) as s, count(*) as n from d left join net on net.entry = d.entry and net.idx = d.idx group by 1),
vo as (select idx, (s - n / (1 + exp(1.0))) / ((exp(1.0) - 1) / (1 + exp(1.0))) as votes, n from vt)"""


@query(f"with {CL_STATE}, {_net_sql()}, {_VOTES} select idx, round(votes, 6) as votes, votes / n >= 0.5 as update from vo")
def base_local_vote(spark, d):
    return baselines.local_vote(event_state(spark, d), entries(spark, d), DAILY, 1.0, 0.5, key("bv")).withColumn("votes", F.round("votes", 6) + 0.0)


def _repeated_sql(rel: str, where: str = "true") -> str:
    """rr: (idx, symbol, estimate) of a fresh survey every interval, of the states st."""
    base = "(4 + exp(1.0))"
    return f"""sm as (select idx, cast({sql_respond(sql_code('value', EVENT_TYPES), 5, 1.0, rel, 'entry', 'idx')} as integer) as c from st where {where}), sn as (select idx, count(*) as n from sm group by 1),
    rr as (select sn.idx, s.symbol, (sum(if({EVENT_TYPES!r}[c + 1] = s.symbol, 1, 0)) - any_value(sn.n) / {base}) / ((exp(1.0) - 1) / {base}) as estimate from sn join sm using (idx), (select unnest({EVENT_TYPES!r}) as symbol) s group by 1, 2)"""


@query(f"with {CL_STATE}, {STATES}, {_repeated_sql('br')} select idx, symbol, round(estimate, 6) as estimate from rr")
def base_repeated_rr(spark, d):
    return _rounded(baselines.repeated_static(states(spark, d), EVENT_TYPES, 1.0, key("br")))


@query(f"""with {CL_STATE}, {_net_sql().replace('en as (', 'en0 as (').replace('from en cross', 'from en0 en cross')}, {STATES}, {_VOTES}, up as (select idx, votes / n >= 0.5 or idx = 0 as renewed from vo), {_repeated_sql('bv', 'idx in (select idx from up where renewed)')},
h as (select up.idx, s.symbol, renewed, estimate from up cross join (select unnest({EVENT_TYPES!r}) as symbol) s left join rr on rr.idx = up.idx and rr.symbol = s.symbol)
select idx, symbol, round(last_value(estimate ignore nulls) over (partition by symbol order by idx), 6) as estimate, renewed from h""")
def base_voted_histogram(spark, d):
    """A histogram that is renewed where entries vote for it, and carried on in between."""
    out = baselines.voted_histogram(event_state(spark, d), entries(spark, d), states(spark, d), DAILY, EVENT_TYPES, 1.0, 1.0, 0.5, key("bv"))
    return _rounded(out)


@query(f"""with {CL_STATE}, t as (select entry, count(distinct {sql_idx(DAY)}) as n from cl where {sql_idx(DAY)} between 0 and 29 group by 1) select cast(m as bigint) as intervals, m * 0.5::double as eps, (select max(n) from t) as touched from (values (30), (365), (10000)) v(m)""")
def base_unconstrained(spark, d):
    """Without a limit an entry may touch every query: the budget grows with their number. touched: the most days that any touches."""
    from ..plans.accounting import Budget

    most = metrics.touch_counts(metrics.touched_disjoint(event_state(spark, d), DAILY)).agg(F.max("touched").alias("touched"))
    rows = [(n, baselines.unconstrained_budget(n, Budget(0.5)).eps) for n in (30, 365, 10_000)]
    return spark.createDataFrame(rows, "intervals long, eps double").crossJoin(most)  # one row


@query(f"""with {CL_STATE}, n as (select entry, max(abs(x)) as v from (select entry, count(*) as x from cl group by 1) group by 1), c as (select cast(least(5, (v > 20)::int + (v > 40)::int + (v > 60)::int + (v > 80)::int + (v > 100)::int) as integer) as cell, count(*) as n from n group by 1),
x as (select cast(i as integer) as cell, coalesce(n, 0) + {sql_laplace(2.0, 'cc', 'i')} as x from range(6) r(i) left join c on c.cell = r.i), y as (select cell, sum(x) over (order by cell) as noisy, sum(x) over () as al from x), f as (select least(4, coalesce(min(cell) filter (where noisy >= 0.9 * al), 4)) as first from y)
select [20.0, 40, 60, 80, 100][cell + 1]::double as clip, round(noisy, 6) as noisy, cell = first as chosen from y, f where cell < 5""")
def clip_choice_private(spark, d):
    """A bound on mutations an entry from a noisy histogram over a public grid."""
    from ..operators import constraints

    counts = constraints.counts(event_state(spark, d))
    out = linear.choose_clip_private(counts, "mutations", [20, 40, 60, 80, 100], 0.9, 0.5, key("cc"))
    return out.withColumn("noisy", F.round("noisy", 6) + 0.0)
