"""Alternatives that the methods are compared with. Each returns the release schema of what it stands against."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid
from ..functions.noise import Key, Noise, laplace, laplace_variance, uniform
from ..plans.accounting import Budget, fold
from . import changelog, constraints, linear, responses
from .hierarchy import hierarchy
from .local import dense_rows, interval_keys
from .release import dense, published


def unconstrained_budget(n: int, b: Budget) -> Budget:
    """An entry that changes in every interval touches every query."""
    return fold(n, b)


def resnapshot_series(cl: DataFrame, grid: IntervalGrid, query: linear.LinearQuery, total_eps: float, key: Key) -> DataFrame:
    """Query the whole table anew at the end of every interval; the budget is dealt out among all. (idx, noisy, eps, sigma2)

    The exact answer at a time is the running total of all changes up to it, so no state of any entry is rebuilt.
    """
    scale = query.l1 * grid.n / total_eps
    sums = dense(grid, linear.change(grid.assign(cl, from_beginning=True), query))
    exact = sums.select("idx", F.sum("exact").over(Window.orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)).alias("exact"))  # over intervals
    noisy = F.col("exact").cast("double") + laplace(scale, key, "0", F.col("idx"))
    return exact.select("idx", noisy.alias("noisy"), F.lit(total_eps / grid.n).alias("eps"), F.lit(laplace_variance(scale)).alias("sigma2"))


def event_level_tree(df: DataFrame, ts, entry: str, grid: IntervalGrid, c: int, h: int, eps: float, key: Key) -> DataFrame:
    """Each row an entry of its own: protects a row, not a user."""
    cl = changelog.from_inserts(df.withColumn("_one", F.lit("1")), entry, ts, "_one")
    return hierarchy(cl, grid, c, h, linear.count_if(lambda v: v.isNotNull()), Noise("laplace", eps), key)


def bounded_user_tree(cl: DataFrame, k: int, grid: IntervalGrid, c: int, h: int, query: linear.LinearQuery, total_eps: float, key: Key) -> DataFrame:
    """Keep k mutations an entry, then a tree at a budget for h k folds."""
    return hierarchy(constraints.enforce_k(cl, k), grid, c, h, query, Noise("laplace", total_eps / (h * k)), key)


def truncation_sweep(cl: DataFrame, grid: IntervalGrid, clips: list[int], eps: float) -> DataFrame:
    """(clip, bias, sigma2): what clipping loses against the noise it saves, for many clips from one scan."""
    rows = grid.assign(cl)
    raw = F.sum(F.coalesce("after", F.lit(0)) - F.coalesce("before", F.lit(0)))
    cut = {c: F.sum(F.least(F.coalesce("after", F.lit(0)), F.lit(c)) - F.least(F.coalesce("before", F.lit(0)), F.lit(c))) for c in clips}
    one = rows.agg(raw.alias("raw"), *[x.alias(f"c{c}") for c, x in cut.items()])
    items = F.array(*[F.struct(F.lit(c).cast("long").alias("clip"), (F.col("raw") - F.col(f"c{c}")).cast("long").alias("bias"), F.lit(laplace_variance(c / eps)).alias("sigma2")) for c in clips])
    return one.select(F.explode(items).alias("s")).select("s.*")


def growing_budget(daily: DataFrame, eps0: float, ratio: float, key: Key) -> DataFrame:
    """daily: (idx, n) rows gained. An answer each time the count passes the next power of two, with budgets that fall off
    geometrically, so that the total stays bounded. (idx, step, noisy, eps)"""
    running = F.sum("n").over(Window.orderBy("idx").rowsBetween(Window.unboundedPreceding, 0))  # over intervals
    seen = daily.select("idx", running.alias("total")).where("total > 0").withColumn("step", F.floor(F.log2(F.col("total").cast("double"))).cast("int"))
    first = seen.groupBy("step").agg(F.min_by("total", "idx").alias("total"), F.min("idx").alias("idx"))
    eps = F.lit(eps0) * F.pow(F.lit(ratio), F.col("step"))
    return first.select("idx", "step", (F.col("total") + laplace(1 / eps, key, "0", F.col("step"))).alias("noisy"), eps.alias("eps"))


def block_budget(df: DataFrame, grid: IntervalGrid, ts: str, eps: float, key: Key) -> DataFrame:
    """Rows belong to the block of their insertion; each block has a budget of its own, so the release spends the largest,
    not the sum. Later changes of a row are never seen. (idx, noisy, eps, sigma2)"""
    counts = grid.assign(df, ts).groupBy("idx").agg(F.count("*").alias("exact"))
    exact = grid.df(df.sparkSession).select("idx").join(counts, "idx", "left").withColumn("exact", F.coalesce("exact", F.lit(0)))
    return published(exact, 1, 1, Noise("laplace", eps), key, "0", "idx")


def memoised_local(states: DataFrame, symbols: list[str], eps: float, key: Key) -> DataFrame:
    """states: (entry, idx, value). One response an entry and answer, repeated while the answer stays. (entry, idx, out_code)"""
    out = responses.respond(responses.code_of("value", symbols), len(symbols), eps, key, F.col("entry"), F.col("value"))
    return states.select("entry", "idx", "value", out.alias("out_code"))


def memo_leak(reports: DataFrame) -> DataFrame:
    """(changes, seen): true changes between neighbouring intervals, and those that the reports give away."""
    w = Window.partitionBy("entry").orderBy("idx")
    pairs = reports.select("value", "out_code", F.lag("value").over(w).alias("v"), F.lag("out_code").over(w).alias("o")).where("v is not null and v <> value")
    return pairs.agg(F.count("*").alias("changes"), F.coalesce(F.sum((F.col("o") != F.col("out_code")).cast("long")), F.lit(0)).alias("seen"))


def local_vote(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, eps: float, threshold: float, key: Key) -> DataFrame:
    """(idx, votes, update): entries say, by a noisy bit, whether they changed; the release is renewed only where the
    estimated share of changes is at least the threshold."""
    p, q = responses.optimal_matrix(2, eps)
    net = changelog.net_change(grid.assign(cl)).select("entry", "idx", F.lit(1).alias("changed"))
    every = dense_rows(entries, net, interval_keys(grid.n), ["idx"], ["changed"])
    truth = F.coalesce("changed", F.lit(0))
    bit = F.when(uniform(key, F.col("entry"), F.col("idx"), salt="v") < p, truth).otherwise(1 - truth)
    counts = every.select("idx", bit.alias("bit")).groupBy("idx").agg(F.sum("bit").alias("s"), F.count("*").alias("n"))
    votes = (F.col("s") - q * F.col("n")) / (p - q)
    return counts.select("idx", votes.alias("votes"), (votes / F.col("n") >= threshold).alias("update"))


def voted_histogram(cl: DataFrame, entries: DataFrame, states: DataFrame, grid: IntervalGrid, symbols: list[str], eps_vote: float, eps_answer: float, threshold: float, key: Key) -> DataFrame:
    """(idx, symbol, estimate, renewed): a histogram that is surveyed anew only where the vote asks for it, and always at the
    first interval; in between the last answer is carried on, at no cost. states: (entry, idx, value)."""
    votes = local_vote(cl, entries, grid, eps_vote, threshold, key).select("idx", (F.col("update") | (F.col("idx") == 0)).alias("renewed"))
    asked = repeated_static(states.join(votes.where("renewed").select("idx"), "idx"), symbols, eps_answer, key)
    names = states.sparkSession.createDataFrame([(s,) for s in symbols], "symbol string")
    held = votes.crossJoin(names).join(asked, ["idx", "symbol"], "left")  # intervals times symbols
    last = F.last("estimate", ignorenulls=True).over(Window.partitionBy("symbol").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0))
    return held.select("idx", "symbol", last.alias("estimate"), "renewed")


def repeated_static(states: DataFrame, symbols: list[str], eps: float, key: Key) -> DataFrame:
    """states: (entry, idx, value). A fresh survey every interval: errors don't add up, budgets do. (idx, symbol, estimate)"""
    z = len(symbols)
    p, q = responses.optimal_matrix(z, eps)
    out = responses.respond(responses.code_of("value", symbols), z, eps, key, F.col("entry"), F.col("idx"))
    counts = states.select("idx", out.alias("c")).groupBy("idx").agg(F.count("*").alias("n"), *[F.sum((F.col("c") == i).cast("long")).alias(f"n{i}") for i in range(z)])
    rows = F.array(*[F.struct(F.lit(s).alias("symbol"), ((F.col(f"n{i}") - q * F.col("n")) / (p - q)).alias("estimate")) for i, s in enumerate(symbols)])
    return counts.select("idx", F.explode(rows).alias("e")).select("idx", "e.symbol", "e.estimate")
