"""The local model: every entry reports on its own, whether or not it exists or changed."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid, ceil_div, ceil_int
from ..functions.noise import Key, laplace, laplace_variance, uniform
from .linear import LinearQuery
from .sliding import SlidingSpec


@dataclass(frozen=True)
class Randomizer:
    """report(exact, key, *parts): what an entry sends; unbiased for its exact value, with at most that variance."""

    report: Callable[..., Column]
    variance: float


def laplace_reports(query: LinearQuery, eps: float) -> Randomizer:
    """Two entries' changes lie up to twice the range apart."""
    scale = 2 * query.l1 / eps
    return Randomizer(lambda exact, key, *parts: exact.cast("double") + laplace(scale, key, *parts), laplace_variance(scale))


def sign_reports(query: LinearQuery, eps: float) -> Randomizer:
    """One bit: plus or minus a fixed size, with odds that make the mean the exact value. Changes lie within plus and minus l1."""
    size = query.l1 * (math.exp(eps) + 1) / (math.exp(eps) - 1)

    def report(exact, key, *parts):
        return F.when(uniform(key, *parts) < 0.5 + exact.cast("double") / (2 * size), F.lit(size)).otherwise(F.lit(-size))

    return Randomizer(report, size * size)


def interval_keys(n: int) -> Column:
    return F.transform(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")), lambda i: F.struct(i.alias("idx")))


def node_keys(n: int, c: int, h: int) -> Column:
    one = lambda j: F.transform(F.sequence(F.lit(0).cast("long"), F.lit(ceil_int(n, c**j) - 1).cast("long")), lambda i: F.struct(F.lit(j).alias("layer"), i.alias("idx")))
    return F.concat(*[one(j) for j in range(h)])


def dense_rows(entries: DataFrame, sparse: DataFrame, grid: Column, keys: list[str], fields: list[str]) -> DataFrame:
    """(entry, keys..., fields...) for every entry and row of a small public grid; null where sparse has none. grid: an array of
    structs of the keys (interval_keys, node_keys).

    Only sparse is shuffled, gathered into a map an entry (no longer than the grid), and entries; the grid is laid out beside each
    entry afterwards, so entries times grid never moves. sparse: (entry, keys..., fields...) without repeats.
    """
    held = sparse.groupBy("entry").agg(F.map_from_entries(F.collect_list(F.struct(F.struct(*keys), F.struct(*fields)))).alias("held"))
    every = entries.select("entry").join(held, "entry", "left")
    out = every.select("entry", F.explode(grid).alias("k"), "held").select("entry", "k", F.try_element_at("held", F.col("k")).alias("v"))
    return out.select("entry", *[F.col(f"k.{c}").alias(c) for c in keys], *[F.col(f"v.{c}").alias(c) for c in fields])


def _sums(rows: DataFrame, query: LinearQuery, keys: list[str]) -> DataFrame:
    return rows.groupBy("entry", *keys).agg(F.sum(query.change()).alias("exact"))


def dense_changes(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, query: LinearQuery) -> DataFrame:
    """(entry, idx, exact) for every entry and interval."""
    every = dense_rows(entries, _sums(grid.assign(cl), query, ["idx"]), interval_keys(grid.n), ["idx"], ["exact"])
    return every.withColumn("exact", F.coalesce("exact", F.lit(0)))


def _reported(every: DataFrame, keys: list[str], how: Randomizer, key: Key, *parts) -> DataFrame:
    sent = every.select(*keys, how.report(F.coalesce("exact", F.lit(0)), key, *parts, F.col("entry")).alias("r"))
    return sent.groupBy(*keys).agg(F.sum("r").alias("estimate"), (F.count("*") * F.lit(float(how.variance))).alias("var"))


def linear_change(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, query: LinearQuery, eps: float, key: Key, how: Randomizer | None = None) -> DataFrame:
    """(idx, estimate, var): each entry randomizes its own change, by Laplace noise or any other randomizer."""
    return _reported(dense_changes(cl, entries, grid, query), ["idx"], how or laplace_reports(query, eps), key, "0", F.col("idx"))


def tree(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, c: int, h: int, query: LinearQuery, eps: float, key: Key, how: Randomizer | None = None) -> DataFrame:
    """(layer, idx, noisy, sigma2) of the nodes of a tree of local reports at eps a node; hierarchy.range_query answers from it."""
    nodes = F.posexplode(F.array(*[F.floor(F.col("idx") / c**j).cast("long") for j in range(h)])).alias("layer", "node")
    rows = grid.assign(cl).select("entry", "before", "after", nodes).withColumnRenamed("node", "idx")
    keys = ["layer", "idx"]
    every = dense_rows(entries, _sums(rows, query, keys), node_keys(grid.n, c, h), keys, ["exact"])
    out = _reported(every, keys, how or laplace_reports(query, eps), key, F.col("layer"), F.col("idx"))
    return out.withColumnsRenamed({"estimate": "noisy", "var": "sigma2"})


def sliding(cl: DataFrame, entries: DataFrame, spec: SlidingSpec, query: LinearQuery, eps: float, key: Key, how: Randomizer | None = None) -> DataFrame:
    """(idx, estimate, var): each entry reports its change over each window. A mutation is copied to the windows that hold it."""
    a = F.col("ts") - spec.t1
    first = F.greatest(F.lit(0).cast("long"), ceil_div(a, spec.p))
    last = F.least(F.lit(spec.n - 1).cast("long"), ceil_div(a + spec.w, spec.p) - 1)
    rows = cl.where((F.col("ts") > spec.t1 - spec.w) & (F.col("ts") <= spec.t1 + (spec.n - 1) * spec.p)).where(first <= last)
    rows = rows.select("entry", "before", "after", F.explode(F.sequence(first, last)).alias("idx"))
    every = dense_rows(entries, _sums(rows, query, ["idx"]), interval_keys(spec.n), ["idx"], ["exact"])
    return _reported(every, ["idx"], how or laplace_reports(query, eps), key, "0", F.col("idx"))


def separating_queries(cl: DataFrame, grid: IntervalGrid, one, other) -> DataFrame:
    """(idx) of intervals that hold a mutation of either entry and whose contents differ between them."""
    rows = grid.assign(cl.where(F.col("entry").isin(one, other)))
    sides = rows.groupBy("idx", "ts", "before", "after").agg(F.sum(F.when(F.col("entry") == one, 1).otherwise(-1)).alias("d"))
    return sides.where("d <> 0").select("idx").distinct()


def separations(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, other) -> DataFrame:
    """(entry, queries): how many intervals tell each entry from one stated entry: those in which the multisets of their
    mutations differ. The other's mutations are laid beside those of all entries by time and value, not entry by entry."""
    rows = grid.assign(cl).groupBy("entry", "idx", "ts", "before", "after").agg(F.count("*").alias("n"))
    mine = rows.where(F.col("entry").eqNullSafe(F.lit(other))).select(F.col("idx").alias("i"), F.col("ts").alias("t"), F.col("before").alias("b"), F.col("after").alias("a"), F.col("n").alias("m"))
    same = F.col("idx").eqNullSafe(F.col("i")) & F.col("ts").eqNullSafe(F.col("t")) & F.col("before").eqNullSafe(F.col("b")) & F.col("after").eqNullSafe(F.col("a"))
    # By entry and interval: mutations that both have alike, and those of the entry alone.
    own = rows.join(mine, same, "left").groupBy("entry", "idx").agg(F.sum(F.when(F.col("m") == F.col("n"), 1).otherwise(0)).alias("alike"), F.count("*").alias("kinds"))
    theirs = mine.groupBy(F.col("i").alias("idx")).agg(F.count("*").alias("others"))
    met = own.join(theirs, "idx", "left")
    equal = (F.col("alike") == F.col("kinds")) & (F.col("kinds") == F.coalesce("others", F.lit(0)))
    per = met.groupBy("entry").agg(F.sum(F.when(~equal, 1).otherwise(0)).alias("d"), F.sum(F.when(F.col("others").isNotNull(), 1).otherwise(0)).alias("common"))
    total = theirs.agg(F.count("*").alias("all"))  # one row
    out = entries.select("entry").join(per, "entry", "left").join(F.broadcast(total))
    return out.select("entry", (F.coalesce("d", F.lit(0)) + F.col("all") - F.coalesce("common", F.lit(0))).alias("queries"))


def touch_pairs(touched: DataFrame, other: DataFrame) -> DataFrame:
    """(one, other, queries): queries touched by each entry or by the other one; touched: (entry, idx) without repeats; other: one
    row (entry). Counts add up less what both touch, so the other's queries (no more than the grid has) are looked up, not copied."""
    theirs = touched.join(F.broadcast(other), "entry", "left_semi").select("idx", F.lit(1).alias("both"))
    size = theirs.agg(F.count("*").alias("size")).crossJoin(other.select(F.col("entry").alias("other")))  # one row
    mine = touched.join(theirs, "idx", "left").groupBy(F.col("entry").alias("one")).agg(F.count("*").alias("n"), F.count("both").alias("both"))
    return mine.join(F.broadcast(size)).select("one", "other", (F.col("n") + F.col("size") - F.col("both")).alias("queries"))


def most_touching(touched: DataFrame) -> DataFrame:
    """(entry): the entry that touches most queries, the smallest id of equals; one row."""
    counts = touched.groupBy("entry").agg(F.count("*").alias("n"))
    return counts.groupBy("n").agg(F.min("entry").alias("entry")).agg(F.max_by("entry", "n").alias("entry"))


def touch_supremum(touched: DataFrame) -> DataFrame:
    """(most, second, bound): the two largest counts of touched queries and their sum; one row.

    No two entries touch more than the sum of their counts, so it bounds the supremum over all pairs without listing pairs.
    """
    counts = touched.groupBy("entry").agg(F.count("*").alias("n"))
    top = counts.orderBy(F.desc("n"), "entry").limit(2).agg(F.max("n").alias("most"), F.sum("n").alias("bound"))
    return top.select("most", (F.col("bound") - F.col("most")).alias("second"), "bound")
