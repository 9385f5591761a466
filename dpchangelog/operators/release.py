"""Disjoint releases: one noisy answer an interval, on a dense grid, from one scan."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid
from ..functions.noise import Key, Noise
from . import linear


def dense(grid: IntervalGrid, exact: DataFrame, domain: DataFrame | None = None, on: tuple[str, ...] = ()) -> DataFrame:
    """Every interval (and every public group), 0 where nothing happened: presence must not show."""
    base = grid.df(exact.sparkSession).select("idx")
    if domain is not None:
        base = base.crossJoin(domain)
    return base.join(exact, ["idx", *on], "left").withColumn("exact", F.coalesce("exact", F.lit(0)))


def disjoint(cl: DataFrame, grid: IntervalGrid, query: linear.LinearQuery, noise: Noise, key: Key, domain: DataFrame | None = None, group: str | None = None, from_beginning: bool = False) -> DataFrame:
    """(idx, [group_key], noisy, eps, sigma2). Groups come from a public domain (group_key), never from the data."""
    indexed = grid.assign(cl, from_beginning=from_beginning)
    by = ("idx",)
    if group:
        indexed, by = indexed.withColumnRenamed(group, "group_key") if group != "group_key" else indexed, ("idx", "group_key")
    exact = dense(grid, linear.change(indexed, query, by), domain, by[1:])
    return published(exact, query.l1, query.l2, noise, key, "0", "idx", *(by[1:]))


def histogram(cl: DataFrame, grid: IntervalGrid, symbols: DataFrame, noise: Noise, key: Key) -> DataFrame:
    """(idx, symbol, noisy, eps, sigma2): change of the histogram over a public alphabet."""
    exact = dense(grid, linear.histogram_change(grid.assign(cl)), symbols, ("symbol",))
    return published(exact, linear.HISTOGRAM_L1, linear.HISTOGRAM_L2, noise, key, "0", "idx", "symbol")


def published(exact: DataFrame, l1: float, l2: float, noise: Noise, key: Key, layer: str, *coords: str) -> DataFrame:
    layer_part = F.col(layer[1:]) if layer.startswith("@") else layer
    noisy = F.col("exact").cast("double") + noise.draw(l1, l2, key, layer_part, *[F.col(c) for c in coords])
    return exact.withColumns({"noisy": noisy, "eps": F.lit(float(noise.eps)), "sigma2": F.lit(float(noise.variance(l1, l2)))}).drop("exact")


def running_total(released: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Totals up to each interval and their variance, which grows with the number of intervals. Rows are intervals."""
    w = Window.partitionBy(*by).orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return released.select("idx", *by, F.sum("noisy").over(w).alias("total"), F.sum("sigma2").over(w).alias("var"))


def heterogeneous(cl: DataFrame, grid: IntervalGrid, mechanisms: list[tuple[str, linear.LinearQuery, Noise]], key: Key) -> DataFrame:
    """Several mechanisms on one grid, from one scan: (mechanism, idx, noisy, eps, sigma2)."""
    sums = grid.assign(cl).groupBy("idx").agg(*[F.sum(q.change()).cast("double").alias(name) for name, q, _ in mechanisms])
    base = grid.df(cl.sparkSession).select("idx").join(sums, "idx", "left")
    rows = []
    for name, q, noise in mechanisms:
        noisy = F.coalesce(F.col(name), F.lit(0.0)) + noise.draw(q.l1, q.l2, key.of(f"{key.release}/{name}"), "0", F.col("idx"))
        rows.append(F.struct(F.lit(name).alias("mechanism"), noisy.alias("noisy"), F.lit(float(noise.eps)).alias("eps"), F.lit(noise.variance(q.l1, q.l2)).alias("sigma2")))
    return base.select("idx", F.explode(F.array(*rows)).alias("m")).select("m.mechanism", "idx", "m.noisy", "m.eps", "m.sigma2")
