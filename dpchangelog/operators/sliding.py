"""Sliding releases: windows of W every P, direct, flat, or from a tree."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid
from ..functions.noise import Key, Noise
from ..plans.accounting import height_for
from . import linear
from .hierarchy import exact_nodes, published_nodes, range_query
from .release import published


#: Base intervals of a sliding release, at most.
BASE_ROWS = 20_000_000


@dataclass(frozen=True)
class SlidingSpec:
    """Window i is (t1 + i P - W, t1 + i P], i = 0 .. n - 1."""

    t1: int
    w: int
    p: int
    n: int

    @property
    def g(self) -> int:
        return math.gcd(self.w, self.p)

    def base_grid(self) -> IntervalGrid:
        """Intervals of the greatest common width, from the start of the first window to the end of the last."""
        return IntervalGrid.regular(self.t1 - self.w, self.g, (self.w + (self.n - 1) * self.p) // self.g)

    def bounded_grid(self) -> IntervalGrid:
        """base_grid, refused where it has more than BASE_ROWS intervals: their frames run in one task (a symbol). A W and P of a
        larger common width, or a direct release a window, answer the same question."""
        grid = self.base_grid()
        if grid.n > BASE_ROWS:
            raise ValueError(f"W and P have a common width of {self.g}, which makes {grid.n} base intervals, more than {BASE_ROWS}")
        return grid

    def ranges(self, spark) -> DataFrame:
        return self.windows(spark).withColumnRenamed("idx", "range_id")

    def windows(self, spark) -> DataFrame:
        """(idx, l, r): window i covers the base intervals l .. r - 1."""
        s, q = self.w // self.g, self.p // self.g
        return spark.range(self.n).select(F.col("id").alias("idx"), (F.col("id") * q).alias("l"), (F.col("id") * q + s).alias("r"))


def base_sums(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery) -> DataFrame:
    """(idx, exact), dense, from one scan; rows of no window (gaps when P > W) fall out later."""
    return _dense(spec, linear.change(spec.bounded_grid().assign(cl), query))


def _dense(spec: SlidingSpec, sums: DataFrame, domain: DataFrame | None = None) -> DataFrame:
    by = domain.columns if domain is not None else []
    every = spec.base_grid().df(sums.sparkSession).select("idx")
    every = every.crossJoin(domain) if domain is not None else every  # base intervals times a public domain
    return every.join(sums, ["idx", *by], "left").withColumn("exact", F.coalesce("exact", F.lit(0)))


def rolled(base: DataFrame, spec: SlidingSpec, by: list[str], **sums: str) -> DataFrame:
    """(idx, by..., name=sum over window idx of a column of base)."""
    s, q = spec.w // spec.g, spec.p // spec.g
    frame = Window.partitionBy(*by).orderBy("idx").rowsBetween(-(s - 1), 0)  # over base intervals, few however large the data
    first = F.col("idx") - (s - 1)
    rolled = base.select("idx", *by, *[F.sum(c).over(frame).alias(name) for name, c in sums.items()])
    return rolled.where((first >= 0) & (first % q == 0)).select((first / q).cast("long").alias("idx"), *by, *sums)


def histogram_base(cl: DataFrame, spec: SlidingSpec, symbols: DataFrame) -> DataFrame:
    """(idx, symbol, exact), dense over the public alphabet."""
    return _dense(spec, linear.histogram_change(spec.bounded_grid().assign(cl)), symbols)


def direct_histogram(cl: DataFrame, spec: SlidingSpec, symbols: DataFrame, noise: Noise, key: Key) -> DataFrame:
    """(idx, symbol, noisy, eps, sigma2): change of the histogram over each window, a draw a window and symbol."""
    exact = rolled(histogram_base(cl, spec, symbols), spec, symbols.columns, exact="exact")
    return published(exact, linear.HISTOGRAM_L1, linear.HISTOGRAM_L2, noise, key, "0", "idx", *symbols.columns)


def histogram_from_hierarchy(cl: DataFrame, spec: SlidingSpec, symbols: DataFrame, noise: Noise, key: Key, c: int, h: int | None = None) -> DataFrame:
    """(idx, symbol, estimate, n_nodes, var) of each window from a tree over the base grid."""
    h = h or height_for(spec.w // spec.g, c)
    nodes = published_nodes(exact_nodes(histogram_base(cl, spec, symbols), spec.base_grid().n, c, h, symbols), linear.HISTOGRAM_L1, linear.HISTOGRAM_L2, noise, key)
    return range_query(nodes, spec.ranges(cl.sparkSession), c, h).withColumnRenamed("range_id", "idx")


def direct_exact(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery) -> DataFrame:
    """(idx, exact) of each window by a frame over base sums: rows of data are not copied ceil(W / P) times."""
    return rolled(base_sums(cl, spec, query), spec, [], exact="exact")


def direct(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery, noise: Noise, key: Key) -> DataFrame:
    """(idx, noisy, eps, sigma2): each window gets a draw of its own."""
    return published(direct_exact(cl, spec, query), query.l1, query.l2, noise, key, "0", "idx")


def nodes_for(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery, noise: Noise, key: Key, c: int, h: int) -> DataFrame:
    return published_nodes(exact_nodes(base_sums(cl, spec, query), spec.base_grid().n, c, h), query.l1, query.l2, noise, key)


def from_hierarchy(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery, noise: Noise, key: Key, c: int, h: int | None = None) -> DataFrame:
    """(idx, estimate, n_nodes, var) of each window from a tree over the base grid."""
    h = h or height_for(spec.w // spec.g, c)
    return range_query(nodes_for(cl, spec, query, noise, key, c, h), spec.ranges(cl.sparkSession), c, h).withColumnRenamed("range_id", "idx")


def from_flat(cl: DataFrame, spec: SlidingSpec, query: linear.LinearQuery, noise: Noise, key: Key) -> DataFrame:
    """A tree of height 1: base intervals are released once, and each window adds up its own."""
    base = published(base_sums(cl, spec, query), query.l1, query.l2, noise, key, "0", "idx")
    return rolled(base, spec, [], estimate="noisy", var="sigma2").select("idx", "estimate", F.lit(spec.w // spec.g).cast("long").alias("n_nodes"), "var")
