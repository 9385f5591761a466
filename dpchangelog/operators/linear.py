"""Linear and aggregatable queries: sums of f(after) - f(before), with f(null) = 0 and f clipped to known bounds."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import Key, laplace


@dataclass(frozen=True)
class LinearQuery:
    """f(value) as a Column; low and high bound f. l1 and l2: how far one entry's change can move the answer."""

    f: Callable[[Column], Column]
    low: float
    high: float
    l1: float
    l2: float

    def of(self, c: str) -> Column:
        return F.coalesce(F.when(F.col(c).isNotNull(), self.f(F.col(c))), F.lit(0))

    def change(self) -> Column:
        return self.of("after") - self.of("before")


def _bounded(f, low, high) -> LinearQuery:
    # An insert or delete moves f against 0, so 0 belongs to the range.
    s = max(high, 0) - min(low, 0)
    return LinearQuery(lambda v: F.greatest(F.lit(low), F.least(F.lit(high), f(v))), low, high, s, s)


def clipped_sum(low, high) -> LinearQuery:
    return _bounded(lambda v: v, low, high)


def moment(power: int, low, high) -> LinearQuery:
    """Sum of whole powers of a value clipped to [low, high]."""
    clip = lambda v: F.greatest(F.lit(low), F.least(F.lit(high), v))
    ends = [low**power, high**power] + ([0] if low < 0 < high else [])

    def f(v):
        out = x = clip(v)
        for _ in range(power - 1):
            out = out * x
        return out

    s = max(*ends, 0) - min(*ends, 0)
    return LinearQuery(f, min(ends), max(ends), s, s)


def count_if(predicate: Callable[[Column], Column]) -> LinearQuery:
    return LinearQuery(lambda v: F.when(predicate(v), 1).otherwise(0), 0, 1, 1, 1)


def custom(f: Callable[[Column], Column], low: float, high: float) -> LinearQuery:
    return _bounded(f, low, high)


def change(indexed: DataFrame, query: LinearQuery, by=("idx",)) -> DataFrame:
    """(by..., exact): one aggregate, combined before its shuffle."""
    return indexed.groupBy(*by).agg(F.sum(query.change()).alias("exact"))


def histogram_change(indexed: DataFrame, by=("idx",)) -> DataFrame:
    """(by..., symbol, exact): +1 at after and -1 at before. One entry's change has L1 norm 2 and L2 norm sqrt(2)."""
    ends = F.array(F.struct(F.col("after").alias("symbol"), F.lit(1).alias("d")), F.struct(F.col("before").alias("symbol"), F.lit(-1).alias("d")))
    rows = indexed.select(*by, F.explode(ends).alias("e")).where("e.symbol is not null")
    return rows.groupBy(*by, F.col("e.symbol").alias("symbol")).agg(F.sum("e.d").cast("long").alias("exact"))


HISTOGRAM_L1, HISTOGRAM_L2 = 2.0, math.sqrt(2)


def vector_change(indexed: DataFrame, width: int, clip_l2: float, by=("idx",)) -> DataFrame:
    """(by..., coord, exact): sums of arrays clipped to a length, a coordinate a row. A coordinate at or beyond width is an error:
    leaving it out would answer another question in silence."""

    def coords(c, sign):
        v = F.col(c)
        size = F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
        factor = F.least(F.lit(1.0), F.lit(float(clip_l2)) / F.greatest(size, F.lit(1e-300)))
        return F.when(v.isNotNull(), F.transform(v, lambda x, i: F.struct(i.alias("coord"), (sign * x.cast("double") * factor).alias("x"))))

    none = F.array().cast("array<struct<coord:int,x:double>>")
    rows = indexed.select(*by, F.explode(F.concat(F.coalesce(coords("after", 1), none), F.coalesce(coords("before", -1), none))).alias("e"))
    inside = F.when(F.col("e.coord") < width, True).otherwise(F.raise_error(F.lit(f"a vector is longer than {width}")).cast("boolean"))
    return rows.where(inside).groupBy(*by, F.col("e.coord").alias("coord")).agg(F.sum("e.x").alias("exact"))


def combine(parts: DataFrame, value: str, by=()) -> DataFrame:
    """Answers of neighbouring ranges add up to that of their union."""
    return parts.groupBy(*by).agg(F.sum(value).alias(value))


@dataclass(frozen=True)
class Aggregatable:
    """A mechanism whose answers on parts combine, without bias, into one on the whole."""

    name: str
    partials: Callable[[DataFrame, tuple], DataFrame]
    combine: Callable[[DataFrame, tuple], DataFrame]


COUNT = Aggregatable("count", lambda df, by: df.groupBy(*by).agg(F.sum(F.when(F.col("after").isNotNull(), 1).otherwise(0) - F.when(F.col("before").isNotNull(), 1).otherwise(0)).alias("count")), lambda parts, by: combine(parts, "count", by))
SUM = Aggregatable("sum", lambda df, by: df.groupBy(*by).agg(F.sum(F.coalesce("after", F.lit(0)) - F.coalesce("before", F.lit(0))).alias("sum")), lambda parts, by: combine(parts, "sum", by))


def mean_and_variance(count: Column, total: Column, squares: Column) -> tuple[Column, Column]:
    """Post-processing of a count, a sum and a second moment."""
    mean = total / count
    return mean, squares / count - mean * mean


def mechanism(indexed: DataFrame, aggregate: Column, by=("idx",)) -> DataFrame:
    """Any aggregate over the mutations of a range, such as their number. Its sensitivity needs a cap on mutations."""
    return indexed.groupBy(*by).agg(aggregate.alias("exact"))


def choose_clip(history: DataFrame, value: str, grid: list[float], share: float) -> float:
    """Smallest bound of a public grid that leaves so large a share unclipped. Not private: for studies only."""
    q = history.agg(F.percentile_approx(F.col(value).cast("double"), share)).first()[0] or 0.0
    return next((g for g in sorted(grid) if g >= q), max(grid))


def choose_clip_private(history: DataFrame, value: str, grid: list[float], share: float, eps: float, key: Key) -> DataFrame:
    """(clip, noisy, chosen): the smallest bound of a public grid below which lies, by noisy counts, so large a share.

    One row of history an entry (or a sensitivity of one row is claimed): each falls in one cell, so the histogram costs eps.
    """
    bounds = sorted(grid)
    cell = F.coalesce(sum((F.when(F.col(value) > b, 1).otherwise(0) for b in bounds), F.lit(0)), F.lit(0))
    counts = history.groupBy(F.least(cell, F.lit(len(bounds))).cast("int").alias("cell")).agg(F.count("*").alias("n"))
    cells = history.sparkSession.range(len(bounds) + 1).select(F.col("id").cast("int").alias("cell")).join(counts, "cell", "left")
    noisy = cells.select("cell", (F.coalesce("n", F.lit(0)) + laplace(1 / eps, key, F.col("cell"))).alias("x"))
    w = Window.partitionBy()  # over len(grid) + 1 rows
    sums = noisy.select("cell", F.sum("x").over(w.orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)).alias("noisy"), F.sum("x").over(w).alias("all"))
    good = sums.withColumn("good", F.col("noisy") >= share * F.col("all"))
    first = F.coalesce(F.min(F.when(F.col("good"), F.col("cell"))).over(w), F.lit(len(bounds) - 1))
    clip = F.element_at(F.array(*[F.lit(float(b)) for b in bounds]), F.col("cell") + 1)
    return good.withColumn("first", F.least(first, F.lit(len(bounds) - 1))).where(F.col("cell") < len(bounds)).select(clip.alias("clip"), "noisy", (F.col("cell") == F.col("first")).alias("chosen"))
