"""Release endpoints: half-open grids (t0 + i W, t0 + (i + 1) W], explicit endpoints, and how many intervals a window can touch.

Time is a LONG of microseconds (or any logical clock). Everything is integer arithmetic, so boundaries are exact.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SECOND = 1_000_000
HOUR = 3600 * SECOND
DAY = 24 * HOUR
#: The folder column of stored changelogs: the day of ts, whole days since 1970.
DAY_COLUMN = "ts_day"


def micros(ts: str | Column) -> Column:
    """Microseconds since 1970 of a TIMESTAMP_NTZ, whatever the session's time zone."""
    c = F.col(ts) if isinstance(ts, str) else ts
    seconds = F.unix_date(F.to_date(c)).cast("long") * 86400 + F.hour(c) * 3600 + F.minute(c) * 60
    return seconds * SECOND + (F.date_part(F.lit("SECOND"), c) * SECOND).cast("long")


def ceil_div(a: Column, w: int | Column) -> Column:
    """ceil(a / w) on whole numbers of either sign."""
    return F.call_function("div", a + F.pmod(-a, F.lit(w)), F.lit(w)).cast("long")


def ceil_int(a, w):
    """ceil(a / w) of whole numbers, or of columns of them."""
    return ceil_div(F.lit(a), w) if isinstance(a, Column) or isinstance(w, Column) else -(-a // w)


def div_int(a, w):
    """a / w without the rest, for whole numbers from 0, or columns of them."""
    return F.call_function("div", F.lit(a), F.lit(w)) if isinstance(a, Column) or isinstance(w, Column) else a // w


def gcd_int(a, b):
    """Greatest common divisor of whole numbers from 0, or of columns of them: 92 steps do for 64 bits."""
    if not (isinstance(a, Column) or isinstance(b, Column)):
        return math.gcd(a, b)
    pair = lambda x, y: F.struct(x.cast("long").alias("x"), y.cast("long").alias("y"))
    step = lambda s, _: F.when(s["y"] == 0, s).otherwise(pair(s["y"], s["x"] % F.when(s["y"] == 0, F.lit(1)).otherwise(s["y"])))
    return F.aggregate(F.sequence(F.lit(1), F.lit(92)), pair(F.lit(a), F.lit(b)), step, lambda s: s["x"])


@dataclass(frozen=True)
class IntervalGrid:
    """Intervals 0 .. n - 1. Regular: start and width; explicit: ascending endpoints t_0 .. t_n, interval i = (t_i, t_(i+1)]."""

    n: int
    start: int = 0
    width: int = 0
    endpoints: tuple[int, ...] = ()

    @staticmethod
    def regular(start: int, width: int, n: int) -> "IntervalGrid":
        if width < 1 or n < 0:
            raise ValueError("width is at least 1 and n at least 0")
        return IntervalGrid(n, start, width)

    @staticmethod
    def explicit(endpoints) -> "IntervalGrid":
        e = tuple(endpoints)
        if any(a >= b for a, b in zip(e, e[1:], strict=False)):
            raise ValueError("endpoints ascend strictly")
        return IntervalGrid(max(0, len(e) - 1), endpoints=e)

    def end(self, i: int) -> int:
        return self.endpoints[i + 1] if self.endpoints else self.start + (i + 1) * self.width

    @property
    def begin(self) -> int:
        return self.endpoints[0] if self.endpoints else self.start

    def position(self, ts: Column | str) -> Column:
        """The first interval that ends at or after a time, unbounded on a regular grid: below 0 before it, n or more behind it."""
        c = F.col(ts) if isinstance(ts, str) else ts
        if self.endpoints:
            return F.size(F.filter(F.array(*[F.lit(e) for e in self.endpoints]), lambda e: e < c)).cast("long") - 1 + F.when(c.isNotNull(), 0)
        return ceil_div(c - F.lit(self.start), self.width) - 1

    def idx(self, ts: Column, from_beginning: bool = False) -> Column:
        """Interval of a time, null outside the grid. from_beginning: interval 0 reaches back without bound."""
        if len(self.endpoints) > 64:
            raise ValueError("use assign() for long lists of endpoints")
        i = self.position(ts)
        if from_beginning:
            i = F.greatest(i, F.lit(0))
        return F.when((i >= 0) & (i < self.n), i)

    def assign(self, df: DataFrame, ts: str = "ts", from_beginning: bool = False) -> DataFrame:
        """df within the grid, with idx. Long endpoint lists go through a join of cells rather than an array per row.

        The bounds are filters on the time column itself, and on the day folders of a stored changelog (DAY_COLUMN), so a release
        reads no more of the history than its grid spans.
        """
        if self.n:
            low, high = self.begin, self.end(self.n - 1)
            df = df.where(F.col(ts) <= high) if from_beginning else df.where((F.col(ts) > low) & (F.col(ts) <= high))
            if DAY_COLUMN in df.columns:
                day = F.col(DAY_COLUMN)
                df = df.where(day <= high // DAY) if from_beginning else df.where((day >= low // DAY) & (day <= high // DAY))
        if not self.endpoints or len(self.endpoints) <= 64:
            return df.withColumn("idx", self.idx(F.col(ts), from_beginning)).where("idx is not null")
        ends = self.df(df.sparkSession)
        day = 1 << max(0, (self.endpoints[-1] - self.endpoints[0]).bit_length() - 12)
        # Equal-width cells, each of which meets the few intervals that overlap it: an equi-join with a residual.
        first, last = F.floor(F.col("start_us") / day), F.floor(F.col("end_us") / day)
        cells = ends.withColumn("cell", F.explode(F.sequence(first.cast("long"), last.cast("long"))))
        held = df.withColumn("cell", F.floor(F.col(ts) / day).cast("long"))
        out = held.join(cells, "cell").where((F.col(ts) > F.col("start_us")) & (F.col(ts) <= F.col("end_us"))).drop("cell", "start_us", "end_us")
        return out if not from_beginning else out.unionByName(df.where(F.col(ts) <= self.endpoints[0]).withColumn("idx", F.lit(0).cast("long")))

    def df(self, spark: SparkSession) -> DataFrame:
        """(idx, start_us, end_us) of every interval, empty ones included."""
        base = spark.range(self.n).withColumnRenamed("id", "idx")
        if self.endpoints:
            rows = [(i, self.endpoints[i], self.endpoints[i + 1]) for i in range(self.n)]
            return spark.createDataFrame(rows, "idx long, start_us long, end_us long")
        return base.select("idx", (F.lit(self.start) + F.col("idx") * self.width).alias("start_us"), (F.lit(self.start) + (F.col("idx") + 1) * self.width).alias("end_us"))


def interval_span(endpoints, b: int) -> int:
    """Most intervals of the endpoints that a closed window of length b can touch, over long grids.

    For each endpoint, the endpoints up to the first that is b or more later (or the last one) count; the largest is taken.
    """
    e = sorted(endpoints)
    return max((min(bisect_left(e, t + b), len(e) - 1) - i + 1 for i, t in enumerate(e)), default=0)
