"""Changelogs: immutable mutations (entry, ts, seq, kind, before, after) of a changing table.

before and after are null where the entry doesn't exist, so all comparisons are null-safe. Order is (ts, seq) within an
entry; no plan relies on physical order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid

COLUMNS = ["entry", "ts", "seq", "kind", "before", "after"]


def _kind(before: str = "before", after: str = "after") -> Column:
    return F.when(F.col(before).isNull(), "insert").when(F.col(after).isNull(), "delete").otherwise("update")


def _with_kind(df: DataFrame) -> DataFrame:
    return df.withColumn("kind", _kind()).select(*COLUMNS, *[c for c in df.columns if c not in COLUMNS])


def from_history(df: DataFrame, entry: str, ts: str, value: str, tiebreak: str | None = None, drop_noop: bool = True) -> DataFrame:
    """Each row sets its entry's value; rows that change nothing are dropped. One shuffle by entry."""
    rows = df.select(F.col(entry).alias("entry"), F.col(ts).alias("ts"), (F.col(tiebreak) if tiebreak else F.lit(0)).cast("long").alias("seq"), F.col(value).alias("after"))
    out = rows.withColumn("before", F.lag("after").over(Window.partitionBy("entry").orderBy("ts", "seq")))
    if drop_noop:
        out = out.where(~F.col("before").eqNullSafe(F.col("after")))
    return _with_kind(out)


def from_snapshots(old: DataFrame, new: DataFrame, key: str, value: str, ts: int) -> DataFrame:
    """The mutations between two snapshots, all at ts."""
    a = old.select(F.col(key).alias("entry"), F.col(value).alias("before"))
    b = new.select(F.col(key).alias("entry"), F.col(value).alias("after"))
    out = a.join(b, "entry", "full_outer").where(~F.col("before").eqNullSafe(F.col("after")))
    return _with_kind(out.select("entry", F.lit(ts).cast("long").alias("ts"), F.lit(0).cast("long").alias("seq"), "before", "after"))


def from_snapshot_series(snapshots: list[tuple[int, DataFrame]], key: str, value: str) -> DataFrame:
    """Inserts at the first time, then what changes between neighbours."""
    (t0, first), *rest = sorted(snapshots, key=lambda x: x[0])
    out, before = initial_inserts(first, key, value, t0), first
    for t, snapshot in rest:
        out, before = out.unionByName(from_snapshots(before, snapshot, key, value, t)), snapshot
    return out


def from_inserts(df: DataFrame, entry: str, ts: str | Column, value: str) -> DataFrame:
    """Each row is an entry that is inserted once."""
    t = F.col(ts) if isinstance(ts, str) else ts
    rows = df.select(F.col(entry).alias("entry"), t.alias("ts"), F.lit(0).cast("long").alias("seq"), F.col(value).alias("after"))
    return _with_kind(rows.withColumn("before", F.lit(None).cast(rows.schema["after"].dataType)))


def initial_inserts(snapshot: DataFrame, key: str, value: str, t0: int) -> DataFrame:
    return from_inserts(snapshot, key, F.lit(t0).cast("long"), value)


def with_deletes(cl: DataFrame, ttl: int | None = None, terminal_values: list | None = None) -> DataFrame:
    """Delete entries ttl after their last mutation, or at once where they reach a terminal value.

    A mutation into a terminal value becomes a delete, and what follows from there an insert.
    """
    if terminal_values is not None:
        gone = lambda c: F.when(~F.col(c).isin(*terminal_values), F.col(c))
        cl = _with_kind(cl.withColumns({"before": gone("before"), "after": gone("after")}).where(~F.col("before").eqNullSafe(F.col("after"))))
    if ttl is not None:
        last = cl.groupBy("entry").agg(F.max(F.struct("ts", "seq", "after")).alias("m")).where("m.after is not null")
        dead = last.select("entry", (F.col("m.ts") + ttl).alias("ts"), (F.col("m.seq") + 1).alias("seq"), F.col("m.after").alias("before"))
        cl = cl.unionByName(_with_kind(dead.withColumn("after", F.lit(None).cast(cl.schema["after"].dataType))))
    return cl


def to_new_value(cl: DataFrame) -> DataFrame:
    """The encoding that carries the new value only; narrow."""
    return cl.drop("before")


def to_value_change(cl: DataFrame) -> DataFrame:
    """Back to pairs: the value before is the entry's previous new value."""
    order = Window.partitionBy("entry").orderBy("ts", "seq")
    return _with_kind(cl.drop("kind").withColumn("before", F.lag("after").over(order)))


def snapshot_at(cl: DataFrame, t: int) -> DataFrame:
    """(entry, value) alive at t, from all mutations up to it; combines before its shuffle."""
    last = cl.where(F.col("ts") <= t).groupBy("entry").agg(F.max_by("after", F.struct("ts", "seq")).alias("value"))
    return last.where("value is not null")


def states_at(cl: DataFrame, grid: IntervalGrid) -> DataFrame:
    """(entry, idx, value): the state of each entry at the end of each interval, null where it isn't alive.

    A version holds from its own time until the next one's, so it is copied to the ends in between; only mutations are shuffled
    and sorted, not entries times intervals.
    """
    order = Window.partitionBy("entry").orderBy("ts", "seq")
    v = cl.select("entry", "after", F.lag("ts").over(order).alias("earlier"), grid.position("ts").alias("i"), grid.position(F.lead("ts").over(order)).alias("j"))
    last = F.least(F.coalesce(F.col("j"), F.lit(grid.n)), F.lit(grid.n)) - 1
    empty = F.array().cast("array<bigint>")
    run = lambda lo, hi: F.when(hi >= lo, F.sequence(lo, hi)).otherwise(empty)
    held = F.transform(run(F.greatest(F.col("i"), F.lit(0)).cast("long"), last.cast("long")), lambda x: F.struct(x.alias("idx"), F.col("after").alias("value")))
    none = F.lit(None).cast(cl.schema["after"].dataType)
    early = F.when(F.col("earlier").isNull(), run(F.lit(0).cast("long"), (F.least(F.col("i"), F.lit(grid.n)) - 1).cast("long"))).otherwise(empty)
    return v.select("entry", F.explode(F.concat(F.transform(early, lambda x: F.struct(x.alias("idx"), none.alias("value"))), held)).alias("s")).select("entry", "s.*")


def chain_violations(cl: DataFrame) -> DataFrame:
    """Mutations whose before is not the previous after of their entry."""
    out = cl.withColumn("expected", F.lag("after").over(Window.partitionBy("entry").orderBy("ts", "seq")))
    return out.where(~F.col("before").eqNullSafe(F.col("expected"))).select("entry", "ts", "seq", "before", "expected")


def ordered(cl: DataFrame) -> DataFrame:
    """Range-partitioned and sorted by (ts, entry), for writing."""
    return cl.repartitionByRange("ts", "entry").sortWithinPartitions("ts", "entry", "seq")


def without_entry(cl: DataFrame, entry) -> DataFrame:
    """The neighbouring changelog: all of one entry's mutations are gone."""
    return cl.where(~F.col("entry").eqNullSafe(F.lit(entry)))


def with_entry(cl: DataFrame, mutations: DataFrame) -> DataFrame:
    return cl.unionByName(mutations)


def net_change(indexed: DataFrame, by: tuple[str, ...] = ("idx",)) -> DataFrame:
    """First before and last after of each entry and interval, where they differ."""
    first = F.min_by("before", F.struct("ts", "seq"))
    last = F.max_by("after", F.struct("ts", "seq"))
    return indexed.groupBy("entry", *by).agg(first.alias("before"), last.alias("after")).where(~F.col("before").eqNullSafe(F.col("after")))


def snapshot_diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """Rows of new that old lacks (+1) and the reverse (-1), multiplicity kept."""
    return new.exceptAll(old).withColumn("sign", F.lit(1)).unionByName(old.exceptAll(new).withColumn("sign", F.lit(-1)))
