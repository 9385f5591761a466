"""Constraints on mutations: at most k an entry, all within b, or one of several rules by entry."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def counts(cl: DataFrame) -> DataFrame:
    return cl.groupBy("entry").agg(F.count("*").alias("mutations"))


def lifespans(cl: DataFrame) -> DataFrame:
    return cl.groupBy("entry").agg((F.max("ts") - F.min("ts")).alias("lifespan"))


def violators(cl: DataFrame, k: int | None = None, b: int | None = None) -> DataFrame:
    """(entry, observed, limit) of entries beyond a constraint."""
    seen, limit = (counts(cl), k) if k is not None else (lifespans(cl), b)
    return seen.toDF("entry", "observed").where(F.col("observed") > limit).withColumn("limit", F.lit(limit).cast("long"))


def _rank() -> Column:
    return F.row_number().over(Window.partitionBy("entry").orderBy("ts", "seq"))


def enforce_k(cl: DataFrame, k: int) -> DataFrame:
    """The first k mutations of each entry. A suffix is cut, so chains stay whole; Spark limits before the shuffle."""
    return cl.withColumn("_n", _rank()).where(F.col("_n") <= k).drop("_n")


def _first() -> Column:
    """Time of the entry's first mutation, by the order that rank and lag use: one shuffle for all, and no entry is buffered."""
    return F.first("ts").over(Window.partitionBy("entry").orderBy("ts", "seq"))


def enforce_b(cl: DataFrame, b: int) -> DataFrame:
    """Mutations within b of their entry's first."""
    return cl.withColumn("_first", _first()).where(F.col("ts") <= F.col("_first") + b).drop("_first")


def enforce_hybrid(cl: DataFrame, rules: dict[str, dict[str, int]], label: str = "constraint_id") -> DataFrame:
    """rules: label -> {"k": ...} or {"b": ...}. Entries of other labels are left out. One pass over each entry."""
    out = cl.withColumns({"_n": _rank(), "_first": _first()})
    keep = F.lit(False)
    for name, rule in rules.items():
        held = F.col("_n") <= rule["k"] if "k" in rule else F.col("ts") <= F.col("_first") + rule["b"]
        keep = keep | ((F.col(label) == name) & held)
    return out.where(keep).drop("_n", "_first")


def transitions(cl: DataFrame) -> DataFrame:
    """State transitions and their counts; null is absence."""
    return cl.groupBy("before", "after").agg(F.count("*").alias("n"))


def strong_components(edges: list[tuple]) -> dict:
    """State -> representative of its strongly connected component. States are few."""
    nodes = sorted({x for e in edges for x in e}, key=str)
    ahead = {x: [b for a, b in edges if a == x] for x in nodes}
    reach = {}
    for x in nodes:
        seen, todo = {x}, [x]
        while todo:
            for y in ahead[todo.pop()]:
                if y not in seen:
                    seen.add(y)
                    todo.append(y)
        reach[x] = seen
    return {x: min((y for y in nodes if y in reach[x] and x in reach[y]), key=str) for x in nodes}


def mutation_bound(edges: list[tuple], start=None) -> tuple[int, dict]:
    """(k, component of each state): most moves between components on a path from start (null: before insertion)."""
    of = strong_components(edges)
    ahead: dict = {}
    for a, b in edges:
        if of[a] != of[b]:
            ahead.setdefault(of[a], set()).add(of[b])
    longest: dict = {}

    def walk(x) -> int:
        if x not in longest:
            longest[x] = max((1 + walk(y) for y in ahead.get(x, ())), default=0)
        return longest[x]

    return walk(of.get(start, start)), of


def composite_states(cl: DataFrame, component: dict) -> DataFrame:
    """The changelog over merged states; moves within a component are no mutations."""
    def merged(c):
        out = F.lit(None).cast("string")
        for state, name in component.items():
            if state is not None:
                out = F.when(F.col(c) == state, F.lit(name)).otherwise(out)
        return out

    out = cl.withColumns({"before": merged("before"), "after": merged("after")})
    return out.where(~F.col("before").eqNullSafe(F.col("after")))


def bucketed(value: Column, cuts: list[int]) -> Column:
    """A few states for many values: 0, 1, ..., len(cuts) by how many cuts are reached."""
    return sum((F.when(value >= c, 1).otherwise(0) for c in cuts), F.lit(0)).cast("long")
