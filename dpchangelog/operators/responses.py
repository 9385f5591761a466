"""Randomized responses: static surveys, responses about mutations, and continual histograms from them.

Symbols carry dense codes 0 .. z - 1; a mutation pair (before, after) carries the code before * (z + 1) + after with
0 for null and symbol code + 1 otherwise. Alphabets are public. Reports are made a row at a time and counted by one
aggregate; only z or (z + 1)^2 counts an interval remain for estimation.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid
from ..functions.noise import Key, uniform
from . import changelog
from .hierarchy import cover_df
from .local import dense_rows, interval_keys, node_keys


def optimal_matrix(z: int, eps: float) -> tuple[float, float]:
    """(p on the diagonal, q off it) of the best eps-local response over z answers."""
    q = 1 / (z - 1 + math.exp(eps))
    return math.exp(eps) * q, q


class ResponseMatrix:
    """p[answer, truth]; each column sums to 1."""

    def __init__(self, p):
        self.p = np.array(p, float)
        if self.p.ndim != 2 or self.p.shape[0] != self.p.shape[1] or (self.p < 0).any() or not np.allclose(self.p.sum(0), 1):
            raise ValueError("a square matrix is needed whose columns are distributions")

    @staticmethod
    def optimal(z: int, eps: float) -> "ResponseMatrix":
        p, q = optimal_matrix(z, eps)
        return ResponseMatrix(np.full((z, z), q) + (p - q) * np.eye(z))

    def delta(self, eps: float) -> float:
        """Least delta at eps: the largest mass by which one column exceeds exp(eps) times another."""
        return max(float(np.maximum(0, self.p[:, [a]] - math.exp(eps) * self.p).sum(0).max()) for a in range(len(self.p)))

    def epsilon(self) -> float:
        """Pure eps; infinite if an answer is impossible for one truth only."""
        with np.errstate(divide="ignore", invalid="ignore"):
            logs = np.log(self.p)
            return float(np.nanmax(logs.max(1) - logs.min(1)))

    def respond(self, code: Column, key: Key, *parts) -> Column:
        """Inverse-CDF draw of an answer code, within whole-stage code. A null code answers for a symbol drawn at random: a mixture
        of the columns, so it is as private as they are, and every row gives an answer."""
        code = F.coalesce(code, F.floor(uniform(key, *parts, salt="f") * len(self.p)).cast("int"))
        u, cumulative = uniform(key, *parts), np.cumsum(self.p, 0)
        out = F.lit(None).cast("int")
        for truth in range(len(self.p)):
            answer = F.lit(len(self.p) - 1)
            for a in range(len(self.p) - 2, -1, -1):
                answer = F.when(u < float(cumulative[a, truth]), a).otherwise(answer)
            out = F.when(code == truth, answer).otherwise(out)
        return out

    def estimate(self, counts) -> np.ndarray:
        """Unbiased histogram from answer counts."""
        if np.linalg.cond(self.p) > 1e10:
            raise ValueError("the matrix can't be inverted")
        return np.linalg.solve(self.p, np.asarray(counts, float))


def respond(code: Column, z: int, eps: float, key: Key, *parts) -> Column:
    """Optimal response: the truth with probability p - q, else uniform over all z answers.

    A null code (null, or a value outside the alphabet) is always uniform, which is what a random symbol would answer: no answer
    gives the absence away, N answers come from N rows, and an estimate counts such a row as 1 / z of each symbol.
    """
    p, q = optimal_matrix(z, eps)
    other = F.floor(uniform(key, *parts, salt="b") * z).cast("int")
    return F.when(code.isNotNull() & (uniform(key, *parts) < p - q), code.cast("int")).otherwise(other)


def code_of(c: str, symbols: list[str]) -> Column:
    """Code of a symbol, null outside the alphabet."""
    return F.nullif(F.array_position(F.array(*[F.lit(s) for s in symbols]), F.col(c)), F.lit(0)).cast("int") - 1


def static_counts(df: DataFrame, entry: str, column: str, symbols: list[str], eps: float, key: Key) -> DataFrame:
    """(out_code, n) for every answer."""
    out = respond(code_of(column, symbols), len(symbols), eps, key, F.col(entry)).alias("out_code")
    seen = df.select(out).groupBy("out_code").agg(F.count("*").alias("n"))
    return df.sparkSession.range(len(symbols)).select(F.col("id").cast("int").alias("out_code")).join(seen, "out_code", "left").withColumn("n", F.coalesce("n", F.lit(0)))


def estimate_histogram(counts: DataFrame, symbols: list[str], eps: float) -> DataFrame:
    """(symbol, estimate): (n - q N) / (p - q), which equals the product with the inverse matrix."""
    p, q = optimal_matrix(len(symbols), eps)
    total = F.sum("n").over(Window.partitionBy())  # over z rows
    name = F.element_at(F.array(*[F.lit(s) for s in symbols]), F.col("out_code") + 1)
    return counts.select(name.alias("symbol"), ((F.col("n") - q * total) / (p - q)).alias("estimate"))


def pair_size(z: int, compact: bool = False) -> int:
    return z * z + z + 1 if compact else (z + 1) ** 2


def pair_code(before: Column, after: Column, z: int, compact: bool = False) -> Column:
    """before, after: codes or null. compact leaves out (r, r): codes are 0 for no change, then the true changes."""
    b, a = F.coalesce(before + 1, F.lit(0)), F.coalesce(after + 1, F.lit(0))
    if not compact:
        return (b * (z + 1) + a).cast("int")
    # Row b of the true changes has z entries, all a other than b.
    return F.when(a == b, 0).otherwise(1 + b * z + a - F.when(a > b, 1).otherwise(0)).cast("int")


def change_matrix(z: int, compact: bool = False) -> np.ndarray:
    """(z, pairs): +1 where a pair ends in a symbol, -1 where it starts there."""
    out = np.zeros((z, pair_size(z, compact)))
    for b in range(z + 1):
        for a in range(z + 1):
            if a == b:
                continue
            code = 1 + b * z + a - (a > b) if compact else b * (z + 1) + a
            if a:
                out[a - 1, code] += 1
            if b:
                out[b - 1, code] -= 1
    return out


def dense_pairs(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, symbols: list[str]) -> DataFrame:
    """(entry, idx, b, a) for every entry and interval; an entry without a change reports too (null, null)."""
    net = changelog.net_change(grid.assign(cl)).select("entry", "idx", code_of("before", symbols).alias("b"), code_of("after", symbols).alias("a"))
    return dense_rows(entries, net, interval_keys(grid.n), ["idx"], ["b", "a"])


def mutation_counts(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, symbols: list[str], eps: float, key: Key, compact: bool = False) -> DataFrame:
    """(idx, out_code, n): counted reports about each entry's net change in each interval."""
    z = len(symbols)
    truth = pair_code(F.col("b"), F.col("a"), z, compact)
    reports = dense_pairs(cl, entries, grid, symbols).select("idx", respond(truth, pair_size(z, compact), eps, key, F.col("entry"), F.col("idx")).alias("out_code"))
    return reports.groupBy("idx", "out_code").agg(F.count("*").alias("n"))


def estimate_change(counts: DataFrame, symbols: list[str], eps: float, compact: bool = False, by: tuple[str, ...] = ("idx",), with_var: bool = False) -> DataFrame:
    """(by..., symbol, estimate, [var]): (reports that end in the symbol - reports that start there) / (p - q).

    The rows of the change matrix add up to 0, so the inverse matrix comes down to this; reports (r, r) cancel. var: the most
    that the estimate's variance can be for that many reports.
    """
    z = len(symbols)
    p, q = optimal_matrix(pair_size(z, compact), eps)
    matrix = change_matrix(z, compact)
    sums = counts.groupBy(*by).agg(F.sum("n").alias("reports"), *[F.sum(F.expr("case " + " ".join(f"when out_code = {k} then {'n' if v > 0 else '-n'}" for k, v in enumerate(row) if v) + " else 0 end")).alias(f"s{i}") for i, row in enumerate(matrix)])
    pairs = F.array(*[F.struct(F.lit(s).alias("symbol"), (F.col(f"s{i}") / (p - q)).alias("estimate")) for i, s in enumerate(symbols)])
    var = [(F.col("reports") * worst_variance(z, eps, compact)).alias("var")] if with_var else []
    return sums.select(*by, F.explode(pairs).alias("e"), *var).select(*by, "e.symbol", "e.estimate", *(["var"] if with_var else []))


def estimate_change_by_matrix(counts, z: int, eps: float, compact: bool = False) -> np.ndarray:
    """The same of one interval's counts by M P^-1."""
    return change_matrix(z, compact) @ ResponseMatrix.optimal(pair_size(z, compact), eps).estimate(counts)


def continual_histogram(changes: DataFrame) -> DataFrame:
    """(idx, symbol, estimate): running sums of changes; rows are intervals times symbols."""
    w = Window.partitionBy("symbol").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return changes.select("idx", "symbol", F.sum("estimate").over(w).alias("estimate"))


def tree_counts(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, symbols: list[str], c: int, h: int, eps: float, key: Key) -> DataFrame:
    """(layer, idx, out_code, n): a survey at each node about the net change over that node's own interval. All layers come from
    one scan and one shuffle of net changes."""
    nodes = F.posexplode(F.array(*[F.floor(F.col("idx") / c**j).cast("long") for j in range(h)])).alias("layer", "node")
    rows = grid.assign(cl).select("entry", "ts", "seq", "before", "after", nodes).withColumnRenamed("node", "idx")
    net = changelog.net_change(rows, ("layer", "idx")).select("entry", "layer", "idx", code_of("before", symbols).alias("b"), code_of("after", symbols).alias("a"))
    every = dense_rows(entries, net, node_keys(grid.n, c, h), ["layer", "idx"], ["b", "a"])
    z = len(symbols)
    out = respond(pair_code(F.col("b"), F.col("a"), z), pair_size(z), eps, key, F.col("layer"), F.col("entry"), F.col("idx")).alias("out_code")
    return every.select("layer", "idx", out).groupBy("layer", "idx", "out_code").agg(F.count("*").alias("n"))


def tree_reports(cl: DataFrame, entries: DataFrame, grid: IntervalGrid, symbols: list[str], c: int, h: int, eps: float, key: Key) -> DataFrame:
    """(layer, idx, symbol, estimate, var): estimated change of each symbol over each node, and the most its variance can be."""
    counts = tree_counts(cl, entries, grid, symbols, c, h, eps, key)
    return estimate_change(counts, symbols, eps, by=("layer", "idx"), with_var=True)


def worst_variance(z: int, eps: float, compact: bool = False) -> float:
    """Most that one report adds to the variance of a symbol's estimated change: that of a report whose pair touches the symbol."""
    p, q = optimal_matrix(pair_size(z, compact), eps)
    gap = p - q
    return (2 * z * q + max(0.0, gap - gap * gap)) / gap**2


def prefix_histogram(nodes: DataFrame, n: int, c: int, h: int) -> DataFrame:
    """(idx, symbol, estimate, n_nodes, var): the histogram after every interval from the nodes that cover its prefix, so the
    variance grows with the logarithm of the time; nodes: tree_reports."""
    spark = nodes.sparkSession
    prefixes = spark.range(n).select(F.col("id").alias("range_id"), F.lit(0).cast("long").alias("l"), (F.col("id") + 1).alias("r"))
    met = cover_df(prefixes, c, h).join(nodes, ["layer", "idx"])
    return met.groupBy(F.col("range_id").alias("idx"), "symbol").agg(F.sum("estimate").alias("estimate"), F.count("*").alias("n_nodes"), F.sum("var").alias("var"))


def project(histogram: DataFrame, total: float, by: tuple[str, ...] = ("idx",)) -> DataFrame:
    """Post-processing: no negative counts, rescaled to a public total. Biased, no less private."""
    w = Window.partitionBy(*by)
    held = histogram.withColumn("estimate", F.greatest("estimate", F.lit(0.0)))
    return held.withColumn("estimate", F.when(F.sum("estimate").over(w) > 0, F.col("estimate") * total / F.sum("estimate").over(w)).otherwise(0.0))


def simulate_null_reports(n: int, z: int, eps: float, seed: int) -> np.ndarray:
    """Answer counts of n entries without a change, as one draw; for studies of utility, not a protocol."""
    p, q = optimal_matrix(z, eps)
    return np.random.default_rng(seed).multinomial(n, [p] + [q] * (z - 1))
