"""Measures of cost and accuracy."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid
from ..functions.noise import Key, Noise
from ..plans.accounting import cover_bound, folds_sliding_b, folds_sliding_k, folds_tree_b, folds_tree_k, height_for
from ..plans.planner import worst_cover
from .hierarchy import cover_df
from .responses import ResponseMatrix, change_matrix, optimal_matrix, pair_size
from .sliding import SlidingSpec


def touched_disjoint(cl: DataFrame, grid: IntervalGrid) -> DataFrame:
    """(entry, idx) of every query an entry touches."""
    return grid.assign(cl).select("entry", "idx").distinct()


def touched_tree(cl: DataFrame, grid: IntervalGrid, c: int, h: int) -> DataFrame:
    nodes = F.posexplode(F.array(*[F.floor(F.col("idx") / c**j).cast("long") for j in range(h)])).alias("layer", "node")
    return touched_disjoint(cl, grid).select("entry", nodes).distinct()


def touched_sliding(cl: DataFrame, spec: SlidingSpec) -> DataFrame:
    """Window i is touched if t1 + i P - W < ts <= t1 + i P."""
    a = F.col("ts") - spec.t1
    first = F.greatest(F.lit(0), F.call_function("div", a + F.pmod(-a, F.lit(spec.p)), F.lit(spec.p)))
    b = a + (spec.w - 1)
    last = F.least(F.lit(spec.n - 1), F.call_function("div", b - F.pmod(b, F.lit(spec.p)), F.lit(spec.p)))
    held = cl.select("entry", first.cast("long").alias("i"), last.cast("long").alias("j")).where("i <= j").distinct()
    return held.select("entry", F.explode(F.sequence("i", "j")).alias("idx")).distinct()


def touch_counts(touched: DataFrame) -> DataFrame:
    return touched.groupBy("entry").agg(F.count("*").alias("touched"))


def parallel_bound(touched: DataFrame, budgets: DataFrame) -> DataFrame:
    """(entry, eps, delta): composed budget of the queries an entry touches; the release's is the largest. budgets: (idx,
    eps, delta). The value depends on the data, so it serves tests and is never published."""
    return touched.join(budgets, "idx").groupBy("entry").agg(F.sum("eps").alias("eps"), F.sum("delta").alias("delta"))


def cover_statistics(c: int, h: int, lengths) -> list[tuple[int, int, int]]:
    """(length, most nodes over all offsets, bound)."""
    return [(n, worst_cover(n, c, h), cover_bound(n, c)) for n in lengths]


def matched_ratio(w: int, p: int, c: int, h: int | None = None, k: int | None = 1, b: int | None = None) -> dict[str, float]:
    """Worst-case variance of tree (bound and exact cover) and flat releases over the direct one's, at one total budget."""
    g = math.gcd(w, p)
    n = w // g
    h = h or height_for(n, c)
    d = folds_sliding_k(k, w, p) if b is None else folds_sliding_b(b, w, p)
    t = folds_tree_k(h, k) if b is None else folds_tree_b(h, c, b, g)
    f = folds_tree_k(1, k) if b is None else folds_tree_b(1, c, b, g)
    return {"tree_bound": 2 * (c - 1) * h * (t / d) ** 2, "tree_exact": worst_cover(n, c, h) * (t / d) ** 2, "flat": n * (f / d) ** 2}


def monte_carlo(exact: DataFrame, noise: Noise, l1: float, l2: float, runs: int, key: Key, layer: str = "0") -> DataFrame:
    """(idx, bias, var): mean and variance of answer less truth, over releases that differ in their key only: run r is released
    under the key's release name and "/r". The data aren't scanned again."""
    draws = exact.crossJoin(exact.sparkSession.range(runs).select(F.col("id").alias("run")))  # intervals times runs
    noisy = F.col("exact").cast("double") + noise.draw(l1, l2, key, layer, F.col("idx"), F.col("run"))
    return draws.select("idx", (noisy - F.col("exact")).alias("e")).groupBy("idx").agg(F.avg("e").alias("bias"), F.var_samp("e").alias("var"))


def cover_monte_carlo(nodes: DataFrame, ranges: DataFrame, c: int, h: int, noise: Noise, l1: float, l2: float, runs: int, key: Key, layer: str | None = None) -> DataFrame:
    """(idx, bias, var) of range answers from a tree over many keys; nodes: (layer, idx, exact); ranges: (range_id, l, r);
    layer: a name that stands for the layer in the draws."""
    held = cover_df(ranges, c, h).join(nodes, ["layer", "idx"])
    draws = held.crossJoin(nodes.sparkSession.range(runs).select(F.col("id").alias("run")))
    noisy = F.col("exact").cast("double") + noise.draw(l1, l2, key, F.col("layer") if layer is None else layer, F.col("idx"), F.col("run"))
    per = draws.groupBy("range_id", "run").agg(F.sum(noisy - F.col("exact")).alias("e"))
    return per.groupBy(F.col("range_id").alias("idx")).agg(F.avg("e").alias("bias"), F.var_samp("e").alias("var"))


def errors(joined: DataFrame, noisy: str = "noisy", exact: str = "exact") -> DataFrame:
    """One row: mae, rmse, max_err, rel_err, l1, l2."""
    e = F.abs(F.col(noisy) - F.col(exact))
    return joined.agg(F.avg(e).alias("mae"), F.sqrt(F.avg(e * e)).alias("rmse"), F.max(e).alias("max_err"), (F.sum(e) / F.greatest(F.sum(F.abs(F.col(exact))), F.lit(1e-12))).alias("rel_err"), F.sum(e).alias("l1"), F.sqrt(F.sum(e * e)).alias("l2"))


def truncation(history: DataFrame, value: str, clips: list[int]) -> DataFrame:
    """(clip, lost, clipped_rows) for many bounds from one scan."""
    v = F.col(value)
    sums = history.agg(*[F.sum(F.greatest(v - c, F.lit(0))).alias(f"l{c}") for c in clips], *[F.sum((v > c).cast("long")).alias(f"n{c}") for c in clips])
    rows = F.array(*[F.struct(F.lit(c).cast("long").alias("clip"), F.col(f"l{c}").alias("lost"), F.col(f"n{c}").alias("clipped_rows")) for c in clips])
    return sums.select(F.explode(rows).alias("r")).select("r.*")


def change_covariance(counts, z: int, eps: float, compact: bool = False) -> np.ndarray:
    """Plug-in covariance of a change estimate from answer counts: A (diag(O) - O O^T / N) A^T with A = M P^-1."""
    o = np.asarray(counts, float)
    p = ResponseMatrix.optimal(pair_size(z, compact), eps).p
    a = change_matrix(z, compact) @ np.linalg.inv(p)
    return a @ (np.diag(o) - np.outer(o, o) / o.sum()) @ a.T


def plug_in_covariance(counts: DataFrame, symbols: list[str], eps: float, by: tuple[str, ...] = ("idx",)) -> DataFrame:
    """(by..., one, other, cov): the same for all pairs of symbols and all intervals at once, from answer counts alone. The rows
    of the change matrix add up to 0, so A is the change matrix over p - q."""
    z = len(symbols)
    p, q = optimal_matrix(pair_size(z), eps)
    m = change_matrix(z)
    case = lambda row: F.expr("case " + " ".join(f"when out_code = {k} then {int(v)}L" for k, v in enumerate(row) if v) + " else 0L end")
    pairs = [(i, j) for i in range(z) for j in range(z)]
    sums = counts.groupBy(*by).agg(F.sum("n").alias("total"), *[F.sum(case(m[i]) * F.col("n")).alias(f"a{i}") for i in range(z)], *[F.sum(case(m[i] * m[j]) * F.col("n")).alias(f"b{i}_{j}") for i, j in pairs])
    cov = lambda i, j: (F.col(f"b{i}_{j}") - F.col(f"a{i}") * F.col(f"a{j}") / F.col("total")) / (p - q) ** 2
    rows = F.array(*[F.struct(F.lit(symbols[i]).alias("one"), F.lit(symbols[j]).alias("other"), cov(i, j).alias("cov")) for i, j in pairs])
    return sums.select(*by, F.explode(rows).alias("r")).select(*by, "r.one", "r.other", "r.cov")


def change_variance(entries: float, touching: float, z: int, eps: float, compact: bool = False) -> float:
    """Exact variance of one symbol's estimate: entries reports, of which touching change that symbol."""
    p, q = optimal_matrix(pair_size(z, compact), eps)
    return (2 * z * q * entries + touching * ((p - q) - (p - q) ** 2)) / (p - q) ** 2


def output_ratio(one, other, bins, smoothing: float = 1.0) -> np.ndarray:
    """Log ratio of the frequencies of two samples of answers, a bin each; for checks on neighbouring tables."""
    a, b = (np.histogram(x, bins)[0] + smoothing for x in (one, other))
    return np.log(a / a.sum()) - np.log(b / b.sum())


def observed(df: DataFrame, name: str):
    """(df, observation): row count taken while df runs."""
    from pyspark.sql import Observation

    o = Observation(name)
    return df.observe(o, F.count(F.lit(1)).alias("rows")), o


def cost(df: DataFrame) -> dict[str, float]:
    """Run df and say what it took: rows, seconds, rows a second, bytes of files scanned and bytes written to shuffles, from the
    metrics of its own physical plan."""
    import time

    qe = df._jdf.queryExecution()
    began = time.time()
    rows = qe.toRdd().count()
    took = time.time() - began
    totals = {"filesSize": 0, "shuffleBytesWritten": 0}
    todo = [qe.executedPlan()]
    while todo:
        node = todo.pop()
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if kind.endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        for name in totals:
            found = node.metrics().get(name)
            totals[name] += found.get().value() if found.isDefined() else 0
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return {"rows": rows, "seconds": took, "rows_a_second": rows / max(took, 1e-9), "scanned_bytes": totals["filesSize"], "shuffled_bytes": totals["shuffleBytesWritten"]}
