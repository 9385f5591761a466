"""Hierarchical releases: layers of disjoint releases of widths W, W c, W c^2, ..., and answers to ranges from their nodes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.intervals import IntervalGrid, ceil_int
from ..functions.noise import Key, Noise
from . import linear
from .release import published


def node_grid(spark, n: int, c: int, h: int) -> DataFrame:
    """(layer, idx) of all nodes over n base intervals; the last node of a layer may reach beyond them."""
    sizes = [ceil_int(n, c**j) for j in range(h)]
    layers = spark.range(h).select(F.col("id").cast("int").alias("layer"), F.element_at(F.array(*[F.lit(s).cast("long") for s in sizes]), (F.col("id") + 1).cast("int")).alias("size"))
    return layers.select("layer", F.explode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1)).alias("idx"))


def exact_nodes(base: DataFrame, n: int, c: int, h: int, domain: DataFrame | None = None) -> DataFrame:
    """base: (idx, exact) of base intervals, from the one scan of the data -> (layer, idx, exact), dense. With a public domain
    (groups, symbols or coordinates), base and result have its columns too."""
    by = domain.columns if domain is not None else []
    rows = base.select(F.posexplode(F.array(*[F.floor(F.col("idx") / c**j).cast("long") for j in range(h)])).alias("layer", "node"), *by, "exact")
    sums = rows.groupBy("layer", F.col("node").alias("idx"), *by).agg(F.sum("exact").alias("exact"))
    every = node_grid(base.sparkSession, n, c, h)
    every = every.crossJoin(domain) if domain is not None else every  # nodes times a public domain, not data
    return every.join(sums, ["layer", "idx", *by], "left").withColumn("exact", F.coalesce("exact", F.lit(0)))


def published_nodes(nodes: DataFrame, l1: float, l2: float, noise: Noise | list[Noise], key: Key) -> DataFrame:
    """(layer, idx, by..., noisy, eps, sigma2). noise: one, or one a layer, where layers have budgets of their own."""
    by = [c for c in nodes.columns if c not in ("layer", "exact")]
    if isinstance(noise, Noise):
        return published(nodes, l1, l2, noise, key, "@layer", *by)
    parts = [F.col("layer"), *[F.col(c) for c in by]]
    pick = lambda values: F.element_at(F.array(*values), F.col("layer") + 1)
    drawn = pick([x.draw(l1, l2, key, *parts) for x in noise])
    return nodes.withColumns({"noisy": F.col("exact").cast("double") + drawn, "eps": pick([F.lit(float(x.eps)) for x in noise]), "sigma2": pick([F.lit(float(x.variance(l1, l2))) for x in noise])}).drop("exact")


def hierarchy(cl: DataFrame, grid: IntervalGrid, c: int, h: int, query: linear.LinearQuery, noise: Noise | list[Noise], key: Key, domain: DataFrame | None = None, group: str | None = None, from_beginning: bool = False) -> DataFrame:
    """(layer, idx, [group_key], noisy, eps, sigma2). Groups come from a public domain (group_key), never from the data.

    from_beginning: the first base interval reaches back without bound, so a prefix is the state and not only its change. The
    nodes over it then hold the state before the grid too; an entry touches no more nodes than before.
    """
    indexed = grid.assign(cl, from_beginning=from_beginning)
    by: tuple[str, ...] = ("idx",)
    if group:
        indexed, by = indexed.withColumnRenamed(group, "group_key") if group != "group_key" else indexed, ("idx", "group_key")
    return published_nodes(exact_nodes(linear.change(indexed, query, by), grid.n, c, h, domain), query.l1, query.l2, noise, key)


def hierarchy_histogram(cl: DataFrame, grid: IntervalGrid, c: int, h: int, symbols: DataFrame, noise: Noise | list[Noise], key: Key, from_beginning: bool = False) -> DataFrame:
    """(layer, idx, symbol, noisy, eps, sigma2): change of the histogram over each node; symbols is the public alphabet."""
    base = linear.histogram_change(grid.assign(cl, from_beginning=from_beginning))
    return published_nodes(exact_nodes(base, grid.n, c, h, symbols), linear.HISTOGRAM_L1, linear.HISTOGRAM_L2, noise, key)


def hierarchy_vector(cl: DataFrame, grid: IntervalGrid, c: int, h: int, width: int, clip_l2: float, noise: Noise | list[Noise], key: Key, from_beginning: bool = False) -> DataFrame:
    """(layer, idx, coord, noisy, eps, sigma2) of sums of vectors clipped to a length. A change moves a sum by twice the clip."""
    coords = cl.sparkSession.range(width).select(F.col("id").cast("int").alias("coord"))
    base = linear.vector_change(grid.assign(cl, from_beginning=from_beginning), width, clip_l2)
    l2 = 2 * clip_l2
    return published_nodes(exact_nodes(base, grid.n, c, h, coords), l2 * width**0.5, l2, noise, key)


def released_by(nodes: DataFrame, grid: IntervalGrid, c: int, now: int) -> DataFrame:
    """Nodes whose interval has ended by now."""
    end = F.lit(grid.start) + (F.col("idx") + 1) * F.lit(grid.width) * F.pow(F.lit(c), F.col("layer")).cast("long")
    return nodes.where(end <= now)


def _div(a: Column, w: int) -> Column:
    return F.floor(a / w).cast("long")


def _of_layer(j: int):
    return lambda i: F.struct(F.lit(j).alias("layer"), i.alias("idx"))


def cover_df(ranges: DataFrame, c: int, h: int) -> DataFrame:
    """ranges: (range_id, l, r) -> (range_id, layer, idx): the nodes that make up (l, r], in closed form, no search.

    At layer j the whole nodes are [ceil(l / c^j), floor(r / c^j)); the ones under a whole node above are left out.
    """
    l, r, parts = F.col("l"), F.col("r"), []
    empty = F.array().cast("array<bigint>")
    run = lambda lo, hi: F.when(hi > lo, F.sequence(lo, hi - 1)).otherwise(empty)
    for j in range(h):
        lo, hi = -_div(-l, c**j), _div(r, c**j)
        if j == h - 1:
            ids = run(lo, hi)
        else:
            up_lo, up_hi = -_div(-l, c ** (j + 1)) * c, _div(r, c ** (j + 1)) * c
            ids = F.when(up_hi <= up_lo, run(lo, hi)).otherwise(F.concat(run(lo, F.least(hi, up_lo)), run(F.greatest(lo, up_hi), hi)))
        parts.append(F.transform(ids, _of_layer(j)))
    return ranges.select("range_id", F.explode(F.concat(*parts)).alias("n")).select("range_id", "n.layer", "n.idx")


def range_query(nodes: DataFrame, ranges: DataFrame, c: int, h: int) -> DataFrame:
    """(range_id, [by...], estimate, n_nodes, var): an equi-join of covers with nodes; by: group, symbol or coordinate of nodes."""
    by = [x for x in nodes.columns if x not in ("layer", "idx", "noisy", "eps", "sigma2")]
    return cover_df(ranges, c, h).join(nodes, ["layer", "idx"]).groupBy("range_id", *by).agg(F.sum("noisy").alias("estimate"), F.count("*").alias("n_nodes"), F.sum("sigma2").alias("var"))


def prefix_series(nodes: DataFrame, n: int, c: int, h: int) -> DataFrame:
    """(idx, [by...], estimate, var): the total over (0, idx + 1] for every base interval; few nodes each."""
    prefixes = nodes.sparkSession.range(n).select(F.col("id").alias("range_id"), F.lit(0).cast("long").alias("l"), (F.col("id") + 1).alias("r"))
    return range_query(nodes, prefixes, c, h).withColumnRenamed("range_id", "idx").drop("n_nodes")


def make_consistent(nodes: DataFrame, n: int, c: int, h: int) -> DataFrame:
    """Least-squares smoothing of a tree of equal node variances, so a parent is the sum of its children.

    Both passes are linear, so neither is a loop. Up: a node's estimate is a weighted sum over its subtree, a weight a layer.
    Down: a node gains c^-d of the gap of each ancestor d layers up, the gap being the ancestor's estimate less its
    children's. A few equi-joins, whatever the height. Needs n to be a multiple of c^(h-1).
    """
    if n % c ** (h - 1):
        raise ValueError("the base intervals fill whole top nodes")
    own = [(c ** (j + 1) - c**j) / (c ** (j + 1) - 1) for j in range(h)]  # 1 at the base
    weight = [[0.0] * h for _ in range(h)]
    for j in range(h):
        weight[j][j] = own[j]
        for k in range(j):
            weight[j][k] = (1 - own[j]) * weight[j - 1][k]
    table = F.array(*[F.array(*[F.lit(x) for x in row]) for row in weight])
    above = lambda idx, d: F.floor(F.col(idx) / F.pow(F.lit(c), d)).cast("long")
    up = nodes.select("layer", "idx", "noisy", F.explode(F.sequence(F.col("layer"), F.lit(h - 1))).alias("j"))
    part = F.element_at(F.element_at(table, F.col("j") + 1), F.col("layer") + 1) * F.col("noisy")
    z = up.select(above("idx", F.col("j") - F.col("layer")).alias("i"), "j", part.alias("x")).groupBy(F.col("j").alias("layer"), F.col("i").alias("idx")).agg(F.sum("x").alias("z"))
    children = z.where(F.col("layer") < h - 1).groupBy((F.col("layer") + 1).alias("layer"), above("idx", F.lit(1)).alias("idx")).agg(F.sum("z").alias("s"))
    gap = z.join(children, ["layer", "idx"]).select(F.col("layer").alias("m"), F.col("idx").alias("a"), (F.col("z") - F.col("s")).alias("g"))
    down = z.where(F.col("layer") < h - 1).select("layer", "idx", F.explode(F.sequence(F.col("layer") + 1, F.lit(h - 1))).alias("m"))
    far = F.col("m") - F.col("layer")
    gain = down.withColumn("a", above("idx", far)).join(gap, ["m", "a"]).groupBy("layer", "idx").agg(F.sum(F.col("g") / F.pow(F.lit(c), far)).alias("d"))
    return z.join(gain, ["layer", "idx"], "left").select("layer", "idx", (F.col("z") + F.coalesce("d", F.lit(0.0))).alias("consistent"))


def layer_weights(h: int, total_eps: float, ratio: float = 1.0) -> list[float]:
    """Budgets of the layers in geometric progression; equal at ratio 1."""
    w = [ratio**j for j in range(h)]
    return [total_eps * x / sum(w) for x in w]
