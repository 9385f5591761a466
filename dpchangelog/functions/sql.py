"""SQL functions and table functions of the library, as temporary functions of a session."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register(spark: SparkSession) -> None:
    """interval_idx(ts, t0, w), keyed_uniform(key), lap_noise(key, scale); interval_grid(t0, w, n), cover_nodes(l, r, c, h) and
    tree_nodes(n, c, h). The first three are SQL bodies, which Catalyst inlines."""
    spark.sql("create or replace temporary function interval_idx(ts bigint, t0 bigint, w bigint) returns bigint return (ts - t0 + pmod(t0 - ts, w)) div w - 1")
    spark.sql("create or replace temporary function keyed_uniform(k string) returns double return (cast(conv(substr(md5(k), 1, 13), 16, 10) as double) + 0.5) / 4503599627370496")
    spark.sql("create or replace temporary function lap_noise(k string, s double) returns double return -s * signum(keyed_uniform(k) - 0.5) * ln(1 - 2 * abs(keyed_uniform(k) - 0.5))")

    @udtf(returnType="idx bigint, start_us bigint, end_us bigint")
    class IntervalRows:
        def eval(self, t0: int, w: int, n: int):
            for i in range(n):
                yield i, t0 + i * w, t0 + (i + 1) * w

    @udtf(returnType="layer int, idx bigint")
    class CoverNodes:
        def eval(self, l: int, r: int, c: int, h: int):
            for layer in range(h):
                w = c**layer
                for i in range(-(-l // w), r // w):
                    p = i // c
                    if layer == h - 1 or p * w * c < l or (p + 1) * w * c > r:
                        yield layer, i

    @udtf(returnType="layer int, idx bigint")
    class TreeNodes:
        def eval(self, n: int, c: int, h: int):
            for layer in range(h):
                for i in range(-(-n // c**layer)):
                    yield layer, i

    for name, f in (("interval_grid", IntervalRows), ("cover_nodes", CoverNodes), ("tree_nodes", TreeNodes)):
        spark.udtf.register(name, f)
