"""Continual releases over streams. Changelog time is commit time, so nothing is late there; event-time variants state what
late rows do. Append mode only: a published node is never changed."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

MICRO = "interval 1 microsecond"


def disjoint_stream(rows: DataFrame, ts: str, width: str, change, delay: str = "0 seconds", slide: str | None = None) -> DataFrame:
    """(start, end, exact) of windows (start, end]. Spark's windows are [start, end), so times are moved back a microsecond."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return rows.withColumn(ts, F.col(ts) - F.expr(MICRO)).withWatermark(ts, delay).groupBy(w.alias("w")).agg(F.sum(change).alias("exact")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "exact")


def dedup_stream(rows: DataFrame, ts: str, keys: list[str], delay: str) -> DataFrame:
    return rows.withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def session_stream(rows: DataFrame, ts: str, entry: str, gap: str, delay: str) -> DataFrame:
    """(entry, start, end, n): bursts of activity as entries of their own."""
    out = rows.withWatermark(ts, delay).groupBy(F.session_window(ts, gap).alias("w"), F.col(entry).alias("entry")).agg(F.count("*").alias("n"))
    return out.select("entry", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def interval_join_stream(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, within: str, delay: str) -> DataFrame:
    """Pairs of one key whose right time is after the left one by at most within; state is bounded by both watermarks."""
    a, b = left.withWatermark(left_ts, delay).alias("a"), right.withWatermark(right_ts, delay).alias("b")
    on = (F.col(f"a.{key}") == F.col(f"b.{key}")) & (F.col(f"b.{right_ts}") > F.col(f"a.{left_ts}")) & (F.col(f"b.{right_ts}") <= F.col(f"a.{left_ts}") + F.expr(f"interval {within}"))
    return a.join(b, on)


def enrich_stream(rows: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream rows with the columns of a static table, read anew in every micro-batch; no state. Rows without a match are kept."""
    return rows.join(static, key, "left")


def changelog_stream(rows: DataFrame, k: int | None = None, b: int | None = None) -> DataFrame:
    """rows: (entry long, ts long, seq long, value string) -> mutations (entry, ts, seq, before, after), no-ops dropped.

    State an entry: its last value and order, how many mutations it had and when the first was. k and b cut a suffix of each
    entry's chain. Rows of one micro-batch are ordered; a row older than its entry's last one goes no further.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        value, at, seq, n, first = state.get if state.exists else (None, -(2**62), -1, 0, -1)
        rows = sorted((tuple(r) for b_ in batches for r in b_[["ts", "seq", "value"]].itertuples(index=False)), key=lambda r: r[:2])
        out = []
        for ts, s, v in rows:
            v = None if v is None or v != v else v
            if (ts, s) <= (at, seq) or v == value:
                continue
            if (k is not None and n >= k) or (b is not None and n and ts > first + b):
                continue
            out.append((key[0], ts, s, value, v))
            first = ts if not n else first
            value, at, seq, n = v, ts, s, n + 1
        state.update((value, at, seq, n, first))
        if out:
            yield pd.DataFrame(out, columns=["entry", "ts", "seq", "before", "after"])

    return rows.groupBy("entry").applyInPandasWithState(step, "entry long, ts long, seq long, before string, after string", "value string, at long, seq long, n long, first long", "append", GroupStateTimeout.NoTimeout)


def late_side_output(rows: DataFrame, ts: str, arrival: str, allowed_micros: int) -> tuple[DataFrame, DataFrame]:
    """(on time, late): late rows are counted on their own and never change a published node."""
    late = F.col(arrival) - F.col(ts) > allowed_micros
    return rows.where(~late), rows.where(late)


def release_sink(release_id: str, folder: str, publish):
    """foreachBatch writer: publish(batch) is written once a batch id, so a restarted batch gives the same folder."""

    def write(batch: DataFrame, batch_id: int) -> None:
        publish(batch).withColumn("release_id", F.lit(release_id)).write.mode("overwrite").parquet(f"{folder}/batch={batch_id}")

    return write


def run_available(stream: DataFrame, folder: str, checkpoint: str) -> DataFrame:
    """Run all that is there and return what was written."""
    q = stream.writeStream.format("parquet").option("path", folder).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(folder)
