"""Sources and sinks: tables by format, snapshot series, changelog and release writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.intervals import DAY, DAY_COLUMN

DAY_PARTS = 16


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """parquet, orc, csv, json, text, jdbc, or whatever the session has; pass a schema for csv and json."""
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema is not None else r).load(path) if fmt != "jdbc" else r.load()


def read_stream(spark: SparkSession, path: str, schema, fmt: str = "parquet", files_a_trigger: int | None = None, **options) -> DataFrame:
    r = spark.readStream.format(fmt).schema(schema).options(**options)
    return (r.option("maxFilesPerTrigger", files_a_trigger) if files_a_trigger else r).load(path)


def snapshot_series(spark: SparkSession, folders: dict[int, str], fmt: str = "parquet") -> list[tuple[int, DataFrame]]:
    """[(time, snapshot)] for changelog.from_snapshot_series."""
    return [(t, read(spark, p, fmt)) for t, p in sorted(folders.items())]


def write_changelog(cl: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Partitioned by day (DAY_COLUMN) and sorted, so a scan of a time range prunes folders and row groups. A day is dealt to
    `DAY_PARTS` tasks, so that no task writes a whole day."""
    day = F.floor(F.col("ts") / DAY).cast("long")
    cl.withColumn(DAY_COLUMN, day).repartition(DAY_COLUMN, F.pmod(F.xxhash64("entry"), F.lit(DAY_PARTS))).sortWithinPartitions(DAY_COLUMN, "ts", "entry").write.partitionBy(DAY_COLUMN).mode(mode).parquet(path)


def save_bucketed(cl: DataFrame, name: str, buckets: int) -> None:
    """As a table bucketed by entry: later windows and joins by entry need no shuffle."""
    cl.write.bucketBy(buckets, "entry").sortBy("entry", "ts").mode("overwrite").saveAsTable(name)


def write_release(release: DataFrame, path: str, fmt: str = "parquet", release_id: str = "") -> None:
    """One folder a release id; writing it twice is an error rather than a second answer."""
    release.withColumn("release_id", F.lit(release_id)).write.format(fmt).mode("errorifexists").save(f"{path}/release={release_id}")
