"""Session helpers and the connected-components routine shared by the near-duplicate operators."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of one Arrow batch. Texts of a batch are held in memory together, so this is below Spark's default of 10,000.
ARROW_ROWS = "2000"
_shipped: set[str] = set()
_made: list[str] = []


def prepare(spark: SparkSession) -> None:
    """Make the package importable on executors, set a checkpoint folder where none is set, and bound Arrow batches."""
    sc = spark.sparkContext
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS)
    if sc.applicationId not in _shipped:
        root = Path(__file__).resolve().parents[1]
        target = os.path.join(tempfile.mkdtemp(), "llm_code.zip")  # the driver serves it to executors
        with zipfile.ZipFile(target, "w") as z:
            for p in sorted(root.rglob("*.py")):
                z.write(p, p.relative_to(root.parent))
        sc.addPyFile(target)
        _shipped.add(sc.applicationId)
    shared_dir(spark)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a local master gets a folder of our
    own; a cluster must name one, as a folder of one machine would lose what others write."""
    sc = spark.sparkContext
    configured = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not configured:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        configured = "file://" + tempfile.mkdtemp(prefix="shared-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(configured)
    return configured.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; made() lists those given out."""
    _made.append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return _made[-1]


def made() -> list[str]:
    return _made


def discard(spark: SparkSession, paths: list[str]) -> None:
    """Delete intermediates once nothing reads them any more."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for p in paths:
        at = jvm.org.apache.hadoop.fs.Path(p)
        at.getFileSystem(conf).delete(at, True)
        if p in _made:
            _made.remove(p)


def cut(df: DataFrame) -> DataFrame:
    """Cut lineage with a reliable checkpoint in the shared folder; survives the loss of executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: for rows too wide to compute twice."""
    at = shared_path(df.sparkSession, name)
    df.write.parquet(at)
    return df.sparkSession.read.schema(df.schema).parquet(at)


def quoted(c: str) -> str:
    """A column's name as SQL takes it, whatever it holds."""
    return "`" + c.replace("`", "``") + "`"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Copies of a label's row in joins by label, so that no task has all members of a large component.
SALTS = 32


def forest(n: int, links) -> np.ndarray:
    """Root of each of n rows, by union of the links; the root is the smallest row."""
    up = np.arange(n)

    def root(i):
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for a, b in links:
        a, b = root(a), root(b)
        if a != b:
            up[max(a, b)] = min(a, b)
    while (up != up[up]).any():
        up = up[up]
    return up


def star_links(root: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(child, parent) ids: each row but the smallest of a root, linked to the smallest."""
    order = np.lexsort((ids, root))
    r = root[order]
    first = np.r_[True, r[1:] != r[:-1]][: len(r)]
    start = np.flatnonzero(first)[np.cumsum(first) - 1] if len(r) else np.zeros(0, np.int64)
    child = np.flatnonzero(~first)
    return ids[order[child]], ids[order[start[child]]]


def _salted(rows: DataFrame, names: DataFrame, key: str) -> DataFrame:
    """rows left-joined with names (key, label), one row a key of names, in SALTS parts of each key."""
    salt = F.pmod(F.xxhash64("node"), F.lit(SALTS)).cast("int")
    return rows.withColumn("salt", salt).join(names.select(key, "label", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt")), [key, "salt"], "left").drop("salt")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable id of every node that has an edge: (u, v) -> (node, component).

    First the graph is contracted, without a join: a node's smaller neighbours are gathered (from stars of buckets these are as
    many as the node's buckets) and all linked to the smallest of them, its parent. Nodes that are nobody's neighbour then go
    with their parents; what is left is about the stars' centres. There minimum labels travel along edges and then jump to their
    label's label, so long chains shrink by about half in each round. Only aggregates that combine before the shuffle and
    equi-joins are used, those by label salted; nothing is collected but one count a round. Self-loops, repeats and either
    direction of an edge are accepted; null ends are ignored.
    """
    e = edges.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    held = cut(e.groupBy("u").agg(F.collect_set("v").alias("vs")).select("u", "vs", F.array_min("vs").alias("p")))
    centres = cut(held.select(F.explode("vs").alias("u")).distinct())
    across = held.select(F.explode("vs").alias("u"), F.col("p").alias("v")).where("u <> v")
    inner = held.join(centres, "u", "left_semi").select("u", F.col("p").alias("v"))
    g = across.unionByName(inner)
    g = cut(g.unionByName(g.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    labels = cut(g.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("m")).select("node", F.least("node", "m").alias("label")))
    for _ in range(max_rounds):
        heard = g.join(labels.select(F.col("node").alias("v"), "label"), "v").groupBy(F.col("u").alias("node")).agg(F.min("label").alias("heard"))
        low = labels.join(heard, "node", "left").select("node", F.col("label").alias("was"), F.least("label", F.coalesce("heard", "label")).alias("at"))
        # Labels that are to move on: few, and one row each before they are salted.
        asked = labels.select(F.col("label").alias("node")).distinct()
        up = labels.where("node <> label").join(asked, "node").select(F.col("node").alias("at"), "label")
        labels = cut(_salted(low, up, "at").select("node", "was", F.least("at", F.coalesce("label", "at")).alias("label")))
        if labels.where("was <> label").isEmpty():
            break
        labels = labels.select("node", "label")
    else:
        raise RuntimeError("components did not settle")
    nodes = held.select(F.col("u").alias("node"), "p").unionByName(centres.select(F.col("u").alias("node"), F.col("u").alias("p"))).groupBy("node").agg(F.min("p").alias("p"))
    return _salted(nodes, labels.select(F.col("node").alias("p"), "label"), "p").select("node", F.coalesce("label", "p").alias("component"))
