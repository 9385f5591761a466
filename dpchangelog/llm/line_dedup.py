"""Operator 3: removal of repeated passages by overlapping three-line windows. DataFrame functions only.

Lines are hashed trimmed of spaces. Every three consecutive lines make a window (windows of blank lines alone make none).
A window that occurs twice or more anywhere keeps its first occurrence, by doc_id and then position; the lines that later
occurrences cover are removed, overlaps merged. A text of fewer than three lines has no window and stays as it is.

Windows carry 128 bits of hash. One aggregate, combined before its shuffle, finds for each window how often and in which
document it first occurs; a window of a third of all documents is one row there. Joining that back is a plain equi-join
of the windows with the repeated ones, whose skew Spark splits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, quoted

WINDOW = 3


def _free(name: str, taken: list[str]) -> str:
    while name.lower() in (c.lower() for c in taken):
        name += "_"
    return name


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """a, b, h: the key of a document (its id, whether that is null, and a hash of its text)."""
    i, t = F.col(quoted(id_col)), F.col(quoted(text_col))
    return docs.select(F.coalesce(i.cast("long"), F.lit(0)).alias("a"), i.isNull().alias("b"), F.xxhash64(t).alias("h"), t.alias("t"), F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias("row"))


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def windows(keyed: DataFrame) -> DataFrame:
    """(a, b, h, pos, x, y, first): window of the lines pos to pos + 2, first within its document or not."""
    hashed = keyed.where(F.length("t") - F.length(F.replace("t", F.lit("\n"))) >= WINDOW - 1).select("a", "b", "h", F.transform(_lines(F.col("t")), lambda s: F.trim(s)).alias("s"))
    hashed = hashed.select("a", "b", "h", F.transform("s", lambda s: F.xxhash64(s)).alias("l"), F.transform("s", lambda s: F.xxhash64(F.lit(1), s)).alias("m"))
    blank = F.xxhash64(F.lit(""))
    at = F.sequence(F.lit(0), F.size("l") - WINDOW)
    made = F.transform(at, lambda i: F.struct(F.xxhash64(F.get("l", i), F.get("l", i + 1), F.get("l", i + 2)).alias("x"), F.xxhash64(F.get("m", i), F.get("m", i + 1), F.get("m", i + 2)).alias("y"), i.alias("pos"), ((F.get("l", i) == blank) & (F.get("l", i + 1) == blank) & (F.get("l", i + 2) == blank)).alias("empty")))
    made = F.sort_array(F.filter(made, lambda w: ~w["empty"]))
    # Sorted by hash, then position: the first of equal neighbours is the first in its document.
    rows = hashed.select("a", "b", "h", made.alias("w"))
    rows = rows.select("a", "b", "h", F.posexplode(F.transform("w", lambda w, k: F.struct(w["x"].alias("x"), w["y"].alias("y"), w["pos"].alias("pos"), ((k == 0) | (F.get("w", k - 1)["x"] != w["x"]) | (F.get("w", k - 1)["y"] != w["y"])).alias("first")))).alias("k", "v"))
    return rows.select("a", "b", "h", "v.*")


def removals(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(a, b, h, gone): line numbers to remove of each document that loses any."""
    w = windows(_keyed(docs, id_col, text_col))
    # The order of documents: ids ascending, a null id last. Repeated rows of one document are one occurrence.
    order = F.when(F.col("b"), F.lit(None)).otherwise(F.col("a"))
    # n counts documents by the extremes of their ids and text hashes, so equal rows of a document don't count as repeats.
    found = w.groupBy("x", "y").agg(
        F.min(order).alias("a1"), F.max(order).alias("a2"), F.min("b").alias("nb"), F.max("b").alias("xb"), F.min("h").alias("h1"), F.max("h").alias("h2"), F.max(~F.col("first")).alias("inside")
    )
    repeated = found.where("inside or a1 <> a2 or nb <> xb or h1 <> h2").select("x", "y", "a1", "h1", "nb")
    later = w.join(repeated, ["x", "y"]).where(~(F.col("first") & F.when(F.col("nb"), F.col("b") & (F.col("h") == F.col("h1"))).otherwise(~F.col("b") & (F.col("a") == F.col("a1")))))
    return later.groupBy("a", "b", "h").agg(F.collect_set("pos").alias("starts"))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with repeated passages cut from the text, and two more columns, n_lines and n_removed (long).

    Null and empty texts stay (0 and 1 lines). Repeated rows of one id and text count as one document and are all treated
    alike; rows of one id with other texts are told apart by text, and the first occurrence among them keeps its lines in
    each. A null id is later than any other; among null ids the smallest text hash is first. Extra columns are kept under
    any name; where one is called n_lines or n_removed (in any case), the new column of that name gets underscores behind it
    until it is free. A document may become an empty text, if all its lines are covered.
    """
    prepare(docs.sparkSession)
    keyed = _keyed(docs, id_col, text_col)
    joined = keyed.join(removals(docs, id_col, text_col), ["a", "b", "h"], "left")
    covered = F.array_distinct(F.flatten(F.transform("starts", lambda p: F.array(p, p + 1, p + 2))))
    # The covered positions in order, as runs: what stays lies between them.
    lines = _lines(F.col("t"))
    sized = joined.withColumn("gone", F.sort_array(covered)).withColumn("n", F.when(F.col("t").isNull(), 0).otherwise(F.size(lines)))
    edges = F.concat(F.array(F.lit(-1)), F.col("gone"), F.array(F.col("n").cast("int")))
    gaps = F.filter(F.transform(F.sequence(F.lit(0), F.size("gone")), lambda k: F.struct(F.get("e", k).alias("lo"), F.get("e", k + 1).alias("hi"))), lambda g: g["hi"] - g["lo"] > 1)
    # The second mention of ls keeps Spark from computing it anew for every gap.
    kept = F.when(F.size("ls") > 0, F.flatten(F.transform(gaps, lambda g: F.slice(F.col("ls"), g["lo"] + 2, g["hi"] - g["lo"] - 1))))
    cut_text = F.when(F.col("gone").isNull(), F.col("t")).otherwise(F.array_join("kept", "\n"))
    sized = sized.withColumn("e", F.when(F.col("gone").isNotNull(), edges)).withColumn("ls", F.when(F.col("gone").isNotNull(), lines)).withColumn("kept", F.when(F.col("gone").isNotNull(), kept))
    out = [cut_text.alias(c) if c == text_col else F.col(f"row.{quoted(c)}").alias(c) for c in docs.columns]
    return sized.select(*out, F.col("n").cast("long").alias(_free("n_lines", docs.columns)), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias(_free("n_removed", docs.columns)))


def op3(spark: SparkSession, docs: DataFrame) -> DataFrame:
    out = dedup_lines(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_removed", F.md5("text").alias("text_md5"))


#: The same over DuckDB; hashes are replaced by the lines themselves.
SQL = """
with ls as (select doc_id, string_split(text, chr(10)) as l from documents where text is not null),
lines as (select doc_id, l[p + 1] as line, p as pos from (select doc_id, l, unnest(range(len(l))) as p from ls)),
win as (
  select doc_id, pos, t1 || chr(10) || t2 || chr(10) || t3 as w from (
    select doc_id, pos, trim(line, ' ') as t1, lead(trim(line, ' ')) over o as t2, lead(trim(line, ' '), 2) over o as t3 from lines window o as (partition by doc_id order by pos))
  where t3 is not null and t1 || t2 || t3 <> ''),
later as (select doc_id, pos from (select doc_id, pos, row_number() over (partition by w order by doc_id, pos) as k from win) where k > 1),
gone as (select distinct doc_id, pos + d as pos from later, (values (0), (1), (2)) as v(d)),
kept as (
  select doc_id, count(g) as n_removed, string_agg(line, chr(10) order by pos) filter (where g is null) as text
  from (select l.doc_id, l.pos, l.line, g.pos as g from lines l left join gone g on l.doc_id = g.doc_id and l.pos = g.pos) group by doc_id)
select d.doc_id, cast(coalesce(len(string_split(d.text, chr(10))), 0) as bigint) as n_lines, cast(coalesce(k.n_removed, 0) as bigint) as n_removed,
  case when d.text is null then null else md5(coalesce(k.text, '')) end as text_md5
from documents d left join kept k on d.doc_id = k.doc_id
"""
