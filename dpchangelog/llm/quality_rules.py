"""Operator 4: quality rules with robust multivariate outliers. DataFrame functions only.

Base rules look at one document. Documents that pass them are held, as vectors of transformed statistics, against the
minimum-covariance-determinant estimate of their language and source: the mean and covariance of the three quarters of
the group's documents with the smallest Mahalanobis distances, found by concentration steps from two starts (median and
quartiles; mean and variance), of which the one with the smaller determinant counts. Documents at a squared distance
above the 0.999 quantile of chi-square are rejected.

Every group has an estimate of its own, whatever its size. Languages and the whole corpus are fitted as well, and a group's
estimate is drawn toward its language's as if SHRINK documents of the language belonged to it, and the language's likewise toward
that of all: a group of a few documents is judged nearly as its language, one of thousands by itself, without a switch between.

One concentration step is one aggregate: documents are put into bins of their logarithmic distance, each bin with its
count, sums and products; whole bins are taken from the nearest on until they hold the wanted share. So a step needs no
sort, no quantile over rows, and moves a bounded number of rows a group, however many documents a group has.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, prepare, quoted, stored

#: Documents of the language that are added to a group, and of the corpus to a language.
SHRINK = 60
SHARE, STEPS = 0.75, 5
#: chi-square with 5 degrees of freedom: the quantile 0.999, and the factor that makes the covariance of the nearest 0.75 consistent.
CUTOFF, CONSISTENCY = 20.515, 1.4125
#: What a document may differ by, in one statistic alone, from a group that is quite alike in it, in the order of VECTOR: ten times
#: the words, twice the mean word length, 10 % of symbols, 15 % of repeated lines and of repeated words.
LIMITS = (10, 2, 1 + 10, 1 + 15, 1 + 15)
#: Standard deviations that are added to each statistic's own, so that each can reject by itself, and only beyond its limit.
FLOOR = tuple(math.log(x) / math.sqrt(CUTOFF) for x in LIMITS)
#: Lines and words without repeats that each document is given for its shares of repeats: a single repeated line is a large
#: share of a short document and says little, and the addition fades in long ones.
CLEAN_LINES, CLEAN_WORDS = 40, 400
#: Bins of distances double their width after so many.
BINS = 16
VECTOR = {
    "x0": "ln(1D + n_words)",
    "x1": "ln(greatest(word_chars, 1L) / cast(greatest(n_words, 1L) as double))",
    "x2": "ln(1D + 100D * n_symbols / greatest(word_chars, 1L))",
    "x3": f"ln(1D + 100D * n_dup_lines / (n_lines + {CLEAN_LINES}L))",
    "x4": f"ln(1D + 100D * n_repeat_words / (n_words + {CLEAN_WORDS}L))",
}
P = len(VECTOR)
PAIRS = [(i, j) for i in range(P) for j in range(i + 1)]
#: Groups whose estimates are broadcast, at most; with more they are joined by a shuffle.
BROADCAST_GROUPS = 100_000
SPAN = 8  # words of a window


def text_statistics(df: DataFrame, text: Column) -> DataFrame:
    """df with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines and base_failed."""
    own = df.columns
    df = df.select(*own, F.coalesce(text, F.lit("")).alias("_t"))
    word = lambda w: w != ""
    df = df.select(*own, "_t", F.filter(F.split("_t", "[ \\t-\\r]+"), word).alias("_w"), F.filter(F.split("_t", "\n"), lambda s: s.rlike("[^ \\t-\\r]")).alias("_l"))
    df = df.select(
        *own,
        F.size("_w").cast("long").alias("n_words"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("_t", "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.size("_l").cast("long").alias("n_lines"),
        F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"),
    )
    stats = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines"]
    df = df.select(*own, *stats, F.when(F.size("_h") > SPAN, F.transform(F.sequence(F.lit(0), F.size("_h") - SPAN), lambda i: F.xxhash64(*[F.get("_h", i + k) for k in range(SPAN)]))).alias("_g"))
    # Windows are sorted only in texts that hold a repeated one; equal neighbours give the repeated positions.
    df = df.select(*own, *stats, F.when(F.size(F.array_distinct("_g")) < F.size("_g"), F.sort_array(F.transform("_g", lambda g, i: F.struct(g.alias("g"), i.alias("i"))))).alias("_s"))
    again = F.transform("_s", lambda v, k: F.when((F.get("_s", k - 1)["g"] == v["g"]) | (F.get("_s", k + 1)["g"] == v["g"]), v["i"]))
    df = df.select(*own, *stats, F.sort_array(F.filter(again, lambda i: i.isNotNull())).alias("_p"))
    covered = F.aggregate(F.transform("_p", lambda x, k: F.least(F.lit(SPAN), F.coalesce(F.get("_p", k + 1) - x, F.lit(SPAN)))), F.lit(0), lambda a, x: a + x)
    # A generator: filters on what it gives aren't pushed into the expressions above, where each would compute them all anew.
    stats.append("n_repeat_words")
    df = df.select(*own, *stats[:-1], F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"))
    df = df.select(*own, F.inline(F.array(F.struct(*stats))))
    return df.withColumn("base_failed", (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words")))


def _key(c: str) -> Column:
    return F.coalesce(F.concat(F.lit("="), F.col(c).cast("string")), F.lit("null"))


def _small(df: DataFrame) -> DataFrame:
    """Broadcast behind a check of the size; df has been cut."""
    return F.broadcast(df) if df.count() <= BROADCAST_GROUPS else df


def _inverse_root(df: DataFrame, keep: list[str]) -> DataFrame:
    """From means m0.. and covariances c00, c10, ...: the inverse i00, i10, ... of the Cholesky factor, and log_det."""
    for j in range(P):
        df = df.withColumn(f"l{j}{j}", F.expr(f"sqrt(greatest(1e-9D, c{j}{j}" + "".join(f" - l{j}{k} * l{j}{k}" for k in range(j)) + "))"))
        if j + 1 < P:
            df = df.withColumns({f"l{i}{j}": F.expr(f"(c{i}{j}" + "".join(f" - l{i}{k} * l{j}{k}" for k in range(j)) + f") / l{j}{j}") for i in range(j + 1, P)})
    df = df.withColumns({f"i{j}{j}": F.expr(f"1D / l{j}{j}") for j in range(P)})
    for d in range(1, P):
        df = df.withColumns({f"i{i}{i - d}": F.expr("-(" + " + ".join(f"l{i}{k} * i{k}{i - d}" for k in range(i - d, i)) + f") / l{i}{i}") for i in range(d, P)})
    return df.select(*keep, *[f"m{j}" for j in range(P)], *[f"i{i}{j}" for i, j in PAIRS], F.expr(" + ".join(f"ln(l{j}{j})" for j in range(P))).alias("log_det"))


def _distance() -> Column:
    return F.expr(" + ".join("pow(" + " + ".join(f"i{i}{j} * (x{j} - m{j})" for j in range(i + 1)) + ", 2)" for i in range(P)))


def _covariance(n: str, factor: float) -> dict[str, Column]:
    out = {f"m{j}": F.expr(f"s{j} / {n}") for j in range(P)}
    for i, j in PAIRS:
        floor = f" + {FLOOR[i] ** 2}D" if i == j else ""
        out[f"c{i}{j}"] = F.expr(f"{factor}D * (s{i}{j} / {n} - s{i} / {n} * s{j} / {n}){floor}")
    return out


def fit(stats: DataFrame) -> DataFrame:
    """(lk, sk, means, inverse Cholesky factors) of every language and source.

    stats: lk, sk and the vector, of documents that passed the base rules.
    """
    levels = F.array(F.struct("lk", "sk"), F.struct("lk", F.lit("*").alias("sk")), F.struct(F.lit("*").alias("lk"), F.lit("*").alias("sk")))
    v = cut(stats.select("lk", "sk", *VECTOR))
    every = v.select(F.explode(levels).alias("g"), *VECTOR).select(F.col("g.lk").alias("gl"), F.col("g.sk").alias("gs"), *VECTOR)
    quartiles = {f"q{j}": F.percentile_approx(f"x{j}", [0.25, 0.5, 0.75], 1000) for j in range(P)}
    start = cut(every.groupBy("gl", "gs").agg(*[c.alias(k) for k, c in quartiles.items()], *[F.avg(f"x{j}").alias(f"a{j}") for j in range(P)], *[F.var_pop(f"x{j}").alias(f"v{j}") for j in range(P)]))
    zero = {f"c{i}{j}": F.lit(0.0) for i, j in PAIRS if i != j}
    a = start.withColumns(zero | {f"m{j}": F.expr(f"q{j}[1]") for j in range(P)} | {f"c{j}{j}": F.expr(f"pow((q{j}[2] - q{j}[0]) / 1.349D, 2) + {FLOOR[j] ** 2}D") for j in range(P)})
    b = start.withColumns(zero | {f"m{j}": F.col(f"a{j}") for j in range(P)} | {f"c{j}{j}": F.expr(f"v{j} + {FLOOR[j] ** 2}D") for j in range(P)})
    keep, values = ["gl", "gs", "start"], [*[f"m{j}" for j in range(P)], *[f"c{i}{j}" for i, j in PAIRS]]
    params = _inverse_root(a.withColumn("start", F.lit(0)).unionByName(b.withColumn("start", F.lit(1))), keep)
    sums = [F.count("*").alias("n"), *[F.sum(f"x{j}").alias(f"s{j}") for j in range(P)], *[F.sum(F.expr(f"x{i} * x{j}")).alias(f"s{i}{j}") for i, j in PAIRS]]
    names = ["n", *[f"s{j}" for j in range(P)], *[f"s{i}{j}" for i, j in PAIRS]]
    for _ in range(STEPS):
        params = cut(params)
        near = every.join(_small(params), ["gl", "gs"]).withColumn("bin", F.greatest(F.lit(-15 * BINS), F.least(F.lit(15 * BINS), F.floor(BINS * F.log2(_distance() + 1e-9)))).cast("int"))
        bins = near.groupBy(*keep, "bin").agg(*sums)
        whole = Window.partitionBy(*keep)
        bins = bins.withColumn("total", F.sum("n").over(whole)).withColumn("before", F.sum("n").over(whole.orderBy("bin")) - F.col("n"))
        taken = bins.where(F.col("before") < F.ceil(F.lit(SHARE) * F.col("total"))).groupBy(*keep).agg(*[F.sum(c).alias(c) for c in names], F.max("total").alias("total"))
        fitted = taken.withColumns(_covariance("n", CONSISTENCY))
        params = _inverse_root(fitted, [*keep, "total", *[c for c in values if c[0] == "c"]])
    params = cut(params)
    best = params.groupBy("gl", "gs").agg(F.min(F.struct("log_det", "start")).alias("best")).select("gl", "gs", "best.start")
    own = cut(params.join(best, keep).select("gl", "gs", "total", *values))
    return cut(_inverse_root(_drawn(own, values), ["lk", "sk"]).drop("log_det"))


def _drawn(own: DataFrame, values: list[str]) -> DataFrame:
    """(lk, sk, means, covariances): estimates drawn toward those of the level above; one row a group, language and corpus."""
    level = lambda where, keys, tag: own.where(where).select(*keys, *[F.col(c).alias(f"{tag}_{c}") for c in ("total", *values)])
    corpus = own.where("gl = '*'").first()  # one row, none of an empty table
    mixed = lambda n, low, high: F.expr(f"({n} * {low} + {float(SHRINK)}D * {high}) / ({n} + {float(SHRINK)}D)")
    language = level("gl <> '*' and gs = '*'", ["gl"], "lang")
    language = language.select("gl", *[mixed("lang_total", f"lang_{c}", f"{(corpus[c] if corpus else 0.0)!r}D").alias(f"l_{c}") for c in values])
    groups = level("gl <> '*' and gs <> '*'", ["gl", "gs"], "own").join(language, "gl")
    return groups.select(F.col("gl").alias("lk"), F.col("gs").alias("sk"), *[mixed("own_total", f"own_{c}", f"l_{c}").alias(c) for c in values])


def judge(stats: DataFrame, estimates: DataFrame) -> DataFrame:
    """stats (with lk, sk, the vector and base_failed) with kept."""
    near = F.coalesce(_distance() <= CUTOFF, F.lit(True))
    return stats.join(_small(estimates), ["lk", "sk"], "left").withColumn("kept", ~F.col("base_failed") & near)


def _measured(docs: DataFrame, id_col: str, text_col: str, lang_col: str, source_col: str, extra: list[Column]) -> DataFrame:
    rows = docs.select(*extra, _key(quoted(lang_col)).alias("lk"), _key(quoted(source_col)).alias("sk"), F.col(quoted(text_col)).alias("_text"))
    own = [c for c in rows.columns if c != "_text"]
    return text_statistics(rows, F.col("_text")).select(*own, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines", "n_repeat_words", "base_failed").withColumns({k: F.expr(x) for k, x in VECTOR.items()})


def quality_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """(doc_id, the statistics, base_failed, kept), one row a row of docs.

    Null and empty texts have no words and fail the base rules. A null language or source is a group of its own. Repeated
    rows each count. An empty table gives no rows; other columns are not read.
    """
    prepare(docs.sparkSession)
    stats = cut(_measured(docs, id_col, text_col, lang_col, source_col, [F.col(quoted(id_col)).alias("doc_id")]))
    estimates = fit(stats.where("not base_failed").select("lk", "sk", *VECTOR))
    return judge(stats, estimates).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def documents_kept(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The rows of docs that quality_rules keeps, with their columns. Rows and statistics are stored once between fit and
    judgement, so the texts are measured once and never shuffled."""
    prepare(docs.sparkSession)
    row = F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias("row")
    stats = stored(_measured(docs, id_col, text_col, lang_col, source_col, [row]), "rules")
    estimates = fit(stats.where("not base_failed").select("lk", "sk", *VECTOR))
    return judge(stats, estimates).where("kept").select("row.*")


def op4(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return quality_rules(docs)
