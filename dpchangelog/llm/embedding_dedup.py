"""Operator 6: near-duplicate vectors by cross-polytope hashing with multiprobe buckets and verified pairs.

Equal vectors meet in one aggregate and are one class. A class is rotated at random a number of times (three rounds of
random signs and a fast Hadamard transform each); its hash in a table is the signed axis nearest to the rotated vector, and its
probes are the next nearest. It is dealt to all its probes' buckets, so two classes meet in a table if any probe is shared.
In a bucket all pairs are compared by matrix products in double precision and only those at or above the threshold are
links. A pair that meets in several buckets counts in the first of them, which each side's probes tell, so links need no
distinct. What leaves a bucket is, for each row, the weight of its links, and a spanning forest: never more than its rows.
A bucket above ROWS is cut into parts, and its pairs of parts are dealt out as jobs. What goes to a bucket is the vector in the width
of its own type and its codes in as few bytes as they take; unit vectors are made where they are compared.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, cut, forest, prepare, quoted, star_links

TABLES, PROBES, ROWS = 10, 2, 4096
#: Share of the pairs at the threshold that are to meet in a table, for any number of vectors.
RECALL = 0.999


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of each row, orthonormal."""
    n, d = x.shape
    h = 1
    while h < d:
        x = x.reshape(n, d // (2 * h), 2, h)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2)
        h *= 2
    return x.reshape(n, d) / np.sqrt(d)


def probe_codes(x: np.ndarray, tables: int = TABLES, probes: int = PROBES, axes: int = 1, seed: int = 11) -> np.ndarray:
    """(rows, tables, probes) bucket codes. axes: rotations whose nearest axes make up a code; further probes exchange one
    axis at a time for the next nearest, those that lose least first."""
    n, d = x.shape
    size = max(2, 1 << (d - 1).bit_length())
    r = np.random.default_rng(seed)
    out = np.zeros((n, tables, probes), np.int64)
    for t in range(tables):
        base, loss, other = np.zeros(n, np.int64), [], []
        for k in range(axes):
            y = np.zeros((n, size))
            y[:, :d] = x
            for _ in range(3):
                y = hadamard(y * r.choice([-1.0, 1.0], size))
            near = np.argsort(-np.abs(y), axis=1, kind="stable")[:, :probes]
            value = np.take_along_axis(y, near, 1)
            code = 2 * near + (value < 0)
            step = (2 * size) ** k
            base += code[:, 0] * step
            loss.append(np.abs(value[:, :1]) - np.abs(value[:, 1:]))
            other.append((code[:, 1:] - code[:, :1]) * step)
        out[:, t, 0] = base
        if probes > 1:
            loss, other = np.concatenate(loss, 1), np.concatenate(other, 1)
            first = np.argsort(loss, axis=1, kind="stable")[:, : probes - 1]
            out[:, t, 1:] = base[:, None] + np.take_along_axis(other, first, 1)
    return out


def axes_for(n: int, d: int) -> int:
    """Rotations a code so that evenly spread buckets hold about a thousand vectors or fewer."""
    axes, size = 1, 2 * max(2, 1 << (d - 1).bit_length())
    while n > 1000 * size**axes:
        axes += 1
    return axes


def tables_for(axes: int, d: int, threshold: float, tables: int = TABLES, probes: int = PROBES, recall: float = RECALL) -> int:
    """Tables, no fewer than given, that pairs at the threshold need to meet with the wanted chance: the chance of a table is
    that of 4,000 random pairs at exactly that cosine, less three standard errors. More rotations a code need more tables."""
    r = np.random.default_rng(5)
    cosine = min(1.0, max(0.0, threshold))
    met = 0.0
    for k in range(4):
        x, z = r.normal(size=(2, 1000, d))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        z -= (z * x).sum(1, keepdims=True) * x
        z /= np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-300)
        y = cosine * x + np.sqrt(1 - cosine**2) * z
        a, b = probe_codes(x, 1, probes, axes, 100 + k), probe_codes(y, 1, probes, axes, 100 + k)
        met += (a[:, :, :, None] == b[:, :, None, :]).any((1, 2, 3)).mean() / 4
    met -= 3 * np.sqrt(met * (1 - met) / 4000)
    if met <= 0:
        raise ValueError(f"pairs at a cosine of {threshold} hardly ever share a bucket of {axes} rotations")
    return tables if met >= 1 else max(tables, int(np.ceil(np.log(1 - recall) / np.log(1 - met))))


def unit(rows: list) -> tuple[np.ndarray, np.ndarray]:
    """(usable, unit vectors of the usable ones in double precision); rows: vectors of one length."""
    x = np.array(rows, np.float64)
    with np.errstate(all="ignore"):
        x = x / np.abs(x).max(1, keepdims=True)  # neither overflow nor underflow in the norm
        x = x / np.sqrt((x * x).sum(1, keepdims=True))
    return np.isfinite(x).all(1), x


def number_kind(vectors: DataFrame, vector_col: str) -> str:
    """Width in which a column's components are kept, without loss: 4 bytes for floats, else 8."""
    return "<f4" if vectors.select(F.col(quoted(vector_col))).schema[0].dataType.simpleString() == "array<float>" else "<f8"


def classes(vectors: DataFrame, id_col: str, vector_col: str, kind: str) -> DataFrame:
    """(vec_id, vec binary or null): the vector's components; null if it can't link."""

    def run(batches):
        for b in batches:
            out = []
            for v in b.column(1).to_pylist():
                a = np.array([np.nan if e is None else e for e in v] if v is not None else [], np.float64) + 0.0
                out.append(a.astype(kind).tobytes() if len(a) and np.isfinite(a).all() and a.any() else None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], ["vec_id", "vec"])

    return vectors.select(F.col(quoted(id_col)).cast("long").alias("vec_id"), F.col(quoted(vector_col)).alias("v")).mapInArrow(run, "vec_id long, vec binary")


def verified_links(distinct: DataFrame, n: int, width: int, threshold: float, tables: int, probes: int, kind: str = "<f8") -> DataFrame:
    """(u, v, weight) from distinct (rep, n, vec): rows with v null carry weights of links, the others make up a forest."""
    axes = axes_for(n, width)
    tables = tables_for(axes, width, threshold, tables, probes)
    most = (2 * max(2, 1 << (width - 1).bit_length())) ** axes
    code_kind = next(k for k in ("<u1", "<u2", "<u4", "<i8") if most - 1 <= np.iinfo(k).max)

    def deal(batches):
        for b in batches:
            vecs = [np.frombuffer(v, kind) for v in b.column(2).to_pylist()]
            for d in sorted({len(v) for v in vecs}):
                at = [i for i, v in enumerate(vecs) if len(v) == d]
                ok, x = unit([vecs[i] for i in at])
                at, x = [i for i, k in zip(at, ok, strict=True) if k], x[ok]
                for k in range(0, len(at), 2000):
                    own, xs = at[k : k + 2000], x[k : k + 2000]
                    codes = probe_codes(xs, tables, probes, axes)
                    rows = b.take(pa.array(own, pa.int64()))
                    yield pa.RecordBatch.from_arrays(
                        [*rows.columns[:3], pa.array([c.tobytes() for c in codes.astype(code_kind)], pa.binary()), pa.array([[[t, c] for t, cs in enumerate(code) for c in cs] for code in codes.tolist()], pa.list_(pa.list_(pa.int64()))), pa.array([d] * len(own), pa.int64())],
                        ["rep", "n", "vec", "codes", "keys", "d"],
                    )

    dealt = cut(distinct.mapInArrow(deal, "rep long, n long, vec binary, codes binary, keys array<array<long>>, d long"))
    keyed = dealt.select("rep", "n", "vec", "codes", "d", F.explode("keys").alias("k")).select("rep", "n", "vec", "codes", "d", F.col("k")[0].alias("t"), F.col("k")[1].alias("code"))
    sizes = dealt.select("d", F.explode("keys").alias("k")).groupBy("d", F.col("k")[0].alias("t"), F.col("k")[1].alias("code")).agg(F.count("*").alias("size")).where("size > 1")
    parts = keyed.join(sizes, ["d", "t", "code"]).withColumn("parts", F.ceil(F.col("size") / ROWS).cast("int")).withColumn("mine", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    pair = F.explode(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least(j, F.col("mine")).alias("a"), F.greatest(j, F.col("mine")).alias("b"))))
    jobs = parts.select("d", "t", "code", pair.alias("p"), "mine", "rep", "n", "vec", "codes").select("d", "t", "code", "p.a", "p.b", "mine", "rep", "n", "vec", "codes")

    def work(rows):
        """Links of one job."""
        d, t, code, a, b = rows[0][:5]
        mine, rep, weight = (np.array([r[k] for r in rows], np.int64) for k in (5, 6, 7))
        x = unit(np.frombuffer(b"".join(r[8] for r in rows), kind).reshape(len(rows), d))[1]
        codes = np.frombuffer(b"".join(r[9] for r in rows), code_kind).astype(np.int64).reshape(len(rows), tables, probes)
        left = np.flatnonzero(mine != b) if a != b else np.arange(len(rows))
        right = np.flatnonzero(mine == b)
        sums, root = np.zeros(len(rows), np.int64), np.arange(len(rows))
        for k in range(0, len(left), 256):
            own = left[k : k + 256]
            i, j = np.nonzero(x[own] @ x[right].T >= threshold)
            i, j = own[i], right[j]
            if a == b:
                i, j = i[i < j], j[i < j]
            for s in range(0, len(i), 20_000):
                p, q = i[s : s + 20_000], j[s : s + 20_000]
                same = codes[p][:, :, :, None] == codes[q][:, :, None, :]
                first = same.any((2, 3)).argmax(1)
                here = np.flatnonzero(first == t)
                shared = np.where(same[here, t].any(2), codes[p[here], t], np.iinfo(np.int64).max).min(1)
                here = here[shared == code]
                p, q = p[here], q[here]
                np.add.at(sums, p, weight[q])
                np.add.at(sums, q, weight[p])
                differ = root[p] != root[q]
                if differ.any():
                    pairs = np.unique(np.sort(np.stack([root[p[differ]], root[q[differ]]], 1), axis=1), axis=0)
                    root = forest(len(rows), pairs.tolist())[root]
        some, (child, parent) = np.flatnonzero(sums), star_links(root, rep)
        return np.r_[rep[some], child], [*[None] * len(some), *parent.tolist()], np.r_[sums[some], np.zeros(len(child), np.int64)]

    def compare(batches):
        """Rows arrive sorted by job; one job is held at a time."""
        held: list = []
        for b in batches:
            done = []
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if held and held[0][:5] != row[:5]:
                    if len(held) > 1:
                        done.append(work(held))
                    held = []
                held.append(row)
            yield out(done)
        if len(held) > 1:
            yield out([work(held)])

    def out(done):
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([x[0] for x in done] or [np.zeros(0, np.int64)]), pa.int64()), pa.array([v for x in done for v in x[1]], pa.int64()), pa.array(np.concatenate([x[2] for x in done] or [np.zeros(0, np.int64)]), pa.int64())], ["u", "v", "weight"])

    by = ["d", "t", "code", "a", "b"]
    return jobs.repartition(*by).sortWithinPartitions(*by).mapInArrow(compare, "u long, v long, weight long")


def near_vectors(vectors: DataFrame, threshold: float = 0.9, id_col: str = "vec_id", vector_col: str = "embedding", tables: int = TABLES, probes: int = PROBES) -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row a vector.

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing, as do vectors of different
    lengths; they are components of their own. Repeated rows of one id are vectors of their own under one id. A null id
    keeps its row; it is never a component's id unless no other is in it. An empty table gives no rows; other columns are
    not read.
    """
    prepare(vectors.sparkSession)
    kind = number_kind(vectors, vector_col)
    rows = cut(classes(vectors, id_col, vector_col, kind))
    # rep: a number of the class, not an id, so that null and repeated ids do no harm.
    groups = rows.where("vec is not null").groupBy("vec").agg(F.count("*").alias("n"), F.min("vec_id").alias("least"))
    groups = cut(groups.withColumn("rep", F.monotonically_increasing_id()))
    size = np.dtype(kind).itemsize
    width = (groups.agg(F.max(F.octet_length("vec"))).first()[0] or 2 * size) // size
    found = cut(verified_links(groups.select("rep", "n", "vec"), groups.count(), width, threshold, tables, probes, kind))
    weights = found.where("v is null").groupBy(F.col("u").alias("rep")).agg(F.sum("weight").alias("weight"))
    member = components(found.where("v is not null").select("u", "v")).select(F.col("node").alias("rep"), "component")
    named = cut(groups.join(weights, "rep", "left").join(member, "rep", "left").select("vec", "n", "least", F.coalesce("weight", F.lit(0)).alias("weight"), F.coalesce("component", "rep").alias("component")))
    # Cut, so that the join below is of two plain shuffles, of which Spark splits the part of a large component.
    least = cut(named.groupBy("component").agg(F.min("least").alias("component_id")))
    final = named.join(least, "component").select("vec", (F.col("n") - 1 + F.col("weight")).alias("n_links"), "component_id")
    out = rows.where("vec is not null").join(final, "vec").select("vec_id", "n_links", "component_id")
    out = out.unionByName(rows.where("vec is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id")))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op6(spark: SparkSession, vectors: DataFrame) -> DataFrame:
    return near_vectors(vectors)
