"""Operator 10: SimHash near-duplicates by bit-sliced comparison.

Fingerprints: 64 bits over the XXH64 hashes of all 4-word shingles. Equal fingerprints meet in one aggregate, so copies cost
nothing later. Two fingerprints within the radius agree on some choice of blocks (64 bits cut into `blocks`, of which any
`blocks - radius` agree), so each fingerprint is dealt to one bucket a choice and compared inside its buckets; nothing is lost.
In a bucket fingerprints are stored as vertical bit planes. A group of queries runs against all of them at once: each plane
is added to bitwise counters with carry-save adders, and a group is abandoned once every counter has passed the radius.
A bucket above ROWS is cut into parts and its pairs of parts are dealt out, so no task holds more than two parts.
Only the links of a spanning forest of a bucket leave it, never more than its rows.

Near copies by similarity (`similar_classes`): the same comparison on wide fingerprints over the sets of five-word shingles. A text
whose set has a Jaccard similarity of 0.8 or more to another's differs from it in about 15 % of the bits, so no choice of blocks
finds it. The sums of which a fingerprint keeps the signs are a vector each; two such texts have vectors at a cosine of 0.889 or
more, and the signed axes nearest to a vector after random rotations (as in operator 6) are its buckets, in as many tables as the
wanted recall takes at that cosine. The radius is wide. What is within it is a candidate; groups of candidates compare their
shingle sets, so a link is never below the similarity.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import SALTS, components, cut, prepare, quoted, star_links
from .embedding_dedup import axes_for, probe_codes, tables_for

BITS = 64
#: Fingerprints of a part of a bucket.
ROWS = 4096
#: Queries compared together.
GROUP = 64


def shingle_hashes(text: str | None, words: int = 4, seed: int = 42) -> np.ndarray:
    """XXH64 of each shingle of the text in lower case (A-Z only), repeats included."""
    import xxhash

    h, ws = xxhash.xxh64_intdigest, (text or "").encode().lower().split()
    if not ws:
        return np.zeros(0, np.uint64)
    line, n = b" ".join(ws), len(ws)
    if n <= words:
        return np.array([h(line, seed)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, ws), np.int64, n) + 1) - 1
    starts = np.r_[0, ends[:-1] + 1]
    return np.fromiter([h(line[a:b], seed) for a, b in zip(starts[: n - words + 1].tolist(), ends[words - 1 :].tolist(), strict=True)], np.uint64, n - words + 1)


def ones(hashes: np.ndarray) -> np.ndarray:
    """In how many hashes each bit is set."""
    out = np.zeros(BITS, np.int64)
    for k in range(0, len(hashes), 1 << 16):
        out += np.unpackbits(hashes[k : k + (1 << 16)].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return out


def fingerprint(hashes: np.ndarray) -> int:
    """A bit is set if it is set in over half of the hashes; none: 0."""
    return int(np.packbits(2 * ones(hashes) > len(hashes), bitorder="little").view("<u8")[0])


def planes_of(fps: np.ndarray) -> np.ndarray:
    """(bits, ceil(n / 64)) words: word w of plane b has bit b of fingerprints 64 w to 64 w + 63. fps: one or more words a row."""
    n, words = len(fps), fps.reshape(len(fps), -1).shape[1] if len(fps) else 1
    bits = np.unpackbits(np.ascontiguousarray(fps.astype("<u8")).view(np.uint8).reshape(n, 8 * words), axis=1, bitorder="little")
    full = np.zeros((-(-n // 64) * 64, BITS * words), np.uint8)
    full[:n] = bits
    return np.ascontiguousarray(np.packbits(full.T, axis=1, bitorder="little")).view("<u8")


def within(planes: np.ndarray, n: int, queries: np.ndarray, radius: int, block: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """(query, row) index pairs at a distance of at most radius."""
    depth = (radius + 1).bit_length()
    counters = [np.zeros((len(queries), planes.shape[1]), np.uint64) for _ in range(depth)]
    over = np.zeros((len(queries), planes.shape[1]), np.uint64)
    if n % 64:
        over[:, -1] = ~np.uint64(0) << np.uint64(n % 64)
    live = np.arange(len(queries))
    words = queries.reshape(len(queries), -1)
    bits = (words[:, :, None] >> np.arange(BITS, dtype=np.uint64)) & np.uint64(1)
    flip = (np.uint64(0) - bits.reshape(len(queries), -1)).astype(np.uint64)
    for b0 in range(0, len(planes), block):
        for b in range(b0, b0 + block, 2):
            x, y = planes[b][None, :] ^ flip[live, b, None], planes[b + 1][None, :] ^ flip[live, b + 1, None]
            # carry-save: counter bit 0 takes x and y at once, its carry has weight two
            low = counters[0]
            half = x ^ y
            carry = (x & y) | (half & low)
            counters[0] = half ^ low
            for k in range(1, depth):
                counters[k], carry = counters[k] ^ carry, counters[k] & carry
            over |= carry
        if b0 + block <= radius:
            continue
        over |= above(counters, radius)
        dead = (over == ~np.uint64(0)).all(1)
        if dead.any():
            keep = ~dead
            live, over, counters = live[keep], over[keep], [c[keep] for c in counters]
            if not len(live):
                break
    hits = np.unpackbits(np.ascontiguousarray(~over).view(np.uint8).reshape(len(live), -1), axis=1, bitorder="little") if len(live) else np.zeros((0, 0), np.uint8)
    q, r = np.nonzero(hits)
    return live[q], r


def above(counters: list[np.ndarray], radius: int) -> np.ndarray:
    """Bit mask of the counters that exceed radius, compared from the highest bit."""
    greater, equal = np.zeros_like(counters[0]), np.full_like(counters[0], ~np.uint64(0))
    for k in range(len(counters) - 1, -1, -1):
        if radius >> k & 1:
            equal = equal & counters[k]
        else:
            greater = greater | (equal & counters[k])
            equal = equal & ~counters[k]
    return greater


def bucket_roots(rows: np.ndarray, left: np.ndarray, right: np.ndarray, radius: int, same=None) -> np.ndarray:
    """Root of each row, by the links between the rows left and right. same(i, j): whether a pair within the radius is a link;
    pairs that are joined already are not asked."""
    planes, root = planes_of(rows[right]), np.arange(len(rows))
    for k in range(0, len(left), GROUP):
        q, r = within(planes, len(right), rows[left[k : k + GROUP]], radius)
        q, r = left[k : k + GROUP][q], right[r]
        differ = root[q] != root[r]
        if same is None:
            starts = np.searchsorted(q, left[k : k + GROUP])
            for i, lo, hi in zip(left[k : k + GROUP].tolist(), starts.tolist(), [*starts[1:].tolist(), len(q)], strict=True) if differ.any() else ():
                met = root[r[lo:hi]]
                if (met != root[i]).any():
                    names = np.unique(np.append(met, root[i]))
                    root[np.isin(root, names)] = names[0]
            continue
        for i in np.unique(q[differ]).tolist():
            others = r[q == i]
            others = others[root[others] != root[i]]
            while len(others):
                j, others = int(others[0]), others[1:]
                if same(i, j):
                    root[root == root[j]] = root[i]
                    others = others[root[others] != root[i]]
    return root


def bucket_links(fps: np.ndarray, other: np.ndarray | None, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links among fps, or of those between fps and other."""
    rows, n = fps if other is None else np.r_[fps, other], len(fps)
    return star_links(bucket_roots(rows, np.arange(n), np.arange(len(rows)) if other is None else np.arange(n, len(rows)), radius), rows)


def scheme(n: int, radius: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Choices of blocks for n distinct fingerprints: [(choice, [(first bit, bits), ...]), ...].

    The fewest blocks whose buckets hold 256 evenly spread fingerprints or fewer. Any number gives the same links.
    """
    for blocks in range(radius + 1, radius + 9):
        bounds = [BITS * k // blocks for k in range(blocks + 1)]
        bits = BITS * (blocks - radius) // blocks
        if n <= 256 << bits or blocks == radius + 8:
            spans = [(a, b - a) for a, b in zip(bounds, bounds[1:], strict=False)]
            return [(i, [spans[k] for k in c]) for i, c in enumerate(combinations(range(blocks), blocks - radius))]
    raise AssertionError


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, h, fp) of every whole text, h a hash of the text; null and empty texts and those without words have fp 0."""

    def run(batches):
        for b in batches:
            fps = np.array([fingerprint(shingle_hashes(t, words, seed)) for t in b.column(2).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fps, pa.int64())], ["doc_id", "h", "fp"])

    return docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.xxhash64(quoted(text_col)).alias("h"), F.col(quoted(text_col)).alias("text")).mapInArrow(run, "doc_id long, h long, fp long")


def fingerprint_links(distinct: DataFrame, n: int, radius: int) -> DataFrame:
    """(u, v) links that join all fingerprints within the radius; distinct: one column fp without repeats."""
    choices = scheme(n, radius)

    def key(parts):
        code, at = F.lit(0).cast("long"), 0
        for first, bits in parts:
            code = code.bitwiseOR(F.shiftleft(F.shiftrightunsigned("fp", first).bitwiseAND(F.lit((1 << bits) - 1)), at))
            at += bits
        return code

    dealt = distinct.select("fp", F.explode(F.array(*[F.struct(F.lit(i).alias("choice"), key(p).alias("code")) for i, p in choices])).alias("k")).select("fp", "k.choice", "k.code")
    sizes = dealt.groupBy("choice", "code").agg(F.count("*").alias("n")).where("n > 1")
    parts = dealt.join(sizes, ["choice", "code"]).withColumn("parts", F.ceil(F.col("n") / ROWS).cast("int"))
    mine = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
    # Part i of a bucket goes to the pairs (0, i) ... (i, i) ... (i, last).
    pair = F.explode(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least(j, F.col("mine")).alias("a"), F.greatest(j, F.col("mine")).alias("b"))))
    jobs = parts.withColumn("mine", mine).select("fp", "choice", "code", "mine", pair.alias("p")).select("choice", "code", "p.a", "p.b", "mine", "fp")

    def compare(batches):
        """Rows arrive sorted by job; one job is held at a time."""
        held, key_now = [], None

        def links(held):
            rows = np.concatenate(held)
            fps, mine, b = rows["fp"].view(np.uint64), rows["mine"], rows["b"][0]
            split = rows["a"][0] != b
            if len(fps) < 2:
                return [], []
            first = bucket_links(fps[mine != b], fps[mine == b], radius) if split else bucket_links(fps, None, radius)
            return first

        kind = np.dtype([("choice", "i4"), ("code", "i8"), ("a", "i4"), ("b", "i4"), ("mine", "i4"), ("fp", "i8")])
        for batch in batches:
            rows = np.empty(batch.num_rows, kind)
            for k, name in enumerate(kind.names):
                rows[name] = batch.column(k).to_numpy(zero_copy_only=False)
            if not len(rows):
                continue
            edge = np.flatnonzero(np.any([rows[c][1:] != rows[c][:-1] for c in ("choice", "code", "a", "b")], axis=0)) + 1
            us, vs = [], []
            for piece in np.split(rows, edge):
                k = tuple(piece[0])[:4]
                if k != key_now:
                    if held:
                        u, v = links(held)
                        us.append(u), vs.append(v)
                    held, key_now = [], k
                held.append(piece)
            yield out(us, vs)
        if held:
            u, v = links(held)
            yield out([u], [v])

    def out(us, vs):
        join = lambda x: pa.array(np.concatenate([np.asarray(y, np.uint64) for y in x] or [np.zeros(0, np.uint64)]).view(np.int64), pa.int64())
        return pa.RecordBatch.from_arrays([join(us), join(vs)], ["u", "v"])

    by = ["choice", "code", "a", "b"]
    return jobs.repartition(*by).sortWithinPartitions(*by).mapInArrow(compare, "u long, v long")


def groups(docs: DataFrame, radius: int = 4, id_col: str = "doc_id", text_col: str = "text", words: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the smallest id of a document reachable by links.

    Null and empty texts have fingerprint 0 and link like any other. Rows of one id are one document of several fingerprints
    only if their texts differ; each row keeps its own fingerprint and component. A null id never represents a component
    that has another id. An empty table gives no rows; other columns are not read.
    """
    return _groups(docs, radius, id_col, text_col, words, seed).select("doc_id", "fp", "component_id")


def _groups(docs, radius, id_col, text_col, words, seed):
    prepare(docs.sparkSession)
    fps = cut(fingerprints(docs, id_col, text_col, words, seed))
    classes = cut(fps.groupBy("fp").agg(F.min("doc_id").alias("least")))  # copies meet here
    links = fingerprint_links(classes.select("fp"), classes.count(), radius)
    member = components(links)
    named = cut(classes.join(member.select(F.col("node").alias("fp"), "component"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component")))
    # Cut, so that the join below is of two plain shuffles, of which Spark splits the part of a large component.
    least = cut(named.groupBy("component").agg(F.min("least").alias("component_id")))
    return fps.join(named.join(least, "component").select("fp", "component", "component_id"), "fp")


#: Bits of a wide fingerprint, and how many of its words a bucket compares.
WIDE, COMPARED = 256, 2
#: Buckets of a text in each table, and share of the pairs at the similarity that are to meet in a table, for any number of texts.
PROBES, RECALL = 3, 0.98
#: Texts whose shingle sets one task holds at a time.
SETS = 1024


def wide_sums(hashes: np.ndarray) -> np.ndarray:
    """For each of WIDE bits, in how many more hashes of a set it is set than not; each word of bits from a mix of its own."""
    out = []
    for k in range(WIDE // BITS):
        x = (hashes ^ np.uint64((0x632BE59BD9B4E019 * (k + 1)) & (2**64 - 1))) * np.uint64(0x9E3779B97F4A7C15)
        out.append(2 * ones(x ^ (x >> np.uint64(32))) - len(hashes))
    return np.concatenate(out)


def wide_fingerprint(sums: np.ndarray) -> np.ndarray:
    """Words of the compared bits: the signs of the sums."""
    return np.packbits(sums[: COMPARED * BITS] > 0, bitorder="little").view("<u8")


def rounded(sums: np.ndarray) -> np.ndarray:
    """Sums as bytes, in proportion to the largest: equal sets give equal bytes."""
    return np.rint(sums * (127 / max(1, np.abs(sums).max(initial=0)))).astype(np.int8)


def bucket_plan(n: int, similarity: float) -> tuple[int, int]:
    """(rotations a code, tables) for n texts. Vectors of WIDE sums show the cosine of two sets with an error, of which two standard
    deviations are allowed for."""
    cosine = 2 * similarity / (1 + similarity)
    axes = axes_for(n, WIDE)
    return axes, tables_for(axes, WIDE, cosine - 2 * (1 - cosine**2) / math.sqrt(WIDE), 1, PROBES, RECALL)


def differing(similarity: float) -> float:
    """Share of bits in which fingerprints of two large sets of one size and that Jaccard similarity differ: the angle of their
    sums. Small sets differ in fewer."""
    return math.acos(2 * similarity / (1 + similarity)) / math.pi


def _binomial(n: int, p: float) -> list[float]:
    return [math.comb(n, k) * p**k * (1 - p) ** (n - k) for k in range(n + 1)]


def radius_for(similarity: float, bits: int = COMPARED * BITS, recall: float = 0.9995) -> int:
    total = 0.0
    for k, x in enumerate(_binomial(bits, differing(similarity))):
        total += x
        if total >= recall:
            return k
    return bits


def similar(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    """Whether two sorted sets have that Jaccard similarity; two empty ones do."""
    if not min(len(a), len(b)):
        return len(a) == len(b)
    if min(len(a), len(b)) < similarity * max(len(a), len(b)):
        return False
    at = np.searchsorted(b, a)
    both = int((b[np.minimum(at, len(b) - 1)] == a).sum())
    return both >= similarity * (len(a) + len(b) - both)


def _jobs(batches, keys: int):
    """Tables of the rows of one job each, a job being equal values of the first columns; rows arrive sorted by job."""
    held, now = [], None
    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(k).to_numpy(zero_copy_only=False) for k in range(keys)]
        edge = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        for lo, hi in zip(np.r_[0, edge].tolist(), np.r_[edge, b.num_rows].tolist(), strict=True):
            key = tuple(c[lo] for c in cols)
            if held and key != now:
                yield pa.Table.from_batches(held)
                held = []
            now = key
            held.append(b.slice(lo, hi - lo))
    if held:
        yield pa.Table.from_batches(held)


def group_links(keyed: DataFrame, by: list[str], radius: int, similarity: float | None, rows: int) -> DataFrame:
    """(u, v): links that join all rows that links join within a group. keyed: by..., h, f0, f1 and, with a similarity, shingles:
    then only pairs whose sets are that similar are links.

    A group above `rows` is cut into parts. Each part meets the group's leader (its smallest h) too, so rows of different parts
    that are both joined to the leader are joined already; only the rows that aren't are dealt out to the other parts. A large
    group of copies of one text so costs about its rows, not its pairs.
    """
    payload = [c for c in keyed.columns if c not in by]
    sizes = cut(keyed.groupBy(*by).agg(F.count("*").alias("size"), F.min("h").alias("leader")).where("size > 1"))
    parts = keyed.join(sizes, by).withColumn("parts", F.ceil(F.col("size") / rows).cast("int")).withColumn("own", F.pmod(F.xxhash64("h"), F.col("parts")).cast("int"))
    everywhere = F.when(F.col("h") == F.col("leader"), F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array("own"))
    first = parts.select(*by, F.explode(everywhere).alias("part"), "leader", "parts", *payload)

    def arrays(t):
        n = t.num_rows
        fps = np.stack([t.column(c).to_numpy().view(np.uint64) for c in ("f0", "f1")], 1)
        if similarity is None:
            return n, t.column("h").to_numpy(), fps, None
        sets = [np.frombuffer(x, np.uint64) for x in t.column("shingles").to_pylist()]
        return n, t.column("h").to_numpy(), fps, lambda i, j: similar(sets[i], sets[j], similarity)

    def inside(batches):
        held: list = []
        for t in _jobs(batches, len(by) + 1):
            if t.num_rows < 2:
                continue
            n, h, fps, same = arrays(t)
            every = np.arange(n)
            root = bucket_roots(fps, every, every, radius, same)
            u, v = star_links(root, h)
            keys = [t.column(c)[0].as_py() for c in by]
            held.append((keys, u, v.tolist()))
            if t.column("parts")[0].as_py() > 1:
                loose = np.flatnonzero(root != root[np.flatnonzero(h == t.column("leader")[0].as_py())[0]])
                held.append((keys, h[loose], [None] * len(loose)))
            if sum(len(x[1]) for x in held) > 5000:
                yield out(held)
                held = []
        yield out(held)

    def out(held):
        cols = [pa.array([x for k, u, _ in held for x in [k[i]] * len(u)], t) for i, t in enumerate(kinds)]
        u = np.concatenate([u for _, u, _ in held] or [np.zeros(0, np.int64)])
        return pa.RecordBatch.from_arrays([*cols, pa.array(u, pa.int64()), pa.array([x for _, _, v in held for x in v], pa.int64())], [*by, "u", "v"])

    kinds = [{"int": pa.int32(), "bigint": pa.int64()}[keyed.schema[c].dataType.simpleString()] for c in by]
    shape = ", ".join(f"{c} {keyed.schema[c].dataType.simpleString()}" for c in by) + ", u long, v long"
    job = [*by, "part"]
    found = cut(first.repartition(*job).sortWithinPartitions(*job).mapInArrow(inside, shape))
    links = found.where("v is not null").select("u", "v")
    loose = found.where("v is null").select(*by, F.col("u").alias("h"))
    if loose.isEmpty():
        return links
    lots = loose.groupBy(*by).agg(F.ceil(F.count("*") / rows).cast("int").alias("lots"))
    marked = parts.join(lots, by).join(loose.withColumn("loose", F.lit(True)), [*by, "h"], "left")
    lot = F.pmod(F.xxhash64("h", F.lit(1)), F.col("lots")).cast("int")
    left = marked.where("loose").select(*by, F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), lot.alias("lot"), F.lit(1).alias("side"), *payload)
    right = marked.select(*by, F.col("own").alias("part"), F.explode(F.sequence(F.lit(0), F.col("lots") - 1)).alias("lot"), F.lit(0).alias("side"), *payload)

    def across(batches):
        for t in _jobs(batches, len(by) + 2):
            _, h, fps, same = arrays(t)
            side = t.column("side").to_numpy()
            a, b = np.flatnonzero(side == 1), np.flatnonzero(side == 0)
            if len(a) and len(b):
                # A loose row of this very part stands on both sides and is the same row.
                root = bucket_roots(fps, a, b, radius, same)
                u, v = star_links(root, h)
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    job = [*by, "part", "lot"]
    return links.unionByName(left.unionByName(right).repartition(*job).sortWithinPartitions(*job).mapInArrow(across, "u long, v long"))


def similar_classes(docs: DataFrame, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(h, component) of every different text: h its hash, component one for all texts that links join; texts link if their sets
    of shingles have the similarity or more.

    Equal texts are one class. Null texts are equal to each other; texts without words are alike, whatever they are; a text of
    fewer words than a shingle is one shingle. Pairs at the very similarity meet with a chance of RECALL or more, more similar ones
    nearly always; none below it is linked. An empty table gives no rows; other columns are not read.
    """
    prepare(docs.sparkSession)
    texts = docs.select(F.xxhash64(quoted(text_col)).alias("h"), F.col(quoted(text_col)).alias("text"))

    def sign(batches):
        for b in batches:
            sums = [wide_sums(np.unique(shingle_hashes(t, words))) for t in b.column(1).to_pylist()]
            fps = np.array([wide_fingerprint(s) for s in sums], np.uint64).reshape(-1, COMPARED).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(f) for f in np.ascontiguousarray(fps.T)], pa.array([rounded(s).tobytes() for s in sums], pa.binary())], ["h", "f0", "f1", "sums"])

    signed = texts.mapInArrow(sign, "h long, f0 long, f1 long, sums binary")
    classes = cut(signed.groupBy("h").agg(*[F.first(c).alias(c) for c in ("f0", "f1", "sums")]))
    axes, tables = bucket_plan(classes.count(), similarity)

    def deal(batches):
        for b in batches:
            for part in (b.slice(k, 1000) for k in range(0, b.num_rows, 1000)):
                x = np.frombuffer(b"".join(part.column(3).to_pylist()), np.int8).reshape(-1, WIDE).astype(float)
                codes = probe_codes(x, tables, PROBES, axes)
                buckets = [[[t, c] for t, cs in enumerate(row) for c in cs] for row in codes.tolist()]
                yield pa.RecordBatch.from_arrays([*part.columns[:3], pa.array(buckets, pa.list_(pa.list_(pa.int64())))], ["h", "f0", "f1", "buckets"])

    dealt = classes.mapInArrow(deal, "h long, f0 long, f1 long, buckets array<array<long>>")
    keyed = dealt.select(F.explode("buckets").alias("b"), "h", "f0", "f1").select(F.col("b")[0].alias("t"), F.col("b")[1].alias("code"), "h", "f0", "f1")
    radius = radius_for(similarity)
    near = components(group_links(keyed, ["t", "code"], radius, None, ROWS)).select(F.col("node").alias("h"), F.col("component").alias("near"))

    def gather(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([np.unique(shingle_hashes(t, words)).tobytes() for t in b.column(1).to_pylist()], pa.binary())], ["h", "shingles"])

    # Only texts that have a candidate send their sets, once each. The join is dealt by input partition too, as a text may be frequent.
    near = cut(near.join(classes.select("h", "f0", "f1"), "h"))
    asked = near.select("h", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    found = texts.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(SALTS))).join(asked, ["h", "salt"], "left_semi")
    sets = cut(found.groupBy("h").agg(F.first("text").alias("text")).mapInArrow(gather, "h long, shingles binary"))
    member = components(group_links(near.join(sets, "h").select("near", "h", "f0", "f1", "shingles"), ["near"], radius, similarity, SETS))
    return cut(classes.select("h").join(member.select(F.col("node").alias("h"), "component"), "h", "left").select("h", F.coalesce("component", "h").alias("component")))


def _hashed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.xxhash64(quoted(text_col)).alias("h"))


def similar_groups(docs: DataFrame, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, h, component): h a hash of the text, component one for all documents that links join; see similar_classes."""
    named = similar_classes(docs, words, similarity, id_col, text_col)  # cut: Spark splits the part of a frequent text
    return _hashed(docs, id_col, text_col).join(named, "h").select("doc_id", "h", "component")


def near_duplicates_removed(docs: DataFrame, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay, with the columns of docs: of each group of similar documents the one with the smallest id.

    Of repeated rows of that document one stays; a null id comes after all others, and a group without ids keeps one row.
    """
    # Smallest id of each text before the join, so that copies meet in an aggregate.
    least = _hashed(docs, id_col, text_col).groupBy("h").agg(F.min("doc_id").alias("doc_id"))
    return first_of_groups(docs, least.join(similar_classes(docs, words, similarity, id_col, text_col), "h"), id_col, text_col)


def fingerprint_duplicates_removed(docs: DataFrame, radius: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """As near_duplicates_removed, with the groups of 64-bit fingerprints within a radius."""
    return first_of_groups(docs, _groups(docs, radius, id_col, text_col, 4, 42), id_col, text_col)


def first_of_groups(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The row of docs of each component's smallest id; found: (doc_id, h, component)."""
    first = found.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("b"), F.coalesce("doc_id", F.lit(0)).alias("a"), "h")).alias("k")).select("k.*")
    keyed = docs.select(F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias("row"), F.col(quoted(id_col)).isNull().alias("b"), F.coalesce(F.col(quoted(id_col)).cast("long"), F.lit(0)).alias("a"), F.xxhash64(quoted(text_col)).alias("h"))
    return keyed.join(first, ["a", "b", "h"], "left_semi").dropDuplicates(["a", "b", "h"]).select("row.*")


def op10(spark: SparkSession, docs: DataFrame) -> DataFrame:
    found = groups(docs)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
