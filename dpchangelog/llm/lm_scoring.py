"""Operator 9: cross-entropy difference of two matched n-gram models.

The target model learns from documents labelled good, the background model from all others. Both are bigram models over
one vocabulary, that of the whole corpus, smoothed alike: bigram counts over a unigram model over a uniform one. The
background's counts are scaled to the target's total, so that both smooth with the same strength. A document's score is the
mean over its tokens of target loss minus background loss (below 0: more like the target); in the model that learnt from
the document its own counts are left out. A first word has no word before it and takes its unigram probability.

Counts are over all documents and of all words and pairs; nothing is dropped, and no model is held in one place. Documents
are dealt to chunks of about CHUNK_BYTES of text. A chunk sends each of its different words and pairs once, with its counts,
to the shard that owns the key; the shard adds up and answers every chunk for the keys that it sent, and the chunk scores its
documents. What moves grows with the input, a very common word costs a row a chunk, and no task holds more than a chunk or a
shard. Words are known by 64 bits of XXH64 and pairs by 64 bits mixed from both: of n different keys, n^2 / 2^65 pairs of
keys are expected to share one (10^-7 at two million, 0.03 at a thousand million).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, quoted, stored, table

#: Words of the uniform model, at least; a corpus with more different words has that many. Sizes of the tables that `slots` numbers.
WORDS, PAIRS = 1 << 18, 1 << 20
SMOOTH, UNIFORM = 16.0, 0.1
#: Labelled ids that are broadcast, at most; more are joined by a shuffle.
BROADCAST_IDS = 250_000
#: Bytes of text of a chunk, and of text for each shard.
CHUNK_BYTES, SHARD_BYTES = 8 << 20, 16 << 20
_numbers: dict = {}


def codes(text: str | None) -> np.ndarray:
    """Hash of each word in lower case (A-Z); a word has the same one in every process."""
    import xxhash

    ws = (text or "").encode().lower().split()
    return np.fromiter(map(xxhash.xxh64_intdigest, ws), np.uint64, len(ws))


def pair_codes(before: np.ndarray, c: np.ndarray) -> np.ndarray:
    x = c ^ (before * np.uint64(0x9E3779B97F4A7C15) + np.uint64(0x632BE59BD9B4E019))
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xC2B2AE3D27D4EB4F)
    return x ^ (x >> np.uint64(29))


def slots(c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word, word before, pair) numbers from 1 on of a text's codes, by first appearance in this process; 0: none. For
    tables that are counted in one process."""
    w = np.array([_number("word", x) for x in c.tolist()], np.int64)
    before = np.r_[0, w[:-1]].astype(np.int64) if len(w) else w
    return w, before, np.array([_number("pair", x) if x[0] else 0 for x in zip(before.tolist(), w.tolist(), strict=True)], np.int64)


def _number(kind: str, x) -> int:
    known = _numbers.setdefault(kind, {})
    return known.setdefault(x, len(known) + 1)


class Models:
    """words, pairs: counts of (background, target) by number, of which 0 stands for no word. total: tokens of each model
    where words are not the whole vocabulary."""

    def __init__(self, words: np.ndarray, pairs: np.ndarray, total: np.ndarray | None = None, vocabulary: int = WORDS):
        self.words, self.pairs, self.vocabulary = words, pairs, vocabulary
        self.total = words.sum(1) if total is None else total
        self.scale = np.array([self.total[1] / self.total[0] if self.total.min() else 1.0, 1.0])

    def losses(self, c: np.ndarray, own: int) -> tuple[float, float]:
        """Summed loss under target and background; own: the model (0, 1) that learnt from this text."""
        a, b = self.token_losses(*slots(c), np.zeros(len(c), np.int64), np.array([own]))
        return float(a.sum()), float(b.sum())

    def token_losses(self, w: np.ndarray, b: np.ndarray, p: np.ndarray, text: np.ndarray, own: np.ndarray) -> list[np.ndarray]:
        """Loss of each token under target and background. w, b, p: numbers of word, word before and pair; text: number of
        the token's text; own: the model that learnt from each text."""
        follows = b > 0
        n_w, n_p = _own(text, w), _own(text, p)
        n_b = np.r_[0, n_w[:-1]] if len(w) else n_w
        length = np.bincount(text, minlength=len(own))[text]
        out = []
        for m in (1, 0):
            mine = own[text] == m
            cw, total = self.words[m][w] - n_w * mine, self.total[m] - length * mine
            cb, cp = np.where(follows, self.words[m][b] - n_b * mine, 0), np.where(follows, self.pairs[m][p] - n_p * mine, 0)
            s = self.scale[m]
            one = (s * cw + UNIFORM) / (s * total + UNIFORM * self.vocabulary)
            out.append(-np.log((s * cp + SMOOTH * one) / (s * cb + SMOOTH)))
        return out


def _own(text: np.ndarray, x: np.ndarray) -> np.ndarray:
    """How often each token's x occurs in its text."""
    if not len(x):
        return x
    _, at, n = np.unique(text * (x.max() + 1) + x, return_inverse=True, return_counts=True)
    return n[at]


def _flagged(docs: DataFrame, good: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, text, target) of all rows."""
    ids = good.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct().withColumn("t", F.lit(1))
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    rows = docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).alias("text"))
    return rows.join(ids, "doc_id", "left").select("doc_id", "text", F.coalesce("t", F.lit(0)).alias("target"))


class Chunk:
    """Tokens of the texts of a chunk. Its different words and pairs are the same, in the same order, however its texts come."""

    def __init__(self, texts: list, target: list):
        held = [codes(t) for t in texts]
        self.own, self.sizes = np.array(target, np.int64), np.array([len(c) for c in held], np.int64)
        self.words = np.concatenate([*held, np.zeros(0, np.uint64)])
        self.text = np.repeat(np.arange(len(held)), self.sizes)
        self.follows = np.r_[False, self.text[1:] == self.text[:-1]][: len(self.words)]
        at = np.flatnonzero(self.follows)
        self.pairs = pair_codes(self.words[at - 1], self.words[at])

    def counted(self) -> list[tuple[np.ndarray, np.ndarray]]:
        """(different keys in order, counts of background and target), of words and of pairs."""
        kind, out = self.own[self.text] == 1 if len(self.words) else np.zeros(0, bool), []
        for keys, good in ((self.words, kind), (self.pairs, kind[self.follows])):
            every, n = np.unique(keys, return_counts=True)
            some, k = np.unique(keys[good], return_counts=True)
            counts = np.stack([n, np.zeros_like(n)])
            counts[1, np.searchsorted(every, some)] = k
            counts[0] -= counts[1]
            out.append((every, counts))
        return out

    def numbers(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(word, word before, pair) numbers from 1 on, in the order of the keys; 0: none."""
        w = 1 + np.unique(self.words, return_inverse=True)[1].astype(np.int64)
        b = np.where(self.follows, np.r_[0, w[:-1]][: len(w)], 0)
        p = np.zeros(len(w), np.int64)
        p[self.follows] = 1 + np.unique(self.pairs, return_inverse=True)[1]
        return w, b, p


def packed(keys: np.ndarray) -> bytes:
    """Sorted keys as steps, by byte planes: those of the high bytes are nearly empty, so that Spark's codec shrinks them."""
    return np.diff(keys, prepend=np.uint64(0)).astype("<u8").view(np.uint8).reshape(-1, 8).T.tobytes()


def unpacked(x: bytes) -> np.ndarray:
    return np.cumsum(np.ascontiguousarray(np.frombuffer(x, np.uint8).reshape(8, -1).T).view("<u8").ravel(), dtype=np.uint64)


def narrow(x: np.ndarray) -> bytes:
    kind = next(k for k in ("<u1", "<u2", "<u4", "<u8") if x.max(initial=0) <= np.iinfo(k).max)
    return kind[-1].encode() + x.astype(kind).tobytes()


def wide(x: bytes) -> np.ndarray:
    return np.frombuffer(x, f"<u{x[:1].decode()}", offset=1).astype(np.int64).reshape(2, -1)


def _chunks(rows: DataFrame) -> tuple[DataFrame, int, int]:
    """rows with the chunk of each, the number of chunks, and that of shards (a power of two)."""
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(rows.sparkSession.sparkContext.defaultParallelism, -(-size // CHUNK_BYTES))
    return rows.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n)).cast("int")), n, 1 << (-(-size // SHARD_BYTES) - 1).bit_length() if size else 1


def answers(rows: DataFrame, chunks: int, shards: int) -> DataFrame:
    """(chunk, shard, words, pairs): counts over the corpus of the keys that a chunk has in a shard, in their order. In the
    row of chunk -1 of each shard, words holds its different words and the tokens of background and target.

    rows: (doc_id, text, target, chunk).
    """
    edges = np.arange(1, shards, dtype=np.uint64) << np.uint64(64 - (shards - 1).bit_length() if shards > 1 else 0)

    def ask(batches):
        texts, target, chunk = [], [], None
        for b in batches:
            if b.num_rows:
                texts += b.column(1).to_pylist()
                target += b.column(2).to_pylist()
                chunk = b.column(3)[0].as_py()
        if chunk is None:
            return
        cols, found = [[] for _ in range(6)], Chunk(texts, target).counted()
        at = [np.r_[0, np.searchsorted(keys, edges), len(keys)] for keys, _ in found]
        for s in range(shards):
            parts = [(keys[a[s] : a[s + 1]], n[:, a[s] : a[s + 1]]) for (keys, n), a in zip(found, at, strict=True)]
            if sum(len(k) for k, _ in parts):
                for c, v in zip(cols, (chunk, s, *[v for k, n in parts for v in (packed(k), narrow(n))]), strict=True):
                    c.append(v)
        yield pa.RecordBatch.from_arrays([*[pa.array(c, pa.int32()) for c in cols[:2]], *[pa.array(c, pa.binary()) for c in cols[2:]]], ["chunk", "shard", "words", "word_counts", "pairs", "pair_counts"])

    def add(batches):
        held = [list(r) for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)]
        if not held:
            return
        replies, total = [], None
        for k in (2, 4):
            keys = [unpacked(r[k]) for r in held]
            every, at = np.unique(np.concatenate(keys), return_inverse=True)
            counts = [wide(r[k + 1]) for r in held]
            sums = np.stack([np.bincount(at, np.concatenate([c[m] for c in counts]), len(every)) for m in (0, 1)]).astype(np.int64)
            total = np.r_[len(every), sums.sum(1)] if total is None else total
            cuts = np.cumsum([len(x) for x in keys])[:-1]
            replies.append([narrow(sums[:, x]) for x in np.split(at, cuts)])
        cols = [pa.array([-1, *[r[0] for r in held]], pa.int32()), pa.array([held[0][1], *[r[1] for r in held]], pa.int32())]
        yield pa.RecordBatch.from_arrays([*cols, pa.array([total.astype(np.int64).tobytes(), *replies[0]], pa.binary()), pa.array([b"", *replies[1]], pa.binary())], ["chunk", "shard", "words", "pairs"])

    asked = rows.repartitionById(chunks, F.col("chunk")).mapInArrow(ask, "chunk int, shard int, words binary, word_counts binary, pairs binary, pair_counts binary")
    return asked.repartitionById(shards, F.col("shard")).mapInArrow(add, "chunk int, shard int, words binary, pairs binary")


def score_documents(docs: DataFrame, good: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, is_target, target_loss, background_loss, score); good: doc_id of target documents.

    Losses are means over tokens, in nats. Null, empty and wordless texts have 0 tokens, losses and score. Null ids are
    background; repeated rows each count; with an empty target or background the other model's smoothing alone is
    compared. An empty table gives no rows; other columns are not read.
    """
    prepare(docs.sparkSession)
    rows, chunks, shards = _chunks(_flagged(docs, good, id_col, text_col))
    replies = stored(answers(rows, chunks, shards), "counts")
    totals = sum((np.frombuffer(r.words, np.int64) for r in replies.where("chunk < 0").select("words").collect()), np.zeros(3, np.int64))  # one row a shard
    vocabulary, total = max(WORDS, int(totals[0])), totals[1:]

    def run(batches):
        ids, texts, target, counts = [], [], [], []
        for b in batches:
            for i, t, k, s, w, p in zip(*(c.to_pylist() for c in b.columns[1:]), strict=True):
                if s is None:
                    ids.append(i), texts.append(t), target.append(k)
                else:
                    counts.append((s, wide(w), wide(p)))
        if not ids:
            return
        counts.sort(key=lambda x: x[0])
        words, pairs = (np.concatenate([np.zeros((2, 1), np.int64), *[c[k] for c in counts]], axis=1) for k in (1, 2))
        chunk = Chunk(texts, target)
        losses = Models(words, pairs, total, vocabulary).token_losses(*chunk.numbers(), chunk.text, chunk.own)
        means = [np.bincount(chunk.text, x, len(ids)) / np.maximum(chunk.sizes, 1) for x in losses]
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(chunk.sizes), pa.array(target, pa.int32()), *[pa.array(m, pa.float64()) for m in means]], ["doc_id", "n_tokens", "target", "target_loss", "background_loss"])

    none = lambda kind: F.lit(None).cast(kind)
    both = rows.select("chunk", "doc_id", "text", "target", none("int").alias("shard"), none("binary").alias("words"), none("binary").alias("pairs"))
    both = both.unionByName(replies.where("chunk >= 0").select("chunk", none("long").alias("doc_id"), none("string").alias("text"), none("int").alias("target"), "shard", "words", "pairs"))
    out = both.repartitionById(chunks, F.col("chunk")).mapInArrow(run, "doc_id long, n_tokens long, target int, target_loss double, background_loss double")
    return out.select("doc_id", "n_tokens", (F.col("target") == 1).alias("is_target"), "target_loss", "background_loss", (F.col("target_loss") - F.col("background_loss")).alias("score"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").where("quality = 1").select("doc_id"))
