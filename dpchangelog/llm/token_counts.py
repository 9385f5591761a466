"""Operator 2: token counts by rank-synchronous merging of ragged arrays.

The distinct words of a batch that are not in the cache are held as one flat array of symbol ids with word offsets. In
each round every word finds the lowest rank among its adjacent pairs, and all its pairs of that rank are merged at once
(leftmost first where they overlap); words without a mergeable pair leave. A word's count is the number of symbols that
survive. Merging one rank at a time gives what one merge at a time does where every token comes from one merge, and merges
use only tokens of earlier ones: then a new symbol's pairs all rank behind the merge that made it. The loader checks both; for
a vocabulary without them the library counts whole texts.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .byte_bpe import load_tokenizer
from .common import prepare, quoted

CACHE_WORDS = 900_000
NONE = np.int32(2**31 - 1)
_loaded: dict = {}


class PairRanks:
    """(left, right) -> (rank, merged id), in a flat hash table with a second one for its collisions."""

    def __init__(self, left: np.ndarray, right: np.ndarray, merged: np.ndarray, size: int):
        self.size, self.left, self.merged = np.int64(size), left, merged
        keys = left * self.size + right
        self.bits, self.key, self.rank = 21, np.full(1 << 21, -1, np.int64), np.full(1 << 21, NONE, np.int32)
        at = self.slot(keys)
        _, first = np.unique(at, return_index=True)
        self.key[at[first]], self.rank[at[first]] = keys[first], first
        rest = np.setdiff1d(np.arange(len(keys)), first)
        order = rest[np.argsort(keys[rest])]
        self.rest_key, self.rest_rank = keys[order], order.astype(np.int32)
        self.clash = np.zeros(1 << 21, bool)
        self.clash[at[rest]] = True

    def slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = left * self.size + right
        at = self.slot(keys)
        out = np.where(self.key[at] == keys, self.rank[at], NONE)
        again = np.flatnonzero((out == NONE) & self.clash[at])
        if len(again):
            k = np.searchsorted(self.rest_key, keys[again]).clip(max=len(self.rest_key) - 1)
            hit = self.rest_key[k] == keys[again]
            out[again[hit]] = self.rest_rank[k[hit]]
        return out


def merge_all(symbols: np.ndarray, sizes: np.ndarray, ranks: PairRanks) -> np.ndarray:
    """Symbols that survive of each word; symbols holds the words one after another."""
    counts = sizes.astype(np.int64).copy()
    words = np.flatnonzero(sizes > 1)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    keep = sizes[owner] > 1
    symbols, owner = symbols[keep].astype(np.int64), owner[keep]
    while len(words):
        inner = owner[1:] == owner[:-1]  # position i and i + 1 are of one word
        rank = np.full(len(symbols), NONE, np.int32)
        at = np.flatnonzero(inner)
        rank[at] = ranks.ranks(symbols[at], symbols[at + 1])
        starts = np.flatnonzero(np.r_[True, ~inner])
        least = np.minimum.reduceat(rank, starts)
        size = np.diff(np.r_[starts, len(symbols)])
        hit = (rank == np.repeat(least, size)) & (rank != NONE)
        # Overlapping pairs of one rank (aaa) follow each other: of each run the 1st, 3rd, ... are merged.
        run = np.flatnonzero(hit)
        if len(run):
            new = np.r_[True, np.diff(run) > 1]
            begin = run[np.maximum.accumulate(np.where(new, np.arange(len(run)), 0))]
            run = run[(run - begin) % 2 == 0]
            symbols[run] = ranks.merged[rank[run]]
            gone = np.zeros(len(symbols), bool)
            gone[run + 1] = True
        else:
            gone = np.zeros(len(symbols), bool)
        done = np.repeat(least == NONE, size)
        live = ~gone & ~done
        ids = owner[starts]
        lost = np.add.reduceat(gone.astype(np.int64), starts)
        counts[ids] = size - lost
        words = ids[least != NONE]
        symbols, owner = symbols[live], owner[live]
    return counts


class TokenCounter:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if model["type"] != "BPE" or spec["normalizer"] or spec["pre_tokenizer"]["type"] != "ByteLevel" or spec["pre_tokenizer"]["add_prefix_space"] or model.get("ignore_merges") or model.get("dropout"):
            raise ValueError("a plain byte-level BPE vocabulary is needed")
        vocab = model["vocab"]
        pairs = [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in model["merges"]]
        ids = np.array([(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs], np.int64)
        self.ranks = PairRanks(ids[:, 0], ids[:, 1], ids[:, 2], max(vocab.values()) + 1)
        self.symbol = np.full(1024, -1, np.int64)
        for t, i in vocab.items():
            if len(t) == 1 and ord(t) < 1024:
                self.symbol[ord(t)] = i
        made = {t: k for k, t in enumerate(ids[:, 2].tolist())}
        uses = np.array([max(made.get(a, -1), made.get(b, -1)) for a, b in ids[:, :2].tolist()], np.int64)
        self.simultaneous = len(made) == len(ids) and bool((uses < np.arange(len(ids))).all())
        self.specials = [t["content"] for t in spec["added_tokens"]]
        if any(t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"] for t in spec["added_tokens"]):
            raise ValueError("special strings that take in their surroundings are not handled")
        self.library = load_tokenizer(path)
        self.pre = self.library.pre_tokenizer
        self.inner: dict[str, int] = {}
        self.first: dict[str, int] = {}
        self.newline = int(self.count_pieces(["\n"])[0])

    def count_pieces(self, texts: list[str]) -> np.ndarray:
        """Tokens of each text that stands on its own, all merged together."""
        pre = [[p for p, _ in self.pre.pre_tokenize_str(t)] for t in texts]
        pieces = [p for ps in pre for p in ps]
        if not pieces:
            return np.zeros(len(texts), np.int64)
        sizes = np.array([len(p) for p in pieces])
        symbols = self.symbol[np.frombuffer("".join(pieces).encode("utf-16-le"), "<u2")]
        counts = merge_all(symbols, sizes, self.ranks)
        owner = np.repeat(np.arange(len(texts)), [len(ps) for ps in pre])
        return np.bincount(owner, counts, len(texts)).astype(np.int64)

    @staticmethod
    def regular(word: str) -> bool:
        return bool(word) and not word[0].isspace() and not word[-1].isspace()

    def learn(self, cache: dict[str, int], words: set[str], lead: str) -> None:
        new = [w for w in words if w not in cache]
        if len(cache) + len(new) > CACHE_WORDS:
            cache.clear()
            new = list(words)
        ok = [w for w in new if self.regular(w)]
        for k in range(0, len(ok), 50_000):
            part = ok[k : k + 50_000]
            cache.update(zip(part, self.count_pieces([lead + w for w in part]).tolist(), strict=True))

    def count(self, texts: list[str | None]) -> list[int]:
        """Tokens of each text; special strings inside count one each. Null: 0."""
        if not self.simultaneous:
            return [len(self.library.encode(t or "", add_special_tokens=False).ids) for t in texts]
        plain, inner, first = [], set(), set()
        for i, t in enumerate(texts):
            if t and not any(s in t for s in self.specials):
                lines = [line.split(" ") for line in t.split("\n")]
                plain.append((i, lines))
                for ws in lines:
                    first.add(ws[0])
                    inner.update(ws[1:])
        self.learn(self.inner, inner, " ")
        self.learn(self.first, first, "")
        out, rest, get, get_first = [0] * len(texts), [], self.inner.__getitem__, self.first.__getitem__
        done = set()
        for i, lines in plain:
            try:
                out[i] = sum([sum(map(get, ws[1:]), get_first(ws[0])) for ws in lines]) + self.newline * (len(lines) - 1)
                done.add(i)
            except KeyError:  # words that don't stand on their own
                pass
        for i, t in enumerate(texts):
            if t and i not in done:
                parts = [t]
                for s in self.specials:
                    cut = [p.split(s) for p in parts]
                    out[i] += sum(len(c) - 1 for c in cut)
                    parts = [p for c in cut for p in c]
                rest += [(i, p) for p in parts if p]
        if rest:
            for (i, _), n in zip(rest, self.count_pieces([p for _, p in rest]).tolist(), strict=True):
                out[i] += n
        return out


def token_counter(path: str) -> TokenCounter:
    if path not in _loaded:
        _loaded.clear()
        _loaded[path] = TokenCounter(path)
    return _loaded[path]


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every whole text.

    Null and empty texts have 0 bytes and tokens. Null and repeated ids stay as rows of their own; an empty table gives no
    rows; other columns are not read.
    """
    prepare(docs.sparkSession)

    def run(batches):
        counter = token_counter(vocabulary)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(counter.count(b.column(2).to_pylist()), pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.coalesce(F.octet_length(quoted(text_col)), F.lit(0)).cast("long").alias("n_bytes"), F.col(quoted(text_col)).alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)


def op2(spark: SparkSession, docs: DataFrame, vocabulary: str) -> DataFrame:
    return count_tokens(docs, vocabulary, 1024)
