"""Operator 7: vector bin packing of training examples under limits on tokens, segments and loss-bearing tokens.

A sequence is a bin with three capacities. The open sequence takes, again and again, the waiting piece with the largest
weighted dot product of its demand with what is left of the capacities (the dot-product heuristic); if none fits whole,
the piece with the largest product is cut to what is left. An example may be cut anywhere, so a sequence closes full unless the
limit on segments or on loss tokens closes it, or nothing waits any more; what it holds then closes as sequences of power-of-two
length, which need no padding. Of an example longer than a sequence, full sequences of its own come first. Each partition packs on its own: no shuffle, state bounded by WINDOW pieces, and the same result when a
task is run again.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .byte_bpe import byte_bpe
from .common import prepare, quoted

#: Pieces that wait to be placed, at most.
WINDOW = 2048


@dataclass(frozen=True)
class Limits:
    tokens: int = 1024
    segments: int = 64
    loss: int = 1024

    def __post_init__(self):
        if min(self.tokens, self.segments, self.loss) < 1:
            raise ValueError("limits are at least 1")


class Packer:
    """Places pieces (key, start, length, prompt): of an example's tokens [start, start + length), those at or beyond
    prompt bear loss. placed() rows: (key, start, length, sequence, offset)."""

    def __init__(self, limits: Limits):
        self.limits = limits
        #: Tokens and loss tokens of what waits in each slot; every piece is one segment. An empty slot fits nowhere.
        self.tokens, self.bearing = np.full(WINDOW, np.inf), np.full(WINDOW, np.inf)
        self.items, self.free = [None] * WINDOW, list(range(WINDOW))
        #: Sequences so far, and bins: a bin that isn't full becomes several sequences.
        self.sequence, self.bins, self.rows = 0, 0, []

    @staticmethod
    def loss(start: int, length: int, prompt: int) -> int:
        return max(0, start + length - max(start, prompt))

    def add(self, key, length: int, prompt: int = 0) -> None:
        at, lim = 0, self.limits
        while length - at >= lim.tokens and self.loss(at, lim.tokens, prompt) <= lim.loss:  # a full sequence of one segment
            self.bins += 1
            self.close([(key, at, lim.tokens, prompt)])
            at += lim.tokens
        while length > at:
            n = min(length - at, self.most(at, lim.tokens, lim.loss, prompt))
            if not self.free:
                self.fill()
            k = self.free.pop()
            self.items[k], self.tokens[k], self.bearing[k] = (key, at, n, prompt), n, self.loss(at, n, prompt)
            at += n

    @staticmethod
    def most(start: int, tokens: float, loss: float, prompt: int) -> int:
        """Longest piece from start within so many tokens and loss tokens."""
        return int(min(tokens, max(0, prompt - start) + loss))

    def close(self, pieces: list) -> None:
        offset = 0
        for key, start, n, _ in pieces:
            self.rows.append((key, start, n, self.sequence, offset))
            offset += n
        self.sequence += 1

    def fill(self) -> None:
        """Close one sequence from the waiting pieces, or what a limit leaves of one."""
        cap = (self.limits.tokens, self.limits.segments, self.limits.loss)
        room, pieces = list(cap), []
        self.bins += 1
        while min(room) >= 1 and len(self.free) < WINDOW:
            fits = (self.tokens <= room[0]) & (self.bearing <= room[2])
            # The segments' share of the product is the same for all.
            product = self.tokens * (room[0] / cap[0] ** 2) + self.bearing * (room[2] / cap[2] ** 2)
            k = int(np.where(fits, product, -1).argmax())
            if fits[k]:
                piece = self.items[k]
                self.items[k], self.tokens[k], self.bearing[k] = None, np.inf, np.inf
                self.free.append(k)
            else:
                k = int(np.where(np.isfinite(self.tokens), product, -1).argmax())
                key, start, n, prompt = self.items[k]
                take = min(n, self.most(start, room[0], room[2], prompt))
                if not take:
                    break
                piece, rest = (key, start, take, prompt), (key, start + take, n - take, prompt)
                self.items[k], self.tokens[k], self.bearing[k] = rest, n - take, self.loss(start + take, n - take, prompt)
            pieces.append(piece)
            room = [room[0] - piece[2], room[1] - 1, room[2] - self.loss(*piece[1:])]
        total = sum(p[2] for p in pieces)
        if total == self.limits.tokens:
            return self.close(pieces)
        while pieces:  # power-of-two sequences, the largest first
            want = 1 << (total.bit_length() - 1)
            total -= want
            part = []
            while want:
                key, start, n, prompt = pieces[0]
                take = min(n, want)
                part.append((key, start, take, prompt))
                want -= take
                if take == n:
                    pieces.pop(0)
                else:
                    pieces[0] = (key, start + take, n - take, prompt)
            self.close(part)

    def finish(self) -> None:
        while len(self.free) < WINDOW:
            self.fill()

    def placed(self) -> list:
        rows, self.rows = self.rows, []
        return rows


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, loss_tokens long"


def pack_texts(docs: DataFrame, vocabulary: str, limits: Limits = Limits(), end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", prompt_col: str | None = None) -> DataFrame:
    """Encode every whole text, append end_id, cut and place: one row a piece.

    prompt_col: an optional text column that precedes the text and bears no loss. Null texts are empty (the end id alone);
    null and repeated ids are kept as they are, each row an example of its own; an empty table gives no rows; other columns
    are not read. Ids wait in memory only while a piece of theirs does.
    """
    prepare(docs.sparkSession)
    rows = docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).alias("text"), (F.col(quoted(prompt_col)) if prompt_col else F.lit(None).cast("string")).alias("prompt"))

    def pack(batches):
        from pyspark import TaskContext

        base = TaskContext.get().partitionId() << 33
        bpe, packer, ids, left, n = byte_bpe(vocabulary), Packer(limits), {}, {}, 0
        last = np.array([end_id], bpe.kind).tobytes()

        def out():
            cols = [[] for _ in range(8)]
            for key, start, length, sequence, offset in packer.placed():
                doc_id, total, prompt, data = ids[key]
                part = data[start : start + length].astype("<u4").tobytes()
                for c, v in zip(cols, (doc_id, start, length, zlib.crc32(part), total, base + sequence, offset, packer.loss(start, length, prompt)), strict=True):
                    c.append(v)
                left[key] -= length
                if not left[key]:
                    del ids[key], left[key]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names)

        names = [x.split()[0] for x in SCHEMA.split(", ")]
        for b in batches:
            for doc_id, text, prompt in zip(*(b.column(k).to_pylist() for k in range(3)), strict=True):
                head = bpe.encode(prompt)
                data = np.frombuffer(head + bpe.encode(text) + last, bpe.kind)
                ids[n], left[n] = (doc_id, len(data), len(head) // bpe.width, data), len(data)
                packer.add(n, len(data), len(head) // bpe.width)
                n += 1
            yield out()
        packer.finish()
        yield out()

    return rows.mapInArrow(pack, SCHEMA)


def instruction_examples(conversations: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(doc_id, conv_id, turn, prompt, text): one example for each answer of the assistant, with the turn before as its prompt
    (null for a first turn). For pack_texts with prompt_col="prompt": only answers bear loss."""
    turns = conversations.select(F.col(quoted(id_col)).alias("conv_id"), F.col(quoted(turn_col)).alias("turn"), F.col(quoted(role_col)).alias("role"), F.col(quoted(text_col)).alias("text"))
    before = F.lag("text").over(Window.partitionBy("conv_id").orderBy("turn", "role", "text"))
    out = turns.withColumn("prompt", before).where("role = 'assistant'")
    return out.select(F.xxhash64("conv_id", "turn").alias("doc_id"), "conv_id", "turn", "prompt", "text")


def padding(pieces: DataFrame, tokens: int = 1024) -> DataFrame:
    """Sequences, tokens and padding of packed pieces: padded to the limit unless the length is a power of two."""
    seq = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.expr("n & (n - 1)") == 0, 0).otherwise(F.lit(tokens) - F.col("n"))
    return seq.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding"))


def op7(spark: SparkSession, docs: DataFrame, vocabulary: str) -> DataFrame:
    return pack_texts(docs, vocabulary)
