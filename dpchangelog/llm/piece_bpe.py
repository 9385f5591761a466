"""Operator 8: encoding and decoding with merge-type SentencePiece vocabularies, by a score-ordered agenda.

A word starts as its characters. An agenda holds the adjacent symbol pairs whose joint text is a piece, best score first
and leftmost on ties; the best pair is merged and its two new neighbours enter the agenda, until it is empty. Symbols
outside the vocabulary become byte pieces.

No piece of such a vocabulary holds a newline, or the space mark after another character (checked at load), so nothing
merges across those places: a text is the sequence of its words, each distinct word is encoded once and kept in a bounded
cache. The new words of an Arrow batch are encoded side by side, their agendas in arrays. New words of every Arrow batch are checked against the sentencepiece library, ids and decoded text. A text whose own ids
or decoded text differ from the library's gets the library's, and says so in by_library; it never stops the job.
"""

from __future__ import annotations

import hashlib
import heapq
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, quoted

SPACE = "▁"
CACHE_WORDS = 450_000
_loaded: dict = {}


class Agenda:
    """Ids of one word by merging."""

    def __init__(self, pieces: list[tuple[str, float, bool]], unknown: int, byte_ids: list[int]):
        """pieces: (text, score, may take part in merges) by id."""
        self.ids = {t: i for i, (t, _, ok) in enumerate(pieces) if ok}
        place = {s: r for r, s in enumerate(sorted({s for _, s, ok in pieces if ok}, reverse=True))}
        #: Text -> place of its score, the best 0; equal scores share one.
        self.cost = {t: place[s] for t, s, ok in pieces if ok}
        self.unknown, self.byte_ids = unknown, byte_ids

    def symbols(self, word: str) -> list[str]:
        """The word cut into the pieces and characters that are left when nothing merges any more."""
        n, get = len(word), self.cost.get
        #: Place of the pair that starts at each symbol, -1 for none. The agenda has place * n + position of these, and of pairs
        #: that have changed since; only what still stands here is merged.
        want = [get(word[i : i + 2], -1) for i in range(n - 1)]
        agenda = [r * n + i for i, r in enumerate(want) if r >= 0]
        symbols = list(word)
        if not agenda:
            return symbols
        want.append(-1)
        before, after = list(range(-1, n - 1)), list(range(1, n + 1))
        heapq.heapify(agenda)
        pop, push = heapq.heappop, heapq.heappush
        while agenda:
            r, i = divmod(pop(agenda), n)
            if want[i] != r:
                continue
            j = after[i]
            t = symbols[i] = symbols[i] + symbols[j]
            symbols[j], want[i], want[j] = "", -1, -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                if (r := get(t + symbols[k], -1)) >= 0:
                    want[i] = r
                    push(agenda, r * n + i)
            if (h := before[i]) >= 0:
                r = want[h] = get(symbols[h] + t, -1)
                if r >= 0:
                    push(agenda, r * n + h)
        return [s for s in symbols if s]

    def encode(self, word: str) -> list[int]:
        return self.numbers(self.symbols(word))

    def numbers(self, symbols: list[str]) -> list[int]:
        out = []
        for s in symbols:
            if (k := self.ids.get(s)) is not None:
                out.append(k)
            elif self.byte_ids:
                out.extend(self.byte_ids[b] for b in s.encode())
            else:
                out.append(self.unknown)
        return out


class BatchAgenda:
    """The same agenda for many words side by side, in arrays: each round takes the best pair of every word, leftmost on ties,
    merges it, and puts its neighbours' new pairs in. A word leaves once it has no pair. Words with characters that are no
    pieces, and words of more than LONGEST characters, which would keep the others' rounds going, are left out."""

    LONGEST, WORDS = 64, 50_000
    NONE = 1 << 30

    def __init__(self, one: Agenda):
        names = list(one.ids)
        at = {t: i for i, t in enumerate(names)}
        self.piece = np.array([one.ids[t] for t in names], np.int64)
        self.chars = np.full(0x110000, -1, np.int64)
        for t, i in at.items():
            if len(t) == 1:
                self.chars[ord(t)] = i
        self.size = max(len(names), 1)
        pairs = sorted((at[t[:k]] * self.size + at[t[k:]], one.cost[t], i) for t, i in at.items() for k in range(1, len(t)) if t[:k] in at and t[k:] in at)
        self.keys, self.ranks, self.joint = (np.array(x, np.int64) for x in zip(*[*pairs, (1 << 62, self.NONE, 0)], strict=True))

    def _pairs(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Place of each pair among the known ones; the last stands for none."""
        key = left * self.size + right
        k = np.searchsorted(self.keys, key)
        return np.where(self.keys[k] == key, k, len(self.keys) - 1)

    def encode(self, words: list[str]) -> list[list[int] | None]:
        """Ids of each word; None for those left out."""
        out: list = [None] * len(words)
        for a in range(0, len(words), self.WORDS):
            some = [i for i in range(a, min(a + self.WORDS, len(words))) if 0 < len(words[i]) <= self.LONGEST]
            if some:
                self._encode([words[i] for i in some], some, out)
        return out

    def _encode(self, words: list[str], places: list[int], out: list) -> None:
        n = np.array(list(map(len, words)))
        sym = self.chars[np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)]
        known = np.minimum.reduceat(sym, np.cumsum(n) - n) >= 0
        sym, word, n = sym[np.repeat(known, n)], np.repeat(np.flatnonzero(known), n[known]), n[known]
        none, done = len(self.keys) - 1, []
        pair = np.full(len(sym), none)
        inner = np.flatnonzero(word[1:] == word[:-1])
        pair[inner] = self._pairs(sym[inner], sym[inner + 1])
        while len(sym):
            first = np.cumsum(n) - n
            best = np.minimum.reduceat((self.ranks[pair] << 32) + np.arange(len(sym)), first)
            open_ = best < self.NONE << 32
            if not open_.all():
                rows = np.repeat(open_, n)
                done.append((word[~rows], sym[~rows]))
                best = (best - np.cumsum(np.where(open_, 0, n)))[open_]  # positions once closed words before have left
                sym, word, pair, n = sym[rows], word[rows], pair[rows], n[open_]
                if not len(sym):
                    break
            i = best & 0xFFFFFFFF
            sym[i] = self.joint[pair[i]]
            keep = np.ones(len(sym), bool)
            keep[i + 1] = False
            i = i - np.arange(len(i))  # one symbol of each word before has gone
            sym, word, n = sym[keep], word[keep], n - 1
            pair = pair[keep]
            last = i + 1 == np.cumsum(n)
            pair[i[last]] = none
            i_in = i[~last]
            pair[i_in] = self._pairs(sym[i_in], sym[i_in + 1])
            h = i[i > np.cumsum(n) - n] - 1
            pair[h] = self._pairs(sym[h], sym[h + 1])
        if not done:
            return
        word, sym = (np.concatenate(x) for x in zip(*done, strict=True))
        order = np.argsort(word, kind="stable")
        ids = self.piece[sym[order]].tolist()
        many = np.bincount(word, minlength=len(words))
        ends = np.cumsum(many).tolist()
        for k, (m, end) in enumerate(zip(many.tolist(), ends, strict=True)):
            if m:
                out[places[k]] = ids[end - m : end]


class _Words(dict):
    """word -> (decimal ids joined by commas, their number, decoded text). mark: the space mark or nothing stands before."""

    def __init__(self, owner: "PieceBpe", mark: str):
        super().__init__()
        self.owner, self.mark, self.new = owner, mark, []

    def __missing__(self, word: str):
        if SPACE in word or not word or (self.mark, word) in self.owner.bad:
            raise KeyError(word)
        ids = self.owner.agenda.encode(self.mark + word)
        if len(self) >= CACHE_WORDS:
            self.clear()
        return self.keep(word, ids)

    def keep(self, word: str, ids: list[int]):
        owner = self.owner
        # Ids that are all pieces' have the word's own text.
        text = owner.surface(ids) if any(map(owner.odd.__contains__, ids)) else " " + word if self.mark else word
        value = self[word] = (",".join(map(owner.decimal.__getitem__, ids)), len(ids), text)
        self.new.append((word, ids, text))
        return value

    def learn(self, words: set[str]) -> None:
        """Encode those not in the cache side by side; what is odd, long or too much for the cache is left to __missing__."""
        new = [w for w in words if w not in self]
        if len(self) + len(new) > CACHE_WORDS:
            self.clear()
            new = list(words)[:CACHE_WORDS]
        new = [w for w in new if w and SPACE not in w and (self.mark, w) not in self.owner.bad]
        for w, ids in zip(new, self.owner.batch.encode([self.mark + w for w in new]), strict=True):
            if ids is not None:
                self.keep(w, ids)


class PieceBpe:
    def __init__(self, path: str, verify: bool = True):
        import sentencepiece

        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        p, n = self.library, self.library.get_piece_size()
        self.verify = verify
        #: Words whose own ids differ from the library's, and how many texts took the library's ids.
        self.bad: set = set()
        self.replaced = 0
        names = [p.id_to_piece(i) for i in range(n)]
        normal = [not (p.is_unknown(i) or p.is_control(i) or p.is_unused(i) or p.is_byte(i)) for i in range(n)]
        by_name = {f"<0x{b:02X}>": b for b in range(256)}
        self.byte_of = {i: by_name[names[i]] for i in range(n) if p.is_byte(i)}
        byte_ids = sorted(self.byte_of, key=self.byte_of.get)
        self.agenda = Agenda([(names[i], p.get_score(i), normal[i]) for i in range(n)], p.unk_id(), byte_ids if len(byte_ids) == 256 else [])
        self.batch = BatchAgenda(self.agenda)
        self.decimal = list(map(str, range(n)))
        self.odd = {i for i in range(n) if not normal[i]}
        self.names, self.control = names, {i for i in range(n) if p.is_control(i)}
        across = re.compile(f"[^{SPACE}]{SPACE}|\n")
        self.by_word = not any(across.search(t) for t, ok in zip(names, normal, strict=True) if ok) and len(byte_ids) == 256
        self.marked, self.plain = _Words(self, SPACE), _Words(self, "")
        self.newline = ",".join(map(str, self.agenda.encode("\n")))

    def surface(self, ids: list[int]) -> str:
        """Decoded text of ids, the leading space kept."""
        out, raw = [], bytearray()
        for i in ids:
            if i in self.byte_of:
                raw.append(self.byte_of[i])
                continue
            if raw:
                out.append(loose_utf8(bytes(raw)))
                raw.clear()
            if i not in self.control:
                out.append(" ⁇ " if i == self.agenda.unknown else self.names[i].replace(SPACE, " "))
        if raw:
            out.append(loose_utf8(bytes(raw)))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        """As the library's decode: without the space that encoding put in front."""
        text = self.surface(ids)
        return text[1:] if ids and ids[0] not in self.byte_of and self.names[ids[0]].startswith(SPACE) else text

    def whole(self, text: str) -> tuple[str, int, str]:
        """By maximal words of the marked text; for texts with runs of spaces or with space marks of their own."""
        ids: list[int] = []
        for chunk in re.findall(f"{SPACE}+[^{SPACE}\n]*|[^{SPACE}\n]+|\n" if self.by_word else "(?s).+", SPACE + text.replace(" ", SPACE)):
            ids += self.agenda.encode(chunk)
        decoded = self.decode(ids)
        if self.verify:
            theirs = self.library.encode(text)
            if ids != theirs or decoded != self.library.decode(theirs):
                self.replaced += 1
                ids, decoded = theirs, self.library.decode(theirs)
        return ",".join(map(str, ids)), len(ids), decoded

    def encode(self, text: str | None) -> tuple[str, int, str]:
        """(ids joined by commas, their number, decoded text); null and empty texts have no ids."""
        if not text:
            return "", 0, ""
        if not self.by_word:
            return self.whole(text)
        marked, plain, ids, n, decoded = self.marked, self.plain, [], 0, []
        try:
            for k, line in enumerate(text.split("\n")):
                words = line.split(" ")
                parts = list(map(marked.__getitem__, words[1:]))
                if not k:
                    parts.insert(0, marked[words[0]])
                elif words[0]:
                    parts.insert(0, plain[words[0]])
                if k:
                    ids.append(self.newline)
                    n += 1
                    decoded.append("\n")
                for a, b, c in parts:
                    ids.append(a)
                    n += b
                    decoded.append(c)
        except KeyError:
            return self.whole(text)
        return ",".join(ids), n, "".join(decoded)[1:]

    def learn(self, texts: list[str | None]) -> None:
        """Encode the words of texts that are new, all at once."""
        if not self.by_word:
            return
        marked, plain = set(), set()
        for text in texts:
            if text:
                first, *rest = text.split("\n")
                marked.update(first.split(" "))
                for line in rest:
                    head, *words = line.split(" ")
                    plain.add(head)
                    marked.update(words)
        self.marked.learn(marked)
        self.plain.learn(plain)

    def check_new(self) -> bool:
        """Hold the words first met since the last call against the library. Those that differ leave the cache for good, so texts
        with them are encoded as a whole; whether there were any."""
        wrong = False
        for words, lead, cut in ((self.marked, "", 0), (self.plain, "\n", 2)):
            new, words.new = words.new, []
            if not (self.verify and new):
                continue
            theirs = self.library.encode([lead + w for w, _, _ in new], num_threads=1)
            bad = {w for (w, ids, _), t in zip(new, theirs, strict=True) if ids != t[cut:]}
            if not cut:
                texts = self.library.decode([ids for _, ids, _ in new])
                bad |= {w for (w, _, own), t in zip(new, texts, strict=True) if own[1:] != t}
            for w in bad:
                words.pop(w, None)
                self.bad.add((words.mark, w))
            wrong = wrong or bool(bad)
        return wrong


def loose_utf8(raw: bytes) -> str:
    """UTF-8, each byte that isn't part of a valid character as U+FFFD."""
    try:
        return raw.decode()
    except UnicodeDecodeError as e:
        return raw[: e.start].decode() + "�" + loose_utf8(raw[e.start + 1 :])


def piece_bpe(path: str, verify: bool = True) -> PieceBpe:
    if (path, verify) not in _loaded:
        _loaded.clear()
        _loaded[path, verify] = PieceBpe(path, verify)
    return _loaded[path, verify]


def encode_decode(docs: DataFrame, model: str, verify: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids string, n_tokens, decoded, by_library) of every whole text.

    ids: decimal, joined by commas; by_library: own ids differed, so the library's stand here. Null texts are empty: no ids, empty
    decoded text. Null and repeated ids stay as rows of their own; an empty table gives no rows; other columns are not read.
    verify=False leaves out the library's check.
    """
    return _map(docs, model, verify, id_col, text_col, lambda ids, n, text: (ids, n, text), "doc_id long, ids string, n_tokens long, decoded string, by_library boolean")


def _map(docs, model, verify, id_col, text_col, shape, schema):
    prepare(docs.sparkSession)
    names = [x.split()[0] for x in schema.split(", ")]
    kinds = [{"long": pa.int64(), "string": pa.string(), "boolean": pa.bool_()}[x.split()[1]] for x in schema.split(", ")]

    def one(coder, text):
        before = coder.replaced
        return (*shape(*coder.encode(text)), coder.replaced > before)

    def run(batches):
        coder = piece_bpe(model, verify)
        for b in batches:
            texts = b.column(1).to_pylist()
            coder.learn(texts)
            rows = [one(coder, t) for t in texts]
            if coder.check_new():
                rows = [one(coder, t) for t in texts]
            cols = list(zip(*rows, strict=True)) or [()] * (len(names) - 1)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds[1:], strict=True))], names)

    return docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).alias("text")).mapInArrow(run, schema)


def digest(ids: str, n: int, text: str) -> tuple[int, str, str]:
    return n, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest()


def op8(spark: SparkSession, docs: DataFrame, model: str) -> DataFrame:
    return _map(docs, model, True, "doc_id", "text", digest, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, by_library boolean")
