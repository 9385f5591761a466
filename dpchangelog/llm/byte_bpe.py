"""Byte-level BPE through the tokenizers library, a word at a time with a bounded cache.

The pre-tokenizer of such vocabularies never joins text across a single space or newline that stands between two
non-space characters, so a text is the sequence of its space-led words and newlines, and each distinct word is encoded by
the library once. A text in which this does not hold (runs of white space, white space at an end, special strings) is
encoded by the library as a whole.
"""

from __future__ import annotations

import os
from array import array

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Distinct words kept in memory before the cache starts again.
CACHE_WORDS = 1_000_000
#: Below this character Python and the library agree on what a letter is; words of such letters are one pre-token.
LETTERS_BELOW = "\u0250"
_loaded: dict = {}


def byte_names(pre_tokenizer) -> dict[int, str]:
    """byte -> the character that stands for it, as the library's pre-tokenizer writes it."""
    out = {}
    for first in (0x00, 0x80):  # ASCII as it is; higher bytes as parts of two-byte characters
        for b in range(first, first + 0x80):
            text = chr(b) if not first else bytes([0xC2 + (b >= 0xC0), 0x80 | b & 0x3F]).decode()
            out[b] = "".join(p for p, _ in pre_tokenizer.pre_tokenize_str(text))[-1]
    # Lead bytes 0xC2 to 0xF4, from characters that start with them.
    for b in range(0xC2, 0xF5):
        for text in (bytes([b, *rest]) for rest in ([0x80], [0xA0, 0x80], [0x80, 0x80], [0x90, 0x80, 0x80], [0x80, 0x80, 0x80])):
            try:
                out[b] = "".join(p for p, _ in pre_tokenizer.pre_tokenize_str(text.decode()))[0]
                break
            except UnicodeDecodeError:
                continue
    return out


class Irregular(Exception):
    """The text can't be taken word by word."""


def load_tokenizer(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def split_words(text: str) -> list[list[str]]:
    return [line.split(" ") for line in text.split("\n")]


class _Words(dict):
    """word -> its ids as bytes; lead is what stands before the word."""

    def __init__(self, owner: "ByteBpe", lead: str):
        super().__init__()
        self.owner, self.lead = owner, lead

    def __missing__(self, word: str) -> bytes:
        if not word or word[0].isspace() or word[-1].isspace():
            raise Irregular
        if word[-1] in ".,;:!?" and len(word) > 1 and word[:-1].isalpha():
            value = self[word[:-1]] + self.owner.mark(word[-1])
        elif word.isalpha() and max(word) < LETTERS_BELOW:
            value = self.owner.letters(self.lead + word)
        else:
            value = self.owner.raw(self.lead + word)
        if len(self) >= CACHE_WORDS:
            self.clear()
        self[word] = value
        return value


class ByteBpe:
    def __init__(self, path: str):
        self.tokenizer = load_tokenizer(path)
        self.width = 2 if self.tokenizer.get_vocab_size() <= 1 << 16 else 4
        self.kind = f"<u{self.width}"
        self.specials = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        # Byte-level BPE only; any other kind of vocabulary always takes whole texts.
        state = self.tokenizer.pre_tokenizer
        self.by_word = type(state).__name__ == "ByteLevel" and not state.add_prefix_space and self.tokenizer.normalizer is None
        self.first, self.inner = _Words(self, ""), _Words(self, " ")
        self.newline, self.marks, self.code = self.raw("\n"), {}, "HI"[self.width // 4]
        self.visible = byte_names(state) if self.by_word else {}
        self.tokenize = self.tokenizer.model.tokenize

    def raw(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.kind).tobytes()

    def letters(self, word: str) -> bytes:
        """Ids of a single pre-token by the library's model."""
        return array(self.code, [t.id for t in self.tokenize(word.encode().decode("latin-1").translate(self.visible))]).tobytes()

    def mark(self, c: str) -> bytes:
        if c not in self.marks:
            self.marks[c] = self.raw(c)
        return self.marks[c]

    def encode(self, text: str | None) -> bytes:
        """Ids of a text as little-endian integers of self.width bytes; null is an empty text."""
        if not text:
            return b""
        if not self.by_word or any(s in text for s in self.specials):
            return self.raw(text)
        first, inner = self.first.__getitem__, self.inner.__getitem__
        try:
            return self.newline.join([first(ws[0]) + b"".join(map(inner, ws[1:])) for ws in split_words(text)])
        except Irregular:
            return self.raw(text)


def byte_bpe(path: str) -> ByteBpe:
    """One encoder a worker process."""
    if path not in _loaded:
        _loaded.clear()
        _loaded[path] = ByteBpe(path)
    return _loaded[path]
