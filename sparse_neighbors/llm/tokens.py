"""Token ids of whole texts with a public tokenizer, through bounded caches of words and of pre-tokens.

Texts are cut before each space that a non-space follows. No pre-token of these vocabularies goes on behind such a
space, so the ids of the cuts, put together, are the ids of the whole text. Most cuts occur again and again and are looked
up; one that isn't known is split into pre-tokens by the vocabulary's own rule, and only a pre-token that isn't known
either reaches the library's model. Each worker keeps its caches for all its tasks that tokenize.

Ids are those of the library with add_special_tokens=False. The strings of special tokens in a text are matched as it does
by default; a text that may hold one is encoded by the library as a whole. With special_as_text they are ordinary text.
"""

from __future__ import annotations

import json
import os
import re
import sys
import types
from array import array
from collections.abc import Iterator
from operator import attrgetter

import numpy as np
import pyarrow as pa
import regex

from .shared import give_back
from .textscan import ENCODERS, drop_tables

CUT = re.compile(r" (?=\S)")
ID = attrgetter("id")
LIMIT = 50_000  # entries of one cache generation, with a vocabulary of lower case four times as many pre-tokens and eight times as many words; two generations are held
STEP = 1 << 20  # characters encoded at a time
BEYOND = re.compile("[^\x00-\x1b\x20-\u012f\u0131-\u024f]").search  # the others mean the same to Python and to the library, in any case
DIVIDERS = re.compile("[\x1c-\x1f]").search  # white space to Python only
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"  # fixed value: the library's byte-level rule


def byte_names() -> dict[int, str]:
    """The byte-level alphabet: a printable byte is its Latin-1 character, the others follow from U+0100 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(own)]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class Unsafe(Exception):
    """A cut that depends on what stands before it."""


class Generations(dict):
    """Cache of two generations of LIMIT entries; what was used since the last change of generation survives it."""

    def __init__(self, make):
        super().__init__()
        self.make, self.old = make, {}

    def __missing__(self, key: str) -> bytes:
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
            if "\n" in key:  # two words across a line's end, seldom the same two again
                return value
        self[key] = value
        return value

    def turn(self, limit: int) -> None:
        if len(self) > limit:
            self.old = dict(self)
            self.clear()


class CachedEncoder:
    def __init__(self, path: str, special_as_text: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        added = () if special_as_text else self.tokenizer.get_added_tokens_decoder().values()
        self.marks = sorted({t.content[:2] for t in added})
        self.model, self.names = self.tokenizer.model, byte_names()
        self._rules(json.loads(self.tokenizer.to_str()))
        self.words = Generations(self._word)
        self.tokens = Generations(self._token)

    def _rules(self, file: dict) -> None:
        """The pre-token pattern, whether text is normalised and what stays before a word, for the forms known here; else the library does all."""
        pre, norm = file["pre_tokenizer"] or {}, file["normalizer"]
        self.pattern, self.lower, self.before = None, False, " "
        if pre.get("type") == "ByteLevel" and pre["use_regex"] and not pre["add_prefix_space"] and norm is None:
            self.pattern = regex.compile(BYTE_LEVEL)
        elif pre.get("type") == "Sequence" and [p["type"] for p in pre["pretokenizers"]] == ["Split", "ByteLevel"]:
            split, level = pre["pretokenizers"]
            kept = split["behavior"] == "Removed" and split["invert"] and not level["use_regex"] and not level["add_prefix_space"]
            if kept and [n["type"] for n in (norm or {}).get("normalizers", [])] == ["NFC", "Replace", "Lowercase"] and norm["normalizers"][1]["pattern"] == {"Regex": r"\s+"}:
                self.pattern, self.lower, self.before = regex.compile(split["pattern"]["Regex"]), True, ""

    def _token(self, part: str) -> bytes:
        """Ids of one pre-token."""
        name = part if part.isalpha() and part.isascii() else (part if part.isascii() else part.encode().decode("latin-1")).translate(self.names)
        return array("I", map(ID, self.model.tokenize(name))).tobytes()

    def _pieces(self, text: str) -> bytes:
        """Ids of a text from its pre-tokens."""
        if self.pattern is not None and (text.isascii() or not BEYOND(text)):
            return b"".join(map(self.tokens.__getitem__, self.pattern.findall(text.lower() if self.lower else text)))
        normal = self.tokenizer.normalizer
        names = self.tokenizer.pre_tokenizer.pre_tokenize_str(text if normal is None else normal.normalize_str(text))
        return b"".join(array("I", [t.id for t in self.model.tokenize(n)]).tobytes() for n, _ in names)

    def _word(self, cut: str) -> bytes:
        if not cut or cut[0].isspace():
            raise Unsafe
        if self.pattern is not None and (cut.isascii() or not BEYOND(cut)):
            if cut.isalpha():
                # without anything before it a word is its pre-token, so one cache holds it
                return self._token(cut.lower()) if self.lower else self.tokens[self.before + cut]
            if cut[-1] in ",." and cut[:-1].isalpha():  # a pre-token of letters ends where they do
                return (self.words[cut[:-1].lower()] if self.lower else self.tokens[self.before + cut[:-1]]) + self.tokens[cut[-1]]
        return self._pieces(" " + cut)

    def _encode(self, text: str) -> bytes:
        if any(m in text for m in self.marks):
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        get = self.words.__getitem__
        if self.lower and (text.isascii() or not BEYOND(text)) and not DIVIDERS(text):  # white space and case don't count
            return b"".join(map(get, text.lower().split()))
        first, *cuts = text.split(" ")
        try:
            rest = b"".join(map(get, cuts))
        except Unsafe:
            first, *cuts = CUT.split(text)
            rest = b"".join(map(get, cuts))
        return self._pieces(first) + rest if first else rest

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        self.words.turn(8 * LIMIT if self.lower else LIMIT)  # with lower, pre-tokens of letters are there only
        self.tokens.turn(4 * LIMIT if self.lower else LIMIT)
        out = [self._encode(t) for t in texts]
        return out if sys.byteorder == "little" else [np.frombuffer(x, ">u4").astype("<u4").tobytes() for x in out]


def encoder(path: str) -> CachedEncoder:
    """One encoder per vocabulary, kept by the worker process until it reads texts for another operator."""
    kept = sys.modules.setdefault(ENCODERS, types.ModuleType(ENCODERS))
    if path not in kept.__dict__:
        drop_tables()
        setattr(kept, path, CachedEncoder(path))
        give_back()  # what reading the vocabulary took
    return getattr(kept, path)


def encoded(column: pa.Array, path: str) -> Iterator[tuple[int, bytes]]:
    """(row, ids) of every text of a batch; null counts as empty."""
    own, texts, held, at = encoder(path), [], 0, 0
    for i, t in enumerate(column):
        texts.append(t.as_py() or "")
        held += len(texts[-1])
        if held >= STEP or i + 1 == len(column):
            yield from enumerate(own.encode(texts), at)
            texts, held, at = [], 0, i + 1
