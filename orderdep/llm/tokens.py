"""Token ids from public tokenizer files, with repeated text pieces encoded once per worker."""

from __future__ import annotations

import json
import re
from array import array

import numpy as np

from .common import let_go

#: Pieces in a generation of a worker's cache.  A full one becomes the old one, from which pieces still in use come back.
#: Python's dict holds two thirds of a power of two before its table doubles; this stays just below (699,050).
CACHE_PIECES = 699_000
#: The same where executors have other work that needs the memory.
FEW_PIECES = 250_000
_LONG = 48
#: Letters whose normal form, lower case and class are the same in every Unicode version and that stay one letter: A to Z
#: and Latin letters in composed form below U+0250, but the dotted capital I, whose lower case ends in a combining mark.
_LETTERS = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f"
_WORD = re.compile(f"[{_LETTERS}]+")
#: Such a letter and the ASCII signs behind it, up to the end of a piece.
_SIGNED = re.compile(f"(.*[{_LETTERS}])([!-/:-@\\[-`{{-~]+)", re.DOTALL)


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_letters() -> dict[int, str]:
    """The character that stands for each byte in byte-level vocabularies: printable ones for themselves, the others from 256 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + k) for k, b in enumerate(rest)}


class _Pieces(dict):
    """text piece -> its ids as little-endian unsigned 32-bit integers."""

    def __init__(self, tokenizer, prefix: str, normalized: bool, most: int):
        self.most = most
        self.tokenizer, self.model, self.prefix, self.normalized = tokenizer, tokenizer.model, prefix, normalized
        self.letters = _byte_letters()
        self.lead = (prefix.encode().decode("latin-1")).translate(self.letters)
        self.plain = self  # for pieces without the leading space
        self.old: dict[str, bytes] = {}

    def _ids(self, piece: str) -> bytes:
        if not piece and not self.prefix:
            return b""
        if _WORD.fullmatch(piece):
            low = piece.lower() if self.normalized else piece
            if low != piece:
                return self[low]
            word = piece if piece.isascii() else piece.encode().decode("latin-1").translate(self.letters)
            return array("I", [t.id for t in self.model.tokenize(self.lead + word)]).tobytes()
        m = _SIGNED.fullmatch(piece)
        if m:  # a letter and the signs behind it never share a token
            return self[m[1]] + self.plain[m[2]]
        if not self.normalized and "\n" in piece:
            head, _, tail = piece.partition("\n")
            if head and tail and not head[-1].isspace() and not tail[0].isspace():  # a line break alone is a piece of its own
                return self[head] + self.plain["\n"] + self.plain[tail]
        return array("I", self.tokenizer.encode(self.prefix + piece, add_special_tokens=False).ids).tobytes()

    def __missing__(self, piece: str) -> bytes:
        ids = self.old.get(piece)
        if ids is None:
            ids = self._ids(piece)
        if len(piece) <= _LONG:
            if len(self) >= self.most:
                self.old = {}  # before the copy, which would else stand beside two generations
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


class TextEncoder:
    """Whole texts to ids, equal to ``Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids``.

    Where the tokenizer's own pre-tokenizer always ends a piece before a space with a letter, digit or sign behind it, a
    text is cut there and each different piece is encoded once; otherwise whole texts are encoded, as are texts that
    hold the string of a special token, which the library makes that token (``special_as_text``: ordinary text).
    """

    #: Splits after which both the part before and the part behind encode on their own.
    _CUT = re.compile(r" (?=\S)")
    _ODD = re.compile(r" (?:[\s\x1c-\x1f]|$)", re.ASCII)
    _WIDE = re.compile(r" [\x1c-\x1f\x85\xa0  -     　]")

    def __init__(self, path: str, most: int = CACHE_PIECES, special_as_text: bool = False):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        added = [t["content"] for t in spec.get("added_tokens") or () if not (special_as_text and t["special"])]
        self.added = re.compile("|".join(map(re.escape, added))).search if added else None
        norm, pre = spec.get("normalizer"), spec.get("pre_tokenizer") or {}
        parts = pre.get("pretokenizers", [pre])
        spaces_dropped = any(p.get("type") == "Split" and p.get("behavior") == "Removed" and p.get("invert") for p in parts) and norm is not None
        spaces_lead = norm is None and pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space")
        self.kind = "dropped" if spaces_dropped else "leading" if spaces_lead else "whole"
        self.first, self.other = _Pieces(self.tokenizer, "", norm is not None, most), _Pieces(self.tokenizer, " ", norm is not None, most)
        self.other.plain = self.first

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if self.added and self.added(text):
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        if self.kind == "dropped":
            return b"".join(map(self.first.__getitem__, text.replace("\n", " ").split(" ")))
        if self.kind == "leading":
            odd = self._ODD.search(text) or (not text.isascii() and self._WIDE.search(text))
            pieces = self._CUT.split(text) if odd else text.split(" ")
            return self.first[pieces[0]] + b"".join(map(self.other.__getitem__, pieces[1:]))
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def ids(self, text: str | None) -> np.ndarray:
        return np.frombuffer(self.encode(text), "<u4")


_encoders: dict[str, TextEncoder] = {}


def encoder(path: str, most: int = CACHE_PIECES) -> TextEncoder:
    """The worker's encoder for a tokenizer file; its cache outlives the task."""
    if path not in _encoders:
        _encoders[path] = TextEncoder(path, most)
    return _encoders[path]


def forget() -> None:
    """Gives the encoders' memory back; for tasks whose executors go on to other work."""
    import gc

    _encoders.clear()
    gc.collect()
    let_go()
