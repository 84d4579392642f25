"""Byte-level BPE through its pre-tokens.

Merges never cross a pre-token, so a text's ids are those of its pre-tokens in turn.  Most
pre-tokens of a corpus are vocabulary strings that encode alone as one token: which ones is proved
once by encoding every vocabulary string with the library.  The rest go through the library's merges,
with a bounded memory of recent answers.

Texts whose splitting could depend on the library's Unicode version, or that hold the strings of
special tokens, go whole through the library.
"""

from __future__ import annotations

import json
import os
import re
import sys
import unicodedata
from array import array
from collections.abc import Iterable, Iterator

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Pre-tokens kept beside the vocabulary; the memory is emptied when it is full.
MEMORY = 1_000_000


def _plain() -> list[str]:
    """Characters whose class no Unicode version since 5 has changed: Latin blocks and common punctuation."""
    ranges = ((0x20, 0x7E), (0xA1, 0xAC), (0xAE, 0x24F), (0x2010, 0x2027), (0x2030, 0x205E), (0x20A0, 0x20B5))
    return ["\t", "\n", "\r", *(chr(c) for a, b in ranges for c in range(a, b + 1))]


def _class(chars: Iterable[str]) -> str:
    return "".join(map(re.escape, chars))


def _byte_letters() -> dict[int, str]:
    """The letter that byte-level vocabularies write for each byte: itself if printable, else the next one from U+0100 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return {b: chr(b if b in printable else next(spare)) for b in range(256)}


_LETTERS = _byte_letters()
_L = _class(c for c in _plain() if unicodedata.category(c)[0] == "L")
_N = _class(c for c in _plain() if unicodedata.category(c)[0] == "N")
_S = r"\t\n\r "
_UNUSUAL = re.compile(f"[^{_class(_plain())}]")
# The split before byte-level merges, for plain characters.
_SPLIT = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{_L}]+| ?[{_N}]+| ?[^{_S}{_L}{_N}]+|[{_S}]+(?![^{_S}])|[{_S}]+")


class _Memory(dict):
    """Answers for pre-tokens: those proved for the vocabulary, and recent ones, found where they are missing."""

    def __init__(self, proved: dict, find):
        super().__init__(proved)
        self.proved, self.find = proved, find

    def __missing__(self, piece: str):
        self[piece] = found = self.find(piece)
        return found

    def bound(self) -> None:
        if len(self) > MEMORY + len(self.proved):
            self.clear()
            self.update(self.proved)


class PretokenEncoder:
    """Ids of texts, exactly as the tokenizers library gives them with add_special_tokens=False."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pre = spec.get("pre_tokenizer") or {}
        #: Whether the vocabulary splits as _SPLIT does; if not, all texts go whole through the library.
        self.splits = spec.get("normalizer") is None and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not (spec["model"].get("dropout") or spec["model"].get("continuing_subword_prefix") or spec["model"].get("end_of_word_suffix"))
        added = [t["content"] for t in spec.get("added_tokens", ())]
        self.special = re.compile("|".join(map(re.escape, added))) if added else None
        self.dtype = np.dtype("<u2" if self.library.get_vocab_size() <= 1 << 16 else "<u4")
        self.merge = self.library.model.tokenize
        self.native = {2: "H", 4: "I"}[self.dtype.itemsize] if sys.byteorder == "little" else None
        self.alone = self._prove() if self.splits else {}
        self.known = _Memory(self.alone, self._merged)
        size = self.dtype.itemsize
        self.sizes = _Memory(dict.fromkeys(self.alone, 1), lambda p: len(self._merged(p)) // size)

    def _prove(self) -> dict[str, bytes]:
        """Vocabulary strings that are one pre-token and encode alone as one token."""
        strings = {}
        for i in self.library.get_vocab().values():
            s = self.library.decode([i], skip_special_tokens=False)
            if s and "�" not in s and not _UNUSUAL.search(s) and _SPLIT.fullmatch(s):
                strings[s] = i
        return {s: self._pack(e.ids) for s, e in zip(strings, self.library.encode_batch(list(strings), add_special_tokens=False)) if len(e.ids) == 1}

    def _pack(self, ids: list[int]) -> bytes:
        return np.array(ids, self.dtype).tobytes()

    def _merged(self, piece: str) -> bytes:
        """The library's merges of one pre-token."""
        tokens = self.merge(piece.encode().decode("latin-1").translate(_LETTERS))
        if self.native is None:
            return self._pack([t.id for t in tokens])
        return array(self.native, [t.id for t in tokens]).tobytes()

    def _whole(self, text: str) -> bool:
        return not self.splits or _UNUSUAL.search(text) is not None or (self.special is not None and self.special.search(text) is not None)

    def packed(self, texts: Iterable[str | None]) -> Iterator[bytes]:
        """The ids of each text as little-endian integers of ``dtype``; a null is an empty text."""
        for t in texts:
            t = t or ""
            if self._whole(t):
                yield self._pack(self.library.encode(t, add_special_tokens=False).ids)
            else:
                yield b"".join(map(self.known.__getitem__, _SPLIT.findall(t)))
                self.known.bound()

    def ids(self, text: str | None) -> np.ndarray:
        return np.frombuffer(next(self.packed([text])), self.dtype)

    def counts(self, texts: Iterable[str | None]) -> Iterator[int]:
        """Number of ids of each text: whole-token pre-tokens count as one each, only the rest is merged."""
        for t in texts:
            t = t or ""
            if self._whole(t):
                yield len(self.library.encode(t, add_special_tokens=False).ids)
            else:
                yield sum(map(self.sizes.__getitem__, _SPLIT.findall(t)))
                self.sizes.bound()


_encoders: dict[str, PretokenEncoder] = {}


def encoder(path: str) -> PretokenEncoder:
    """One encoder for each worker process."""
    if path not in _encoders:
        _encoders[path] = PretokenEncoder(path)
    return _encoders[path]
