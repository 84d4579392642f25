"""SentencePiece encoding that keeps, for every piece, the bytes of the text it stands for.

The model's compiled character map rewrites the text by longest prefixes; each normalised byte
remembers the source bytes it came from.  The library gives the ids; the pieces' lengths, laid end
to end over the normalised text, give each piece's normalised span, and the alignment projects
it to the text as it was.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import lean

_SPACE = "▁".encode()


def _fields(message: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and values of a serialised protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = message[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(message):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
            continue
        size = {1: 8, 5: 4}.get(kind) or varint()
        yield key >> 3, message[at : at + size]
        at += size


class CharacterMap:
    """Longest-prefix rewriting by a compiled character map: a double array over UTF-8 bytes, and the replacements."""

    def __init__(self, blob: bytes):
        size = int.from_bytes(blob[:4], "little") if blob else 0
        self.units = np.frombuffer(blob, "<u4", size // 4, 4).tolist() if blob else []
        self.strings = blob[4 + size :] if blob else b""

    def longest(self, text: bytes, at: int) -> tuple[int, bytes] | None:
        """Length of the longest key that text[at:] begins with, and its replacement."""
        units, found = self.units, None
        if not units:
            return None
        node = self._children(units[0], 0)
        for i in range(at, len(text)):
            node ^= text[i]
            if node >= len(units):
                break
            unit = units[node]
            if unit & 0x800000FF != text[i]:
                break
            node = self._children(unit, node)
            if unit >> 8 & 1:
                found = i + 1 - at, units[node] & 0x7FFFFFFF
        if found is None:
            return None
        length, where = found
        return length, self.strings[where : self.strings.index(0, where)]

    @staticmethod
    def _children(unit: int, node: int) -> int:
        return node ^ (unit >> 10 << ((unit & 512) >> 6))


class Aligned(NamedTuple):
    """Normalised text, and the source byte at which each of its bytes (and its end) begins."""

    text: bytes
    source: np.ndarray


class PieceCodec:
    def __init__(self, path: str):
        import sentencepiece

        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        spec = dict(_fields(next((v for f, v in _fields(self.library.serialized_model_proto()) if f == 3), b"")))
        # The field numbers of a model's normaliser, and their defaults.
        self.map = CharacterMap(spec.get(2, b""))
        self.dummy_prefix, self.strip, self.escape = bool(spec.get(3, 1)), bool(spec.get(4, 1)), bool(spec.get(5, 1))
        proc = self.library
        self.lengths = np.array([1 if proc.is_byte(i) else 0 if proc.is_control(i) or proc.is_unknown(i) else len(proc.id_to_piece(i).encode()) for i in range(proc.get_piece_size())], np.int64)
        self.unknown = proc.unk_id()
        self.end_id = proc.eos_id()

    def align(self, text: bytes) -> Aligned:
        """The model's normalisation of a text, with its alignment."""
        if not self.map.units and not self.strip:
            return self._align_plain(text)
        out, source, at = bytearray(), [], 0
        while at < len(text):
            found = self.map.longest(text, at)
            if found is None:
                lead = text[at]
                length = 1 if lead < 0xC0 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
                new = text[at : at + length]
            else:
                length, new = found
            out += new
            # Bytes of an unchanged character keep their own places.
            source += range(at, at + length) if new == text[at : at + length] else [at] * len(new)
            at += length
        raw, where = bytes(out), np.array([*source, len(text)], np.int64)
        if self.strip:
            keep = np.frombuffer(raw, np.uint8) != 0x20
            follows = np.concatenate([[False], keep[:-1]]) if len(keep) else keep
            keep = keep | follows
            last = np.flatnonzero(np.frombuffer(raw, np.uint8) != 0x20)
            keep[(last[-1] + 1 if len(last) else 0) :] = False
            raw = np.frombuffer(raw, np.uint8)[keep].tobytes()
            where = np.concatenate([where[:-1][keep], [where[:-1][last[-1]] + 1 if len(last) else 0]])
        if not raw:
            return Aligned(b"", np.array([len(text)], np.int64))
        plain = self._align_plain(raw)
        return Aligned(plain.text, where[plain.source])

    def _align_plain(self, text: bytes) -> Aligned:
        """Spaces written as the space sign, and the dummy prefix."""
        if not text:
            return Aligned(b"", np.zeros(1, np.int64))
        raw = np.frombuffer(text, np.uint8)
        wide = np.where((raw == 0x20) & self.escape, len(_SPACE), 1)
        source = np.concatenate([np.repeat(np.arange(len(raw)), wide), [len(raw)]])
        new = text.replace(b" ", _SPACE) if self.escape else text
        if self.dummy_prefix:
            mark = _SPACE if self.escape else b" "
            return Aligned(mark + new, np.concatenate([np.zeros(len(mark), np.int64), source]))
        return Aligned(new, source)

    def encode(self, texts: list[str]) -> list[list[int]]:
        """Ids with the end id, as the library gives them."""
        return self.library.encode(texts, out_type=int, add_bos=False, add_eos=True, num_threads=1)

    def spans(self, text: str, ids: list[int]) -> np.ndarray:
        """For each id, the bytes [begin, end) of the text it stands for; an end id stands for none.

        Byte pieces stand for their byte alone.  Pieces of unknown characters are placed by the
        library, as their lengths are not in the vocabulary.
        """
        aligned = self.align(text.encode())
        sizes = self.lengths[np.asarray(ids, np.int64)] if ids else np.zeros(0, np.int64)
        if self.unknown in ids or sizes.sum() != len(aligned.text):
            return self._spans_by_library(text, ids)
        ends = np.cumsum(sizes)
        return np.stack([aligned.source[ends - sizes], aligned.source[ends]], 1)

    def _spans_by_library(self, text: str, ids: list[int]) -> np.ndarray:
        got = [(p.begin, p.end) for p in self.library.encode(text, return_type="proto").pieces]
        size = len(text.encode())
        got += [(size, size)] * (len(ids) - len(got))
        return np.array(got, np.int64).reshape(-1, 2)

    def decode(self, ids: list[list[int]]) -> list[str]:
        return self.library.decode(ids, num_threads=1)


_codecs: dict[str, PieceCodec] = {}


def codec(path: str) -> PieceCodec:
    if path not in _codecs:
        _codecs[path] = PieceCodec(path)
    return _codecs[path]


def _blocks(b: pa.RecordBatch, most: int = 1 << 20) -> Iterator[tuple[int, list[str]]]:
    """Consecutive rows of about ``most`` characters, with the first row's place."""
    first, texts, size = 0, [], 0
    for i in range(b.num_rows):
        t = b.column(1)[i].as_py() or ""
        if texts and size + len(t) > most:
            yield first, texts
            first, texts, size = i, [], 0
        texts.append(t)
        size += len(t)
    if texts:
        yield first, texts


def encode(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, ids, and begins and ends (byte spans in the text's UTF-8).

    A null text is an empty one: the end id alone.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(model)
        for b in batches:
            for first, texts in _blocks(b):
                ids = c.encode(texts)
                spans = [c.spans(t, i) for t, i in zip(texts, ids)]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(first, len(texts)), pa.array(ids, pa.list_(pa.int32())), pa.array([s[:, 0] for s in spans], pa.list_(pa.int64())), pa.array([s[:, 1] for s in spans], pa.list_(pa.int64()))],
                    ["id", "ids", "begins", "ends"],
                )

    return rows.mapInArrow(lean(run), f"id {kind}, ids array<int>, begins array<bigint>, ends array<bigint>").withColumnRenamed("id", id_col)


def digests(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, n_tokens, ids_sha256, decoded_sha256, n_covered, spans_sha256.

    The ids come from ``PieceCodec.encode`` and are decoded again; n_covered is the number of the
    text's bytes in the pieces' spans, spans_sha256 is of the spans as little-endian 8-byte pairs.
    A null text is an empty one.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = rows.schema["id"].dataType.simpleString()

    def sha(raw: bytes) -> str:
        return hashlib.sha256(raw).hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(model)
        words = list(map(str, range(c.library.get_piece_size())))
        for b in batches:
            for first, texts in _blocks(b):
                ids = c.encode(texts)
                spans = [c.spans(t, i) for t, i in zip(texts, ids)]
                columns = [
                    b.column(0).slice(first, len(texts)),
                    pa.array(map(len, ids), pa.int64()),
                    pa.array([sha(" ".join(map(words.__getitem__, i)).encode()) for i in ids], pa.string()),
                    pa.array([sha(t.encode()) for t in c.decode(ids)], pa.string()),
                    pa.array([int((s[:, 1] - s[:, 0]).sum()) for s in spans], pa.int64()),
                    pa.array([sha(s.astype("<i8").tobytes()) for s in spans], pa.string()),
                ]
                yield pa.RecordBatch.from_arrays(columns, ["id", "n_tokens", "ids_sha256", "decoded_sha256", "n_covered", "spans_sha256"])

    return rows.mapInArrow(lean(run), f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string, n_covered long, spans_sha256 string").withColumnRenamed("id", id_col)
