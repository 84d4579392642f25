"""Quality rules on compression: how far zstandard shrinks a text tells repetition and noise.

A text, and each fixed chunk of it, has a ratio of compressed to raw bytes.  ``BANDS`` gives, for
a length, the lowest and the highest ratio of ordinary prose: below, the text repeats itself;
above, it is incompressible.  The verdict is against a text whose own ratio lies outside its band
or most of whose chunks lie outside theirs.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import lean
from .words import Words, grams, hash_words, mix, slices

# From so many bytes on, the lowest and highest ratio of compressed to raw bytes.
BANDS = ((0, 0.40, 4.0), (64, 0.36, 1.8), (128, 0.30, 1.05), (256, 0.28, 0.95), (512, 0.28, 0.86), (1024, 0.27, 0.80), (2048, 0.26, 0.76), (4096, 0.25, 0.72), (8192, 0.22, 0.70), (32768, 0.20, 0.68))
# The characters that count as symbols, and those between words.
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"

CHUNK = 2048
LEVEL = 3
MIN_WORDS = 20
WINDOW = 8
MAX_REPEAT_PERCENT = 30

FIELDS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, ratio double, n_chunks long, n_odd_chunks long, kept boolean"


class Bands(NamedTuple):
    """ratio of the whole text, number of chunks, how many lie outside their band, and the verdict."""

    ratio: float
    chunks: int
    odd: int
    passed: bool


_FROM = np.array([b[0] for b in BANDS])


def in_band(raw: int, packed: int) -> bool:
    _, low, high = BANDS[int(np.searchsorted(_FROM, raw, "right")) - 1]
    return low * raw <= packed <= high * raw


def bands(text: str | None, coder: zstandard.ZstdCompressor, chunk: int = CHUNK) -> Bands:
    """A null or empty text has ratio 0 and no chunks, and fails."""
    raw = (text or "").encode()
    if not raw:
        return Bands(0.0, 0, 0, False)
    packed = len(coder.compress(raw))
    if len(raw) <= chunk:
        good = in_band(len(raw), packed)
        return Bands(packed / len(raw), 1, int(not good), good)
    parts = [raw[i : i + chunk] for i in range(0, len(raw), chunk)]
    odd = sum(not in_band(len(p), len(coder.compress(p))) for p in parts)
    return Bands(packed / len(raw), len(parts), odd, in_band(len(raw), packed) and 2 * odd <= len(parts))


def repeated_words(words: Words, window: int = WINDOW) -> np.ndarray:
    """For each row, the words that lie in a window of words found twice or more in that row."""
    n = len(words.bounds) - 1
    g = grams(words, window)
    counts = np.diff(g.bounds)
    row = np.repeat(np.arange(n), counts)
    keys = g.hashes ^ mix(row.astype(np.uint64) + np.uint64(1 << 33))
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    twice = np.zeros(len(keys), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    at = (np.arange(len(keys)) - np.repeat(g.bounds[:-1], counts) + np.repeat(words.bounds[:-1], counts))[twice]
    cover = np.zeros(len(words.hashes) + 1, np.int64)
    np.add.at(cover, at, 1)
    np.add.at(cover, at + window, -1)
    covered = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
    return covered[words.bounds[1:]] - covered[words.bounds[:-1]]


def measure(texts: pa.Array) -> pa.StructArray:
    """All measures and the verdict of a column of texts (see FIELDS)."""
    coder = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False, write_content_size=False)
    words = hash_words(texts, lower=False)
    n_words, repeats = np.diff(words.bounds), repeated_words(words)
    failed = (n_words < MIN_WORDS) | (100 * repeats > MAX_REPEAT_PERCENT * n_words)
    chars, symbols, lines, found = [], [], [], []
    for t in texts:
        t = t.as_py() or ""
        chars.append(len(t) - sum(map(t.count, SPACES)))
        symbols.append(sum(map(t.count, SYMBOLS)))
        full = [x for x in t.split("\n") if x.strip(SPACES)]
        lines.append(len(full) - len(set(full)))
        found.append(bands(t, coder))
    kept = [b.passed and not f for b, f in zip(found, failed)]
    return pa.StructArray.from_arrays(
        [pa.array(n_words, pa.int64()), pa.array(chars, pa.int64()), pa.array(symbols, pa.int64()), pa.array(lines, pa.int64()), pa.array(repeats, pa.int64()), pa.array(failed),
         pa.array([b.ratio for b in found], pa.float64()), pa.array([b.chunks for b in found], pa.int64()), pa.array([b.odd for b in found], pa.int64()), pa.array(kept, pa.bool_())],
        [f.split()[0] for f in FIELDS.split(", ")],
    )


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id and FIELDS.

    A null text has no words: it fails as an empty one does.  Other columns of the input are not
    looked at, whatever their names.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in slices(b, 1):
                m = measure(part.column(1))
                yield pa.RecordBatch.from_arrays([part.column(0), *m.flatten()], ["id", *(f.name for f in m.type)])

    kind = rows.schema["id"].dataType.simpleString()
    return rows.mapInArrow(lean(run), f"id {kind}, {FIELDS}").withColumnRenamed("id", id_col)


def keep_good(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, that pass the base rules and the bands."""
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in slices(b, at):
                yield part.filter(measure(part.column(at)).field("kept"))

    return docs.mapInArrow(lean(run), docs.schema)
