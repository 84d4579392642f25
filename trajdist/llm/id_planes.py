"""Token-id files in shuffled planes.

A file holds the ids of consecutive documents in blocks of a fixed number of ids.  Each block is
transposed, into one plane for each byte or each bit that its largest id needs, and each plane is
compressed by itself with zstandard.  An index at the file's end places every block and every
document, so any range of ids can be read without the rest.

Layout (little-endian): MAGIC; the blocks' planes; the index, compressed; its length (8 bytes); MAGIC.
The index is six 8-byte numbers (documents, blocks, ids, block size, planes are bits, flags), then
the documents' ids, null marks and token counts, then for each block its offset, ids and planes,
then the planes' lengths.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from typing import BinaryIO

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .pretokens import encoder
from .shared import filesystem, stored, write_file

MAGIC = b"IDPLANE1"
BLOCK = 1 << 16
LEVEL = 1


def to_planes(ids: np.ndarray, bits: bool) -> list[bytes]:
    """Planes of a block, lowest first; as many as its largest id needs, one at least."""
    top = int(ids.max()).bit_length() if len(ids) else 1
    if bits:
        return [np.packbits((ids >> np.uint32(k)).astype(np.uint8) & 1).tobytes() for k in range(max(1, top))]
    rows = np.ascontiguousarray(ids, "<u4").view(np.uint8).reshape(-1, 4)
    return [np.ascontiguousarray(rows[:, k]).tobytes() for k in range(max(1, (top + 7) // 8))]


def from_planes(planes: list[bytes], n: int, bits: bool) -> np.ndarray:
    out = np.zeros(n, np.uint32)
    for k, p in enumerate(planes):
        raw = np.frombuffer(p, np.uint8)
        part = np.unpackbits(raw, count=n) if bits else raw
        out |= part.astype(np.uint32) << np.uint32(k if bits else 8 * k)
    return out


class PlaneWriter:
    """Appends documents to a stream; memory follows the block and the number of documents."""

    def __init__(self, out: BinaryIO, block: int = BLOCK, bits: bool = False):
        self.out, self.block, self.bits = out, block, bits
        self.coder = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False)
        self.names: list[int] = []
        self.nulls: list[bool] = []
        self.counts: list[int] = []
        self.blocks: list[tuple[int, int, int]] = []
        self.lengths: list[int] = []
        self.waiting: list[np.ndarray] = []
        self.n_waiting = 0
        self.at = len(MAGIC)
        out.write(MAGIC)

    def add(self, name: int | None, ids: np.ndarray) -> None:
        self.names.append(0 if name is None else name)
        self.nulls.append(name is None)
        self.counts.append(len(ids))
        self.waiting.append(ids)
        self.n_waiting += len(ids)
        if self.n_waiting >= 4 * self.block:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.waiting).astype(np.uint32) if self.waiting else np.zeros(0, np.uint32)
        end = len(ids) if last else len(ids) - len(ids) % self.block
        for i in range(0, end, self.block):
            part = ids[i : min(i + self.block, end)]
            packed = [self.coder.compress(p) for p in to_planes(part, self.bits)]
            self.blocks.append((self.at, len(part), len(packed)))
            self.lengths += map(len, packed)
            for p in packed:
                self.out.write(p)
                self.at += len(p)
        self.waiting, self.n_waiting = [ids[end:]], len(ids) - end

    def close(self) -> None:
        self._flush(True)
        head = [len(self.names), len(self.blocks), sum(self.counts), self.block, int(self.bits), 0]
        parts = [head, self.names, self.nulls, self.counts, *zip(*self.blocks), self.lengths]
        index = self.coder.compress(b"".join(np.array(list(p), "<i8").tobytes() for p in parts))
        self.out.write(index + len(index).to_bytes(8, "little") + MAGIC)


class PlaneFile:
    """Reads a file of PlaneWriter through any seekable stream."""

    def __init__(self, stream, size: int):
        self.stream = stream
        stream.seek(0)
        head = stream.read(len(MAGIC))
        stream.seek(size - 16)
        tail = stream.read(16)
        if head != MAGIC or tail[8:] != MAGIC:
            raise ValueError("not a whole id file")
        length = int.from_bytes(tail[:8], "little")
        stream.seek(size - 16 - length)
        v = np.frombuffer(zstandard.ZstdDecompressor().decompress(stream.read(length)), "<i8")
        n_docs, n_blocks, self.n_ids, self.block, bits, _ = v[:6].tolist()
        self.bits = bool(bits)
        ends = np.cumsum([6, n_docs, n_docs, n_docs, n_blocks, n_blocks, n_blocks])
        self.names, self.nulls, self.counts, self.offsets, self.sizes, self.planes = (v[a:b] for a, b in zip(ends[:-1], ends[1:]))
        self.lengths = v[ends[-1] :]
        self.first_plane = np.concatenate([[0], np.cumsum(self.planes)])
        self.starts = np.concatenate([[0], np.cumsum(self.counts)])
        self.decoder = zstandard.ZstdDecompressor()

    def read_block(self, k: int) -> np.ndarray:
        lengths = self.lengths[self.first_plane[k] : self.first_plane[k + 1]].tolist()
        self.stream.seek(int(self.offsets[k]))
        raw, at, planes = self.stream.read(sum(lengths)), 0, []
        for n in lengths:
            planes.append(self.decoder.decompress(raw[at : at + n]))
            at += n
        return from_planes(planes, int(self.sizes[k]), self.bits)

    def read(self, start: int, stop: int) -> np.ndarray:
        """Ids start..stop of the file."""
        if stop <= start:
            return np.zeros(0, np.uint32)
        first = start // self.block
        got = np.concatenate([self.read_block(k) for k in range(first, (stop - 1) // self.block + 1)])
        return got[start - first * self.block : stop - first * self.block]

    def documents(self) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """Each document's name, start in the file and ids; blocks are read once, in order."""
        have, have_at, k = np.zeros(0, np.uint32), 0, 0
        for i in range(len(self.names)):
            start, stop = int(self.starts[i]), int(self.starts[i + 1])
            if have_at + len(have) < stop:
                parts = [have[start - have_at :]]
                have_at, total = start, len(parts[0])
                while have_at + total < stop:
                    parts.append(self.read_block(k))
                    total += len(parts[-1])
                    k += 1
                have = np.concatenate(parts)
            yield (None if self.nulls[i] else int(self.names[i])), start, have[start - have_at : stop - have_at]


def write_ids(docs: DataFrame, folder: str, vocabulary: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, bits: bool = False) -> DataFrame:
    """Encodes every whole text, appends ``end_id``, and writes files in ascending id order.

    Ids are split by range, so each file holds the documents between two ids, sorted; rows of the
    same id stand together, in the order of their texts.  Null ids come first.  Returns one row
    for each file: part, path, n_docs, n_tokens.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    ordered = rows.repartitionByRange("id").sortWithinPartitions("id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, writers = encoder(vocabulary), TaskContext.get().partitionId(), []
        end = np.array([end_id], np.uint32)

        def fill(out) -> None:
            writer = PlaneWriter(out, block, bits)
            writers.append(writer)
            for b in batches:
                names = b.column(0).to_pylist()
                for name, raw in zip(names, encode.packed(t.as_py() for t in b.column(1))):
                    writer.add(name, np.concatenate([np.frombuffer(raw, encode.dtype).astype(np.uint32), end]))
            writer.close()

        path = write_file(folder, f"ids-{part:07d}.planes", fill)
        w = writers[0]
        yield pa.RecordBatch.from_pydict({"part": [part], "path": [path], "n_docs": [len(w.names)], "n_tokens": [sum(w.counts)]}, pa.schema([("part", pa.int64()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

    return stored(ordered.mapInArrow(run, "part long, path string, n_docs long, n_tokens long"), f"{folder}/index")


def read_ids(spark: SparkSession, files: DataFrame) -> DataFrame:
    """Reads the files back: doc_id, start (ids of all documents before it), n_tokens, ids_crc32.

    The driver sees one small row for each file, to place it; documents and ids stay on executors.
    """
    begin, placed = 0, []
    for f in sorted(files.where("n_docs > 0").select("part", "path", "n_tokens").collect()):
        placed.append((f.path, begin))
        begin += f.n_tokens
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if not placed:
        return spark.createDataFrame([], schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, begin in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                store, name = filesystem(path)
                with store.open_input_file(name) as stream:
                    got = [(n, begin + at, len(ids), zlib.crc32(ids.astype("<u4").tobytes())) for n, at, ids in PlaneFile(stream, stream.size()).documents()]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*got)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    # One file for each task.
    return spark.createDataFrame(placed, "path string, begin long").repartition(len(placed)).mapInArrow(run, schema)
