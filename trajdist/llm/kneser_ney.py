"""Interpolated modified Kneser-Ney n-gram model: counted in Spark, kept as sorted hash arrays that
workers map into memory.

Vocabulary.  A first job counts words and numbers them: in each shard of the hash range by frequency, so
that frequent words have small numbers.  n-grams are tuples of these numbers.

Counting.  Each task turns its texts into n-grams, adds equal ones, and sends one packed block to
each shard of the hash range.  A shard merges its blocks as they come, writes the array of
its n-grams with their counts, and sends on two things in the same packed form: what its n-grams
add to their contexts (total, and how many followers were seen once, twice, more often), and what
they add to the continuation counts of the (n-1)-grams that end them.  Both are facts about n-grams of the
next lower order, and stand in one row there.  n-grams are dealt by the hash of all their words, so a
frequent word or word pair loads no shard; the number of shards follows the bytes of text, so that a shard
stays as large as it is, whatever the corpus.

Arrays.  n-grams of a shard are dealt by a 64-bit hash.  A directory by the upper bits tells where each
bucket of about four begins, and the lower 32 bits, in order inside a bucket, tell them apart: an n-gram that is
not there is taken for another with a chance of 1e-9, and a search for it ends at the first larger one.  Words are compared by all 64 bits.

Scoring.  A worker maps the arrays of all shards and looks up the sorted keys of a batch of texts.
Pages are shared by the workers of a machine and read as needed.  The folder of the model has to be
one that workers can open as files; from other stores the arrays are read into memory.

Words are lower-cased (A-Z) runs between white space; each text ends with one end token.  A null
text is an empty one: the end token alone.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import filesystem, lean, shared_folder, write_file
from .words import Words, hash_words, mix, mix_int, slices

ORDER = 3
#: Tokens that a task gathers before it sends their n-grams on.
GATHER = 1_500_000
#: Bytes of text that are scored together.
BATCH = 4 << 20
#: Bytes of text for each shard of the arrays, and the fewest shards.
SHARD_BYTES, SHARDS = 8 << 20, 8
#: Rows that a merge holds beside what it has merged.
HELD = 1 << 18
#: n-grams of a bucket, on average.
BUCKET = 4
#: Counts from here on stand beside an array's bytes.
LARGE = 255

BEGIN, END = mix_int(0xBE61), mix_int(0xE4D)
#: Number of the begin mark; words are numbered from 1.  UNKNOWN is no word's number.
BEGIN_ID, UNKNOWN = 0, (1 << 64) - 1
_P = np.uint64(0x9E3779B97F4A7C15)
#: Kinds of rows: n-grams by their number of words, the vocabulary, and a finished shard's statistics.
WORDS, STATS = 0, 200


def gram_key(columns: list[np.ndarray]) -> np.ndarray:
    h = np.full(len(columns[0]), len(columns), np.uint64)
    for w in columns:
        h = mix(h * _P + w.astype(np.uint64))
    return h


def _place(key: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray]:
    """Equal ranges of the hashes, so shards in order are sorted as a whole; and 32 bits for the place inside."""
    at = (key >> np.uint64(32)) * np.uint64(shards)
    return (at >> np.uint64(32)).astype(np.int64), at & np.uint64(0xFFFFFFFF)


_pack = zstandard.ZstdCompressor(level=3)
_unpack = zstandard.ZstdDecompressor()


class Grams(NamedTuple):
    """Different rows in the order of their columns, with values.

    Values of n-grams below the model's order: the count, then total, ones, twos and more of the context that they are."""

    columns: list[np.ndarray]
    values: list[np.ndarray]


def pack(g: Grams) -> bytes:
    """Byte planes, compressed; the first column by its differences."""
    out = [np.array([len(g.columns), len(g.values), len(g.columns[0])], "<u8").tobytes()]
    for i, c in enumerate([*g.columns, *g.values]):
        c = c.astype("<u8")
        c = np.diff(c, prepend=np.uint64(0)) if i == 0 else c
        width = max(1, (int(c.max(initial=0)).bit_length() + 7) // 8)
        z = _pack.compress(np.ascontiguousarray(c.view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes())
        out += [np.array([width, len(z)], "<u8").tobytes(), z]
    return b"".join(out)


def _narrow(c: np.ndarray) -> np.ndarray:
    return c.astype(np.uint32) if int(c.max(initial=0)) < 1 << 32 else c


def unpack(blob: bytes) -> Grams:
    names, values, rows = np.frombuffer(blob, "<u8", 3).tolist()
    at, out = 24, []
    for i in range(names + values):
        width, size = np.frombuffer(blob, "<u8", 2, at).tolist()
        planes = np.frombuffer(_unpack.decompress(blob[at + 16 : at + 16 + size], max_output_size=width * rows), np.uint8)
        c = np.zeros((rows, 8), np.uint8)
        c[:, :width] = planes.reshape(width, rows).T
        c = c.view("<u8").reshape(-1)
        out.append(_narrow(np.cumsum(c, dtype=np.uint64) if i == 0 else c))
        at += 16 + size
    return Grams(out[:names], out[names:])


def _added(columns: list[np.ndarray], values: list[np.ndarray] | None) -> Grams:
    """Equal rows added up, in order; without values, how many they are."""
    n, keys, room, widths = len(columns[0]), [], 0, []
    for c in columns:
        bits = max(1, int(c.max(initial=0)).bit_length())
        if bits > room:
            keys.append(np.zeros(n, np.uint64))
            widths.append([])
            room = 64
        if widths[-1]:
            keys[-1] <<= np.uint64(bits)
        keys[-1] |= c.astype(np.uint64)
        widths[-1].append(bits)
        room -= bits
    if values is None and len(keys) == 1:
        order = None
        keys[0].sort()
    else:
        order = np.argsort(keys[0], kind="stable") if len(keys) == 1 else np.lexsort(keys[::-1])
        for i, key in enumerate(keys):
            keys[i] = key[order]
    fresh = np.ones(n, bool)
    fresh[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    at, names = np.flatnonzero(fresh), []
    for key, bits in zip(keys, widths):
        key, part = key[at], []
        for b in reversed(bits):
            part.append(_narrow(key & np.uint64((1 << b) - 1)))
            key = key >> np.uint64(b) if b < 64 else key
        names += part[::-1]
    if values is None:
        return Grams(names, [np.diff(at, append=n).astype(np.uint64)])
    return Grams(names, [_narrow(np.add.reduceat(v[order], at, dtype=np.uint64)) if n else v[:0] for v in values])


def _joined(parts: list[Grams]) -> Grams:
    if len(parts) == 1:
        return parts[0]
    return _added([np.concatenate(c) for c in zip(*(p.columns for p in parts))], [np.concatenate(v) for v in zip(*(p.values for p in parts))])


def _blocks(kind: int, g: Grams, keys: np.ndarray, shards: int) -> Iterator[tuple[int, int, bytes]]:
    """Rows split by shard; each block stays in order."""
    shard = _place(keys, shards)[0]
    order = np.argsort(shard, kind="stable")
    cuts = np.searchsorted(shard[order], np.arange(shards + 1))
    for s in range(shards):
        rows = order[cuts[s] : cuts[s + 1]]
        if len(rows):
            yield kind, s, pack(Grams([c[rows] for c in g.columns], [v[rows] for v in g.values]))


class Sequence(NamedTuple):
    """Tokens of all texts with a begin mark before each, which rows they belong to, and their places."""

    tokens: np.ndarray
    row: np.ndarray
    place: np.ndarray


def sequence(words: Words) -> Sequence:
    sizes = np.diff(words.bounds) + 2
    ends = np.cumsum(sizes)
    begins = ends - sizes
    tokens = np.empty(int(sizes.sum()), np.uint64)
    inner = np.ones(len(tokens), bool)
    inner[begins] = inner[ends - 1] = False
    tokens[begins], tokens[ends - 1], tokens[inner] = BEGIN, END, words.hashes
    row = np.repeat(np.arange(len(sizes)), sizes)
    return Sequence(tokens, row, np.arange(len(tokens)) - begins[row])


def _gathered(send):
    """Sends what a task gathers, some millions of tokens at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            for part in slices(b, 0):
                s = sequence(hash_words(part.column(0)))
                held.append(s)
                size += len(s.tokens)
                if size >= GATHER:
                    yield _rows(send(held))
                    held, size = [], 0
        if held:
            yield _rows(send(held))

    return lean(run)


def _send_words(shards: int):
    def send(parts: list[Sequence]) -> Iterator[tuple[int, int, bytes]]:
        g = _added([np.concatenate([p.tokens[p.place > 0] for p in parts])], None)
        yield from _blocks(WORDS, g, g.columns[0], shards)

    return send


def _with_context(g: Grams) -> Grams:
    """Counts as rows of an order below the model's: nothing about contexts yet."""
    return Grams(g.columns, [*g.values, *(np.zeros(len(g.columns[0]), np.uint8) for _ in range(4))])


def _send_grams(order: int, folder: str, shards: int):
    def send(parts: list[Sequence]) -> Iterator[tuple[int, int, bytes]]:
        place = np.concatenate([p.place for p in parts])
        words, local = np.unique(np.concatenate([p.tokens for p in parts]), return_inverse=True)
        number = vocabulary(folder, shards).find(words)[1]
        # Local numbers in the order of the words' own, so that n-grams are sorted as small numbers and stay in order.
        by_number = np.argsort(number)
        number, back = number[by_number], np.empty(len(words), np.uint64)
        back[by_number] = np.arange(len(words))
        local = back[local]
        for k in range(order, 0, -1):
            # Lower orders get their counts from above, but for those that begin a text.
            last = np.flatnonzero(place >= k - 1 if k == order else (place == k - 1) & (place > 0))
            if len(last):
                g = _added([local[last - k + 1 + i] for i in range(k)], None)
                g = Grams([number[c] for c in g.columns], g.values)
                yield from _blocks(k, g if k == order else _with_context(g), gram_key(g.columns), shards)

    return send


_SCHEMA = "kind int, shard int, block binary"


def _rows(blocks: Iterable[tuple[int, int, bytes]]) -> pa.RecordBatch:
    got = list(blocks)
    return pa.RecordBatch.from_arrays([pa.array([g[0] for g in got], pa.int32()), pa.array([g[1] for g in got], pa.int32()), pa.array([g[2] for g in got], pa.binary())], ["kind", "shard", "block"])


def _padded(a: np.ndarray) -> bytes:
    raw = a.tobytes()
    return raw + bytes(-len(raw) % 8)


def _byte_column(v: np.ndarray) -> bytes:
    """A byte for each value; the places and values of large ones before them."""
    large = np.flatnonzero(v >= LARGE)
    return np.array([len(large)], "<u8").tobytes() + large.astype("<u8").tobytes() + v[large].astype("<u8").tobytes() + _padded(np.minimum(v, LARGE).astype(np.uint8))


class _Reader:
    def __init__(self, raw: np.ndarray):
        self.raw, self.at = raw, 0

    def take(self, n: int, kind: str) -> np.ndarray:
        size = n * int(kind[2])
        out = self.raw[self.at : self.at + size].view(kind)
        self.at += size + -size % 8
        return out

    def byte_column(self, n: int):
        m = int(self.take(1, "<u8")[0])
        places, values, small = self.take(m, "<u8"), self.take(m, "<u8"), self.take(n, "<u1")

        def get(at: np.ndarray) -> np.ndarray:
            found = small[at].astype(np.uint64)
            large = np.flatnonzero(found == LARGE)
            found[large] = values[np.searchsorted(places, at[large])]
            return found

        return get


def _write_words(folder: str, shard: int, shards: int, g: Grams) -> None:
    """Sorted hashes, counts, and numbers: the most frequent word of each shard first."""
    hashes, count = g.columns[0], g.values[0]
    number = np.empty(len(hashes), np.uint64)
    number[np.lexsort((hashes, -count.astype(np.int64)))] = np.arange(len(hashes), dtype=np.uint64) * np.uint64(shards) + np.uint64(1 + shard)
    write_file(folder, f"{WORDS}-{shard}.arrays", lambda out: out.write(np.array([len(hashes)], "<u8").tobytes() + hashes.astype("<u8").tobytes() + number.astype("<u8").tobytes() + _byte_column(count)))


def _write_grams(folder: str, kind: int, shard: int, shards: int, keys: np.ndarray, values: list[np.ndarray]) -> None:
    """Where buckets begin, the keys' lower 32 bits, counts, and what is known of them as contexts.

    Most contexts have one of few sets of numbers: a byte tells which, and those of other sets stand beside."""
    buckets = max(1, len(keys) // BUCKET)
    bucket = _place(keys, shards)[1] * np.uint64(buckets) >> np.uint64(32)
    order = np.argsort(bucket << np.uint64(32) | keys & np.uint64(0xFFFFFFFF))
    keys, bucket, values = keys[order], bucket[order], [v[order] for v in values]
    begins = np.searchsorted(bucket, np.arange(buckets + 1, dtype=np.uint64))
    out = [np.array([len(keys), buckets, len(values)], "<u8").tobytes(), _padded(begins.astype("<u4")), _padded((keys & np.uint64(0xFFFFFFFF)).astype("<u4")), _byte_column(values[0])]
    if len(values) > 1:
        rows = np.stack([v.astype(np.uint64) for v in values[1:]], 1)
        fits = (rows < 1 << 16).all(1)
        short = rows[:, 0] << np.uint64(48) | rows[:, 1] << np.uint64(32) | rows[:, 2] << np.uint64(16) | rows[:, 3]
        found, counts = np.unique(short[fits], return_counts=True)
        common = np.sort(found[np.argsort(-counts, kind="stable")[: LARGE - 1]])
        code = np.searchsorted(common, short)
        code[code == len(common)] = 0
        code = np.where(fits & (common[code] == short if len(common) else False), code, LARGE)
        rare = np.flatnonzero(code == LARGE)
        out += [np.array([len(common), len(rare)], "<u8").tobytes(), common.astype("<u8").tobytes(), rare.astype("<u8").tobytes(), np.ascontiguousarray(rows[rare].T).astype("<u8").tobytes(), _padded(code.astype(np.uint8))]
    write_file(folder, f"{kind}-{shard}.arrays", lambda stream: stream.write(b"".join(out)))


def _merge(folder: str, shards: int, k: int, order: int):
    """Merges the blocks of each shard that are due when n-grams of k words are (0: the vocabulary), writes their arrays, and
    sends on what the next lower order needs.  What is not due yet, and what is finished, passes."""

    def stats(kind: int, *numbers: int) -> tuple[int, int, bytes]:
        return STATS, kind, pack(Grams([np.arange(len(numbers), dtype=np.uint64)], [np.array(numbers, np.uint64)]))

    def finish(shard: int, g: Grams) -> Iterator[tuple[int, int, bytes]]:
        if k == WORDS:
            _write_words(folder, shard, shards, g)
            yield stats(k, len(g.columns[0]), int(g.values[0].sum()))
            return
        _write_grams(folder, k, shard, shards, gram_key(g.columns), g.values)
        count = g.values[0]
        yield stats(k, int((count > 0).sum()), int(count.sum()), *(int((count == i).sum()) for i in range(1, 5)))
        if k > 1:
            seen = np.flatnonzero(count > 0)
            columns, count = [c[seen] for c in g.columns], count[seen]
            # Rows stand in order, so those of a context stand together.
            fresh = np.ones(len(count), bool)
            fresh[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns[:-1]])
            at = np.flatnonzero(fresh)
            facts = [_narrow(np.add.reduceat(v, at, dtype=np.uint64)) if len(at) else count for v in (count, count == 1, count == 2, count > 2)]
            context = Grams([c[at] for c in columns[:-1]], [np.zeros(len(at), np.uint8), *facts])
            ending = _with_context(_added(columns[1:], None))
            del g, columns, fresh, at, seen, facts
            both = _joined([context, ending])
            del context, ending
            yield from _blocks(k - 1, both, gram_key(both.columns), shards)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for b in batches:
            for kind, shard, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if kind != k:
                    yield _rows([(kind, shard, blob.as_py())])
                    continue
                if shard != now:
                    if held:
                        yield _rows(finish(now, _joined(held)))
                    now, held = shard, []
                held.append(unpack(blob.as_py()))
                if len(held) > 1 and sum(len(g.columns[0]) for g in held[1:]) > max(HELD, len(held[0].columns[0]) // 2):
                    held = [_joined(held)]
        if held:
            yield _rows(finish(now, _joined(held)))

    return lean(run)


def discounts(counts: list[int]) -> tuple[float, float, float]:
    """For n-grams seen once, twice, more often, from how many were seen one to four times.

    Where the estimate is undefined, halves of the count."""
    n1, n2, n3, n4 = counts
    if min(n1, n2, n3, n4) == 0:
        return 0.5, 1.0, 1.5
    y = n1 / (n1 + 2 * n2)
    found = (1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3)
    return tuple(min(max(d, 0.0), float(i)) for i, d in enumerate(found, 1))


def train(docs: DataFrame, folder: str, text_col: str = "text", order: int = ORDER, shards: int | None = None) -> dict:
    """Writes the model of the texts below ``folder``; returns its description, which scoring needs.

    ``shards`` is the number of parts of each array, by default one for SHARD_BYTES of text.  Orders follow each other in
    one job: each merge sends straight to the next, and nothing but the arrays is written.  Arrays are written whole and
    moved into place, so a task that runs again leaves the same."""
    if order < 2:
        raise ValueError("order is at least 2")
    folder = f"{folder}/arrays"
    texts = docs.select(F.col(text_col).alias("text"))
    if shards is None:
        size = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        shards = max(SHARDS, -(-size // SHARD_BYTES))
    stats: dict[int, list[int]] = {}

    def merged(rows: DataFrame, k: int) -> DataFrame:
        dealt = rows.repartitionById(shards, F.pmod("shard", F.lit(shards))).sortWithinPartitions("kind", "shard")
        return dealt.mapInArrow(_merge(folder, shards, k, order), _SCHEMA)

    def collect(rows: DataFrame) -> None:
        # A few numbers for each array.
        for r in rows.where(F.col("kind") == STATS).collect():
            got = [int(x) for x in unpack(bytes(r.block)).values[0]]
            stats[r.shard] = [a + b for a, b in zip(stats.get(r.shard, [0] * len(got)), got)]

    collect(merged(texts.mapInArrow(_gathered(_send_words(shards)), _SCHEMA), WORDS))
    rows = texts.mapInArrow(_gathered(_send_grams(order, folder, shards)), _SCHEMA)
    for k in range(order, 0, -1):
        rows = merged(rows, k)
    collect(rows)
    words = stats.pop(WORDS, [0, 0])
    grams = {str(k): {"total": s[1], "types": s[0], "counts": s[2:]} for k, s in stats.items()}
    return {"folder": folder, "order": order, "shards": shards, "types": words[0], "tokens": words[1], "grams": grams}


class Arrays:
    """The arrays of one kind, of all shards."""

    def __init__(self, folder: str, kind: int, shards: int):
        self.shards, self.parts = shards, []
        store, path = filesystem(folder)
        local = store.type_name == "local"
        for s in range(shards):
            name = f"{path}/{kind}-{s}.arrays"
            try:
                raw = np.memmap(name, np.uint8, "r") if local else np.frombuffer(store.open_input_file(name).read(), np.uint8)
            except FileNotFoundError:
                self.parts.append(None)
                continue
            self.parts.append(self.part(_Reader(raw)))

    def find(self, keys: np.ndarray) -> list[np.ndarray]:
        """The value columns at the keys; of those that are not there, ``missing``."""
        asked, back = np.unique(keys, return_inverse=True)
        out = [np.full(len(asked), m, np.uint64) for m in self.missing]
        shard, inside = _place(asked, self.shards)
        cuts = np.searchsorted(shard, np.arange(self.shards + 1))
        for s, part in enumerate(self.parts):
            a, z = cuts[s], cuts[s + 1]
            if part is None or a == z:
                continue
            rows, at = self.look(part, asked[a:z], inside[a:z])
            for o, get in zip(out, part[-1]):
                o[a + rows] = get(at)
        return [o[back] for o in out]


class Vocabulary(Arrays):
    """Counts and numbers of words."""

    missing = (0, UNKNOWN)

    def __init__(self, folder: str, shards: int):
        super().__init__(folder, WORDS, shards)

    @staticmethod
    def part(r: _Reader) -> tuple:
        n = int(r.take(1, "<u8")[0])
        hashes, number = r.take(n, "<u8"), r.take(n, "<u8")
        return hashes, [r.byte_column(n), lambda at: number[at]]

    @staticmethod
    def look(part: tuple, asked: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(part[0], asked)
        at[at == len(part[0])] = 0
        rows = np.flatnonzero(part[0][at] == asked)
        return rows, at[rows]

    def find(self, keys: np.ndarray) -> list[np.ndarray]:
        count, number = super().find(keys)
        number[keys == np.uint64(BEGIN)] = BEGIN_ID
        return [count, number]


class GramArrays(Arrays):
    """Counts of n-grams; and, where they are contexts, total, ones, twos and more."""

    missing = (0, 0, 0, 0, 0)

    @staticmethod
    def part(r: _Reader) -> tuple:
        n, buckets, columns = r.take(3, "<u8").tolist()
        begins, low = r.take(buckets + 1, "<u4"), r.take(n, "<u4")
        get = [r.byte_column(n)]
        if columns > 1:
            m, extra = r.take(2, "<u8").tolist()
            common, places, values, code = r.take(m, "<u8"), r.take(extra, "<u8"), r.take(4 * extra, "<u8").reshape(4, extra), r.take(n, "<u1")

            def fact(i: int):
                table = np.append(common >> np.uint64(16 * (3 - i)) & np.uint64(0xFFFF), np.zeros(LARGE + 1 - m, np.uint64))

                def value(at: np.ndarray) -> np.ndarray:
                    which = code[at]
                    found = table[which]
                    rare = np.flatnonzero(which == LARGE)
                    found[rare] = values[i][np.searchsorted(places, at[rare])]
                    return found

                return value

            get += [fact(i) for i in range(4)]
        return begins, low, buckets, get

    @staticmethod
    def look(part: tuple, asked: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        begins, low, buckets, _ = part
        bucket = inside * np.uint64(buckets) >> np.uint64(32)
        at, end = begins[bucket].astype(np.int64), begins[bucket + np.uint64(1)].astype(np.int64)
        want = (asked & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        rows, found_rows, found_at = np.flatnonzero(at < end), [], []
        at, end, want = at[rows], end[rows], want[rows]
        while len(rows):  # as often as the fullest bucket has rows
            here = low[at]
            hit = here == want
            found_rows.append(rows[hit])
            found_at.append(at[hit])
            on = np.flatnonzero((here < want) & (at + 1 < end))
            rows, at, end, want = rows[on], at[on] + 1, end[on], want[on]
        none = np.zeros(0, np.int64)
        return np.concatenate([none, *found_rows]), np.concatenate([none, *found_at])


_vocabularies: dict[str, Vocabulary] = {}


def vocabulary(folder: str, shards: int) -> Vocabulary:
    if folder not in _vocabularies:
        _vocabularies.clear()
        _vocabularies[folder] = Vocabulary(folder, shards)
    return _vocabularies[folder]


class Scorer:
    """log10 probabilities of texts under a model, in a worker."""

    def __init__(self, model: dict):
        self.model, n = model, model["order"]
        self.words = Vocabulary(model["folder"], model["shards"])
        self.grams = {k: GramArrays(model["folder"], k, model["shards"]) for k in range(1, n + 1)}
        empty = {"total": 0, "types": 0, "counts": [0] * 4}
        self.stats = {k: model["grams"].get(str(k), empty) for k in range(1, n + 1)}
        self.discounts = {k: np.array([0.0, *discounts(s["counts"])]) for k, s in self.stats.items()}

    def _shares(self, k: int, count: np.ndarray) -> np.ndarray:
        return np.maximum(count - self.discounts[k][np.minimum(count, 3).astype(np.int64)], 0)

    def probabilities(self, s: Sequence, number: np.ndarray) -> np.ndarray:
        """Of each token but the begin marks, in order.

        The row of an n-gram tells its own count, and what follows it: it is looked up once for both."""
        p, place = np.full(len(number), 1 / (self.model["types"] + 1)), s.place
        before: list[np.ndarray] = []
        for k in range(1, self.model["order"] + 1):
            where = np.flatnonzero(place >= k - 1)
            found = self.grams[k].find(gram_key([number[where - k + 1 + i] for i in range(k)]))
            count, *facts = [f.astype(np.float64) for f in found]
            d, after = self.discounts[k], [np.zeros(len(number)) for _ in facts]
            for a, f in zip(after, facts):
                a[where] = f
            if k == 1:
                one = self.stats[1]
                if one["total"]:
                    ones, twos = one["counts"][:2]
                    more = one["types"] - ones - twos
                    p[where] = self._shares(1, count) / one["total"] + (d[1] * ones + d[2] * twos + d[3] * more) / one["total"] * p[where]
            else:
                total, ones, twos, more = (b[where - 1] for b in before)
                seen = np.flatnonzero(total > 0)
                at, t = where[seen], total[seen]
                p[at] = self._shares(k, count[seen]) / t + (d[1] * ones[seen] + d[2] * twos[seen] + d[3] * more[seen]) / t * p[at]
            before = after
        return p[place > 0]

    def measure(self, texts: pa.Array) -> dict[str, np.ndarray]:
        """n_tokens, n_known, base_score and score of each text."""
        s = sequence(hash_words(texts))
        count, number = self.words.find(s.tokens)
        token = s.place > 0
        count, row = count[token].astype(np.float64), s.row[token]
        n, v = self.model["tokens"], self.model["types"]
        add = lambda x: np.bincount(row, x, len(texts))
        return {
            "n_tokens": np.bincount(row, minlength=len(texts)),
            "n_known": add(count > 0).astype(np.int64),
            "base_score": add(np.log10((count + 0.5) / (n + 0.5 * (v + 1)))),
            "score": add(np.log10(self.probabilities(s, number))),
        }


_scorers: dict[str, Scorer] = {}


def scorer(description: str) -> Scorer:
    if description not in _scorers:
        _scorers.clear()
        _scorers[description] = Scorer(json.loads(description))
    return _scorers[description]


def score(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, n_tokens, n_known, base_score, score, perplexity."""
    description = json.dumps(model)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = scorer(description)
        for b in batches:
            for part in slices(b, 1, BATCH):
                m = s.measure(part.column(1))
                perplexity = 10 ** np.minimum(-m["score"] / m["n_tokens"], 300)
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(x) for x in m.values()), pa.array(perplexity)], ["id", *m, "perplexity"])

    return rows.mapInArrow(run, f"id {kind}, n_tokens long, n_known long, base_score double, score double, perplexity double").withColumnRenamed("id", id_col)


def held_out_scores(docs: DataFrame, training: Column, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER) -> tuple[DataFrame, dict]:
    """Learns from the training rows, scores all rows."""
    model = train(docs.where(training), shared_folder(docs.sparkSession, "lm"), text_col, order)
    return score(docs, model, id_col, text_col), model
