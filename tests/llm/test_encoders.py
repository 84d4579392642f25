"""Token ids, counts, files and pieces against their libraries."""

from __future__ import annotations

import hashlib
import io
import zlib

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from trajdist.llm import id_planes, pieces, token_counts
from trajdist.llm.pretokens import encoder
from trajdist.llm.shared import shared_folder

BPE, PIECES = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("piece_bpe_32k.model")
TEXTS = ["", " ", "plain words, and more", "a<|endoftext|>b <|endoftext|>", "\r\n \t x  \n\n", "It's we'll I'VE 12 ½ x²", "日本語 и кириллица", "\x00\x1f\x7f   end", "😀😀 é è" * 9, "x" * 5000]
SCHEMA = "doc_id long, text string, n_tokens int, id string"
ROWS = [(5, "second row"), (None, "no id"), (3, None), (3, None), (9, ""), (1, "word " * 30_000), (5, "a second text of one id"), *((100 + i, t) for i, t in enumerate(TEXTS))]


def table(spark, rows):
    return spark.createDataFrame([(i, t, 7, "clash") for i, t in rows], SCHEMA)


@pytest.mark.parametrize("text", TEXTS)
def test_ids_as_the_library(text):
    e = encoder(BPE)
    want = e.library.encode(text, add_special_tokens=False).ids
    assert e.ids(text).tolist() == want and list(e.counts([text])) == [len(want)]


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=st.one_of(st.characters(max_codepoint=0x24F), st.characters(codec="utf-8"), st.sampled_from(" '\n\tst19")), max_size=60))
def test_any_text(text):
    e = encoder(BPE)
    want = e.library.encode(text, add_special_tokens=False).ids
    assert e.ids(text).tolist() == want and list(e.counts([text])) == [len(want)]


def test_other_vocabularies_go_whole():
    e = encoder(public_tokenizers.path("word_bpe_49k.json"))
    assert not e.splits
    assert e.ids("Some Words").tolist() == e.library.encode("Some Words", add_special_tokens=False).ids


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 2**32 - 1), max_size=50), max_size=12), st.booleans(), st.integers(1, 40))
def test_plane_files_round_trip(docs, bits, block):
    out = io.BytesIO()
    w = id_planes.PlaneWriter(out, block, bits)
    for i, d in enumerate(docs):
        w.add(None if i % 5 == 4 else i, np.array(d, np.uint32))
    w.close()
    f = id_planes.PlaneFile(io.BytesIO(out.getvalue()), len(out.getvalue()))
    got = list(f.documents())
    assert [g[2].tolist() for g in got] == docs and [g[0] for g in got] == [None if i % 5 == 4 else i for i in range(len(docs))]
    flat = [x for d in docs for x in d]
    for a, b in ((0, len(flat)), (len(flat) // 3, 2 * len(flat) // 3), (0, 0)):
        assert f.read(a, b).tolist() == flat[a:b]


def test_broken_file():
    with pytest.raises(ValueError):
        id_planes.PlaneFile(io.BytesIO(b"x" * 40), 40)


@pytest.mark.parametrize("bits", [False, True])
def test_written_and_read(spark, bits):
    folder = shared_folder(spark, "ids")
    files = id_planes.write_ids(table(spark, ROWS), folder, BPE, 2, block=100, bits=bits)
    got = id_planes.read_ids(spark, files).orderBy("start").collect()
    e, start = encoder(BPE), 0
    for r, (name, text) in zip(got, sorted(ROWS, key=lambda x: (x[0] is not None, x[0] or 0, x[1] is not None, x[1] or "")), strict=True):
        ids = [*e.ids(text).tolist(), 2]
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (name, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)


def test_no_documents(spark):
    none = table(spark, [])
    assert id_planes.read_ids(spark, id_planes.write_ids(none, shared_folder(spark, "ids"), BPE, 2)).count() == 0
    assert token_counts.count_tokens(none, BPE).count() == 0 and pieces.digests(none, PIECES).count() == 0


@pytest.mark.parametrize("path", [BPE, PIECES])
def test_counts(spark, path):
    got = token_counts.count_tokens(table(spark, ROWS), path).collect()
    c = pieces.codec(PIECES)
    count = (lambda t: len(c.library.encode(t))) if path == PIECES else (lambda t: len(encoder(BPE).library.encode(t, add_special_tokens=False).ids))
    want = sorted((str(i), len((t or "").encode()), count(t or "")) for i, t in ROWS)
    assert sorted((str(r.doc_id), r.n_bytes, r.n_tokens) for r in got) == want


def test_pieces_as_the_library(spark):
    lib = pieces.codec(PIECES).library
    got = pieces.digests(table(spark, ROWS), PIECES).collect()
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = []
    for i, t in ROWS:
        ids = lib.encode(t or "", add_eos=True)
        want.append((str(i), len(ids), sha(" ".join(map(str, ids))), sha(lib.decode(ids)), len((t or "").encode())))
    assert sorted((str(r.doc_id), r.n_tokens, r.ids_sha256, r.decoded_sha256, r.n_covered) for r in got) == sorted(want)


def test_spans_cover_the_text(spark):
    c = pieces.codec(PIECES)
    for text in TEXTS:
        (ids,) = c.encode([text])
        spans, raw = c.spans(text, ids), text.encode()
        assert b"".join(raw[a:b] for a, b in spans) == raw
        for i, (a, b) in zip(ids, spans):
            if not (c.library.is_byte(i) or c.library.is_control(i)):
                assert c.library.id_to_piece(i).replace("▁", " ").strip() == raw[a:b].decode().strip()
    row = pieces.encode(table(spark, [(1, "one two")]), PIECES).first()
    assert row.ends[-1] == 7 and len(row.ids) == len(row.begins) == len(row.ends)


def test_character_map():
    # A map of one rule, laid out by hand: "A" becomes "ab".
    units = [0] * 128
    units[0] = 1 << 10
    units[0x40] = 0x41 | 1 << 8 | 2 << 10
    units[0x42] = 1 << 31
    blob = np.array(units, "<u4").tobytes()
    m = pieces.CharacterMap(len(blob).to_bytes(4, "little") + blob + b"ab\x00")
    assert m.longest(b"xA", 1) == (1, b"ab") and m.longest(b"xA", 0) is None
    c = pieces.codec(PIECES)
    keep = c.map
    try:
        c.map = m
        got = c.align("é A".encode())
        assert got.text == "▁é▁ab".encode() and got.source.tolist() == [0, 0, 0, 0, 1, 2, 2, 2, 3, 3, 4]
    finally:
        c.map = keep
