"""Canonical digests of licences."""

from __future__ import annotations

import os

import pytest

from trajdist.llm import license_scan

COMMON = "/usr/share/common-licenses"


def rows_of(spark, rows):
    return spark.createDataFrame([(i, t, "clash", "clash") for i, t in rows], "doc_id long, text string, license string, digest string")


def test_known_texts(spark):
    mit = license_scan.KNOWN["MIT"]
    british = mit.replace("sublicense", "sub-licence").replace("without limitation", "without   limitation").replace('"AS IS"', "“as is”")
    rows = [
        (1, mit), (2, f"MIT License\n\nCopyright (c) 2020 Some One <a@b.c>\n© 2019 Other\n\n{british.upper().replace('“AS IS”', '“AS IS”')}\n"), (3, "# " + mit.replace("\n", "\n# ")), (4, mit + " More."), (5, None), (6, ""), (7, "Copyright 2020 Only"),
        (1, mit), (None, license_scan.KNOWN["Zlib"].replace("acknowledgment", "acknowledgement")), (8, "word " * 100_000), (9, license_scan.KNOWN["BSD-3-Clause"]),
        (10, "Some text\nReleased under the MIT licence\nmore\n Licensed under CC BY-NC 4.0.\nlicensed under nothing"),
    ]
    got = sorted((str(r.doc_id), r.license, r.n_canonical_words, r.notices) for r in license_scan.scan(rows_of(spark, rows), license_scan.known_licenses(spark)).collect())
    names = {(i, l) for i, l, _, _ in got}
    assert names == {("1", "MIT"), ("2", "MIT"), ("3", "MIT"), ("4", None), ("5", None), ("6", None), ("7", None), ("None", "Zlib"), ("8", None), ("9", "BSD-3-Clause"), ("10", None)}
    assert len(got) == len(rows) and {n for i, _, n, _ in got if i in "567"} == {0} and [n for i, _, n, _ in got if i == "8"] == [100_000]
    assert [x for i, _, _, x in got if i == "10"] == [["CC-BY-NC-4.0", "MIT"]]


def test_spellings(spark):
    pairs = [("the organisation's colour", "The ORGANIZATION S color"), ("sub licensed licence", "sublicensed license"), ("whilst per cent https", "while percent http"), ("copyright owners", "Copyright holders"), ("fulfilment", "fulfillment"), ("a  -- b", "a b")]
    for a, b in pairs:
        x, y = (spark.createDataFrame([(t,)], "text string").select(license_scan.canonical(license_scan.F.col("text")).alias("c")).first().c for t in (a, b))
        assert x == y, (x, y)


def test_own_table_and_nothing(spark):
    known = license_scan.known_licenses(spark, {"b": "Some Terms", "a": "some, terms!", "empty": ""})
    got = {r.doc_id: r.license for r in license_scan.scan(rows_of(spark, [(1, "SOME TERMS"), (2, "")]), known).collect()}
    assert got == {1: "a", 2: None}
    assert license_scan.scan(rows_of(spark, []), known).count() == 0
    assert license_scan.scan(rows_of(spark, [(1, "x")]), license_scan.known_licenses(spark, {})).first().license is None


@pytest.mark.skipif(not os.path.isdir(COMMON), reason="licence texts are not installed")
def test_longer_licences(spark):
    files = {"Apache-2.0": "Apache-2.0", "GPL-2.0": "GPL-2", "GPL-3.0": "GPL-3", "LGPL-2.1": "LGPL-2.1", "LGPL-3.0": "LGPL-3", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0"}
    rows, want = [], {}
    for i, (name, file) in enumerate(files.items()):
        with open(f"{COMMON}/{file}", encoding="utf-8") as f:
            text = f.read()
        short = text.split("END OF TERMS AND CONDITIONS")[0]
        rows += [(4 * i, text), (4 * i + 1, text.upper().replace("\n", "\n * ")), (4 * i + 2, short), (4 * i + 3, text + " and more")]
        want |= {4 * i: name, 4 * i + 1: name, 4 * i + 2: name, 4 * i + 3: None}
    got = {r.doc_id: r.license for r in license_scan.scan(rows_of(spark, rows), license_scan.known_licenses(spark)).collect()}
    assert got == want


@pytest.mark.skipif(not os.path.isdir(COMMON), reason="licence texts are not installed")
def test_sql_on_planted_texts(spark):
    """Whole copies, short and long, and notices in long lines: the operator and its SQL give the same rows, with names."""
    import duckdb
    import pandas as pd

    rows = [(1, license_scan.KNOWN["MIT"]), (2, "ISC License\n\nCopyright (c) 2020 A B\n\n" + license_scan.KNOWN["ISC"].upper()), (3, "x" * 500 + "\n" + "-" * 400 + " Licensed under CC BY 4.0. " + "*" * 300), (4, None), (5, "no terms")]
    for i, file in enumerate(("GPL-3", "Apache-2.0", "LGPL-2.1", "MPL-2.0")):
        with open(f"{COMMON}/{file}", encoding="utf-8") as f:
            rows.append((10 + i, f.read()))
    con = duckdb.connect()
    documents = pd.DataFrame(rows, columns=["doc_id", "text"])  # noqa: F841
    con.execute("CREATE TABLE documents AS SELECT * FROM documents")
    want = {r[0]: r[1:] for r in con.execute(f"SELECT doc_id, digest, n_canonical_words, license, notices FROM ({license_scan.scan_sql()})").fetchall()}
    found = license_scan.scan(rows_of(spark, rows), license_scan.known_licenses(spark)).collect()
    assert {r.doc_id: (r.digest, r.n_canonical_words, r.license, ",".join(r.notices)) for r in found} == want
    assert {i: w[2] for i, w in want.items() if w[2]} == {1: "MIT", 2: "ISC", 10: "GPL-3.0", 11: "Apache-2.0", 12: "LGPL-2.1", 13: "MPL-2.0"} and want[3][3] == "CC-BY-4.0"
