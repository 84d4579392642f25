"""Operators on texts against plain versions, with nulls, empties, repeats, long texts and clashing columns."""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from trajdist.llm import decontamination, kneser_ney, language_id, near_dup, quality
from trajdist.llm.shared import remainder, shared_folder, table
from trajdist.llm.words import grams, hash_words

WORD = re.compile("[^\x20\x09-\x0d]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, n_words int, kept string, doc string, key long"


def words(t):
    return WORD.findall((t or "").translate(LOWER))


def docs(spark, rows):
    return spark.createDataFrame([(i, t, 1, "clash", "clash", 5) for i, t in rows], SCHEMA)


def prose(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


@settings(max_examples=100, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet=" \t\nabABé ", max_size=30)), max_size=8))
def test_hashed_words(texts):
    got = hash_words(pa.array(texts, pa.string()))
    want = [words(t) for t in texts]
    assert [len(w) for w in want] == (got.bounds[1:] - got.bounds[:-1]).tolist()
    flat = [x for w in want for x in w]
    same = defaultdict(set)
    for w, h in zip(flat, got.hashes.tolist()):
        same[w].add(h)
    assert all(len(v) == 1 for v in same.values()) and len({next(iter(v)) for v in same.values()}) == len(same)
    g = grams(got, 3, short=True)
    assert (g.bounds[1:] - g.bounds[:-1]).tolist() == [max(len(w) - 2, 1) if w else 0 for w in want]


def test_segments_do_not_matter(monkeypatch):
    from trajdist.llm import words as module

    texts = pa.array(["a bb  ccc " * 50, None, "x" * 300, " " * 100, "end"])
    want = hash_words(texts)
    monkeypatch.setattr(module, "SEGMENT", 16)
    got = hash_words(texts)
    assert (got.hashes == want.hashes).all() and (got.bounds == want.bounds).all()


# ---- near duplicates -----------------------------------------------------------------------------------------


def groups_of(rows):
    sets = {}
    for i, t in rows:
        w = words(t)
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set())
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = list(sets)
    for a in ids:
        for b in ids:
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= 75 * len(sets[a] | sets[b]):
                p, q = sorted((find(a), find(b)))
                parent[q] = p
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_duplicates(spark):
    rng = random.Random(3)
    rows, n = [], 0
    for _ in range(25):
        base = prose(rng, rng.randint(3, 120)).split()
        for _ in range(rng.randint(1, 9)):
            copy = list(base)
            for _ in range(rng.choice([0, 0, 1, 2, 3])):
                copy[rng.randrange(len(copy))] = "new%d" % rng.randrange(50)
            rows.append((n, " ".join(copy)))
            n += 1
    rows += [(n, None), (n + 1, ""), (n + 2, " \n "), (n + 3, "one"), (n + 4, "ONE"), (n + 5, "long " * 40_000), (n + 6, "long " * 30_000)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dup.near_duplicates(docs(spark, rows)).collect()}
    assert got == groups_of(rows)


def test_dense_regions_split(spark, monkeypatch):
    rng = random.Random(4)
    base = prose(rng, 90).split()
    rows = []
    for i in range(60):
        copy = list(base)
        copy[rng.randrange(90)] = f"v{i}"
        rows.append((i, " ".join(copy)))
    monkeypatch.setattr(near_dup, "REGION", 8)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dup.near_duplicates(docs(spark, rows)).collect()}
    assert got == groups_of(rows)


@pytest.mark.parametrize("broadcast", [near_dup.BROADCAST_IDS, 0])
def test_near_duplicates_of_a_large_region(spark, monkeypatch, broadcast):
    """A text whose one link is to a text of a region that is far too large: splitting the region must not lose it."""
    monkeypatch.setattr(near_dup, "REGION", 32)
    monkeypatch.setattr(near_dup, "BROADCAST_IDS", broadcast)
    base = [f"w{i}" for i in range(400)]
    copies = [(i, " ".join(w if at != i else f"c{i}" for at, w in enumerate(base))) for i in range(1, 251)]
    far = [(1000 + k, " ".join(f"f{k}n{at}" if at % 36 == k else w for at, w in enumerate(base))) for k in range(30)]
    rows = [(0, " ".join(base)), *copies, *far]
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(docs(spark, rows)).collect()}
    want = {i: c for i, (_, c) in groups_of(rows).items()}
    assert set(want.values()) == {0} and got == want


def test_links_in_a_dense_region(spark):
    """With the settings as they are: 2,200 texts of one form, each with one link just above the threshold among thousands just below."""
    common, rows = " ".join(f"c{i}" for i in range(164)), []
    for i in range(1100):
        pair = " ".join(f"p{i}_{j}" for j in range(3))
        rows += [(2 * i + k, f"{common} {pair} " + " ".join(f"o{i}_{k}_{j}" for j in range(26))) for k in (0, 1)]
    a, b, c = ({tuple(w[j : j + 5]) for j in range(len(w) - 4)} for w in (rows[0][1].split(), rows[1][1].split(), rows[2][1].split()))
    assert len(a & b) / len(a | b) >= 0.75 > len(a & c) / len(a | c) > 0.73 and len(rows) > near_dup.REGION
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(docs(spark, rows)).collect()}
    assert all(got[2 * i] == 2 * i and got[2 * i + 1] in (2 * i, 2 * i + 1) for i in range(1100))
    assert sum(got[2 * i + 1] == 2 * i for i in range(1100)) >= 1098


def test_near_duplicate_edges(spark):
    rows = [(None, "a b c d e f"), (4, "a b c d e f"), (4, "a b c d e f"), (2, "A b c d E f"), (7, "other words")]
    got = sorted((str(r.doc_id), str(r.component_id)) for r in near_dup.near_duplicates(docs(spark, rows)).collect())
    assert got == [("2", "2"), ("4", "2"), ("4", "2"), ("7", "7"), ("None", "None")]
    kept = near_dup.keep_first(docs(spark, rows))
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["2", "7", "None"] and kept.columns == docs(spark, []).columns
    assert near_dup.near_duplicates(docs(spark, [])).count() == 0


def test_components(spark):
    chain = [(i + 1, i) for i in range(40)] + [(100, 101), (101, 102), (200, 201)]
    got = {r.id: r.component for r in near_dup.components(spark.createDataFrame(chain, "a long, b long"), shared_folder(spark, "c")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 102: 100, 200: 200, 201: 200}


# ---- decontamination -----------------------------------------------------------------------------------------

TERM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def terms(t):
    return TERM.findall((t or "").translate(LOWER))


def hits(text, tests, size=13):
    w, covered, items = terms(text), set(), set()
    for name, t in tests:
        v = terms(t)
        k = min(len(v), size)
        for a in range(len(v) - k + 1) if v else ():
            for b in range(len(w) - k + 1):
                if w[b : b + k] == v[a : a + k]:
                    covered.update(range(b, b + k))
                    items.add(name)
    return len(w), len(covered), sorted(items)


def test_decontamination(spark):
    rng = random.Random(6)
    tests = [(i, prose(rng, rng.choice([3, 12, 13, 20, 40]), 60)) for i in range(12)] + [(50, None), (51, "!!"), (52, "same same same"), (53, "Same, SAME same")]
    rows = []
    for i in range(60):
        parts = [prose(rng, rng.randint(0, 60), 60)]
        for _ in range(rng.randint(0, 2)):
            t = (rng.choice(tests)[1] or "").split()
            a = rng.randint(0, max(0, len(t) - 3))
            parts.insert(rng.randint(0, len(parts)), " ".join(t[a : a + rng.randint(5, 45)]))
        rows.append((i, "; ".join(parts).upper() if i % 3 else "\n".join(parts)))
    rows += [(70, None), (71, ""), (None, tests[4][1]), (72, tests[4][1]), (72, tests[4][1]), (73, "same " * 5000)]
    bench = spark.createDataFrame(tests, "item_id long, text string")
    got = decontamination.matches(docs(spark, rows), bench).collect()
    names = [(str(i), t) for i, t in tests]
    want = sorted((str(i), *hits(t, names)) for i, t in rows if i != 73) + [("73", 5000, 5000, ["52", "53"])]
    assert sorted((str(r.doc_id), r.n_words, r.n_hit, r["items"]) for r in got) == sorted(want)
    clean = decontamination.keep_clean(docs(spark, rows), bench)
    assert clean.columns == docs(spark, []).columns
    bad = {str(i) for i, t in rows if (h := hits(t, names) if i != 73 else (1, 1, []))[1] > 0 and 20 * h[1] >= h[0]}
    assert sorted(str(r.doc_id) for r in clean.collect()) == sorted(str(i) for i, _ in rows if str(i) not in bad)
    for d, b in ((docs(spark, []), bench), (docs(spark, rows[:2]), bench.limit(0))):
        assert decontamination.matches(d, b).where("n_hit > 0").count() == 0


def test_phrases_and_proximity(spark):
    rows = [(1, "a b c a b d"), (2, "b a x x a b"), (3, "c"), (4, None)]
    tests = spark.createDataFrame([(1, "a b"), (2, "b c a"), (3, "zz")], "item_id long, text string")
    index = decontamination.build_index(docs(spark, rows), decontamination.test_items(tests), shared_folder(spark, "i"))
    got = sorted((r.doc, r.item_id, r.start) for r in decontamination.phrases(index, tests).collect())
    assert got == [(1, "1", 0), (1, "1", 3), (1, "2", 1), (2, "1", 4)]
    near = sorted((r.doc, r.pos, r.other_pos) for r in decontamination.proximity(index, "a", "c", 2).collect())
    assert near == [(1, 0, 2), (1, 3, 2)]


# ---- language model ------------------------------------------------------------------------------------------


def plain_model(train, order):
    counts = {k: Counter() for k in range(1, order + 1)}
    raw = Counter()
    for w in train:
        s = ["<s>", *w, "</s>"]
        raw.update(s[1:])
        for j in range(len(s) - order + 1):
            counts[order][tuple(s[j : j + order])] += 1
        for k in range(2, order):
            if len(s) >= k:
                counts[k][tuple(s[:k])] += 1
    for k in range(order, 1, -1):
        for g in counts[k]:
            counts[k - 1][g[1:]] += 1
    return raw, counts


@pytest.mark.parametrize("order", [2, 3, 4])
def test_kneser_ney(spark, order):
    rng = random.Random(order)
    rows = [(i, prose(rng, rng.randint(0, 40), 30)) for i in range(80)] + [(90, None), (91, ""), (92, "W1 w1 W1"), (92, "W1 w1 W1"), (None, "w2 unseen")]
    is_held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 == 1
    d = docs(spark, rows)
    got, model = kneser_ney.held_out_scores(d, F.coalesce(remainder(F.col("doc_id"), 5) != 1, F.lit(True)), order=order)
    raw, counts = plain_model([words(t) for i, t in rows if not is_held(i)], order)
    n, v = sum(raw.values()), len(raw)
    assert (model["tokens"], model["types"]) == (n, v)
    d3 = {k: kneser_ney.discounts([Counter(c.values())[i] for i in range(1, 5)]) for k, c in counts.items()}
    contexts = {k: defaultdict(lambda: [0, 0, 0, 0]) for k in counts}
    for k, c in counts.items():
        for g, x in c.items():
            s = contexts[k][g[:-1]]
            s[0] += x
            s[min(x, 3)] += 1

    def probability(s, j):
        p = 1 / (v + 1)
        for k in range(1, order + 1):
            g = tuple(s[j - k + 1 : j + 1])
            if j - k + 1 < 0 or g[:-1] not in contexts[k]:
                break
            x, c = contexts[k][g[:-1]], counts[k].get(g, 0)
            p = (max(c - d3[k][min(c, 3) - 1], 0) if c else 0) / x[0] + sum(a * b for a, b in zip(d3[k], x[1:])) / x[0] * p
        return p

    def measures(t):
        s = ["<s>", *words(t), "</s>"]
        return len(s) - 1, sum(raw[x] > 0 for x in s[1:]), sum(math.log10((raw[x] + 0.5) / (n + 0.5 * (v + 1))) for x in s[1:]), sum(math.log10(probability(s, j)) for j in range(1, len(s)))

    want = sorted((str(i), *measures(t)) for i, t in rows)
    for r, w in zip(sorted(got.collect(), key=lambda r: (str(r.doc_id), r.n_tokens)), want, strict=True):
        assert (str(r.doc_id), r.n_tokens, r.n_known) == w[:3]
        assert r.base_score == pytest.approx(w[3], abs=1e-8) and r.score == pytest.approx(w[4], abs=1e-8)
    some = tuple(["<s>"])
    total = sum(probability([*some, x], 1) for x in raw)
    assert total + probability([*some, "never seen"], 1) == pytest.approx(1)


def test_model_of_nothing(spark):
    got, model = kneser_ney.held_out_scores(docs(spark, [(1, "some words"), (2, None)]), F.lit(False))
    assert model["tokens"] == 0 and sorted(r.score for r in got.collect()) == [0.0, 0.0]
    assert kneser_ney.held_out_scores(docs(spark, []), F.lit(True))[0].count() == 0


# ---- quality -------------------------------------------------------------------------------------------------


def base_measures(t):
    t = t or ""
    w = WORD.findall(t)
    windows = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = {j for i in range(len(w) - 7) if windows[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), dup, len(covered), len(w) < 20 or 100 * len(covered) > 30 * len(w)


def test_quality(spark, sf_dir):
    rng = random.Random(8)
    odd = [(-1, None), (-2, ""), (-3, " \n\n "), (-4, "same words here\n" * 40), (-5, prose(rng, 60) + "\n" + prose(rng, 40)), (-5, "x"), (-6, "é# " * 90_000), (None, "  a")]
    rows = odd + [(r.doc_id, r.text) for r in table(spark, sf_dir, "documents").select("doc_id", "text").collect()]
    got = quality.score(docs(spark, rows)).collect()
    want = sorted((str(i), *base_measures(t)) for i, t in rows)
    assert sorted((str(r.doc_id), r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got) == want
    assert all(not (r.kept and r.base_failed) for r in got)
    kept = quality.keep_good(docs(spark, rows))
    assert sorted(r.doc_id for r in kept.collect()) == sorted(r.doc_id for r in got if r.kept) and kept.columns == docs(spark, []).columns


def test_bands():
    import base64

    rng = random.Random(1)
    coder = quality.zstandard.ZstdCompressor(level=quality.LEVEL)
    text = " ".join("".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 9))) for _ in range(900))
    assert quality.bands(text, coder).passed
    assert not quality.bands("again and again " * 400, coder).passed
    assert not quality.bands(base64.b85encode(rng.randbytes(9000)).decode(), coder).passed
    half = text[:3000] + "the same " * 2000
    assert not quality.bands(half, coder).passed and quality.bands(half, coder).odd > 0


# ---- language ------------------------------------------------------------------------------------------------


def test_language_held_out(spark, sf_dir):
    sf = sf_dir.replace("sf0.001", "sf0.01")
    d = table(spark, sf, "documents")
    model = language_id.fit(d, remainder(F.col("doc_id"), 4) != 2)
    assert sorted(model) == ["de", "en", "es", "fr"]
    held = d.where(remainder(F.col("doc_id"), 4) == 2)
    got = {r.doc_id: r for r in language_id.predict(held, model).collect()}
    truth = {r.doc_id: r.lang for r in held.select("doc_id", "lang").collect()}
    right = sum(got[i].lang_pred == l for i, l in truth.items())
    assert right >= 0.95 * len(truth) and sum(r.rejected for r in got.values()) <= 0.03 * len(got)
    assert all(0 <= r.score <= 1 for r in got.values())


def test_language_edges(spark):
    rows = [(1, "der die das und nicht ein eine", "de"), (2, "the and of with this that", "en"), (3, None, "en"), (4, "123 !!", None), (5, "", "fr")]
    d = spark.createDataFrame([(*r, 0.5, True) for r in rows], "doc_id long, text string, lang string, score double, rejected boolean")
    model = language_id.fit(d, F.lit(True))
    assert sorted(model) == ["de", "en"]
    got = {r.doc_id: (r.lang_pred, r.rejected) for r in language_id.predict(d, model).collect()}
    assert got[1] == ("de", False) and got[2] == ("en", False) and got[3] == got[4] == got[5] == ("und", True)
    assert sorted(r.doc_id for r in language_id.keep_identified(d, model).collect()) == [1, 2]
    assert {r.lang_pred for r in language_id.predict(d, {}).collect()} == {"und"}
    assert language_id.predict(d.limit(0), model).count() == 0 and language_id.fit(d.limit(0), F.lit(True)) == {}


def test_model_sees_two_words_back(spark):
    """What follows "b" is told by the word before it: the query's model has to use it."""
    rows = [(i, "a b c" if i % 2 else "d b e") for i in range(40)]
    mean = lambda found: sum(r.score for r in found[0].collect())
    assert mean(kneser_ney.held_out_scores(docs(spark, rows), F.lit(True))) > mean(kneser_ney.held_out_scores(docs(spark, rows), F.lit(True), order=2)) + 1


def test_blocks_of_grams():
    """Packing, merging, and the way for columns that do not fit one number, against counters."""
    import numpy as np

    rng = random.Random(4)
    parts, want = [], Counter()
    for i in range(6):
        ids = np.array([rng.randrange(1 << (10 + 4 * i)) % 97 * (1 << i) for _ in range(400)], np.uint64)
        want.update(zip(ids[:-2].tolist(), ids[1:-1].tolist(), ids[2:].tolist()))
        g = kneser_ney._added([ids[:-2], ids[1:-1], ids[2:]], None)
        parts += [kneser_ney.unpack(b) for _, _, b in kneser_ney._blocks(3, g, kneser_ney.gram_key(g.columns), 5)]
    whole = kneser_ney._joined(parts)
    rows = list(zip(*(c.tolist() for c in whole.columns)))
    assert rows == sorted(want) and dict(zip(rows, whole.values[0].tolist())) == want
    high = [c << np.uint64(40) for c in whole.columns]
    wide = kneser_ney._added([np.concatenate([c, c]) for c in high], [np.concatenate([whole.values[0]] * 2)])
    assert (wide.values[0] == 2 * whole.values[0]).all() and all((a == b).all() for a, b in zip(wide.columns, high))


def test_gram_arrays(tmp_path):
    """Large counts, rare and common sets of numbers, and keys that are not there."""
    import numpy as np

    rng = random.Random(5)
    folder, n, shards = f"file://{tmp_path}", 3000, 3
    keys = np.array([rng.getrandbits(64) for _ in range(2 * n)], np.uint64)
    values = [np.array([rng.choice([0, 1, 2, 254, 255, 2**40]) for _ in range(n)], np.uint64)] + [np.array([rng.choice([0, 1, rng.randrange(900), 2**20]) for _ in range(n)], np.uint64) for _ in range(4)]
    shard = kneser_ney._place(keys[:n], shards)[0]
    for s in range(shards):
        mine = np.flatnonzero(shard == s)
        kneser_ney._write_grams(folder, 2, s, shards, keys[mine], [v[mine] for v in values])
    got = kneser_ney.GramArrays(folder, 2, shards).find(keys)
    for g, v in zip(got, values, strict=True):
        assert (g[:n] == v).all() and (g[n:] == 0).all()


def test_language_by_plain_compression(spark, sf_dir):
    """Every row against compression under each dictionary, one text and one language at a time; ties go to the first name."""
    import zstandard

    d = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = language_id.fit(d, remainder(F.col("doc_id"), 4) != 2)
    texts = [r.text for r in d.orderBy("doc_id").limit(60).collect()]
    rows = list(enumerate([*texts, texts[0], texts[0], None, "", "123 !?", " ".join(texts[:20]) * 3, "é", "word"]))

    def plain(text):
        if text is None or not any(c.isalpha() for c in text):
            return "und", 0.0, True
        raw = re.sub(r"[\W\d_]+", " ", text).strip().lower().encode()
        parts = [raw[i : i + language_id.CHUNK] for i in range(0, len(raw), language_id.CHUNK)]
        if len(raw) < language_id.SHORT:
            parts += [raw[i + 1 :] for i in range(len(raw)) if raw[i : i + 1] == b" "]
        sizes = []
        for name in sorted(model):
            words = zstandard.ZstdCompressionDict(model[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            words.precompute_compress(level=language_id.LEVEL)
            sizes.append((sum(len(zstandard.ZstdCompressor(level=language_id.LEVEL, dict_data=words, write_checksum=False, write_content_size=False, write_dict_id=False).compress(p)) for p in parts), name))
        (best, name), (second, _) = sorted(sizes)[:2]
        return name, min(1.0, 4 * (1 - best / second)), 1 - best / second < language_id.MARGIN

    got = {r.doc_id: (r.lang_pred, r.score, r.rejected) for r in language_id.predict(docs(spark, rows), model).collect()}
    assert got == {i: plain(t) for i, t in rows}
    tied = language_id.Classifier({"b": b"one two three", "a": b"one two three"})
    assert tied("one two") == ("a", 0.0, True)
    again = language_id.predict(docs(spark, rows * 2), model)
    assert again.count() == 2 * len(rows) and again.distinct().count() == len(rows)


def test_arrays_are_in_order_inside_buckets(tmp_path):
    """What is there is found with its count; a search for what is not ends at the first larger number, in buckets of about four."""
    import numpy as np

    rng, shards = np.random.default_rng(5), 2
    keys = np.unique(rng.integers(0, 1 << 64, 40_000, np.uint64))
    count = np.arange(len(keys), dtype=np.uint64) % np.uint64(400)
    shard = kneser_ney._place(keys, shards)[0]
    for s in range(shards):
        kneser_ney._write_grams(f"file://{tmp_path}", 3, s, shards, keys[shard == s], [count[shard == s]])
    arrays = kneser_ney.GramArrays(f"file://{tmp_path}", 3, shards)
    assert (arrays.find(keys)[0] == count).all()
    assert (arrays.find(rng.integers(0, 1 << 64, 1000, np.uint64))[0] > 0).sum() == 0
    for begins, low, buckets, _ in arrays.parts:
        bucket = np.repeat(np.arange(buckets), np.diff(begins.astype(np.int64)))
        assert len(low) < 5 * buckets and (np.diff(low.astype(np.int64))[np.diff(bucket) == 0] > 0).all()
