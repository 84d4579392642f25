"""Benchmark decontamination with a distributed positional inverted index, in DataFrame operations only.

``build_index`` stores the postings (term, document, position) of every training token that is a
term of the tests, and each document's length.  ``matches`` looks for the tests' windows of
consecutive words: of each window it takes the rarest terms, shifts their postings by the terms'
places in the test, and intersects the shifted lists; what survives is compared word by word.
``phrases`` and ``proximity`` answer from the postings alone.

Words are runs of characters outside \\x00-\\x2F, \\x3A-\\x60 and \\x7B-\\x7F after A-Z is lower-cased.
A null text has no words.  Rows are told apart by their id and a hash of their text, so
repeated rows get the same answer each, and null ids are allowed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import shared_folder, stored

WINDOW = 13
#: Shifted lists that must meet before words are compared.
LISTS = 2
#: Bytes of test terms up to which they are broadcast; beyond, they are joined by shuffle.
BROADCAST_BYTES = 64 << 20

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BETWEEN = r"[\x00-/:-`{-\x7F]+"
#: Stands after each document's last word; no word is a space.
_END = " "


def words(text: Column) -> Column:
    """The words of a text, in order."""
    return F.coalesce(F.array_remove(F.split(F.translate(text, _UPPER, _LOWER), _BETWEEN), ""), F.array().cast("array<string>"))


def _row_key(id_col: str, text_col: str) -> list[Column]:
    return [F.col(id_col).alias("doc"), F.xxhash64(F.col(text_col)).alias("text_hash")]


def _same_row(a: DataFrame, b: DataFrame) -> Column:
    return a["doc"].eqNullSafe(b["doc"]) & (a["text_hash"] == b["text_hash"])


def _bounded(small: DataFrame, text: str) -> DataFrame:
    """Broadcast if its measured size is within BROADCAST_BYTES."""
    size = small.agg(F.coalesce(F.sum(F.octet_length(text) + 64), F.lit(0)).alias("n")).first().n
    return F.broadcast(small) if size <= BROADCAST_BYTES else small


def test_items(tests: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """item (a dense number), item_id (text), words: distinct tests that have words."""
    named = tests.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("item_id"), words(F.col(text_col)).alias("words")).where("size(words) > 0").distinct()
    return named.select(F.xxhash64("item_id", "words").alias("item"), "item_id", "words")


def build_index(docs: DataFrame, items: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Stores and returns the postings doc, text_hash, term, pos of all terms of ``items``.

    Each document also has one posting of the term that marks its end; its pos is the number of
    words.  The tokens meet the terms where they are read; nothing is shuffled.
    """
    terms = items.select(F.explode("words").alias("term")).union(items.sparkSession.createDataFrame([(_END,)], "term string")).distinct()
    tokens = docs.select(*_row_key(id_col, text_col), F.posexplode(F.concat(words(F.col(text_col)), F.array(F.lit(_END)))).alias("pos", "term"))
    return stored(tokens.join(_bounded(terms, "term"), "term").select("doc", "text_hash", "term", "pos"), folder)


def frequencies(index: DataFrame) -> DataFrame:
    """How often each term of the index occurs in all documents."""
    return index.where(F.col("term") != _END).groupBy("term").agg(F.count(F.lit(1)).alias("freq"))


def lengths(index: DataFrame) -> DataFrame:
    return index.where(F.col("term") == _END).select("doc", "text_hash", F.col("pos").cast("long").alias("n_words"))


def rarest(items: DataFrame, freq: DataFrame, window: int = WINDOW, lists: int = LISTS) -> DataFrame:
    """item, ipos, term: the places in the tests that are among the rarest of some window there.

    Windows with a term that no document holds have no match and give no place.  ``need`` is how
    many lists that test's windows have.
    """
    n = F.size("words")
    length = F.least(n, F.lit(window))
    places = (
        items.select("item", n.alias("n"), length.alias("length"), F.posexplode("words").alias("ipos", "term"))
        .join(_bounded(freq, "term"), "term", "left")
        .select("item", "length", "ipos", "term", "freq", F.explode(F.sequence(F.greatest(F.col("ipos") - F.col("length") + 1, F.lit(0)), F.least("ipos", F.col("n") - F.col("length")))).alias("start"))
    )
    w = Window.partitionBy("item", "start")
    ranked = places.withColumn("absent", F.max(F.col("freq").isNull()).over(w)).where("not absent").withColumn("rank", F.row_number().over(w.orderBy("freq", "ipos")))
    return ranked.where(F.col("rank") <= lists).select("item", "ipos", "term", F.least("length", F.lit(lists)).alias("need")).distinct()


def candidates(index: DataFrame, places: DataFrame) -> DataFrame:
    """doc, text_hash, item, shift: where shifted lists of the rarest terms meet.

    ``shift`` is the document position at which the test's first word would stand."""
    hits = index.join(_bounded(places, "term"), "term").select("doc", "text_hash", "item", (F.col("pos") - F.col("ipos")).alias("shift"), "ipos", "need")
    met = hits.groupBy("doc", "text_hash", "item", "shift").agg(F.countDistinct("ipos").alias("n"), F.max("need").alias("need"))
    return met.where("n >= need").select("doc", "text_hash", "item", "shift")


def compared(found: DataFrame, docs: DataFrame, items: DataFrame, id_col: str, text_col: str, window: int = WINDOW) -> DataFrame:
    """doc, text_hash, item_id, starts, length: windows that occur, by comparing all their words.

    The documents that have candidates are split into words once each."""
    per_doc = found.groupBy("doc", "text_hash").agg(F.collect_set(F.struct("item", "shift")).alias("at"))
    texts = docs.select(*_row_key(id_col, text_col), F.col(text_col).alias("text"))
    rows = per_doc.join(texts, _same_row(per_doc, texts)).select(per_doc["doc"], per_doc["text_hash"], "at", words(F.col("text")).alias("w"))
    begin = F.greatest("a.shift", F.lit(0))
    spread = rows.select("doc", "text_hash", "w", F.explode("at").alias("a"))
    # As many words as the longest test has, from where this one would begin.
    most = items.agg(F.max(F.size("words"))).first()[0] or 0
    parts = spread.select("doc", "text_hash", "a.item", F.col("a.shift").alias("shift"), begin.alias("begin"), F.slice("w", begin + 1, F.lit(most)).alias("part"))
    both = parts.join(_bounded(items.select(F.col("item").alias("i"), "item_id", F.col("words").alias("iw")), "item_id"), F.col("item") == F.col("i"))
    first = F.col("begin") - F.col("shift")
    same = F.zip_with(F.slice("part", 1, F.size("iw") - first), F.slice("iw", first + 1, F.size("iw")), lambda a, b: F.coalesce(a == b, F.lit(False)))
    checked = both.select("doc", "text_hash", "item_id", "begin", F.least(F.size("iw"), F.lit(window)).alias("length"), same.alias("same")).where("size(same) >= length")
    starts = F.filter(F.sequence(F.lit(0), F.size("same") - F.col("length")), lambda i: F.forall(F.slice("same", i + 1, F.col("length")), lambda x: x))
    return checked.select("doc", "text_hash", "item_id", "length", F.transform(starts, lambda i: i + F.col("begin")).alias("starts")).where("size(starts) > 0")


def matches(docs: DataFrame, tests: DataFrame, id_col: str = "doc_id", text_col: str = "text", test_id: str = "item_id", test_text: str = "text", window: int = WINDOW) -> DataFrame:
    """One row per document: its id, n_words, n_hit (words inside occurring windows), items (their ids, sorted).

    A test of fewer than ``window`` words, but not none, is one window.
    """
    spark = docs.sparkSession
    items = stored(test_items(tests, test_id, test_text), shared_folder(spark, "tests"))
    index = build_index(docs, items, shared_folder(spark, "postings"), id_col, text_col)
    freq = stored(frequencies(index), shared_folder(spark, "frequencies"))
    places = stored(rarest(items, freq, window), shared_folder(spark, "places"))
    found = stored(candidates(index, places), shared_folder(spark, "candidates"))
    hits = compared(found, docs, items, id_col, text_col, window)
    ranges = F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.transform("starts", lambda s: F.struct(s.alias("lo"), (s + F.col("length")).alias("hi")))))))
    per_doc = hits.groupBy("doc", "text_hash").agg(ranges.alias("ranges"), F.array_sort(F.collect_set("item_id")).alias("items"))
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
    covered = F.aggregate(
        "ranges", zero,
        lambda acc, r: F.struct((acc["n"] + F.greatest(r["hi"] - F.greatest(r["lo"], acc["end"]), F.lit(0))).alias("n"), F.greatest(r["hi"], acc["end"]).alias("end")),
        lambda acc: acc["n"].cast("long"),
    )
    per_doc = per_doc.select("doc", "text_hash", covered.alias("n_hit"), "items")
    sizes = lengths(index)
    return sizes.join(per_doc, _same_row(sizes, per_doc), "left").select(
        sizes["doc"].alias(id_col), sizes["text_hash"], "n_words", F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items")
    )


def contaminated(n_hit: Column, n_words: Column) -> Column:
    """At least one word in twenty lies in a test's window."""
    return (n_hit > 0) & (20 * n_hit >= n_words)


def keep_clean(docs: DataFrame, tests: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, that are not contaminated."""
    found = matches(docs, tests, id_col, text_col)
    bad = found.where(contaminated(F.col("n_hit"), F.col("n_words"))).select(F.col(id_col).alias("doc"), "text_hash").distinct()
    h = F.xxhash64(docs[text_col])
    return docs.join(bad, docs[id_col].eqNullSafe(bad["doc"]) & (h == bad["text_hash"]), "left_anti")


def phrases(index: DataFrame, tests: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """doc, item_id, start: exact occurrences of whole tests, from the postings alone.

    Candidates come from the rarest terms; the other terms' postings are looked up at the places
    where the candidates need them."""
    items = test_items(tests, id_col, text_col)
    most = items.agg(F.max(F.size("words"))).first()[0] or 1
    found = candidates(index, rarest(items, frequencies(index), window=most))
    need = found.join(items, "item").select("doc", "text_hash", "item_id", "shift", F.size("words").alias("n"), F.posexplode("words").alias("i", "term")).withColumn("pos", F.col("shift") + F.col("i")).withColumnRenamed("doc", "d")
    here = index.distinct()
    met = need.join(here, need["d"].eqNullSafe(here["doc"]) & (need["text_hash"] == here["text_hash"]) & (need["term"] == here["term"]) & (need["pos"] == here["pos"]))
    return met.groupBy("d", need["text_hash"], "item_id", "shift", "n").count().where("count = n").select(F.col("d").alias("doc"), "item_id", F.col("shift").alias("start"))


def proximity(index: DataFrame, one: str, other: str, within: int) -> DataFrame:
    """doc, pos, other_pos: the two terms at most ``within`` words apart, in either order.

    Positions meet by blocks of ``within`` + 1 words, so a document's lists are never paired whole."""
    block = F.floor(F.col("pos") / (within + 1))
    here = index.distinct()
    a = here.where(F.col("term") == one).select("doc", "text_hash", "pos", F.explode(F.array(block - 1, block, block + 1)).alias("block"))
    b = here.where(F.col("term") == other).select("doc", "text_hash", F.col("pos").alias("other_pos"), block.alias("block"))
    met = a.join(b, _same_row(a, b) & (a["block"] == b["block"]))
    return met.where((F.abs(F.col("pos") - F.col("other_pos")) <= within) & (F.col("pos") != F.col("other_pos"))).select(a["doc"], "pos", "other_pos")
