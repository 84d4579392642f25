"""Main text of web pages by deducing each host's template.

Every page becomes tokens: its tags, told apart by the path of block tags above them, and the texts
of its blocks.  Tokens that occur equally often in the same pages of a host have equal occurrence
vectors and form an equivalence class.  A class that is large and frequent is a candidate; it belongs
to the template if its tags, and its texts below each path, stand in one order in all pages, over and over
where they repeat, and nest below one tag of another class or their own.  What stands between template tokens are slots: the texts
below the nearest tag of the template.  Slots whose text differs from page to page, is long, and is not
mostly links hold the article; that one is in an article or main element is evidence for it.  The article is
the region around these slots, with all of its blocks.  Menus, notices, adverts, forms, comments and
the like are told by tag and by class or id.  Pages that no template fits, and hosts of too few pages
to have one, are left to tags and links.

Pages that have the same blocks count once.  Vectors are kept as sums that combine in any order, so a
host with a third of all pages is never gathered in one task.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import shared_folder, stored

# HTML's void, inline and raw-text elements, and those that hold no article text.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var br img wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
CHROME = frozenset("head script style noscript template nav footer aside form button select option textarea iframe svg canvas object embed dialog menu fieldset".split())
ROOT = frozenset(("article", "main"))
# Words in a class or id that tell boilerplate.
_HINT = re.compile(
    r"(?:^|[\s_-])(?:nav|navbar|navigation|menu|breadcrumbs?|sidebar|side|footer|header|masthead|banner|ads?|advert\w*|sponsor\w*|promo\w*|cookies?|consent|notice|gdpr|popup|modal|overlay|comments?|replies|disqus|respond|share|sharing|social|related|recommended|newsletter|subscribe|signup|login|search|widget|pagination|pager|toolbar|copyright)(?:$|[\s_-])",
    re.I,
)
_MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+|[^>]*)(?:>|\Z)", re.S)
_NAMED = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)

#: A template token is on at least this share of a host's pages, and on so many pages at least.
SHARE, PAGES = 0.5, 3
#: Tokens that a class has at least.
CLASS = 2
#: Mean characters of a page's text in a slot that can hold an article.
SLOT_CHARS = 80
#: How many times the text of slots in article elements counts against that of others.
ROOT_WEIGHT = 4
# Elements that are parts of an article and not the region around it, and those around every region.
PARTS = frozenset("p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd blockquote pre figure figcaption table tbody thead tfoot tr td th caption address center".split())
OUTER = frozenset(("", "html", "body"))


class Block(NamedTuple):
    path: str
    text: str
    linked: int
    chrome: bool
    root: bool


class Parsed(NamedTuple):
    blocks: list[Block]
    tags: dict[str, int]
    order: list[str | Block]


def parse(source: str) -> Parsed:
    """Blocks of text in page order, how often each tag occurs under its path, and paths of tags and blocks in page order.

    White space in a block is one space; character references are decoded.  Unclosed and misplaced
    tags are mended as browsers do: a paragraph ends where the next block begins, an end tag closes what
    was opened inside its element, and one without a start is ignored.
    """
    blocks: list[Block] = []
    tags: dict[str, int] = {}
    both: list[str | Block] = []
    open_tags: list[tuple[str, str, bool, bool]] = []  # name, path, chrome, root
    words: list[str] = []
    linked = link = 0

    def flush() -> None:
        nonlocal linked
        if words:
            text = " ".join(html.unescape("".join(words)).split())
            words.clear()
            if text:
                _, path, chrome, root = open_tags[-1] if open_tags else ("", "", False, False)
                blocks.append(Block(path, text, linked, chrome, root))
                both.append(blocks[-1])
        linked = 0

    def text(part: str) -> None:
        nonlocal linked
        if part:
            words.append(part)
            if link:
                linked += len(part)

    at = 0
    while True:
        m = _MARKUP.search(source, at)
        if m is None:
            text(source[at:])
            break
        text(source[at : m.start()])
        at = m.end()
        closing, name, rest = m[1], m[2], m[3]
        if name is None:
            if m[0].startswith("<![CDATA["):
                text(html.escape(m[0][9:].removesuffix("]]>")))
            continue
        name = name.lower()
        if name in INLINE:
            if name == "a":
                link = 0 if closing else 1
            elif name == "br":
                words.append(" ")
            continue
        flush()
        if closing:
            where = next((i for i in range(len(open_tags) - 1, -1, -1) if open_tags[i][0] == name), None)
            if where is not None:
                del open_tags[where:]
                link = 0
            continue
        while open_tags and (open_tags[-1][0] == "p" or name in ("li", "dt", "dd", "tr", "td", "th") and open_tags[-1][0] in {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th")}.get(name, ("td", "th"))):
            open_tags.pop()
        named = " ".join(next(filter(None, g), "") for g in _NAMED.findall(rest))
        _, above, chrome, root = open_tags[-1] if open_tags else ("", "", False, False)
        path = f"{above}/{name}" + (f".{named.replace('/', '_')}" if named else "")
        tags[path] = tags.get(path, 0) + 1
        both.append(path)
        chrome = chrome or name in CHROME or (name == "header" and not root) or bool(named and name not in ("html", "body") and _HINT.search(named) and name not in ROOT)
        if name in VOID or rest.rstrip().endswith("/") and name not in RAW:
            continue
        if name in RAW:
            end = re.compile(f"</{re.escape(name)}", re.I).search(source, at)
            at = end.start() if end else len(source)
        open_tags.append((name, path, chrome, root or name in ROOT))
    flush()
    return Parsed(blocks, tags, both)


def token(*parts: str) -> int:
    """A path, or a text under a path, as a signed 64-bit number."""
    x = xxhash.xxh3_64_intdigest("\x00".join(parts))
    return x - (1 << 64) if x >> 63 else x


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.\-]*://([^/?#]*)", 1), F.lit("")))


def _parent(path: str) -> str:
    return path.rpartition("/")[0]


def _name(path: str) -> str:
    return path.rpartition("/")[2].partition(".")[0]


_TOKENS = "host string, token long, slot long, page long, times int"


def _rows(rows: list[tuple], kinds: tuple, names: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], [f.split()[0] for f in names.split(", ")])


def _body(p: Parsed) -> int:
    """A page's blocks as a number: pages with equal ones are copies."""
    return token(*(x for b in p.blocks if not b.chrome for x in (b.path, b.text)))


def _tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each token of each page; slot is null for tags and the enclosing path's token for texts.  Token 0 is the page."""
    for b in batches:
        for at in range(0, b.num_rows, 500):
            part = b.slice(at, 500)
            rows = []
            for host, source in zip(part.column(0).to_pylist(), part.column(1)):
                if not (source := source.as_py()):
                    continue
                p = parse(source)
                page = _body(p)
                rows.append((host, 0, None, page, 1))
                rows += [(host, token(path), None, page, n) for path, n in p.tags.items()]
                texts: dict[tuple[str, str], int] = {}
                for x in p.blocks:
                    if not x.chrome:
                        texts[x.path, x.text] = texts.get((x.path, x.text), 0) + 1
                rows += [(host, token(path, text), token(path), page, n) for (path, text), n in texts.items()]
            if rows:
                yield _rows(rows, (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int32()), _TOKENS)


_FITS = "host string, vector long, ordered boolean, form long, path string, inside boolean, page long, text long, chars long, linked long"


def _fits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each page and candidate class, whether its tokens stand in one order, and that order and the tag around them; and for each slot, its texts."""
    kinds = (pa.string(), pa.int64(), pa.bool_(), pa.int64(), pa.string(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
    for b in batches:
        rows = []
        for host, source, found in zip(b.column(0).to_pylist(), b.column(1), b.column(2)):
            if not (source := source.as_py()):
                continue
            classes = {x["token"]: x["vector"] for x in found.as_py()}
            p = parse(source)
            page = _body(p)
            runs: dict[int, list[int]] = {}
            around: dict[int, str] = {}
            slots: dict[str, list] = {}
            for x in p.order:
                if isinstance(x, str):
                    t, above = token(x), _parent(x)
                elif x.chrome:
                    continue
                else:
                    t, above = token(x.path, x.text), x.path
                v = classes.get(t)
                if v is not None:
                    runs.setdefault(v, []).append(t)
                    if v in around:
                        while not f"{above}/".startswith(f"{around[v]}/"):
                            around[v] = _parent(around[v])
                    else:
                        around[v] = above
                elif not isinstance(x, str):
                    path = x.path
                    while path and token(path) not in classes:
                        path = _parent(path)
                    sums = slots.setdefault(path, [x.root, [], 0, 0])
                    sums[0] |= x.root
                    sums[1].append(x.text)
                    sums[2] += len(x.text)
                    sums[3] += x.linked
            for v, run in runs.items():
                size = len(set(run))
                while around[v] and token(around[v]) not in classes:
                    around[v] = _parent(around[v])
                rows.append((host, v, run == run[:size] * (len(run) // size), token(around[v], *map(str, run[:size])), None, None, page, 0, 0, 0))
            rows += [(host, classes.get(token(path)), None, None, path, root, page, token(*texts), chars, linked) for path, (root, texts, chars, linked) in slots.items()]
            if len(rows) > 20_000:
                yield _rows(rows, kinds, _FITS)
                rows = []
        if rows:
            yield _rows(rows, kinds, _FITS)


def templates(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """host, dropped (template texts) and slots (paths that can hold an article, if they are in article elements, and how much text they have) of each host."""
    sources = pages.select(host_of(F.col(url_col)).alias("host"), F.col(html_col).alias("html"))
    folder = shared_folder(pages.sparkSession, "template")
    tokens = sources.mapInArrow(_tokens, _TOKENS).groupBy("host", "token", "slot", "page").agg(F.min("times").alias("times"))
    vectors = stored(tokens.groupBy("host", "token", "slot").agg(F.count(F.lit(1)).alias("support"), F.expr("bit_xor(xxhash64(page, times))").alias("vector")).where(F.col("support") >= PAGES), f"{folder}/vectors")
    sizes = vectors.where("token = 0").select("host", F.col("support").alias("n"))
    frequent = vectors.where("token != 0").join(sizes, "host").where(F.col("support") >= SHARE * F.col("n"))
    classes = frequent.groupBy("host", "vector").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") >= CLASS).select("host", "vector")
    # A class's tags have an order of their own, and so have its texts below each path.
    candidates = stored(frequent.join(classes, ["host", "vector"]).select("host", "token", F.xxhash64("vector", "slot").alias("vector"), "slot"), f"{folder}/candidates")
    by_host = candidates.groupBy("host").agg(F.collect_list(F.struct("token", "vector")).alias("found"))
    size = 64 * candidates.count()
    met = sources.join(F.broadcast(by_host) if size <= 32 << 20 else by_host, "host").select("host", "html", "found")
    fits = stored(met.mapInArrow(_fits, _FITS), f"{folder}/fits")
    valid = fits.where("path is null").groupBy("host", "vector").agg(F.min("ordered").alias("ordered"), F.min("form").alias("a"), F.max("form").alias("b")).where("ordered and a = b").select("host", "vector")
    template = candidates.join(valid, ["host", "vector"])
    dropped = template.where("slot is not null").groupBy("host").agg(F.collect_set("token").alias("dropped"))
    one = fits.where("path is not null").groupBy("host", "path", "page").agg(F.max("inside").alias("inside"), F.min("text").alias("text"), F.max("chars").alias("chars"), F.max("linked").alias("linked"))
    per_slot = one.groupBy("host", "path").agg(F.count(F.lit(1)).alias("support"), F.countDistinct("text").alias("different"), F.max("inside").alias("inside"), F.sum("chars").alias("chars"), F.sum("linked").alias("linked"))
    good = per_slot.where((F.col("support") >= PAGES) & (F.col("chars") >= SLOT_CHARS * F.col("support")) & (2 * F.col("linked") <= F.col("chars")) & (2 * F.col("different") > F.col("support")))
    slots = good.groupBy("host").agg(F.collect_set(F.struct("path", "inside", "chars")).alias("slots"))
    tags = template.where("slot is null").groupBy("host").agg(F.collect_set("token").alias("tags"))
    return tags.join(dropped, "host", "left").join(slots, "host", "left")


def regions(slots: list[dict], tags: frozenset[int]) -> tuple[str, ...]:
    """Paths of the elements that hold a host's article: the one around all its slots, or each slot's own where only the body is around all.

    Slots in article elements are taken where their text, weighted, is not less than the others'; then the element is an article or main.
    """
    inside = [s for s in slots if s["inside"]]
    if inside:
        chosen = inside if ROOT_WEIGHT * sum(s["chars"] for s in inside) >= sum(s["chars"] for s in slots if not s["inside"]) else [s for s in slots if not s["inside"]]
    else:
        chosen = slots
    places = set()
    for s in chosen:
        path = s["path"]
        while path and (_name(path) in PARTS or token(path) not in tags):
            path = _parent(path)
        if s["inside"]:
            up = path
            while up and _name(up) not in ROOT:
                up = _parent(up)
            path = up or path
        places.add(path)
    if not places:
        return ()
    whole = min(places, key=len)
    while not all(f"{x}/".startswith(f"{whole}/") for x in places):
        whole = _parent(whole)
    if _name(whole) not in OUTER:
        return (whole,)
    own = tuple(sorted(x for x in places if _name(x) not in OUTER))
    return own if len(own) == len(places) else (whole,)


def main_text(source: str | None, dropped: frozenset[int] = frozenset(), places: tuple[str, ...] = ()) -> str:
    """The article's blocks, joined by line breaks; empty for a null page."""
    if not source:
        return ""
    found = [b for b in parse(source).blocks if not b.chrome]
    narrow = [x for x in places if _name(x) not in OUTER]
    if main := [b for b in found if any(f"{b.path}/".startswith(f"{x}/") for x in narrow)]:
        return "\n".join(b.text for b in main)
    inside = [b for b in found if b.root]
    if inside:
        return "\n".join(b.text for b in inside)
    return "\n".join(b.text for b in found if token(b.path, b.text) not in dropped and 2 * b.linked <= len(b.text))


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per input row: its id and url, text and n_chars.

    A null or empty page has an empty text.  Pages without a url are one host.  A host's template is broadcast
    with all others while they are measured to be small; beyond, pages meet it by a join.
    """
    known = stored(templates(pages, url_col, html_col), shared_folder(pages.sparkSession, "templates"))
    size = known.agg(F.coalesce(F.sum(64 + 8 * (F.size("tags") + F.greatest(F.size("dropped"), F.lit(0))) + 200 * F.greatest(F.size("slots"), F.lit(0))), F.lit(0)).alias("n")).first().n
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"), host_of(F.col(url_col)).alias("host"))
    joined = rows.join(F.broadcast(known) if size <= 32 << 20 else known, "host", "left").select("id", "url", "html", "dropped", "slots", "tags")
    kind = joined.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(h.as_py(), frozenset(d.as_py() or ()), regions(s.as_py() or [], frozenset(t.as_py() or ()))) for h, d, s, t in zip(*b.columns[2:6])]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["id", "url", "text", "n_chars"])

    out = joined.mapInArrow(run, f"id {kind}, url string, text string, n_chars long")
    return out.withColumnRenamed("url", url_col).withColumnRenamed("id", id_col)
