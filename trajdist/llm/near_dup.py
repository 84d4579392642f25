"""Near duplicates by a MinHash LSH forest, confirmed on full sets.

Each text is the set of its five-word shingles.  TREES independent orders sort the texts by DEPTH
MinHash values each; texts whose labels share a prefix stand together in an order.  Starting from
a prefix of two values, a region of an order that holds too many texts is split by longer
prefixes, so depth adapts to density.  Within a region, signatures estimate every similarity, and
the strongest links that connect its texts become candidates.  Candidates are confirmed on the full
sets; connected components of the confirmed links are groups.  A second look takes the full sets of
all texts that may have a link to another group of their region, and compares each with all such
others, without a cap; a link that joins two groups is enough of them.  It reads the regions of two
values whole: those that were split are dealt into blocks that meet in pairs, so longer prefixes
order the work and drop no pair.

Texts with equal sets are one node.  Ids that are null link with nothing.  Rows that repeat
an id are one node.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import lean, shared_folder, stored
from .words import grams, hash_words, mix, slices

SHINGLE = 5
TREES = 12
DEPTH = 16
HASHES = TREES * DEPTH
#: Percent of the union that the intersection must reach.
PERCENT = 75
#: Least number of equal MinHash values for a candidate: 4 deviations below the threshold's mean of 144, raised for chance matches of 8-bit values.
AGREE = 120
#: Texts in a region above which it is split by longer prefixes, and the lengths of prefixes.
REGION = 2048
LENGTHS = (2, 4, 8, 16)
#: Ids up to which a list of ids is broadcast to the texts; beyond, the texts meet it by a shuffle.
BROADCAST_IDS = 2_000_000


def _multipliers(seed: int) -> np.ndarray:
    return (mix(np.arange(1, HASHES + 1, dtype=np.uint64) * np.uint64(seed)) >> np.uint64(32)).astype(np.uint32) | np.uint32(1)


_A, _B = _multipliers(0x51ED270B), _multipliers(0x9E3779B1)


def shingle_sets(texts: pa.Array, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all rows, end to end, and where each row's begin."""
    g = grams(hash_words(texts), size, short=True)
    row = np.repeat(np.arange(len(g.bounds) - 1), np.diff(g.bounds))
    order = np.lexsort((g.hashes, row))
    h, r = g.hashes[order], row[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
    return h[fresh], np.searchsorted(r[fresh], np.arange(len(g.bounds)))


def signatures(h: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """MinHash values, a row for each set that is not empty."""
    begins = bounds[:-1][np.diff(bounds) > 0]
    low, high = h.astype(np.uint32), (h >> np.uint64(32)).astype(np.uint32)
    out = np.empty((len(begins), HASHES), np.uint32)
    for k in range(HASHES):
        out[:, k] = np.minimum.reduceat(low * _A[k] + high * _B[k], begins)
    return out


def _describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for part in slices(b, 1, 4 << 20):
            h, bounds = shingle_sets(part.column(1))
            sizes = np.diff(bounds)
            full = sizes > 0
            names = ["id", "n", "s1", "s2", "keys", "sig"]
            n = len(sizes)
            s1, s2 = np.zeros(n, np.int64), np.zeros(n, np.int64)
            keys, sigs = [None] * n, [None] * n
            if full.any():
                begins = bounds[:-1][full]
                for out, salt in ((s1, 0x2545F4914F6CDD1D), (s2, 0x27D4EB2F165667C5)):
                    out[full] = np.add.reduceat(mix(h ^ np.uint64(salt)), begins).view(np.int64)
                m = signatures(h, bounds)
                first = m[:, 0::DEPTH].astype(np.uint64) << np.uint64(32) | m[:, 1::DEPTH]
                tree_keys = mix(first + np.arange(TREES, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)
                short = (m * np.uint32(0x9E3779B1) >> np.uint32(24)).astype(np.uint8)
                for i, r in enumerate(np.flatnonzero(full)):
                    keys[r], sigs[r] = tree_keys[i], short[i].tobytes()
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(s1), pa.array(s2), pa.array(keys, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], names)


def _edges_of(ids: np.ndarray, n: np.ndarray, sig: np.ndarray) -> Iterator[tuple[int, int]]:
    """A region's strongest links that join its texts where estimates allow (Prim's spanning forest)."""
    m = len(ids)
    best, via, out = np.full(m, -1, np.int32), np.zeros(m, np.int64), np.zeros(m, bool)
    at = 0
    for _ in range(m):
        out[at] = True
        agree = (sig == sig[at]).sum(1, dtype=np.int32)
        agree[(PERCENT * np.maximum(n, n[at]) > 100 * np.minimum(n, n[at])) | (agree < AGREE)] = -1
        better = agree > best
        best[better], via[better] = agree[better], at
        rest = np.where(out, -2, best)
        at = int(rest.argmax())
        if rest[at] == -2:
            return
        if rest[at] >= AGREE:
            yield int(ids[at]), int(ids[via[at]])


def _rivals(n: np.ndarray, sig: np.ndarray, group: np.ndarray, i: int) -> np.ndarray:
    """Places of a region's texts of other groups that may be linked with text i."""
    agree = (sig == sig[i]).sum(1, dtype=np.int32)
    return np.flatnonzero((agree >= AGREE) & (group != group[i]) & (PERCENT * np.maximum(n, n[i]) <= 100 * np.minimum(n, n[i])))


def _bridges(ids: np.ndarray, n: np.ndarray, sig: np.ndarray, group: np.ndarray, items: list[np.ndarray]) -> Iterator[tuple[int, int]]:
    """Links on full sets between a region's groups, until no link is left that would join two of them."""
    group = group.copy()
    names, counts = np.unique(group, return_counts=True)
    main = names[counts.argmax()]
    for i in range(len(ids)):
        if group[i] == main:
            continue  # met from the other side
        near = _rivals(n, sig, group, i)
        if not len(near):
            continue
        parts = [items[j] for j in near]
        all_items = np.concatenate(parts)
        at = np.searchsorted(items[i], all_items)
        at[at == len(items[i])] = 0
        begins = np.cumsum([0, *map(len, parts[:-1])])
        shared = np.add.reduceat((items[i][at] == all_items).astype(np.int64), begins)
        for j in near[100 * shared >= PERCENT * (n[i] + n[near] - shared)]:
            if group[j] != group[i]:
                yield int(ids[i]), int(ids[j])
                old, new = sorted((group[i], group[j]), key=lambda g: g == main)
                group[group == old] = new


def _by_region(work, schema: pa.Schema):
    """Runs ``work(table)`` on whole regions: some at a time, from rows that are sorted by key.

    ``work`` gets the rows, and where each region begins and ends; it gives tuples of the schema."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in chain(batches, [None]):
            if b is not None:
                if b.num_rows == 0:
                    continue
                held.append(b)
                if sum(x.num_rows for x in held) < 8192 and len(held) < 64:
                    continue
            if not held:
                continue
            t = pa.Table.from_batches(held).combine_chunks()
            key = t["key"].to_numpy()
            cut = len(key)
            if b is not None:  # the last region may go on
                other = np.flatnonzero(key != key[-1])
                cut = int(other[-1]) + 1 if len(other) else 0
            if cut == 0:
                continue
            part, key = t.slice(0, cut).combine_chunks(), key[:cut]
            held = t.slice(cut).to_batches()
            begins = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            found = sorted(set(work(part, begins, np.concatenate([begins[1:], [cut]]))))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*found), schema)], schema.names)

    return run


def _columns(t: pa.Table, *names: str) -> list[np.ndarray]:
    sig = np.frombuffer(b"".join(t["sig"].to_pylist()), np.uint8).reshape(-1, HASHES)
    return [sig, *(t[c].to_numpy() for c in names)]


def _ordered(a: int, b: int) -> tuple[int, int]:
    return (a, b) if a < b else (b, a)


def _strongest(t: pa.Table, begins: np.ndarray, ends: np.ndarray) -> Iterator[tuple[int, int]]:
    sig, ids, n = _columns(t, "id", "n")
    two = begins[ends - begins == 2]
    agree = (sig[two] == sig[two + 1]).sum(1)
    good = two[(agree >= AGREE) & (PERCENT * np.maximum(n[two], n[two + 1]) <= 100 * np.minimum(n[two], n[two + 1]))]
    yield from map(_ordered, ids[good].tolist(), ids[good + 1].tolist())
    for a, z in zip(begins, ends):
        if z - a > 2:
            yield from (_ordered(*p) for p in _edges_of(ids[a:z], n[a:z], sig[a:z]))


def _undecided(t: pa.Table, begins: np.ndarray, ends: np.ndarray) -> Iterator[tuple[int, int]]:
    """key and id of the texts that may have a link to another group of their region."""
    sig, key, ids, n, group = _columns(t, "key", "id", "n", "group")
    for a, z in zip(begins, ends):
        names, counts = np.unique(group[a:z], return_counts=True)
        if len(names) > 1:
            touched = np.zeros(z - a, bool)
            for i in np.flatnonzero(group[a:z] != names[counts.argmax()]):
                near = _rivals(n[a:z], sig[a:z], group[a:z], i)
                touched[near] = True
                touched[i] |= len(near) > 0
            yield from ((int(key[a]), int(x)) for x in ids[a:z][touched])


def _decided(t: pa.Table, begins: np.ndarray, ends: np.ndarray) -> Iterator[tuple[int, int]]:
    sig, ids, n, group = _columns(t, "id", "n", "group")
    for a, z in zip(begins, ends):
        items = [np.frombuffer(x.as_py(), np.uint64) for x in t["items"].slice(a, z - a)]
        yield from (_ordered(*p) for p in _bridges(ids[a:z], n[a:z], sig[a:z], group[a:z], items))


_PAIR = pa.schema([("a", pa.int64()), ("b", pa.int64())])
_PLACE = pa.schema([("key", pa.int64()), ("id", pa.int64())])


def _regionwise(rows: DataFrame, work, schema: pa.Schema) -> DataFrame:
    """``rows`` has to be stored: a repartition straight after a join may be dropped, and the join then run by broadcast."""
    kind = ", ".join(f"{n} long" for n in schema.names)
    return rows.repartition("key").sortWithinPartitions("key", "id").mapInArrow(lean(_by_region(work, schema)), kind).distinct()


def _regions(nodes: DataFrame, folder: str) -> tuple[DataFrame, DataFrame | None]:
    """key, id, whole of all regions with company, each of at most about REGION rows; key, id of those that were split.

    A region that is too large is dealt by a longer prefix of its own order.  Where even the whole
    label leaves too many, they are dealt into blocks, each with the region's first text.
    """
    large = None
    rows = nodes.select("id", F.posexplode("keys").alias("tree", "key"))
    done, more = [], rows
    for step, length in enumerate(LENGTHS):
        if step:
            start = F.col("tree") * DEPTH + 1 + LENGTHS[step - 1]
            signed = more.drop("size", "first").join(nodes.select("id", "sig"), "id")
            more = signed.withColumn("key", F.xxhash64("key", F.col("sig").substr(start, F.lit(length - LENGTHS[step - 1])))).drop("sig")
        sizes = more.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.min("id").alias("first")).where("size > 1")
        sized = stored(more.join(sizes, "key"), f"{folder}/{length}")
        done.append(sized.where(F.col("size") <= REGION).select("key", "id", F.lit(step == 0).alias("whole")))
        more = sized.where(F.col("size") > REGION)
        if more.isEmpty():
            break
        if step == 0:
            large = more.select("key", "id")
    else:
        blocks = F.ceil(F.col("size") / REGION).cast("int")
        leaders = more.where("id = first").withColumn("block", F.explode(F.sequence(F.lit(0), blocks - 1)))
        dealt = more.where("id != first").withColumn("block", F.pmod(F.xxhash64("id"), blocks).cast("int")).unionByName(leaders)
        done.append(dealt.select(F.xxhash64("key", "block").alias("key"), "id", F.lit(False).alias("whole")))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out, large


def _paired(large: DataFrame, groups: DataFrame, nodes: DataFrame, folder: str) -> DataFrame:
    """key, id, n, sig, group of regions that are too large, dealt so that all texts of different groups meet.

    Of two such texts one at least is outside the region's largest group: blocks of those outside meet
    blocks of all texts, about REGION rows at a time.
    """
    placed = stored(large.join(groups.select("id", "component"), "id", "left").select("key", "id", F.coalesce("component", "id").alias("group")), f"{folder}/placed")
    sizes = placed.groupBy("key", "group").agg(F.count(F.lit(1)).alias("size"))
    # At most a row for REGION texts of an order, which grows with the texts.
    mixed = sizes.groupBy("key").agg(F.max_by("group", F.struct("size", "group")).alias("main"), F.sum("size").alias("size"), F.max("size").alias("most")).where("most < size")
    mixed = stored(mixed, f"{folder}/sizes")
    mixed = F.broadcast(mixed) if mixed.count() <= BROADCAST_IDS // 4 else mixed
    half = REGION // 2
    rows = placed.join(mixed, "key").join(nodes.select("id", "n", "sig"), "id")
    rows = rows.withColumn("blocks", F.ceil(F.col("size") / half).cast("int")).withColumn("outside", F.ceil((F.col("size") - F.col("most")) / half).cast("int"))
    rows = stored(rows, f"{folder}/mixed")

    def dealt(own: str, own_blocks: str, other: str, other_blocks: str) -> list:
        return [F.pmod(F.xxhash64("id", F.lit(own)), F.col(own_blocks)).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.col(other_blocks) - 1)).alias(other)]

    kept = ("key", "id", "n", "sig", "group")
    out = rows.where("group != main").select(*kept, *dealt("p", "outside", "q", "blocks")).unionByName(rows.select(*kept, *dealt("q", "blocks", "p", "outside")))
    return out.select(F.xxhash64("key", "p", "q").alias("key"), "id", "n", "sig", "group").dropDuplicates(["key", "id"])


def _full_sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """id, items: the full shingle sets of the wanted ids, as sorted 8-byte numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in slices(b, 1):
                h, bounds = shingle_sets(part.column(1))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([h[i:j].tobytes() for i, j in zip(bounds[:-1], bounds[1:])], pa.binary())], ["id", "items"])

    wanted = F.broadcast(wanted) if wanted.count() <= BROADCAST_IDS else wanted
    return docs.join(wanted, "id", "left_semi").mapInArrow(lean(run), "id long, items binary")


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        good = []
        for x, y in zip(b.column(2), b.column(3)):
            p, q = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
            both = np.concatenate([p, q])
            both.sort()
            shared = int((both[1:] == both[:-1]).sum())
            good.append(100 * shared >= PERCENT * (len(p) + len(q) - shared))
        keep = pa.array(good, pa.bool_())
        yield pa.RecordBatch.from_arrays([b.column(0).filter(keep), b.column(1).filter(keep)], ["a", "b"])


def confirmed(pairs: DataFrame, docs: DataFrame, folder: str) -> DataFrame:
    """The pairs a, b whose full sets reach the threshold."""
    wanted = stored(pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct(), f"{folder}/wanted")
    sets = stored(_full_sets(docs, wanted), f"{folder}/sets")
    left = sets.select(F.col("id").alias("a"), F.col("items").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("items").alias("y"))
    rows = pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y")
    return stored(rows.mapInArrow(lean(_confirm), "a long, b long").distinct(), f"{folder}/links")


def components(links: DataFrame, folder: str) -> DataFrame:
    """id, component (smallest id reachable) of every id that has a link.

    Alternates two steps until the edges are stars: every node points its larger neighbours at its
    smallest neighbour, then every node points its smaller neighbours at the smallest.  Nodes are
    met by joins and pre-aggregated minima; each step is stored.
    """
    edges = stored(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct(), f"{folder}/0")

    def stars() -> bool:
        """Every node has one edge, or is where edges end."""
        ends = edges.groupBy("u").agg(F.count(F.lit(1)).alias("n"), F.lit(0).alias("end")).union(edges.select("v").distinct().select(F.col("v").alias("u"), F.lit(0).cast("long"), F.lit(1)))
        return ends.groupBy("u").agg(F.sum("n").alias("n"), F.max("end").alias("end")).where("n > 1 OR (n > 0 AND end = 1)").isEmpty()

    k = 0
    while not stars():
        k += 1
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        large = stored(large, f"{folder}/{k}l")
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        met = large.join(low, "u")
        small = met.select(F.col("v").alias("u"), F.col("m").alias("v")).union(met.select("u", F.col("m").alias("v"))).where("u != v").distinct()
        edges = stored(small, f"{folder}/{k}s")
    found = edges.select(F.col("u").alias("id"), F.col("v").alias("component"))
    return found.union(found.select("component", "component").distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, n_shingles, component_id.

    component_id is the smallest id reachable over links; without words, text or id a row is alone
    (a null id stays null).
    """
    spark = docs.sparkSession
    folder = shared_folder(spark, "near")
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    described = stored(texts.mapInArrow(lean(_describe), "id long, n long, s1 long, s2 long, keys array<bigint>, sig binary"), f"{folder}/described")
    named = described.where("n > 0 and id is not null")
    classes = named.groupBy("s1", "s2", "n").agg(F.min("id").alias("rep"))
    member = stored(named.select("id", "s1", "s2", "n").join(classes, ["s1", "s2", "n"]).select("id", "rep"), f"{folder}/member")
    reps = member.where("id = rep").select("id").distinct()
    nodes = named.join(reps, "id", "left_semi").select("id", "n", "keys", "sig").dropDuplicates(["id"])
    first, large = _regions(nodes, f"{folder}/regions")
    regions = stored(first.join(nodes.select("id", "n", "sig"), "id"), f"{folder}/regions/all")
    known = texts.where("id is not null and text is not null")

    pairs = stored(_regionwise(regions, _strongest, _PAIR), f"{folder}/pairs")
    links = confirmed(pairs, known, f"{folder}/first")
    # Rows of one id that differ in text are one node: their sets' classes belong together.
    split = member.where("id != rep").select(F.col("id").alias("a"), F.col("rep").alias("b"))
    groups = stored(components(links, f"{folder}/groups1"), f"{folder}/grouped1")
    placed = regions.where("whole").join(groups.select("id", "component"), "id", "left").select("key", "id", "n", "sig", F.coalesce("component", "id").alias("group"))
    mixed = placed.groupBy("key").agg(F.min("group").alias("lo"), F.max("group").alias("hi")).where("lo != hi").select("key")
    again = placed.join(mixed, "key", "left_semi")
    if large is not None:
        again = again.unionByName(_paired(large, groups, nodes, f"{folder}/regions/large"))
    again = stored(again, f"{folder}/regions/mixed")
    more = spark.createDataFrame([], "a long, b long")
    open_ids = stored(_regionwise(again, _undecided, _PLACE), f"{folder}/undecided")
    if not open_ids.isEmpty():
        sets = stored(_full_sets(known, stored(open_ids.select("id").distinct(), f"{folder}/second/wanted")), f"{folder}/second/sets").dropDuplicates(["id"])
        full = stored(open_ids.join(again, ["key", "id"]).join(sets, "id"), f"{folder}/regions/full")
        more = stored(_regionwise(full, _decided, _PAIR), f"{folder}/second/links")
    repeated = named.groupBy("id").agg(F.countDistinct("s1", "s2").alias("sets")).where("sets > 1").select(F.col("id").alias("a"))
    more = stored(more.union(split.join(repeated, "a", "left_semi")), f"{folder}/more")
    if not more.isEmpty():
        # Groups that the second look joins: components of the groups themselves.
        def named_by(side: str) -> DataFrame:
            return groups.select(F.col("id").alias(side), F.col("component").alias(f"{side}_group"))

        met = more.join(named_by("a"), "a", "left").join(named_by("b"), "b", "left").select(F.coalesce("a_group", "a").alias("a"), F.coalesce("b_group", "b").alias("b"))
        joined = stored(components(met, f"{folder}/groups2"), f"{folder}/grouped2").select(F.col("id").alias("component"), F.col("component").alias("whole"))
        known_groups = groups.join(joined, "component", "left").select("id", F.coalesce("whole", "component").alias("component"))
        groups = known_groups.union(joined.select("component", "whole").join(groups.select(F.col("id").alias("component")), "component", "left_anti"))
    final = member.join(groups.select(F.col("id").alias("rep"), "component"), "rep", "left").groupBy("id").agg(F.min(F.least(F.coalesce("component", "rep"), "rep")).alias("component"))
    rows = described.select("id", "n")
    return rows.join(final, "id", "left").select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component", "id").alias("component_id"))


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose id is the smallest of its group."""
    found = near_duplicates(docs, id_col, text_col)
    later = found.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col)).distinct()
    return docs.join(later, id_col, "left_anti").select(docs.columns)
