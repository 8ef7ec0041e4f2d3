"""N-gram Jaccard join over a MinHash LSH forest.

Documents are sets of five-word shingles (a text of fewer words, but not none,
is one shingle). Equal sets are one class from the start. Each distinct set has
a path of ``DEPTH`` minhashes in each of ``TREES`` prefix tries. All paths start
at full length. A set's paths are shortened one after the other, those first
whose surroundings in the sorted trie are the emptiest, each as far as a pair
at the threshold needs (``FLOOR`` hashes), until the chance that such a pair
shares no searched prefix is under ``1 - TARGET_RECALL``; the paths in its most
crowded places stay whole. Two sets meet in a tree when their common prefix
reaches the shorter of their two searched lengths.

A pair goes on only from the first tree in which it meets, and only if its
paths' hashes and set sizes leave the threshold possible; its Jaccard similarity
is then computed from the whole sets.

Tries are sorted runs of equal prefixes. Runs of more than ``BLOCK`` sets are
split into blocks, and each pair of blocks is one unit of work: no task holds an
unbounded run and no run is capped. Pairs are never rows: a unit gives each
member's number of links and the least member that its links lead to, which is
all that classes need.

Null and empty texts have no shingles; they link with nothing and are classes
of their own. Repeated rows and equal texts belong to one class. The links of a
document are the other documents at the threshold or above, copies included.
Rows without a doc_id link like others; a class's id is its least doc_id that is
not null, if it has one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

WORDS, THRESHOLD = 5, 0.8
TREES, DEPTH = 16, 8
TARGET_RECALL = 0.9999
BLOCK = 256
HASHES = TREES * DEPTH
#: Bytes of one hash of a path, and of a path.
STEP = 2
PATH = STEP * DEPTH


def floor_length(threshold: float = THRESHOLD, recall: float = TARGET_RECALL) -> int:
    """Longest prefix at which a pair at the threshold still meets with the target recall if all trees are searched at it."""
    for length in range(DEPTH, 1, -1):
        if 1 - (1 - threshold**length) ** TREES >= recall:
            return length
    return 1


def trees_to_shorten(threshold: float = THRESHOLD, recall: float = TARGET_RECALL) -> int:
    """How many paths of a set come down to the floor, the others whole, until the target recall holds."""
    floor = floor_length(threshold, recall)
    for n in range(TREES + 1):
        if 1 - (1 - threshold**floor) ** n * (1 - threshold**DEPTH) ** (TREES - n) >= recall:
            return n
    return TREES


def least_agreement(threshold: float = THRESHOLD) -> int:
    """Hashes that a pair at the threshold agrees on, less five standard deviations."""
    return int(HASHES * threshold - 5 * (HASHES * threshold * (1 - threshold)) ** 0.5)


def shingles(raw: bytes, k: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's word k-grams."""
    words = common.words_of(raw)
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - k + 1)
    return np.unique(np.fromiter((xxhash.xxh3_64_intdigest(b" ".join(words[i : i + k])) for i in range(n)), np.uint64, n))


def _family() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(1, 2**63, HASHES, dtype=np.uint64) * 2 + 1, rng.integers(0, 2**63, HASHES, dtype=np.uint64)


def signature(hashes: np.ndarray, family: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    a, b = family
    out = np.full(HASHES, 2**64 - 1, np.uint64)
    for i in range(0, len(hashes), 4096):
        mixed = hashes[i : i + 4096, None] * a + b
        np.minimum(out, mixed.min(0), out=out)
    return (out >> np.uint64(32)).astype(np.uint32)


SIGNED = "set_id binary, n int, paths binary"


def sign(docs: DataFrame) -> DataFrame:
    """doc_id, digest and size of the shingle set, and its paths in all trees laid end to end, most significant bytes first so that they sort."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        family = _family()
        for batch in common.small(batches):
            ids, sizes, paths = [], [], []
            for raw in common.raw_texts(batch):
                found = shingles(raw)
                ids.append(xxhash.xxh3_128_digest(found.tobytes()))
                sizes.append(len(found))
                paths.append((signature(found, family) & 0xFFFF).astype(">u2").tobytes() if len(found) else b"")
            arrays = [batch.column(batch.schema.get_field_index("doc_id")), pa.array(ids, pa.binary()), pa.array(sizes, pa.int32()), pa.array(paths, pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "set_id", "n", "paths"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, {SIGNED}")


def prefix(tree: Column, length: int) -> Column:
    """The first hashes of a set's path in a tree."""
    return F.substring(F.col("paths"), tree * PATH + 1, F.lit(STEP * length))


def searched_lengths(sets: DataFrame, threshold: float = THRESHOLD) -> tuple[DataFrame, DataFrame]:
    """(set, whole) and (set, tree, at, members): which trees a set searches at full length, a bit each, and its places that it shares.

    Trees are shortened in the order of the sets that share the floor prefix; a
    tree in which the set is alone there costs nothing and comes first.
    """
    floor, shorten = floor_length(threshold), trees_to_shorten(threshold)
    trees = F.explode(F.sequence(F.lit(0), F.lit(TREES - 1))).alias("tree")
    nodes = sets.select("set", "paths", trees).select("set", "tree", prefix(F.col("tree"), floor).alias("at"))
    crowds = nodes.groupBy("tree", "at").agg(F.count(F.lit(1)).alias("members")).filter("members > 1")
    shared = nodes.join(crowds, ["tree", "at"])
    # crowded last; a set that shares fewer places than may stay whole searches all of them whole
    ranked = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("members")).alias("m"), "tree"))), 1, TREES - shorten)
    bits = F.aggregate(ranked, F.lit(0), lambda s, x: s.bitwiseOR(F.call_function("shiftleft", F.lit(1), x["tree"])))
    return shared.groupBy("set").agg(bits.alias("whole")), shared


class Unit:
    """Members of one run of a trie, or of two of its blocks: who may link with whom.

    A pair counts in the first tree in which it meets, so once in all units.
    """

    def __init__(self, tree: int, length: int, low: int, high: int, rows: list[tuple], threshold: float) -> None:
        self.tree, self.length, self.one, self.threshold = tree, length, low == high, threshold
        self.block = np.array([r[0] for r in rows])
        self.ids = np.array([r[1] for r in rows])
        self.sizes = np.array([r[2] for r in rows])
        self.paths = np.frombuffer(b"".join([r[3] for r in rows]), np.uint16).reshape(-1, TREES, DEPTH)
        whole = np.array([r[4] for r in rows])
        self.lengths = np.where(whole[:, None] >> np.arange(TREES) & 1, DEPTH, floor_length(threshold))
        self.least = least_agreement(threshold)
        self.low = low

    def partners(self) -> Iterator[tuple[int, np.ndarray]]:
        """(member, later members) that meet here first and that paths and sizes leave possible."""
        other = None if self.one else np.flatnonzero(self.block != self.low)
        earlier = np.arange(self.tree + 1)
        for i in range(len(self.ids)) if self.one else np.flatnonzero(self.block == self.low).tolist():
            near = np.arange(i + 1, len(self.ids)) if self.one else other
            near = near[np.minimum(self.sizes[i], self.sizes[near]) >= self.threshold * np.maximum(self.sizes[i], self.sizes[near])]
            if not near.size:
                continue
            same = self.paths[i] == self.paths[near]
            able = same.sum((1, 2)) >= self.least
            near, same = near[able], same[able]
            if not near.size:
                continue
            # the common prefix in this tree and those before, against the shorter searched length
            shared = np.logical_and.accumulate(same[:, earlier], axis=2).sum(2)
            met = shared >= np.minimum(self.lengths[i, earlier], self.lengths[near][:, earlier])
            here = np.minimum(self.lengths[i, self.tree], self.lengths[near, self.tree]) == self.length
            near = near[here & met[:, -1] & ~met[:, :-1].any(1)]
            if near.size:
                yield i, near


def _units(batches: Iterator[pa.RecordBatch], make):
    """Runs of rows that share UNIT, passed on as lists; the next list starts with the next unit."""
    key, held = None, []
    for batch in common.small(batches):
        for tree, length, at, low, high, *row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if key != (tree, length, at, low, high):
                if len(held) > 1:
                    yield from make(key, held)
                key, held = (tree, length, at, low, high), []
            held.append(row)
    if len(held) > 1:
        yield from make(key, held)


def _meet(threshold: float):
    """Members of each unit that have a possible partner there: rows as many as members, never as pairs."""

    def make(key, held) -> Iterator[pa.RecordBatch]:
        tree, length, at, low, high = key
        unit, some = Unit(tree, length, low, high, held, threshold), set()
        for i, near in unit.partners():
            some.add(i)
            some.update(near.tolist())
        if some:
            rows = sorted(some)
            n = len(rows)
            arrays = [pa.array([tree] * n, pa.int32()), pa.array([length] * n, pa.int32()), pa.array([at] * n, pa.binary()), pa.array([low] * n, pa.int32()), pa.array([high] * n, pa.int32())]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(unit.block[rows].astype(np.int32)), pa.array(unit.ids[rows])], names=[*UNIT, "block", "set"])

    def run(batches):
        common.fresh_worker()
        return _units(batches, make)

    return run


def _link(threshold: float):
    """For each member of a unit, its links there (copies counted) and the least member that links lead to.

    The pairs of the signatures are checked on whole sets: one member's shingles are
    flagged in the unit's dictionary, and its partners' flags are summed.
    """

    def make(key, held) -> Iterator[pa.RecordBatch]:
        tree, length, _, low, high = key
        unit = Unit(tree, length, low, high, held, threshold)
        copies, sets = np.array([r[5] for r in held]), [np.frombuffer(r[6], np.uint64) for r in held]
        words, codes = np.unique(np.concatenate(sets), return_inverse=True)
        ends = np.cumsum([len(x) for x in sets])
        codes = np.split(codes, ends[:-1])
        flags, links, root = np.zeros(len(words), np.int64), np.zeros(len(sets), np.int64), list(range(len(sets)))

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for i, near in unit.partners():
            flags[codes[i]] = 1
            theirs = [codes[j] for j in near]
            sizes = unit.sizes[near]
            both = np.add.reduceat(flags[np.concatenate(theirs)], np.cumsum(sizes) - sizes)
            flags[codes[i]] = 0
            for j in near[both >= threshold * (unit.sizes[i] + sizes - both) - 1e-9].tolist():
                links[i] += copies[j]
                links[j] += copies[i]
                x, y = find(i), find(j)
                if x != y:
                    x, y = (x, y) if unit.ids[x] < unit.ids[y] else (y, x)
                    root[y] = x
        rows = np.flatnonzero(links)
        if len(rows):
            least = unit.ids[[find(i) for i in rows.tolist()]]
            yield pa.RecordBatch.from_arrays([pa.array(unit.ids[rows]), pa.array(links[rows]), pa.array(least)], names=["set", "links", "least"])

    def run(batches):
        common.fresh_worker()
        return _units(batches, make)

    return run


UNIT = ["tree", "length", "at", "low", "high"]


def meetings(sets: DataFrame, places: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """UNIT, block and set: members of prefix runs, dealt into pairs of blocks, with a possible partner.

    ``sets`` has set (long), n, paths and whole; ``places`` is that of ``searched_lengths``.
    In a run of floor prefixes, sets that search it come in the first blocks and meet
    all; sets that search this tree at full length meet only them there, and each
    other in the run of their whole path.
    """
    floor = floor_length(threshold)
    own = places.join(sets.select("set", "whole", "paths"), "set").withColumn("searched", F.call_function("shiftright", "whole", F.col("tree")).bitwiseAND(1) == 0)
    runs = own.groupBy("tree", "at").agg(F.count_if("searched").alias("short"), F.count_if(~F.col("searched")).alias("long")).filter("short > 0")
    first, rest = F.ceil(F.col("short") / BLOCK).cast("int"), F.ceil(F.col("long") / BLOCK).cast("int")
    dealt = own.join(runs, ["tree", "at"]).withColumns({"first": first, "rest": rest})
    block = F.when(F.col("searched"), F.pmod(F.xxhash64("set"), F.col("first"))).otherwise(F.col("first") + F.pmod(F.xxhash64("set"), F.greatest("rest", F.lit(1)))).cast("int")
    dealt = dealt.withColumn("block", block).select("tree", F.lit(floor).alias("length"), "at", "set", "block", F.when(F.col("searched"), F.col("first") + F.col("rest")).otherwise(F.col("first")).alias("reach"))
    whole = own.filter(~F.col("searched")).select("tree", F.lit(DEPTH).alias("length"), prefix(F.col("tree"), DEPTH).alias("at"), "set")
    crowds = whole.groupBy("tree", "at").agg(F.count(F.lit(1)).alias("members")).filter("members > 1")
    deep = whole.join(crowds, ["tree", "at"]).withColumn("reach", F.ceil(F.col("members") / BLOCK).cast("int"))
    deep = deep.withColumn("block", F.pmod(F.xxhash64("set"), F.col("reach")).cast("int")).select(*dealt.columns)
    # a member of block i works in the pairs (i, j) and (j, i) of blocks; low <= high names the pair
    units = dealt.unionByName(deep).select("tree", "length", "at", "set", "block", F.explode(F.sequence(F.lit(0), F.col("reach") - 1)).alias("other"))
    units = units.select("tree", "length", "at", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "set")
    full = units.join(sets.select("set", "n", "paths", "whole"), "set").select(*UNIT, "block", "set", "n", "paths", "whole")
    ready = full.repartition(*UNIT).sortWithinPartitions(*UNIT)
    return ready.mapInArrow(_meet(threshold), "tree int, length int, at binary, low int, high int, block int, set long")


def links(docs: DataFrame, sets: DataFrame, met: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(set, links, least): links of each set to other sets, counted on the whole shingle sets, unit by unit."""
    needed = met.select("set").distinct()
    spots = sets.join(needed, "set").select("set", "doc_id", "set_id")
    texts = docs.select("doc_id", "text").join(spots, "doc_id").select("set", "set_id", "text")

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in common.small(batches):
            found = [shingles(raw).tobytes() for raw in common.raw_texts(batch)]
            # rows that share a doc_id but not the text are told apart by the set's digest
            mine = [xxhash.xxh3_128_digest(x) == y for x, y in zip(found, batch.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.binary())], names=["set", "hashes"]).filter(pa.array(mine, pa.bool_()))

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in common.small(batches):
            found = [shingles(raw).tobytes() for raw in common.raw_texts(batch)]
            yield pa.RecordBatch.from_arrays([pa.array([xxhash.xxh3_128_digest(x) for x in found], pa.binary()), pa.array(found, pa.binary())], names=["set_id", "hashes"])

    # sets that only rows without a doc_id hold meet their texts by digest: an equal null would pair all such rows
    unnamed = docs.filter("doc_id IS NULL").select("text").mapInArrow(digests, "set_id binary, hashes binary")
    unnamed = unnamed.join(spots.filter("doc_id IS NULL").select("set", "set_id"), "set_id").select("set", "hashes")
    hashes = common.persist_shared(texts.mapInArrow(whole, "set long, hashes binary").unionByName(unnamed).dropDuplicates(["set"]))
    full = met.join(sets.select("set", "n", "paths", "whole", "copies"), "set").join(hashes, "set")
    ready = full.select(*UNIT, "block", "set", "n", "paths", "whole", "copies", "hashes").repartition(*UNIT).sortWithinPartitions(*UNIT)
    return ready.mapInArrow(_link(threshold), "set long, links long, least long")


def components(edges: DataFrame) -> DataFrame:
    """(set, class): the least set that each linked set reaches.

    Each round hooks every set to the least label among itself and its
    neighbours and then follows labels one step further, until nothing moves;
    the state of each round is a written table, so a lost executor costs a round.
    """
    both = common.persist_shared(edges.select(F.col("a").alias("set"), F.col("b").alias("to")).unionByName(edges.select(F.col("b").alias("set"), F.col("a").alias("to"))))
    labels = common.persist_shared(both.groupBy("set").agg(F.min("to").alias("near")).select("set", F.least("set", "near").alias("class")))
    while True:
        told = both.join(labels.select(F.col("set").alias("to"), "class"), "to").groupBy("set").agg(F.min("class").alias("near"))
        hooked = labels.join(told, "set").select("set", F.col("class").alias("old"), F.least("class", "near").alias("class"))
        jump = labels.select(F.col("set").alias("class"), F.col("class").alias("further"))
        after = common.persist_shared(hooked.join(jump, "class", "left").select("set", "old", F.least("class", F.coalesce("further", "class")).alias("class")))
        if after.filter("class <> old").isEmpty():
            return after.select("set", "class")
        labels = after.select("set", "class")


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, class_id, n_links) for every row: class_id is the least doc_id of the class."""
    signed = common.persist_shared(sign(docs))
    # doc_id alone cannot name a set: rows may repeat it with other texts
    grouped = signed.filter("n > 0").groupBy("set_id").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"), F.first("n").alias("n"), F.first("paths").alias("paths"))
    sets = common.persist_shared(grouped.withColumn("set", F.xxhash64("set_id")))
    whole, places = searched_lengths(sets, threshold)
    places = common.persist_shared(places.select("set", "tree", "at"))
    shared_sets = common.persist_shared(sets.join(whole, "set"))
    met = common.persist_shared(meetings(shared_sets, places, threshold))
    found = common.persist_shared(links(docs, shared_sets, met, threshold))
    outer = found.groupBy("set").agg(F.sum("links").alias("outer_links"))
    classes = components(found.select(F.col("set").alias("a"), F.col("least").alias("b")).filter("a <> b").distinct())
    joined = sets.select("set", "set_id", "doc_id", "copies").join(outer, "set", "left").join(classes, "set", "left").withColumn("class", F.coalesce("class", "set"))
    named = joined.groupBy("class").agg(F.min("doc_id").alias("class_id"))
    whole = joined.join(named, "class").select("set_id", "class_id", (F.col("copies") - 1 + F.coalesce("outer_links", F.lit(0))).alias("n_links"))
    linked = signed.filter("n > 0").select("doc_id", "set_id").join(whole, "set_id").select("doc_id", "class_id", "n_links")
    alone = signed.filter("n = 0").select("doc_id", F.col("doc_id").alias("class_id"), F.lit(0).cast("long").alias("n_links"))
    return linked.unionByName(alone)


def query(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(common.load(spark, sf_dir, "documents").select("doc_id", "text"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w FROM documents),
s AS (SELECT DISTINCT doc_id, hash(array_to_string(w[i:i + 4], ' ')) g FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 4) + 1)) i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) n FROM s GROUP BY 1),
l AS (SELECT a, b FROM (SELECT x.doc_id a, y.doc_id b, count(*) c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2) JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 10 * c >= 8 * (p.n + q.n - c)),
r AS (SELECT doc_id id, doc_id root FROM w UNION SELECT l.b, r.root FROM r JOIN l ON l.a = r.id)
SELECT w.doc_id, (SELECT min(root) FROM r WHERE r.id = w.doc_id) class_id, (SELECT count(*) FROM l WHERE l.a = w.doc_id) n_links FROM w
"""
