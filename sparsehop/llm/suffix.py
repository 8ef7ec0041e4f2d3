"""Repeated passages by enhanced suffix arrays and common-prefix interval trees.

A byte goes if a ``WINDOW``-byte string that also starts earlier covers it. To
find such strings without all pairs of documents or one array over the corpus:

1. Every window is led by an anchor: the place inside it whose ``GRAM``-byte
   hash is least. Equal windows have equal anchors at equal offsets, so equal
   strings meet under their anchor's hash. Neighbouring windows that share an
   anchor form a run; a run with its bytes is a context.
2. Runs are dealt by anchor and sorted, and a streaming scan folds equal
   contexts: the first stays as representative, the others are repeats of it as
   a whole. Anchors with one distinct context are finished.
3. The contexts of the other anchors form texts over which an enhanced suffix
   array (suffixes at the runs' window starts, with common-prefix lengths) is
   built. A stack scan yields its common-prefix intervals; those of WINDOW bytes
   or more whose members differ in the byte to the left (or begin their context)
   are maximal repeats, given with all occurrences. All but the first
   occurrence are removed.
4. An anchor with more than ``MOST_CONTEXTS`` distinct contexts is not put into
   one array: its windows become contexts of their own, keyed by their own hash,
   and take step 2 again, where equal windows fold and nothing is left over.

Removed spans of a document are united and cut from its bytes. Null and empty
texts have no bytes and no spans. Rows that are equal in doc_id and text are one
document and get equal results; rows that share a doc_id (null first) but not
the text are documents in the order of their texts' digests; so are documents
whose ids are not whole numbers, in the order of the ids.

``repeat_groups`` lists the groups themselves, with every occurrence.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WINDOW, GRAM = 100, 40
SPREAD = WINDOW - GRAM + 1
#: Distinct contexts of an anchor that one suffix array takes; anchors beyond go window by window.
MOST_CONTEXTS = 2_000
#: Bytes of text that are hashed at once, and of contexts that share one suffix array.
SLICE_BYTES, ARRAY_BYTES = 600_000, 500_000

RUN = "anchor bigint, c1 bigint, c2 bigint, doc bigint, start int, windows int"
FOUND = "kind int, doc bigint, start int, length int, anchor bigint"
REMOVED, CONTESTED, CROWDED = 0, 1, 2


class Hasher:
    """Two independent polynomial hashes of every substring, modulo 2**64, from prefix sums."""

    def __init__(self) -> None:
        rng = np.random.default_rng(7)
        self.tables = [rng.integers(1, 2**63, 256, dtype=np.uint64) * 2 + 1 for _ in range(2)]
        self.bases = [int(x) | 1 for x in rng.integers(2**40, 2**62, 2)]
        self.size = 0

    def _grow(self, n: int) -> None:
        if n <= self.size:
            return
        self.size, self.powers, self.inverses = n, [], []
        for base in self.bases:
            for where, b in ((self.powers, base), (self.inverses, pow(base, -1, 1 << 64))):
                p, have, step = np.ones(n, np.uint64), 1, b
                while have < n:  # doubling: powers beyond ``have`` are those before, times b**have
                    take = min(have, n - have)
                    p[have : have + take] = p[:take] * np.uint64(pow(b, have, 1 << 64))
                    have += take
                where.append(p)

    def prefix(self, data: np.ndarray, which: int) -> np.ndarray:
        self._grow(len(data) + 1)
        return np.concatenate([np.zeros(1, np.uint64), np.cumsum(self.tables[which][data] * self.powers[which][: len(data)], dtype=np.uint64)])

    def at(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray, which: int) -> np.ndarray:
        x = (prefix[end] - prefix[start]) * self.inverses[which][start]
        x ^= x >> np.uint64(31)
        x *= np.uint64(0x9E3779B97F4A7C15)
        return x ^ (x >> np.uint64(29))


def _least_places(h: np.ndarray, width: int) -> np.ndarray:
    """Place of the least value (the first of equals) in each stretch of ``width``, by doubling."""
    value, place, have = h, np.arange(len(h)), 1

    def merge(v, p, shift):
        w, q = v[shift:], p[shift:]
        n = len(w)
        right = w < v[:n]
        return np.where(right, w, v[:n]), np.where(right, q, p[:n])

    while have * 2 <= width:
        value, place = merge(value, place, have)
        have *= 2
    if have < width:
        value, place = merge(value, place, width - have)
    return place


def runs_of(data: np.ndarray, lengths: np.ndarray, hasher: Hasher):
    """Runs of all texts of a slice laid end to end: text, start, windows, anchor hash, two context hashes."""
    starts = np.cumsum(lengths) - lengths
    if len(data) < WINDOW:
        return (np.zeros(0, np.int64),) * 6
    one, two = hasher.prefix(data, 0), hasher.prefix(data, 1)
    at = np.arange(len(data) - GRAM + 1)
    lead = _least_places(hasher.at(one, at, at + GRAM, 0), SPREAD)
    owner = np.repeat(np.arange(len(lengths)), lengths)
    n = len(data) - WINDOW + 1
    inside = owner[:n] == owner[WINDOW - 1 :]
    lead, owner = lead[:n], owner[:n]
    new = inside.copy()
    new[1:] &= ~(inside[:-1] & (lead[1:] == lead[:-1]) & (owner[1:] == owner[:-1]))
    begin = np.flatnonzero(new)
    # windows that cross a text's end belong to no run: count those inside up to the next beginning
    ends = np.append(begin[1:], n)
    total = np.concatenate([[0], np.cumsum(inside)])
    windows = total[ends] - total[begin]
    anchor = lead[begin]
    stop = begin + windows + WINDOW - 1
    key = hasher.at(one, anchor, anchor + GRAM, 0)
    offset = (anchor - begin).astype(np.uint64)
    c1 = hasher.at(one, begin, stop, 0) + offset * np.uint64(0xC2B2AE3D27D4EB4F)
    c2 = hasher.at(two, begin, stop, 1) ^ (windows.astype(np.uint64) * np.uint64(0x165667B19E3779F9))
    text = owner[begin]
    return text, begin - starts[text], windows, key.view(np.int64), c1.view(np.int64), c2.view(np.int64)


def _fold(keys: list[np.ndarray], doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of rows by (keys, doc, start), and which rows repeat the row before in all keys."""
    order = np.lexsort([start, doc, *keys[::-1]])
    same = np.ones(max(len(order) - 1, 0), bool)
    for k in keys:
        same &= k[order[1:]] == k[order[:-1]]
    return order, np.concatenate([[False], same])[: len(order)]


def _collect_runs(batches: Iterator[pa.RecordBatch], fold: bool = True) -> Iterator[pa.RecordBatch]:
    """Runs of (doc, text) rows; with ``fold``, a slice's own repeats are folded before they are sent anywhere."""
    common.fresh_worker()
    hasher = Hasher()
    for batch in common.small(batches):
        raws, docs = common.raw_texts(batch), np.array(batch.column(0).to_pylist(), np.int64)
        for a, b in common.slices([len(x) for x in raws], SLICE_BYTES):
            data = np.frombuffer(b"".join(raws[a:b]), np.uint8)
            text, start, windows, key, c1, c2 = runs_of(data, np.array([len(x) for x in raws[a:b]]), hasher)
            if not len(text):
                continue
            doc = docs[a:b][text]
            if not fold:
                yield _runs_batch(key, c1, c2, doc, start, windows)
                continue
            order, again = _fold([key, c1, c2], doc, start)
            # a repeat inside the slice is certain to have an earlier start: it needs its span alone
            gone, kept = order[again], order[~again]
            yield _runs_batch(key[kept], c1[kept], c2[kept], doc[kept], start[kept], windows[kept])
            if len(gone):
                spread = doc[gone] * 1000003 + start[gone] // 4096
                nothing = np.zeros(len(gone), np.int64)
                yield _runs_batch(spread, nothing, nothing, doc[gone], start[gone], -windows[gone])


def _runs_batch(key, c1, c2, doc, start, windows) -> pa.RecordBatch:
    arrays = [pa.array(np.asarray(x, np.int64)) for x in (key, c1, c2, doc)] + [pa.array(np.asarray(x, np.int32)) for x in (start, windows)]
    return pa.RecordBatch.from_arrays(arrays, names=["anchor", "c1", "c2", "doc", "start", "windows"])


def _scan_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Streaming scan of runs sorted by (anchor, context, doc, start): repeats, and contexts of contested anchors.

    State over batches is the last row and the waiting contexts of one anchor, at
    most MOST_CONTEXTS; an anchor with more is crowded from there on.
    """
    common.fresh_worker()
    anchor, context, waiting, crowded = None, None, [], False

    def out(kind, doc, start, length, key) -> pa.RecordBatch:
        n = len(doc)
        arrays = [pa.array(np.full(n, kind, np.int32)), pa.array(np.asarray(doc, np.int64)), pa.array(np.asarray(start, np.int32)), pa.array(np.asarray(length, np.int32)), pa.array(np.asarray(key, np.int64))]
        return pa.RecordBatch.from_arrays(arrays, names=["kind", "doc", "start", "length", "anchor"])

    for batch in batches:
        key, c1, c2, doc, start, windows = (batch.column(i).to_numpy() for i in range(6))
        if not len(key):
            continue
        known = windows < 0
        if known.any():
            yield out(REMOVED, doc[known], start[known], -windows[known] + WINDOW - 1, key[known])
            key, c1, c2, doc, start, windows = (x[~known] for x in (key, c1, c2, doc, start, windows))
            if not len(key):
                continue
        same_key = np.concatenate([[key[0] == anchor if anchor is not None else False], key[1:] == key[:-1]])
        same = same_key & np.concatenate([[(c1[0], c2[0]) == context], (c1[1:] == c1[:-1]) & (c2[1:] == c2[:-1])])
        if same.any():
            yield out(REMOVED, doc[same], start[same], windows[same] + WINDOW - 1, key[same])
        fresh = np.flatnonzero(~same)
        if len(fresh):
            # groups of distinct contexts: the first may go on from the batch before, the last stays open
            begins = np.flatnonzero(~same_key[fresh])
            edges = np.concatenate([[0], begins, [len(fresh)]])
            sizes = np.diff(edges)
            for g in np.flatnonzero((sizes > 1) | (np.arange(len(sizes)) == 0) | (np.arange(len(sizes)) == len(sizes) - 1)):
                rows = fresh[edges[g] : edges[g + 1]]
                if g > 0:
                    if len(waiting) > 1:
                        yield out(CONTESTED, *zip(*waiting, strict=True))
                    waiting, crowded = [], False
                items = [*zip(doc[rows].tolist(), start[rows].tolist(), (windows[rows] + WINDOW - 1).tolist(), key[rows].tolist(), strict=True)]
                if not crowded and len(waiting) + len(items) > MOST_CONTEXTS:
                    items, waiting, crowded = waiting + items, [], True
                if crowded and items:
                    yield out(CROWDED, *zip(*items, strict=True))
                elif items:
                    waiting = waiting + items
        anchor, context = key[-1], (c1[-1], c2[-1])
    if len(waiting) > 1:
        yield out(CONTESTED, *zip(*waiting, strict=True))


def ranked(text: np.ndarray, depth: int) -> np.ndarray:
    """Rank of every suffix by its first ``depth`` symbols, by prefix doubling; positions past the end rank below all."""
    rank = np.unique(text, return_inverse=True)[1] + 1
    have = 1
    while have < depth:
        step = min(have, depth - have)
        tail = np.concatenate([rank[step:], np.zeros(step, rank.dtype)])
        rank = np.unique(rank * (int(rank.max()) + 1) + tail, return_inverse=True)[1] + 1
        have += step
    return rank


def suffix_array(text: np.ndarray, places: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes that begin at ``places``, sorted by their first ``depth`` symbols, and each one's common prefix with the one before."""
    rank = ranked(text, depth)
    order = places[np.argsort(rank[places], kind="stable")]
    common_prefix = np.zeros(len(order), np.int64)
    alive = np.arange(1, len(order))
    a, b = order[:-1].copy(), order[1:].copy()
    for _ in range(depth):
        if not len(alive):
            break
        fits = (a < len(text)) & (b < len(text))
        fits[fits] = text[a[fits]] == text[b[fits]]
        alive, a, b = alive[fits], a[fits] + 1, b[fits] + 1
        common_prefix[alive] += 1
    return order, common_prefix


def prefix_intervals(common_prefix: np.ndarray, least: int) -> Iterator[tuple[int, int, int]]:
    """(length, first, last) of the tree of common-prefix intervals of at least ``least`` symbols, by a stack scan."""
    stack: list[tuple[int, int]] = []
    for i in [*np.flatnonzero((common_prefix >= least) | np.append(common_prefix[:-1] >= least, False) | np.concatenate([[False], common_prefix[:-1] >= least])).tolist(), len(common_prefix)]:
        depth, left = int(common_prefix[i]) if i < len(common_prefix) else 0, i - 1
        while stack and stack[-1][0] > depth:
            length, left = stack.pop()
            yield length, left, i - 1
        if depth >= least and (not stack or stack[-1][0] < depth):
            stack.append((depth, left))


def maximal_repeats(contexts: list[bytes], windows: list[int]) -> Iterator[tuple[int, list[tuple[int, int]]]]:
    """(length, occurrences) of the maximal repeats of WINDOW bytes or more among contexts; an occurrence is (context, offset).

    Each context ends in a symbol of its own, so no repeat runs over an end.
    """
    sizes = np.array([len(c) for c in contexts])
    ends = np.cumsum(sizes + 1)
    starts = ends - sizes - 1
    text = np.zeros(int(ends[-1]), np.int64)
    filled = np.ones(len(text), bool)
    filled[ends - 1] = False
    text[filled] = np.frombuffer(b"".join(contexts), np.uint8)
    text[ends - 1] = 256 + np.arange(len(contexts))
    counts = np.array(windows)
    places = np.repeat(starts, counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    order, shared = suffix_array(text, places, 2 * WINDOW)
    owner = np.searchsorted(ends, order, side="right")
    first = order == starts[owner]
    before = np.where(first, -1 - owner, text[order - 1])
    for length, low, high in prefix_intervals(shared, WINDOW):
        lefts = before[low : high + 1]
        if lefts[0] < 0 or (lefts != lefts[0]).any():
            yield length, [*zip(owner[low : high + 1].tolist(), (order[low : high + 1] - starts[owner[low : high + 1]]).tolist(), strict=True)]


REPEATS = "repeat string, length int, doc bigint, start int, earlier boolean, context_doc bigint, context_start int"


def _arrays(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Suffix arrays over whole anchors' contexts, several anchors to an array."""
    common.fresh_worker()
    held: list[tuple[int, int, int, int, bytes]] = []
    size = 0

    def packed(rows: list[tuple]) -> pa.RecordBatch:
        columns = [*zip(*rows, strict=True)]
        types = (pa.string(), pa.int32(), pa.int64(), pa.int32(), pa.bool_(), pa.int64(), pa.int32())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["repeat", "length", "doc", "start", "earlier", "context_doc", "context_start"])

    def finish() -> Iterator[pa.RecordBatch]:
        """Intervals nest, so their occurrences can be many more than the contexts: they leave as they are found."""
        rows: list[tuple] = []
        contexts, counts = [h[4] for h in held], [h[3] - WINDOW + 1 for h in held]
        for k, (length, places) in enumerate(maximal_repeats(contexts, counts) if len(held) > 1 else ()):
            spots = sorted({(held[c][1], held[c][2] + o): (held[c][1], held[c][2]) for c, o in places}.items())
            name = f"{held[places[0][0]][0]}:{spots[0][0][0]}:{spots[0][0][1]}:{k}"
            rows += [(name, length, *spot, i > 0, *context) for i, (spot, context) in enumerate(spots)]
            if len(rows) > 5000:
                yield packed(rows)
                rows = []
        if rows:
            yield packed(rows)

    last = None
    for batch in common.small(batches):
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if row[0] != last and size > ARRAY_BYTES:
                yield from finish()
                held, size = [], 0
            last = row[0]
            held.append(row)
            size += len(row[4])
    yield from finish()


def _numbered(docs: DataFrame) -> DataFrame:
    """(doc, text) of ``remove_repeats``'s documents: unique numbers in the order of the documents."""
    return docs.select(F.col("doc_id").cast("long").alias("doc"), common.text_of().alias("text"))


def _told_apart(docs: DataFrame) -> DataFrame:
    """Distinct (doc_id, digest, text) with ``number``, increasing over the whole range-sorted table."""
    rows = docs.select("doc_id", F.md5(common.text_of()).alias("digest"), common.text_of().alias("text")).dropDuplicates(["doc_id", "digest"])
    ordered = rows.repartitionByRange("doc_id", "digest").sortWithinPartitions("doc_id", "digest")
    return common.persist_shared(ordered.withColumn("number", F.monotonically_increasing_id()))


def _deal(runs: DataFrame) -> DataFrame:
    ready = runs.repartition("anchor").sortWithinPartitions("anchor", "c1", "c2", "doc", "start")
    return ready.mapInArrow(_scan_runs, FOUND)


def _with_bytes(docs: DataFrame, wanted: DataFrame, cut, schema: str) -> DataFrame:
    """Rows of ``wanted`` (doc, spans) joined to their texts and passed to ``cut``."""
    by_doc = wanted.groupBy("doc").agg(F.collect_list(F.struct("anchor", "start", "length")).alias("spans"))
    return _numbered(docs).join(by_doc, "doc").select("doc", "text", "spans").mapInArrow(cut, schema)


def _cut_contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    common.fresh_worker()
    for batch in common.small(batches):
        rows: list[tuple] = []
        for doc, raw, spans in zip(batch.column(0).to_pylist(), common.raw_texts(batch), batch.column(2).to_pylist(), strict=True):
            rows += [(s["anchor"], doc, s["start"], s["length"], raw[s["start"] : s["start"] + s["length"]]) for s in spans]
        columns = [*zip(*rows, strict=True)]
        types = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["anchor", "doc", "start", "length", "context"])


def _cut_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every window of the crowded contexts as a context of its own."""
    hasher = Hasher()
    for batch in common.small(batches):
        for doc, raw, spans in zip(batch.column(0).to_pylist(), common.raw_texts(batch), batch.column(2).to_pylist(), strict=True):
            data = np.frombuffer(raw, np.uint8)
            one, two = hasher.prefix(data, 0), hasher.prefix(data, 1)
            at = np.concatenate([np.arange(s["start"], s["start"] + s["length"] - WINDOW + 1) for s in spans])
            c1, c2 = hasher.at(one, at, at + WINDOW, 0).view(np.int64), hasher.at(two, at, at + WINDOW, 1).view(np.int64)
            order, again = _fold([c1, c2], np.full(len(at), doc), at)
            for rows, windows in ((order[~again], 1), (order[again], -1)):
                if len(rows):
                    yield _runs_batch(c1[rows], c1[rows], c2[rows], np.full(len(rows), doc), at[rows], np.full(len(rows), windows))


def repeated_passages(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(removed spans, maximal repeats): spans are (doc, start, length); repeats are rows as in REPEATS, one an occurrence.

    A whole context that a slice or an anchor folds away is a repeat of its
    representative and appears among the spans; the repeats table holds what the
    suffix arrays find among distinct contexts, and ``repeat_groups`` has both.
    """
    runs = _numbered(docs).select("doc", "text").mapInArrow(_collect_runs, RUN)
    found = common.persist_shared(_deal(runs))
    contested = found.filter(F.col("kind") == CONTESTED)
    contexts = _with_bytes(docs, contested, _cut_contexts, "anchor bigint, doc bigint, start int, length int, context binary")
    repeats = common.persist_shared(contexts.repartition("anchor").sortWithinPartitions("anchor", "doc", "start").mapInArrow(_arrays, REPEATS).drop("context_doc", "context_start"))
    removed = found.filter(F.col("kind") == REMOVED).select("doc", "start", "length").unionByName(repeats.filter("earlier").select("doc", "start", "length"))
    crowded = found.filter(F.col("kind") == CROWDED)
    if not crowded.isEmpty():
        again = common.persist_shared(_deal(_with_bytes(docs, crowded, _cut_windows, RUN)))
        removed = removed.unionByName(again.filter(F.col("kind") == REMOVED).select("doc", "start", "length"))
    return removed, repeats


def repeat_groups(docs: DataFrame) -> DataFrame:
    """(repeat, length, doc, start, earlier): every group of repeats with all its occurrences; doc is doc_id, which must be unique.

    Three kinds of groups: whole contexts that stand in several places, maximal
    repeats that the interval trees find among different contexts, and, under
    anchors with more than ``MOST_CONTEXTS`` contexts, equal windows. A tree sees one
    place of each context; all other places of that context are added to its groups.
    """
    runs = common.persist_shared(_numbered(docs).select("doc", "text").mapInArrow(lambda batches: _collect_runs(batches, False), RUN))
    by = ["anchor", "c1", "c2"]
    heads = runs.groupBy(*by).agg(F.min(F.struct("doc", "start")).alias("head"), F.count(F.lit(1)).alias("n"), F.first("windows").alias("windows"))
    heads = common.persist_shared(heads.select(*by, F.col("head.doc").alias("context_doc"), F.col("head.start").alias("context_start"), "n", (F.col("windows") + (WINDOW - 1)).alias("length")))
    hot = common.hot_keys(heads.select(*by, "n"), by, "n")
    members = common.salted(runs.select(*by, "doc", "start"), by, hot, F.struct("doc", "start")).join(common.repeated_for_salts(heads, by, hot), [*by, "salt"])
    members = common.persist_shared(members.select("context_doc", "context_start", "doc", "start", "n", "length"))
    whole = members.filter("n > 1").select(F.concat_ws(":", F.lit("whole"), "context_doc", "context_start").alias("repeat"), "length", "doc", "start")
    several = heads.groupBy("anchor").agg(F.count(F.lit(1)).alias("contexts")).filter("contexts > 1")
    judged = heads.join(several, "anchor").select("anchor", F.col("context_doc").alias("doc"), F.col("context_start").alias("start"), "length", "contexts")
    texts = _with_bytes(docs, judged.filter(F.col("contexts") <= MOST_CONTEXTS), _cut_contexts, "anchor bigint, doc bigint, start int, length int, context binary")
    parts = texts.repartition("anchor").sortWithinPartitions("anchor", "doc", "start").mapInArrow(_arrays, REPEATS).select("repeat", "length", "start", "context_doc", "context_start")
    spans = judged.filter(F.col("contexts") > MOST_CONTEXTS)
    windows = spans.select(F.col("doc").alias("context_doc"), F.col("start").alias("context_start"), F.explode(F.sequence(F.lit(0), F.col("length") - WINDOW)).alias("shift"))
    hashed = _with_bytes(docs, spans, _cut_windows, RUN).select("c1", "c2", F.col("doc").alias("context_doc"), "start").distinct()
    placed = hashed.join(windows.withColumn("start", F.col("context_start") + F.col("shift")), ["context_doc", "start"]).select(F.concat_ws(":", F.lit("window"), "c1", "c2").alias("repeat"), F.lit(WINDOW).alias("length"), "start", "context_doc", "context_start")
    found = parts.unionByName(placed).withColumn("shift", F.col("start") - F.col("context_start")).drop("start")
    every = found.join(members.select("context_doc", "context_start", "doc", F.col("start").alias("at")), ["context_doc", "context_start"])
    out = whole.unionByName(every.select("repeat", "length", "doc", (F.col("at") + F.col("shift")).cast("int").alias("start"))).distinct()
    first = out.groupBy("repeat").agg(F.min(F.struct("doc", "start")).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    return out.join(first, "repeat").select("repeat", "length", "doc", "start", (F.struct("doc", "start") > F.col("first")).alias("earlier"))


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    common.fresh_worker()
    for batch in common.small(batches):
        out = []
        for raw, spans in zip(common.raw_texts(batch, "text"), batch.column(batch.schema.get_field_index("spans")).to_pylist(), strict=True):
            parts, at, n, removed = [], 0, 0, 0
            low = high = -1
            merged = []
            for s, e in sorted((s["start"], s["start"] + s["length"]) for s in spans or ()):
                if s > high:
                    if high > low:
                        merged.append((low, high))
                    low, high = s, e
                else:
                    high = max(high, e)
            if high > low:
                merged.append((low, high))
            for s, e in merged:
                parts.append(raw[at:s])
                at, n, removed = e, n + 1, removed + e - s
            kept = b"".join([*parts, raw[at:]])
            out.append((len(raw), removed, n, common.sha256_hex(kept), kept))
        columns = [*zip(*out, strict=True)]
        types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        keep = [batch.column(0)]
        yield pa.RecordBatch.from_arrays(keep + [pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the remaining bytes) of each row."""
    doubtful = docs.groupBy("doc_id").agg(F.count("*").alias("n")).filter(F.col("doc_id").isNull() | (F.col("n") > 1))
    if not isinstance(docs.schema["doc_id"].dataType, T.IntegralType) or not doubtful.isEmpty():
        apart = _told_apart(docs)
        done = remove_repeats(apart.select(F.col("number").alias("doc_id"), "text")).withColumnRenamed("doc_id", "number")
        named = apart.select("doc_id", "digest", "number").join(done, "number")
        back = docs.select(F.col("doc_id").alias("id"), F.md5(common.text_of()).alias("d")).join(named, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("d") == F.col("digest")))
        return back.drop("id", "d", "digest", "number")
    spans, _ = repeated_passages(docs)
    by_doc = spans.groupBy("doc").agg(F.collect_list(F.struct("start", "length")).alias("spans"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", "text").join(by_doc, F.col("doc_id") == F.col("doc"), "left").select("doc_id", "text", "spans")
    return rows.mapInArrow(_remove, f"doc_id {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string, kept binary")


def query(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(common.load(spark, sf_dir, "documents").select("doc_id", "text")).drop("kept")


ORACLE = None
"""SQL would hold a row for every byte; tests compare with a brute force over all windows."""
