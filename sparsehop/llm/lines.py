"""Line dedup by a segment-partition edit join, on DataFrame functions alone.

A line of ``MIN_CHARS`` characters or more goes if an equal line, or one within
``MAX_EDITS`` edits, stands earlier in the corpus (smaller doc_id, or same
document and smaller line number). Lines are judged on the input. With a smaller
``least``, lines from that length on go if an equal one stands earlier; the two
edits still need ``MIN_CHARS``, as they leave nothing to compare in shorter lines.

Distinct lines are cut into MAX_EDITS + 1 segments: a line within that many
edits keeps one of them. The index has each segment by its number, the line's
length and its hash; a probing line looks up, for each length that is in reach
and not above its own, the substrings that may stand where the segment stood.
Keys of one or two lines give pairs. On keys of more, each line looks for one
earlier line within reach among bounded lists of the others, and no further once
it has one, so that a crowd never becomes all its pairs. On all keys the banded
bit-parallel edit distance decides: the band of 2 * MAX_EDITS + 1 diagonals is one
integer, updated once a character; parities and pieces that a true pair must share go
before it.

Null and empty texts have one empty line, which is shorter than any ``least`` and
stays. Rows that repeat a doc_id share their places: equal lines at one place
are one line and stay both.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

MIN_CHARS, MAX_EDITS = 20, 2
#: Lines of one key that meet as one list.
BLOCK = 256
OWN = ("n_lines", "n_removed")


NO_DOC, LINES = -(2**63), 2**31


def _place() -> Column:
    """A line's place as one number, in the order of the corpus; null documents come first."""
    doc = F.coalesce(F.col("doc_id").cast("decimal(20,0)"), F.lit(NO_DOC).cast("decimal(20,0)"))
    return (doc * F.lit(LINES).cast("decimal(10,0)") + F.col("line_no").cast("decimal(10,0)")).cast("decimal(38,0)")


def _doc_of(place: Column, kind: str) -> Column:
    doc = F.call_function("div", place - F.pmod(place, F.lit(LINES).cast("decimal(38,0)")), F.lit(LINES).cast("decimal(38,0)"))
    return F.when(doc != NO_DOC, doc).cast(kind)


def _line_of(place: Column) -> Column:
    return F.pmod(place, F.lit(LINES).cast("decimal(38,0)")).cast("int")


def occurrences(docs: DataFrame, edits: int | None = None, least: int = MIN_CHARS, below: int | None = None) -> DataFrame:
    """h1, h2 (hashes of the line) and place of every line of ``least`` characters or more; with ``edits``, its probe keys.

    The keys are plain columns p0, p1, ..., the line's own index keys first; the lines themselves go no further.
    """
    split = docs.select("doc_id", F.posexplode(F.split(common.text_of(), "\n", -1)).alias("line_no", "line"))
    long = split.withColumn("size", F.char_length("line")).filter(F.col("size") >= least)
    if below is not None:
        long = long.filter(F.col("size") < below)
    own = [F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2")]
    probes = [] if edits is None else [k.alias(f"p{n}") for n, k in enumerate(probe_keys(F.col("line"), edits, F.col("size"), least))]
    return long.select(*own, _place().alias("place"), *probes)


# Characters whose numbers in a line are told apart as odd or even, a bit each.
COUNTED = "abcdefghijklmnopqrstuvwxyz .,-0123456789"


def parities(line: Column) -> Column:
    """Whether each counted character stands in a line an odd number of times, a bit each."""
    total = F.lit(0).cast("bigint")
    for i, c in enumerate(COUNTED):
        odd = (F.octet_length(line) - F.octet_length(F.replace(line, F.lit(c), F.lit("")))) % 2
        total = total.bitwiseOR(F.shiftleft(odd.cast("bigint"), i))
    return total


def parities_agree(a: Column, b: Column, edits: int) -> Column:
    """Whether two lines' characters allow the distance: an edit turns two bits at most."""
    return F.bit_count(a.bitwiseXOR(b)) <= 2 * edits


def _bounds(length: Column, segment: int, edits: int) -> tuple[Column, Column]:
    """0-based start and size of a segment; the later segments take the characters that are left over."""
    parts = edits + 1
    size, rest = F.call_function("div", length, F.lit(parts)).cast("int"), length % parts
    longer = F.greatest(rest - (parts - segment), F.lit(0))
    start = F.lit(segment) * size + longer
    return start.cast("int"), (size + F.when(rest > parts - 1 - segment, 1).otherwise(0)).cast("int")


def _key(line: Column, segment: int, length: Column, start: Column, size: Column) -> Column:
    return F.xxhash64(F.lit(segment), length, F.substring(line, start + 1, size))


def probe_keys(line: Column, edits: int, length: Column, least: int = 0) -> list[Column]:
    """Keys of the substrings at which a line no longer than this one may have its segments.

    With d characters less and s segments before it, a segment lies at most s places to the left
    of its own start and, counted from the end, at most edits - s places to the right of it.
    Where no line is shorter than ``least`` and every segment has a character, none leaves the line:
    the s before it and the edits - s after it hold one character each at least.
    """
    keys = []
    for less, s, shift in probe_places(edits):
        other = length - less
        start, size = _bounds(other, s, edits)
        at = start + shift
        key = _key(line, s, other, at, size)
        keys.append(key if least > 2 * edits else F.when((other > 0) & (at >= 0) & (at + size <= length), key))
    return keys


def probe_places(edits: int) -> list[tuple[int, int, int]]:
    """(characters less, segment, shift) of the keys, in their order; the first edits + 1 are the line's own index keys."""
    every = [(less, s, shift) for less in range(edits + 1) for s in range(edits + 1) for shift in range(-edits, edits + 1) if abs(shift) <= s and abs(shift - less) <= edits - s]
    return sorted(every, key=lambda x: (x[0] != 0 or x[2] != 0, x))


def _let(value: Column, use) -> Column:
    """``use`` of a value that is computed once: a lambda's argument is not inlined."""
    return F.element_at(F.transform(F.array(value), use), 1)


def code_points(line: Column) -> Column:
    return F.transform(F.split(line, ""), lambda c: F.ascii(c))


def banded_distance(p: Column, t: Column, edits: int) -> Column:
    """Edit distance of two lists of code points whose lengths differ by ``edits`` at most; right up to ``edits``, above it beyond.

    Both are plain columns of stored rows: an expression in their place would be
    evaluated anew in every step, and in the state it would be copied in every step.
    """
    width, mask = 2 * edits + 1, 2 ** (2 * edits + 1) - 1
    word = lambda x: F.lit(x).cast("bigint")
    m, n = F.size(p), F.size(t)
    first = F.struct(word(mask ^ ((1 << edits) - 1)).alias("vp"), word(0).alias("vn"), F.least(m, F.lit(edits)).cast("int").alias("score"))

    def step(s, j):
        def matches(c):
            hits = [F.when(F.get(p, j - 1 - edits + d) == c, word(1 << d)).otherwise(word(0)) for d in range(width)]
            total = hits[0]
            for h in hits[1:]:
                total = total + h
            return total.bitwiseOR(s["vn"])

        def diagonals(x):
            d0 = ((x.bitwiseAND(s["vp"]) + s["vp"]).bitwiseXOR(s["vp"])).bitwiseOR(x).bitwiseAND(word(mask))
            return _let(d0, lambda d: F.struct(d.alias("d0"), s["vn"].bitwiseOR(d.bitwiseOR(s["vp"]).bitwiseXOR(word(mask))).alias("hp"), d.bitwiseAND(s["vp"]).alias("hn")))

        def moved(r):
            row = m - j + edits
            level = F.call_function("shiftright", r["hp"], row).bitwiseAND(word(1)) - F.call_function("shiftright", r["hn"], row).bitwiseAND(word(1))
            diagonal = F.when(r["d0"].bitwiseAND(word(1 << (2 * edits))) == 0, word(1)).otherwise(word(0))
            by = F.when(j <= m - edits, diagonal).when(row >= 0, level).otherwise(word(0))
            down = F.shiftright(r["d0"], 1)
            return F.struct(r["hn"].bitwiseOR(down.bitwiseOR(r["hp"]).bitwiseXOR(word(mask))).bitwiseAND(word(mask)).alias("vp"), down.bitwiseAND(r["hp"]).alias("vn"), (s["score"] + by).cast("int").alias("score"))

        return _let(_let(_let(F.get(t, j - 1), matches), diagonals), moved)

    return F.aggregate(F.sequence(F.lit(1), n), first, step, lambda s: s["score"])


def pieces_agree(x: Column, y: Column, edits: int) -> Column:
    """Whether the distance of two lines may be ``edits`` or less, by pieces.

    y is cut into 2 * edits + 2 pieces. An edit spoils one piece at most, and the
    others stand in x at most ``edits`` places away; so all but ``edits`` are found there.
    """
    pieces = 2 * edits + 2
    size = F.floor(F.char_length(y) / pieces).cast("int")
    found = F.lit(0)
    for k in range(pieces):
        start = size * k + 1
        around = F.substring(x, F.greatest(start - edits, F.lit(1)), size + 2 * edits)
        found = found + F.when(F.instr(around, F.substring(y, start, size)) > 0, 1).otherwise(0)
    return found >= pieces - edits


def distinct_lines(docs: DataFrame, edits: int = MAX_EDITS, least: int = MIN_CHARS) -> DataFrame:
    """h1, h2, first place, n places and probe keys of each distinct line; lines under ``MIN_CHARS`` have no keys."""
    counted = [F.min("place").alias("first"), F.count(F.lit(1)).alias("n")]
    seen = occurrences(docs, edits, max(least, MIN_CHARS))
    keys = [c for c in seen.columns if c[0] == "p" and c != "place"]
    long = seen.groupBy("h1", "h2").agg(*counted, *[F.first(c).alias(c) for c in keys])
    if least >= MIN_CHARS:
        return long
    # short lines go their own way: keys that stay null would cost as much as those of long ones
    short = occurrences(docs, None, least, MIN_CHARS).groupBy("h1", "h2").agg(*counted)
    return long.unionByName(short, allowMissingColumns=True)


def meetings(lines: DataFrame, edits: int = MAX_EDITS) -> DataFrame:
    """(a, key, n, low, high, own): a line's probe that meets an index key of n lines, low and high among them.

    ``own`` marks the line's own index keys. Rows are as many as probes that meet, whatever n is.
    """
    keys = [c for c in lines.columns if c[0] == "p"]
    lines = lines.filter("p0 IS NOT NULL")
    index = lines.select(F.col("h1").alias("b"), F.explode(F.array(*keys[: edits + 1])).alias("key"))
    index = index.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("b").alias("low"), F.max("b").alias("high"))
    probes = lines.select(F.col("h1").alias("a"), F.posexplode(F.array(*keys)).alias("at", "key")).filter("key IS NOT NULL")
    met = probes.join(index, "key").filter("n > 1 OR low <> a")
    return met.select("a", "key", "n", "low", "high", (F.col("at") <= edits).alias("own"))


def _common_prefix(x: Column, y: Column) -> Column:
    """Length of the common prefix, by halving steps."""
    steps = F.array(*[F.lit(1 << k) for k in range(30, -1, -1)])

    def walk(least):
        grown = lambda at, k: F.when((at + k <= least) & (F.substring(x, at + 1, k) == F.substring(y, at + 1, k)), at + k).otherwise(at)
        return F.aggregate(F.filter(steps, lambda k: k <= least), F.lit(0), grown)

    return _let(F.least(F.char_length(x), F.char_length(y)), walk)


def _stripped(x: Column, y: Column, use) -> Column:
    """``use`` of two strings without their common prefix, backwards; what the strings have in common there is no edit."""
    rest = lambda v, n: F.reverse(F.substring(v, n + 1, F.char_length(v)))
    return _let(_common_prefix(x, y), lambda n: _let(rest(x, n), lambda a: _let(rest(y, n), lambda b: use(a, b))))


def within(x: Column, y: Column, edits: int) -> Column:
    """Whether two lines are within ``edits`` edits: shared pieces first, then the banded distance of what is between their common ends."""

    def distance(a, b):
        empty = (F.char_length(a) == 0) | (F.char_length(b) == 0)
        banded = _let(code_points(b), lambda p: _let(code_points(a), lambda t: banded_distance(p, t, edits) <= edits))
        return F.when(empty, F.lit(True)).otherwise(banded)

    close = F.abs(F.char_length(x) - F.char_length(y)) <= edits
    return close & pieces_agree(x, y, edits) & _stripped(x, y, lambda a, b: _stripped(a, b, distance))


def crowded_lines(rows: DataFrame, texts: DataFrame, edits: int) -> DataFrame:
    """(h1): lines on keys of three lines or more that have an earlier line within the distance there.

    ``rows`` has a, key and own. The lines on a key are dealt into blocks by a hash; a
    line meets whole blocks, each as one list, so pairs are never rows and no list is
    unbounded. A line that finds an earlier one asks no further: each round, those that
    are left ask twice as many blocks. Probes look among the index's lines and these
    among the probes.
    """
    held = texts.select(F.col("h1").alias("a"), "first", "parity", "line")
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("probes"))
    full = rows.join(sizes, "key").withColumn("blocks", F.ceil(F.col("probes") / BLOCK).cast("int")).join(held, "a")
    full = common.persist_shared(full.withColumn("block", F.pmod(F.xxhash64("a"), F.col("blocks")).cast("int")).drop("probes"))
    most = full.agg(F.max("blocks")).first()[0]
    if most is None:
        return rows.select(F.col("a").alias("h1")).limit(0)

    def witness(y):
        return (y["b"] != F.col("a")) & (y["first"] < F.col("first")) & parities_agree(y["parity"], F.col("parity"), edits) & within(F.col("line"), y["line"], edits)

    done, low, high = None, 0, 1
    while low < most:
        left = full.filter(F.col("blocks") > low)
        if done is not None:
            left = left.join(done.withColumnRenamed("h1", "a"), "a", "left_anti")
        some = None
        asked_of = full.filter((F.col("block") >= low) & (F.col("block") < high))
        for mine, theirs in ((left, asked_of.filter("own")), (left.filter("own"), asked_of)):
            lists = theirs.groupBy("key", "block").agg(F.collect_list(F.struct("first", F.col("a").alias("b"), "parity", "line")).alias("others"))
            asked = mine.select("a", "key", "first", "parity", "line", F.explode(F.sequence(F.lit(low), F.least("blocks", F.lit(high)) - 1)).alias("block"))
            one = asked.join(lists, ["key", "block"]).filter(F.exists("others", witness)).select(F.col("a").alias("h1"))
            some = one if some is None else some.unionByName(one)
        some = common.persist_shared(some.distinct())
        done = some if done is None else done.unionByName(some)
        low, high = high, 2 * high + 1
    return done


def line_texts(docs: DataFrame, ends: DataFrame) -> DataFrame:
    """``ends`` (h1, h2, first) with each line's text and parities, read from the document where it stands first."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    spots = ends.groupBy(_doc_of(F.col("first"), kind).alias("id")).agg(F.collect_set(_line_of(F.col("first"))).alias("wanted"))
    texts = docs.select("doc_id", "text").join(spots, F.col("doc_id").eqNullSafe(F.col("id")))
    read = texts.select("doc_id", F.split(common.text_of(), "\n", -1).alias("pieces"), F.explode("wanted").alias("line_no"))
    found = read.select(_place().alias("first"), F.get("pieces", F.col("line_no")).alias("line")).withColumn("h1", F.xxhash64("line")).dropDuplicates(["first", "h1"])
    return ends.join(found, ["first", "h1"]).withColumn("parity", parities(F.col("line")))


def near_lines(docs: DataFrame, lines: DataFrame, edits: int = MAX_EDITS) -> DataFrame:
    """(h1, h2) of the distinct lines that have another within ``edits`` edits before them; ``lines`` is ``distinct_lines``."""
    met = common.persist_shared(meetings(lines, edits))
    pairs = met.filter("n < 3").select("a", F.explode(F.array("low", "high")).alias("b")).filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    crowd = met.filter("n > 2").select("a", "key", "own")
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("h1")).union(crowd.select("a")).distinct()
    texts = common.persist_shared(line_texts(docs, lines.select("h1", "h2", "first").join(wanted, "h1")))
    side = lambda k, t: texts.select(F.col("h1").alias(k), F.col("first").alias(f"{k}_first"), F.col("parity").alias(f"{k}_parity"), F.col("line").alias(t))
    both = pairs.join(side("a", "x"), "a").join(side("b", "y"), "b").filter(parities_agree(F.col("a_parity"), F.col("b_parity"), edits) & within(F.col("x"), F.col("y"), edits))
    later = both.select(F.when(F.col("a_first") > F.col("b_first"), F.col("a")).otherwise(F.col("b")).alias("h1"))
    gone = common.persist_shared(later.unionByName(crowded_lines(crowd, texts, edits)).distinct())
    return gone.join(texts.select("h1", "h2"), "h1")


def removed_lines(docs: DataFrame, edits: int = MAX_EDITS, least: int = MIN_CHARS) -> DataFrame:
    """(doc_id, line_no) of every line that goes, once each."""
    lines = common.persist_shared(distinct_lines(docs, edits, least))
    near = near_lines(docs, lines, edits).withColumn("near", F.lit(True))
    judged = lines.select("h1", "h2", "first", "n").join(near, ["h1", "h2"], "left").filter("near OR n > 1").select("h1", "h2", "first", "near")
    hot, by = common.hot_keys(lines.select("h1", "h2", "n"), ["h1", "h2"], "n"), ["h1", "h2"]
    places = common.salted(occurrences(docs, least=least), by, hot, F.col("place"))
    gone = places.join(common.repeated_for_salts(judged, by, hot), [*by, "salt"]).filter(F.col("near") | (F.col("place") > F.col("first")))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return gone.select("place").distinct().select(_doc_of(F.col("place"), kind).alias("doc_id"), _line_of(F.col("place")).alias("line_no"))


def dedup_lines(docs: DataFrame, edits: int = MAX_EDITS, least: int = MIN_CHARS) -> DataFrame:
    """``docs`` with the lines that stay as ``text``, and n_lines and n_removed.

    ``least`` is the length from which equal lines go: 1 takes every line that is not empty.
    A document that loses no line keeps its text as it is; one that loses all has an empty text.
    """
    gone = removed_lines(docs, edits, least).groupBy(F.col("doc_id").alias("id")).agg(F.collect_set("line_no").alias("gone"))
    rest = docs.drop(*OWN)
    joined = rest.join(gone, rest["doc_id"].eqNullSafe(gone["id"]), "left").drop("id")
    pieces = F.split(common.text_of(), "\n", -1)
    # a place shared by rows of one doc_id may be a short line in one of them, which stays
    stays = F.filter(pieces, lambda line, i: (F.char_length(line) < least) | ~F.array_contains("gone", i))
    kept = F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(stays, "\n"))
    return joined.withColumns({"n_lines": F.size(pieces).cast("long"), "n_removed": F.when(F.col("gone").isNull(), 0).otherwise(F.size(pieces) - F.size(stays)).cast("long"), "text": kept}).drop("gone")


def query(spark, sf_dir: str) -> DataFrame:
    done = dedup_lines(common.load(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", "n_lines", "n_removed", F.sha2(common.text_of(), 256).alias("kept_sha256"))


ORACLE = f"""
WITH o AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) line, unnest(range(0, len(string_split(coalesce(text, ''), chr(10))))) no FROM documents),
l AS (SELECT line, min((doc_id, no)) AS f, len(line) n FROM o WHERE len(line) >= {MIN_CHARS} GROUP BY line),
g AS (SELECT DISTINCT x.line FROM l x JOIN l y ON y.n BETWEEN x.n - {MAX_EDITS} AND x.n + {MAX_EDITS} AND x.line <> y.line AND y.f < x.f AND levenshtein(x.line, y.line) <= {MAX_EDITS}),
m AS (SELECT o.doc_id, o.no, o.line, l.line IS NULL OR (g.line IS NULL AND (o.doc_id, o.no) = l.f) keep FROM o LEFT JOIN l ON l.line = o.line LEFT JOIN g ON g.line = o.line)
SELECT doc_id, count(*) n_lines, count(*) FILTER (NOT keep) n_removed, sha256(coalesce(string_agg(line, chr(10) ORDER BY no) FILTER (keep), '')) kept_sha256 FROM m GROUP BY doc_id
"""
