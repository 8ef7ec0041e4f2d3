"""Benchmark decontamination by Wu-Manber search over word sequences.

Patterns are the windows of ``window`` consecutive words of the benchmark items
(an item of fewer words is one window). For each pattern length a shift table
over blocks of two words says how far the search may jump; where the shift is
nought, the suffix block selects a bucket, the pattern's first block selects
inside it, and the words are compared one by one.

The windows are a written table, made by Spark. Tables of up to ``BLOCK_BYTES``
of windows are sent to every executor as one broadcast; a larger benchmark is
dealt into blocks of that size by a hash of the window, and each block takes a
pass over the documents that adds to what the passes before it found. The driver
holds one block at a time, and never the items' texts.

Null and empty texts have no words and no hits. Items without words give no
window. Repeated documents and repeated items are each judged as they stand; an
item without an id counts under the empty id.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WINDOW = 13
#: Bytes of windows and their item ids that one pass over the documents searches; a larger benchmark takes more passes.
BLOCK_BYTES = 32_000_000
OWN = ("n_words", "hits", "item_ids", "n_hit")


class WuManber:
    """All patterns of one length ``m``; a match is reported by its start and the pattern's items."""

    def __init__(self, patterns: dict[tuple[bytes, ...], set[str]], m: int) -> None:
        self.m, self.block = m, min(2, m)
        self.jump = m - self.block + 1
        self.shift: dict[bytes, int] = {}
        self.buckets: dict[bytes, dict[bytes, list[tuple[tuple[bytes, ...], frozenset[str]]]]] = {}
        for words, items in patterns.items():
            for end in range(self.block, m + 1):
                block = b" ".join(words[end - self.block : end])
                self.shift[block] = min(self.shift.get(block, self.jump), m - end)
            suffix, prefix = b" ".join(words[m - self.block :]), b" ".join(words[: self.block])
            self.buckets.setdefault(suffix, {}).setdefault(prefix, []).append((words, frozenset(items)))

    def search(self, words: list[bytes]) -> Iterator[tuple[int, frozenset[str]]]:
        m, block, n = self.m, self.block, len(words)
        shift, jump, buckets = self.shift.get, self.jump, self.buckets
        end = m
        while end <= n:
            key = words[end - 1] if block == 1 else words[end - 2] + b" " + words[end - 1]
            step = shift(key, jump)
            if step:
                end += step
                continue
            start = end - m
            for pattern, items in buckets[key].get(b" ".join(words[start : start + block]), ()):
                if tuple(words[start:end]) == pattern:
                    yield start, items
            end += 1


def searchers(windows: Iterable[tuple[bytes, str]]) -> list[WuManber]:
    """Tables of a block of (window, item): words and item ids are held once."""
    by_length: dict[int, dict[tuple[bytes, ...], set[str]]] = {}
    once: dict = {}
    for window, item in windows:
        words = tuple([once.setdefault(w, w) for w in window.split(b" ")])
        by_length.setdefault(len(words), {}).setdefault(words, set()).add(once.setdefault(item, item))
    return [WuManber(patterns, m) for m, patterns in sorted(by_length.items())]


def merged(spans: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [(s, e) for s, e in out]


def benchmark_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(window, item): every distinct window of every item, its words joined by spaces."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in common.small(batches):
            for item, raw in zip(batch.column(0).to_pylist(), common.raw_texts(batch), strict=True):
                words = common.words_of(raw)
                for a in range(0, max(1, len(words) - window + 1) if words else 0, 4096):
                    found = [b" ".join(words[i : i + window]) for i in range(a, min(a + 4096, max(1, len(words) - window + 1)))]
                    yield pa.RecordBatch.from_arrays([pa.array(found, pa.binary()), pa.array([item] * len(found), pa.string())], names=["window", "item"])

    rows = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), common.text_of().alias("text"))
    return rows.mapInArrow(cut, "window binary, item string").distinct()


def _scan(schema: pa.Schema, sent, owner):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = common.worker_memory(owner, lambda: searchers(zip(*sent.value, strict=True)))
        for batch in common.small(batches):
            n_words, hits, items = [], [], []
            before = batch.column(batch.schema.get_field_index("hits")).to_pylist()
            found = batch.column(batch.schema.get_field_index("item_ids")).to_pylist()
            for raw, spans, ids in zip(common.raw_texts(batch), before, found, strict=True):
                words = common.words_of(raw)
                mine, names = [(x["start"], x["end"]) for x in spans], set(ids)
                for table in tables:
                    for start, who in table.search(words):
                        # windows that follow each other grow one span, so a long copy costs no list
                        if mine and mine[-1][0] <= start <= mine[-1][1]:
                            mine[-1] = (mine[-1][0], max(mine[-1][1], start + table.m))
                        else:
                            mine.append((start, start + table.m))
                        names |= who
                n_words.append(len(words))
                hits.append([{"start": s, "end": e} for s, e in merged(mine)])
                items.append(sorted(names))
            keep = [batch.column(i) for i, name in enumerate(batch.schema.names) if name not in OWN]
            yield pa.RecordBatch.from_arrays(
                [*keep, pa.array(n_words, pa.int64()), pa.array(hits, schema.field("hits").type), pa.array(items, schema.field("item_ids").type)], schema=schema
            )

    return scan


def benchmark_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``docs`` with n_words, hits (merged word spans inside occurring windows), n_hit and item_ids (sorted)."""
    from pyspark.sql.pandas.types import to_arrow_schema

    context = docs.sparkSession.sparkContext
    span = T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))
    out = docs.drop(*OWN).withColumns({"n_words": F.lit(0).cast("long"), "hits": F.array().cast(span), "item_ids": F.array().cast("array<string>")})
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in out.schema])
    windows = common.persist_shared(benchmark_windows(benchmark, window))
    size = windows.agg(F.coalesce(F.sum(F.octet_length("window") + F.octet_length("item")), F.lit(0))).first()[0]
    blocks = max(1, -(-int(size) // block_bytes))
    for k in range(blocks):
        table = windows.filter(F.pmod(F.xxhash64("window"), F.lit(blocks)) == k).toArrow()
        sent = context.broadcast((table.column(0).to_pylist(), table.column(1).to_pylist()))
        del table
        out = out.mapInArrow(_scan(to_arrow_schema(schema), sent, ("windows", uuid.uuid4().hex)), schema)
        if k < blocks - 1:  # one pass is one worker's memory: a chain of them would be as many
            out = common.persist_shared(out)
            sent.unpersist()
    total = F.aggregate("hits", F.lit(0).cast("long"), lambda n, x: n + x["end"] - x["start"])
    return out.withColumn("n_hit", total)


def contaminated() -> Column:
    """A document is contaminated when hit words are a twentieth of its words or more."""
    return (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))


def query(spark, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents").select("doc_id", "text")
    found = benchmark_hits(docs, common.load(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "item_ids"), 256).alias("items_sha256"), contaminated().alias("contaminated")
    )


ORACLE = r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w FROM documents),
bw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w FROM benchmark),
pat AS (SELECT DISTINCT item_id, least(13, len(w)) m, array_to_string(w[i:i + least(13, len(w)) - 1], ' ') p
        FROM (SELECT item_id, w, unnest(range(1, greatest(1, len(w) - 12) + 1)) i FROM bw WHERE len(w) > 0)),
ms AS (SELECT DISTINCT m FROM pat),
win AS (SELECT doc_id, m, s, array_to_string(w[s:s + m - 1], ' ') p
        FROM (SELECT doc_id, w, m, unnest(range(1, len(w) - m + 2)) s FROM dw, ms WHERE len(w) >= m)),
occ AS (SELECT doc_id, item_id, s, win.m FROM win JOIN pat USING (p, m)),
hit AS (SELECT doc_id, count(DISTINCT k) n FROM (SELECT doc_id, unnest(range(s, s + m)) k FROM occ) GROUP BY 1),
its AS (SELECT doc_id, count(*) n, string_agg(i, ',' ORDER BY i) l FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) i FROM occ) GROUP BY 1)
SELECT dw.doc_id, CAST(len(w) AS BIGINT) n_words, CAST(coalesce(hit.n, 0) AS BIGINT) n_hit, CAST(coalesce(its.n, 0) AS BIGINT) n_items,
       sha256(coalesce(its.l, '')) items_sha256, coalesce(hit.n, 0) > 0 AND 20 * coalesce(hit.n, 0) >= len(w) contaminated
FROM dw LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id)
"""
