"""Byte-level BPE by merge replay over an inverted index.

The distinct pre-tokens of a block of rows are laid end to end as symbols. An
inverted index leads from the rank that a pair of neighbours would merge into
to the positions where such pairs stand; a heap gives the ranks in order, and
each merge touches its two neighbours only. A word whose merge opens a pair of
a lower rank puts its remaining positions back, so that every word sees its
merges in the order in which a word-by-word encoder makes them.

Null and empty texts have no ids; the digest of no ids is that of the empty
string. Texts of one endless pre-token are encoded in n log n steps.
"""

from __future__ import annotations

import base64
import heapq
from array import array
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Bytes, as Python holds them, of the pre-tokens with their ids that one generation of a worker's memory takes.
CACHE_BYTES = 48_000_000
#: Pairs of ids whose rank a worker remembers.
CACHE_PAIRS = 200_000
#: Bytes of text that are split at once, and of new pre-tokens that are encoded together.
BLOCK_BYTES, REPLAY_BYTES = 2_000_000, 200_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


def _ascending(places: array) -> Iterable[int]:
    """Positions in order; of many, a bounded list of Python integers at a time."""
    if len(places) < 4096:
        return sorted(places)
    ordered = np.sort(np.frombuffer(places, np.int32))
    return (i for at in range(0, len(ordered), 65_536) for i in ordered[at : at + 65_536].tolist())


class MergeReplay:
    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.ranks = ranks
        self.tokens: list[bytes] = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.pairs: dict[int, int] = {}

    def rank_of(self, a: int, b: int) -> int:
        """Rank of two neighbours joined, -1 where the vocabulary lacks it."""
        key = a << 32 | b
        rank = self.pairs.get(key)
        if rank is None:
            rank = self.ranks.get(self.tokens[a] + self.tokens[b], -1)
            if len(self.pairs) >= CACHE_PAIRS:
                self.pairs.clear()
            self.pairs[key] = rank
        return rank

    def encode(self, words: list[bytes]) -> list[tuple[int, ...]]:
        """Ids of each word, as ranks merge them in order."""
        out: list[tuple[int, ...] | None] = [(whole,) if (whole := self.ranks.get(w)) is not None else None if w else () for w in words]
        # machine integers, so that one endless pre-token costs some twenty bytes a byte
        symbol, owner, left, right = array("i"), array("i"), array("i"), array("i")
        first: dict[int, int] = {}
        single = [self.ranks.get(bytes([b]), -1) for b in range(256)]
        index: dict[int, array] = {}
        rank_of = self.rank_of
        for k, word in enumerate(words):
            if out[k] is not None:
                continue
            base, n = len(symbol), len(word)
            first[k] = base
            symbol.extend([single[b] for b in word])
            owner.extend(array("i", [k]) * n)
            left.extend(range(base - 1, base + n - 1))
            right.extend(range(base + 1, base + n + 1))
            left[base], right[base + n - 1] = -1, -1
            for i in range(base, base + n - 1):
                if (rank := rank_of(symbol[i], symbol[i + 1])) >= 0:
                    if rank not in index:
                        index[rank] = array("i")
                    index[rank].append(i)
        heap = [*index]
        heapq.heapify(heap)
        while heap:
            rank = heapq.heappop(heap)
            places = index.pop(rank, None)
            if places is None:
                continue
            held: set[int] = set()
            for i in _ascending(places):
                j = right[i]
                if symbol[i] < 0 or j < 0 or rank_of(symbol[i], symbol[j]) != rank:
                    continue
                if owner[i] in held:
                    if rank not in index:
                        index[rank] = array("i")
                        heapq.heappush(heap, rank)
                    index[rank].append(i)
                    continue
                symbol[i], symbol[j] = rank, -1
                after = right[i] = right[j]
                if after >= 0:
                    left[after] = i
                for at in (left[i], i):
                    if at < 0 or (then := right[at]) < 0:
                        continue
                    opened = rank_of(symbol[at], symbol[then])
                    if opened < 0:
                        continue
                    if opened not in index:
                        index[opened] = array("i")
                        heapq.heappush(heap, opened)
                    index[opened].append(at)
                    if opened < rank:
                        held.add(owner[i])
        for k, at in first.items():
            ids = []
            while at >= 0:
                ids.append(symbol[at])
                at = right[at]
            out[k] = tuple(ids)
        return out  # type: ignore[return-value]


class Worker:
    """Encoder of a Python worker, with the ids of the pre-tokens it met, as joined text.

    Two generations bound the memory: when the young one is full it becomes the old
    one, and pre-tokens that are met again move back, so the frequent ones always stay.
    """

    def __init__(self, path: str) -> None:
        self.replay = MergeReplay(read_ranks(path))
        self.by_name = {str(rank): token for rank, token in enumerate(self.replay.tokens)}
        self.young: dict[str, str] = {}
        self.old: dict[str, str] = {}
        self.held = 0

    def learn(self, pieces: set[str]) -> dict[str, str]:
        """A table that has all the given pre-tokens."""
        if self.held > CACHE_BYTES:
            self.young, self.old, self.held = {}, self.young, 0
        young, old = self.young, self.old
        fresh = []
        for p in pieces.difference(young):
            if p in old:
                young[p] = old[p]
                self.held += common.weight(p, young[p])
            else:
                fresh.append(p)
        raw = [p.encode("utf-8", "surrogatepass") for p in fresh]
        for a, b in common.slices([len(x) for x in raw], REPLAY_BYTES):
            for p, ids in zip(fresh[a:b], self.replay.encode(raw[a:b]), strict=True):
                young[p] = ",".join(map(str, ids))
                self.held += common.weight(p, young[p])
        return young


def _worker(path: str) -> Worker:
    return common.worker_memory(("bpe", path), lambda: Worker(path))


def _encode_rows(texts: list[str], path: str, pattern) -> Iterator[tuple[int, str, bytes]]:
    """(number of ids, ids joined by commas, bytes the ids stand for) of each text."""
    worker = _worker(path)
    pieces = [pattern.findall(t) for t in texts]
    known, tokens = worker.learn(set(chain.from_iterable(pieces))), worker.by_name
    for row in pieces:
        joined = ",".join(map(known.__getitem__, row))
        ids = joined.split(",") if joined else []
        yield len(ids), joined, b"".join(map(tokens.__getitem__, ids))


def _encoder(path: str, pattern: str, schema: pa.Schema, keep: list[str], with_ids: bool):
    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = regex.compile(pattern)
        for batch in common.small(batches):
            raws = common.raw_texts(batch)
            for a, b in common.slices([len(x) for x in raws], BLOCK_BYTES):
                n, ids, id_sha, back = [], [], [], []
                for count, joined, decoded in _encode_rows([x.decode("utf-8", "replace") for x in raws[a:b]], path, split):
                    n.append(count)
                    id_sha.append(common.sha256_hex(joined.encode()))
                    back.append(common.sha256_hex(decoded))
                    if with_ids:
                        ids.append([int(x) for x in joined.split(",")] if joined else [])
                part = batch.slice(a, b - a)
                columns = [part.column(part.schema.get_field_index(c)) for c in keep]
                own = [pa.array(n, pa.int64()), pa.array(id_sha), pa.array(back), *([pa.array(ids, pa.list_(pa.int32()))] if with_ids else [])]
                yield pa.RecordBatch.from_arrays([*columns, *own], names=schema.names)

    return encode


def bpe_encode(docs: DataFrame, path: str, pattern: str, with_ids: bool = True) -> DataFrame:
    """``docs`` with n_tokens, ids_sha256, decoded_sha256 (of the bytes the ids stand for) and, if asked, ids.

    ``path`` leads to a rank file that every executor has, as tokenizer files of an installed package do.
    """
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    own = [T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    own += [T.StructField("ids", T.ArrayType(T.IntegerType()))] * with_ids
    rest = docs.drop(*(f.name for f in own))
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in rest.schema] + own)
    return rest.mapInArrow(_encoder(path, pattern, to_arrow_schema(schema), rest.columns, with_ids), schema)


def decode(ids: list[int], path: str) -> bytes:
    tokens = _worker(path).replay.tokens
    return b"".join([tokens[i] for i in ids])


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN


def query(spark, sf_dir: str) -> DataFrame:
    path, pattern = default_vocabulary()
    docs = common.load(spark, sf_dir, "documents").select("doc_id", "text")
    return bpe_encode(docs, path, pattern, with_ids=False).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


ORACLE = None
"""SQL has no byte-pair encoding; tests compare the ids with the tiktoken library's and the bytes with the text's."""
