"""Toxicity by noisy-channel deobfuscation.

A character trigram model is counted over the whole corpus. Every run of text
that a writer may have disguised (digits or signs for letters, letters repeated
three times or more, letters set apart one by one) becomes a lattice of
readings, and a Viterbi search finds the likeliest one under the model and the
channel's costs; all other text has a single reading and needs no search. A
logistic regression over the restored words scores the document.

Labels come from rows whose crc32(doc_id as text) mod 5 is not 0 and, of these,
from at most ``TRAIN_ROWS`` (taken in the order of a hash of doc_id); that
sample fits the classifier alone. Language, source, doc_id and labels are never
features.

Null and empty texts have no features and take the score of the bias. With no
usable labels, or labels of one class, every score is the smoothed share of
toxic labels. Several labels of one document count as toxic if any does.
"""

from __future__ import annotations

import math
import re
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Bound of the labelled sample that fits the classifier.
TRAIN_ROWS = 20_000
#: Bytes, as Python holds them, of the tokens whose slots a worker remembers, and disguised runs whose reading it remembers.
KNOWN_BYTES, KNOWN_RUNS = 32_000_000, 20_000
#: Code points whose trigrams are counted at once.
COUNT_POINTS = 1 << 20
SLOTS = 1 << 18
SIZE = 64
#: Letters the model tells apart: 1-26 for a-z, 27-59 for the lower-case Latin-1 letters; 0 is all else.
ALPHABET = {c: i for i, c in enumerate([chr(x) for x in [*range(97, 123), *range(0xDF, 0x100)]], 1)}
# Letters that a sign may stand for.
SIGNS = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "*": "aeiou"}
COST_SIGN, COST_KEEP, COST_DOUBLE, COST_JOIN, COST_SPLIT = 0.7, 5.0, 0.7, 0.3, 2.0

_SPACED = re.compile(r"(?<![\w@$])[^\W_]?(?:(?<=[\w@$!0-9])[ ._*-]{1,2}[\w@$!](?![\w@$!])){2,}")
_SINGLES = re.compile(r"(?<![\w@$!])[\w@$!][ ._*-]{1,2}[\w@$!][ ._*-]{1,2}[\w@$!](?![\w@$!])")
_DISGUISED = re.compile(r"[^\W\d_][0-9@$!|+(*]|[0-9@$!|+(*][^\W\d_]|([^\W\d_])\1\1")
_EDGES = re.compile(r"^[^\w@$]+|([^\w$@]+|([^\w])\2+)$")
_WORD = re.compile(r"[^\W\d_]+")


def _codepoint_table() -> np.ndarray:
    table = np.zeros(65536, np.int64)
    for c, i in ALPHABET.items():
        table[ord(c)] = i
    return table


def trigram_counts(docs: DataFrame) -> DataFrame:
    """(code, n) of every character trigram of every text; codes are bounded by the alphabet, counts add up over all rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        table, total = _codepoint_table(), np.zeros(SIZE**3, np.int64)
        for batch in common.small(batches):
            raws = common.raw_texts(batch)
            for a, b in common.slices([len(x) for x in raws], 1_000_000):
                joined = b"\n\n".join(raws[a:b]).decode("utf-8", "replace").lower()
                for at in range(0, len(joined) - 2, COUNT_POINTS):  # windows overlap by two, so each trigram is in one
                    points = np.frombuffer(joined[at : at + COUNT_POINTS + 2].encode("utf-32-le"), np.uint32)
                    codes = table[np.minimum(points, 65535)]
                    total += np.bincount((codes[:-2] * SIZE + codes[1:-1]) * SIZE + codes[2:], minlength=SIZE**3)
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(total[seen])], names=["code", "n"])

    return docs.select("text").mapInArrow(count, "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))


def language_model(counts: DataFrame) -> np.ndarray:
    """Log probability of each third character after two; at most SIZE**3 rows reach the driver."""
    n = np.zeros(SIZE**3)
    for row in counts.toLocalIterator():
        n[row.code] = row.n
    n = n.reshape(SIZE, SIZE, SIZE)
    bi, uni = n.sum(0), n.sum((0, 1))
    one = (uni + 0.5) / (uni.sum() + 0.5 * SIZE)
    two = (bi + 20 * one) / (bi.sum(1, keepdims=True) + 20)
    three = (n + 10 * two[None]) / (n.sum(2, keepdims=True) + 10)
    return np.log(three).astype(np.float32)


class Deobfuscator:
    def __init__(self, model: np.ndarray) -> None:
        self.model = model
        self.known: dict[str, str] = {}

    def lattice(self, run: str) -> list[list[tuple[str, float]]]:
        """Readings of each place: the emitted letters (a space is the boundary) and the channel's cost."""
        out: list[list[tuple[str, float]]] = []
        for found in re.finditer(r"(.)\1*", run, re.DOTALL):
            c, n = found[1], len(found[0])
            if c in " ._-*" and len(run) > 2 and not (c == "*" and _DISGUISED.search(run)):
                out.append([("", COST_JOIN), (" ", COST_SPLIT)])
            elif c in SIGNS:
                for _ in range(n):
                    out.append([*((x, COST_SIGN) for x in SIGNS[c]), (" ", COST_KEEP)])
            elif c in ALPHABET and n > 2:
                out.append([(c, 0.0), (c + c, COST_DOUBLE)])
            else:
                out.extend([[(c, 0.0)]] * n)
        return out

    def decode(self, run: str) -> str:
        """The likeliest reading of a disguised run, by Viterbi over states of two characters."""
        if run in self.known:
            return self.known[run]
        model, best = self.model, {(0, 0): (0.0, None)}
        for options in [*self.lattice(run), [(" ", 0.0)]]:
            after: dict[tuple[int, int], tuple[float, tuple | None]] = {}
            for (a, b), (score, path) in best.items():
                for letters, cost in options:
                    x, y, value = a, b, score - cost
                    for c in letters:
                        i = ALPHABET.get(c, 0)
                        value += float(model[x, y, i])
                        x, y = y, i
                    if (x, y) not in after or value > after[x, y][0]:
                        after[x, y] = (value, (path, letters))
            best = after
        path, parts = max(best.values(), key=lambda v: v[0])[1], []
        while path:
            path, letters = path
            parts.append(letters)
        read = "".join(reversed(parts)).strip()
        if len(run) < 200:
            if len(self.known) >= KNOWN_RUNS:
                self.known.clear()
            self.known[run] = read
        return read

    def token_words(self, token: str) -> set[str]:
        """Words of one run without white space, as it stands and, if it is disguised, as it reads."""
        words = set(_WORD.findall(token))
        if _DISGUISED.search(token) and _DISGUISED.search(core := _EDGES.sub("", token)):
            words.update(_WORD.findall(self.decode(core)))
        return words

    def restored(self, text: str) -> set[str]:
        """Lower-cased words of a text, disguised and spaced-out runs read as well."""
        low, words = text.lower(), set()
        for token in set(low.split()):
            words |= self.token_words(token)
        for run in spaced_runs(low):
            words.update(_WORD.findall(self.decode(run)))
        return words


def spaced_runs(low: str) -> Iterator[str]:
    """Stretches of three or more single characters that one or two signs or spaces set apart."""
    if _SINGLES.search(low):
        for found in _SPACED.finditer(low):
            yield found[0].strip(" ._-")


class Features:
    """Slots of a document's distinct words and of their beginnings; tokens are remembered by a worker.

    ``wanted`` tells the slots that are of use: a scorer wants those with a weight, so most tokens have none.
    """

    def __init__(self, model: np.ndarray, wanted: np.ndarray | None = None) -> None:
        self.reader, self.wanted = Deobfuscator(model), wanted
        self.known: dict[str, tuple[int, ...]] = {}
        self.held = 0

    def of_word(self, word: str) -> list[int]:
        names = [word] + [f"{n}:{word[:n]}" for n in (4, 5, 6) if len(word) > n]
        slots = [zlib.crc32(x.encode()) % SLOTS for x in names]
        return slots if self.wanted is None else [i for i in slots if self.wanted[i]]

    def of_token(self, token: str) -> tuple[int, ...]:
        found = tuple({i for word in self.reader.token_words(token) for i in self.of_word(word)})
        if self.held > KNOWN_BYTES:
            self.known.clear()
            self.held = 0
        if len(token) < 60:
            self.known[token] = found
            self.held += common.weight(token) + (40 + 36 * len(found) if found else 0)
        return found

    def of_text(self, raw: bytes) -> set[int]:
        low = raw.decode("utf-8", "replace").lower()
        known, slots = self.known, set()
        for token in set(low.split()):
            found = known.get(token)
            if found is None:
                found = self.of_token(token)
            if found:
                slots.update(found)
        for run in spaced_runs(low):
            for word in _WORD.findall(self.reader.decode(run)):
                slots.update(self.of_word(word))
        return slots


def held_out() -> F.Column:
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 5 == 0


def training_slots(docs: DataFrame, labels: DataFrame, model: np.ndarray, most: int = TRAIN_ROWS) -> DataFrame:
    """(slots, label) of at most ``most`` labelled documents; of rows that share a doc_id, the text of the least digest stands for all."""
    usable = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("label"))
    taken = usable.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    named = docs.select("doc_id", common.text_of().alias("text")).join(F.broadcast(taken), "doc_id")
    least = named.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("digest"), "text")).alias("one"), F.first("label").alias("label"))
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def slots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        features = Features(sent.value)
        for batch in common.small(batches):
            found = [sorted(features.of_text(raw)) for raw in common.raw_texts(batch)]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.int32())), batch.column(1)], names=["slots", "label"])

    return common.persist_shared(least.select("one.text", "label").mapInArrow(slots, "slots array<int>, label int"))


def telling_slots(rows: DataFrame) -> tuple[np.ndarray, int, int]:
    """(slots that tell the classes apart, rows, toxic rows): counted by Spark; at most SLOTS counts reach the driver."""
    size = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("label"), F.lit(0)).alias("toxic")).first()
    if not 0 < size.toxic < size.n:
        return np.zeros(0, np.int64), size.n, size.toxic
    counted = rows.select(F.explode("slots").alias("slot"), "label").groupBy("slot").agg(F.count(F.lit(1)).alias("have"), F.sum("label").alias("toxic")).filter("have >= 2").toArrow()
    slot, have, toxic = (counted.column(i).to_numpy().astype(np.float64) for i in range(3))
    share = size.toxic / size.n
    z = (toxic - have * share) / np.sqrt(have * share * (1 - share) + 0.1)
    return np.sort(slot[np.abs(z) >= 2.5].astype(np.int64)), size.n, size.toxic


def fit(rows: DataFrame) -> tuple[np.ndarray, float]:
    """Weights and bias of a logistic regression on the slots that tell the classes apart; only these slots of a row reach the driver."""
    telling, n, n_toxic = telling_slots(rows)
    prior = (n_toxic + 0.5) / (n + 1.0 if n else 1e3)
    weights, bias = np.zeros(SLOTS), math.log(prior / (1 - prior))
    if not len(telling):
        return weights.astype(np.float32), bias
    wanted = np.zeros(SLOTS, bool)
    wanted[telling] = True
    sent = rows.sparkSession.sparkContext.broadcast(wanted)

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.fresh_worker()
        for batch in batches:
            lists = batch.column(0)
            flat, sizes = lists.flatten().to_numpy(zero_copy_only=False), lists.value_lengths().to_numpy(zero_copy_only=False)
            mine = sent.value[flat]
            row = np.repeat(np.arange(len(sizes)), sizes)[mine]
            ends = np.cumsum(np.bincount(row, minlength=len(sizes)))
            kept = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(flat[mine], pa.int32()))
            yield pa.RecordBatch.from_arrays([kept, batch.column(1)], names=["slots", "label"])

    # the order of rows decides the last digits of the sums: sorted, equal inputs give equal weights
    table = rows.mapInArrow(pick, "slots array<int>, label int").orderBy("label", "slots").toArrow()
    y = table.column("label").to_numpy().astype(np.float64)
    lists = table.column("slots").combine_chunks()
    flat = np.searchsorted(telling, lists.flatten().to_numpy())
    row = np.repeat(np.arange(len(y)), lists.value_lengths().to_numpy())
    w = np.zeros(len(telling))
    grow, bias_grow = np.full(len(w), 1e-6), 1e-6
    for _ in range(150):
        p = 1 / (1 + np.exp(-np.clip(bias + np.bincount(row, weights=w[flat], minlength=n), -30, 30)))
        g = p - y
        step, step_bias = np.bincount(flat, weights=g[row], minlength=len(w)) / n + 1e-4 * w, g.mean()
        grow += step**2
        bias_grow += step_bias**2
        w -= 0.5 * step / np.sqrt(grow)
        bias -= 0.5 * step_bias / math.sqrt(bias_grow)
    weights[telling] = w
    return weights.astype(np.float32), float(bias)


def score_toxicity(docs: DataFrame, model: np.ndarray, weights: np.ndarray, bias: float) -> DataFrame:
    """``docs`` with ``score`` (0 to 1) and ``predicted``; model and weights are tables of fixed size."""
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    rest = docs.drop("score", "predicted")
    schema = T.StructType([T.StructField(f.name, f.dataType, True) for f in rest.schema] + [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    arrow, sent = to_arrow_schema(schema), docs.sparkSession.sparkContext.broadcast((model, weights))
    owner = ("toxicity", uuid.uuid4().hex)  # another model's words are another memory

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, weights = sent.value
        features = common.worker_memory(owner, lambda: Features(model, weights != 0))
        weight = dict(zip(np.flatnonzero(weights).tolist(), weights[weights != 0].tolist(), strict=True))
        for batch in common.small(batches):
            values = []
            for raw in common.raw_texts(batch):
                total = bias + math.fsum(weight[i] for i in features.of_text(raw))
                values.append(1 / (1 + math.exp(-max(-30.0, min(30.0, total)))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(values, pa.float64()), pa.array([int(v >= 0.5) for v in values], pa.int32())], schema=arrow)

    return rest.mapInArrow(score, schema)


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` with ``score`` and ``predicted``: model counted, classifier fitted, every row scored."""
    model = language_model(trigram_counts(docs))
    return score_toxicity(docs, model, *fit(training_slots(docs, labels, model)))


def query(spark, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity(docs, common.load(spark, sf_dir, "labels"))
    return scored.select("doc_id", held_out().alias("held_out"), "score", "predicted")


ORACLE = None
"""A fitted classifier has no SQL form; tests measure it on held-out labels and on disguised copies."""
