"""License scan by diagonal voting.

Every rolling word k-gram of every text is hashed and joined to the positions
of the same hash in the license templates. A hit votes for the diagonal (place
in the text less place in the template); neighbouring diagonals that an
inserted or lost word sets apart are merged. Each hit is verified by a second,
independent hash of its words, and a candidate span by the share of the
template's words that its hits cover; short phrases and one-line notices must
match word for word on one diagonal. Phrases alone count for the base columns.

Null and empty texts have no words, no labels and score 0. Very long texts are
read whole; their diagonals are rows and never one list. Rows that repeat a
doc_id are told apart by their text; equal rows get equal results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

# Phrases with their labels, and license wordings in public use.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: One-line notices, whose every word must match.
NOTICES = {
    "released under the mit license": "mit",
    "licensed under the mit license": "mit",
    "licensed under the apache license version 2": "apache-2",
    "licensed under the bsd": "bsd",
    "bsd 3 clause license": "bsd",
    "bsd 2 clause license": "bsd",
    "licensed under the gnu general public license": "gpl",
    "gnu general public license version 3": "gpl",
    "gnu general public license v3": "gpl",
    "gnu gpl v3": "gpl",
    "licensed under cc by nc": "cc-by-nc",
    "creative commons attribution noncommercial": "cc-by-nc",
    "licensed under cc by 4 0": "cc-by",
    "creative commons attribution 4 0": "cc-by",
    "mozilla public license version 2": "mpl-2",
    "mozilla public license v 2": "mpl-2",
    "all rights reserved": "reserved",
}
WORDINGS = {
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so",
    "apache-2": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "gpl": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version",
    "cc-by-nc": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License",
    "cc-by": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "mpl-2": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
    "reserved": "All rights reserved. No part of this publication may be reproduced, distributed, or transmitted in any form or by any means",
}
K = 3
#: Words whose hashes a Python worker remembers, and bytes of text that it takes at once.
KNOWN_WORDS, SLICE_BYTES = 400_000, 2_000_000
#: Diagonals this far apart join; least share of a wording's words that a verified span repeats.
MERGE_GAP, LEAST_SHARE = 3, 0.6


class Grams:
    """Two independent 64-bit hashes of every rolling word k-gram of many texts, from hashes of the words."""

    def __init__(self) -> None:
        rng = np.random.default_rng(11)
        self.factors = rng.integers(1, 2**63, (2, K), dtype=np.uint64) * 2 + 1
        self.known: dict[bytes, int] = {}
        self.hashes = np.zeros((2, 1 << 12), np.uint64)

    def _number(self, word: bytes) -> int:
        n = self.known[word] = len(self.known)
        if n >= self.hashes.shape[1]:
            self.hashes = np.concatenate([self.hashes, np.zeros_like(self.hashes)], axis=1)
        self.hashes[:, n] = xxhash.xxh3_64_intdigest(word, 1), xxhash.xxh3_64_intdigest(word, 2)
        return n

    def of(self, texts: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(text, place, hash, check) of each k-gram."""
        if len(self.known) > KNOWN_WORDS:
            self.known.clear()
        known, number = self.known, self._number
        numbers = np.array([known[w] if w in known else number(w) for words in texts for w in words], np.int64)
        sizes = np.array([len(w) for w in texts], np.int64)
        starts = np.cumsum(sizes) - sizes
        text = np.repeat(np.arange(len(texts)), sizes)
        n = max(len(numbers) - K + 1, 0)
        whole = np.flatnonzero(text[:n] == text[K - 1 : K - 1 + n])
        out = []
        for h, factors in zip(self.hashes, self.factors, strict=True):
            words = h[numbers]
            x = sum(words[whole + i] * factors[i] for i in range(K)) if len(whole) else np.zeros(0, np.uint64)
            x = x ^ (x >> np.uint64(29))
            out.append((x * np.uint64(0x9E3779B97F4A7C15)).view(np.int64))
        return text[whole], whole - starts[text[whole]], *out


def templates(spark, phrases: dict[str, str] = PHRASES, wordings: dict[str, str] = WORDINGS, notices: dict[str, str] = NOTICES) -> DataFrame:
    """One row a k-gram of each template: a fixed table of fixed size, so safe to broadcast."""
    texts = [(label, True, True, text) for text, label in phrases.items()] + [(label, False, True, text) for text, label in notices.items()]
    texts += [(label, False, False, text) for label, text in wordings.items()]
    words = [common.words_of(t[-1].encode()) for t in texts]
    if any(len(w) < K for w in words):
        raise ValueError(f"a template needs {K} words")
    rows = [(int(i), *texts[i][:3], len(words[i]), int(at), int(h), int(c)) for i, at, h, c in zip(*Grams().of(words), strict=True)]
    return spark.createDataFrame(rows, "template int, label string, phrase boolean, whole boolean, t_len int, t_at int, hash long, t_check long")


def _gram_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each k-gram, and one with place -1 and the number of words for each text."""
    common.fresh_worker()
    grams = Grams()
    for batch in common.small(batches):
        raws = common.raw_texts(batch)
        for a, b in common.slices([len(x) for x in raws], SLICE_BYTES):
            texts = [common.words_of(x) for x in raws[a:b]]
            text, at, h, check = grams.of(texts)
            every = np.arange(b - a)
            own = np.array([xxhash.xxh3_64_intdigest(x) for x in raws[a:b]], np.uint64).view(np.int64)
            who = np.concatenate([every, text])
            ids = batch.column(0).slice(a, b - a).take(pa.array(who))
            nothing = np.zeros(b - a, np.int64)
            columns = [np.concatenate([np.full(b - a, -1), at]).astype(np.int32), np.concatenate([np.array([len(w) for w in texts]), h]), np.concatenate([nothing, check])]
            yield pa.RecordBatch.from_arrays([ids, pa.array(own[who]), *map(pa.array, columns)], names=["doc_id", "text_id", "at", "hash", "check"])


def votes(docs: DataFrame, table: DataFrame) -> DataFrame:
    """Every k-gram joined to the template positions of its hash; rows with place -1 stand for the texts themselves."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    grams = docs.select("doc_id", "text").mapInArrow(_gram_rows, f"doc_id {kind}, text_id long, at int, hash long, check long")
    met = grams.join(F.broadcast(table), "hash", "left").filter((F.col("at") < 0) | (F.col("check") == F.col("t_check")))
    return met.select("doc_id", "text_id", "at", F.when(F.col("at") < 0, F.col("hash")).alias("n_words"), "template", "label", "phrase", "whole", "t_len", "t_at")


def license_spans(met: DataFrame) -> DataFrame:
    """Verified spans from ``votes``: doc_id, text_id, template, label, phrase, first and last word (inclusive), share."""
    hits = met.filter("at >= 0").select("doc_id", "text_id", "template", "label", "phrase", "whole", "t_len", "at", "t_at", (F.col("at") - F.col("t_at")).alias("diagonal")).distinct()
    # one row a diagonal: votes and the words that it covers
    by = ["doc_id", "text_id", "template", "label", "phrase", "whole", "t_len"]
    kept = [c for c in by if c not in ("whole", "t_len")]
    diagonals = hits.groupBy(*by, "diagonal").agg(F.count("*").alias("votes"), F.min("at").alias("first"), (F.max("at") + K - 1).alias("last"), F.collect_set("t_at").alias("t_ats"))
    exact = diagonals.filter(F.col("whole") & (F.col("votes") == F.col("t_len") - (K - 1))).select(*kept, "first", "last", F.lit(1.0).alias("share"))
    # neighbours on the text's own scale of diagonals: a running count of the gaps numbers the merged ones
    order = Window.partitionBy(*by).orderBy("diagonal")
    gap = (F.col("diagonal") - F.lag("diagonal").over(order) > MERGE_GAP).cast("int")
    numbered = diagonals.filter(~F.col("whole")).withColumn("gap", F.coalesce(gap, F.lit(0))).withColumn("group", F.sum("gap").over(order))
    merged = numbered.select(*by, "group", "first", "last", F.explode("t_ats").alias("t_at")).groupBy(*by, "group").agg(F.min("first").alias("first"), F.max("last").alias("last"), F.collect_set("t_at").alias("t_ats"))
    covered = F.size(F.array_distinct(F.flatten(F.transform("t_ats", lambda i: F.sequence(i, i + (K - 1))))))
    close = (F.col("last") - F.col("first") + 1) <= 2 * F.col("t_len")
    voted = merged.withColumn("share", covered / F.col("t_len")).filter(close & (F.col("share") >= LEAST_SHARE)).select(*kept, "first", "last", "share")
    return exact.unionByName(voted)


def scan_licenses(docs: DataFrame, table: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for each row of ``docs``."""
    met = common.persist_shared(votes(docs, table))
    spans = license_spans(met)
    summed = spans.groupBy("doc_id", "text_id").agg(
        F.count_if("phrase").alias("n_base"),
        F.min(F.when(F.col("phrase"), F.col("first"))).cast("long").alias("first_word"),
        F.max(F.when(F.col("phrase"), F.col("first"))).cast("long").alias("last_word"),
        F.array_sort(F.collect_set(F.when(F.col("phrase"), F.col("label")))).alias("base"),
        F.array_sort(F.collect_set("label")).alias("all"),
        F.max("share").alias("score"),
    )
    rows = met.filter("at < 0").select("doc_id", "text_id", "n_words")
    both = rows.alias("r").join(summed.alias("s"), F.col("r.doc_id").eqNullSafe(F.col("s.doc_id")) & (F.col("r.text_id") == F.col("s.text_id")), "left")
    return both.select(
        "r.doc_id", "n_words", F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"), "first_word", "last_word",
        F.coalesce(F.concat_ws(",", "base"), F.lit("")).alias("base_labels"), F.coalesce(F.concat_ws(",", "all"), F.lit("")).alias("labels"),
        F.coalesce(F.round("score", 6), F.lit(0.0)).alias("score"),
    )


def query(spark, sf_dir: str) -> DataFrame:
    return scan_licenses(common.load(spark, sf_dir, "documents").select("doc_id", "text"), templates(spark))


ORACLE = None
"""Base columns have a brute-force twin in the tests; the voted labels are checked there too."""
