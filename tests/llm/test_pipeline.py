import random

import corpus_pipeline
from sparsehop.llm import lines, neardup

from .test_operators import prose


def tables(spark, tmp_path):
    rows, marks = [], []
    for i in range(160):
        toxic = i % 8 == 0
        rows.append((i, prose(1000 + i, 60, 400) + (" idiot and moron" if toxic else ""), "en", "s", 1))
        marks.append((i, 1, int(toxic)))
    bench = [(1, prose(5, 40, 900)), (2, prose(6, 40, 900))]
    edited = rows[3][1].split()
    edited[30] = "other"
    line = prose(77, 20, 300)
    rows += [(200, rows[1][1], "en", "s", 1), (201, " ".join(edited), "en", "s", 1), (202, f"{prose(9, 30, 800)} {bench[0][1]}", "en", "s", 1), (203, f"{line}\n{prose(10, 30, 700)}", "en", "s", 1), (204, f"{prose(11, 30, 700)}\n{line}x", "en", "s", 1), (205, None, "en", "s", 0)]
    random.Random(1).shuffle(rows)
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(marks, "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame(bench, "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    return {r[0]: r[1] for r in rows}, {m[0] for m in marks if m[2]}, line


def test_stages_take_effect_and_keep_clean_documents(spark, tmp_path):
    texts, toxic, line = tables(spark, tmp_path)
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.persist_shared(stage(spark, docs, str(tmp_path)))
        seen[name] = {r.doc_id: r for r in docs.collect()}
        if name != "bpe":
            assert docs.columns == corpus_pipeline.COLUMNS
    assert set(texts) - set(seen["toxicity"]) == toxic
    deduped = seen["line_dedup"]
    assert deduped.keys() == seen["toxicity"].keys()
    assert line in deduped[203].text and line not in deduped[204].text and deduped[204].n_chars == len(deduped[204].text)
    assert deduped[200].text == "" and deduped[2].text == texts[2]
    kept = seen["near_duplicates"]
    assert 201 not in kept and 3 in kept and 205 in kept
    assert set(kept) - set(seen["decontaminate"]) == {202}
    assert set(seen["bpe"]) == set(seen["decontaminate"])
    again = {r.doc_id: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert {k: v.ids_sha256 for k, v in again.items()} == {k: v.ids_sha256 for k, v in seen["bpe"].items()}
    assert lines.MIN_CHARS == 20 and neardup.THRESHOLD == 0.8


def test_short_equal_lines_go_and_short_near_lines_stay(spark):
    long = prose(1, 12, 99)
    texts = {1: "Les.\nAnd ornd.\n\nLes.", 2: f"Les.\n{long}\nx\n", 3: f"Lest.\nLes.\n{long}é\nx\nAnd ornd", 4: "Les.", 5: None, 6: ""}
    docs = spark.createDataFrame([(d, t, "en", "s", len(t or "")) for d, t in texts.items()], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = {r.doc_id: (r.text, r.n_chars) for r in corpus_pipeline.drop_repeated_lines(spark, docs, "").collect()}
    want = {1: "Les.\nAnd ornd.\n", 2: f"{long}\nx\n", 3: "Lest.\nAnd ornd", 4: "", 5: None, 6: ""}
    assert got == {d: (t, len(t or "")) for d, t in want.items()}
