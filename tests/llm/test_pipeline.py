import random

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from densegrid.llm import decontaminate, langid, sentencepiece_codec
from tests.llm.test_near_copies import leaders
from tests.llm.test_operators import prose, python_dedup


def test_stage_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "line_dedup", "simhash_near_dedup", "benchmark_decontamination", "sentencepiece"]


def test_pipeline_equals_brute_force(spark, sf):
    """Each stage in plain Python on what the stage before kept."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    rows = {i: t for i, t in rows.items() if t and any(c.isalpha() for c in t)}
    rows = python_dedup(rows.items())
    lead = leaders(rows)
    rows = {i: rows[i] for i in sorted(rows) if lead[i] == i}
    items = [(r["item_id"], r["text"].encode()) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    asked = [decontaminate.question_answer(t) for _, t in items]
    kept = {}
    for i, t in rows.items():
        w = decontaminate.words(t.encode())
        have = {tuple(w[k : k + 5]) for k in range(len(w) - 4)}
        share = lambda part: decontaminate.overlap(part, have | {tuple(w[k : k + n]) for n in range(1, 5) for k in range(len(w) - n + 1)})  # noqa: B023, E731
        if not any(all(share(p) >= 0.5 for p in parts if p) for parts in asked):
            kept[i] = t
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.MODEL)
    got = {r["doc_id"]: r["ids"] for r in corpus_pipeline.run(spark, sf).collect()}
    assert got == {i: lib.encode(t) for i, t in kept.items()}


@pytest.mark.parametrize("k", range(5))
def test_stages_take_nulls_repeated_ids_clashing_columns_and_no_rows(spark, sf, k):
    rows = [(1, "a first text that has its own words to say", "en", "s", 1), (1, "zwei andere ganz eigene worte stehen hier drin", "de", "s", 1), (1, "a first text that has its own words to say", "en", "s", 1), (None, "a text without any id at all here", None, None, None), (None, None, None, None, None), (7, None, "en", None, None), (8, "", "en", "s", 0), (9, "x" * 5000, "en", "s", 5000)]
    docs = spark.createDataFrame([(*r, 1.0, "x", [1], 2, True) for r in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, node string, ids array<int>, n_tokens int, _th boolean")
    stage = corpus_pipeline.STAGES[k][1]
    kept = {(r["doc_id"], r["text"]) for r in stage(spark, docs, sf).collect()} if k < 4 else None
    if k == 4:
        assert stage(spark, docs, sf).count() == len(rows)
    else:
        assert {(1, rows[0][1]), (1, rows[1][1]), (None, rows[3][1])} <= kept  # both texts of the repeated id stay
    assert stage(spark, docs.limit(0), sf).count() == 0


@pytest.mark.parametrize("k", range(4))
def test_stages_keep_columns_and_clean_documents(spark, sf, k):
    rng = random.Random(k)
    docs = spark.createDataFrame([(i, prose(60, rng), "en", "s", 1, 2.0, "z") for i in range(30)] + [(50, None, None, None, None, None, None)], "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, lang_pred string")
    out = corpus_pipeline.STAGES[k][1](spark, docs, sf)
    assert out.columns == docs.columns
    assert out.where("doc_id < 30").count() == 30
    assert corpus_pipeline.STAGES[k][1](spark, docs.limit(0), sf).count() == 0


def test_language_stage_rejects_texts_without_letters(spark, sf):
    docs = spark.createDataFrame([(1, "words here", "en"), (2, "12 34 !!", "en"), (3, None, "en"), (4, "mehr davon", "de")] + [(10 + i, f"word {i} and more", "en") for i in range(9)], "doc_id bigint, text string, lang string")
    left = {r["doc_id"] for r in corpus_pipeline.STAGES[0][1](spark, docs, sf).collect()}
    assert 2 not in left and 3 not in left and {1, 4, 10} <= left
    assert langid.UNKNOWN == "und" and F is not None
