import random

import corpus_pipeline
import numpy as np

from densegrid.llm import near_copies
from tests.llm.test_operators import prose


def shingles(text):
    ws = (text or "").translate({c: c + 32 for c in range(65, 91)}).encode().split()
    return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))} if ws else set()


def leaders(rows):
    """Smallest id reachable over pairs with a Jaccard likeness of 0.8, all pairs compared."""
    sets = {i: shingles(t) for i, t in rows.items()}
    lead = {i: i for i in rows}
    linked = [(i, j) for i in rows for j in rows if i < j and len(sets[i] & sets[j]) * 5 >= 4 * len(sets[i] | sets[j])]
    for _ in rows:
        for i, j in linked:
            lead[i] = lead[j] = min(lead[i], lead[j])
    return lead


def edited_copies():
    rng = random.Random(11)
    common, rows = prose(30, rng), {}
    for k in range(12):
        words = prose(rng.randint(60, 200), rng).split()
        rows[len(rows)] = " ".join(words)
        for edits in (1, 2, 3, 4, 8):
            copy = list(words)
            for at in rng.sample(range(len(copy)), edits):
                copy[at] = "edited"
            rows[len(rows)] = " ".join(copy)
        rows[len(rows)] = common + " " + prose(rng.randint(1, 60), rng)
    return rows | {500: "", 501: " ", 502: "one two", 503: "One  two", 504: "two one"}


def test_stage_drops_all_edited_copies(spark, sf):
    rows = edited_copies()
    lead = leaders(rows)
    docs = spark.createDataFrame(list(rows.items()), "doc_id bigint, text string")
    kept = {r["doc_id"] for r in corpus_pipeline.STAGES[2][1](spark, docs, sf).collect()}
    assert kept == {i for i in rows if lead[i] == i}


def test_recall_on_documents_is_whole(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = {r["doc_id"]: r["component_id"] for r in near_copies.near_copies(docs).collect()}
    assert got == leaders(rows)


def test_alike_sets_share_a_prefix_in_any_order():
    r = np.random.default_rng(2)
    for _ in range(300):
        n = int(r.integers(1, 60))
        a = np.unique(r.integers(0, 1 << 60, n).astype(np.uint64))
        b = np.unique(np.concatenate([a[r.random(len(a)) > 0.1], r.integers(0, 1 << 60, 2).astype(np.uint64)]))
        common = np.unique(r.choice(a, len(a) // 2 + 1))
        rank = r.permutation(len(common))
        if near_copies.alike(a, b):
            assert np.intersect1d(near_copies.prefix(a, common, rank), near_copies.prefix(b, common, rank)).size


def test_parities_never_differ_in_more_bits_than_the_sets_do_in_shingles():
    r = np.random.default_rng(3)
    for size in (0, 1, 5, 80, 3000):
        a = np.unique(r.integers(0, 1 << 60, size).astype(np.uint64))
        for share in (0.0, 0.05, 0.3, 1.0):
            b = np.unique(np.concatenate([a[r.random(len(a)) >= share], r.integers(0, 1 << 60, int(size * share)).astype(np.uint64)]))
            bits = int(np.bitwise_count((near_copies.parities(a) ^ near_copies.parities(b)).view(np.uint64)).sum())  # of signed words it counts the absolute value
            assert bits <= len(np.setxor1d(a, b)) and (share or not bits)
