import random

from densegrid.llm import decontaminate
from tests.llm.test_operators import prose


def test_scores_do_not_depend_on_parts(spark):
    """Parts of one item would weigh all words alike."""
    rng = random.Random(21)
    items = [(i, "what of the " + prose(12, rng) + "?\nthe one of the " + prose(rng.randint(10, 60), rng)) for i in range(12)]
    docs = [(i, prose(60, rng) + " " + t + " " + prose(60, rng)) for i, t in items]
    docs += [(100 + i, prose(50, rng) + " " + " ".join(t.split()[: len(t.split()) * 2 // 3]) + " " + prose(50, rng)) for i, t in items]
    bench, df = spark.createDataFrame(items, "item_id bigint, text string"), spark.createDataFrame(docs, "doc_id bigint, text string")
    found = [sorted((r["doc_id"], r["item_id"], round(r["score"], 9)) for r in decontaminate.find_leaks(df, bench, size).collect()) for size in (1000, 12, 11, 5, 1)]
    assert found[0] and all(f == found[0] for f in found[1:])
