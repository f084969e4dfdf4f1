import os

from pyspark.sql import functions as F

from densegrid.llm import near_copies
from densegrid.plans import lineage
from tests.llm.test_near_copies import edited_copies, leaders


def shuffle_files(spark):
    found = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {f for f in (found.apply(i).getName() for i in range(found.size())) if f.startswith("shuffle_") and f.endswith(".data")}


def test_a_cut_leaves_no_shuffle_files(spark):
    before = shuffle_files(spark)
    got = lineage.cut(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert shuffle_files(spark) <= before and got.count() == 7
    assert spark.conf.get(lineage.CLEAN, None) in (None, "false")


def test_near_copies_drop_their_large_files(spark, monkeypatch):
    made = []

    class Seen(lineage.Cut):
        def __init__(self, df):
            super().__init__(df)
            made.append((self.path.removeprefix("file://"), df.columns))

    monkeypatch.setattr(near_copies, "Cut", Seen)
    rows = edited_copies()
    docs = spark.createDataFrame(list(rows.items()), "doc_id bigint, text string")
    assert {r["doc_id"]: r["component_id"] for r in near_copies.near_copies(docs).collect()} == leaders(rows)
    assert sum("keys" in c or "key" in c for _, c in made) == 3 and not any(os.path.exists(p) for p, _ in made)
