"""Canonical exact fingerprints of documents, in DataFrame functions only.

A text is normalised to Unicode NFKC, case-folded, normalised again, and its
runs of white space become one space; the 128-bit fingerprint is two xxHash64
values of that canonical form with different seeds. Rows of one digest are
compared byte by byte; texts that collide get different fingerprints.

Spark has no normalisation function of its own, but ships the ICU library, whose
static methods the SQL function ``reflect`` calls inside the JVM. Pure ASCII
texts, which normalisation leaves alone, take ``lower`` instead.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from densegrid.plans.lineage import cut

#: Ids and digests that a semi-join may broadcast (some 20 MB each); more are joined by a shuffle.
BROADCAST_IDS, BROADCAST_DIGESTS = 1_000_000, 200_000


def _compose(c: Column) -> Column:
    return F.reflect(F.lit("com.ibm.icu.text.Normalizer"), F.lit("compose"), c, F.lit(True))


def canonical(text: Column) -> Column:
    """NFKC, full case folding, NFKC again, white space as single spaces, trimmed."""
    folded = F.reflect(F.lit("com.ibm.icu.lang.UCharacter"), F.lit("foldCase"), _compose(text), F.lit(True))
    any_script = F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(_compose(folded))
    return F.trim(F.regexp_replace(any_script, r"[\s\p{Z}]+", " "))


def digest(canon: Column) -> Column:
    """32 hex digits: xxHash64 under seed 42 and under a second, derived seed."""
    halves = [F.lpad(F.lower(F.hex(h)), 16, "0") for h in (F.xxhash64(canon), F.xxhash64(F.lit(1), canon))]
    return F.concat(*halves)


def successors(ids: DataFrame, key: str) -> DataFrame:
    """Adds ``next_<key>``: the next smaller key, for the smallest the largest.

    ``ids`` has distinct keys (a null counts as the smallest). They are sorted by
    range over all partitions; only each partition's first key meets the others'.
    """
    spread = cut(ids.repartitionByRange(F.col(key).desc_nulls_last()).withColumn("_part", F.spark_partition_id()))
    down = F.col(key).desc_nulls_last()
    inside = spread.withColumn("_next", F.lead(F.struct(key)).over(Window.partitionBy("_part").orderBy(down)))
    heads = spread.groupBy("_part").agg(F.max(F.struct(F.col(key).isNotNull().alias("known"), F.col(key).alias("k"))).alias("head"))
    ring = Window.orderBy("_part")  # one row per partition
    every = Window.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    heads = heads.select("_part", F.coalesce(F.lead("head").over(ring), F.first("head").over(every))["k"].alias("_wrap"))
    return inside.join(F.broadcast(heads), "_part").select(*ids.columns, F.when(F.col("_next").isNotNull(), F.col("_next")[key]).otherwise(F.col("_wrap")).alias(f"next_{key}"))


def collision_ranks(texts: DataFrame, prints: DataFrame) -> DataFrame:
    """(digest, canon, rank) of the texts that share a digest with another text: empty but for hash collisions.

    ``texts``: doc_id, text. ``prints``: doc_id, digest. Only documents of digests
    that occur twice are read; copies fold in the partial aggregate.
    """
    twice = cut(prints.groupBy("digest").agg(F.count("*").alias("_n")).where("_n > 1").select("digest"))
    few = twice.count() <= BROADCAST_DIGESTS  # then the rows of a huge group needn't meet in one partition
    ids = cut(prints.join(F.broadcast(twice) if few else twice, "digest", "left_semi").select("doc_id").distinct())
    small = ids.count() <= BROADCAST_IDS
    some = texts.join(F.broadcast(ids) if small else ids, texts["doc_id"].eqNullSafe(ids["doc_id"]), "left_semi")
    groups = some.select(canonical(F.col("text")).alias("canon")).withColumn("digest", digest(F.col("canon"))).groupBy("digest", "canon").agg(F.count("*").alias("_n"))
    clash = groups.groupBy("digest").agg(F.count("*").alias("_n")).where("_n > 1").select("digest")
    return cut(groups.join(clash, "digest", "left_semi").select("digest", "canon", (F.row_number().over(Window.partitionBy("digest").orderBy("canon")) - 1).alias("rank")))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint for every row; equal canonical texts, and only they, share one.

    A null text counts as empty. Rows with a null or a repeated id are rows like
    any other. No rows give no rows; other columns are ignored.
    """
    texts = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    prints = cut(texts.select("doc_id", canonical(F.col("text")).alias("canon")).select("doc_id", digest(F.col("canon")).alias("digest")))
    ranks = collision_ranks(texts, prints)
    if ranks.isEmpty():
        return prints.select("doc_id", F.col("digest").alias("fingerprint"))
    every = texts.select("doc_id", canonical(F.col("text")).alias("canon")).withColumn("digest", digest(F.col("canon")))
    return every.join(ranks, ["digest", "canon"], "left").select("doc_id", F.concat("digest", F.when(F.col("rank") > 0, F.concat(F.lit("-"), "rank")).otherwise("")).alias("fingerprint"))


def fingerprint_report(docs: DataFrame) -> DataFrame:
    """The contract rows: fingerprints of each text and of its edited form, and their likeness.

    The edited text has its last floor(n/2) code points replaced by the first as
    many of the next document in descending ``doc_id``. Rows that share a doc_id
    share their successor; of a successor's several rows the one with the least
    text hash counts. A single document follows itself. Likeness is 1 for equal
    fingerprints, else 0: an exact digest knows no degrees.
    """
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    ids = base.groupBy("doc_id").agg(F.max(F.char_length("text")).alias("n"), F.min(F.xxhash64("text")).alias("h"))
    order = successors(ids, "doc_id")
    want = order.select(F.col("next_doc_id").alias("want_id"), F.col("doc_id").alias("for_id"), F.floor(F.col("n") / 2).cast("int").alias("k"))
    want = want.join(order.select(F.col("doc_id").alias("own_id"), "h"), F.col("want_id").eqNullSafe(F.col("own_id"))).drop("own_id")
    head = base.join(want.hint("merge"), base["doc_id"].eqNullSafe(want["want_id"]), "left")
    head = head.where(F.col("h").bitwiseXOR(F.xxhash64("text")) == 0)  # no join key, so that both joins share one exchange of the texts
    head = head.select("for_id", F.substring("text", F.lit(1), F.col("k")).alias("prefix"), canonical(F.col("text")).alias("canon"))
    head = head.select("for_id", "prefix", digest(F.col("canon")).alias("next_digest")).dropDuplicates(["for_id"])
    rows = base.join(head.hint("merge"), base["doc_id"].eqNullSafe(head["for_id"]), "left")
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - half), F.substring("prefix", F.lit(1), half))
    rows = rows.select("doc_id", n.cast("long").alias("n_chars"), F.col("text"), edited.alias("edited"), "next_digest")
    rows = rows.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), canonical(F.col("text")).alias("canon"), canonical(F.col("edited")).alias("edited_canon"), "next_digest")
    rows = cut(rows.select("doc_id", "n_chars", "edited_sha256", digest(F.col("canon")).alias("digest"), digest(F.col("edited_canon")).alias("edited_digest"), (F.col("canon") == F.col("edited_canon")).alias("same"), "next_digest"))
    ranks = collision_ranks(base, rows.select("doc_id", "digest"))
    mark = F.col("digest")
    if not ranks.isEmpty():  # two texts of one digest: the texts' own order tells them apart
        marks = base.select("doc_id", canonical(F.col("text")).alias("canon")).withColumn("digest", digest(F.col("canon"))).join(ranks, ["digest", "canon"]).select(F.col("doc_id").alias("_id"), F.col("digest").alias("_digest"), "rank").distinct()
        rows = rows.join(marks, rows["doc_id"].eqNullSafe(marks["_id"]) & (rows["digest"] == marks["_digest"]), "left")
        mark = F.concat("digest", F.when(F.col("rank") > 0, F.concat(F.lit("-"), "rank")).otherwise(""))
    return rows.select(
        "doc_id", "n_chars", "edited_sha256", mark.alias("fingerprint"),
        F.when(F.col("same"), mark).otherwise(F.col("edited_digest")).alias("edited_fingerprint"),
        F.col("same").cast("double").alias("near_edited"), (F.col("digest") == F.col("next_digest")).cast("double").alias("near_next"),
    )
