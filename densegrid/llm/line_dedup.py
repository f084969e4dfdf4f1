"""Removing repeated passages found as windows of three consecutive lines.

Lines are hashed three at a time with an overlap of two; a window that occurs
anywhere before, in the order of (doc_id, position), marks its lines, and the
marked positions of a document merge into the spans that go.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

WINDOW = 3
_BLANKS = " \t\r\x0b\x0c"


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def windows(docs: DataFrame) -> DataFrame:
    """(doc_id, th, i0, i2, h1, h2): every window of three consecutive non-blank lines.

    i0 and i2 are its first and last line numbers, h1 and h2 a 128-bit hash of
    its trimmed lines, th the text's own hash, which tells rows of one id apart.
    """
    numbered = F.transform(_lines(F.col("text")), lambda s, i: F.struct(i.alias("i"), F.btrim(s, F.lit(_BLANKS)).alias("s")))
    solid = docs.select("doc_id", "th", F.filter(numbered, lambda x: x["s"] != "").alias("b")).where(F.size("b") >= WINDOW)

    def at(j: Column) -> Column:
        x = [F.col("b")[j + k] for k in range(WINDOW)]
        s = [c["s"] for c in x]
        return F.struct(x[0]["i"].alias("i0"), x[-1]["i"].alias("i2"), F.xxhash64(*s).alias("h1"), F.xxhash64(F.lit(1), *s).alias("h2"))

    found = solid.select("doc_id", "th", F.explode(F.transform(F.sequence(F.lit(0), F.size("b") - WINDOW), at)).alias("w"))
    return found.select("doc_id", "th", "w.*")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with later occurrences of repeated three-line passages cut out of ``text``.

    All columns stay (``n_chars``, where there is one, follows the text) and a
    ``removed_lines`` column is added. The first occurrence by (doc_id, position)
    stays. Blank lines count in no window; those between covered lines go with
    them. Fewer than three non-blank lines: unchanged. Null texts stay null, a
    null doc_id sorts first. Rows of one id and equal texts count as one document.
    A hot passage is counted by partial aggregates and its join may be split.
    """
    kept = [(c, c if c in ("doc_id", "text", "n_chars") else f"c{i}") for i, c in enumerate(docs.columns) if c != "removed_lines"]
    out = _dedup(docs.select(*[F.col(f"`{c}`").alias(plain) for c, plain in kept]))  # other names can't clash with this module's
    return out.select(*[F.col(plain).alias(c) for c, plain in kept], "removed_lines")


def _dedup(docs: DataFrame) -> DataFrame:
    base = docs.select(*[f"`{c}`" for c in docs.columns if c not in ("th", "removed_lines")]).withColumn("th", F.xxhash64("text"))
    occ = windows(base.select("doc_id", "th", "text").where("text IS NOT NULL"))
    place = F.struct("doc_id", "th", "i0")
    dups = occ.groupBy("h1", "h2").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    later = occ.join(dups, ["h1", "h2"]).where(~place.eqNullSafe(F.col("first")))
    cover = later.groupBy("doc_id", "th").agg(F.collect_set(F.struct("i0", "i2")).alias("spans")).withColumnsRenamed({"doc_id": "_id", "th": "_th"})
    rows = base.join(cover, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("th") == F.col("_th")), "left")
    lines = _lines(F.col("text"))
    gone = F.flatten(F.transform("spans", lambda s: F.sequence(s["i0"], s["i2"])))
    rows = rows.withColumn("_keep", F.when(F.col("spans").isNotNull(), F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), gone)))
    text = F.when(F.col("_keep").isNull(), F.col("text")).otherwise(F.array_join(F.transform("_keep", lambda i: lines[i]), "\n"))
    rows = rows.withColumn("removed_lines", F.when(F.col("_keep").isNull(), F.lit(0)).otherwise(F.size(lines) - F.size("_keep"))).withColumn("text", text)
    if "n_chars" in docs.columns:
        rows = rows.withColumn("n_chars", F.char_length("text").cast("long"))
    return rows.select(*[f"`{c}`" for c in docs.columns if c != "removed_lines"], "removed_lines")
