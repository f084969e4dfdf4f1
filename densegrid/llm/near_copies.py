"""Near-copies by Jaccard likeness of word shingles, without loss.

Two texts are linked if their sets of five-word shingles have a Jaccard likeness
of ``LIKE`` or more. Candidates come from the SimHash index, which folds most of
a group cheaply, and from shared rare shingles: sets that are so alike share one
among the first few of each in any common order, so no pair is lost. A
candidate goes unread if the parities of its two sets differ in more bits than
alike sets can; every other is verified on the whole sets before it links.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window, functions as F

from densegrid.llm._text import column, mix, of_columns, text_slices, words_of
from densegrid.llm._skew import hot_join
from densegrid.llm.simhash import leading_rows, links, simhash
from densegrid.operators.components import components
from densegrid.plans.lineage import Cut, cut
from densegrid.plans.shipping import ship

SHINGLE = 5
#: The likeness as a fraction of whole numbers, so that the test is exact.
LIKE = (4, 5)
#: Documents whose shingles are counted to find common ones, and how many of those are kept; they only set the order.
COUNTED, COMMON = 20_000, 1 << 18
#: 64-bit words of a set's parities; more of them rule out more pairs, and never an alike one.
PARITY = 8
_ODD = np.uint64(0x9E3779B97F4A7C15)


def shingle_sets(texts: list[bytes | None]) -> Iterator[np.ndarray]:
    """For each text its distinct shingles as sorted 64-bit hashes; fewer than SHINGLE words are one shingle."""
    _, _, _, h, first = words_of(texts)
    chain = lambda parts: [g := np.uint64(1) * np.ones_like(parts[0]), *(g := mix(g * _ODD + x) for x in parts)][-1]
    every = chain([h[k : len(h) - SHINGLE + 1 + k] for k in range(SHINGLE)]) if len(h) >= SHINGLE else h[:0]
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= SHINGLE:
            yield np.unique(every[a : b - SHINGLE + 1])
        else:
            yield chain([h[k : k + 1] for k in range(a, b)]) if b > a else h[:0]


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sorted sets have a Jaccard likeness of LIKE or more."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * LIKE[1] >= LIKE[0] * (len(a) + len(b) - both)


def parities(shingles: np.ndarray) -> np.ndarray:
    """For each of 64 * PARITY classes of shingles whether the set has an odd number of them, as PARITY words.

    Every shingle that only one of two sets has turns one bit, so the sets differ
    in at least as many shingles as their parities do in bits.
    """
    odd = np.bincount((shingles % np.uint64(64 * PARITY)).astype(np.int64), minlength=64 * PARITY) & 1
    return np.packbits(odd.astype(bool), bitorder="little").view(np.int64)


def may_be_alike() -> Column:
    """Whether sets of n and m shingles with parities p0, p1, ... and q0, q1, ... can have a likeness of LIKE."""
    n, m = F.col("n"), F.col("m")
    differ = sum((F.bit_count(F.col(f"p{i}").bitwiseXOR(F.col(f"q{i}"))) for i in range(PARITY)), F.lit(0))
    sizes = F.least(n, m) * LIKE[1] >= F.greatest(n, m) * LIKE[0]
    return sizes & (differ * (LIKE[1] + LIKE[0]) <= (n + m) * (LIKE[1] - LIKE[0]))


def may_meet_first() -> Column:
    """Whether sets as alike can have their first common shingle, in the order of the prefixes, at their places i and j.

    Before it they share nothing, so no more than what follows it in either set.
    An alike pair meets this at its first common shingle, and so is never lost.
    """
    n, m = F.col("n"), F.col("m")
    return F.least(n - F.col("i"), m - F.col("j")) * (LIKE[1] + LIKE[0]) >= (n + m) * LIKE[0]


def prefix(shingles: np.ndarray, common: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The first shingles, rare ones before common ones, of which a set as alike must have one among its own first."""
    n = len(shingles)
    if not n:
        return shingles
    at = np.minimum(np.searchsorted(common, shingles), max(0, len(common) - 1))
    place = np.where(common[at] == shingles, rank[at], -1) if len(common) else np.full(n, -1)
    return shingles[np.lexsort((shingles, place))[: n - -(-n * LIKE[0] // LIKE[1]) + 1]]


def _node(shingles: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(shingles.tobytes()) - (1 << 63)


def _common(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hashes, sorted, and frequency ranks of shingles that are common in some of the documents."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, texts in text_slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*shingle_sets(texts), np.empty(0, np.uint64)]).view(np.int64))], ["k"])

    total = docs.count()
    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int(min(1.0, COUNTED / max(1, total)) * (1 << 20)))
    found = some.mapInArrow(run, "k long").groupBy("k").agg(F.count("*").alias("c")).where("c > 2").orderBy(F.desc("c"), "k").limit(COMMON).toArrow()
    keys = found.column("k").to_numpy().view(np.uint64)
    order = np.argsort(keys)
    return keys[order], (len(keys) - order).astype(np.int64)


def _marks(docs: DataFrame) -> DataFrame:
    """(doc_id, th, node, n, fp, keys, p0, ...): th is a hash of the text, node names the text's shingle set, keys is its prefix."""
    odd = [f"p{i}" for i in range(PARITY)]
    shipped = ship(docs.sparkSession, _common(docs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common, rank = shipped()
        for batch in batches:
            for at, texts in text_slices(batch, "text"):
                sets = list(shingle_sets(texts))
                keys = [prefix(s, common, rank).view(np.int64) for s in sets]
                fps = np.array([simhash(t, SHINGLE) for t in texts], np.uint64).view(np.int64)
                ends = np.cumsum([0, *map(len, keys)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*keys, np.empty(0, np.int64)])))
                bits = np.array([parities(s) for s in sets], np.int64).reshape(-1, PARITY)
                own = [batch.column(0).slice(at, len(texts)), batch.column(2).slice(at, len(texts)), pa.array([_node(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(fps), lists]
                yield pa.RecordBatch.from_arrays([*own, *map(pa.array, np.ascontiguousarray(bits.T))], ["doc_id", "th", "node", "n", "fp", "keys", *odd])

    return docs.withColumn("th", F.xxhash64("text")).mapInArrow(run, "doc_id long, th long, node long, n long, fp long, keys array<long>, " + ", ".join(f"{c} long" for c in odd))


def verified(docs: DataFrame, nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """Those of the ``pairs`` (a, b) of nodes whose whole sets are alike."""
    asked = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    ids = cut(nodes.join(asked, "node", "left_semi").select("doc_id").distinct())  # of known size, so that few are broadcast

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, texts in text_slices(batch, "text"):
                pressed = [pa.compress(t or b"", codec="zstd", asbytes=True) for t in texts]
                yield pa.RecordBatch.from_arrays([pa.array([_node(s) for s in shingle_sets(texts)], pa.int64()), pa.array([len(t or b"") for t in texts], pa.int64()), pa.array(pressed, pa.binary())], ["node", "size", "text"])

    # Compressed texts take a third of the room of shingle sets, which are made again where two texts meet.
    held = Cut(docs.join(ids, "doc_id", "left_semi").select("text").mapInArrow(read, "node long, size long, text binary"))  # repeated ids may repeat a text, which only repeats links

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, own = None, None
        for batch in batches:
            good = []
            for a, m, x, n, y in zip(*(column(batch, c) for c in ("a", "m", "x", "n", "y")), strict=True):
                if a != last:  # the rows come sorted by their first text
                    last, own = a, next(shingle_sets([pa.decompress(x, m, "zstd", asbytes=True) if m else b""]))
                good.append(alike(own, next(shingle_sets([pa.decompress(y, n, "zstd", asbytes=True) if n else b""]))))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    side = lambda node, size, text: held.frame.select(F.col("node").alias(node), F.col("size").alias(size), F.col("text").alias(text))
    met = pairs.join(side("b", "n", "y"), "b").join(side("a", "m", "x"), "a")
    out = cut(met.select("a", "b", "m", "x", "n", "y").mapInArrow(test, "a long, b long"))
    held.drop()
    return out


def near_copies(docs: DataFrame) -> DataFrame:
    """(doc_id, component_id) for every row with a doc_id: the smallest doc_id reachable over links of likeness."""
    rows = grouped(docs)
    return hot_join(rows, rows.groupBy("root").agg(F.min("doc_id").alias("component_id")), "root").select("doc_id", "component_id")


def grouped(docs: DataFrame) -> DataFrame:
    """(doc_id, th, root) for every row with a doc_id: a hash of its text, and what names its group.

    Texts with one and the same set fold into a node first (sets are told apart by
    64-bit hashes); texts without words are one node. A shared shingle first pairs
    its texts with one leader only, by chance another for each shingle, so that large
    groups fold in pairs as many as texts have shingles; then all pairs that are still apart and share a shingle are verified.
    """
    some = of_columns(docs, doc_id="long", text="binary").where("doc_id IS NOT NULL")
    marked = Cut(_marks(some))  # what is dropped below is large, and read for the last time by the cut before
    marks = marked.frame
    members = cut(marks.select("doc_id", "th", "node"))
    odd, even = ([f"{c}{i}" for i in range(PARITY)] for c in "pq")
    nodes = cut(marks.groupBy("node").agg(F.min("doc_id").alias("doc_id"), *[F.min(c).alias(c) for c in ("n", "fp", *odd)]))
    sizes = nodes.select("node", "n", *odd)
    met = Window.partitionBy("key")  # one shuffle of the keys; common ones stand last in the order, so few texts bring them
    keyed = marks.select("node", F.posexplode("keys").alias("i", "key")).select("*", F.min_by("node", F.xxhash64("key", "node")).over(met).alias("lead"), (F.min("node").over(met) < F.max("node").over(met)).alias("met"))
    asked = Cut(keyed.where("met").drop("met").distinct().join(sizes, "node"))
    shared = asked.frame
    marked.drop()
    sizes = sizes.withColumnsRenamed({"node": "lead", "n": "m", **dict(zip(odd, even, strict=True))})
    star = shared.where("node <> lead").drop("key", "i").distinct().join(sizes, "lead").where(may_be_alike()).select(F.col("lead").alias("a"), F.col("node").alias("b"))
    prints = nodes.groupBy("fp").agg(F.min("node").alias("least"))
    same = nodes.join(prints, "fp").where("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b"))
    index = links(prints.select("fp"))
    at = [prints.select(F.col("fp").alias(c), F.col("least").alias(f"_{c}")) for c in "ab"]
    bits = index.join(at[0], "a").join(at[1], "b").select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b"))
    first = verified(some, nodes, cut(star.unionByName(same).unionByName(bits).distinct()))
    found = cut(components(first))
    held = shared.join(found, "node", "left").select("key", "i", "node", "n", F.coalesce("root", "node").alias("root"), *odd)
    apart = held.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 < r1").select("key")
    left = Cut(held.join(apart, "key", "left_semi"))
    held = left.frame
    asked.drop()
    other = held.withColumnsRenamed({"node": "node2", "i": "j", "n": "m", "root": "root2", **dict(zip(odd, even, strict=True))})
    cross = held.join(other, "key").where((F.col("node") < F.col("node2")) & (F.col("root") != F.col("root2")) & may_meet_first() & may_be_alike()).select(F.col("node").alias("a"), F.col("node2").alias("b")).distinct()
    cross = cut(cross)
    left.drop()
    done = components(first.unionByName(verified(some, nodes, cross)))
    roots = nodes.join(done, "node", "left").select("node", F.coalesce("root", "node").alias("root"))
    return cut(hot_join(members, roots, "node").select("doc_id", "th", "root"))


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that lead their group (``simhash.leading_rows``), with all their columns."""
    return leading_rows(docs, grouped(docs))
