"""SimHash near-duplicates through a hierarchical index over Gray-ordered fingerprints.

Every pair of fingerprints within four differing bits agrees on one of five bit
blocks, so equal block values bring all such pairs together without a cross
join. Inside such a bucket the fingerprints are sorted by their rank in the
reflected Gray code; runs of neighbours form the leaves of a tree, whose upper
nodes hold the bits that all members share. A search adds the differences to a
node's own shared bits on the way down and drops whole groups beyond the limit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from densegrid.llm._skew import hot_join
from densegrid.llm._text import column, of_columns
from densegrid.operators.components import components
from densegrid.plans.lineage import cut

SEED, SHINGLE, LIMIT = 42, 4, 4
#: A bucket with more fingerprints than this is dealt by a second block as well.
BUCKET = 20_000
FANOUT, ASK = 8, 512


def simhash(text: bytes | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """The 64-bit fingerprint of a text; no words give 0, fewer than ``shingle`` words count as one shingle."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    whole = b" ".join(words)
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(whole, seed)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    digest, ones = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    pairs = zip(starts[: len(words) - shingle + 1].tolist(), ends[shingle - 1 :].tolist(), strict=True)
    total = len(words) - shingle + 1
    for at in range(0, total, 1 << 16):
        n = min(1 << 16, total - at)
        h = np.fromiter((digest(whole[s:e], seed) for (s, e), _ in zip(pairs, range(n), strict=False)), np.uint64, n)
        ones += np.unpackbits(h.view(np.uint8).reshape(n, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > total, bitorder="little").view(np.uint64)[0])


def text_hash(docs: DataFrame) -> Column:
    return F.xxhash64(docs["text"].cast("binary"))


def fingerprint_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, th): one row per document, fp as a signed 64-bit value, th a hash of the text as it stands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([simhash(t) for t in column(batch, "text")], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64)), batch.column(2)], ["doc_id", "fp", "th"])

    return of_columns(docs, doc_id="long", text="binary").withColumn("th", F.xxhash64("text")).mapInArrow(run, "doc_id long, fp long, th long")


def gray_rank(fps: np.ndarray) -> np.ndarray:
    """The position of each 64-bit pattern in the reflected Gray code."""
    rank = fps.copy()
    for s in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(s)
    return rank


class GrayTree:
    """An index over distinct fingerprints; ``near`` finds all within ``limit`` bits."""

    def __init__(self, fps: np.ndarray):
        self.order = np.argsort(gray_rank(fps), kind="stable")
        leaves = fps[self.order]
        both, some, sizes = leaves, leaves, []
        levels = [(both, some)]
        while len(levels[-1][0]) > 1:
            both, some = levels[-1]
            cuts = np.arange(0, len(both), FANOUT)
            levels.append((np.bitwise_and.reduceat(both, cuts), np.bitwise_or.reduceat(some, cuts)))
        self.nodes = []  # from the root down: pattern, bits shared here but not already above
        above = None
        for both, some in reversed(levels):
            shared = ~(both ^ some)
            own = shared if above is None else shared & ~np.repeat(above, FANOUT)[: len(shared)]
            self.nodes.append((both, own))
            above = shared
            sizes.append(len(both))

    def near(self, asked: np.ndarray, limit: int = LIMIT) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (row of ``asked``, row of the indexed fingerprints) within ``limit`` bits."""
        q, node, acc = np.arange(len(asked)), np.zeros(len(asked), np.int64), np.zeros(len(asked), np.int64)
        for depth, (pattern, own) in enumerate(self.nodes):
            if depth:
                n = len(q)
                node = (node[:, None] * FANOUT + np.arange(FANOUT)).ravel()
                q, acc = np.repeat(q, FANOUT), np.repeat(acc, FANOUT)
                there = node < len(pattern)
                if n and not there.all():
                    q, node, acc = q[there], node[there], acc[there]
            acc = acc + np.bitwise_count((asked[q] ^ pattern[node]) & own[node])
            alive = acc <= limit
            q, node, acc = q[alive], node[alive], acc[alive]
        return q, self.order[node]


def spanning_links(fps: np.ndarray, limit: int = LIMIT) -> list[tuple[int, int]]:
    """Links that connect exactly what all links within ``limit`` bits connect; fewer than fingerprints."""
    tree, parent = GrayTree(fps), list(range(len(fps)))

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    out = []
    for at in range(0, len(fps), ASK):
        q, other = tree.near(fps[at : at + ASK], limit)
        q = q + at
        keep = q < other
        for i, j in zip(q[keep].tolist(), other[keep].tolist(), strict=True):
            if (a := find(i)) != (b := find(j)):
                parent[max(a, b)] = min(a, b)
                out.append((i, j))
    return out


def _blocks(bits: int, parts: int) -> list[tuple[int, int]]:
    """(first bit, width) of ``parts`` blocks over ``bits`` bits."""
    edges = [bits * i // parts for i in range(parts + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:], strict=False)]


def links(prints: DataFrame, limit: int = LIMIT, bucket: int = BUCKET) -> DataFrame:
    """(a, b): links among the distinct fingerprints ``fp`` that connect all within ``limit`` bits.

    A bucket of more than ``bucket`` fingerprints is split by the value of a second
    block: its members agree on the first, so the same argument holds for the rest.
    """
    def value(of, first: int, width: int):
        return F.shiftrightunsigned(of, first).bitwiseAND(F.lit((1 << width) - 1))

    parts = _blocks(64, limit + 1)
    deal = [F.struct(F.lit(i).alias("part"), value(F.col("fp"), *p).alias("value")) for i, p in enumerate(parts)]
    keyed = prints.select("fp", F.explode(F.array(*deal)).alias("k")).select("fp", "k.*")
    large = keyed.groupBy("part", "value").agg(F.count("*").alias("n")).where(F.col("n") > bucket).select("part", "value", F.lit(True).alias("large"))
    keyed = keyed.join(large, ["part", "value"], "left")
    split = F.array(F.struct(F.lit(-1).alias("part2"), F.lit(0).cast("long").alias("value2")))
    for i, (first, width) in enumerate(parts):
        turned = F.shiftleft("fp", 64 - first - width).bitwiseOR(F.shiftrightunsigned("fp", first + width))  # the block on top
        finer = [F.struct(F.lit(j).alias("part2"), value(turned, *p).alias("value2")) for j, p in enumerate(_blocks(64 - width, limit + 1))]
        split = F.when((F.col("part") == i) & F.col("large"), F.array(*finer)).otherwise(split)
    keyed = keyed.select("fp", "part", "value", F.explode(split).alias("s")).select("fp", "part", "value", "s.*")
    key = ["part", "value", "part2", "value2"]
    run = keyed.select(F.xxhash64(*key).alias("key"), "fp").repartition("key").sortWithinPartitions("key", "fp")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def linked(rest: list[np.ndarray]) -> pa.RecordBatch | None:
            fps = np.unique(np.concatenate(rest).view(np.uint64))
            found = np.array(spanning_links(fps, limit) if len(fps) > 1 else [], np.int64).reshape(-1, 2)
            pair = fps.view(np.int64)[found]
            return pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"]) if len(pair) else None

        held, now = [], None
        for batch in batches:
            keys, fps = (batch.column(i).to_numpy() for i in (0, 1))
            cuts = [0, *(np.flatnonzero(np.diff(keys)) + 1).tolist(), len(keys)]
            for s, e in zip(cuts, cuts[1:], strict=False):
                if s == e:
                    continue
                if held and keys[s] != now:
                    if (out := linked(held)) is not None:
                        yield out
                    held = []
                now = keys[s]
                held.append(fps[s:e])
        if held and (out := linked(held)) is not None:
            yield out

    return run.mapInArrow(search, "a long, b long")


def grouped(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(doc_id, fp, th, root) for every row: ``th`` is a hash of its text, ``root`` names its component."""
    prints = cut(fingerprint_rows(docs))
    folded = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    found = components(links(folded.select("fp"), limit))
    roots = folded.join(found, folded["fp"] == found["node"], "left").select("fp", F.coalesce("root", "fp").alias("root"))
    return cut(hot_join(prints, roots, "fp"))


def near_duplicates(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of ``docs``.

    component_id is the smallest doc_id reachable over links of ``limit`` or fewer
    differing bits. Null and empty texts have fingerprint zero and link like any
    other. A null doc_id keeps its row and never names a component; repeated ids
    are rows like any other. Equal fingerprints fold before the search, so groups
    of copies cost one entry. No rows give no rows; other columns are ignored.
    """
    rows = grouped(docs, limit)
    least = rows.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return hot_join(rows, least, "root").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def leading_rows(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """The row of ``docs`` that leads each of the ``groups`` (doc_id, th, root): the smallest doc_id, then text hash.

    Rows are told apart by id and text, so an id with two texts may lead two groups.
    Rows without a doc_id stay; of repeated rows one does.
    """
    leads = groups.where("doc_id IS NOT NULL").groupBy("root").agg(F.min(F.struct("doc_id", "th")).alias("m")).select(F.col("m.doc_id").alias("_lead"), F.col("m.th").alias("_hash")).distinct()
    th = "_th" + "_" * max(map(len, docs.columns))  # longer than any of their names
    marked = docs.withColumn(th, text_hash(docs))
    led = marked.join(leads, (marked["doc_id"].cast("long") == leads["_lead"]) & (marked[th] == leads["_hash"]), "left_semi").dropDuplicates(["doc_id", th]).drop(th)
    return led.unionByName(docs.where("doc_id IS NULL"))


def drop_near_duplicates(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """The rows of ``docs`` that lead their group (``leading_rows``), with all their columns."""
    return leading_rows(docs, grouped(docs, limit))
