"""Finding benchmark items in training text: a BM25 index searched with block-max WAND.

Test items are cut into segments, the documents of a small inverted index whose
postings are sorted by segment and kept in blocks with their largest impact.
Every training document is read as overlapping passages; each passage is a query.
An item is reported when a passage scores at least ``THETA`` of a segment's own
score and the text then shows the item's question and its answer by shared word runs.

Passages that can't reach the threshold for any segment are told by the segments'
essential terms before the search (``ItemIndex.candidates``); none that can is lost.
"""

from __future__ import annotations

import bisect
import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from densegrid.llm._text import column, of_columns
from densegrid.plans.lineage import cut
from densegrid.plans.shipping import ship

K1, B = 1.2, 0.75
#: Words in an index segment, in half a passage, and in a run compared for overlap.
SEGMENT, HALF, RUN = 40, 40, 5
#: Share of a segment's own score that a passage must reach; overlap that verifies.
THETA, OVERLAP = 0.5, 0.5
BLOCK = 8
#: Items that one index holds (some 10 MB); more are searched index by index.
ITEMS = 5_000

_MARKS = re.compile(rb"[!-/:-@\[-`{-~]+")


def words(text: bytes | None) -> list[bytes]:
    """Lower-cased words without ASCII punctuation."""
    return _MARKS.sub(b"", (text or b"").lower()).split()


def question_answer(text: bytes | None) -> tuple[list[bytes], list[bytes]]:
    """An item's question and answer: parted at its last line break, else its last sentence, else its middle."""
    t = (text or b"").strip()
    at = t.rfind(b"\n")
    if at < 0:
        at = max(t.rfind(m, 0, max(len(t) - 1, 0)) for m in (b". ", b"? ", b"! "))
    q, a = words(t[: at + 1]), words(t[at + 1 :])
    if at < 0 or len(q) < RUN or len(a) < RUN:
        every = words(t)
        q, a = every[: (len(every) + 1) // 2], every[(len(every) + 1) // 2 :]
    return q, a


def segments(text: bytes | None) -> list[list[bytes]]:
    """An item's words in even pieces of at most SEGMENT; none of a wordless item."""
    ws = words(text)
    parts = max(1, -(-len(ws) // SEGMENT))
    return [piece for p in range(parts) if (piece := ws[len(ws) * p // parts : len(ws) * (p + 1) // parts])]


class ItemIndex:
    """BM25 over item segments; impacts are shares of the segment's score against itself.

    ``whole`` has the number of segments, their mean length and the segments that
    each word is in, of the benchmark of which the items are a part.
    """

    def __init__(self, items: list[tuple[int, bytes]], whole: tuple[int, float, dict[bytes, int]] | None = None):
        self.items = [(i, *question_answer(t)) for i, t in items]
        bags, self.owner = [], []
        for k, (_, t) in enumerate(items):
            for piece in segments(t):
                bags.append(piece)
                self.owner.append(k)
        n = len(bags)
        tf: dict[bytes, dict[int, int]] = defaultdict(dict)
        for s, bag in enumerate(bags):
            for w in bag:
                tf[w][s] = tf[w].get(s, 0) + 1
        every, mean, df = whole or (n, sum(map(len, bags)) / max(1, n), {w: len(found) for w, found in tf.items()})
        self.terms = {w: t for t, w in enumerate(sorted(tf))}
        raw = []
        for w in self.terms:
            idf = np.log(1 + (every - df[w] + 0.5) / (df[w] + 0.5))
            raw.append([(s, idf * c * (K1 + 1) / (c + K1 * (1 - B + B * len(bags[s]) / mean))) for s, c in sorted(tf[w].items())])
        own = np.zeros(n)
        for post in raw:
            for s, x in post:
                own[s] += x
        self.segments = n
        self.postings = [([s for s, _ in post], [x / own[s] for s, x in post]) for post in raw]
        self.blocks = [[(ids[min(at + BLOCK, len(ids)) - 1], max(xs[at : at + BLOCK])) for at in range(0, len(ids), BLOCK)] for ids, xs in self.postings]
        self.bound = [max(xs) for _, xs in self.postings]
        self._essential()

    def _essential(self) -> None:
        """For each segment the strongest terms, without which no passage reaches ``THETA``.

        The weak terms of a segment sum to ``rest`` < THETA / 2, so a passage must
        collect THETA - rest from the essential ones. Their postings lie flat.
        """
        by_segment = defaultdict(list)
        for t, (ids, xs) in enumerate(self.postings):
            for s, x in zip(ids, xs, strict=True):
                by_segment[s].append((x, t))
        self.rest, flat = np.zeros(self.segments), defaultdict(list)
        for s, found in by_segment.items():
            for x, t in sorted(found):
                if self.rest[s] + x < THETA / 2 and t is not None:
                    self.rest[s] += x
                else:
                    flat[t].append((s, x))
        self.first = np.zeros(len(self.terms) + 2, np.int64)
        pairs = []
        for t in range(len(self.terms)):
            pairs += flat.get(t, [])
            self.first[t + 1] = len(pairs)
        self.first[-1] = len(pairs)
        self.seg = np.array([s for s, _ in pairs], np.int64)
        self.impact = np.array([x for _, x in pairs])

    def search(self, terms: set[int], theta: float = THETA) -> list[tuple[int, float]]:
        """(segment, score) of every segment scoring ``theta`` or more: block-max WAND, exact."""
        lists = [[self.postings[t][0][0], 0, t] for t in terms]  # current segment, place, term
        out = []
        while lists:
            lists.sort()
            bound, pivot = 0.0, -1
            for k, (_, _, t) in enumerate(lists):
                bound += self.bound[t]
                if bound >= theta - 1e-9:
                    pivot = k
                    break
            if pivot < 0:
                return out
            target = lists[pivot][0]
            while pivot + 1 < len(lists) and lists[pivot + 1][0] == target:
                pivot += 1
            block, skip = 0.0, self.segments
            for _, _, t in lists[: pivot + 1]:
                k = bisect.bisect_left(self.blocks[t], (target, -1.0))
                if k < len(self.blocks[t]):
                    last, most = self.blocks[t][k]
                    block, skip = block + most, min(skip, last + 1)
            if block < theta - 1e-9:  # no segment up to the nearest block end can do
                if pivot + 1 < len(lists):
                    skip = min(skip, lists[pivot + 1][0])
                to = max(skip, target + 1)
            elif lists[0][0] == target:
                score = sum(self.postings[t][1][at] for s, at, t in lists if s == target)
                if score >= theta - 1e-9:
                    out.append((target, score))
                to = target + 1
            else:
                to = target
            moved = []
            for s, at, t in lists:
                if s < to:
                    at = bisect.bisect_left(self.postings[t][0], to, at)
                    if at == len(self.postings[t][0]):
                        continue
                    s = self.postings[t][0][at]
                moved.append([s, at, t])
            lists = moved
        return out

    def candidates(self, ids: np.ndarray) -> np.ndarray:
        """Half-passages k (of ``HALF`` words) such that halves k and k+1 may reach ``THETA`` for a segment.

        ``ids`` holds the document's words as term numbers, -1 where no item has the word.
        """
        halves = -(-len(ids) // HALF)
        at = np.flatnonzero(ids >= 0)
        t, half = ids[at], at // HALF
        pair = np.unique(half * (len(self.terms) + 1) + t)  # a term counts once in each half
        half, t = pair // (len(self.terms) + 1), pair % (len(self.terms) + 1)
        n = self.first[t + 1] - self.first[t]
        if not n.any():
            return np.empty(0, np.int64)
        where = np.repeat(self.first[t] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        mass = np.bincount(np.repeat(half, n) * self.segments + self.seg[where], self.impact[where], halves * self.segments).reshape(halves, self.segments)
        mass[:-1] += mass[1:]
        return np.flatnonzero((mass >= THETA - self.rest - 1e-9).any(axis=1))


def overlap(part: list[bytes], runs: set[tuple[bytes, ...]]) -> float:
    """The share of the part's runs of RUN words (all of a shorter part) that the text has too."""
    n = max(1, len(part) - RUN + 1)
    own = [tuple(part[i : i + RUN]) for i in range(n)]
    return sum(r in runs for r in own) / n


def leaks(text: bytes | None, index: ItemIndex) -> list[tuple[int, float, float, float]]:
    """(item, best score, question overlap, answer overlap) of the verified items in one text."""
    ws = words(text)
    if not ws or not index.segments:
        return []
    get = index.terms.get
    ids = np.fromiter((get(w, -1) for w in ws), np.int64, len(ws))
    best: dict[int, float] = {}
    spans: dict[int, set[int]] = defaultdict(set)
    step = min(2000, max(1, 4_000_000 // index.segments))  # a long text goes in pieces of a bounded table
    for big in range(0, max(1, len(ids) - HALF), HALF * step):
        for k in index.candidates(ids[big : big + HALF * (step + 1)]).tolist():
            at = big + k * HALF
            here = ids[at : at + 2 * HALF]
            for s, score in index.search(set(here[here >= 0].tolist())):
                item = index.owner[s]
                best[item] = max(best.get(item, 0.0), score)
                spans[item].add(at)
    out = []
    for item, score in sorted(best.items()):
        i, q, a = index.items[item]
        reach = len(q) + len(a)
        runs = set()
        for at in spans[item]:
            near = ws[max(0, at - reach) : at + 2 * HALF + reach]
            for size in {RUN, *(len(p) for p in (q, a) if len(p) < RUN)}:
                runs.update(tuple(near[k : k + size]) for k in range(len(near) - size + 1))
        oq, oa = overlap(q, runs), overlap(a, runs) if a else 1.0  # an item of one word has no answer apart
        if min(oq, oa) >= OVERLAP:
            out.append((i, float(score), oq, oa))
    return out


class Whole:
    """What all items of a benchmark have in common, counted by aggregates; a part asks for its own words only."""

    def __init__(self, benchmark: DataFrame):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                seen = [(w, n) for t in column(batch, "text") for piece in segments(t) for w, n in [(None, len(piece)), *((w, 0) for w in {*piece})]]
                yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in seen], pa.binary()), pa.array([n for _, n in seen], pa.int64())], ["w", "n"])

        self.counts = cut(of_columns(benchmark, text="binary").mapInArrow(run, "w binary, n long").groupBy("w").agg(F.count("*").alias("df"), F.sum("n").alias("n")))
        total = self.counts.where("w IS NULL").first()
        self.segments, length = (total["df"], total["n"]) if total else (0, 0)
        self.mean = length / max(1, self.segments)

    def of(self, items: list[tuple[int, bytes]]) -> tuple[int, float, dict[bytes, int]]:
        own = sorted({w for _, t in items for w in words(t)})
        asked = self.counts.sparkSession.createDataFrame(pa.table({"w": pa.array(own, pa.binary())}))
        found = self.counts.join(asked, "w", "left_semi").toLocalIterator()
        return self.segments, self.mean, {bytes(r["w"]): r["df"] for r in found}


def find_leaks(docs: DataFrame, benchmark: DataFrame, items_per_index: int = ITEMS) -> DataFrame:
    """(doc_id, item_id, score, question_overlap, answer_overlap) for every verified pair.

    Every passage of every document is searched against every item. The index is
    shipped to the executors only in parts of ``items_per_index`` items; a larger
    benchmark is searched part by part, with the word frequencies and lengths of the
    whole, so that scores don't depend on the parts. Null or wordless texts and items match
    nothing; a null doc_id or item_id is carried along; repeated rows repeat their
    pairs. Items are read to the driver part by part, documents never.
    """
    spark = docs.sparkSession
    schema = "doc_id long, item_id long, score double, question_overlap double, answer_overlap double"
    some, out, part = of_columns(docs, doc_id="long", text="binary"), None, []

    whole = None

    def searched(items: list[tuple[int, bytes]], last: bool) -> DataFrame:
        nonlocal whole
        if whole is None and not (last and out is None):  # a single part is the whole
            whole = Whole(benchmark)
        shipped = ship(spark, ItemIndex(items, whole.of(items) if whole else None))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = shipped()
            names = schema.replace(" long", "").replace(" double", "").split(", ")
            for batch in batches:
                rows = [(d, *x) for d, t in zip(column(batch, "doc_id"), column(batch, "text"), strict=True) for x in leaks(t, index)]
                if rows:
                    cols = list(zip(*rows, strict=True))
                    kinds = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64()]
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

        return some.mapInArrow(run, schema)

    for row in of_columns(benchmark, item_id="long", text="binary").toLocalIterator():
        if len(part) == items_per_index:
            found = searched(part, last=False)
            out = found if out is None else out.union(found)
            part = []
        part.append((row["item_id"], bytes(row["text"] or b"")))
    found = searched(part, last=True)
    return found if out is None else out.union(found)


def drop_leaking(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs`` in which no benchmark item was verified; rows without a doc_id stay."""
    return docs.join(find_leaks(docs, benchmark).select(F.col("doc_id").alias("_leak")).distinct(), F.col("doc_id") == F.col("_leak"), "left_anti")
