"""Encoding with a SentencePiece BPE model by suffix-array matching, and decoding.

Texts fall into segments that no piece crosses (a run of spaces with the word
after it, or a line break). The distinct segments of a batch are joined to one
text, over which a suffix array is built to the depth of the longest piece.
Every piece is found in it by binary search; the occurrences are edges, laid out
by position; then all segments relax at once: in each, the best edge over two
adjacent symbols, the leftmost of equal ones, replaces them, until none is left.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from densegrid.llm._text import column, of_columns, slices
from densegrid.plans.shipping import ship

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
DEPTH = 16
#: Distinct segments that a task remembers; segments longer than LONG code points relax through a heap.
MEMORY, LONG = 300_000, 200
BATCH = 300_000

_SEGMENT = re.compile(f"{SPACE}*[^{SPACE}\n]+|\n|{SPACE}+")
_NONE = np.int64(1 << 40)


class Codec:
    """A BPE model with byte fallback, a dummy prefix and no normalisation."""

    def __init__(self, path: str = MODEL):
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        norm, trained = model.normalizer_spec, model.trainer_spec
        if trained.model_type != 2 or not trained.byte_fallback or norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.add_dummy_prefix:
            raise ValueError("only BPE models with byte fallback, a dummy prefix and identity normalisation")
        plain = [(i, p.piece, p.score) for i, p in enumerate(model.pieces) if p.type == 1]
        if any(len(p) > DEPTH or SPACE in p.lstrip(SPACE) or "\n" in p for _, p, _ in plain):
            raise ValueError("pieces must be short and hold spaces only in front")
        self.byte_id = np.zeros(256, np.int64)
        for i, p in enumerate(model.pieces):
            if p.type == 6:
                self.byte_id[int(p.piece[3:-1], 16)] = i
        self.alphabet = np.unique(np.frombuffer("".join(p for _, p, _ in plain).encode("utf-32-le"), np.uint32))
        self.ids = np.array([i for i, _, _ in plain], np.int64)
        self.sizes = np.array([len(p) for _, p, _ in plain], np.int64)
        codes = np.zeros((len(plain), DEPTH), np.uint64)
        for k, (_, p, _) in enumerate(plain):
            codes[k, : len(p)] = self._codes(p)
        high = np.where(np.arange(DEPTH) < self.sizes[:, None], codes, np.uint64(0xFFFF))
        self.low_key, self.high_key = self._packed(codes), self._packed(high)
        scores = np.array([s for _, _, s in plain])
        _, order = np.unique(-scores, return_inverse=True)
        self.rank = np.full(len(model.pieces) + 1, _NONE)
        self.rank[self.ids] = order
        spelled = [b""] * len(model.pieces)
        for i, p in enumerate(model.pieces):
            spelled[i] = p.piece.replace(SPACE, " ").encode() if p.type == 1 else bytes([int(p.piece[3:-1], 16)]) if p.type == 6 else b""
        self.spelled = np.frombuffer(b"".join(spelled), np.uint8)
        self.spelled_size = np.array([len(s) for s in spelled], np.int64)
        self.spelled_at = np.cumsum(self.spelled_size) - self.spelled_size

    def _codes(self, text: str) -> np.ndarray:
        """1-based places in the alphabet, 0 for code points that no piece has."""
        points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        at = np.searchsorted(self.alphabet, points)
        known = self.alphabet[np.minimum(at, len(self.alphabet) - 1)] == points
        return np.where(known, at + 1, 0).astype(np.uint64)

    @staticmethod
    def _packed(codes: np.ndarray) -> np.ndarray:
        """Four codes of 16 bits in each of four columns, so that columns compare like code strings."""
        c = codes.reshape(len(codes), 4, 4)
        return c[:, :, 0] << np.uint64(48) | c[:, :, 1] << np.uint64(32) | c[:, :, 2] << np.uint64(16) | c[:, :, 3]

    @staticmethod
    def suffix_array(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions sorted by their first DEPTH codes (by doubling), and their four packed key columns in that order."""
        n = len(codes)
        padded = np.concatenate([codes, np.zeros(DEPTH, np.uint64)])
        four = padded[:n] << np.uint64(48) | padded[1 : n + 1] << np.uint64(32) | padded[2 : n + 2] << np.uint64(16) | padded[3 : n + 3]
        rank = np.unique(four, return_inverse=True)[1].astype(np.uint64) + np.uint64(1)
        for step in (4, 8):
            after = np.concatenate([rank[step:], np.zeros(min(step, n), np.uint64)])[:n]
            pair = rank << np.uint64(32) | after
            order = np.argsort(pair)
            grown = np.concatenate([[0], np.cumsum(np.diff(pair[order]) != 0)])
            rank = np.empty(n, np.uint64)
            rank[order] = (grown + 1).astype(np.uint64)
        keys = np.concatenate([four, np.zeros(DEPTH, np.uint64)])
        return order, np.stack([keys[order + 4 * k] for k in range(4)], axis=1)

    @staticmethod
    def _bisect(keys: np.ndarray, asked: np.ndarray, right: bool) -> np.ndarray:
        """For each row of ``asked`` the first place in the sorted rows ``keys`` not below (``right``: above) it."""
        low, high = np.zeros(len(asked), np.int64), np.full(len(asked), len(keys), np.int64)
        while (open_ := low < high).any():
            mid = (low + high) // 2
            row = keys[np.minimum(mid, len(keys) - 1)]
            differs = row != asked
            at = differs.argmax(axis=1)
            pick = np.arange(len(asked))
            less = np.where(differs.any(axis=1), row[pick, at] < asked[pick, at], right)
            low, high = np.where(open_ & less, mid + 1, low), np.where(open_ & ~less, mid, high)
        return low

    def edges(self, codes: np.ndarray) -> np.ndarray:
        """By position and length (1 to DEPTH) the id of the piece there, or -1."""
        order, keys = self.suffix_array(codes)
        low, high = self._bisect(keys, self.low_key, False), self._bisect(keys, self.high_key, True)
        n = high - low
        where = np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())
        table = np.full((len(codes), DEPTH), -1, np.int32)
        table[order[where], np.repeat(self.sizes - 1, n)] = np.repeat(self.ids, n)
        return table

    def _relax(self, table: np.ndarray, start: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Merges symbols (start, word; sorted) to the end: their start, size and word, sorted."""
        size = np.ones(len(start), np.int64)
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(start):
            both = size[:-1] + size[1:]
            can = (word[:-1] == word[1:]) & (both <= DEPTH)
            rank = np.full(len(start), _NONE)
            at = np.flatnonzero(can)
            rank[at] = self.rank[table[start[at], both[at] - 1]]
            heads = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            best = np.minimum.reduceat(rank, heads)
            each = np.repeat(best, np.diff(np.append(heads, len(start))))
            hit = np.flatnonzero((rank == each) & (each < _NONE))
            hit = hit[np.concatenate([[True], word[hit][1:] != word[hit][:-1]])] if len(hit) else hit
            ended = each == _NONE
            if ended.any():
                done.append((start[ended], size[ended], word[ended]))
            size[hit] += size[hit + 1]
            stay = ~ended
            stay[hit + 1] = False
            start, size, word = start[stay], size[stay], word[stay]
        if not done:
            return start, size, word
        s, z, w = (np.concatenate(x) for x in zip(*done, strict=True))
        order = np.argsort(s, kind="stable")
        return s[order], z[order], w[order]

    def _relax_long(self, table: np.ndarray, first: int, n: int) -> tuple[list[int], list[int]]:
        """The same for one long segment, its candidates in a heap."""
        size, left, right = [1] * n, list(range(-1, n - 1)), list(range(1, n + 1))
        heap: list[tuple[int, int, int]] = []

        def offer(i: int) -> None:
            if i >= 0 and (j := right[i]) < n and (z := size[i] + size[j]) <= DEPTH and (p := int(table[first + i, z - 1])) >= 0:
                heapq.heappush(heap, (int(self.rank[p]), i, z))

        for i in range(n):
            offer(i)
        while heap:
            _, i, z = heapq.heappop(heap)
            j = right[i] if size[i] else n
            if j >= n or size[i] + size[j] != z:
                continue
            size[i], size[j], right[i] = z, 0, right[j]
            if right[i] < n:
                left[right[i]] = i
            offer(i)
            offer(left[i])
        alive = [i for i in range(n) if size[i]]
        return [first + i for i in alive], [size[i] for i in alive]

    def encode_segments(self, segments: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all segments in a row, and the number of ids of each."""
        whole = "\n".join(segments) + "\n"  # a line break is in no piece
        codes = self._codes(whole)
        table = self.edges(codes)
        sizes = np.fromiter(map(len, segments), np.int64, len(segments))
        first = np.cumsum(sizes + 1) - sizes - 1
        short = np.flatnonzero(sizes <= LONG)
        n = sizes[short]
        start = np.repeat(first[short] - np.cumsum(n) + n, n) + np.arange(n.sum())
        parts = [self._relax(table, start, np.repeat(short, n))]
        for k in np.flatnonzero(sizes > LONG).tolist():
            s, z = self._relax_long(table, int(first[k]), int(sizes[k]))
            parts.append((np.array(s), np.array(z), np.full(len(s), k)))
        start, size, word = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(start, kind="stable")
        start, size, word = start[order], size[order], word[order]
        ids = table[start, size - 1].astype(np.int64)
        counts = np.ones(len(ids), np.int64)
        unknown = np.flatnonzero(ids < 0)
        if len(unknown):
            spelled = [whole[i].encode() for i in start[unknown].tolist()]
            counts[unknown] = [len(b) for b in spelled]
            ids = np.repeat(ids, counts)
            ids[ids < 0] = self.byte_id[np.frombuffer(b"".join(spelled), np.uint8)]
        return ids, np.bincount(word, counts, len(segments)).astype(np.int64)

    def decode_ids(self, ids: np.ndarray, bounds: np.ndarray) -> list[bytes]:
        """The bytes that each range of ids spells, without the dummy prefix."""
        n = self.spelled_size[ids]
        ends = np.concatenate([[0], np.cumsum(n)])
        flat = self.spelled[np.repeat(self.spelled_at[ids] - ends[:-1], n) + np.arange(ends[-1])].tobytes()
        cuts = ends[bounds].tolist()
        out = (flat[a:b] for a, b in zip(cuts, cuts[1:], strict=False))
        return [t[1:] if t[:1] == b" " else t for t in out]


class Encoder:
    """Encodes texts in turn, remembering the segments it has met."""

    def __init__(self, codec: Codec):
        self.codec = codec
        self._forget()

    def _forget(self) -> None:
        self.known: dict[str, int] = {}
        self.ids, self.at, self.n = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64)

    def _learn(self, new: list[str]) -> None:
        held = 0
        part: list[str] = []
        ids, counts = [], []
        for k, s in enumerate(new):
            part.append(s)
            held += len(s) + 1
            if held > BATCH or k + 1 == len(new):
                i, c = self.codec.encode_segments(part)
                ids.append(i.astype(np.int32))
                counts.append(c)
                part, held = [], 0
        n = np.concatenate(counts)
        self.at = np.concatenate([self.at, len(self.ids) + np.cumsum(n) - n])
        self.n = np.concatenate([self.n, n])
        self.ids = np.concatenate([self.ids, *ids])
        self.known.update(zip(new, range(len(self.known), len(self.known) + len(new)), strict=True))

    def encode(self, texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and their bounds."""
        segments, counts = [], np.zeros(len(texts), np.int64)
        for i, t in enumerate(texts):
            if t:
                found = _SEGMENT.findall(SPACE + t.decode("utf-8", "replace").replace(" ", SPACE))
                counts[i] = len(found)
                segments += found
        new = set(segments).difference(self.known)
        if len(new) + len(self.known) > MEMORY and self.known:
            self._forget()
            new = set(segments)
        if new:
            self._learn(sorted(new))
        which = np.fromiter(map(self.known.__getitem__, segments), np.int64, len(segments))
        n = self.n[which]
        ends = np.concatenate([[0], np.cumsum(n)])
        ids = self.ids[np.repeat(self.at[which] - ends[:-1], n) + np.arange(ends[-1])]
        return ids, ends[np.concatenate([[0], np.cumsum(counts)])]


def encode(docs: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, ids, n_tokens, round_trip) for every row.

    ids equal those of the reference library; round_trip tells whether decoding
    them gave the text again (not so only for texts that hold U+2581, which is
    how the model spells a space). A null or empty text has no ids. Null and
    repeated ids are carried along; other columns are ignored. ``model`` is read
    on the driver; executors need no file.
    """
    shipped = ship(docs.sparkSession, Codec(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(shipped())
        for batch in batches:
            texts = column(batch, "text")
            for s, e in slices(texts):
                ids, bounds = encoder.encode(texts[s:e])
                back = encoder.codec.decode_ids(ids, bounds)
                same = [a == (b or b"") for a, b in zip(back, texts[s:e], strict=True)]
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids, pa.int32()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(s, e - s), lists, pa.array(np.diff(bounds)), pa.array(same, pa.bool_())], ["doc_id", "ids", "n_tokens", "round_trip"])

    return of_columns(docs, doc_id="long", text="binary").mapInArrow(run, "doc_id long, ids array<int>, n_tokens long, round_trip boolean")


def decode(tokens: DataFrame, model: str = MODEL) -> DataFrame:
    """(doc_id, text) from (doc_id, ids). Null ids give an empty text; ids out of range raise an error."""
    shipped = ship(tokens.sparkSession, Codec(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shipped()
        for batch in batches:
            lists = [x or [] for x in column(batch, "ids")]
            bounds = np.concatenate([[0], np.cumsum([len(x) for x in lists], dtype=np.int64)])
            flat = np.fromiter((i for x in lists for i in x), np.int64, bounds[-1])
            texts = [t.decode("utf-8", "replace") for t in codec.decode_ids(flat, bounds)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return of_columns(tokens, doc_id="long", ids="array<int>").mapInArrow(run, "doc_id long, text string")
