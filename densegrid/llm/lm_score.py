"""Scoring texts by a causal self-attention model over subword ids, beside a unigram base.

A word enters the model as two subword ids, its head (first four bytes) and its
tail (last three), hashed. From the ids of the words before, masked attention
predicts the word's class: one class for each of the most frequent words and for
the end, and one for each topic, to which head and tail assign all other words.
Within a topic's class a word has its discounted share of the class's count over
the whole training corpus; unseen words share what was discounted by a byte
model. So log10 p(text) is a sum over tokens of log10 p(class | before) +
log10 p(word | class), and the word probabilities of a context sum to at most 1.

Long texts are read in overlapping windows; each token is scored once, with at
least ``WINDOW - STRIDE`` tokens before it (fewer only where the text begins).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from densegrid.llm._text import joined, sums_between, text_slices, word_spans, words_of
from densegrid.llm.langid import hash_share, held_out
from densegrid.plans.lineage import cut
from densegrid.plans.shipping import ship

WINDOW, STRIDE = 48, 32
WIDTH, HIDDEN, IDS = 16, 32, 4096
SINGLES, TOPICS = 60, 12
#: Documents that topics and network start from (in expectation; twice that at most), and the steps of that start.
START, STEPS, BATCH = 1500, 500, 64
#: Training documents of one group, in expectation, in the pass over all of them; its windows a step and first rate.
GROUP, PASS_BATCH, PASS_RATE = 8_000, 128, 0.002
#: Words whose counts every executor holds; all other counts are joined by a shuffle.
HEAVY = 1 << 18
#: Bytes of text that a task works on at once.
SLICE = 1 << 18
END = np.uint64(1)

_BASE = 10.0


def subwords(buf: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed ids (from 2 on; 0 is the start, 1 the end of a text) of each word's head and tail."""
    n = e - s
    head, tail = np.zeros(len(s), np.uint64), np.zeros(len(s), np.uint64)
    for k in range(4):
        head = head << np.uint64(8) | np.where(k < n, buf[np.minimum(s + k, len(buf) - 1)], 0).astype(np.uint64)
    for k in range(3):
        tail = tail << np.uint64(8) | np.where(k < n, buf[np.maximum(e - 1 - k, 0)], 0).astype(np.uint64)
    mul = np.uint64(0x9E3779B97F4A7C15)
    return tuple(((x * mul) >> np.uint64(40)).astype(np.int64) % (IDS - 2) + 2 for x in (head, tail))


class ByteModel:
    """Words spelled byte by byte, each given the two before, for every topic."""

    def __init__(self, words: list[tuple[bytes, int]], topics: int):
        short = self.shorts(np.bincount(np.frombuffer(b"".join(w for w, _ in words), np.uint8), minlength=256))
        codes, n = self.steps([w for w, _ in words], np.array([z for _, z in words], np.int64), short)
        self.smooth(short, codes, n, topics)

    @staticmethod
    def shorts(seen: np.ndarray) -> np.ndarray:
        """Contexts know the 39 most frequent bytes, the rest alike, and the word's start."""
        short = np.full(257, 39)
        short[np.argsort(-seen, kind="stable")[:39]] = np.arange(39)
        short[256] = 40
        return short

    @staticmethod
    def steps(words: list[bytes], topic: np.ndarray, short: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in the table that the words' bytes and ends fall on, and how often."""
        n = np.fromiter(map(len, words), np.int64, len(words)) + 1
        here = np.full(n.sum(), 256)
        last = np.zeros(len(here), bool)
        last[np.cumsum(n) - 1] = True
        here[~last] = np.frombuffer(b"".join(words), np.uint8)
        one, two = (np.concatenate([[256] * k, here[:-k]])[: len(here)] for k in (1, 2))
        two[one == 256] = 256
        return np.unique(((np.repeat(topic, n) * 41 + short[two]) * 41 + short[one]) * 257 + here, return_counts=True)

    @classmethod
    def counted(cls, short: np.ndarray, codes: np.ndarray, n: np.ndarray, topics: int) -> ByteModel:
        made = cls.__new__(cls)
        made.smooth(short, codes, n, topics)
        return made

    def smooth(self, short: np.ndarray, codes: np.ndarray, n: np.ndarray, topics: int) -> None:
        self.short, table = short, np.zeros(topics * 41 * 41 * 257, np.float32)
        table[codes] = n
        table = table.reshape(topics, 41, 41, 257)
        every = table.sum(axis=0)
        one = every.sum(axis=0) + 5 * (every.sum(axis=(0, 1)) + 0.5) / (every.sum() + 128)
        one /= one.sum(axis=-1, keepdims=True)
        two = every + 5 * one[None]
        two /= two.sum(axis=-1, keepdims=True)
        table += 5 * two
        table /= table.sum(axis=-1, keepdims=True)
        self.table = np.log10(0.99 * table + 0.01 / 257).astype(np.float32)

    def score(self, buf: np.ndarray, s: np.ndarray, e: np.ndarray, topic: np.ndarray) -> np.ndarray:
        n = e - s + 1
        ends = np.concatenate([[0], np.cumsum(n)])
        word = np.repeat(np.arange(len(s)), n)
        place = np.arange(ends[-1]) - ends[:-1][word]
        at = s[word] + place
        last = place == n[word] - 1
        buf = buf.astype(np.int64)  # 256 stands for a word's end or start
        here = np.where(last, 256, buf[np.minimum(at, len(buf) - 1)])
        one = np.where(place > 0, buf[np.maximum(at - 1, 0)], 256)
        two = np.where(place > 1, buf[np.maximum(at - 2, 0)], 256)
        return sums_between(self.table[topic[word], self.short[two], self.short[one], here], ends)


class Attention:
    """One masked attention layer and a feed-forward layer, predicting the next word's class."""

    def __init__(self, classes: int, seed: int = 5):
        r = np.random.default_rng(seed)
        g = lambda *shape, scale: (r.standard_normal(shape) * scale).astype(np.float32)
        d, w = WIDTH, WIDTH**-0.5
        self.p = {
            "head": g(IDS, d, scale=0.3), "tail": g(IDS, d, scale=0.3), "q": g(d, d, scale=w), "k": g(d, d, scale=w), "v": g(d, d, scale=w), "o": g(d, d, scale=w),
            "near": np.zeros(WINDOW, np.float32), "w1": g(d, HIDDEN, scale=w), "b1": np.zeros(HIDDEN, np.float32), "w2": g(HIDDEN, d, scale=HIDDEN**-0.5),
            "out": g(d, classes, scale=0.1), "bias": np.zeros(classes, np.float32),
        }
        query, key = np.arange(WINDOW - STRIDE, WINDOW)[:, None], np.arange(WINDOW)[None, :]
        self.gap = np.clip(query - key, 0, WINDOW - 1)
        self.later = np.where(key > query, np.float32(-1e9), np.float32(0))

    def forward(self, head: np.ndarray, tail: np.ndarray, empty: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Log-probabilities of the classes after each of the last STRIDE places of the windows.

        ``empty`` marks places before the text's start, which nothing attends to.
        """
        p, (n, _), d = self.p, head.shape, WIDTH
        x = p["head"][head]
        x += p["tail"][tail]
        last = np.ascontiguousarray(x[:, WINDOW - STRIDE :])
        wide, rows = x.reshape(-1, d), last.reshape(-1, d)  # one product for all windows, not one each
        q, k, v = (rows @ (p["q"] * p["q"].dtype.type(d**-0.5))).reshape(n, STRIDE, d), (wide @ p["k"]).reshape(n, WINDOW, d), (wide @ p["v"]).reshape(n, WINDOW, d)
        a = q @ k.transpose(0, 2, 1)
        a += p["near"][self.gap] + self.later
        if empty.any():
            a += np.where(empty, np.float32(-1e9), np.float32(0))[:, None, :]
        a -= a.max(axis=2, keepdims=True)
        np.exp(a, out=a)
        a /= a.sum(axis=2, keepdims=True)
        mixed = (a @ v).reshape(-1, d)
        y = rows + mixed @ p["o"]
        h = y @ p["w1"]
        h += p["b1"]
        np.maximum(h, 0, out=h)
        z = y + h @ p["w2"]
        logits = z @ p["out"]
        logits += p["bias"]
        logits -= logits.max(axis=1, keepdims=True)
        logits -= np.log(np.exp(logits).sum(axis=1, keepdims=True))
        logits = logits.reshape(n, STRIDE, -1)
        if keep is not None:
            keep |= {"x": x, "last": rows, "wide": wide, "q": q, "k": k, "v": v, "a": a, "mixed": mixed, "y": y, "h": h, "z": z}
        return logits

    def gradients(self, head, tail, empty, target, weight) -> tuple[float, dict[str, np.ndarray]]:
        """Mean loss over the weighted targets and the gradients of all parameters."""
        p, m = self.p, {}
        logp = self.forward(head, tail, empty, m)
        total, width, classes = max(1.0, float(weight.sum())), WIDTH, logp.shape[2]
        logp, at, w = logp.reshape(-1, classes), np.arange(target.size), (weight / total).ravel().astype(np.float32)
        d = np.exp(logp)
        loss = -float((logp[at, target.ravel()] * w).sum())
        d[at, target.ravel()] -= 1
        d *= w[:, None]
        g = {"out": m["z"].T @ d, "bias": d.sum(axis=0)}
        dz = d @ p["out"].T
        dh = dz @ p["w2"].T
        dh *= m["h"] > 0
        g |= {"w2": m["h"].T @ dz, "w1": m["y"].T @ dh, "b1": dh.sum(axis=0)}
        dy = dz + dh @ p["w1"].T
        g["o"] = m["mixed"].T @ dy
        dmix = (dy @ p["o"].T).reshape(m["q"].shape)
        ds = dmix @ m["v"].transpose(0, 2, 1)
        dv = (m["a"].transpose(0, 2, 1) @ dmix).reshape(-1, width)
        ds -= np.einsum("nsw,nsw->ns", ds, m["a"])[:, :, None]
        ds *= m["a"]
        g["near"] = np.bincount(self.gap.ravel(), ds.sum(axis=0).ravel(), WINDOW).astype(np.float32)
        dq, dk = (ds @ m["k"]).reshape(-1, width), (ds.transpose(0, 2, 1) @ m["q"]).reshape(-1, width)  # q holds the scale
        dq *= dq.dtype.type(width**-0.5)
        g |= {"q": m["last"].T @ dq, "k": m["wide"].T @ dk, "v": m["wide"].T @ dv}
        dx = (dk @ p["k"].T + dv @ p["v"].T).reshape(m["x"].shape)
        dx[:, WINDOW - STRIDE :] += (dy + dq @ p["q"].T).reshape(m["q"].shape)
        for name, ids in (("head", head), ("tail", tail)):
            order = np.argsort(ids, axis=None, kind="stable")
            held = ids.ravel()[order]
            first = np.flatnonzero(np.concatenate([[True], held[1:] != held[:-1]]))
            g[name] = np.zeros_like(p[name])
            g[name][held[first]] = np.add.reduceat(dx.reshape(-1, width)[order], first, axis=0)
        return loss, g

    def fit(self, windows, n: int, steps: int = STEPS, rate: float = 0.01, seed: int = 3) -> float:
        """Adam over random batches of the ``n`` windows that ``windows(rows)`` makes; the last batches' mean loss."""
        rng, adam = np.random.default_rng(seed), Adam(self)
        losses = [adam.step(windows(rng.integers(0, n, min(BATCH, n))), rate * min(1.0, 3 * (1 - t / steps))) for t in range(steps)]
        return float(np.mean(losses[-20:]))


class Adam:
    """Steps along the gradients of a network, changed in place."""

    def __init__(self, net: Attention):
        self.net, self.t = net, 0
        self.first, self.second = ({k: np.zeros_like(v) for k, v in net.p.items()} for _ in range(2))

    def step(self, batch: tuple[np.ndarray, ...], rate: float) -> float:
        loss, g = self.net.gradients(*batch)
        self.t += 1
        for k, v in self.net.p.items():
            self.first[k] += 0.1 * (g[k] - self.first[k])
            self.second[k] += 0.01 * (g[k] ** 2 - self.second[k])
            v -= rate * (self.first[k] / (1 - 0.9**self.t)) / (np.sqrt(self.second[k] / (1 - 0.99**self.t)) + 1e-8)
        return loss


def windows_of(first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For texts whose words lie between the bounds ``first``: each window's text and the target at which its scored part begins."""
    n = np.diff(first) + 1
    count = -(-n // STRIDE)
    text = np.repeat(np.arange(len(n)), count)
    return text, (np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)) * STRIDE


class Model:
    """Everything that scoring needs but the counts.

    ``single``: the words with classes of their own; ``seen``: how often each head
    and each tail stands in the texts of each topic, other words left aside.
    """

    def __init__(self, single: np.ndarray, seen: np.ndarray):
        self.single, self.topics = single, seen.shape[2]
        self.end = self.topics + len(single)
        prior = seen[0].sum(axis=0) + 1.0
        prior /= prior.sum()
        self.by = [(np.log((x + 2 * prior) / (x.sum(axis=1, keepdims=True) + 2)) - 0.5 * np.log(prior)).astype(np.float32) for x in seen]
        self.bytes, self.net = None, Attention(self.end + 1)

    def weights(self) -> np.ndarray:
        return np.concatenate([v.ravel() for v in self.net.p.values()])

    def load(self, weights: np.ndarray) -> None:
        at = 0
        for k, v in self.net.p.items():
            self.net.p[k] = weights[at : at + v.size].astype(np.float32).reshape(v.shape)
            at += v.size

    def windows(self, texts: list[bytes]):
        """The number of the texts' windows, and a function that makes those asked for: inputs and targets."""
        buf, s, e, h, first = words_of(texts)
        head, tail = subwords(buf, s, e)
        k, (text, begin) = self.classes(h, head, tail), windows_of(first)

        def made(at: np.ndarray) -> tuple[np.ndarray, ...]:
            return *self._inputs(head, tail, first, text[at], begin[at]), *self._targets(k, first, text[at], begin[at])

        return len(text), made

    def classes(self, h: np.ndarray, head: np.ndarray, tail: np.ndarray) -> np.ndarray:
        k = (self.by[0][head] + self.by[1][tail]).argmax(axis=1)
        if len(self.single):
            at = np.minimum(np.searchsorted(self.single, h), len(self.single) - 1)
            k = np.where(self.single[at] == h, self.topics + at, k)
        return k

    @staticmethod
    def _inputs(head, tail, first, text, begin) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Subword ids before each target: place j of a window precedes target begin - (WINDOW - STRIDE) + j."""
        target = begin[:, None] - (WINDOW - STRIDE) + np.arange(WINDOW)[None, :]
        n = np.diff(first)[text][:, None]
        at = np.clip(first[text][:, None] + target - 1, 0, max(len(head) - 1, 0))
        inner = (target >= 1) & (target <= n)
        ids = [np.where(inner, x[at] if len(x) else 0, 0) for x in (head, tail)]
        return ids[0], ids[1], (target < 0) | (target > n)

    def _targets(self, k, first, text, begin) -> tuple[np.ndarray, np.ndarray]:
        target = begin[:, None] + np.arange(STRIDE)[None, :]
        n = np.diff(first)[text][:, None]
        at = np.clip(first[text][:, None] + target, 0, max(len(k) - 1, 0))
        return np.where(target < n, k[at] if len(k) else self.end, self.end), (target <= n).astype(np.float32)

    def class_scores(self, head, tail, k, first) -> np.ndarray:
        """For each text the sum of log10 p(class | before) over its words and its end."""
        text, begin = windows_of(first)
        out = np.zeros(len(first) - 1)
        for a in range(0, len(text), 256):
            t, b = text[a : a + 256], begin[a : a + 256]
            target, weight = self._targets(k, first, t, b)
            logp = self.net.forward(*self._inputs(head, tail, first, t, b))
            picked = np.take_along_axis(logp, target[:, :, None], axis=2)[:, :, 0]
            np.add.at(out, t, (picked * weight).sum(axis=1, dtype=np.float64))
        return out / np.log(_BASE)


def spelled(buf: np.ndarray, s: np.ndarray, e: np.ndarray) -> pa.Array:
    """The bytes of each span."""
    ends = np.concatenate([[0], np.cumsum(e - s)])
    return pa.Array.from_buffers(pa.binary(), len(s), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(buf[np.repeat(s - ends[:-1], e - s) + np.arange(ends[-1])])])


def _merged(parts: list[tuple]) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    h, n = (np.concatenate([p[i] for p in parts]) for i in (0, 2))
    words, at, back = np.unique(h, return_index=True, return_inverse=True)
    return words, pa.concat_arrays([p[1] for p in parts]).take(pa.array(at)), np.bincount(back, n, len(words)).astype(np.int64)


def corpus_counts(training: DataFrame) -> DataFrame:
    """(h, word, c): the count of every word, by hash, and of the end (its word null), over the training documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0

        def flush() -> pa.RecordBatch:
            h, words, n = parts[0] if len(parts) == 1 else _merged(parts)
            return pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), words, pa.array(n)], ["h", "word", "c"])

        for batch in batches:
            for s, texts in text_slices(batch, "text", SLICE):
                buf, a, b, h, _ = words_of(texts)
                words, at, n = np.unique(h, return_index=True, return_counts=True)
                parts.append((np.append(words, END), pa.concat_arrays([spelled(buf, a[at], b[at]), pa.nulls(1, pa.binary())]), np.append(n, len(texts))))
                held += len(words)
                if held > 1_000_000:
                    parts = [_merged(parts)]
                    held = len(parts[0][0])
                    if held > 500_000:
                        yield flush()
                        parts, held = [], 0
        if parts:
            yield flush()

    rows = training.select("text").mapInArrow(run, "h long, word binary, c long")
    return rows.repartition("h").groupBy("h").agg(F.first("word").alias("word"), F.sum("c").alias("c"))


def _tail_shares(tail: np.ndarray, doc: np.ndarray, texts: int) -> np.ndarray:
    """The texts' tail frequencies, hashed to 256, on the unit sphere."""
    x = np.sqrt(np.bincount(doc * 256 + tail % 256, minlength=texts * 256).reshape(texts, 256))
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)


def _moved(centre: np.ndarray, sums: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(sums, axis=1, keepdims=True)
    return np.where(size > 0, sums / np.maximum(size, 1e-9), centre)


def _centres(x: np.ndarray, topics: int) -> np.ndarray:
    """k-means on the unit sphere."""
    centre = x[:1]
    while len(centre) < topics:  # the text farthest from all centres so far is the next
        centre = np.vstack([centre, x[(x @ centre.T).max(axis=1).argmin()]])
    for _ in range(15):
        sums = np.zeros_like(centre)
        np.add.at(sums, (x @ centre.T).argmax(axis=1), x)
        centre = _moved(centre, sums)
    return centre


def _added(training: DataFrame, shipped, shape: tuple[int, ...], add) -> np.ndarray:
    """The sum over the tasks of what ``add(shipped(), texts, sums)`` adds up for all texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, sums = shipped(), np.zeros(shape)
        for batch in batches:
            for _, texts in text_slices(batch, "text", SLICE):
                add(here, texts, sums)
        at = np.flatnonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(sums.ravel()[at])], ["at", "v"])

    found = training.select("text").mapInArrow(run, "at long, v double").groupBy("at").agg(F.sum("v").alias("v")).toArrow()
    out = np.zeros(math.prod(shape))
    out[found.column("at").to_numpy()] = found.column("v").to_numpy()
    return out.reshape(shape)


def _add_shares(centre: np.ndarray, texts: list[bytes], sums: np.ndarray) -> None:
    buf, ends = joined(texts)
    s, e = word_spans(buf)
    x = _tail_shares(subwords(buf, s, e)[1], np.searchsorted(ends, s, "right"), len(texts))
    z = (x @ centre.T).argmax(axis=1)
    for t in np.unique(z):
        sums[t] += x[z == t].sum(axis=0)


def _add_seen(here: tuple[np.ndarray, np.ndarray], texts: list[bytes], sums: np.ndarray) -> None:
    centre, single = here
    buf, s, e, h, first = words_of(texts)
    doc = np.repeat(np.arange(len(texts)), np.diff(first))
    head, tail = subwords(buf, s, e)
    z = (_tail_shares(tail, doc, len(texts)) @ centre.T).argmax(axis=1)[doc]
    rest = ~np.isin(h, single)
    for which, ids in enumerate((head, tail)):
        sums[which] += np.bincount(ids[rest] * len(centre) + z[rest], minlength=sums[which].size).reshape(sums[which].shape)


def _each_word(counts: DataFrame, model: Model, more=None) -> DataFrame:
    """(kind, k, n): over all words and the end, by class, their count (0), number (1), those met once (2) and twice
    (3); and of words met once in topics' classes the bytes by value (4) or, by ``more``, the steps of the byte model (5)."""
    shipped = ship(counts.sparkSession, (model, more))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, short = shipped()
        for batch in batches:
            words, c = batch.column(1).to_pylist(), batch.column(2).to_numpy()
            h = batch.column(0).to_numpy().view(np.uint64)
            n = np.fromiter((len(w or b"") for w in words), np.int64, len(words))
            e = np.cumsum(n)
            buf = np.frombuffer(b"".join(w or b"" for w in words) or b" ", np.uint8)
            k = np.where(h == END, here.end, here.classes(h, *subwords(buf, e - n, e)))
            once = np.flatnonzero((c == 1) & (k < here.topics))
            some = [words[i] for i in once.tolist()]
            if short is None:
                out = [(kind, *np.unique(k, return_inverse=True), x) for kind, x in ((0, c), (1, np.ones(len(c))), (2, c == 1), (3, c == 2))]
                out = [(kind, at, np.bincount(back, x, len(at))) for kind, at, back, x in out]
                out.append((4, np.arange(256), np.bincount(np.frombuffer(b"".join(some), np.uint8), minlength=256)))
            else:
                out = [(5, *ByteModel.steps(some, k[once], short))]
            kind = np.concatenate([np.full(len(at), i) for i, at, _ in out])
            yield pa.RecordBatch.from_arrays([pa.array(kind.astype(np.int32)), *(pa.array(np.concatenate([o[i] for o in out]).astype(np.int64)) for i in (1, 2))], ["kind", "k", "n"])

    return counts.select("h", "word", "c").mapInArrow(run, "kind int, k long, n long").groupBy("kind", "k").agg(F.sum("n").alias("n"))


def _fit_all(training: DataFrame, model: Model, groups: int) -> None:
    """Goes over every window of every training document once: groups of documents, drawn by their ids, each take
    steps from the same start, and the network becomes the mean of theirs, by their numbers of windows."""
    shipped = ship(training.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, met = shipped(), 0
        adam, rng = Adam(here.net), np.random.default_rng(11)
        for batch in batches:
            for _, texts in text_slices(batch, "text", 4 * SLICE):
                n, made = here.windows(texts)
                order = rng.permutation(n)
                for at in range(0, n, PASS_BATCH):
                    adam.step(made(order[at : at + PASS_BATCH]), PASS_RATE / math.sqrt(1 + adam.t / 50))
                met += n
        if met:
            yield pa.RecordBatch.from_arrays([pa.array([met]), pa.array([here.weights().tobytes()], pa.binary())], ["met", "net"])

    dealt = training.withColumn("turn", F.xxhash64(F.lit("pass"), "doc_id", "text"))
    dealt = dealt.repartition(groups, "turn").sortWithinPartitions("turn").select("text")
    total, mean = 0, 0.0
    for row in dealt.mapInArrow(run, "met long, net binary").collect():
        mean = mean + row["met"] * np.frombuffer(row["net"], np.float32).astype(np.float64)
        total += row["met"]
    if total:
        model.load(mean / total)


def _in_one_task(some: DataFrame, model: Model | None, find) -> tuple[int, np.ndarray]:
    """Of a few documents their number, and what ``find(texts, model)`` finds; the driver holds none of them."""
    shipped = ship(some.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((i or 0, t) for b in batches for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True))
        found = find([t for _, t in rows] or [b""], shipped())
        yield pa.RecordBatch.from_arrays([pa.array([len(rows)]), pa.array([found.astype(np.float32).tobytes()], pa.binary())], ["met", "found"])

    for row in some.select("doc_id", "text").repartition(1).mapInArrow(run, "met long, found binary").collect():
        return row["met"], np.frombuffer(row["found"], np.float32)
    return 0, find([b""], model)


def _begin_topics(texts: list[bytes], _) -> np.ndarray:
    buf, ends = joined(texts)
    s, e = word_spans(buf)
    x = _tail_shares(subwords(buf, s, e)[1], np.searchsorted(ends, s, "right"), len(texts))
    return _centres(x, max(1, min(TOPICS, len(texts))))


def _begin_network(texts: list[bytes], model: Model) -> np.ndarray:
    n, made = model.windows(texts)
    model.net.fit(made, n)
    return model.weights()


def learn(training: DataFrame, counts: DataFrame, start: int = START) -> tuple[Model, dict[int, dict[int, int]]]:
    """The model of all training documents, and figures of the counts by kind and class (``_each_word``).

    Topics and network begin from about ``start`` documents; then the topics' centres,
    the words with classes of their own, the heads and tails by topic, the byte model
    and the network are all taken from every training document.
    """
    spark = training.sparkSession
    total = training.select("doc_id").count()
    some = training.where(hash_share(F.col("doc_id"), "lm") < min(1.0, start / max(1, total))).limit(2 * start)
    held, centre = _in_one_task(some, None, _begin_topics)
    centre = centre.astype(np.float64).reshape(-1, 256)
    centre = _moved(centre, _added(training, ship(spark, centre), centre.shape, _add_shares))
    top = counts.where(F.col("word").isNotNull()).orderBy(F.desc("c"), "h").limit(SINGLES).select("h").collect()
    single = np.sort(np.array([r["h"] for r in top], np.int64).view(np.uint64))
    model = Model(single, _added(training, ship(spark, (centre, single)), (2, IDS, len(centre)), _add_seen))
    if total:
        model.load(_in_one_task(some, model, _begin_network)[1])
        if total > held:
            _fit_all(training, model, min(64, -(-total // GROUP)))
    figures: dict[int, dict[int, int]] = {kind: {} for kind in range(5)}
    for r in _each_word(counts, model).collect():
        figures[r["kind"]][r["k"]] = r["n"]
    short = ByteModel.shorts(np.array([figures[4].get(x, 0) for x in range(256)]))
    steps = _each_word(counts, model, short).toArrow()
    model.bytes = ByteModel.counted(short, steps.column("k").to_numpy(), steps.column("n").to_numpy(), model.topics)
    return model, figures


def score(docs: DataFrame, start: int = START) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row.

    The training documents are those outside the held-out fold; a null doc_id is
    not held out. A null or empty text has one token, its end. Repeated rows
    count and are scored each for itself; other columns are ignored. Without any
    training document all base probabilities are 1 and words are spelled in bytes.
    Words are told apart by 64-bit hashes: two of a billion words may share one.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), 10, 0).alias("held_out"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))
    training = rows.where(~F.col("held_out"))
    counts = cut(corpus_counts(training))
    model, figures = learn(training, counts, start)
    tokens, sorts, once, twice = (figures[kind] for kind in range(4))
    n, v = sum(tokens.values()), sum(sorts.values())
    classes = model.end + 1
    share, rest = np.ones(classes), np.zeros(classes)  # of a class: its count, and log10 of what unseen words share
    drop = np.zeros(classes)
    for k, c in tokens.items():
        share[k] = c
        if k < model.topics:
            drop[k] = (once[k] + 0.5) / (once[k] + 2 * twice[k] + 1)
            rest[k] = np.log10(drop[k] * sorts[k] / c)
    bottom = n + 0.1 * (v + 1)
    # Heavy words are those of the top count classes (an eighth of a doubling each) that fit together.
    level = F.floor(F.log2(F.col("c").cast("double")) * 8)
    least, held = None, 0
    for r in counts.groupBy(level.alias("level")).agg(F.count("*").alias("words")).orderBy(F.desc("level")).collect():
        held += r["words"]
        if held > HEAVY:
            break
        least = r["level"]
    heavy = counts.where(level >= (least if least is not None else 1 << 20)).select("h", F.col("c").cast("double").alias("c")).orderBy("h").toArrow()
    tables = {c: heavy.column(c).to_numpy() for c in ("h", "c")}
    shipped, known = ship(spark, model), ship(spark, (tables, share, rest, drop, bottom))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, (heavy, share, rest, drop, bottom) = shipped(), known()

        def rates(c, k, spelled):
            with np.errstate(divide="ignore"):
                return np.where(c > 0, np.log10(np.maximum(c - drop[k], 1e-9) / share[k]), rest[k] + spelled)

        for batch in batches:
            for s, texts in text_slices(batch, "text", SLICE):
                e = s + len(texts)
                buf, a, b, h, first = words_of(texts)
                rid = batch.column(0).slice(s, e - s).to_numpy()
                head, tail = subwords(buf, a, b)
                k = here.classes(h, head, tail)
                doc = np.repeat(np.arange(e - s), np.diff(first))
                key = h.view(np.int64)
                at = np.minimum(np.searchsorted(heavy["h"], key), max(0, len(heavy["h"]) - 1))
                hit = heavy["h"][at] == key if len(heavy["h"]) else np.zeros(len(key), bool)
                c = heavy["c"][at[hit]] if len(heavy["h"]) else np.zeros(0)
                base = np.bincount(doc[hit], np.log10((c + 0.1) / bottom), e - s).astype(float)
                model_part = np.bincount(doc[hit], rates(c, k[hit], 0.0), e - s) + here.class_scores(head, tail, k, first)
                ends = heavy["c"][heavy["h"] == END.view(np.int64)]
                ends = float(ends[0]) if len(ends) else 0.0
                base += np.log10((ends + 0.1) / bottom)
                seen = np.bincount(doc[hit], minlength=e - s) + (ends > 0)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(rid), *(batch.column(i).slice(s, e - s) for i in (1, 2)), pa.array(np.zeros(e - s, np.int64), mask=np.ones(e - s, bool)), pa.array(np.diff(first) + 1), pa.array(np.full(e - s, here.end, np.int32)), pa.array(base), pa.array(model_part), pa.array(seen.astype(np.int64))],
                    ["rid", "doc_id", "held_out", "h", "n", "k", "base", "model", "seen"])
                rare = np.flatnonzero(~hit)
                if len(rare):
                    order = rare[np.lexsort((key[rare], doc[rare]))]
                    new = np.flatnonzero(np.concatenate([[True], (np.diff(key[order]) != 0) | (np.diff(doc[order]) != 0)]))
                    one, times = order[new], np.diff(np.append(new, len(order)))
                    topic = np.minimum(k[one], here.topics - 1)
                    spelled = here.bytes.score(buf, a[one], b[one], topic)
                    none = pa.nulls(len(one))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(rid[doc[one]]), none.cast(pa.int64()), none.cast(pa.bool_()), pa.array(key[one]), pa.array(times.astype(np.int64)), pa.array(k[one].astype(np.int32)), none.cast(pa.float64()), pa.array(spelled), none.cast(pa.int64())],
                        ["rid", "doc_id", "held_out", "h", "n", "k", "base", "model", "seen"])

    made = rows.withColumn("rid", F.monotonically_increasing_id()).select("rid", "doc_id", "held_out", "text").mapInArrow(run, "rid long, doc_id long, held_out boolean, h long, n long, k int, base double, model double, seen long")
    # A text's own row has no word: it gets a key of its own, spread like the words' and marked by the flag.
    whole = F.col("h").isNull()
    keyed = made.select("*", whole.alias("whole")).withColumn("h", F.coalesce("h", F.xxhash64("rid")))
    other = counts.select(F.col("h").alias("word"), F.col("c"))
    met = keyed.join(other.hint("merge"), (F.col("h") == F.col("word")) & ~F.col("whole"), "left").withColumn("c", F.coalesce("c", F.lit(0)))
    table = lambda x: F.element_at(F.array(*[F.lit(float(y)) for y in x]), F.col("k") + 1)
    rate = F.when(F.col("c") > 0, F.log10(F.greatest(F.col("c") - table(drop), F.lit(1e-9)) / table(share))).otherwise(table(rest) + F.col("model"))
    parts = met.select(
        "rid", "doc_id", "held_out", F.when(F.col("whole"), F.col("n")).alias("n_tokens"),
        F.when(F.col("whole"), F.col("seen")).when(F.col("c") > 0, F.col("n")).otherwise(0).alias("n_known"),
        F.when(F.col("whole"), F.col("base")).otherwise(F.col("n") * F.log10((F.col("c") + 0.1) / F.lit(bottom))).alias("base_score"),
        F.when(F.col("whole"), F.col("model")).otherwise(F.col("n") * rate).alias("score"),
    )
    sums = parts.groupBy("rid").agg(F.max("doc_id").alias("doc_id"), F.max("held_out").alias("held_out"), F.max("n_tokens").alias("n_tokens"), F.sum("n_known").alias("n_known"), F.sum("base_score").alias("base_score"), F.sum("score").alias("score"))
    return sums.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")
