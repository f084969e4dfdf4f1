"""Batch helpers over UTF-8 bytes shared by the operators of this subpackage."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

CHUNK = 1 << 20
_WHITE = np.zeros(256, bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True
_ODD = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_ODD), -1, 1 << 64))


def of_columns(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, cast: ``of_columns(df, doc_id="long", text="binary")``."""
    return df.select(*[F.col(f"`{c}`").cast(t).alias(c) for c, t in columns.items()])


def column(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def slices(texts: list[bytes | None], most: int = CHUNK) -> Iterator[tuple[int, int]]:
    """Ranges of rows with about ``most`` bytes each, so that temporaries stay small."""
    at = held = 0
    for i, t in enumerate(texts):
        n = len(t or b"")
        if held and held + n > most:
            yield at, i
            at, held = i, 0
        held += n
    if at < len(texts):
        yield at, len(texts)


def text_slices(batch: pa.RecordBatch, name: str, most: int = CHUNK) -> Iterator[tuple[int, list]]:
    """First row and texts of ranges of about ``most`` bytes; only one range is held as Python objects."""
    col = batch.column(batch.schema.get_field_index(name))
    sizes = np.asarray(pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False), np.int64)
    at = held = 0
    for i, n in enumerate(sizes.tolist()):
        if held and held + n > most:
            yield at, col.slice(at, i - at).to_pylist()
            at, held = i, 0
        held += n
    if at < len(sizes):
        yield at, col.slice(at).to_pylist()


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (the finaliser of a public generator)."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


class _Powers:
    """Powers of the hash base and of its inverse, made where they are needed and never shipped."""

    def __init__(self):
        self.tables: list[np.ndarray] = []

    def __getstate__(self) -> dict:
        return {"tables": []}

    def upto(self, n: int) -> list[np.ndarray]:
        if not self.tables or len(self.tables[0]) < n:
            self.tables = []
            for base in (_ODD, _INVERSE):
                steps = np.full(max(n, CHUNK // 2), base, np.uint64)
                steps[0] = 1
                self.tables.append(np.multiply.accumulate(steps))
        return self.tables


_POWERS = _Powers()


def word_spans(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of bytes other than 0x20 and 0x09-0x0D."""
    solid = np.empty(len(buf) + 2, np.int8)
    solid[0] = solid[-1] = 0
    np.logical_not(_WHITE[buf], out=solid[1:-1].view(bool))
    edge = np.diff(solid)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span; equal bytes give equal hashes wherever they stand."""
    out = np.empty(len(starts), np.uint64)
    at = 0
    while at < len(starts):
        low = int(starts[at])
        to = max(at + 1, int(np.searchsorted(ends, low + CHUNK, "right")))
        high = int(ends[to - 1])
        p, q = _POWERS.upto(high - low + 1)
        sums = np.zeros(high - low + 1, np.uint64)
        np.cumsum((buf[low:high].astype(np.uint64) + np.uint64(1)) * p[: high - low], out=sums[1:])
        s, e = starts[at:to] - low, ends[at:to] - low
        out[at:to] = mix((sums[e] - sums[s]) * q[s] + (e - s).astype(np.uint64))
        at = to
    return out


def joined(texts: list[bytes | None], low: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """The texts with a newline after each, A-Z lower-cased if ``low``; and where each ends."""
    whole = b"\n".join([*(t or b"" for t in texts), b""])
    ends = np.cumsum(np.fromiter((len(t or b"") + 1 for t in texts), np.int64, len(texts)))
    return np.frombuffer(whole.lower() if low else whole, np.uint8), ends


def words_of(texts: list[bytes | None], low: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """buffer, word starts, word ends, word hashes, and the number of words before each text and after all."""
    buf, ends = joined(texts, low)
    s, e = word_spans(buf)
    return buf, s, e, span_hashes(buf, s, e), np.concatenate([[0], np.searchsorted(s, ends)])


def sums_between(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Row sums of ``values`` between consecutive bounds (empty ranges: 0)."""
    sums = np.zeros((len(values) + 1, *values.shape[1:]), np.float64)
    np.cumsum(values, axis=0, out=sums[1:], dtype=np.float64)
    return sums[bounds[1:]] - sums[bounds[:-1]]
