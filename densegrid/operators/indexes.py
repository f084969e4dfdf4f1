"""Neighbour indexes over the occupied cells of one tile, and over its points.

All take the cells' addresses (sorted rows of whole numbers) and answer which
cells may hold points within eps of a given one.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np

from densegrid.functions.geometry import reachable_offset_count, safe_reach


def gaps2(cells: np.ndarray, i: int, others: np.ndarray) -> np.ndarray:
    g = np.maximum(np.abs(cells[others] - cells[i]) - 1, 0)
    return (g * g).sum(axis=1)


def bit_table(column: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The occupied positions of one dimension, each cell's row, and a row of bits, one for each cell, by position."""
    n = len(column)
    pos, row = np.unique(column, return_inverse=True)
    bits = np.zeros((len(pos), (n + 63) // 64 * 8), np.uint8)
    np.bitwise_or.at(bits, (row, np.arange(n) // 8), (1 << (np.arange(n) % 8)).astype(np.uint8))
    return pos, row, bits.view(np.uint64)


def decoded(words: np.ndarray) -> np.ndarray:
    """The places of the bits that are set; words without any cost next to nothing."""
    full = np.flatnonzero(words)
    bits = np.flatnonzero(np.unpackbits(words[full].view(np.uint8), bitorder="little"))
    return full[bits >> 6] * 64 + (bits & 63)


def near_blocks(x: np.ndarray, rows: np.ndarray, size: int) -> list[np.ndarray]:
    """``rows`` in blocks of up to ``size`` that lie near one another in all dimensions: halved along the widest, over and over."""
    out, todo = [], [rows]
    while todo:
        part = todo.pop()
        if len(part) <= size:
            out.append(part)
            continue
        p = x[part]
        by = p[:, (p.max(axis=0) - p.min(axis=0)).argmax()]
        half = size * ((-(-len(part) // size) + 1) // 2)
        order = np.argpartition(by, half)
        todo += [part[order[half:]], part[order[:half]]]
    return out


class SlabIndex:
    """One bit table per dimension: a row for each occupied position, a column for each cell.

    A query ORs the rows within reach in every dimension and ANDs the results.
    The OR of a window depends on the position alone, so each is made once and the
    rows themselves are let go. Dimensions whose windows are narrowest come first;
    those whose tables don't fit into ``budget`` bytes are posting lists: the cells
    by position, of which a window is a slice.
    """

    name = "slab"

    def __init__(self, cells: np.ndarray, budget: int = 256 << 20, **_):
        self.cells, (self.n, self.d) = cells, cells.shape
        self.r = safe_reach(self.d)
        wide = []
        for i in range(self.d):
            pos, n = np.unique(cells[:, i], return_counts=True)
            before = np.concatenate([[0], np.cumsum(n)])
            held = before[np.searchsorted(pos, pos + self.r, "right")] - before[np.searchsorted(pos, pos - self.r)]
            wide.append((int((held * n).sum()), i, len(pos)))
        self.dims, self.rest, self.row, self.windows = [], [], {}, {}
        for _, i, positions in sorted(wide):
            size = positions * ((self.n + 63) // 64) * 8
            if size > budget:
                self.rest.append(i)
                continue
            budget -= size
            pos, self.row[i], table = bit_table(cells[:, i])
            low, high = np.searchsorted(pos, pos - self.r), np.searchsorted(pos, pos + self.r, "right")
            self.windows[i] = np.stack([np.bitwise_or.reduce(table[a:b], axis=0) for a, b in zip(low, high, strict=True)])
            self.dims.append(i)
        if not self.dims:
            self.posting = np.argsort(cells[:, self.rest[0]], kind="stable")
            self.posted = cells[self.posting, self.rest[0]]

    def bits(self, i) -> np.ndarray:
        """The cells within reach of cell ``i`` (or of each of several) by the bit tables, as words."""
        first, *others = self.dims
        out = self.windows[first][self.row[first][i]].copy()
        for k in others:
            out &= self.windows[k][self.row[k][i]]
        return out

    def _slice(self, low: int, high: int) -> np.ndarray:
        return np.sort(self.posting[np.searchsorted(self.posted, low - self.r) : np.searchsorted(self.posted, high + self.r, "right")])

    def candidates(self, i: int) -> np.ndarray:
        """Cells whose every coordinate lies within reach (the box rule), itself left out."""
        found = decoded(self.bits(i)) if self.dims else self._slice(self.cells[i, self.rest[0]], self.cells[i, self.rest[0]])
        for k in self.rest:
            found = found[np.abs(self.cells[found, k] - self.cells[i, k]) <= self.r]
        return found[found != i]

    def each(self, several: np.ndarray, block: int = 256) -> Iterator[np.ndarray]:
        """``candidates`` of one cell after the other, the words of a block at once."""
        if not self.dims or self.rest:
            yield from map(self.candidates, several.tolist())
            return
        for at in range(0, len(several), block):
            part = several[at : at + block]
            words = self.bits(part)
            words[np.arange(len(part)), part >> 6] &= ~(np.uint64(1) << (part & 63).astype(np.uint64))
            for row in words:
                yield decoded(row)

    def together(self, block: int) -> int:
        """Of so many cells how many ``meeting`` takes at once; none where bit tables don't hold all dimensions."""
        return 0 if self.rest else max(1, min(block, OffsetIndex.HELD // max(1, self.n)))

    def meeting(self, several: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
        """Cells from ``least`` on, and which of them lie within reach of each of several, themselves too."""
        words = self.bits(several)[:, least >> 6 :]
        bits = np.unpackbits(words.view(np.uint8), axis=1, bitorder="little")[:, least & 63 : self.n - (least >> 6 << 6)].view(bool)
        return np.arange(least, self.n), bits

    def around(self, several: np.ndarray) -> np.ndarray:
        """At least the cells within reach of any of several: windows are joined dimension by dimension."""
        if not self.dims:
            return self.union(several)
        out = None
        for k in self.dims:
            rows = self.row[k][several]
            words = np.bitwise_or.reduce(self.windows[k][rows.min() : rows.max() + 1], axis=0)
            out = words if out is None else np.bitwise_and(out, words, out=out)
        return decoded(out)

    def union(self, several: np.ndarray) -> np.ndarray:
        """At least the cells within reach of any of several cells, those included."""
        if self.dims:
            return decoded(np.bitwise_or.reduce(self.bits(several), axis=0))
        at = self.cells[several, self.rest[0]]
        return self._slice(at.min(), at.max())

    def neighbours(self, i: int) -> np.ndarray:
        found = self.candidates(i)
        return found[gaps2(self.cells, i, found) <= self.d]

    def nbytes(self) -> int:
        """Of all that queries read but the cells' addresses: windows, rows, posting lists."""
        return sum(x.nbytes for t in (self.windows, self.row) for x in t.values()) + (0 if self.dims else self.posting.nbytes + self.posted.nbytes)


def _union(index, several: np.ndarray) -> np.ndarray:
    return np.unique(np.concatenate([several, *(index.candidates(int(i)) for i in several)]))


def _each(index, several: np.ndarray) -> Iterator[np.ndarray]:
    return map(index.candidates, several.tolist())


class OffsetIndex:
    """A hash of occupied cells, probed at every reachable offset: exponential in the dimension.

    Where the offsets outnumber ``max_offsets`` every query goes over all occupied
    cells instead, which finds the same ones; a block of queries goes over them together.
    """

    name = "offsets"
    BLOCK, HELD, GROUP = 64, 1 << 22, 32

    def __init__(self, cells: np.ndarray, max_offsets: int = 100_000, **_):
        self.cells, (self.n, self.d) = cells, cells.shape
        self.r, self.at, self.place, self.offsets = safe_reach(self.d), None, {}, None
        if reachable_offset_count(self.d) <= max_offsets:
            self.place = {c: i for i, c in enumerate(map(tuple, cells.tolist()))}
            span = range(-self.r, self.r + 1)
            self.offsets = [o for o in product(span, repeat=self.d) if any(o) and sum(max(abs(x) - 1, 0) ** 2 for x in o) <= self.d]
        elif self.n:
            low = cells - cells.min(axis=0)
            self.by_dim = np.ascontiguousarray(low.T, np.int16 if low.max() < 32_000 and (self.r + 1) ** 2 * self.d < 32_000 else np.int64)
            groups = near_blocks(cells, np.arange(self.n), self.GROUP)
            self.grouped, self.group_at = np.concatenate(groups), np.cumsum([0, *map(len, groups)])
            kind = np.int32 if self.d * (int(low.max()) + 2) ** 2 < 2**31 else np.int64  # gaps are squared
            self.least, self.whole_by = cells.min(axis=0), np.ascontiguousarray(low.T, kind)
            self.low_by, self.high_by = (np.ascontiguousarray(f(low[self.grouped], self.group_at[:-1], axis=0).T, kind) for f in (np.minimum.reduceat, np.maximum.reduceat))

    def _box(self, several: np.ndarray, least: int = 0) -> np.ndarray:
        """The cells, from ``least`` on, that lie in reach of the box around several: gone over by groups, then one by one."""
        at = self.cells[several] - self.least
        low, high = at.min(axis=0), at.max(axis=0)
        near = np.flatnonzero(self._gaps2(self.low_by, self.high_by, None, low, high) <= self.d)
        begin = self.group_at[near]
        n = self.group_at[near + 1] - begin
        other = self.grouped[np.repeat(begin - np.cumsum(n) + n, n) + np.arange(n.sum())]
        other = other[other >= least] if least else other
        return np.sort(other[self._gaps2(self.whole_by, self.whole_by, other, low, high) <= self.d])

    @staticmethod
    def _gaps2(lows: np.ndarray, highs: np.ndarray, some: np.ndarray | None, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Squared gaps, in cells, between boxes (``some`` of them) and one box."""
        total = None
        for a, b, x, y in zip(lows, highs, low.tolist(), high.tolist(), strict=True):
            if some is not None:
                a = a[some]
                b = a if lows is highs else b[some]
            gap = np.maximum(a - (y + 1), (x - 1) - b)
            np.maximum(gap, 0, out=gap)
            gap *= gap
            total = gap if total is None else np.add(total, gap, out=total)
        return total

    def around(self, several: np.ndarray) -> np.ndarray:
        """At least the cells within reach of any of several: of their box, where cells are scanned."""
        return self.union(several) if self.offsets is not None else self._box(several)

    def together(self, block: int) -> int:
        return 0 if self.offsets is not None else max(1, min(block, self.HELD // max(1, self.n)))

    def meeting(self, several: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
        """Cells from ``least`` on that lie near the box around several: each of these meets them all."""
        other = self._box(several, least)
        return other, np.ones((len(several), len(other)), bool)

    def _met(self, several: np.ndarray, least: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """The cells near the box around several, and which of them lie in reach of each."""
        other = self._box(several, least)
        total = np.zeros((len(several), len(other)), self.by_dim.dtype)
        for x in self.by_dim:
            gap = x[other][None, :] - x[several][:, None]
            np.abs(gap, out=gap)
            gap -= 1
            np.clip(gap, 0, self.r + 1, out=gap)
            gap *= gap
            total += gap
        return other, total <= self.d

    def neighbours(self, i: int) -> np.ndarray:
        if self.offsets is None:
            if self.at is None or not self.at <= i < self.at + len(self.hit):
                self.at = i
                self.other, self.hit = self._met(np.arange(i, min(self.n, i + max(1, min(self.BLOCK, self.HELD // self.n)))))
            found = self.other[self.hit[i - self.at]]
            return found[found != i]
        c, get = self.cells[i].tolist(), self.place.get
        found = (get(tuple(x + y for x, y in zip(c, o, strict=True))) for o in self.offsets)
        return np.array(sorted(x for x in found if x is not None), np.int64)

    candidates = neighbours
    each = _each

    def union(self, several: np.ndarray) -> np.ndarray:
        if self.offsets is not None:
            return _union(self, several)
        step, near = max(1, min(self.BLOCK, self.HELD // max(1, self.n))), np.zeros(self.n, bool)
        near[several] = True
        for at in range(0, len(several), step):
            other, hit = self._met(several[at : at + step])
            near[other[hit.any(axis=0)]] = True
        return np.flatnonzero(near)

    def nbytes(self) -> int:
        """Of the hash table, its keys and the offsets; of nothing where the cells are scanned."""
        return 0 if self.offsets is None else (self.n + len(self.offsets)) * 8 * self.d + 16 * self.n


class BucketIndex(OffsetIndex):
    """The cells of two blocks of a bucket join: a cell's are found by going over all of them, a block's by its box."""

    name = "bucket"

    def __init__(self, cells: np.ndarray, **_):
        super().__init__(cells, max_offsets=0)


class KdIndex:
    """A median-split tree over the occupied cells, searched by boxes."""

    name = "kdtree"
    LEAF = 16

    def __init__(self, cells: np.ndarray, **_):
        self.cells, (self.n, self.d) = cells, cells.shape
        self.r = safe_reach(self.d)
        self.index, nodes = np.arange(self.n), []
        self._build(nodes, 0, self.n)
        self.low, self.high, self.dim, self.value, self.left, self.right = np.array(nodes, np.int64).reshape(-1, 6).T.copy()

    def _build(self, nodes: list, low: int, high: int) -> int:
        me = len(nodes)
        nodes.append((low, high, -1, 0, -1, -1))
        if high - low > self.LEAF:
            part = self.cells[self.index[low:high]]
            dim = int((part.max(axis=0) - part.min(axis=0)).argmax())
            order = np.argsort(part[:, dim], kind="stable")
            self.index[low:high] = self.index[low:high][order]
            mid = (low + high) // 2
            value = int(self.cells[self.index[mid], dim])
            left = self._build(nodes, low, mid)
            nodes[me] = (low, high, dim, value, left, self._build(nodes, mid, high))
        return me

    def candidates(self, i: int) -> np.ndarray:
        """Cells whose every coordinate lies within reach, itself left out; the tree is walked level by level."""
        found = self._inside(self.cells[i] - self.r, self.cells[i] + self.r)
        return found[found != i]

    def _inside(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Cells of the box between two addresses."""
        open_, leaves = np.zeros(1, np.int64), []
        while len(open_):
            dim = self.dim[open_]
            leaves.append(open_[dim < 0])
            open_, dim = open_[dim >= 0], dim[dim >= 0]
            value = self.value[open_]
            open_ = np.concatenate([self.left[open_[low[dim] <= value]], self.right[open_[high[dim] >= value]]])
        leaves = np.concatenate(leaves)
        start, n = self.low[leaves], self.high[leaves] - self.low[leaves]
        found = self.index[np.repeat(start - np.cumsum(n) + n, n) + np.arange(n.sum())]
        for k in range(0, self.d, 6):
            part = self.cells[found, k : k + 6]
            found = found[((part >= low[k : k + 6]) & (part <= high[k : k + 6])).all(axis=1)]
        return np.sort(found)

    def together(self, block: int) -> int:
        return max(1, min(block, OffsetIndex.HELD // max(1, self.n)))

    def meeting(self, several: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
        """Cells from ``least`` on that one search by the box around several finds: each of these meets them all."""
        other = self.union(several)
        other = other[np.searchsorted(other, least) :]
        return other, np.ones((len(several), len(other)), bool)

    def union(self, several: np.ndarray) -> np.ndarray:
        """At least the cells within reach of any of several, those included: one search by the box around them."""
        at = self.cells[several]
        return self._inside(at.min(axis=0) - self.r, at.max(axis=0) + self.r)

    each = _each

    def neighbours(self, i: int) -> np.ndarray:
        found = self.candidates(i)
        return found[gaps2(self.cells, i, found) <= self.d]

    def nbytes(self) -> int:
        """Of all that queries read but the cells' addresses: nodes and the cells' order."""
        return self.index.nbytes + sum(x.nbytes for x in (self.low, self.high, self.dim, self.value, self.left, self.right))


class RectangleTree:
    """Bulk-loaded rectangles over points (sort-tile-recursive), standing in for an insertion-built tree."""

    FAN = 32

    def __init__(self, x: np.ndarray):
        self.x, d = x, x.shape[1]
        order = np.arange(len(x))
        groups = [order]
        for dim in range(d):
            leaves = sum(-(-len(g) // self.FAN) for g in groups)
            if leaves <= len(groups):
                break
            parts = max(1, round((leaves / len(groups)) ** (1 / (d - dim)))) if dim < d - 1 else None
            new = []
            for g in groups:
                g = g[np.argsort(x[g, dim], kind="stable")]
                step = self.FAN if parts is None else max(self.FAN, -(-len(g) // parts))
                new += [g[a : a + step] for a in range(0, len(g), step)]
            groups = new
        self.order = np.concatenate(groups) if groups else order
        cuts = np.arange(0, len(x), self.FAN)
        self.levels = [(np.minimum.reduceat(x[self.order], cuts), np.maximum.reduceat(x[self.order], cuts))] if len(x) else []
        while self.levels and len(self.levels[-1][0]) > 1:
            lo, hi = self.levels[-1]
            cuts = np.arange(0, len(lo), self.FAN)
            self.levels.append((np.minimum.reduceat(lo, cuts), np.maximum.reduceat(hi, cuts)))

    def near(self, p: np.ndarray, limit2, wanted: np.ndarray | None = None) -> np.ndarray:
        """Rows of the leaves that a ball around any of several points meets; all of them go down the tree together.

        With ``wanted`` only such rows, and no leaf that holds none of them is looked at.
        """
        if not self.levels or wanted is not None and not wanted.any():
            return np.zeros(0, np.int64)
        full = None if wanted is None else np.logical_or.reduceat(wanted[self.order], np.arange(0, len(self.x), self.FAN))
        at, low, high = np.zeros(1, np.int64), p.min(axis=0), p.max(axis=0)
        for depth, (lo, hi) in enumerate(reversed(self.levels)):
            if depth:
                at = (at[:, None] * self.FAN + np.arange(self.FAN)).ravel()
                at = at[at < len(lo)]
            if full is not None and len(lo) == len(full):
                at = at[full[at]]
            gap = np.maximum(np.maximum(lo[at] - high, low - hi[at]), 0)
            at = at[(gap * gap).sum(axis=1) <= limit2]  # those that the box around all of them meets
            keep, step = [], max(1, (1 << 16) // len(p))
            for k in range(0, len(at), step):
                some = at[k : k + step]
                total = np.zeros((len(p), len(some)), lo.dtype)
                for x, a, b in zip(p.T, lo[some].T, hi[some].T, strict=True):
                    gap = np.maximum(a[None, :] - x[:, None], x[:, None] - b[None, :])
                    np.maximum(gap, 0, out=gap)
                    gap *= gap
                    total += gap
                keep.append((total <= limit2).any(axis=0))
            at = at[np.concatenate([*keep, np.zeros(0, bool)])]
        leaves = at
        rows = (leaves[:, None] * self.FAN + np.arange(self.FAN)).ravel()
        found = self.order[rows[rows < len(self.x)]]
        return found if wanted is None else found[wanted[found]]

    def within(self, p: np.ndarray, limit2) -> tuple[np.ndarray, np.ndarray]:
        """Rows within the closed ball around ``p`` and their squared distances."""
        rows = self.near(p[None, :], limit2)
        diff = self.x[rows] - p
        dd = (diff * diff).sum(axis=1)
        keep = dd <= limit2
        return rows[keep], dd[keep]


INDEXES = {"slab_pruned": SlabIndex, "slab_full": SlabIndex, "grid_full": OffsetIndex, "grid_approx": OffsetIndex, "kdtree_pruned": KdIndex, "reference": SlabIndex, "bucket_pruned": BucketIndex}
