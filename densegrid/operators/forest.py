"""Union-find forests and merging over them (M2 to M4)."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


class Forest:
    """Disjoint trees over 0..n-1; ``policy`` says which root stays, ``compress`` whether finds shorten paths."""

    def __init__(self, n: int, policy: str = "by_size", compress: bool = True):
        if policy not in ("naive", "by_size", "by_min_id"):
            raise ValueError(policy)
        self.parent, self.size, self.policy, self.compress, self.hops = list(range(n)), [1] * n, policy, compress, 0

    def find(self, x: int) -> int:
        p = self.parent
        root = x
        while p[root] != root:
            root = p[root]
            self.hops += 1
        while self.compress and p[x] != root:
            p[x], x = root, p[x]
        return root

    def union(self, x: int, y: int) -> bool:
        """Makes one root a child of the other; false if they were one already."""
        a, b = self.find(x), self.find(y)
        if a == b:
            return False
        if (self.policy == "by_size" and self.size[a] < self.size[b]) or (self.policy == "by_min_id" and b < a):
            a, b = b, a
        self.parent[b] = a
        self.size[a] += self.size[b]
        return True

    def roots(self) -> list[int]:
        return [self.find(x) for x in range(len(self.parent))]


def packed(members, n: int) -> np.ndarray:
    """The members of 0..n-1 as bits in words."""
    bits = np.zeros((n + 63) // 64 * 64, np.uint8)
    bits[members] = 1
    return np.packbits(bits, bitorder="little").view(np.uint64)


class FlatForest:
    """Roots kept flat, so that many cells are compared at once; the smaller tree is relabelled.

    Trees of ``LARGE`` cells and more are also kept as bits.
    """

    LARGE = 64

    def __init__(self, n: int):
        self.root, self.members, self._words = np.arange(n), {i: [i] for i in range(n)}, {}

    def union(self, x: int, y: int) -> None:
        a, b = int(self.root[x]), int(self.root[y])
        if len(self.members[a]) < len(self.members[b]):
            a, b = b, a
        moved = self.members.pop(b)
        self.root[moved] = a
        self.members[a] += moved
        gone = self._words.pop(b, None)
        if a in self._words:
            own = self._words[a]
            if gone is not None:
                own |= gone
            else:
                for i in moved:
                    own[i >> 6] |= np.uint64(1 << (i & 63))

    def words(self, x: int) -> np.ndarray | None:
        """The tree of ``x`` as bits, if it is large."""
        a = int(self.root[x])
        if a not in self._words and len(self.members[a]) >= self.LARGE:
            self._words[a] = packed(self.members[a], len(self.root))
        return self._words.get(a)


@dataclass
class MergeCounts:
    """Pairs met; of these, skipped since their roots were equal, ruled out by boxes, checked; and unions made."""

    considered: int = 0
    skipped: int = 0
    boxed: int = 0
    checks: int = 0
    unions: int = 0
    links: list[tuple[int, int]] = field(default_factory=list)


def merge_cells(vertices, partners, check, n: int, pruned: bool = True, visit: str = "once", narrow=None, meet=None, among=None, forest: FlatForest | None = None) -> tuple[FlatForest, MergeCounts]:
    """Merges cells. ``partners(g)`` are the core cells near g in visiting order, ``check(g, h)`` the costly test.

    With ``pruned`` a pair whose roots are equal is skipped; roots are compared
    again after each union, so the order is that of one pair after the other.
    ``once`` drops partners before their cell, ``both`` meets each pair from both
    ends. ``narrow(g, cells)`` may drop partners that cannot pass the check; it is
    asked only about those that would be checked. ``meet(g, forest)``, in place of
    ``partners``, gives the number met and those whose roots differ; if it has ``checked``, these
    have passed the check, as some of so many. ``among(g, cells)``
    checks all of a cell's partners at once; without ``pruned`` none depends on another.
    Every pair considered is counted once: as skipped, boxed or checked. ``forest``: trees to begin from.
    """
    forest, counts = forest or FlatForest(n), MergeCounts()
    for g in vertices:
        if meet is not None:
            met, near = meet(g, forest)
            if (checked := getattr(meet, "checked", None)) is not None:  # what is left has passed the check
                counts.considered += met
                counts.checks += checked
                counts.skipped += met - checked
                while len(near):
                    h = int(near[0])
                    forest.union(g, h)
                    counts.unions += 1
                    counts.links.append((g, h))
                    near = near[forest.root[near] != forest.root[g]]
                continue
        else:
            near = partners(g)
            if visit == "once":
                near = near[near > g]
            met = len(near)
            if pruned:
                near = near[forest.root[near] != forest.root[g]]
        counts.considered += met
        counts.skipped += met - len(near)
        if narrow is not None and len(near):
            left = narrow(g, near)
            counts.boxed += len(near) - len(left)
            near = left
        if among is not None and not pruned and len(near):
            counts.checks += len(near)
            near = near[among(g, near)]
            near = near[forest.root[near] != forest.root[g]]
            while len(near):
                h = int(near[0])
                forest.union(g, h)
                counts.unions += 1
                counts.links.append((g, h))
                near = near[forest.root[near] != forest.root[g]]
            continue
        while len(near):
            rest = near[:0]
            for k, h in enumerate(near.tolist()):
                counts.checks += 1
                if check(g, h) and forest.root[g] != forest.root[h]:
                    forest.union(g, h)
                    counts.unions += 1
                    counts.links.append((g, h))
                    if pruned:
                        rest = near[k + 1 :]
                        break
            near = rest[forest.root[rest] != forest.root[g]]
            counts.skipped += len(rest) - len(near)
    return forest, counts
