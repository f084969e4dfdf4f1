import numpy as np
import pytest

from densegrid.operators.forest import Forest, merge_cells
from densegrid.operators.indexes import KdIndex, OffsetIndex, RectangleTree, SlabIndex, bit_table, gaps2
from densegrid.workloads import CELLS9, FOREST6


def cells(d, n, seed, spread=12):
    return np.unique(np.random.default_rng(seed).integers(-spread, spread, (n, d)), axis=0)


@pytest.mark.parametrize("d", [1, 2, 3, 4, 5])
def test_indexes_agree(d):
    c = cells(d, 200, d, spread=6)
    slab, tree = SlabIndex(c), KdIndex(c)
    offsets = OffsetIndex(c) if d <= 4 else None
    for i in range(len(c)):
        want = [j for j in range(len(c)) if j != i and gaps2(c, i, np.array([j]))[0] <= d]
        assert slab.neighbours(i).tolist() == want == tree.neighbours(i).tolist()
        if offsets:
            assert offsets.neighbours(i).tolist() == want


@pytest.mark.parametrize("d", [12, 40, 54])
def test_high_dimensions(d):
    c = cells(d, 150, d, spread=3)
    slab, tree = SlabIndex(c), KdIndex(c)
    for i in range(0, len(c), 7):
        want = [j for j in range(len(c)) if j != i and gaps2(c, i, np.array([j]))[0] <= d]
        assert slab.neighbours(i).tolist() == want == tree.neighbours(i).tolist()


def test_bit_tables():
    c = cells(3, 300, 9)
    for i in range(3):
        _, _, t = bit_table(c[:, i])
        assert len(t) == len(np.unique(c[:, i]))
        assert np.bitwise_count(t).sum() == len(c)  # every cell sets one bit in each dimension


def test_worked_layout():
    names = [n for n, _, _ in CELLS9]
    c = np.array([(x, y) for _, x, y in CELLS9])
    slab = SlabIndex(c)
    box = {n: {names[j] for j in slab.candidates(i) if (np.abs(c[j] - c[i]) <= 2).all()} for i, n in enumerate(names)}
    exact = {n: {names[j] for j in range(9) if j != i and gaps2(c, i, np.array([j]))[0] < 2} for i, n in enumerate(names)}
    assert [len(bit_table(c[:, i])[0]) for i in range(2)] == [6, 3]
    assert box["a"] == set("bcd") and box["d"] == set("abcefgi") and box["f"] == set("cdeghi") and box["g"] == set("cdefhi")
    assert exact["a"] == set("bcd") and exact["d"] == set("abcefgi") and exact["f"] == set("cdeghi") and exact["g"] == set("defi")


def test_gaps_between_positions():
    c = np.array([[x] for x in (-3, 0, 1, 5, 6, 40)])
    slab = SlabIndex(c)
    assert slab.neighbours(4).tolist() == [3]  # 6 sees 5, and not 40, its neighbour by rank
    assert slab.neighbours(5).tolist() == []


@pytest.mark.parametrize("budget", [0, 2000, 1 << 20])
def test_byte_budget_changes_nothing(budget):
    c = cells(5, 300, 4, spread=9)
    slab, tree = SlabIndex(c, budget=budget), KdIndex(c)
    assert (len(slab.dims) == 0) == (budget == 0) and (len(slab.dims) == 5) == (budget == 1 << 20)
    assert sum(w.nbytes for w in slab.windows.values()) <= budget
    for i in range(len(c)):
        assert slab.candidates(i).tolist() == tree.candidates(i).tolist()
    some = np.arange(3, 40, 5)
    assert {*np.concatenate([tree.candidates(int(i)) for i in some]).tolist(), *some.tolist()} <= {*slab.union(some).tolist()}


def test_index_bytes_count_what_queries_read():
    c = cells(3, 300, 9)
    slab, tree = SlabIndex(c), KdIndex(c)
    assert slab.nbytes() == sum(x.nbytes for t in (slab.windows, slab.row) for x in t.values())
    tree.left[:] = tree.right[:] = 0  # the arrays that are counted are those that are searched
    tree.dim[:] = -1
    tree.high[0] = 5
    assert len(tree.candidates(int(tree.index[0]))) <= 4


def test_offsets_beyond_the_bound_scan_the_cells():
    c = cells(7, 150, 1, spread=4)
    scan, tree = OffsetIndex(c), KdIndex(c)
    assert scan.offsets is None
    for i in range(len(c)):
        assert scan.neighbours(i).tolist() == tree.neighbours(i).tolist()


def test_rectangle_tree():
    x = np.random.default_rng(2).integers(0, 100, (700, 3))
    tree = RectangleTree(x)
    for i in range(0, 700, 13):
        rows, dd = tree.within(x[i], 400)
        want = ((x - x[i]) ** 2).sum(axis=1)
        assert sorted(rows.tolist()) == np.flatnonzero(want <= 400).tolist() and (want[rows] == dd).all()


@pytest.mark.parametrize("visit,want", [("once", (7, 1, 6, 4)), ("both", (14, 7, 7, 4))])
def test_worked_forest(visit, want):
    pairs, good = FOREST6
    near = {v: np.array(sorted({b for a, b in pairs if a == v} | {a for a, b in pairs if b == v})) for v in range(7)}
    forest, c = merge_cells(range(1, 7), lambda g: near[g], lambda a, b: (min(a, b), max(a, b)) in good, 7, True, visit)
    assert (c.considered, c.skipped, c.checks, c.unions) == want
    assert len({forest.root[i] for i in (1, 2, 3)}) == 1 == len({forest.root[i] for i in (4, 5, 6)}) and forest.root[1] != forest.root[4]


@pytest.mark.parametrize("policy", ["naive", "by_size", "by_min_id"])
@pytest.mark.parametrize("compress", [True, False])
def test_union_find(policy, compress):
    rng = np.random.default_rng(4)
    f, label = Forest(60, policy, compress), list(range(60))
    unions = 0
    for a, b in rng.integers(0, 60, (80, 2)).tolist():
        unions += f.union(a, b)
        label = [label[a] if x == label[b] else x for x in label]
    assert len(set(f.roots())) == len(set(label)) == 60 - unions
    assert all((f.find(a) == f.find(b)) == (label[a] == label[b]) for a in range(60) for b in range(60))


def test_checks_are_counted():
    rng = np.random.default_rng(8)
    n = 80
    near = {i: np.array(sorted(set(rng.integers(0, n, 20).tolist()) - {i})) for i in range(n)}
    for i in range(n):
        for j in near[i].tolist():
            near[j] = np.unique(np.append(near[j], i))
    good = lambda a, b: (min(a, b) * 7 + max(a, b)) % 3 == 0
    full, c_full = merge_cells(range(n), near.get, good, n, False, "both")
    both, c_both = merge_cells(range(n), near.get, good, n, True, "both")
    once, c_once = merge_cells(range(n), near.get, good, n, True, "once")
    assert c_once.checks <= c_both.checks <= c_full.checks
    assert c_full.unions == c_both.unions == c_once.unions == n - len(set(full.root.tolist()))
    for c in (c_full, c_both, c_once):
        assert c.considered == c.skipped + c.boxed + c.checks and c.checks >= c.unions
    assert c_full.skipped == c_full.boxed == 0
    same = lambda r: [r.tolist().index(x) for x in r.tolist()]
    assert same(full.root) == same(both.root) == same(once.root)
