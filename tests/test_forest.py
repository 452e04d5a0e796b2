import pytest

from neardup.operators.forest import BoundedForest, DisjointSets, fold_buckets

RUNS = {k: set(range(7 * k + 1, 7 * k + 50)) for k in range(4)}


def sim(x, y):
    return len(RUNS[x] & RUNS[y]) / len(RUNS[x] | RUNS[y])


def test_similarities_of_the_fixture():
    assert (sim(0, 1), round(sim(0, 2), 3), sim(0, 3)) == (0.75, 0.556, 0.4)


def test_union_that_would_break_the_guarantee_is_refused():
    f = BoundedForest(0.4, sim)
    assert f.union(0, 1) and f.union(2, 3) and not f.union(1, 2)
    assert f.find(0) == f.find(1) != f.find(2) == f.find(3)
    assert f.bound[f.find(0)] == 0.75


def test_lower_tree_threshold_accepts_and_lowers_the_bound():
    assert not (f := BoundedForest(0.4, sim)).union(0, 1) or not f.union(1, 2)
    f = BoundedForest(0.3, sim)
    assert f.union(0, 1) and f.union(1, 2)
    assert f.bound[f.find(0)] == pytest.approx(sim(0, 2)) and f.rank[f.find(0)] == 1


def test_first_of_two_singles_becomes_root():
    f = BoundedForest(0.4, lambda x, y: 0.8)
    assert f.union(5, 3) and f.find(3) == 5 and f.rank[5] == 1 and f.bound[5] == pytest.approx(0.8)


def test_fold_compares_roots_only():
    forest, seen = fold_buckets([[0, 1], [0, 1, 2], [2, 3]], sim, 0.7, 0.4)
    assert [(x, y) for x, y, _ in seen] == [(0, 1), (0, 2), (2, 3)]
    assert forest.find(0) == forest.find(1) and forest.find(2) == forest.find(3) != forest.find(0)


def test_plain_sets_chain_everything():
    d = DisjointSets()
    assert all(d.union(i, i + 1) for i in range(50)) and len({d.find(i) for i in range(51)}) == 1 and not d.union(0, 50)


def test_guarantee_holds_for_any_order():
    import random

    r = random.Random(1)
    sets = [frozenset(r.sample(range(40), 25)) for _ in range(40)]
    s = lambda x, y: len(sets[x] & sets[y]) / len(sets[x] | sets[y])
    for _ in range(20):
        pairs = [(i, j) for i in range(40) for j in range(i)]
        r.shuffle(pairs)
        f = BoundedForest(0.4, s)
        for i, j in pairs:
            if s(i, j) > 0.5:
                f.union(i, j)
        for i, j in pairs:
            if f.find(i) == f.find(j):
                assert s(i, j) >= 0.4 - 1e-9
        assert all(s(f.find(i), i) >= f.bound.get(f.find(i), 1.0) - 1e-9 for i in range(40))
