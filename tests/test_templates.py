from itertools import permutations
from math import comb, factorial

import pytest

from treecount.plans import cost
from treecount.plans.templates import CATALOGUE, TreeTemplate, automorphisms, last_use, merge, partition

#: template: k, automorphisms, sub-templates, splits unshared, splits shared, passive columns by parent and by shape, widest table.
KNOWN = {
    "path3": (3, 2, 3, 9, 9, 6, 6, 3), "path4": (4, 2, 4, 28, 28, 14, 14, 6), "star4": (4, 6, 4, 28, 28, 12, 4, 6), "path5": (5, 2, 5, 75, 75, 30, 30, 10), "star5": (5, 24, 5, 75, 75, 20, 5, 10), "spider6": (6, 2, 4, 195, 135, 36, 21, 15),
    "bin7": (7, 8, 5, 469, 322, 84, 42, 35), "t10": (10, 2, 7, 6012, 5742, 607, 517, 252), "t12": (12, 4, 7, 44385, 40887, 1300, 793, 495), "t13": (13, 1296, 7, 108862, 101114, 2184, 728, 1287), "t14": (14, 2, 9, 217828, 216008, 8010, 7905, 3432),
    "t15a": (15, 128, 7, 525585, 290175, 13810, 6905, 6435), "t15b": (15, 2, 9, 431550, 430290, 16398, 16383, 6435), "t16": (16, 48, 7, 2207952, 2116032, 13360, 4504, 8008), "t17": (17, 31104, 8, 4845408, 4809912, 9571, 2397, 24310),
}


@pytest.mark.parametrize("name", KNOWN)
def test_plans(name):
    t = CATALOGUE[name]
    p, u = partition(t), partition(t, share=False)
    widest = max(comb(t.size, s.size) for s in p)
    assert (t.size, automorphisms(t), len(p), cost.split_sum(u, t.size), cost.split_sum(p, t.size), cost.walked_sum(p, t.size), cost.walked_sum(p, t.size, True), widest) == KNOWN[name]


@pytest.mark.parametrize("name", [n for n, t in CATALOGUE.items() if t.size <= 7])
def test_automorphisms_by_permutation(name):
    t = CATALOGUE[name]
    edges = {frozenset(e) for e in t.edges()}
    assert automorphisms(t) == sum({frozenset((p[a], p[b])) for a, b in t.edges()} == edges for p in permutations(range(t.size)))


@pytest.mark.parametrize("cut", ["largest", "smallest", "first", "balanced"])
def test_children_before_parents(cut):
    for t in CATALOGUE.values():
        for root in range(0, t.size, 3):
            seen = {}
            for s in partition(t, root, cut):
                assert s.active is None or (seen[s.active] == s.active_size and seen[s.passive] == s.passive_size and s.active_size + s.passive_size == s.size)
                seen[s.key] = s.size
            assert s.size == t.size


def test_rejects_what_is_no_tree():
    for parents in ([], [0], [-1, 2, 1], [-1, 1], [-1, 5]):
        with pytest.raises(ValueError):
            TreeTemplate(tuple(parents))


def test_same_tree_from_other_roots():
    assert CATALOGUE["path5"].canonical() == CATALOGUE["path5mid"].canonical() != CATALOGUE["fork5"].canonical()


def test_merge_and_last_use():
    p, q = partition(CATALOGUE["path4"]), partition(CATALOGUE["star4"])
    both = merge([p, q])
    assert len(both) < len(p) + len(q) and len({s.key for s in both}) == len(both)
    assert last_use(p)[p[-1].key] == len(p) - 1


def test_cost_identities():
    for k in range(2, 14):
        for s in range(2, k + 1):
            for p in range(1, s):
                assert comb(k, p) * cost.reuse_factor(k, s, p) == comb(k, s) * comb(s, p)
    assert cost.reuse_factor(3, 2, 1) == 2 and cost.reuse_factor(5, 5, 2) == 1


def test_binomial_bounds_hold_with_one_constant():
    for i in range(3):
        ratios = [cost.binomial_maxima(n)[i] / cost.binomial_bounds(n)[i] for n in range(2, 31)]
        assert max(ratios) <= 2


def test_improvement_bounds_and_limits():
    c = cost.Constants(2.0, 1.0, 3.0)
    for n in ("t10", "t12", "t13", "t14", "t15a", "t15b", "t16", "t17"):
        t = CATALOGUE[n]
        p = partition(t, share=False)
        low, high = cost.split_sum_bounds(t.size)
        assert low <= cost.split_sum(p, t.size) <= high
        for d in (2, 50, 200, 1e6):
            lo, hi = cost.improvement_bounds(t.size, d, c)
            assert lo <= cost.improvement(p, t.size, d, c) <= hi <= c.gamma * d / c.beta
    assert cost.improvement_bounds(12, 1e12, c)[0] == pytest.approx(c.gamma / c.alpha * 12 / 2)
    assert cost.improvement_bounds(12, 50, c, paper_form=True)[1] > cost.improvement_bounds(12, 50, c)[1]


def test_improvement_grows_with_size_and_degree():
    c = cost.Constants(2.0, 1.0, 3.0)
    by_size = [cost.improvement(partition(CATALOGUE[n]), CATALOGUE[n].size, 100, c) for n in ("t10", "t12", "t13", "t16", "t17")]
    assert by_size == sorted(by_size)
    p = partition(CATALOGUE["t12"])
    assert cost.improvement(p, 12, 0.02, c) / cost.improvement(p, 12, 0.01, c) == pytest.approx(2, rel=0.05)


def test_memory_and_root_choice():
    t = CATALOGUE["t17"]
    widest, peak = cost.memory(partition(t), 17, 1e6, 4)
    assert widest == 1e6 * 24310 * 4 and peak >= widest
    root, cut = cost.best_root(CATALOGUE["t10"])
    assert cost.memory(partition(CATALOGUE["t10"], root, cut), 10, 1)[1] <= cost.memory(partition(CATALOGUE["t10"]), 10, 1)[1]


def test_factorial_scale():
    from treecount.plans.estimator import factor, iterations_for

    assert factor(CATALOGUE["path3"]) == pytest.approx(27 / factorial(3) / 2)
    assert iterations_for(0.1, 0.1, 3) == 4625 and iterations_for(0.1, 0.1, 5) == 34174
