import random

import pytest

from dense_tucker.model.meta import NAMED, NoValidGrid, TensorMeta
from dense_tucker.plans import grids as G
from dense_tucker.plans import optimal, trees
from dense_tucker.plans.planner import STRATEGIES, Plan, plan, strategy


def metas(seed, sizes, most, count):
    rng = random.Random(seed)
    for _ in range(count):
        n = rng.choice(sizes)
        L = [rng.randint(1, most) for _ in range(n)]
        yield TensorMeta(tuple(L), tuple(rng.randint(1, x) for x in L))


def test_published_loads():
    want = {"HCCI": (1506.3373, 1023.7201, 1091.5947, 699.1798), "TJLR": (2283.1454, 1923.8609, 1864.4309, 1129.8101), "SP": (581.3944, 314.4360, 578.6546, 257.9103), "least_gain": (1435.35, 179.0, 247.75, 417.3), "greatest_gain": (474.48, 138.28, 167.64, 127.28)}
    for name, loads in want.items():
        m = NAMED[name]
        got = [trees.tree_load(trees.chain_tree(trees.mode_order(m, by)), m, True) for by in ("natural", "K", "h")]
        got.append(trees.tree_load(trees.balanced_tree(trees.mode_order(m)), m, True))
        assert [round(x, 4) for x in got] == list(loads)
        assert optimal.optimal_tree(m)[1] <= min(got) * m.cardinality()


def test_small_worked_cases():
    m = TensorMeta((4, 4, 4), (2, 2, 2))
    assert [trees.tree_load(t, m) for t in (trees.chain_tree([0, 1, 2]), trees.balanced_tree([0, 1, 2]), optimal.optimal_tree(m)[0])] == [576, 448, 448]
    assert [trees.ttm_count(trees.balanced_tree(list(range(n)))) for n in range(2, 7)] == [2, 5, 8, 12, 16]
    m = TensorMeta((1000, 100, 100), (1000, 1, 1))
    assert optimal.Search(m).solve(0, 0b110) == 22 * m.cardinality()
    assert optimal.Search(m, "always_reuse").solve(0, 0b110) == 1002 * m.cardinality()
    assert optimal.optimal_tree(m)[1] * 100 == 2201 * m.cardinality()
    assert any(sets == (0b0100, 0b0011, 0b1000) for sets in trees.classify(trees.balanced_tree([0, 1, 2, 3]), 4).values())


def test_grid_counts():
    assert [[G.count_grids(2**e, n) for n in range(5, 11)] for e in (5, 10)] == [[126, 252, 462, 792, 1287, 2002], [1001, 3003, 8008, 19448, 43758, 92378]]
    assert G.count_grids(2**20, 10) == 10015005
    assert all(len(G.enumerate_grids(p, n)) == G.count_grids(p, n) for p in (1, 6, 12, 32) for n in (1, 2, 3, 4))
    with pytest.raises(NoValidGrid):
        G.valid_grids(TensorMeta((3, 3), (2, 2)), 7)


def test_optimal_tree_equals_brute_force():
    for m in metas(1, (2, 3, 4), 12, 40):
        tree, load, stats = optimal.optimal_tree(m)
        trees.validate_tree(tree, m.n)
        assert load == optimal.brute_force_load(m) == trees.tree_load(tree, m)
        assert stats.states <= 3**m.n and stats.lookups <= 2 * 4**m.n
        for by in ("natural", "K", "h"):
            for build in (trees.chain_tree, trees.balanced_tree):
                other = build(trees.mode_order(m, by))
                two = trees.binarise(other)
                trees.validate_tree(two, m.n)
                assert all(len(x.children) <= 2 for *_, x in two.walk())
                assert load <= trees.tree_load(two, m) <= trees.tree_load(other, m)
                trace = trees.execution_schedule(other)
                assert trees.peak_live_tensors(trace) <= trees.depth(other)
                assert sum(1 if w == "make" else -1 for w, _ in trace) == 0


def test_dynamic_grids_equal_brute_force():
    checked = 0
    for m in metas(2, (2, 3), 8, 30):
        tree = optimal.optimal_tree(m)[0]
        for p in (1, 2, 4):
            try:
                grids = G.valid_grids(m, p)
            except NoValidGrid:
                continue
            best = G.best_dynamic_scheme(tree, m, p)
            assert best.total <= G.best_static_grid(tree, m, p)[1]
            assert best.total <= G.best_dynamic_scheme(tree, m, p, "children_only").total
            assert p > 1 or best.total == 0
            if len(grids) ** (1 + trees.ttm_count(tree)) < 20_000:
                assert best.total == min(x.total for x in G.enumerate_schemes(tree, m, p))
                checked += 1
    assert checked > 20


def test_plans():
    for m in NAMED.values():
        plans = {name: strategy(m, 32, name) for name in STRATEGIES}
        assert plans["opt_dynamic"].load == plans["opt_static"].load == min(p.load for p in plans.values())
        assert plans["opt_dynamic"].volume <= plans["opt_static"].volume
        again = Plan.from_json(plans["opt_dynamic"].to_json())
        assert (again.load, again.volume, again.tree) == (plans["opt_dynamic"].load, plans["opt_dynamic"].volume, plans["opt_dynamic"].tree)
        assert "factor 1" in again.explain()
    assert plan(NAMED["SP"], 32, joint=True).load <= strategy(NAMED["SP"], 32, "chain_K").load


def test_validation():
    with pytest.raises(ValueError):
        TensorMeta((2, 2), (3, 1))
    with pytest.raises(ValueError):
        trees.validate_tree(trees.root(trees.leaf(0), trees.leaf(1)), 2)
    with pytest.warns(UserWarning):
        TensorMeta((9, 2), (9, 2)).validate()
