"""Worked examples by hand, exact baselines and invariants that need no cluster."""

import random

import numpy as np
import pytest

from blockwright.functions import hashes as h
from blockwright.model import BlockingConfig, BlockTree, HashFn, Interval, Node, RoundPlan
from blockwright.operators import cost, drilldown, learn, rollup
from blockwright.operators.sizes import Features


def test_scores_by_hand():
    sizes, pairs = np.array([250.0, 120.0]), np.array([4.0, 2.0])
    got = [learn.elimination(s, 2, sizes, pairs, 100) for s in learn.SCORERS]
    assert got[:2] == [2, 8] and got[2] == pytest.approx(5.666667, abs=1e-6)


def test_rollup_by_hand():
    sizes = {"A": 4, "B": 3, "C": 5, "D": 2}
    cross = {("A", "B"): 3, ("A", "C"): 4, ("B", "D"): 1, ("C", "D"): 2}
    groups = rollup.greedy(sizes, cross, 8)
    assert {frozenset(g) for g in groups} == {frozenset("AB"), frozenset("CD")}
    assert rollup.recovered(groups, cross) == 5 == rollup.recovered(rollup.exact_rollup(sizes, cross, 8), cross)


def test_rollup_trap_and_safeguard():
    sizes, cross = {"X": 10, "a": 1, "b": 10}, {("X", "a"): 2, ("X", "b"): 10}
    assert rollup.recovered(rollup.greedy(sizes, cross, 20), cross) == 2
    assert rollup.recovered(rollup.best_greedy(sizes, cross, 20), cross) == 10


def test_rollup_random_against_exact():
    rnd = random.Random(3)
    for _ in range(60):
        sizes = {f"b{i}": rnd.randint(1, 6) for i in range(6)}
        cross = {(a, b): rnd.randint(1, 5) for a in sizes for b in sizes if a < b and rnd.random() < 0.4}
        groups = rollup.best_greedy(sizes, cross, 10)
        assert sorted(k for g in groups for k in g) == sorted(sizes)
        assert all(sum(sizes[k] for k in g) <= 10 for g in groups)
        assert rollup.recovered(groups, cross) <= rollup.recovered(rollup.exact_rollup(sizes, cross, 10), cross)
        packed = rollup.first_fit(list(sizes.items()), 10)
        assert sorted(k for g in packed for k in g) == sorted(sizes) and all(sum(sizes[k] for k in g) <= 10 for g in packed)
        # first fit by falling size, the plain way
        bins: list = []
        for k, n in sorted(sizes.items(), key=lambda x: (-x[1], x[0])):
            fit = next((b for b in bins if sum(sizes[x] for x in b) + n <= 10), None)
            bins.append([k]) if fit is None else fit.append(k)
        assert packed == bins
        assert len(rollup.first_fit(list(sizes.items()), 10, target=len(sizes))) == len(sizes) and len(rollup.first_fit(list(sizes.items()), 10**6, target=2)) == 2


def _naive_greedy(sizes, cross, cap):
    """Recount every benefit before every merge."""
    groups = {k: {k} for k in sizes}
    while True:
        size = {g: sum(sizes[k] for k in ks) for g, ks in groups.items()}
        of = {k: g for g, ks in groups.items() for k in ks}
        gain: dict = {}
        for (a, b), n in cross.items():
            x, y = sorted((of[a], of[b]))
            if x != y and size[x] + size[y] <= cap:
                gain[(x, y)] = gain.get((x, y), 0) + n
        if not gain:
            return {frozenset(g) for g in groups.values()}
        x, y = min(gain, key=lambda p: (-gain[p] / min(size[p[0]], size[p[1]]), p))
        groups[x] |= groups.pop(y)


def test_lazy_greedy_is_the_plain_greedy():
    rnd = random.Random(6)
    for _ in range(200):
        sizes = {f"b{i:02}": rnd.randint(1, 6) for i in range(12)}
        cross = {(a, b): rnd.randint(1, 5) for a in sizes for b in sizes if a < b and rnd.random() < 0.3}
        assert {frozenset(g) for g in rollup.greedy(sizes, cross, 14)} == _naive_greedy(sizes, cross, 14)


def test_drilldown_by_hand():
    counts = [(v, 2) for v in range(1, 7)]
    pairs = [(1, 2), (2, 3), (3, 4), (3, 4), (5, 6)]
    assert drilldown.exhaustive_drilldown(counts, pairs, 6) == 1
    ends = list(range(1, 7))
    assert drilldown.solve(ends, pairs, drilldown.reach_of([2] * 6, [0] * 5, 6))[0] == 1


def test_drilldown_recurrence_against_all_cuts_and_ends_alone():
    rnd = random.Random(11)
    for _ in range(400):
        m = rnd.randint(1, 9)
        counts = [(v, rnd.randint(1, 4)) for v in range(m)]
        pairs = [tuple(sorted((rnd.randrange(m), rnd.randrange(m)))) for _ in range(rnd.randint(0, 6))]
        value, starts = drilldown.solve_full(counts, pairs, 7)
        assert value == drilldown.exhaustive_drilldown(counts, pairs, 7)
        of = np.searchsorted(starts, range(m), "right")
        assert sum(of[a] != of[b] for a, b in pairs) == value
    counts = [(v, rnd.randint(1, 30)) for v in range(400)]
    pairs = [(a, min(399, a + rnd.randrange(12))) for a in (rnd.randrange(400) for _ in range(300))]
    ends, by = sorted({x for p in pairs for x in p}), dict(counts)
    gaps = [sum(by[v] for v in range(a + 1, b)) for a, b in zip(ends, ends[1:])]
    assert drilldown.solve_full(counts, pairs, 150)[0] == drilldown.solve(ends, pairs, drilldown.reach_of([by[e] for e in ends], gaps, 150))[0]


def test_drilldown_solver_grows_nearly_in_proportion():
    import time

    def seconds(k):
        rnd = random.Random(k)
        pairs = [(a, min(k - 1, a + rnd.randrange(200))) for a in (rnd.randrange(k) for _ in range(k))]
        t = time.perf_counter()
        drilldown.solve(list(range(k)), pairs, [k - 1] * k)
        return time.perf_counter() - t

    small, large = min(seconds(5_000) for _ in range(3)), seconds(50_000)
    assert large < 30 * small + 0.5


def test_drilldown_random_against_all_cuts():
    rnd = random.Random(1)
    for _ in range(800):
        m = rnd.randint(1, 9)
        counts = [(v, rnd.randint(1, 4)) for v in range(m)]
        pairs = [tuple(sorted((rnd.randrange(m), rnd.randrange(m)))) for _ in range(rnd.randint(0, 6))]
        cap = rnd.randint(4, 12)
        ends, by = sorted({x for p in pairs for x in p}), dict(counts)
        gaps = [sum(by[v] for v in range(a + 1, b)) for a, b in zip(ends, ends[1:])]
        value, runs = drilldown.solve(ends, pairs, drilldown.reach_of([by[e] for e in ends], gaps, cap))
        assert value == drilldown.exhaustive_drilldown(counts, pairs, cap)
        assert [r[0] for r in runs[1:]] == [r[1] + 1 for r in runs[:-1]]


def test_intervals_cover():
    t = drilldown.tile([(1, 3), (4, 2)], 5)
    assert drilldown.is_dcc(t) and not drilldown.is_dcc(t[:1])
    assert drilldown.broken(t, [(1, 3), (3, 4), (None, 4)]) == 1


def test_machines():
    ones = [1] * 8
    assert cost.schedule(ones, 4)[0] == 2
    rnd = random.Random(5)
    for _ in range(40):
        sq = [rnd.randint(1, 9) ** 2 for _ in range(7)]
        lower = max(max(sq), sum(sq) / 3)
        best = cost.schedule(sq, 3, "exact")[0]
        for m in ("lpt", "list"):
            got = cost.schedule(sq, 3, m)[0]
            assert lower <= best <= got <= 2 * lower
        assert cost.schedule(sq, 3, "round_robin")[0] >= lower


def _features(codes, values, same, code, names=None):
    lib = [HashFn("identity", n) for n in (names or [f"a{i}" for i in range(codes.shape[1])])]
    n = len(same)
    vals = np.array([["v"] * codes.shape[1]] * n, object).reshape(n, codes.shape[1])
    for p in range(n):
        for k in range(codes.shape[1]):
            vals[p, k] = values[k][code[p, k] - 1] if code[p, k] else "light"
    return Features(lib, 2, float(len(codes)), codes, np.ones(len(codes)), values, np.array([(i, i + 100) for i in range(n)]).reshape(n, 2), same, code, vals, np.zeros((n, 2), np.int64))


def test_learners_on_random_tables():
    """Exactly one leaf a record, optimistic <= expected <= pessimistic, block tree's root = single's function, rounds never lose."""
    rnd = np.random.default_rng(2)
    for _ in range(30):
        k, n, cap = 4, 60, 6
        raw = rnd.integers(0, 4, (n, k))
        values, codes = [], np.zeros((n, k), np.int32)
        for j in range(k):
            heavy = [v for v in range(4) if (raw[:, j] == v).sum() > cap]
            values.append([f"v{v}" for v in heavy])
            for i, v in enumerate(heavy):
                codes[raw[:, j] == v, j] = i + 1
        l, r = rnd.integers(0, n, 25), rnd.integers(0, n, 25)
        same = raw[l] == raw[r]
        code = np.where(same, codes[l], 0)
        f = _features(codes, values, same, code)
        every = np.arange(n), np.arange(25)
        scores = [learn.score_all(f, *every, cap, s).score for s in learn.SCORERS]
        assert (scores[0] <= scores[2] + 1e-9).all() and (scores[2] <= scores[1] + 1e-9).all()
        for h_ in range(k):
            one = learn.split(f, *every, h_, cap, "expected")
            assert one.score == pytest.approx(scores[2][h_]) and one.broken == scores[0][h_]
        c = BlockingConfig(cap, scorer="expected")
        trees = {name: learner(f, c) for name, learner in learn.LEARNERS.items()}
        assert trees["single"].root.hash == trees["block_tree"].root.hash
        for t in trees.values():
            assert BlockTree.from_json(t.to_json()) == t
            assert 0 <= learn.recall(f, t) <= 1
        plan = learn.learn_rounds(f, c, "block_tree")
        seen = np.logical_or.accumulate(learn.covered_by_round(f, plan), axis=1).sum(0)
        assert (np.diff(seen) >= 0).all() and list(np.diff(np.concatenate([[0], seen]))) == plan.covered
        assert RoundPlan.from_json(plan.to_json()) == plan


def test_greedy_is_no_better_than_the_best_tree():
    rnd = np.random.default_rng(4)
    for _ in range(20):
        n, k, cap = 40, 3, 8
        raw = rnd.integers(0, 3, (n, k))
        values = [[f"v{v}" for v in range(3) if (raw[:, j] == v).sum() > cap] for j in range(k)]
        codes = np.zeros((n, k), np.int32)
        for j in range(k):
            for i, v in enumerate(values[j]):
                codes[raw[:, j] == int(v[1:]), j] = i + 1
        l, r = rnd.integers(0, n, 20), rnd.integers(0, n, 20)
        same = raw[l] == raw[r]
        f = _features(codes, values, same, np.where(same, codes[l], 0))
        best = learn.exhaustive_tree(f, BlockingConfig(cap), k)
        t = learn.learn_block_tree(f, BlockingConfig(cap))
        assert best is None or best.height <= k and all(x.size <= cap or x.hash for x in best.root.walk())
        if best is not None and all(x.parts == 1 for x in t.root.walk()):
            assert learn.recall(f, t) <= learn.recall(f, best) + 1e-9


def test_hash_names_are_stable():
    assert h.prefix("title", 3).name == "title.prefix_3" and h.identity("t").name == "t.identity"
    assert h.interval_hash("n", [Interval(None, 3), Interval(3, None, True)]).name == "n.interval2"
