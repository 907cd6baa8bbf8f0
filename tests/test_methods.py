"""Detectors, the mechanism, budgets, searches and their privacy."""

import math
from collections import Counter
from itertools import product

import numpy as np
import pytest

from ctxrelease.functions import mechanism as mech
from ctxrelease.functions.student import critical_values, upper_quantile
from ctxrelease.operators import detectors as det
from ctxrelease.operators import matching
from ctxrelease.operators.search import Search, starting_context
from ctxrelease.schema import AttributeSpec, ContextSchema

SCHEMA = ContextSchema("t", (AttributeSpec("a", "a", ("0", "1")), AttributeSpec("b", "b", ("0", "1", "2")), AttributeSpec("c", "c", ("0", "1"))), "v", "id")


def make_slice(rows):
    by = {}
    for cell, x in rows:
        by.setdefault(cell, []).append(x)
    cells = sorted(by)
    v = Counter(rows)
    keys = sorted(v, key=lambda k: (k[1], k[0]))
    arr = lambda f, t=np.int64: np.array([f(by[c]) for c in cells], t)
    return det.Slice(np.array(cells, np.int64), arr(len), arr(sum, np.float64), arr(lambda q: sum(x * x for x in q), np.float64), arr(min), arr(max),
                     np.array([k[0] for k in keys], np.int64), np.array([k[1] for k in keys], np.int64), np.array([v[k] for k in keys], np.int64))


def sample(seed=1, n=240):
    rng = np.random.default_rng(seed)
    rows = []
    for _ in range(n):
        cell = SCHEMA.bit(0, int(rng.integers(2))) | SCHEMA.bit(1, int(rng.integers(3))) | SCHEMA.bit(2, int(rng.integers(2)))
        rows.append((cell, int(rng.exponential(200))))
    mine = (SCHEMA.bit(0, 0) | SCHEMA.bit(1, 1) | SCHEMA.bit(2, 0), 2_500)
    return [*rows, mine], mine


def searcher(detector=None, seed=1, start="minimal"):
    rows, (cell, x) = sample(seed)
    s = Search(SCHEMA, make_slice(rows), detector or det.Grubbs(), cell, x)
    s.start = starting_context(s, start, mech.SeededNoise(1))
    return s, rows


def test_quantiles():
    got = upper_quantile(np.array([0.025, 0.05, 0.005]), np.array([1.0, 10.0, 30.0]))
    assert np.allclose(got, [12.7062047364, 1.81246112281, 2.74999565357], rtol=1e-9)
    assert np.allclose(critical_values(np.array([3, 10, 100])), [1.1543, 2.2900, 3.3841], atol=2e-4)
    assert np.isinf(critical_values(np.array([2]))[0])


def test_detectors_against_plain_definitions():
    rows, (cell, x) = sample()
    part = make_slice(rows)
    for ctx in (cell, SCHEMA.full, cell | SCHEMA.bit(1, 0)):
        xs = np.array([v for c, v in rows if c & ctx == c], float)
        flag, score = det.Grubbs().flags(part, np.array([ctx]), x)
        assert math.isclose(score[0], abs(x - xs.mean()) / xs.std(ddof=1), rel_tol=1e-9)
        d = np.abs(xs[:, None] - xs[None, :])
        np.fill_diagonal(d, np.inf)
        k = 5
        kd = np.sort(d, 1)[:, k - 1]
        near = d <= kd[:, None]
        reach = np.maximum(d, kd[None, :])
        lrd = near.sum(1) / np.where(near, reach, 0).sum(1)
        me = int(np.flatnonzero(xs == x)[0])
        want = (np.where(near[me], lrd, 0).sum() / near[me].sum()) / lrd[me]
        assert math.isclose(det.LOF(k).flags(part, np.array([ctx]), x)[1][0], want, rel_tol=1e-9)


def test_histogram_rule_and_ties():
    rows = [(SCHEMA.full & 0b1001010, i % 50) for i in range(900)]
    cell = rows[0][0]
    h = det.Histogram()
    assert not h.flags(make_slice(rows), np.array([cell]), 10)[0][0]
    assert h.flags(make_slice([*rows, (cell, 4_000)]), np.array([cell]), 4_000)[0][0]
    few = [(cell, 1)] * 100 + [(cell, 999)]
    assert not h.flags(make_slice(few), np.array([cell]), 999)[0][0]  # at most 400 rows: never
    same = [(cell, 7)] * 30
    assert det.LOF(5).flags(make_slice(same), np.array([cell]), 7)[1][0] == 1.0
    assert not det.Grubbs().flags(make_slice(same), np.array([cell]), 7)[0][0]
    assert det.iterative_outliers(np.array([1, 2, 3, 4, 1000]), np.array([5, 9, 9, 5, 1])) == {1000}


def test_budget():
    assert mech.allocate("direct", 0.2, 0) == mech.allocate("uniform", 0.2, 50) == mech.allocate("walk", 0.2, 50) == 0.1
    for n in (25, 50, 100, 200):
        assert math.isclose(mech.allocate("bfs", 0.2, n), 0.2 / (2 * n + 2)) and math.isclose(mech.allocate("dfs", 0.2, n), 0.2 / (2 * n + 2))
    assert math.isclose(mech.allocate("dfs", 0.2, 50, "last"), 0.002) and math.isclose(mech.allocate("bfs", 0.2, 50, inclusive=True), 0.2 / 104)
    assert mech.weight(0.4, 2, "half") == 0.1 and mech.group_epsilon(0.2, 5) == 1.0
    assert mech.utility_tail_bound(100, 8, 0.1, 1) < 100


def test_draws_follow_the_exponential_law():
    masks, us, factor = [1, 2, 4], [0.0, 1.0, 3.0], 0.7
    noise = mech.SeededNoise(3)
    n = 6000
    got = Counter(masks[mech.draw_local(masks, us, factor, noise, k)] for k in range(n))
    e = np.exp(factor * np.array(us))
    want = n * e / e.sum()
    assert sum((got[m] - w) ** 2 / w for m, w in zip(masks, want)) < 13.8  # 0.999 point, 2 degrees
    assert mech.draw_local([5, 6], [1e12, 0.0], 1.0, noise, 0) == 0


def test_released_contexts_are_valid():
    s, rows = searcher()
    valid = s.valid()
    for method, trial in product(("direct", "uniform", "walk", "dfs", "bfs"), range(25)):
        o = s.run(method, 0.5, 4, mech.SeededNoise(9), trial)
        assert o.ctx in valid and o.ctx & s.cell == s.cell and SCHEMA.wellformed(o.ctx)
        assert o.utility == sum(c & o.ctx == c for c, _ in rows)
    t = SCHEMA.t
    assert s.direct(0.2, mech.SeededNoise(0)).verified == 2 ** (t - SCHEMA.m)
    for method in ("walk", "dfs", "bfs"):
        o = s.run(method, 0.2, 5, mech.SeededNoise(0), 1)
        assert o.verified <= 5 * t and o.draws <= 6 and len(o.path) <= 5
        assert len(s.run(method, 0.2, 5, mech.SeededNoise(0), 1, inclusive=True).path) <= 6


def test_greedy_and_overlap():
    s, rows = searcher()
    assert s.greedy(12).utility == max(s.valid().values())
    o, _ = searcher()
    o.overlap, o.start = True, o.cell | SCHEMA.bit(1, 0)
    o.memo.clear()
    for c, u in o.valid().items():
        assert u == sum(r & c & o.start == r for r, _ in rows)


def test_no_valid_context_charges_nothing():
    rows = [(73, v) for v in range(50)]
    s = Search(SCHEMA, make_slice(rows), det.Grubbs(), 73, 25)
    with pytest.raises(mech.NoValidContext):
        starting_context(s)
    with pytest.raises(mech.NoValidContext):
        s.direct(0.2, mech.SeededNoise(0))
    with pytest.raises(mech.NoValidContext):
        s.bfs(0.2, 3, mech.SeededNoise(0))


def exact_law(search, method, n, eps):
    """Probability of each output, summed over all paths."""
    e1 = mech.allocate(method, eps, n)
    util = search.valid()
    out = Counter()

    def soft(cands):
        w = np.exp(e1 * (np.array([util[c] for c in cands]) - max(util[c] for c in cands)))
        return w / w.sum()

    def finish(path, p):
        for c, q in zip(path, soft(path)):
            out[c] += p * q

    def step(frontier, path, p):
        if len(path) == n or not frontier:
            return finish(path, p)
        if method == "bfs":
            for c, q in zip(frontier, soft(frontier)):
                new = [k for b in search.free if (k := c ^ b) in util and k not in frontier and k not in path]
                step([f for f in frontier if f != c] + [k for k in new if k != c], [*path, c], p * q)
        elif method == "dfs":
            stack = list(frontier)
            while stack:
                kids = [k for b in search.free if (k := stack[-1] ^ b) in util and k not in path]
                if kids:
                    for c, q in zip(kids, soft(kids)):
                        step([*stack, c], [*path, c], p * q)
                    return None
                stack.pop()
            return finish(path, p)
        else:
            kids = [k for b in search.free if (k := path[-1] ^ b) in util]
            if not kids:
                return finish(path, p)
            for c in kids:
                step(frontier, [*path, c], p / len(kids))
        return None

    step([search.start], [] if method == "bfs" else [search.start], 1.0)
    return out


@pytest.mark.parametrize("method", ["bfs", "dfs", "walk"])
def test_exact_output_law_is_private(method):
    """On neighbours with equal valid sets no output's probability moves by more than the budget allows."""
    s, rows = searcher()
    eps, n, tested = 0.4, 3, 0
    for drop in range(0, 40, 5):
        other = Search(SCHEMA, make_slice(rows[:drop] + rows[drop + 1 :]), det.Grubbs(), s.cell, s.x, s.start)
        if other.valid().keys() != s.valid().keys():
            continue
        tested += 1
        p, q = exact_law(s, method, n, eps), exact_law(other, method, n, eps)
        assert p.keys() == q.keys() and math.isclose(sum(p.values()), 1, rel_tol=1e-9)
        assert all(max(p[c] / q[c], q[c] / p[c]) <= math.exp(eps) + 1e-9 for c in p)
    assert tested
    if method == "bfs":  # the law of the implementation is the exact one
        draws = Counter(s.run(method, eps, n, mech.SeededNoise(4), k).ctx for k in range(3000))
        p = exact_law(s, method, n, eps)
        assert sum((draws[c] - 3000 * v) ** 2 / (3000 * v) for c, v in p.items()) < 3 * len(p) + 20


def test_removed_records_change_moments_exactly():
    rows, _ = sample()
    gone = rows[3:9]
    edges = {c: (np.sort([v for k, v in rows if k == c])[:8], np.sort([v for k, v in rows if k == c])[::-1][:8]) for c in {k for k, _ in rows}}
    a = matching.remove_records(make_slice(rows), gone, edges)
    b = make_slice([r for k, r in enumerate(rows) if not 3 <= k < 9])
    for f in ("cell", "n", "s", "ss", "lo", "hi", "v_cell", "v_x", "v_cnt"):
        assert np.array_equal(getattr(a, f), getattr(b, f)), f


def test_plug_in_utility_and_detector():
    rows, (cell, x) = sample()
    s = Search(SCHEMA, make_slice(rows), det.ZScore(2.0), cell, x, utility=lambda st: np.sqrt(st["n"]), sensitivity=0.5)
    s.start = starting_context(s)
    o = s.bfs(1.0, 4, mech.SeededNoise(2))
    assert o.utility == math.sqrt(sum(c & o.ctx == c for c, _ in rows))
    assert s.direct(1e6, mech.SeededNoise(2)).utility == max(s.valid().values())
