import math
import random

import numpy as np

from chronoweave.index.bits import BitTrie, RankBits, UpdateMatrix, VersionedBitTrie
from chronoweave.model.query import OrderClause, TimeVar, parse
from chronoweave.operators.leapfrog import intersect, intersect_time
from chronoweave.plans import bounds
from chronoweave.plans import order as plan
from chronoweave.workloads.shapes import arcs, shape_query


def text(bits):
    return "".join(map(str, bits.bits()))


def test_worked_update_matrix():
    keys, signs = [2, 3, 6, 2, 4, 3], [1, 1, 1, -1, 1, -1]
    m = UpdateMatrix.build(keys, signs, 3)
    assert [text(b) for b in m.B] == ["001010", "111110", "010100"]
    assert [text(e) for e in m.E] == ["111111", "111011", "111011", "101011"]
    left, at = m.child(0, (0, 6), 0, 5)
    assert left == (0, 4) and at == 3 and not m.alive(1, left, at)
    assert m.child(1, left, 0, 3)[0] == (0, 0)
    assert m.bits == 6 * 2 * 3
    assert [m.members(v) for v in range(1, 7)] == [[2], [2, 3], [2, 3, 6], [3, 6], [3, 4, 6], [4, 6]]


def test_tries_of_the_worked_example():
    t = BitTrie([2, 3, 6], 3)
    assert [t.seek(x) for x in range(8)] == [2, 2, 2, 3, 6, 6, 6, None]
    v = VersionedBitTrie(3)
    v.apply([2, 3, 6])
    v.apply([4])
    v.apply((), [3])
    assert [v.members(i) for i in range(3)] == [[2, 3, 6], [2, 3, 4, 6], [2, 4, 6]]
    assert v.roots[2].right is v.roots[1].right and v.roots[1].left is v.roots[0].left


def test_joined_keys_and_levels():
    pairs = [(2, 5), (3, 4), (3, 5), (6, 4), (6, 6), (6, 7)]
    keys = [(a << 3) | b for a, b in pairs] + [(2 << 3) | 5, (6 << 3) | 1]
    m = UpdateMatrix.build(keys, [1] * 6 + [-1, 1], 6)
    first = []
    x = 0
    while (got := m.seek(x, 8, levels=3)) is not None:
        first.append(got)
        x = got + 1
    assert first == [3, 6]


def test_matrix_against_sets():
    rng = random.Random(2)
    for _ in range(30):
        live, keys, signs, states = set(), [], [], [set()]
        for _ in range(60):
            k = rng.randrange(32)
            keys.append(k)
            signs.append(-1 if k in live else 1)
            live ^= {k}
            states.append(set(live))
        m, v = UpdateMatrix.build(keys, signs, 5), VersionedBitTrie(5)
        for i, (k, s) in enumerate(zip(keys, signs, strict=True), 1):
            v.apply([k] if s > 0 else [], [k] if s < 0 else [])
            for x in range(0, 33, 5):
                want = min((y for y in states[i] if y >= x), default=None)
                assert m.seek(x, i) == want == v.seek(i - 1, x) == BitTrie(states[i], 5).seek(x)
        for a in range(1, 60, 7):
            for b in range(a, 61, 9):
                assert m.window(a, b, "any") == sorted(set().union(*states[a : b + 1]))
                assert m.window(a, b, "all") == sorted(set.intersection(*map(set, states[a : b + 1])))


def test_rank():
    bits = (np.random.default_rng(1).random(3000) < 0.4).astype(np.uint8)
    r = RankBits(bits)
    assert all(r.rank(i) == bits[:i].sum() for i in range(0, 3001, 37))


def test_intersections():
    rng = random.Random(3)
    for _ in range(100):
        lists = [sorted(rng.sample(range(60), rng.randint(0, 40))) for _ in range(rng.randint(1, 4))]
        assert intersect([np.array(x, np.int64) for x in lists]) == sorted(set.intersection(*map(set, lists)))
        ranges = []
        for _ in range(rng.randint(1, 3)):
            cuts = sorted(rng.sample(range(60), 8))
            ranges.append([(cuts[i], cuts[i + 1]) for i in range(0, 8, 2)])
        lo, hi = rng.randrange(20), rng.randrange(30, 60)
        ticks = set(range(lo, hi)).intersection(*[{t for a, b in r for t in range(a, b)} for r in ranges])
        got = intersect_time(ranges, lo, hi)
        assert {t for a, b in got for t in range(a, b)} == ticks
        assert [a for a, _ in intersect_time(ranges, lo, hi, "tick")] == sorted(ticks)


def test_bounds_in_closed_form():
    n = 1000
    for shape, power in (("circle3", 1.5), ("clique4", 2), ("star4", 4), ("circle5", 2.5)):
        q = shape_query(shape, ["p"] * len(arcs(shape)))
        assert math.isclose(bounds.agm(q, [n] * len(q.patterns), times=False), n**power, rel_tol=1e-6)


def test_orders_and_clauses():
    q = parse("?x a ?y @t ; ?y b ?z @t ; ?z c ?w @t")
    stats = [plan.PatternStats(1000, {"x": 500, "y": 10}, 3, 100), plan.PatternStats(50, {"y": 10, "z": 40}, 3, 100), plan.PatternStats(900, {"z": 40, "w": 800}, 3, 100)]
    assert plan.greedy(q, stats, "JF")[-1] == "t" and plan.greedy(q, stats, "TF")[0] == "t"
    assert plan.greedy(q, stats, "JF")[:2] == ["y", "z"]
    assert plan.pick_permutation(q.patterns[0], ["y", "t", "x"]) == "pots"
    two = plan.normalise(parse("?x a ?y @t1 ; ?x b ?z @t2 ; @t1 <= @t2 ; @t2 <= @t1"))
    assert two.times == ["t1"] and not two.clauses
    assert plan.normalise(parse("?x a ?y @t1 ; ?x b ?z @t2 ; @t1 < @t2 ; @t2 <= @t1")).unsatisfiable
    assert parse("?x a ?y @t ; @t <= @u + 3").clauses == (OrderClause(TimeVar("t"), TimeVar("u"), 3),)
