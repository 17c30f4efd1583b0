import math
import random
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hetjoin.operators import baselines, execute
from hetjoin.plans import bounds, lp, pack, sides
from hetjoin.plans.cost import Linear, Power, Tabulated, check_well_behaved
from hetjoin.plans.query import Atom, FullCQ, parse_cq
from hetjoin.workloads import CARTESIAN, EXAMPLE, JOIN, TRIANGLE, profiles

W = EXAMPLE
ONE = {"R": 1000, "S": 1000, "T": 1000}


def test_parse_refuses_what_is_no_full_query():
    with pytest.raises(ValueError):
        parse_cq("q(x) :- R(x, y)")
    with pytest.raises(ValueError):
        parse_cq("q(x, y) :- R(x, y), R(y, x)")
    assert parse_cq("q(x, y) :- R(x, y), R(y, x)", allow_copies=True).atoms[1].name == "R__2"


@pytest.mark.parametrize("q, total", [(CARTESIAN, 2), (JOIN, 1), (TRIANGLE, Fraction(3, 2)), (parse_cq("q(n,r,c,o) :- A(n,r), B(c,n), C(o,c)"), 2), (parse_cq("q(a,b,c,d) :- A(a,b), B(b,c), C(c,d), D(d,a)"), 2)])
def test_cover_and_packing_totals(q, total):
    v, u = lp.min_vertex_cover(q), lp.max_edge_packing(q)
    assert lp.is_vertex_cover(q, v) and lp.is_edge_packing(q, u)
    assert sum(v.values()) == sum(u.values()) == total and lp.duality_gap(q) == 0
    assert max(map(sum, lp.packing_vertices(q))) == total


@settings(max_examples=40, deadline=None)
@given(st.lists(st.sets(st.sampled_from("abcde"), min_size=1, max_size=3), min_size=1, max_size=5))
def test_duality_on_random_queries(edges):
    q = FullCQ(tuple(Atom(f"R{i}", tuple(sorted(e))) for i, e in enumerate(edges)))
    assert lp.duality_gap(q) == 0


def test_worked_example():
    assert bounds.norm(W, 2) == pytest.approx(8)
    made = sides.uniform(CARTESIAN, W)
    assert [round(s["x"] * 8, 9) for s in made[:4]] == [4, 4, 3, 2]
    assert sum(s["x"] * s["y"] for s in made) == pytest.approx(1)
    p = pack.pack(CARTESIAN, made)
    assert pack.covers(p) and len(p.used()) == 10
    assert max(p.inflation(CARTESIAN).values()) <= 2


@pytest.mark.parametrize("name", profiles())
@pytest.mark.parametrize("q", [CARTESIAN, JOIN, TRIANGLE])
def test_packing_covers_once_within_the_constant(name, q):
    w = profiles()[name]
    made = sides.uniform(q, w)
    for rounding in ("up", "search"):
        m = {a.name: 1000 for a in q.atoms}
        p = pack.pack(q, made, rounding=rounding, m=m, w=w)
        assert pack.covers(p)
        for (c, a), factor in p.inflation(q).items():
            assert rounding == "search" or factor <= 2 ** (len(q.vars) + 1 + len(q.atom(a).vars))
        r = pack.refine(p, q, m, w)
        assert pack.covers(r) and r.planned_load(q, m, w) <= p.planned_load(q, m, w) + 1e-9


def test_search_is_never_worse_and_intervals_are_exact():
    for w in profiles().values():
        for q in (CARTESIAN, TRIANGLE):
            m, made = {a.name: 1000 for a in q.atoms}, sides.uniform(q, w)
            assert pack.pack(q, made, rounding="search", m=m, w=w).planned_load(q, m, w) <= pack.pack(q, made).planned_load(q, m, w) + 1e-9
        p = pack.intervals(JOIN, sides.uniform(JOIN, w))
        assert pack.covers(p) and p.planned_load(JOIN, {"R": 1000, "S": 1000}, w) == pytest.approx(2 * 1000 / sum(w), rel=1e-2)


def test_inner_boxes_cover_once_and_part_the_load():
    for q in (CARTESIAN, JOIN, TRIANGLE, parse_cq("q(n,r,c,o) :- A(n,r), B(c,n), C(o,c)")):
        m = {a.name: 1000 * (i + 1) for i, a in enumerate(q.atoms)}
        p = pack.pack(q, sides.uniform(q, W))
        for parts in (2, 3, 4, 12):
            inner = pack.subdivide(p, q, m, parts)
            assert pack.covers(inner) and {c // parts for c in inner.used()} == set(p.used())
            assert inner.planned_load(q, m, [1.0] * inner.machines) < p.planned_load(q, m, [1.0] * p.machines)
    by_free = pack.subdivide(pack.pack(JOIN, sides.uniform(JOIN, W)), JOIN, ONE, 4, by=("x", "y"))
    assert pack.covers(by_free) and all(len({tuple(by_free.boxes[c * 4 + i]["z"]) for i in range(4)}) == 1 for c in {c // 4 for c in by_free.used()})


@pytest.mark.parametrize("costs", [[Power(w, 2.0) for w in W], [Power(w, 0.5) for w in W], [Tabulated(((500 * w, 100.0), (900 * w, 5000.0))) for w in W]])
def test_plans_go_by_the_real_cost(costs):
    made = execute.plan(TRIANGLE, ONE, costs)
    load = max(costs[c](sum(1000 * made.packing.share(c, a.vars) for a in TRIANGLE.atoms)) for c in made.packing.used())
    assert made.packing.planned_load(TRIANGLE, ONE, costs) == pytest.approx(load)
    assert pack.covers(made.packing) and made.bound <= load <= min(g(3000) for g in costs)
    by_weight = pack.refine(pack.pack(TRIANGLE, sides.uniform(TRIANGLE, W), rounding="search", m=ONE, w=W), TRIANGLE, ONE, W)
    assert load <= by_weight.planned_load(TRIANGLE, ONE, costs) * 1.5


def test_bounds_of_unequal_sizes_stay_below_the_plan():
    q = parse_cq("q(r, n, c, o) :- region(r), nation(n, r), customer(c, n), orders(o, c)")
    sizes = {"region": 5, "nation": 25, "customer": 15_000, "orders": 150_000}
    for mode in ("padded", "dual", "general", "uniform"):
        made = execute.plan(q, sizes, [Linear(w) for w in W], mode)
        assert made.bound <= made.packing.planned_load(q, sizes, W) * (1 + 1e-9), mode
    assert execute.plan(q, sizes, [Linear(w) for w in W], "padded").bound == pytest.approx(5357.14, abs=0.1)
    assert "bound" in execute.plan(q, sizes, [Power(w, 2.0) for w in W]).notes


def test_grids_and_shares():
    m = {"R": 100, "S": 100, "T": 100}
    assert baselines.shares(TRIANGLE, m, 27, "lp") == {"x": 3, "y": 3, "z": 3}
    assert baselines.shares(TRIANGLE, m, 27) == {"x": 3, "y": 3, "z": 3}
    w = [float(1 + i % 5) for i in range(100)]
    grid, load = baselines.fastest_grid(TRIANGLE, m, w)
    assert load == min(baselines.grid_load(TRIANGLE, m, baselines.shares(TRIANGLE, m, q), w) for q in range(1, 101)) == baselines.grid_load(TRIANGLE, m, grid, w)


def test_explicit_sides_and_shrinking():
    made = sides.explicit([{"x": 0.75, "y": 1.0}, {"x": 0.75, "y": 1.0}])
    for shrink in (False, True):
        p = pack.pack(CARTESIAN, made, shrink=shrink)
        assert pack.covers(p)


def test_odd_domains_are_covered():
    p = pack.pack(CARTESIAN, sides.uniform(CARTESIAN, W), domain={"x": 1000, "y": 77})
    assert pack.covers(p)


def test_bounds():
    assert bounds.tightness(TRIANGLE, 1000, 1 << 16, W) == pytest.approx(16)
    for a in (0.5, 1.0, 2.0, 3.0):
        got = bounds.lower_general(10**9, [Power(w, a) for w in W], 2)
        assert got == pytest.approx(bounds.lower_power(10**9, W, a, 2), rel=1e-5)
    assert bounds.lower_power(1500, W, 1, 1.5) == pytest.approx(bounds.lower_uniform(1500, W, 1.5))
    assert bounds.lower_mixed(TRIANGLE, {"R": 15000, "S": 3000, "T": 3000}, W)[0] == pytest.approx(545.65, abs=0.01)
    assert bounds.lower_mixed(TRIANGLE, ONE, W)[0] == pytest.approx(bounds.lower_uniform(1000, W, 1.5), rel=1e-6)
    r = random.Random(3)
    for _ in range(20):
        w, m = [r.randint(1, 30) for _ in range(r.randint(1, 20))], {k: r.randint(1, 9999) for k in "RST"}
        low, high = bounds.mixed_bracket(m, w)
        exact, _ = bounds.lower_mixed(TRIANGLE, m, w)
        rough, steps = bounds.lower_mixed(TRIANGLE, m, w, "double")
        assert low * (1 - 1e-9) <= exact <= high * (1 + 1e-9) and exact <= rough * (1 + 1e-9) <= 2 * exact * (1 + 1e-6)
        assert steps <= math.ceil(math.log2(max(len(w), 2)))


def test_unequal_sides_meet_their_bounds():
    r = random.Random(4)
    for _ in range(200):
        w, m = [float(r.randint(1, 40)) for _ in range(8)], {k: r.randint(10, 9999) for k in "RST"}
        load = bounds.lower_mixed(TRIANGLE, m, w)[0]
        made = sides.triangle(TRIANGLE, m, w, load)
        assert sides.chain(made, w) and sum(math.prod(s.values()) for s in made) == pytest.approx(1, rel=1e-4)
        for s, c in zip(made, w):
            for a in TRIANGLE.atoms:
                assert math.prod(s[x] for x in a.vars) <= load * c / m[a.name] * (1 + 1e-6)


def test_costs():
    t = Tabulated(((10.0, 5.0), (20.0, 30.0)))
    assert t(10) == 5 and t(15) == 17.5 and t.inverse(17.5) == 15
    assert check_well_behaved(Power(2, 2), 2, range(1, 50))[0] and not check_well_behaved(Power(2, 3), 2, range(1, 50))[0]
    assert Linear(3).inverse(2.0) == 6 and Power(2, 2).inverse(8) == 4


def test_measures_of_knowledge():
    assert bounds.expected_output(TRIANGLE, {k: 100 for k in "RST"}, 100) == pytest.approx(1)
    assert bounds.expected_output(TRIANGLE, ONE, 10, theta=0.5) == 125
    assert bounds.known_fraction({"R": 0.25, "S": 1.0}, {"R": 0.5, "S": 0.5}) == 0.5
    assert bounds.tail(10**6, [1.0], 1, 0.5) < 1e-9


def test_planner_is_fast_for_many_machines():
    import time

    w = [float(1 + i % 7) for i in range(10_000)]
    start = time.perf_counter()
    p = pack.pack(TRIANGLE, sides.uniform(TRIANGLE, w))
    assert time.perf_counter() - start < 10 and len(p.used()) > 1000
