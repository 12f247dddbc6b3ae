import itertools

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hetpart.operators import capacity
from hetpart.operators.machines import Fleet, Machine


def test_two_machines_share_by_speed():
    fleet = Fleet((Machine(1e9, 0, 1, 1), Machine(1e9, 0, 2, 1)))
    assert capacity.plan(fleet, 30, 10) == [20, 10]
    cost = [1, 2]
    assert capacity.whole(cost, [5, 100], capacity.rounds(cost, [5, 100], 30), 30) == [5, 25]
    with pytest.raises(capacity.Infeasible):
        capacity.rounds(cost, [5, 5], 30)


machines = st.lists(st.tuples(st.integers(1, 9), st.integers(1, 40)), min_size=1, max_size=5)


@settings(max_examples=200, deadline=None)
@given(machines, st.integers(1, 60))
def test_greedy_remainder_is_optimal(ms, edges):
    cost, cap = [c for c, _ in ms], [k for _, k in ms]
    if sum(cap) < edges:
        return
    real = capacity.rounds(cost, cap, edges)
    assert abs(sum(real) - edges) < 1e-6
    got = capacity.whole(cost, cap, real, edges)
    assert sum(got) == edges and all(0 <= x <= k for x, k in zip(got, cap))
    level = max(c * x for c, x in zip(cost, got))
    assert level == pytest.approx(capacity.exact_level(cost, cap, edges))
    assert level <= max(c * x for c, x in zip(cost, real)) + max(cost)


@settings(max_examples=40, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 5), st.integers(1, 12)), min_size=2, max_size=3), st.integers(1, 14))
def test_branch_and_bound_agrees(ms, edges):
    cost, cap = [c for c, _ in ms], [k for _, k in ms]
    if sum(cap) < edges:
        return
    best = capacity.branch_and_bound(cost, cap, edges)
    assert max(c * x for c, x in zip(cost, best)) == pytest.approx(capacity.exact_level(cost, cap, edges))
    brute = min(max(c * x for c, x in zip(cost, p)) for p in capacity.all_plans(len(cost), edges) if all(x <= k for x, k in zip(p, cap)))
    assert max(c * x for c, x in zip(cost, best)) == brute


def test_relational_waterfill_equals_rounds(spark):
    for edges in (10, 40, 75):
        cost, cap = [1.0, 2.0, 4.0, 1.5], [20.0, 30.0, 40.0, 5.0]
        t = spark.createDataFrame([(i, c, k) for i, (c, k) in enumerate(zip(cost, cap))], "machine int, cost double, cap double")
        got = [r["amount"] for r in capacity.waterfill(t, edges).orderBy("machine").collect()]
        assert got == pytest.approx(capacity.rounds(cost, cap, edges))


def test_remainder_modes():
    cost, cap = [3, 3, 3], [10, 10, 10]
    real = capacity.rounds(cost, cap, 10)
    assert capacity.whole(cost, cap, real, 10, "last") == [3, 3, 4]
    assert capacity.whole(cost, cap, real, 10, "none") == [3, 3, 3]
    assert list(itertools.islice(capacity.all_plans(2, 2), 3)) == [(0, 2), (1, 1), (2, 0)]


@pytest.mark.parametrize("name, v, e, fleet, level", [("co", 3_072_441, 117_185_083, "large", 12.73), ("lj", 4_847_570, 33_099_465, "small", 13.40), ("po", 1_632_803, 30_622_564, "small", 11.81), ("cp", 3_774_768, 16_518_947, "small", 6.96), ("rn", 1_965_206, 2_766_607, "small", 1.43), ("tw", 41_652_230, 1_202_513_046, "large", 131.18)])
def test_levels_of_the_published_graphs(name, v, e, fleet, level):
    """Balanced compute time on the published sizes and unscaled fleets, in millions."""
    from hetpart.operators import machines

    f = machines.small(33_099_465) if fleet == "small" else machines.large(117_185_083)
    cost, cap = capacity.terms(f, e, v)
    got = max(c * x for c, x in zip(cost, capacity.rounds(cost, cap, e)))
    assert got / 1e6 == pytest.approx(level, abs=0.006)
