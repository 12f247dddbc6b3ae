import itertools

import numpy as np
import pytest

from hetpart.operators import costs
from hetpart.operators.growth import Block
from hetpart.operators.machines import THREE, Fleet, Machine
from hetpart.operators.refine import State

#: The running example: edges ab, bc, cf, de, ef with a..f = 0..5.
EDGES = [(0, 1), (1, 2), (2, 5), (3, 4), (4, 5)]
FIRST, SECOND = [0, 0, 2, 1, 1], [0, 1, 1, 2, 2]


def frame(spark, machines, edges=EDGES):
    return spark.createDataFrame([(a, b, m) for (a, b), m in zip(edges, machines)], "src long, dst long, machine int")


def test_running_example(spark):
    rows = costs.costs(frame(spark, FIRST), THREE).orderBy("machine").collect()
    assert [r["t_cal"] for r in rows] == [2, 4, 1]
    assert [r["t_com"] for r in rows] == [2, 3, 5]
    assert [r["mem_used"] for r in rows] == [7, 7, 4]
    assert costs.total(frame(spark, FIRST), THREE).first()[0] == 7
    assert costs.replication_factor(frame(spark, FIRST)).first()[0] == pytest.approx(8 / 6)
    assert costs.total(frame(spark, SECOND), THREE).first()[0] == 10
    assert [r["fits"] for r in costs.memory(frame(spark, SECOND), THREE).orderBy("machine").collect()] == [True, True, False]


def test_brute_force_optimum_is_seven():
    block = Block(np.array([a for a, _ in EDGES]), np.array([b for _, b in EDGES]))
    found = []
    for m in itertools.product(range(3), repeat=5):
        s = State(block, THREE, np.array(m, np.int32), np.zeros(5, np.int64))
        if (s.used <= s.mem).all():
            found.append(s.goal())
    assert len(found) == 6 and min(found) == 7 and found.count(7) == 4


def test_incremental_costs_equal_recomputed():
    rng = np.random.default_rng(3)
    pairs = np.unique(rng.integers(0, 40, (300, 2)), axis=0)
    pairs = pairs[pairs[:, 0] < pairs[:, 1]]
    block = Block(pairs[:, 0], pairs[:, 1])
    fleet = Fleet(tuple(Machine(1e6, 1 + i, 2 + i, 3 + i) for i in range(5)))
    s = State(block, fleet, rng.integers(0, 5, len(pairs)).astype(np.int32), np.arange(len(pairs)))
    for e in rng.integers(0, len(pairs), 200).tolist():
        s.remove(e)
        s.add(e, int(rng.integers(0, 5)))
    com, nv, ne = s.t_com.copy(), s.n_vertices.copy(), s.n_edges.copy()
    s.recompute()
    assert np.allclose(com, s.t_com) and np.allclose(nv, s.n_vertices) and np.allclose(ne, s.n_edges)


def test_machines_without_edges_and_empty_graph(spark):
    c = costs.costs(frame(spark, [0] * 5), THREE).orderBy("machine").collect()
    assert [r["n_edges"] for r in c] == [5, 0, 0] and [r["t"] for r in c][1:] == [0, 0]
    empty = frame(spark, [], [])
    assert [r["t"] for r in costs.costs(empty, THREE).collect()] == [0, 0, 0]


def test_identity_and_border(spark):
    unit = Fleet((Machine(1e9, 1, 1, 1),) * 3)
    assert costs.homogeneous_identity(frame(spark, FIRST), unit).first()[0] == 2
    assert tuple(costs.border_count(frame(spark, FIRST)).first()) == (2, 6)
    assert {tuple(r) for r in costs.overlap(frame(spark, FIRST), 2).collect()} == {(0, 1), (1, 1)}


def test_no_pair_join_in_the_communication_plan(spark, sf):
    from hetpart.operators.partitioners import hash_placement
    from hetpart.sources import graphs

    plan = costs.t_com(hash_placement(graphs.order_part(spark, sf), 30), Fleet((Machine(1e9, 1, 1, 1),) * 30))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in plan
