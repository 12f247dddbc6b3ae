"""Growth, repair and quotas as DataFrame rounds: memory is kept or the call fails."""

import pytest
from pyspark.sql import functions as F

from hetpart.operators import costs, extensions, machines, rounds
from hetpart.operators.capacity import Infeasible
from hetpart.operators.machines import Fleet, Machine
from hetpart.operators.partitioners import hash_placement, kernel, method, partition
from hetpart.sources import graphs


@pytest.fixture(scope="module")
def mesh(spark):
    return graphs.grid(spark, 12, 10)


def test_left_edges_go_where_memory_is(spark, mesh):
    fleet = Fleet((Machine(400, 5, 10, 10), Machine(250, 5, 10, 10), Machine(400, 5, 10, 10)))
    state = rounds.Filling(fleet, spark)
    rounds.place_left(mesh, state, 1)
    got = costs.invariants(state.placed(), mesh, fleet).first()
    assert got["n_over_memory"] == 0 and got["n_assigned"] == got["n_edges"] == 218 and got["n_duplicate"] == 0


def test_short_memory_is_an_error(spark, mesh):
    fleet = Fleet((Machine(60, 5, 10, 10), Machine(60, 5, 10, 10)))
    with pytest.raises(Infeasible):
        rounds.place_left(mesh, rounds.Filling(fleet, spark), 1)
    with pytest.raises(ValueError, match="one task takes"):
        partition(mesh, fleet, mode="sequential") if False else kernel(mesh, method("full", fleet), limit=10)


def test_quota_holds_and_too_many_vertices_are_an_error(spark, mesh):
    a = hash_placement(mesh, 4)
    h = extensions.to_vertex_partition(a, 31, 4)
    assert max(r["count"] for r in h.groupBy("machine").count().collect()) <= 31
    assert h.count() == h.select("v").distinct().count() == 120
    free = extensions.to_vertex_partition(a, 120, 4).exceptAll(extensions.to_vertex_partition(a))
    assert free.count() == 0  # without a shortage all get their first choice
    with pytest.raises(Infeasible):
        extensions.to_vertex_partition(a, 29, 4)


def test_newest_equals_a_plain_sort(spark, mesh):
    a = hash_placement(mesh, 3).withColumn("seq", (F.col("src") * 7 + F.col("dst")) % 50)
    got = {tuple(r) for r in rounds.newest(a, spark.createDataFrame([(0,), (2,)], "machine int"), 0.1, bands=5).collect()}
    want = set()
    for m in (0, 2):
        own = sorted((tuple(r) for r in a.where(F.col("machine") == m).select("src", "dst", "machine", "seq").collect()), key=lambda r: (-r[3], -r[0], -r[1]))
        want |= set(own[: -(-len(own) // 10)])
    assert got == want


def test_repair_moves_only_into_free_memory(spark, mesh):
    fleet = Fleet((Machine(300, 5, 10, 10), Machine(260, 5, 10, 10), Machine(300, 1, 2, 1)))
    a = hash_placement(mesh, 3).withColumn("seq", F.lit(0).cast("long"))
    over = costs.memory(a, fleet).where("NOT fits").count()
    lost = a.where("machine = 0 AND (src + dst) % 3 = 0")
    out = rounds.repair(lost, a.join(lost, ["src", "dst"], "left_anti").select("src", "dst", "machine", "seq"), fleet, 10)
    assert out.select("src", "dst").exceptAll(mesh).count() == 0 and out.count() == mesh.count()
    assert costs.memory(out, fleet).where("NOT fits").count() <= over


def test_no_form_changes_by_itself(mesh):
    with pytest.raises(ValueError):
        partition(mesh, machines.small(218).with_memory(9), "sorted_balance", mode="parallel")
