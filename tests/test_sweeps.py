"""Sweeps beyond one task."""

import tracemalloc

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from hetpart.operators import machines, streams
from hetpart.operators.growth import Block
from hetpart.plans import experiments as X
from hetpart.sources import graphs


def test_sweep_in_blocks_places_every_edge(spark, sf, monkeypatch):
    edges = graphs.order_part(spark, sf)
    n = edges.count()
    monkeypatch.setattr(X, "SWEEP_EDGES", n // 2)
    monkeypatch.setattr(X, "BLOCK_EDGES", n // 3)
    runs = [("full", "none", 0.0), ("sorted_balance", "none", 0.0), ("full", "gamma", 0.5)]
    rows = X.sweep(edges, "g4", runs).collect()
    assert [(r["method"], r["parameter"]) for r in rows] == [(m, p) for m, p, _ in runs]
    assert all(r["n_edges"] == n and r["agrees"] and r["blocks"] > 1 and r["over_memory"] == 0 and r["rf"] >= 1 for r in rows)


@pytest.mark.parametrize("p", [3, 62, 90])
def test_totals_are_those_of_one_task(spark, p):
    e = graphs.rmat(spark, 7).toPandas()
    rng = np.random.default_rng(p)
    block = Block(e.src.to_numpy(), e.dst.to_numpy())
    machine = rng.integers(0, p, len(e)).astype(np.int32)
    fleet = machines.share_super(len(e), p)
    df = spark.createDataFrame([(int(a), int(b), int(m)) for a, b, m in zip(block.src, block.dst, machine, strict=True)], "src long, dst long, machine int").repartition(3)
    got = X._measured(X._totals(X._held(df, p), fleet), fleet)
    want = X.measure(block, fleet, machine)
    assert got.pop("agrees") and X.agrees(block, fleet, machine, want["tc"])
    assert got == pytest.approx(want)


def test_edges_without_room_in_their_block_are_placed(spark, monkeypatch):
    edges = graphs.rmat(spark, 8)
    n = edges.count()
    monkeypatch.setattr(X, "SWEEP_EDGES", 1)
    monkeypatch.setattr(X, "BLOCK_EDGES", n // 4)
    real, seen = X.place_left, []
    monkeypatch.setattr(X, "place_left", lambda *a: seen.append(1) or real(*a))
    monkeypatch.setattr(X, "method", lambda *a: lambda b: (np.where(np.arange(len(b.src)) % 5 == 0, -1, np.arange(len(b.src)) % 4).astype(np.int32), None))
    r = X.sweep(edges, "rmat", [("full", "none", 0.0)], lambda k, p, v: machines.homogeneous(k, 4).with_memory(20)).first()
    assert seen and r["agrees"] and r["n_edges"] == n


def test_one_large_cluster_is_cut_into_pieces(spark, monkeypatch):
    monkeypatch.setattr(X, "BLOCK_EDGES", 50)
    part, blocks = X.blocked(graphs.star(spark, 400), 399)
    assert part.count() == 399 and blocks >= 7 and part.groupBy("block").count().agg({"count": "max"}).first()[0] < 120


def test_mesh_of_turns(spark, sf):
    e = graphs.turn_mesh(spark, sf)
    d = graphs.degrees(e).agg({"degree": "max"}).first()[0]
    assert e.count() == e.distinct().count() > graphs.turn_chain(spark, sf).count() and 3 <= d <= 4


@pytest.mark.parametrize("name, tables", [("example_costs", ["orders"]), ("exp_gap", ["customer", "orders"]), ("exp_compare_grid", ["conversations"]), ("exp_alpha_rmat", ["pages"]), ("exp_ablation_rmat", ["pages"])])
def test_measured_values_come_from_given_tables(spark, sf, monkeypatch, name, tables):
    from hetpart import registry

    read, seen = graphs.read, []
    monkeypatch.setattr(graphs, "read", lambda s, d, t: seen.append(t) or read(s, d, t))
    rows = registry.QUERIES[name](spark, sf).collect()
    assert rows and sorted(set(seen)) == tables
    if "agrees" in rows[0]:
        assert all(r["agrees"] and r["graph"] in ("g10", "g13") for r in rows)


SWEEPS_OF_G9 = ["exp_compare_g9", "inv_exp_compare_g9", "inv_exp_nine_g9", "exp_beta_g9", "inv_exp_beta_g9", "inv_exp_alpha_g9", "exp_gamma_g9", "inv_exp_gamma_g9", "exp_t0_g9", "inv_exp_t0_g9", "exp_theta_g9", "inv_exp_theta_g9", "exp_n0_g9"]


@pytest.fixture(scope="module")
def many_vectors(tmp_path_factory):
    """5,000 vectors of 64 numbers, as a folder with the table of them."""
    d, n = tmp_path_factory.mktemp("vectors"), 5_000
    x = np.random.default_rng(4).normal(size=(n, 64)).astype(np.float32)
    pq.write_table(pa.table({"vec_id": np.arange(n), "embedding": list(x)}), f"{d}/embeddings.parquet")
    return str(d), x


@pytest.mark.parametrize("name", SWEEPS_OF_G9)
def test_search_for_a_sweep_holds_slices(spark, many_vectors, monkeypatch, name):
    """The task that finds neighbours for a sweep of g9 holds slices, whatever the number of
    vectors that it gets; all vectors and settings reach the sweep."""
    from hetpart import registry

    (d, x), tasks, given = many_vectors, [], []
    monkeypatch.setattr(X, "sweep", lambda edges, g, runs, fleet_of=None: given.append((edges, g, runs)) or spark.createDataFrame([], X.RESULT))
    frame = type(spark.range(0))
    real = frame.mapInArrow
    monkeypatch.setattr(frame, "mapInArrow", lambda self, f, *a, **k: tasks.append(f) or real(self, f, *a, **k))
    registry.QUERIES[name](spark, d)
    (edges, g, runs), (task,) = given[0], tasks
    settings = X.SWEEPS.get(name.removeprefix("inv_").split("_")[1])
    assert g == "g9" and [v for _, _, v in runs] == (settings[1] if settings else [0.0] * len(X.FIVE))
    assert graphs.degrees(edges).count() == len(x)
    some = pa.RecordBatch.from_pydict({"vec_id": np.arange(2_500), "embedding": list(x[:2_500])})
    tracemalloc.start()
    found = sum(b.num_rows for b in task(iter([some])))
    peak = tracemalloc.get_traced_memory()[1] / 1e6
    tracemalloc.stop()
    assert found == 8 * 2_500 and peak < 130


def test_search_among_near_copies_holds_slices():
    """Vectors that single precision hardly tells apart are all compared again, in slices."""
    rng = np.random.default_rng(7)
    x = (rng.normal(size=8) + 1e-6 * rng.normal(size=(4_000, 8))).astype(np.float32)
    near = graphs.Nearest(np.arange(len(x)), x, 8)
    near.prepare()
    tracemalloc.start()
    got = [np.concatenate(y) for y in zip(*near.pairs(np.arange(2_000)), strict=True)]
    peak = tracemalloc.get_traced_memory()[1] / 1e6
    tracemalloc.stop()
    own = x.astype(float)
    norm = np.add.accumulate(own * own, axis=1)[:, -1]
    for me in range(0, 2_000, 97):
        w = np.clip(np.add.accumulate(own[me] * own, axis=1)[:, -1] / np.sqrt(norm[me] * norm), -1, 1)
        want = [v for v in np.lexsort((np.arange(len(x)), -w)) if v != me][:8]
        assert got[1][got[0] == me].tolist() == want
    assert len(got[0]) == 8 * 2_000 and peak < 200


def test_vectors_are_prepared_in_slices(monkeypatch):
    x = np.random.default_rng(4).normal(size=(20_000, 64)).astype(np.float32)
    near = graphs.Nearest(np.arange(len(x)), x, 8)
    monkeypatch.setattr(graphs, "PRODUCTS", 64_000)
    tracemalloc.start()
    near.prepare()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    own = near.vectors.astype(float)
    assert np.array_equal(near.norm, np.add.accumulate(own * own, axis=1)[:, -1])
    assert peak < 1.5 * x.nbytes


@pytest.mark.parametrize("cells", [40, 4_000_000])
def test_levels_hold_no_edges_of_their_own(monkeypatch, cells):
    """The multilevel comparator on a graph whose edges hardly merge: many levels."""
    rng = np.random.default_rng(6)
    a, b = rng.integers(0, 6_000, 60_000), rng.integers(0, 6_000, 60_000)
    e = np.unique(np.minimum(a, b)[a != b] * 6_000 + np.maximum(a, b)[a != b])
    block, p = Block(e // 6_000, e % 6_000), 3
    if cells == 40:  # ranges of vertices give the same homes
        e = e[:3_000]
        block = Block(e // 6_000, e % 6_000)
        want = streams.multilevel_homes(block, p)
        monkeypatch.setattr(streams, "CELLS", cells)
        assert np.array_equal(streams.multilevel_homes(block, p), want)
        return
    tracemalloc.start()
    homes = streams.multilevel_homes(block, p)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.bincount(homes, minlength=p).min() > 0 and peak < 200 * len(e)


def test_compare_grid_doesnt_depend_on_size_bounds(spark, sf, monkeypatch):
    """The same method on the whole graph, whatever the bounds on edges side by side and of a block."""
    same_by_any_bounds(spark, sf, monkeypatch, "exp_compare_grid")


def test_gains_doesnt_depend_on_size_bounds(spark, sf, monkeypatch):
    """Gains are of the method itself, not of blocks."""
    same_by_any_bounds(spark, sf, monkeypatch, "exp_gains")


def test_gamma_g1_doesnt_depend_on_size_bounds(spark, sf, monkeypatch):
    same_by_any_bounds(spark, sf, monkeypatch, "exp_gamma_g1")


def test_hetero_rmat_doesnt_depend_on_size_bounds(spark, sf, monkeypatch):
    same_by_any_bounds(spark, sf, monkeypatch, "exp_hetero_rmat")


def same_by_any_bounds(spark, sf, monkeypatch, name):
    from hetpart import registry

    def values():
        r = registry.QUERIES[name](spark, sf)
        rows = sorted(tuple(x) for x in r.drop("seconds", "edges_per_second", "blocks").collect())
        return rows, {x["blocks"] for x in r.collect()} if "blocks" in r.columns else set()

    want, one = values()
    monkeypatch.setattr(X, "SWEEP_EDGES", 1)
    monkeypatch.setattr(X, "BLOCK_EDGES", 40)
    got, many = values()
    assert want and got == want and one <= {1} and (not many or min(many) > 1)


@pytest.mark.parametrize("ordered", [True, False])
def test_block_has_all_neighbours_in_order(monkeypatch, ordered):
    """Adjacency made in slices, of edges and of arcs that point both ways; a hub of 300."""
    from hetpart.operators import growth
    from hetpart.operators.refine import State

    monkeypatch.setattr(growth, "SLICE", 7)
    e = np.unique(np.random.default_rng(3).integers(0, 400, (900, 2)), axis=0)
    e = e[e[:, 0] < e[:, 1]] if ordered else e[e[:, 0] != e[:, 1]]
    e = np.unique(np.concatenate([e, [[0, v] for v in range(1, 301)]]), axis=0) * 16 + 5
    shuffled = np.random.default_rng(4).permutation(e)
    ends = [shuffled[:, 0], shuffled[:, 1]]
    block = Block.taking(ends) if ordered else Block(*ends)
    assert not ends if ordered else len(ends) == 2
    assert np.array_equal(np.stack([block.src, block.dst], 1), e)
    a, b = np.searchsorted(block.ids, e[:, 0]), np.searchsorted(block.ids, e[:, 1])
    for v in range(len(block.ids)):
        want = sorted([(int(b[k]), int(k)) for k in np.flatnonzero(a == v)] + [(int(a[k]), int(k)) for k in np.flatnonzero(b == v)])
        lo, hi = block.ptr[v], block.ptr[v + 1]
        assert sorted(zip(block.nbr[lo:hi].tolist(), block.eid[lo:hi].tolist(), strict=True)) == want and np.all(np.diff(block.nbr[lo:hi]) >= 0)
    s = State(block, machines.homogeneous(len(e), 2), np.zeros(len(e), np.int32), np.zeros(len(e), np.int64))
    assert s.count[0].tolist() == np.diff(block.ptr).tolist() and s.count.max() >= 300


def test_seeds_come_as_from_one_heap():
    """Keys that fell since stay as they were till they come up, as in one heap of all vertices."""
    from hetpart.operators.growth import Seeds

    rng = np.random.default_rng(5)
    e = np.unique(np.sort(rng.integers(0, 60, (200, 2)), axis=1), axis=0)
    for policy in ("low_degree", "max_degree", "random"):
        block = Block(*e[e[:, 0] < e[:, 1]].T)
        n, sign = len(block.ids), -1 if policy == "max_degree" else 1
        rank, seeds = np.random.default_rng(2).permutation(n), Seeds(block, policy, 2)
        heap = [(int(rank[v]) if policy == "random" else sign * int(block.degree[v]), v) for v in range(n)]
        for _ in range(300):
            done, aside, want = rng.random(n) < 0.5, [], None
            while heap and want is None:
                x = min(heap)
                heap.remove(x)
                key, v = x
                d = int(block.degree[v])
                if d and policy != "random" and key != sign * d:
                    heap.append((sign * d, v))
                elif d:
                    aside.append(x)
                    want = None if done[v] else v
            heap += aside
            assert seeds.next(done) == want
            block.degree[rng.integers(n)] //= 2
