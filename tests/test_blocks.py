"""Blocks follow counts, and merge orders, relations and labels against brute force."""

import numpy as np
import pytest

from cellcluster import baselines, blocks, cells, cluster, gaptest, measures, merge, points
from cellcluster.prefixtree import PrefixTree
from cellcluster.spec import ClusterSpec


def made(spark, n, d=2, seed=1, dense=0.9, width=10_000):
    r = np.random.default_rng(seed)
    x = r.integers(0, 100_000, (n, d))
    k = int(n * dense)
    x[:k] = 40_000 + r.integers(0, width, (k, d))
    return spark.createDataFrame([(i, *map(int, p)) for i, p in enumerate(x)], "point_id bigint, " + ", ".join(f"x{j + 1} bigint" for j in range(d))), x


def brute_labels(x, eps, min_pts):
    near = np.square(x[:, None] - x[None]).sum(axis=2) <= eps * eps
    core = near.sum(axis=1) >= min_pts
    label = np.arange(len(x))
    while True:
        new = np.array([label[near[i] & core].min() if core[i] else label[i] for i in range(len(x))])
        if (new == label).all():
            return near, core, label
        label = new


def test_dense_regions_are_cut_to_the_limit(spark):
    """Nine points in ten lie in a hundredth of the area."""
    ps, x = made(spark, 4000)
    spec = ClusterSpec(300, 5, block_points=500)
    load = measures.block_load(ps, spec).collect()
    assert sum(r.home for r in load) == len(x) and max(r.home for r in load) <= 500
    assert sum(r.home for r in load if r.home > 250) > len(x) / 2  # not cut for nothing


def test_coarse_counts_are_refined(spark, monkeypatch):
    monkeypatch.setattr(blocks, "PLAN_ROWS", 40)
    ps, x = made(spark, 3000, seed=2)
    spec = ClusterSpec(300, 5, block_points=200)
    load = measures.block_load(ps, spec).collect()
    assert sum(r.home for r in load) == len(x) and max(r.home for r in load) <= 400
    found = {r.point_id: r.cluster_id for r in cluster.cell_exact(ps, spec).membership.where("role = 'core'").collect()}
    _, core, label = brute_labels(x, 300, 5)
    assert found == {int(i): int(label[i]) for i in np.flatnonzero(core)}


def test_halo_copies_reach_every_block_within_reach():
    plan = blocks.BlockPlan(2)
    a, b = plan.cut(plan.node(), 0, 10)
    plan.leaf(a)
    c, e = plan.cut(b, 1, 5)
    plan.leaf(c), plan.leaf(e)
    keys = np.array([[0, 0], [9, 4], [11, 4], [30, 9], [8, 20]])
    low, high = plan.boxes(2)
    row, block, home = plan.assign(keys)
    for k, cell in enumerate(keys):
        near = {int(n) for n in range(3) if (np.maximum(low[n] - cell, cell - high[n]).clip(0) <= 2).all()}
        own = {int(n) for n in range(3) if ((low[n] <= cell) & (cell <= high[n])).all()}
        assert set(block[row == k].tolist()) >= near and set(block[(row == k) & home].tolist()) == own
    groups = plan.colours(2)
    assert sorted(int(b) for g in groups for b in g) == [0, 1, 2]


def test_weights_count_as_points(spark):
    x = [(0, 0)] * 10 + [(40, 0)] * 3 + [(500, 500)]
    ps = spark.createDataFrame([(i, *p) for i, p in enumerate(x)], "point_id bigint, x1 bigint, x2 bigint")
    spec, places = ClusterSpec(50, 13), points.collapse_duplicates(ps)
    whole = sorted(tuple(r) for r in cluster.cell_exact(ps, spec).membership.collect())
    assert sorted(tuple(r) for r in points.expand_duplicates(cluster.cell_exact(places, spec).membership, ps, places).collect()) == whole
    assert sum(r[2] == "core" for r in whole) == 13


@pytest.mark.parametrize("order", ["graph", "sparse_first"])
def test_merge_orders_test_what_the_simulation_tests(spark, order):
    ps, x = made(spark, 700, seed=3, dense=0.8, width=6000)
    spec = ClusterSpec(900, 4, block_points=10**6)
    result = cluster.run(ps, spec, order=order, boxes=False, trace=True)
    core = result.flagged.where("is_core").toPandas()
    keys, own = np.unique(core[["k1", "k2"]].to_numpy(), axis=0, return_inverse=True)
    groups = [core[["x1", "x2"]].to_numpy()[own.ravel() == k] for k in range(len(keys))]
    q, o, _ = PrefixTree(keys).query(keys, spec.reach(2))
    run = merge.merge_search if order == "graph" else merge.merge_sparse_first
    _, count = run(groups, [o[q == k] for k in range(len(keys))], spec.eps)
    profile = result.merge_profile().first()
    kappa = result.kappa_profile().toPandas()
    if len(result.plan.boxes(2)[0]) == 1:
        assert profile.checks == count["checks"]
    assert profile.kappa == kappa["kappa"].max() and profile.checks == len(kappa) == len(kappa[["a", "b"]].drop_duplicates())


def test_sparse_first_tests_no_more_than_the_search(spark):
    ps, _ = made(spark, 1500, seed=4, dense=0.85, width=9000)
    spec = ClusterSpec(700, 4, block_points=10**6)
    one, other = (cluster.run(ps, spec, order=o, boxes=False).merge_profile().first().checks for o in ("sparse_first", "graph"))
    assert one <= other


def test_relations_and_nearest_core_labels(spark):
    ps, x = made(spark, 250, seed=6, dense=0.7, width=4000)
    near, core, label = brute_labels(x, 700, 4)
    spec = ClusterSpec(700, 4)
    assert {tuple(r) for r in baselines.direct_reach(ps, spec).collect()} == {(i, j) for i in range(250) for j in range(250) if core[i] and near[i, j]}
    reach = {(i, j) for i in range(250) if core[i] for j in range(250) if any(core[m] and label[m] == label[i] and near[m, j] for m in range(250))}
    assert {tuple(r) for r in baselines.reach_closure(ps, spec).collect()} == reach
    for r in cluster.cell_exact(ps, spec).labels("nearest_core").collect():
        if r.role == "border":
            square = np.square(x - x[r.point_id]).sum(axis=1)
            assert r.cluster_id == min((square[m], label[m]) for m in range(250) if core[m])[1]


def test_ball_blocks_by_both_searches(spark):
    ps, _ = made(spark, 600, seed=7, dense=0.8, width=5000)
    spec = ClusterSpec(800, 4, block_points=100)
    exact = baselines.ball_block_exact(ps, spec)
    assert measures.same_clustering(exact.membership, cluster.cell_exact(ps, spec).membership).isEmpty()
    linear = baselines.ball_block(ps, spec, gap="alternating_prune", search="linear")
    assert linear.merge_profile().first().checks >= exact.merge_profile().first().checks
    # every ball has its points within half of eps of its centre
    inside = exact.flagged.where("inner_core").toPandas()
    at = inside.set_index("point_id")[["x1", "x2"]]
    assert ((inside[["x1", "x2"]].to_numpy() - at.loc[inside["cell"].astype(int)].to_numpy()) ** 2).sum(axis=1).max() * 4 <= 800**2


def test_written_order_is_checked(spark):
    ps, _ = made(spark, 400, seed=8)
    placed = cells.assign_cells(ps, 900)
    assert cells.check_cell_order(cells.partition_cells(placed)).isEmpty()
    assert not cells.check_cell_order(placed.repartition(3)).isEmpty()


def test_approximate_counts_and_clipping():
    r = np.random.default_rng(5)
    for _ in range(150):
        d = int(r.integers(2, 5))
        a, b = r.integers(0, 60, (int(r.integers(1, 25)), d)), r.integers(0, 60, (int(r.integers(1, 25)), d)) + np.array([int(r.integers(0, 70))] + [0] * (d - 1))
        eps, least = int(r.integers(3, 40)), None
        least = gaptest.min_square(a, b)
        x, y = gaptest.clip(a, b, eps)
        assert (len(x) > 0 and len(y) > 0 and gaptest.brute(x, y, eps).yes) == (least <= eps * eps)
        for rho in (0.01, 0.3):
            yes = gaptest.rho_count(a, b, eps, rho).yes
            assert yes if least <= eps * eps else not yes or least <= (eps * (1 + rho)) ** 2
        assert gaptest.nn_index(a, b, eps).yes == gaptest.centre_filter(a, b, eps, "medoid").yes == (least <= eps * eps)


def _block(x, d, core):
    """A block of home points, all of them core points or not, as its kernel gets it."""
    import pyarrow as pa

    keys = np.floor(x * np.sqrt(d) / 100).astype(np.int64)
    columns = {"point_id": np.arange(len(x)), **{f"x{j + 1}": x[:, j] for j in range(d)}, **{f"k{j + 1}": keys[:, j] for j in range(d)}, "is_core": core, "home": np.ones(len(x), bool)}
    return pa.table({k: pa.array(v) for k, v in columns.items()})


def test_a_block_hands_on_stars(spark):
    """A path of 400 cells: as a path it would take the joining of blocks many rounds."""
    x = np.stack([np.arange(400) * 80, np.zeros(400, np.int64)], axis=1)
    for order in ("graph", "sparse_first"):
        links = blocks.merge_kernel(ClusterSpec(100, 1), 2, order=order)(_block(x, 2, np.ones(400, bool))).to_pylist()
        edges = [(r["a"], r["b"]) for r in links if r["kind"] == "edge"]
        assert {a for a, _ in edges} == {"0,0"} and len({b for _, b in edges}) == len(edges) > 300


def test_leaves_stay_out_of_the_rounds(spark):
    from cellcluster.components import durable, star_components

    # a star whose centre is no smallest vertex, a pair, a triangle with leaves, the last of them smaller than all of it
    rows = [(50, 100 + k) for k in range(300)] + [(1, 50), (2, 3), (60, 61), (61, 62), (60, 62), (62, 63), (4, 60)]
    kept = []
    found = star_components(spark.createDataFrame(rows, "a bigint, b bigint"), keep=lambda df: kept.append(df) or durable(df), few=5)
    got = {r.vertex: r.component for r in found.collect()}
    assert got == {**dict.fromkeys([1, 50, *range(100, 400)], 1), 2: 2, 3: 2, **dict.fromkeys([4, 60, 61, 62, 63], 4)}
    assert len(kept) <= 6


def test_neighbours_and_pairs_of_a_block_are_met_in_bounded_stretches(monkeypatch):
    """Points of 5 dimensions with hundreds of neighbour cells: answers come in stretches, and a kernel's answer does not depend on them."""
    r = np.random.default_rng(6)
    x = np.unique(r.integers(0, 220, (700, 5)), axis=0)
    core = np.arange(len(x)) % 3 > 0
    part, spec = _block(x, 5, core), ClusterSpec(100, 30)
    kernels = [blocks.core_kernel(spec, 5), blocks.merge_kernel(spec, 5), blocks.merge_kernel(spec, 5, order="sparse_first")]
    asked = blocks.Cells(part, 5)
    whole, found = [k(part).to_pylist() for k in kernels], asked.tree.query(asked.grid, spec.reach(5), with_self=True)
    monkeypatch.setattr(blocks, "LOOKED", 6000)
    monkeypatch.setattr(blocks, "COMPARED", 500)
    sizes = [len(other) for _, other, _ in asked.neighbours(np.arange(len(asked.grid)), spec.reach(5))]
    assert sum(sizes) == len(found[0]) > 20 * 6000 and max(sizes[1:]) <= 4 * 6000
    assert [sorted(map(str, k(part).to_pylist())) for k in kernels] == [sorted(map(str, w)) for w in whole]
    near = np.square(x[:, None] - x[None]).sum(axis=2) <= 100**2
    assert {v["point_id"] for v in whole[0] if v["is_core"]} == set(np.flatnonzero(near.sum(axis=1) >= 30).tolist())
    assert {v["point_id"] for v in whole[1] if v["kind"] == "border"} == set(np.flatnonzero(~core & (near & core).any(axis=1)).tolist())
