"""Queries and workloads answer for all of their input, at sizes where a cut would show."""

import inspect

import duckdb
import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from cellcluster import baselines, cluster, measures, workloads
from cellcluster.components import star_components, task_forest
from cellcluster.operators import joins
from cellcluster.plans import registry
from cellcluster.prefixtree import PrefixTree
from cellcluster.spec import ClusterSpec

LARGER = "/root/testdata/sf0.01"


def test_intervals_of_all_parts_are_joined(spark):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW part AS SELECT * FROM '{LARGER}/part.parquet'")
    got = sorted((r.a_id, r.b_id) for r in registry.QUERIES["interval_all_parts"](spark, LARGER).collect())
    assert max(a for a, _ in got) > 400
    assert got == sorted(c.execute(registry.ORACLES["interval_all_parts"]).fetchall())
    i = c.execute("SELECT p_partkey, p_size * 10, p_size * 10 + p_partkey % 15 FROM part").fetchall()
    assert got == sorted((a, b) for a, lo, hi in i if a % 2 == 0 for b, low, high in i if b % 2 == 1 and lo <= high and low <= hi)


def test_ball_blocks_absorb_every_dense_point_of_a_chain(spark):
    """Ids in the order of a line: by smallest id each round would pick one centre, 250 in all."""
    ps = spark.range(1500).selectExpr("id AS point_id", "id AS x1", "0L AS x2")
    for method in (baselines.ball_block, baselines.ball_block_exact):
        result = method(ps, ClusterSpec(10, 5))
        seen = baselines.block_profile(result).first()
        assert (seen.absorbed, seen.outer_cores) == (1500, 0)
    assert result.membership.select("cluster_id", "role").distinct().collect() == [(0, "core")]


def test_index_ablation_asks_for_every_cell(spark, monkeypatch):
    """More cells than 100,000, and the neighbours that one tree over all of them finds."""
    ps = spark.range(110_000).selectExpr("id AS point_id", "id % 400 * 200 AS x1", "id DIV 400 * 300 AS x2", "0L AS x3")
    monkeypatch.setattr(workloads.fixtures, "points", lambda *_: ps)
    got = list(workloads.index_ablation(spark, "", ("any",), (150, 300)))
    x = np.array([[i % 400 * 200, i // 400 * 300, 0] for i in range(110_000)])
    for eps in (150, 300):
        # no coordinate lies on a side, as the square root of 3 is irrational
        keys = np.unique(np.floor(x * np.sqrt(3) / eps).astype(np.int64), axis=0)
        found = sum(len(PrefixTree(keys).query(keys[k : k + 4096], 2)[0]) for k in range(0, len(keys), 4096))
        assert len(keys) == 110_000
        assert [(r["tree"], r["cells"], r["mean_nbr"]) for r in got if r["eps"] == eps] == [(t, len(keys), found / len(keys)) for t in ("prefix", "rect")]


def test_whole_index_ladder_is_registered(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(workloads, "index_costs", lambda own: asked.append(len(own.columns)) or spark.createDataFrame([("prefix", 1, 1, 1, 0.0)], "tree string, cells bigint, found bigint, visited bigint, seconds double"))
    got = {(r["name"], r.eps) for r in registry.QUERIES["workload_w9_index"](spark, "/root/testdata/sf0.001").collect()}
    assert got == {(n, e) for n in ("embed4", "line5", "line7") for e in workloads.EPS} | {("embed4", 12000)} and len(asked) == 22


def _asked(monkeypatch, name):
    """Arguments, defaults filled in, with which a workload is called."""
    calls, sign = [], inspect.signature(getattr(workloads, name))

    def record(*args, **how):
        bound = sign.bind(*args, **how)
        bound.apply_defaults()
        calls.append(bound.arguments)
        return iter(())

    monkeypatch.setattr(workloads, name, record)
    return calls


def test_cluster_counts_are_registered_for_both_densities_and_eps(spark, monkeypatch):
    calls = _asked(monkeypatch, "cluster_counts")
    registry.QUERIES["workload_w3_cluster_counts"](spark, LARGER)
    (c,) = calls
    assert (set(c["kinds"]), set(c["ladder_"])) == ({"even", "varied"}, {2000, 4500}) and c["n"] >= 3000


def test_merge_orders_are_registered_for_all_sets(spark, monkeypatch):
    calls = _asked(monkeypatch, "merge_ablation")
    registry.QUERIES["workload_w10_merge_orders"](spark, LARGER)
    assert {n for c in calls for n in c["names"]} == {"part", "events", "line3"}


def test_ladders_take_walks_and_given_tables(monkeypatch):
    monkeypatch.setattr(workloads, "measured", lambda name, method, make, spec, run: (name, method, spec.eps, spec.min_pts))
    high, plane = {"embed4", "line5", "line7", "docs7"}, {"events", "part", "cust", "orders"}
    for which, tables in (("W4", high), ("W6", plane), ("W7", plane), ("W5", {f"{n}_{s}" for n in ("line3", "line5", "line7") for s in workloads.SCALES}), ("W8", {f"events_{s}" for s in workloads.SCALES})):
        got = list(workloads.ladder(None, LARGER, which))
        assert {g[0] for g in got if not g[0].startswith("walk")} == tables and any(g[0].startswith("walk") for g in got)
        if which in ("W4", "W7"):
            assert all({g[3] for g in got if g[0] == t} == set(workloads.MIN_PTS) for t in tables)


def copied(spark, n=300, copies=7, width=4000):
    """Places of a plane with copies of shifted ids, as a pandas frame and as points."""
    r = np.random.default_rng(3)
    x = np.repeat(r.integers(0, width, (n, 2)), copies, axis=0)
    df = pd.DataFrame({"point_id": np.arange(len(x)), "x1": x[:, 0], "x2": x[:, 1]})
    return spark.createDataFrame(df), x


def test_pairs_compare_places_and_lose_no_copy(spark, monkeypatch):
    ps, x = copied(spark)
    compared = []
    near_places = baselines.near_places
    monkeypatch.setattr(baselines, "near_places", lambda at, *a: compared.append(at.count()) or near_places(at, *a))
    near = np.square(x[:, None] - x[None]).sum(axis=2) <= 90_000
    for how in ("cell", "theta"):
        got = baselines.eps_pairs(ps, 300, how).toPandas()
        assert len(got) == near.sum() and near[got["i"], got["j"]].all() and not got.duplicated().any()
        n = {r.point_id: r.n for r in baselines.core_pointwise(ps, ClusterSpec(300, 30), how).collect()}
        assert n == {int(i): int(k) for i, k in enumerate(near.sum(axis=1)) if k >= 30}
    assert compared and max(compared) <= 300
    plan = baselines.eps_pairs(ps, 300)._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=merge" in plan  # the copies that look for their bins are not broadcast


def test_points_reached_by_two_components_pair_once(spark):
    x = np.array([[0, 0]] * 11 + [[200, 0], [450, 0], [700, 0]] + [[900, 0]] * 11 + [[5000, k] for k in range(20)])
    ps, spec = spark.createDataFrame(pd.DataFrame({"point_id": np.arange(len(x)), "x1": x[:, 0], "x2": x[:, 1]})), ClusterSpec(250, 12)
    near = np.square(x[:, None] - x[None]).sum(axis=2) <= 250**2
    reach = {}
    for r in baselines.reach_closure(ps, spec).collect():
        reach.setdefault(r.p, set()).add(r.q)
    core = near.sum(axis=1) >= 12
    assert set(reach) == set(np.flatnonzero(core).tolist())
    want = {(p, q) for qs in map(frozenset, reach.values()) for p in qs for q in qs if p < q}
    seen = {}
    for qs in {frozenset(v) for v in reach.values()}:
        for q in qs:
            seen[q] = seen.get(q, 0) + 1
    assert max(seen.values()) > 1  # some border point is shared
    got = [tuple(r) for r in baselines.connected_pairs(ps, spec).collect()]
    assert len(got) == len(set(got)) and set(got) == want


def test_pointwise_and_sampled_methods_on_copies(spark):
    ps, _ = copied(spark, 400, 5, 6000)
    for eps, min_pts in ((250, 11), (120, 6)):
        spec = ClusterSpec(eps, min_pts)
        flag = cluster.cell_exact(ps, spec)
        for how in ("theta", "cell"):
            assert measures.same_clustering(baselines.pointwise(ps, spec, how).membership, flag.membership).isEmpty()
        # asked of all points, the sampled method misses nothing
        assert measures.same_clustering(baselines.sampled_expansion(ps, spec, reps=10**6).membership, flag.membership).isEmpty()
        assert measures.check_axioms(flag, ps, spec).isEmpty()
        m = flag.membership
        wrong = cluster.ClusterResult(m.withColumn("cluster_id", F.when(F.col("point_id") % 5 == 1, F.col("point_id")).otherwise(F.col("cluster_id"))), flag.flagged, flag.counters)
        assert {r.violation for r in measures.check_axioms(wrong, ps, spec).select("violation").distinct().collect()} == {"split", "left out", "unreached"}


def test_forest_of_a_task_joins_what_its_edges_join(spark):
    r = np.random.default_rng(5)
    rows = [(int(a), int(b)) for a, b in r.integers(0, 400, (260, 2))]
    edges = spark.createDataFrame(rows, "a bigint, b bigint").repartition(3)
    for most in (16, 1 << 20):
        kept = task_forest(edges, most)
        assert kept.count() <= 3 * 400
        assert {tuple(x) for x in star_components(kept).collect()} == {tuple(x) for x in star_components(edges.where("a <> b")).collect()}


def test_copies_share_their_nearest_rows_and_their_intervals(spark, monkeypatch):
    r = np.random.default_rng(6)
    place = lambda n, copies: np.repeat(r.integers(0, 900, (n, 2)), copies, axis=0)
    x, y = place(30, 4), place(40, 6)
    a = spark.createDataFrame(pd.DataFrame({"a": np.arange(len(x)), "ax": x[:, 0], "ay": x[:, 1]}))
    b = spark.createDataFrame(pd.DataFrame({"b": np.arange(len(y)), "bx": y[:, 0], "by": y[:, 1]}))
    asked, eps_join = [], joins.eps_join
    monkeypatch.setattr(joins, "eps_join", lambda l, r, *a: asked.append((l.count(), r.count())) or eps_join(l, r, *a))
    got = {(v.a, v["rank"]): (v.sq, v.b) for v in joins.knn_join(a, b, 8, ["ax", "ay"], ["bx", "by"], "a", "b", 60).collect()}
    sq = np.square(x[:, None] - y[None]).sum(axis=2)
    assert got == {(i, k + 1): v for i in range(len(x)) for k, v in enumerate(sorted((int(sq[i, j]), j) for j in range(len(y)))[:8])}
    assert max(n for n, _ in asked) <= 30 and max(n for _, n in asked) <= 40
    i, j = ([(k, int(v), int(v + w)) for k, (v, w) in enumerate(np.repeat(r.integers(0, 60, (25, 2)), 5, axis=0))] for _ in range(2))
    both = joins.interval_join(spark.createDataFrame(i, "i long, l long, h long"), spark.createDataFrame(j, "j long, m long, g long"), ("l", "h"), ("m", "g"), 25)
    assert sorted((v.i, v.j) for v in both.collect()) == sorted((p, q) for p, l, h in i for q, m, g in j if l <= g and m <= h)


def test_walks_number_the_rows_of_given_tables(spark):
    for name, table, key in (("generator_even_2d", "events", "event_id"), ("generator_varied_3d", "orders", "o_orderkey"), ("membership_walk_2d", "customer", "c_custkey"), ("membership_walk_7d", "customer", "c_custkey")):
        given = spark.read.parquet(f"/root/testdata/sf0.001/{table}.parquet").select(F.col(key).alias("point_id"))
        made = registry.QUERIES[name](spark, "/root/testdata/sf0.001").select("point_id").distinct()
        assert made.exceptAll(given).isEmpty() and given.exceptAll(made).isEmpty()
        assert f"FROM {table}" in registry.ORACLES[name]
    assert {r.table for r in workloads.settings("W1")} == {"supplier"} and all("FROM supplier" in r.sql("") for r in workloads.settings("W1"))


def test_counts_come_from_shared_places_with_their_weights(spark, monkeypatch):
    small, asked = "/root/testdata/sf0.001", []
    runs = [workloads.Run("line5", 4000, 10), workloads.Run("line5", 2000, 40), workloads.Run("walk_3d_even", 4000, 3, 1500, 3, "even", "supplier")]
    monkeypatch.setattr(workloads, "settings", lambda which: runs)
    places = workloads.Run.places
    monkeypatch.setattr(workloads.Run, "places", lambda self, *a: asked.append(self.source) or places(self, *a))
    c = duckdb.connect()
    for t in ("lineitem", "supplier"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    got = sorted(tuple(r) for r in workloads.counted(spark, small, "W2").collect())
    assert got == sorted(c.execute(workloads.counted_sql("W2")).fetchall())
    assert len(asked) == len(set(asked)) == 2


def test_load_of_blocks_counts_copies_of_a_place_as_points(spark, monkeypatch):
    """Copies of a place fall into one block: they count as home points and are one row there."""
    r = np.random.default_rng(8)
    x = np.repeat(r.integers(0, 100_000, (400, 2)), 30, axis=0)
    made = spark.createDataFrame(pd.DataFrame({"point_id": np.arange(len(x)), "x1": x[:, 0] // 20, "x2": x[:, 1] // 20}))
    monkeypatch.setattr("cellcluster.fixtures.points", lambda *a: made)
    assert registry.QUERIES["block_load_events"](spark, "").collect() == [(len(x), 0)]


def test_frequent_keys_meet_as_lists(spark):
    """A key of 1,100 and 700 rows: no row of the join holds more than a list of ids, and every pair comes once."""
    a = spark.range(1103).selectExpr("CASE WHEN id < 1100 THEN 1L ELSE id END AS k", "id AS a")
    b = spark.range(702).selectExpr("CASE WHEN id < 700 THEN 1L ELSE id + 400 END AS k", "id AS b")
    sizes = [r.n for r in joins.packs(a, ["k"], "a", "ids").selectExpr("size(ids) AS n").collect()]
    assert max(sizes) <= joins.PACK and sum(sizes) == 1103
    got = joins.packed_join(a, b, ["k"], "a", "b").toPandas()
    want = {(i, j) for i in range(1100) for j in range(700)} | {(1100, 700), (1101, 701)}
    assert len(got) == len(want) and set(zip(got["a"], got["b"], strict=True)) == want


def test_pairs_are_unfolded_after_their_last_join(spark):
    ps, _ = copied(spark)
    joined = lambda df: df._jdf.queryExecution().optimizedPlan().toString().splitlines()
    spec = ClusterSpec(300, 30)
    pairs = [baselines.eps_pairs(ps, 300), baselines.eps_pairs(ps, 300, "theta"), baselines.direct_reach(ps, spec), baselines.reach_closure(ps, spec), baselines.connected_pairs(ps, spec), registry.QUERIES["pair_metrics_supp"](spark, LARGER)]
    for df in pairs:
        names = [line.lstrip(" :+-").split(" ")[0].split("(")[0] for line in joined(df)]
        assert names.count("Generate") >= 2 and "Join" not in names[: names.index("Generate") + 1]


def test_merge_orders_run_by_component_in_tasks(spark, monkeypatch):
    """The counters of both orders over all cells at once, without bringing points to the driver."""
    r = np.random.default_rng(4)
    x = np.concatenate([r.integers(0, 9_000, (900, 2)), r.integers(40_000, 49_000, (700, 2))])
    ps = spark.createDataFrame(pd.DataFrame({"point_id": np.arange(len(x)), "x1": x[:, 0], "x2": x[:, 1]}))
    monkeypatch.setattr(workloads.fixtures, "points", lambda *_: ps)
    spec = ClusterSpec(workloads.fixtures.SETS["part"].eps // 5, 5)
    monkeypatch.setitem(workloads.fixtures.SETS, "part", workloads.fixtures.PointSet("part", "p_partkey", ("a", "b"), spec.eps, spec.min_pts))
    core = cluster.mark_core(ps, spec)[0].where("is_core").orderBy("point_id").toPandas()
    monkeypatch.setattr(type(ps), "toPandas", lambda self: (_ for _ in ()).throw(AssertionError("points on the driver")))
    got = {(g["order"], g["gap"]): {k: v for k, v in g.items() if k not in ("set", "order", "gap")} for g in workloads.merge_ablation(spark, "", ("part",))}
    grid, own = np.unique(core[["k1", "k2"]].to_numpy(), axis=0, return_inverse=True)
    groups = [core[["x1", "x2"]].to_numpy()[own.ravel() == k] for k in range(len(grid))]
    q, o, _ = PrefixTree(grid).query(grid, spec.reach(2))
    near = [o[q == k] for k in range(len(grid))]
    assert len(got) == 2 * len(workloads.gaptest.EXACT)
    for order, run in workloads.MERGE_ORDERS.items():
        for gap in workloads.gaptest.EXACT:
            label, count = run(groups, near, spec.eps, workloads.gaptest.TESTS[gap])
            assert got[order, gap] == {"components": len(set(label)), **count} and count["checks"] > 0


def test_points_of_places_are_not_broadcast(spark):
    ps, _ = copied(spark)
    plan = baselines.members(ps, baselines.collapse_duplicates(ps))._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=merge" in plan


def test_sampled_expansion_broadcasts_nothing_that_grows(spark):
    """A plan may take 1.2 M border points for small; the joins with points are by merge in the plan that runs too."""
    ps, _ = copied(spark)
    noise = baselines.sampled_expansion(ps, ClusterSpec(300, 30)).membership.where("role = 'noise'")
    noise.collect()
    plan = noise._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastExchange" not in plan


def test_all_pairs_of_places_meet_as_lists_over_several_tasks(spark, monkeypatch):
    r = np.random.default_rng(9)
    x, y = r.integers(0, 900, (300, 3)), r.integers(0, 900, (200, 3))
    a = spark.createDataFrame(pd.DataFrame({"i": np.arange(300), **{f"x{j + 1}": x[:, j] for j in range(3)}})).coalesce(1)
    b = spark.createDataFrame(pd.DataFrame({"j": np.arange(200), **{f"y_x{j + 1}": y[:, j] for j in range(3)}})).coalesce(1)
    monkeypatch.setattr(baselines, "PACK", 16)
    near = baselines._near(a, b, 150, "theta")
    assert near._jdf.queryExecution().optimizedPlan().toString().count("Repartition 24, true") == 1
    got = [(v.i, v.j) for v in near.collect()]
    assert len(got) == len(set(got)) and set(got) == {(int(i), int(j)) for i, j in np.argwhere(np.square(x[:, None] - y[None]).sum(axis=2) <= 150**2)}


def test_bins_of_few_bytes_stay_dealt(spark):
    """Lists of a few bins are few bytes but many rows: their join is not merged into one task."""
    ps, _ = copied(spark)
    at = baselines.packs(ps, ["x1", "x2"], "point_id", "ids")
    plan = baselines._pairs(at, at, 300, "cell", "i", "j")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionByExpression [g1") == 2


def _exchanged(df):
    """Lines of the plan that stand between the last join and the scans below it: what is dealt is dealt before it."""
    names = [line.lstrip(" :+-").split(" ")[0].split("(")[0] for line in df._jdf.queryExecution().optimizedPlan().toString().splitlines()]
    return names[: names.index("Join")]


def test_pairs_of_lists_are_made_where_they_are_unfolded(spark):
    """Pairs of lists grow with the square of the rows, so they are never exchanged."""
    ps, _ = copied(spark)
    spec = ClusterSpec(300, 30)
    for df in (baselines.reach_closure(ps, spec), baselines.connected_pairs(ps, spec), registry.QUERIES["pair_metrics_supp"](spark, LARGER), registry.QUERIES["interval_all_parts"](spark, LARGER)):
        assert "RepartitionByExpression" not in _exchanged(df) and _exchanged(df).count("Generate") == 2


def test_stripes_of_lists_lose_no_pair(spark, monkeypatch):
    """More lists than a stripe holds on both sides, null rows among equal intervals, and ends that other columns stand between."""
    monkeypatch.setattr(joins, "STRIPE", 2)
    pack = joins.packs
    monkeypatch.setattr(joins, "packs", lambda *a: pack(*a, size=8))
    a = spark.range(103).selectExpr("CASE WHEN id < 100 THEN 1L ELSE id END AS k", "id AS a")
    b = spark.range(72).selectExpr("CASE WHEN id < 70 THEN 1L ELSE id + 30 END AS k", "id AS b")
    got = [(r.a, r.b) for r in joins.packed_join(a, b, ["k"], "a", "b").collect()]
    assert len(got) == len(set(got)) and set(got) == {(i, j) for i in range(100) for j in range(70)} | {(100, 70), (101, 71)}
    i = [(10, k if k % 9 else None, 12, str(k)) for k in range(40)] + [(30, 1, 60, "x"), (None, 1, 60, "y")]
    j = [(k % 2, 11, 11 + k % 3) for k in range(50)] + [(5, 60, 90), (None, 61, 62)]
    got = joins.interval_join(spark.createDataFrame(i, "l long, i long, h long, s string"), spark.createDataFrame(j, "j long, m long, g long"), ("l", "h"), ("m", "g"), 7)
    assert got.columns == ["l", "i", "h", "s", "j", "m", "g"]
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(str((*x, *y)) for x in i for y in j if x[0] is not None and x[0] <= y[2] and y[1] <= x[2])
