"""Whole methods against an in-memory reference, edge cases, oracles in DuckDB at the smallest size, streams, round trips."""

import numpy as np
import pytest
from .conftest import DATA
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellcluster import baselines, cells, cluster, measures, points
from cellcluster.components import star_components
from cellcluster.functions.surface import cluster_arrays, gap_verdict
from cellcluster.plans import registry
from cellcluster.sources import generators, tables
from cellcluster.spec import ClusterSpec
from cellcluster.streaming import events


def frame(spark, rows, d):
    return spark.createDataFrame([(i, *map(int, r)) for i, r in enumerate(rows)], "point_id bigint, " + ", ".join(f"x{j + 1} bigint" for j in range(d)))


def rows(m):
    return sorted((r.point_id, r.cluster_id if r.cluster_id is not None else -1, r.role) for r in m.collect())


def want(x, eps, min_pts):
    return sorted((p, -1 if c is None else c, r) for p, c, r in cluster_arrays(np.arange(len(x)), np.array(x), eps, min_pts))


CASES = {
    "exactly_eps": ([(0, 0), (300, 400)], 500, 2),
    "one_point": ([(5, 5)], 10, 1),
    "all_alike": ([(7, 7)] * 6, 10, 6),
    "too_few": ([(7, 7)] * 5, 10, 6),
    "huge_eps": ([(0, 0), (99_999, 99_999), (5, 80_000)], 200_000, 2),
    "border_of_two": ([(v, 0) for v in [-5] * 5 + [0] * 4 + [10] + [20] * 4 + [25] * 5], 10, 10),
}


@pytest.mark.parametrize("name", CASES)
def test_edge_cases(spark, name):
    x, eps, m = CASES[name]
    ps = frame(spark, x, 2)
    for method in (cluster.cell_exact, cluster.cell_exact_ldf):
        assert rows(method(ps, ClusterSpec(eps, m)).membership) == want(x, eps, m)


def test_empty_set(spark):
    assert rows(cluster.cell_exact(frame(spark, [], 2), ClusterSpec(5, 2)).membership) == []


@pytest.mark.parametrize("d", [1, 2, 4])
def test_methods_agree_on_random_points(spark, d):
    x = np.random.default_rng(d).integers(0, 2500, (160, d))
    eps, m = (40, 4) if d == 1 else (250, 4) if d == 2 else (700, 4)
    ps = frame(spark, x, d)
    spec = ClusterSpec(eps, m)
    truth = want(x, eps, m)
    assert rows(cluster.cell_exact(ps, spec).membership) == truth
    assert rows(cluster.cell_exact_ldf(ps, ClusterSpec(eps, m, block_points=20, early_stop=False), tree="rect", boxes=False).membership) == truth
    if d == 2:
        for method in (baselines.ball_block_exact, baselines.hash_grid_exact, baselines.planar_front, baselines.plane_grid):
            assert rows(method(ps, spec).membership) == truth


def test_duplicated_points_and_doubled_density_have_the_same_cores(spark):
    x = np.random.default_rng(2).integers(0, 1500, (80, 2))
    once = {r[0] for r in rows(cluster.cell_exact(frame(spark, x, 2), ClusterSpec(200, 4)).membership) if r[2] == "core"}
    twice = {r[0] for r in rows(cluster.cell_exact(frame(spark, np.vstack([x, x]), 2), ClusterSpec(200, 8)).membership) if r[2] == "core"}
    assert {p for p in twice if p < 80} == once


def test_plane_methods_refuse_other_dimensions(spark):
    with pytest.raises(ValueError):
        baselines.plane_grid(frame(spark, [(1, 2, 3)], 3), ClusterSpec(5, 2))


def test_invalid_rows_are_rejected_and_constants_become_zero(spark):
    df = spark.createDataFrame([(1, 1.0, 5.0), (2, None, 5.0), (3, float("nan"), 5.0), (4, float("inf"), 5.0), (5, 3.0, 5.0)], "point_id bigint, f1 double, f2 double")
    assert sorted((r.point_id, r.x1, r.x2) for r in points.normalise(df).collect()) == [(1, 0, 0), (5, 100_000, 0)]
    with pytest.raises(ValueError):
        points.normalise(df, on_invalid="fail")


def test_exact_cells_at_edges(spark):
    for d, eps in ((1, 7), (2, 10), (4, 6), (3, 1000)):
        t = np.unique(np.r_[np.arange(0, 4 * eps), np.arange(99_000, 99_050)])
        ps = frame(spark, [[v] * d for v in t], d)
        placed = cells.assign_cells(ps, eps, at=[0] * d).collect()
        for r in placed:
            k, v = r.k1, r.x1
            assert k * k * eps * eps <= v * v * d < (k + 1) ** 2 * eps * eps


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, v) for v in range(101, 160)] + [(200, 200), (159, 300)]
    found = {r.vertex: r.component for r in star_components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert {found[v] for v in range(41)} == {0} and {found[v] for v in (100, 130, 159, 300)} == {100} and 200 not in found


def test_rand_of_equal_and_split_labels(spark):
    a = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 3)], "point_id bigint, cluster_id bigint")
    b = spark.createDataFrame([(1, 1), (2, 2), (3, 3), (4, 3)], "point_id bigint, cluster_id bigint")
    assert measures.rand_scores(a, a).first().rand == 1.0
    assert abs(measures.rand_scores(a, b).first().rand - 5 / 6) < 1e-9


def test_round_trips(spark, tmp_path):
    ps = generators.gen_walk(spark, 200, 2)
    for fmt in ("parquet", "orc", "json", "csv"):
        ps.write.format(fmt).save(str(tmp_path / fmt))
        assert sorted(map(tuple, tables.points(spark, str(tmp_path / fmt), fmt, 2).collect())) == sorted(map(tuple, ps.collect()))
    placed = cells.assign_cells(ps, 1000)
    tables.save_cells(placed, str(tmp_path / "cells"))
    assert tables.load_cells(spark, str(tmp_path / "cells")).count() == 200
    tables.write(placed.withColumn("b", F.col("k1") % 3), str(tmp_path / "by"), by=["b"])
    assert spark.read.parquet(str(tmp_path / "by")).count() == 200
    spark.dataSource.register(generators.PointSource)
    assert spark.read.format("cell_points").option("n", 50).option("d", 3).load().count() == 50


def test_gap_udf(spark):
    df = spark.createDataFrame([([[0, 0]], [[3, 4]], 5), ([[0, 0]], [[3, 5]], 5)], "a array<array<bigint>>, b array<array<bigint>>, eps bigint")
    assert [r.v.yes for r in df.select(gap_verdict("a", "b", "eps").alias("v")).collect()] == [True, False]


def _duck(sql):
    import duckdb

    c = duckdb.connect()
    for t in tables.NAMES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    r = c.execute(sql)
    return [x[0] for x in r.description], r.fetchall()


@pytest.mark.parametrize("name", ["membership_part", "cell_exact_ldf_events", "neighbours_part_prefix", "neighbours_part_rtree", "merge_edges_part", "eps_join_semi", "knn_supp_cust", "asof_events", "generator_varied_3d", "levels_part", "udtf_density_cluster", "events_session"])
def test_against_duckdb(spark, name):
    df = registry.QUERIES[name](spark, DATA)
    cols, data = _duck(registry.ORACLES[name])
    assert sorted(df.columns) == sorted(cols)
    order = sorted(cols)
    assert sorted(repr([r[c] for c in order]) for r in df.collect()) == sorted(repr([r[cols.index(c)] for c in order]) for r in data)


def test_statements_find_nothing(spark):
    for name in ("axioms_part", "sandwich_rho_part", "sandwich_delta_part", "cell_order_events", "kappa_events"):
        assert registry.QUERIES[name](spark, DATA).first().violations == 0


def _stream(spark, tmp_path, df, parts=3):
    for k in range(parts):
        df.where(F.pmod(F.col("point_id"), F.lit(parts)) == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return tables.stream(spark, str(tmp_path / "in"), df.schema, 1)


def test_incremental_cores_equal_the_batch(spark, tmp_path):
    ps = generators.gen_walk(spark, 120, 2, clusters=3, radius=2000, stride=100)
    spec = ClusterSpec(2500, 5)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    q = events.incremental_core(_stream(spark, tmp_path, ps), spec, 30_000).writeStream.format("memory").queryName("cores").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.point_id for r in spark.table("cores").collect()}
    assert got == {r[0] for r in rows(cluster.cell_exact(ps, spec).membership) if r[2] == "core"}


def test_cluster_each_batch_and_windows(spark, tmp_path):
    ps = spark.range(60).selectExpr("id AS point_id", "double(id % 10) AS f1", "double(id % 7) AS f2")
    out = []
    q = events.stream_cluster(_stream(spark, tmp_path, ps, 2), ClusterSpec(30_000, 3), [(0.0, 10.0), (0.0, 7.0)], lambda df, n: out.append(df.count()), str(tmp_path / "c"))
    q.awaitTermination()
    assert sum(out) >= 60 and len(out) == 2
    schema = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType())])
    spark.sql("SELECT 1L AS event_id, TIMESTAMP'2024-01-01 00:10:00' AS ts, 'a' AS event_type, 1.0D AS value UNION ALL SELECT 1L, TIMESTAMP'2024-01-01 00:10:00', 'a', 1.0D UNION ALL SELECT 2L, TIMESTAMP'2024-01-01 00:50:00', 'a', 2.0D").write.parquet(str(tmp_path / "e"))
    stream = events.dedupe(events.with_lateness(tables.stream(spark, str(tmp_path / "e"), schema)), "event_id")
    q = events.windowed_counts(stream, "1 hour").writeStream.format("memory").queryName("w").outputMode("complete").option("checkpointLocation", str(tmp_path / "w")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert [r.n for r in spark.table("w").collect()] == [2]
