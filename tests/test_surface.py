"""The surface around the methods: streams with late and expiring rows, joins of streams, restarts, functions, sinks, measures."""

import numpy as np
from pyspark.sql import functions as F

from cellcluster import cells, cluster, measures, neighbours
from cellcluster.components import star_components
from cellcluster.functions.surface import register_functions, set_radius
from cellcluster.prefixtree import PrefixTree
from cellcluster.sources import generators, tables
from cellcluster.spec import ClusterSpec
from cellcluster.streaming import events

SCHEMA = "event_id bigint, ts timestamp, user_id bigint, x1 bigint, x2 bigint"


def batch(spark, path, rows, name):
    spark.createDataFrame(rows, SCHEMA.replace("timestamp", "string")).withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(str(path / name))


def streamed(spark, path, max_files=1):
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", max_files).parquet(str(path))


def run(df, name, where, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(where)).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_star_rounds_and_one_task_agree(spark):
    r = np.random.default_rng(2)
    edges = spark.createDataFrame([(int(a), int(b)) for a, b in r.integers(0, 300, (220, 2))] + [(0, k) for k in range(500, 700)], "a bigint, b bigint")
    assert {tuple(x) for x in star_components(edges, few=0).collect()} == {tuple(x) for x in star_components(edges).collect()}
    names = edges.select(F.col("a").cast("string"), F.col("b").cast("string"))
    assert {tuple(x) for x in star_components(names, few=0).collect()} == {tuple(x) for x in star_components(names).collect()}


def test_expiry_late_rows_and_restart(spark, tmp_path):
    src = tmp_path / "in"
    batch(spark, src, [(1, "2024-01-01 00:10:00", 1, 5, 5), (2, "2024-01-01 06:00:00", 1, 5, 5)], "a")
    made = lambda: events.expiring_cells(streamed(spark, src / "*"), 100, "2 hours", "2 hours", "1 hour").withColumn("start", F.unix_seconds("start"))
    go = lambda: made().writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    go().awaitTermination()
    # the same checkpoint goes on where it stopped; this row is behind the watermark
    batch(spark, src, [(3, "2024-01-01 00:20:00", 1, 5, 5), (4, "2024-01-01 12:00:00", 1, 5, 5)], "b")
    q = go()
    q.awaitTermination()
    assert events.late_rows(q) == 1
    got = {(r.start, r.n_pts) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    day = 1704067200
    assert (day, 1) in got and (day + 6 * 3600, 1) in got and not any(n > 1 for _, n in got)


def test_joins_of_streams(spark, tmp_path):
    batch(spark, tmp_path / "a", [(1, "2024-01-01 00:00:00", 7, 0, 0), (2, "2024-01-01 05:00:00", 7, 0, 0)], "x")
    batch(spark, tmp_path / "b", [(11, "2024-01-01 00:20:00", 7, 0, 0), (12, "2024-01-01 02:00:00", 7, 0, 0), (13, "2024-01-01 00:10:00", 8, 0, 0)], "x")
    a, b = (streamed(spark, tmp_path / n / "*").withWatermark("ts", "1 hour") for n in "ab")
    run(events.interval_stream_join(a, b, "user_id"), "joined", tmp_path / "c1")
    assert [(r.a, r.b) for r in spark.table("joined").collect()] == [(1, 11)]
    names = spark.createDataFrame([(7, "seven")], "user_id bigint, name string")
    run(events.enrich(streamed(spark, tmp_path / "b" / "*"), names, "user_id"), "named", tmp_path / "c2")
    assert {(r.event_id, r.name) for r in spark.table("named").collect()} == {(11, "seven"), (12, "seven"), (13, None)}
    placed = streamed(spark, tmp_path / "a" / "*").select(F.col("event_id").alias("point_id"), "x1", "x2")
    run(events.stream_cells(placed, 100), "cells", tmp_path / "c3", "complete")
    assert [(r.k1, r.k2, r.n_pts) for r in spark.table("cells").collect()] == [(0, 0, 2)]


def test_functions_for_sql(spark):
    register_functions(spark)
    assert spark.sql("SELECT dist2_2d(0, 0, 3, 4) AS a, cell_offset(1, 5) AS b").first().asDict() == {"a": 25, "b": 9}
    df = spark.createDataFrame([(1, 0.0, 0.0), (1, 6.0, 8.0), (2, 1.0, 1.0)], "g int, x double, y double")
    assert {r.g: r.r for r in df.groupBy("g").agg(set_radius("x", "y").alias("r")).collect()} == {1: 5.0, 2: 0.0}


def test_bucketed_sink_and_choice_of_strategy(spark):
    df = cells.assign_cells(generators.gen_walk(spark, 300, 2), 2000)
    tables.write_bucketed(df, "bucketed_cells", ["k1", "k2"], 4)
    assert spark.table("bucketed_cells").count() == 300
    assert neighbours.choose(df.select("k1", "k2").distinct()) == "template" and neighbours.choose(df.select("k1", "k2").distinct(), 10) == "broadcast"
    spark.sql("DROP TABLE bucketed_cells")


def test_scan_of_small_nodes_and_jump_tables():
    r = np.random.default_rng(4)
    keys = np.unique(r.integers(0, 12, (200, 3)), axis=0)
    tree = PrefixTree(keys)
    one, other = tree.query(keys, 2), tree.query(keys, 2, mode="scan", fanout=5)
    assert all((a == b).all() for a, b in zip(one, other, strict=True))
    first = keys[:, 0]
    assert tree.jump_table(0, 0, 2, 14) == {k: int(min(v for v in first if k - 2 <= v)) for k in range(15) if any(k - 2 <= v <= k + 2 for v in first)}


def test_measures_of_a_run(spark):
    ps, spec = generators.gen_walk(spark, 400, 2), ClusterSpec(2000, 5)
    times = measures.step_times(ps, spec)
    assert set(times) == {"cells", "neighbours", "core", "whole", "merge"} and times["whole"] > 0
    bytes_ = measures.shuffled(spark, lambda: cluster.mark_core(ps, spec)[0])
    assert bytes_["stages"] > 0 and bytes_["shuffle_written"] > 0 and bytes_["spilled"] == 0
