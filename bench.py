"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from cellcluster import baselines, cells, cluster, fixtures, neighbours  # noqa: E402
from cellcluster.sources.generators import gen_walk  # noqa: E402
from cellcluster.sources.tables import noop  # noqa: E402
from cellcluster.spec import ClusterSpec  # noqa: E402


def headline(spark: SparkSession, sf_dir: str) -> dict:
    """Name to a function that makes the result; the workloads of the reference at a size for one machine."""
    ps = lambda name: fixtures.points(spark, sf_dir, name)
    walk = lambda n, d, kind: gen_walk(spark, n, d, kind=kind)
    cell = lambda name: cells.assign_cells(ps(name), fixtures.SETS[name].eps)
    return {
        "normalise_events": lambda: ps("events"),
        "cell_table_events": lambda: cells.cell_summary(cell("events")),
        "neighbours_prefix_tree_line5": lambda: neighbours.by_block(cell("line5")),
        "neighbours_rect_tree_line5": lambda: neighbours.by_block(cell("line5"), tree="rect"),
        "cell_exact_events": lambda: cluster.cell_exact(ps("events"), ClusterSpec(1000, 40)).membership,
        "cell_exact_ldf_events": lambda: cluster.cell_exact_ldf(ps("events"), ClusterSpec(1000, 40)).membership,
        "plane_grid_events": lambda: baselines.plane_grid(ps("events"), ClusterSpec(1000, 40)).membership,
        "planar_front_events": lambda: baselines.planar_front(ps("events"), ClusterSpec(1000, 40)).membership,
        "cell_exact_line3": lambda: cluster.cell_exact(ps("line3"), ClusterSpec(500, 20)).membership,
        "cell_exact_walk_2d_200k": lambda: cluster.cell_exact(walk(200_000, 2, "even"), ClusterSpec(500, 20)).membership,
        "cell_exact_walk_2d_2m": lambda: cluster.cell_exact(walk(2_000_000, 2, "even"), ClusterSpec(500, 20)).membership,
        "cell_exact_ldf_walk_7d_100k": lambda: cluster.cell_exact_ldf(walk(100_000, 7, "varied"), ClusterSpec(2000, 20)).membership,
        "cell_exact_walk_7d_100k": lambda: cluster.cell_exact(walk(100_000, 7, "varied"), ClusterSpec(2000, 20)).membership,
        "grid_closest_pair_walk_7d_100k": lambda: baselines.grid_bcp(walk(100_000, 7, "varied"), ClusterSpec(2000, 20)).membership,
        "rho_grid_events": lambda: baselines.rho_grid(ps("events"), ClusterSpec(1000, 40), 0.01).membership,
        "ball_block_part": lambda: baselines.ball_block(ps("part"), ClusterSpec(1000, 10)).membership,
        "ball_block_exact_part": lambda: baselines.ball_block_exact(ps("part"), ClusterSpec(1000, 10)).membership,
    }


def walk_(spark: SparkSession):
    return gen_walk(spark, 1000, 2)


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    root = os.path.dirname(os.path.abspath(__file__))
    os.environ["PYTHONPATH"] = os.pathsep.join([root, os.environ.get("PYTHONPATH", "")])
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries = headline(spark, sf_dir)
    only = sys.argv[1:]
    times = {}
    # the first workers and plans of each kind are not timed
    noop(cluster.cell_exact(walk_(spark), ClusterSpec(1000, 10)).membership)
    noop(baselines.ball_block_exact(walk_(spark), ClusterSpec(1000, 10)).membership)
    for name, make in queries.items():
        if only and name not in only:
            continue
        at = time.perf_counter()
        noop(make())
        times[name] = round(time.perf_counter() - at, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
