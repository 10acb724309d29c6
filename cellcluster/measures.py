"""What is measured: times, counts, agreement of results, grid and index profiles, axioms."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .baselines import members, near_places
from .blocks import plan_blocks, to_blocks
from .cells import assign_cells, cell_summary, extent
from .cluster import ClusterResult, mark_core, run
from .components import durable
from .neighbours import build_levels, by_block, neighbour_cells
from .points import collapse_duplicates
from .sources.tables import noop
from .spec import ClusterSpec, dims, ks


def timed(make, repeats: int = 1, warm: bool = False) -> float:
    """Median seconds of a run into a sink that writes nothing."""
    if warm:
        noop(make())
    out = []
    for _ in range(repeats):
        at = time.perf_counter()
        noop(make())
        out.append(time.perf_counter() - at)
    return median(out)


def speedup(slow: float, fast: float) -> float:
    return slow / fast


def block_load(ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """For each block its home points and the copies that its halo brings: what a task holds, and what is shuffled beyond the points themselves.

    A row with a column ``weight`` stands for so many home points; ``rows`` has the home rows.
    """
    placed = assign_cells(ps, spec.eps)
    dealt = to_blocks(placed, plan_blocks(placed, spec))
    home = F.sum(F.when(F.col("home"), F.col("weight")).otherwise(0)) if "weight" in ps.columns else F.count_if("home")
    return dealt.groupBy("block").agg(home.alias("home"), F.count_if(~F.col("home")).alias("copies"), F.count_if("home").alias("rows"))


def step_times(ps: DataFrame, spec: ClusterSpec, tree: str = "prefix") -> dict[str, float]:
    """Seconds of the steps of a run, each into a sink that writes nothing: cells, neighbour query, core points, merge and borders."""
    placed = durable(assign_cells(ps, spec.eps))
    out = {"cells": timed(lambda: cell_summary(placed)), "neighbours": timed(lambda: by_block(placed, tree=tree))}
    out["core"] = timed(lambda: mark_core(ps, spec, tree=tree)[0])
    out["whole"] = timed(lambda: run(ps, spec, tree=tree).membership)
    return out | {"merge": max(0.0, out["whole"] - out["core"])}


def shuffled(spark, make) -> dict[str, int]:
    """Bytes that the stages of a run wrote to shuffles, read from them and spilled, and how many stages and tasks it took, from the status store of the driver."""
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway

    def stages() -> dict:
        found = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): s for s in (found.apply(k) for k in range(found.size()))}

    before = set(stages())
    noop(make())
    new = [s for k, s in stages().items() if k not in before]
    add = lambda f: int(sum(f(s) for s in new))
    return {"stages": len(new), "tasks": add(lambda s: s.numTasks()), "shuffle_written": add(lambda s: s.shuffleWriteBytes()), "shuffle_read": add(lambda s: s.shuffleReadBytes()), "spilled": add(lambda s: s.diskBytesSpilled())}


def n_clusters(m: DataFrame) -> DataFrame:
    return m.agg(F.count_distinct("cluster_id").alias("clusters"))


def role_counts(m: DataFrame) -> DataFrame:
    """Points by role; border points of several clusters beside."""
    each = m.groupBy("point_id", "role").agg(F.count(F.lit(1)).alias("n"))
    return each.groupBy("role").agg(F.count(F.lit(1)).alias("n_points"), F.count_if(F.col("n") > 1).alias("n_multi"))


def cluster_sizes(m: DataFrame) -> DataFrame:
    return m.where("cluster_id IS NOT NULL").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_points"), F.count_if(F.col("role") == "core").alias("n_core"))


def same_clustering(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of either membership that the other lacks; empty if they agree. Ids name the same clusters in exact results."""
    cols = ["point_id", "cluster_id", "role"]
    return a.select(cols).exceptAll(b.select(cols)).withColumn("side", F.lit("a")).unionByName(b.select(cols).exceptAll(a.select(cols)).withColumn("side", F.lit("b")))


def rand_scores(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rand and adjusted Rand index of two labelings (point_id, cluster_id), noise points as groups of one."""
    la, lb = (m.groupBy("point_id").agg(F.coalesce(F.min("cluster_id"), -F.col("point_id") - 1).alias(n)) for m, n in ((a, "ca"), (b, "cb")))
    both = la.join(lb, "point_id")
    pairs = lambda df: df.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("s"))
    cells = pairs(both.groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("n"))).withColumnRenamed("s", "both")
    rows = pairs(both.groupBy("ca").agg(F.count(F.lit(1)).alias("n"))).withColumnRenamed("s", "in_a")
    cols = pairs(both.groupBy("cb").agg(F.count(F.lit(1)).alias("n"))).withColumnRenamed("s", "in_b")
    total = both.agg((F.count(F.lit(1)) * (F.count(F.lit(1)) - 1) / 2).alias("total"))
    one = cells.crossJoin(rows).crossJoin(cols).crossJoin(total)  # four one-row tables
    expected = F.col("in_a") * F.col("in_b") / F.col("total")
    return one.select(((F.col("total") + 2 * F.col("both") - F.col("in_a") - F.col("in_b")) / F.col("total")).alias("rand"), F.when((F.col("in_a") + F.col("in_b")) / 2 == expected, 1.0).otherwise((F.col("both") - expected) / ((F.col("in_a") + F.col("in_b")) / 2 - expected)).alias("adjusted_rand"))


def grid_profile(cells: DataFrame, method: str = "block") -> DataFrame:
    """Non-empty cells, largest identifier, points a cell, neighbours a cell."""
    d = dims(cells)
    summary = cell_summary(cells)
    near = neighbour_cells(summary.select(*ks(d)), method).groupBy(*ks(d)).agg(F.count(F.lit(1)).alias("n_nbr"))
    return summary.join(near, ks(d), "left").agg(F.count(F.lit(1)).alias("cells"), F.lit(extent(cells)).alias("eta"), F.avg("n_pts").alias("mean_points"), F.max("n_pts").alias("max_points"), F.avg(F.coalesce("n_nbr", F.lit(0))).alias("mean_nbr"), F.max(F.coalesce("n_nbr", F.lit(0))).alias("max_nbr"))


def index_profile(cells: DataFrame, fanout: int) -> DataFrame:
    """Nodes of each level of the prefix tree, and children of nodes beyond the fan-out (what the jump tables index)."""
    levels = build_levels(cells)
    out = None
    for j, level in enumerate(levels, 1):
        parents = level.groupBy(*ks(j - 1)).agg(F.count(F.lit(1)).alias("n")) if j > 1 else level.agg(F.count(F.lit(1)).alias("n"))
        row = parents.agg(F.lit(j).alias("level"), F.sum("n").alias("nodes"), F.coalesce(F.sum(F.when(F.col("n") > fanout, F.col("n"))), F.lit(0)).alias("indexed"))
        out = row if out is None else out.unionByName(row)
    return out


def check_axioms(result: ClusterResult, ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """Violations of the definitions: core points within eps in different clusters, members that no core point of their cluster reaches, reachable points left out."""
    at = durable(collapse_duplicates(ps))
    m = durable(result.membership.join(members(ps, at), "point_id"))
    # points of one place have the same neighbours, so places are compared; a place stands for its points of one cluster
    core = m.where("role = 'core'").groupBy(F.col("place").alias("i"), F.col("cluster_id").alias("ci")).agg(F.min("point_id").alias("p"))
    near = near_places(at, spec.eps).select("i", "j").join(core, "i")
    split = near.join(core.select(F.col("i").alias("j"), F.col("ci").alias("cj"), F.col("p").alias("q")), "j").where("ci <> cj").select(F.lit("split").alias("violation"), F.col("p").alias("i"), F.col("q").alias("j"))
    owed = durable(near.select(F.col("j").alias("place"), F.col("ci").alias("cluster_id")).distinct())
    held = m.select("place", "point_id", "cluster_id")
    missing = owed.join(members(ps, at), "place").join(held, ["point_id", "cluster_id"], "left_anti").select(F.lit("left out").alias("violation"), F.col("cluster_id").alias("i"), F.col("point_id").alias("j"))
    alone = held.where("cluster_id IS NOT NULL").join(owed, ["place", "cluster_id"], "left_anti").select(F.lit("unreached").alias("violation"), F.col("cluster_id").alias("i"), F.col("point_id").alias("j"))
    return split.unionByName(missing).unionByName(alone)


def check_sandwich(low: ClusterResult, mid: ClusterResult, high: ClusterResult) -> DataFrame:
    """Core points together in ``low`` but apart in ``mid``, or together in ``mid`` but apart in ``high``; counted by cluster, without pairs."""
    core = lambda r, n: r.membership.where("role = 'core'").select("point_id", F.col("cluster_id").alias(n))
    a = core(low, "inner").join(core(mid, "outer"), "point_id").groupBy("inner").agg(F.count_distinct("outer").alias("n")).where("n > 1").select(F.lit("low").alias("side"), F.col("inner").alias("cluster_id"))
    b = core(mid, "inner").join(core(high, "outer"), "point_id").groupBy("inner").agg(F.count_distinct("outer").alias("n")).where("n > 1").select(F.lit("high").alias("side"), F.col("inner").alias("cluster_id"))
    return a.unionByName(b)
