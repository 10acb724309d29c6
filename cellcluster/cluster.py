"""Exact density clustering on cells, and its variants.

cell_exact       cells, prefix tree, core points, gap tests as a graph search over core cells meets them
cell_exact_ldf   the same with cells of few core points first, so more pairs are already joined
cell_delta       gap tests that may answer yes up to eps + slack
hash_grid_exact  cells that are only hashed, neighbours by template, the same exact gap test
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import blocks
from .cells import assign_cells
from .components import durable, star_components
from .spec import ClusterSpec, dims, ks, xs


@dataclass
class ClusterResult:
    """membership (point_id, cluster_id, role: a border point has a row for each cluster it belongs to), flagged points, counters."""

    membership: DataFrame
    flagged: DataFrame
    counters: DataFrame
    plan: blocks.BlockPlan | None = None
    eps: int = 0

    tests: DataFrame | None = None

    def labels(self, rule: str = "min_cluster") -> DataFrame:
        """One label a point: of several clusters of a border point the smallest, or that of the nearest core point (``nearest_core``; of ties the smallest)."""
        role = self.membership.groupBy("point_id").agg(F.min("cluster_id").alias("cluster_id"), F.first("role").alias("role"), F.count(F.lit(1)).alias("n"))
        if rule == "min_cluster":
            return role.drop("n")
        if rule != "nearest_core":
            raise ValueError("the rule is min_cluster or nearest_core")
        # only border points of several clusters have a choice
        d = dims(self.flagged)
        several = role.where("n > 1").select("point_id").join(self.flagged.select("point_id", *xs(d)), "point_id")
        core = self.membership.where("role = 'core'").join(self.flagged.select(F.col("point_id").alias("id"), *[F.col(x).alias(f"y_{x}") for x in xs(d)]), F.col("point_id") == F.col("id"))
        core = core.select(*[f"y_{x}" for x in xs(d)], F.col("cluster_id").alias("own"))
        near = within(several, core, self.eps).groupBy("point_id").agg(F.min(F.struct("sq", "own")).alias("m")).select(F.col("point_id").alias("id"), F.col("m.own").alias("own"))
        return role.join(near, F.col("point_id") == F.col("id"), "left").select("point_id", F.coalesce("own", "cluster_id").alias("cluster_id"), "role")

    def merge_profile(self) -> DataFrame:
        """Gap tests done and left out, most iterations, distances, and points pruned by rule."""
        return self.counters.agg(F.sum("checks").alias("checks"), F.sum("skipped").alias("skipped"), F.max("kappa").alias("kappa"), F.sum("distances").alias("distances"), F.sum("pruned_triangle").alias("pruned_triangle"), F.sum("pruned_angle").alias("pruned_angle"))

    def kappa_profile(self) -> DataFrame:
        """Iterations, distances and pruned points of each pair of cells (a, b) that was tested; for runs with ``trace``."""
        if self.tests is None:
            raise ValueError("run with trace=True")
        return self.tests.select("a", "b", "kappa", "distances", "pruned_triangle", "pruned_angle")


def square(d: int, a: str = "", b: str = "y_") -> Column:
    """Squared distance of x1, ... with one prefix to those with another."""
    diff = [F.col(f"{a}x{j}") - F.col(f"{b}x{j}") for j in range(1, d + 1)]
    return reduce(lambda s, t: s + t, [e * e for e in diff])


def within(left: DataFrame, right: DataFrame, eps: int, tasks: int = 0) -> DataFrame:
    """Rows of ``left`` (x1, ...) and ``right`` (y_x1, ...) at most eps apart, with the squared distance sq: an equality join on bins of eps in up to three dimensions.

    With ``tasks`` bins are dealt over so many partitions, or those of a shuffle if these are more, and not merged for their few bytes.
    """
    d = dims(left)
    binned = range(1, min(d, 3) + 1)
    for j in binned:
        left = left.withColumn(f"g{j}", F.floor(F.col(f"x{j}") / eps))
        right = right.withColumn(f"g{j}", F.explode(F.sequence(F.floor(F.col(f"y_x{j}") / eps) - 1, F.floor(F.col(f"y_x{j}") / eps) + 1)))
    bins = [f"g{j}" for j in binned]
    if tasks:
        tasks = max(tasks, int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")))
        left, right = left.repartition(tasks, *bins), right.repartition(tasks, *bins)
    both = left.join(right, bins).withColumn("sq", square(d))
    return both.where(F.col("sq") <= eps * eps).drop(*bins)


def mark_core(ps: DataFrame, spec: ClusterSpec, plan: blocks.BlockPlan | None = None, tree: str = "prefix", at: list[int] | None = None) -> tuple[DataFrame, blocks.BlockPlan]:
    """Points with cells and is_core: one exchange with a halo, one kernel a block. A column ``weight`` of ``ps`` counts as so many points."""
    d = dims(ps)
    weight = ["weight"] if "weight" in ps.columns else []
    placed = assign_cells(ps.select("point_id", *xs(d), *weight), spec.eps, at=at)
    plan = blocks.plan_blocks(placed, spec) if plan is None else plan
    return blocks.to_blocks(placed, plan).groupBy("block").applyInArrow(blocks.core_kernel(spec, d, tree), blocks.core_schema(d)), plan


def finish(flagged: DataFrame, edges: DataFrame, border: DataFrame, cell: str = "cell") -> DataFrame:
    """Membership from core points (flagged: point_id, cell, is_core), edges (a, b) between cells, and border (point_id, cell)."""
    core = flagged.where("is_core").select("point_id", F.col(cell).alias("cell"))
    found = star_components(edges.select("a", "b"))
    cells = core.groupBy("cell").agg(F.min("point_id").alias("least")).join(found.withColumnRenamed("vertex", "cell"), "cell", "left")
    cells = cells.withColumn("component", F.coalesce("component", "cell"))
    ids = cells.groupBy("component").agg(F.min("least").alias("cluster_id"))
    named = cells.join(ids, "component").select("cell", "cluster_id")
    inside = core.join(named, "cell").select("point_id", "cluster_id", F.lit("core").alias("role"))
    edge = border.join(named, "cell").select("point_id", "cluster_id", F.lit("border").alias("role")).distinct()
    # most points may be border points, so their ids are not broadcast
    noise = flagged.where("NOT is_core").join(border.select("point_id").distinct().hint("merge"), "point_id", "left_anti").select("point_id", F.lit(None).cast("bigint").alias("cluster_id"), F.lit("noise").alias("role"))
    return inside.unionByName(edge).unionByName(noise)


def run(ps: DataFrame, spec: ClusterSpec, gap: str = "alternating_prune", order: str = "graph", boxes: bool = True, slack: float = 0, rho: float = 0, tree: str = "prefix", plan: blocks.BlockPlan | None = None, trace: bool = False) -> ClusterResult:
    d = dims(ps)
    flagged, plan = mark_core(ps, spec, plan, tree)
    flagged = durable(flagged)
    # halo points that are no core are of no use to another block
    dealt = blocks.to_blocks(flagged.select("point_id", *xs(d), *ks(d), "is_core"), plan).where("is_core OR home")
    found = durable(dealt.groupBy("block").applyInArrow(blocks.merge_kernel(spec, d, gap, order, boxes, slack, rho, tree, trace), blocks.LINKS))
    marked = flagged.withColumn("cell", F.concat_ws(",", *ks(d)))
    membership = finish(marked, found.where("kind = 'edge'"), found.where("kind = 'border'").select("point_id", F.col("a").alias("cell")))
    return ClusterResult(membership, marked, found.where("kind = 'counters'"), plan, spec.eps, found.where("kind = 'test'") if trace else None)


def cell_exact(ps: DataFrame, spec: ClusterSpec, **how) -> ClusterResult:
    return run(ps, spec, **how)


def cell_exact_ldf(ps: DataFrame, spec: ClusterSpec, **how) -> ClusterResult:
    return run(ps, spec, order="sparse_first", **how)


def cell_delta(ps: DataFrame, spec: ClusterSpec, slack: float, **how) -> ClusterResult:
    return run(ps, spec, slack=slack, **how)
