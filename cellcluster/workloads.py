"""The experiment workloads: ladders of eps, min_pts and n over walks and point sets, with times and the counters that explain them.

``python -m cellcluster.workloads W1 [sf_dir]`` prints one JSON line for each run.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, cells, cluster, fixtures, gaptest, measures, merge, neighbours
from .components import durable, star_components
from .prefixtree import PrefixTree, RectTree
from .points import collapse_duplicates
from .sources.generators import gen_walk, walk_over, walk_sql
from .sources.tables import table
from .spec import ClusterSpec, dims, ks, xs

EPS = (500, 1000, 2000, 3000, 4000, 4500, 5000)
MIN_PTS = (10, 20, 40, 60, 80, 100)
N = (100_000, 500_000, 2_000_000, 10_000_000)
SCALES = ("sf0.001", "sf0.01", "sf0.1")

HIGH: dict[str, Callable[[DataFrame, ClusterSpec], cluster.ClusterResult]] = {
    "cell_exact": cluster.cell_exact, "cell_exact_ldf": cluster.cell_exact_ldf, "grid_bcp": baselines.grid_bcp,
    "rho_grid": baselines.rho_grid, "ball_block": baselines.ball_block, "ball_block_exact": baselines.ball_block_exact,
}
PLANE = {**{k: HIGH[k] for k in ("cell_exact", "cell_exact_ldf", "ball_block", "ball_block_exact")}, "planar_front": baselines.planar_front, "plane_grid": baselines.plane_grid}


def _sets(spark: SparkSession, sf_dir: str, plane: bool, real: bool, n: int) -> Iterator[tuple[str, Callable[[], DataFrame], ClusterSpec]]:
    if real:
        for name in ("events", "part", "cust", "orders") if plane else ("embed4", "line5", "line7", "docs7"):
            s = fixtures.SETS[name]
            yield name, (lambda name=name: fixtures.points(spark, sf_dir, name)), ClusterSpec(s.eps, s.min_pts)
    else:
        for d in (2,) if plane else (3, 5, 7):
            for kind in ("even", "varied"):
                yield f"walk_{d}d_{kind}", (lambda d=d, kind=kind: gen_walk(spark, n, d, kind=kind)), ClusterSpec(2000, 10)


def measured(name: str, method: str, make: Callable[[], DataFrame], spec: ClusterSpec, run: Callable) -> dict:
    at = time.perf_counter()
    result = run(make(), spec)
    roles = {r.role: r.n_points for r in measures.role_counts(result.membership).collect()}
    seconds = time.perf_counter() - at
    profile = result.merge_profile().first().asDict()
    return {"set": name, "method": method, "eps": spec.eps, "min_pts": spec.min_pts, "seconds": round(seconds, 3), "clusters": measures.n_clusters(result.membership).first()[0], **roles, **profile}


def _scaled(spark: SparkSession, sf_dir: str, plane: bool) -> Iterator[tuple[str, Callable[[], DataFrame], ClusterSpec]]:
    """Given tables at each size beside ``sf_dir``, where the ladder is one of n."""
    root = sf_dir.rstrip("/").rpartition("/")[0]
    for sf in SCALES:
        for name in ("events",) if plane else ("line3", "line5", "line7"):
            s = fixtures.SETS[name]
            yield f"{name}_{sf}", (lambda name=name, sf=sf: fixtures.points(spark, f"{root}/{sf}", name)), ClusterSpec(s.eps, s.min_pts)


def ladder(spark: SparkSession, sf_dir: str, which: str, n: int = 2_000_000) -> Iterator[dict]:
    """Rows of W1-W8: W1/W2/W4/W5 in three dimensions and more, W6/W7/W8 in the plane; eps, eps on tables, min_pts, n.

    W4, W6 and W7 take walks and tables; W5 and W8 walks of each n, then tables of each size.
    """
    plane = which in ("W6", "W7", "W8")
    methods = PLANE if plane else HIGH
    kinds = {"W1": (False,), "W2": (True,), "W5": (False,), "W8": (False,)}.get(which, (False, True))
    steps = {"W1": EPS, "W2": EPS, "W6": EPS, "W4": MIN_PTS, "W7": MIN_PTS, "W5": N, "W8": N}[which]
    for step in steps:
        for real in kinds:
            for name, make, spec in _sets(spark, sf_dir, plane, real, step if which in ("W5", "W8") else n):
                spec = ClusterSpec(step, spec.min_pts) if steps is EPS else ClusterSpec(spec.eps, step) if steps is MIN_PTS else spec
                for method, run in methods.items():
                    yield measured(name, method, make, spec, run)
    if steps is N:
        for name, make, spec in _scaled(spark, sf_dir, plane):
            for method, run in methods.items():
                yield measured(name, method, make, spec, run)


#: The exact methods that a count of the registered workloads runs.
COUNTED = {"cell_exact": cluster.cell_exact, "cell_exact_ldf": cluster.cell_exact_ldf}
#: Sizes of the registered ladders of n, and points of a walk where n is fixed.
COUNTED_N, COUNTED_WALK = (1_000, 2_000, 4_000, 8_000), 1_500


#: Tables that number the rows of walks, and their keys.
WALKED = {"supplier": "s_suppkey", "customer": "c_custkey", "events": "event_id", "orders": "o_orderkey"}


@dataclass(frozen=True)
class Run:
    """One setting of a workload: a given set, or a walk ``kind`` of ``d`` dimensions, with its parameters."""

    name: str
    eps: int
    min_pts: int
    n: int = 0
    d: int = 0
    kind: str = ""
    table: str = ""  # whose keys number the rows of a walk; without one they are counted

    @property
    def source(self) -> tuple:
        """What the points depend on; runs of one source share them."""
        return self.name, self.n, self.table

    def places(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """The places of the points, with their numbers of points as weight."""
        if not self.kind:
            return fixtures.places(spark, sf_dir, self.name)
        made = walk_over(table(spark, sf_dir, self.table), WALKED[self.table], self.n, self.d, kind=self.kind) if self.table else gen_walk(spark, self.n, self.d, kind=self.kind)
        return collapse_duplicates(made)

    def sql(self, select: str) -> str:
        d = self.d or fixtures.SETS[self.name].d
        prefix = f"p AS MATERIALIZED ({walk_sql(self.n, self.d, self.table, WALKED.get(self.table, ""), kind=self.kind)})" if self.kind else fixtures.points_sql(self.name)
        return fixtures.cluster_sql(self.eps, self.min_pts, d, prefix) + select


def settings(which: str) -> list[Run]:
    """The runs of a registered workload W1-W8, at sizes that a check by SQL can follow point by point."""
    walk = lambda d, kind, eps=2000, min_pts=10, n=COUNTED_WALK, table="": Run(f"walk_{d}d_{kind}", eps, min_pts, n, d, kind, table)
    given = lambda name, eps=0, min_pts=0: Run(name, eps or fixtures.SETS[name].eps, min_pts or fixtures.SETS[name].min_pts)
    kinds, high, plane = ("even", "varied"), ("embed4", "docs7"), ("events", "part", "cust", "orders")
    return {
        "W1": [walk(d, k, e, table="supplier") for d in (3, 5, 7) for k in kinds for e in EPS],
        "W2": [given(s, e) for s in high for e in EPS] + [given("embed4"), given("line5"), given("line5", 2000), given("line7"), given("line7", 2000)],
        "W4": [walk(d, "varied", 4500, m) for d in (3, 5, 7) for m in MIN_PTS] + [given(s, 0, m) for s in high for m in MIN_PTS],
        "W5": [walk(d, "varied", 4500, n=n) for d in (3, 5, 7) for n in COUNTED_N] + [given("line3"), given("line5"), given("line7")],
        "W6": [walk(2, k, e) for k in kinds for e in EPS] + [given(s, e) for s in ("part", "cust") for e in EPS] + [given(s, e) for s in ("events", "orders") for e in EPS[:3]],
        "W7": [walk(2, k, 2000, m) for k in kinds for m in MIN_PTS] + [given(s, 0, m) for s in plane for m in MIN_PTS],
        "W8": [walk(2, k, 1000, n=n) for k in kinds for n in COUNTED_N] + [given("events")],
    }[which]


def counted(spark: SparkSession, sf_dir: str, which: str, at_once: int = 6) -> DataFrame:
    """For each run and exact method: points, clusters, core, border and noise points. Runs share the cluster, a few at a time, and the places of their points, written once."""

    def one(job: tuple[Run, str]) -> tuple:
        run, method = job
        ps = places[run.source]
        m = COUNTED[method](ps, ClusterSpec(run.eps, run.min_pts)).membership
        # a border point has a row for each cluster, a core point one
        each = m.groupBy("point_id", "role").agg(F.min("cluster_id").alias("cluster_id")).join(ps.select("point_id", "weight"), "point_id")
        roles = [F.coalesce(F.sum(F.when(F.col("role") == r, F.col("weight"))), F.lit(0)).alias(r) for r in ("core", "border", "noise")]
        return (run.name, method, run.eps, run.min_pts, run.n, *each.agg(F.count_distinct(F.when(F.col("role") == "core", F.col("cluster_id"))).alias("clusters"), *roles).first())

    first = {r.source: r for r in settings(which)}
    with ThreadPoolExecutor(at_once) as pool:
        places = dict(zip(first, pool.map(lambda r: durable(r.places(spark, sf_dir)), first.values()), strict=True))
        rows = list(pool.map(one, [(r, m) for r in settings(which) for m in COUNTED]))
    return spark.createDataFrame(rows, "name string, method string, eps int, min_pts int, n int, clusters bigint, core bigint, border bigint, noise bigint")


def counted_sql(which: str) -> str:
    """The same rows from the definitions, point by point."""
    methods = ", ".join(f"('{m}')" for m in COUNTED)
    each = []
    for r in settings(which):
        roles = ", ".join(f"count(DISTINCT point_id) FILTER (role = '{x}') AS {x}" for x in ("core", "border", "noise"))
        head = f"'{r.name}' AS name, CAST({r.eps} AS INT) AS eps, CAST({r.min_pts} AS INT) AS min_pts, CAST({r.n} AS INT) AS n"
        each.append("SELECT * FROM (" + r.sql(f"SELECT {head}, count(DISTINCT cluster_id) AS clusters, {roles} FROM membership") + ")")
    return f"SELECT name, method, eps, min_pts, n, clusters, core, border, noise FROM ({' UNION ALL '.join(each)}), (VALUES {methods}) AS m(method)"


def kappa_rows(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("part", "cust", "docs", "pages", "conv", "embed4", "docs7", "events")) -> DataFrame:
    """W11: for each set the gap tests that took more than 11 iterations; boxes answer none beforehand."""

    def one(name: str) -> tuple:
        s = fixtures.SETS[name]
        found = cluster.cell_exact(fixtures.points(spark, sf_dir, name), ClusterSpec(s.eps, s.min_pts), boxes=False, trace=True)
        return name, found.kappa_profile().where("kappa > 11").count()

    with ThreadPoolExecutor(4) as pool:
        return spark.createDataFrame(list(pool.map(one, names)), "name string, beyond bigint")


def cluster_counts(spark: SparkSession, sf_dir: str, n: int = 3_000, kinds: tuple[str, ...] = ("even", "varied"), ladder_: tuple[int, ...] = (2000, 4500)) -> Iterator[dict]:
    """W3: clusters of the approximate and the exact block method on seven-dimensional walks over the suppliers, and how far they agree; a walk goes one step further every ``n`` / 200 of them."""
    for kind in kinds:
        for eps in ladder_:
            ps = durable(walk_over(table(spark, sf_dir, "supplier"), WALKED["supplier"], n, 7, kind=kind))
            spec = ClusterSpec(eps, 10)
            exact, near = baselines.ball_block_exact(ps, spec), baselines.ball_block(ps, spec)
            flag = cluster.cell_exact(ps, spec)
            r = measures.rand_scores(exact.membership, near.membership).first()
            yield {"kind": kind, "eps": eps, "exact": measures.n_clusters(exact.membership).first()[0], "approximate": measures.n_clusters(near.membership).first()[0], "flagship": measures.n_clusters(flag.membership).first()[0], "adjusted_rand": r.adjusted_rand}


def index_costs(own: DataFrame, block_cells: int = 60_000) -> DataFrame:
    """For each kind of tree: cells, neighbours found, nodes looked at, seconds of queries, over trees by block of cells."""
    dealt, reach = neighbours.in_blocks(own, block_cells)
    d = neighbours.cell_dims(own)

    def run(part: pa.Table) -> pa.Table:
        keys, home = neighbours.block_keys(part, d)
        asked, out = keys[home], []
        for kind, make in (("prefix", PrefixTree), ("rect", RectTree)):
            tree, at = make(keys), time.perf_counter()
            found = sum(len(tree.query(asked[k : k + 4096], reach)[0]) for k in range(0, len(asked), 4096))
            out.append({"tree": kind, "cells": len(asked), "found": found, "visited": int(tree.visited), "seconds": time.perf_counter() - at})
        return pa.Table.from_pylist(out)

    each = dealt.groupBy("block").applyInArrow(run, "tree string, cells bigint, found bigint, visited bigint, seconds double")
    return each.groupBy("tree").agg(*[F.sum(c).alias(c) for c in ("cells", "found", "visited", "seconds")])


def index_ablation(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("embed4", "line5", "line7"), ladder_: tuple[int, ...] = EPS) -> Iterator[dict]:
    """W9: neighbour queries of all cells by prefix tree and rectangle tree, a tree for each block with its halo: cells, neighbours, nodes looked at, seconds summed over blocks."""
    for name in names:
        ps = durable(fixtures.points(spark, sf_dir, name))
        d = dims(ps)
        template = len(neighbours.template(d))
        for eps in ladder_:
            for r in sorted(index_costs(durable(cells.assign_cells(ps, eps).select(*ks(d)).distinct())).collect()):
                yield {"set": name, "eps": eps, "tree": r.tree, "cells": r.cells, "mean_nbr": r.found / max(1, r.cells), "visited": r.visited, "seconds": round(r.seconds, 3), "template": template}


def merge_ablation(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("part", "events", "line3")) -> Iterator[dict]:
    """W10 and W11: gap tests done by search order and by low density, for each exact gap test, with iterations and distances.

    Neither order leaves a component of the graph of neighbouring cells, so each
    component and gap test is a task of its own and counts add up; points of a
    cell are taken in the order of their ids.
    """
    for name in names:
        s = fixtures.SETS[name]
        d = s.d
        flagged = cluster.mark_core(fixtures.points(spark, sf_dir, name), ClusterSpec(s.eps, s.min_pts))[0]
        core = durable(flagged.where("is_core").select("point_id", *xs(d), *ks(d)).withColumn("cell", F.concat_ws(",", *ks(d))))
        near = neighbours.neighbour_cells(core.select(*ks(d)).distinct(), "block")
        links = near.select(F.concat_ws(",", *ks(d)).alias("a"), F.concat_ws(",", *[f"n{j}" for j in range(1, d + 1)]).alias("b"))
        found = star_components(links)
        gaps = [g for g in gaptest.EXACT if g != "planar_front" or d == 2]
        dealt = core.join(found.hint("merge"), F.col("cell") == F.col("vertex"), "left").select("point_id", *xs(d), *ks(d), F.coalesce("component", "cell").alias("component"))
        dealt = durable(dealt).withColumn("gap", F.explode(F.array(*map(F.lit, gaps))))
        each = dealt.groupBy("component", "gap").applyInArrow(_merge_orders(d, s.eps), "turn string, gap string, components bigint, checks bigint, repeats bigint, kappa bigint, distances bigint")
        total = each.groupBy("turn", "gap").agg(*[f(c).alias(c) for c, f in (("components", F.sum), ("checks", F.sum), ("repeats", F.sum), ("kappa", F.max), ("distances", F.sum))])
        got = {(r.turn, r.gap): r.asDict() for r in total.collect()}  # a row an order and gap test
        for order in MERGE_ORDERS:
            for gap in gaps:
                r = got.get((order, gap), dict.fromkeys(("components", "checks", "repeats", "kappa", "distances"), 0))
                more = {"repeats": r["repeats"]} if order == "sparse_first" else {}
                yield {"set": name, "order": order, "gap": gap, "components": r["components"], "checks": r["checks"], **more, "kappa": r["kappa"], "distances": r["distances"]}


MERGE_ORDERS = {"search": merge.merge_search, "sparse_first": merge.merge_sparse_first}


def _merge_orders(d: int, eps: int) -> Callable[[pa.Table], pa.Table]:
    """Counters of both orders over the core points of a component of neighbouring cells."""

    def run(part: pa.Table) -> pa.Table:
        part, gap = part.sort_by("point_id"), part.column("gap")[0].as_py()
        matrix = lambda names: np.stack([part.column(c).to_numpy() for c in names], axis=1).astype(np.int64)
        x = matrix(xs(d))
        grid, own = np.unique(matrix(ks(d)), axis=0, return_inverse=True)
        order = np.argsort(own.ravel(), kind="stable")
        groups = np.split(x[order], np.cumsum(np.bincount(own.ravel()))[:-1])
        q, o, _ = PrefixTree(grid).query(grid, ClusterSpec(1, 1).reach(d))
        at = np.argsort(q, kind="stable")
        near = np.split(o[at], np.cumsum(np.bincount(q, minlength=len(grid)))[:-1])
        rows_ = []
        for turn, merged in MERGE_ORDERS.items():
            label, count = merged(groups, near, eps, gaptest.TESTS[gap])
            rows_.append({"turn": turn, "gap": gap, "components": len(set(label)), "repeats": 0, **count})
        return pa.Table.from_pylist([{k: r[k] for k in ("turn", "gap", "components", "checks", "repeats", "kappa", "distances")} for r in rows_])

    return run


def rows(spark: SparkSession, sf_dir: str, which: str) -> Iterator[dict]:
    if which == "W3":
        return cluster_counts(spark, sf_dir)
    if which == "W9":
        return index_ablation(spark, sf_dir)
    if which in ("W10", "W11"):
        return merge_ablation(spark, sf_dir)
    return ladder(spark, sf_dir, which)


def main() -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").getOrCreate()
    for row in rows(spark, sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01", sys.argv[1]):
        print(json.dumps(row, default=int), flush=True)


if __name__ == "__main__":
    main()
