"""Methods to compare with: point by point, grids in the plane and in more dimensions, approximate counts, ball blocks."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import blocks, gaptest
from .cells import assign_cells
from .cluster import ClusterResult, finish, mark_core, run, square, within
from .components import durable, star_components, task_forest
from .operators.joins import DEALT, PACK, dealt_lists, packed_join, packs, unfold
from .points import collapse_duplicates
from .spec import ClusterSpec, dims, ks, xs


def eps_pairs(ps: DataFrame, eps: int, how: str = "cell") -> DataFrame:
    """(i, j) within eps, each point with itself. ``theta`` compares all pairs of places (small data only), ``cell`` joins cells of side eps.

    Points of one place have the same neighbours, so places are compared with
    the lists of their points at hand, and pairs of lists are unfolded last.
    """
    at = durable(packs(ps, xs(dims(ps)), "point_id", "ids"))
    return _pairs(at, at, eps, how, "i", "j")


def _pairs(left: DataFrame, right: DataFrame, eps: int, how: str, a: str, b: str) -> DataFrame:
    """The ids of places (x1, ..., ids) within eps, of ``left`` as ``a`` and of ``right`` as ``b``."""
    d = dims(left)
    right = right.select(F.col("ids").alias("y_ids"), *[F.col(x).alias(f"y_{x}") for x in xs(d)])
    return unfold(_near(left.select("ids", *xs(d)), right, eps, how), ("ids", a), ("y_ids", b))


def _near(left: DataFrame, right: DataFrame, eps: int, how: str) -> DataFrame:
    """Rows within eps. The copies that look for their bins are never broadcast; bins are dealt over a fixed number of tasks, as few bytes may unfold to many rows."""
    return _theta(left, right, eps) if how == "theta" else within(left, right.hint("merge"), eps, DEALT // 4)


def _theta(left: DataFrame, right: DataFrame, eps: int) -> DataFrame:
    """Rows within eps, every one compared with every other, as lists: pairs of lists whose boxes are within eps meet and are unfolded in the task that finds them."""
    d = dims(left)
    a, b = _listed(left, eps, xs(d), "a"), _listed(right, eps, [f"y_{x}" for x in xs(d)], "b")
    gap = [F.greatest(F.col(f"lo_a{j}") - F.col(f"hi_b{j}"), F.col(f"lo_b{j}") - F.col(f"hi_a{j}"), F.lit(0)) for j in range(1, d + 1)]
    both = a.repartition(DEALT // 4).join(b.repartition(4), reduce(lambda s, t: s + t, [e * e for e in gap]) <= eps * eps)
    rows = both.select(F.explode("rows_a").alias("a"), "rows_b").select("a.*", F.explode("rows_b").alias("b")).select(*left.columns, "b.*")
    return rows.where(square(d) <= eps * eps)


def _listed(df: DataFrame, eps: int, at: list[str], tag: str) -> DataFrame:
    """The rows in lists of neighbours, as rows_``tag``, and the box of each list: slabs of eps, cut in the order of the coordinates."""
    slabs = df.withColumn("__slab", F.floor(F.col(at[0]) / eps))
    turn = F.row_number().over(W.partitionBy("__slab").orderBy(*at[1:], at[0]))
    box = [f(x).alias(f"{n}_{tag}{j}") for j, x in enumerate(at, 1) for n, f in (("lo", F.min), ("hi", F.max))]
    return slabs.withColumn("__no", F.floor((turn - 1) / PACK)).groupBy("__slab", "__no").agg(F.collect_list(F.struct(*df.columns)).alias(f"rows_{tag}"), *box).drop("__slab", "__no")


def near_places(at: DataFrame, eps: int, how: str = "cell") -> DataFrame:
    """(i, j, weight) of places within eps, each with itself; the weight is that of j."""
    left = at.select(F.col("point_id").alias("i"), *xs(dims(at)))
    return _near(left, _others(at, "j", "weight"), eps, how).select("i", "j", "weight")


def members(ps: DataFrame, at: DataFrame) -> DataFrame:
    """(point_id, place) of all points; plans take few columns of many rows for small, so neither side is broadcast."""
    d = dims(ps)
    return ps.select("point_id", *xs(d)).join(at.select(F.col("point_id").alias("place"), *xs(d)).hint("merge"), xs(d)).select("point_id", "place")


def _spread(ps: DataFrame, at: DataFrame, df: DataFrame, *names: str) -> DataFrame:
    """``df`` with the points of a place for the place itself, in each of the columns."""
    own = members(ps, at)
    for name in names:
        df = df.withColumnRenamed(name, "__at").join(own.select(F.col("place").alias("__at"), F.col("point_id").alias(name)).hint("merge"), "__at").drop("__at")
    return df


def _core_places(near: DataFrame, min_pts: int) -> DataFrame:
    return near.groupBy("i").agg(F.sum("weight").alias("n")).where(F.col("n") >= min_pts)


def _others(ps: DataFrame, name: str, *more: str) -> DataFrame:
    return ps.select(F.col("point_id").alias(name), *more, *[F.col(x).alias(f"y_{x}") for x in xs(dims(ps))])


def direct_reach(ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """(p, q): q is directly reachable from the core point p. Places of core points meet all places with the lists of their points at hand."""
    d = dims(ps)
    packed = durable(packs(ps, xs(d), "point_id", "ids"))
    at = durable(packed.groupBy(*xs(d)).agg(F.min(F.element_at("ids", 1)).alias("point_id"), F.sum(F.size("ids")).alias("weight")))
    core = at.join(_core_places(near_places(at, spec.eps), spec.min_pts).select(F.col("i").alias("point_id")).hint("merge"), "point_id", "left_semi").select(*xs(d))
    return _pairs(durable(packed.join(core.hint("merge"), xs(d), "left_semi")), packed, spec.eps, "cell", "p", "q")


def _direct(at: DataFrame, spec: ClusterSpec) -> DataFrame:
    near = near_places(at, spec.eps)
    return near.join(_core_places(near, spec.min_pts).select("i"), "i", "left_semi").select(F.col("i").alias("p"), F.col("j").alias("q"))


def _reached(at: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, DataFrame]:
    """(p, component) of the core places, and the (component, q) of places that a component reaches."""
    direct = durable(_direct(at, spec))
    core = direct.select(F.col("p").alias("vertex")).distinct()
    links = direct.join(core, direct["q"] == core["vertex"], "left_semi").where("p < q").select(F.col("p").alias("a"), F.col("q").alias("b"))
    found = star_components(task_forest(links))
    part = durable(core.join(found, "vertex", "left").select(F.col("vertex").alias("p"), F.coalesce("component", "vertex").alias("component")))
    return part, direct.join(part, "p").select("component", "q").distinct()


def reach_closure(ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """(p, q): q is reachable from p over any number of direct steps; every core point reaches what its component does."""
    at = durable(collapse_duplicates(ps))
    part, reached = _reached(at, spec)
    return packed_join(_spread(ps, at, part, "p"), _spread(ps, at, reached, "q"), ["component"], "p", "q").select("p", "q")


def connected_pairs(ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """(p, q) with p < q that some core point reaches both.

    Points that the same components reach are a class; only border points are
    reached by several. Classes with a common component are paired once, and so
    are the lists of their points, so no pair is met twice.
    """
    at = durable(collapse_duplicates(ps))
    classed = _reached(at, spec)[1].groupBy("q").agg(F.array_sort(F.collect_list("component")).alias("class"))
    lists = durable(packs(_spread(ps, at, classed, "q"), ["class"], "q", "ids"))
    own = lists.select("class").distinct().select("class", F.explode("class").alias("component"))
    links = own.join(own.withColumnRenamed("class", "other").hint("merge"), "component").where(F.col("class") <= F.col("other")).select("class", "other").distinct()
    other = lists.select(F.col("class").alias("other"), F.col("ids_no").alias("y_no"), F.col("ids").alias("y_ids"))
    both = dealt_lists(links.join(lists.hint("merge"), "class"), other, ["other"], "y_no")
    both = both.where("class < other OR ids_no <= y_no").withColumn("same", F.expr("class = other AND ids_no = y_no"))
    pairs = unfold(both, ("ids", "a"), ("y_ids", "b"), "same").where("NOT same OR a < b")
    return pairs.select(F.least("a", "b").alias("p"), F.greatest("a", "b").alias("q"))


def core_pointwise(ps: DataFrame, spec: ClusterSpec, how: str = "cell") -> DataFrame:
    at = durable(collapse_duplicates(ps))
    return _spread(ps, at, _core_places(near_places(at, spec.eps, how), spec.min_pts).withColumnRenamed("i", "point_id"), "point_id").select("point_id", "n")


def pointwise(ps: DataFrame, spec: ClusterSpec, how: str = "theta") -> ClusterResult:
    """The definitions carried out: pairs, counts, components over core pairs, borders. Ground truth for small data.

    Pairs of places are not written: each step meets them anew and hands on
    counts, a forest of each task, and the components that a border place reaches.
    """
    d = dims(ps)
    at = durable(collapse_duplicates(ps))
    near = near_places(at, spec.eps, how)
    core = durable(_core_places(near, spec.min_pts).select(F.col("i").alias("c")))
    dense, rest = (at.join(core, F.col("point_id") == F.col("c"), k) for k in ("left_semi", "left_anti"))
    links = near_places(dense, spec.eps, how).where("i < j").select(F.col("i").alias("a"), F.col("j").alias("b"))
    found = star_components(task_forest(links))
    part = durable(core.join(found, F.col("c") == F.col("vertex"), "left").select("c", F.coalesce("component", "c").alias("component")))
    left = rest.select("point_id", *xs(d))
    right = dense.join(part, F.col("point_id") == F.col("c")).select("component", *[F.col(x).alias(f"y_{x}") for x in xs(d)])
    reach = _near(left, right, spec.eps, how)
    border = durable(_spread(ps, at, reach.select("point_id", "component").distinct(), "point_id").select("point_id", F.col("component").cast("string").alias("cell")))
    named = members(ps, at).join(part, F.col("place") == F.col("c"), "left").select(F.col("point_id").alias("id"), F.col("c").isNotNull().alias("is_core"), F.coalesce("component", "point_id").cast("string").alias("cell"))
    flagged = durable(ps.join(named, F.col("point_id") == F.col("id")).drop("id"))
    # components are joined already
    return ClusterResult(finish(flagged, flagged.sparkSession.createDataFrame([], "a string, b string"), border), flagged, _no_counters(ps))


def _no_counters(df: DataFrame) -> DataFrame:
    return df.sparkSession.createDataFrame([], blocks.LINKS)


def pointwise_sequential(points: np.ndarray, eps: int, min_pts: int, order: np.ndarray | None = None) -> list[set[int]]:
    """One point after another, in a given visiting order: clusters as sets of rows. Clusters do not depend on the order, only on who claims a shared border point."""
    near = [np.flatnonzero(np.square(points - p).sum(axis=1) <= eps * eps) for p in points]
    done, out = np.zeros(len(points), bool), []
    for s in range(len(points)) if order is None else order:
        if done[s] or len(near[s]) < min_pts:
            continue
        members, queue = {int(s)}, [int(s)]
        done[s] = True
        while queue:
            for y in near[queue.pop()]:
                members.add(int(y))
                if not done[y] and len(near[y]) >= min_pts:
                    done[y] = True
                    queue.append(int(y))
        out.append(members)
    return out


def plane_grid(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    """Two dimensions: cells of side eps / sqrt 2, dense cells at once, nearest core points of neighbour cells from a search tree."""
    _plane(ps)
    return run(ps, spec, gap="nn_index", boxes=False)


def planar_front(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    """Two dimensions: cells as before, neighbour cells tested along their separating line."""
    _plane(ps)
    return run(ps, spec, gap="planar_front", boxes=False)


def _plane(ps: DataFrame) -> None:
    if dims(ps) != 2:
        raise ValueError("a method of the plane")


def grid_bcp(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    """Cells in any dimension, closest pairs of neighbour cells from two search trees."""
    return run(ps, spec, gap="closest_pair", boxes=False)


def centre_filter_grid(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    return run(ps, spec, gap="centre_filter", boxes=False)


def rho_grid(ps: DataFrame, spec: ClusterSpec, rho: float = 0.01) -> ClusterResult:
    """Core points exact; neighbour cells joined by approximate counts over halved sub-cells."""
    return run(ps, spec, rho=rho)


def hash_grid_exact(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    """Cells that are only hashed, never ordered: neighbours by equality joins (moved by the template up to three dimensions, by prefixes beyond), the exact gap test on the two cells of a pair."""
    d = dims(ps)
    placed = durable(assign_cells(ps.select("point_id", *xs(d)), spec.eps))
    from .neighbours import by_prefix, by_template

    own = placed.select(*ks(d)).distinct()
    near = durable(by_template(own) if d <= 3 else by_prefix(own))
    counts = placed.groupBy(*ks(d)).agg(F.count(F.lit(1)).alias("n_cell"))
    placed = placed.join(counts, ks(d))
    sparse = placed.where(F.col("n_cell") < spec.min_pts)
    both = near.select(*ks(d), *[f"n{j}" for j in range(1, d + 1)]).unionByName(own.select(*ks(d), *[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)]))
    other = placed.select(*[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)], F.col("point_id").alias("other"), *[F.col(x).alias(f"y_{x}") for x in xs(d)])
    n = [f"n{j}" for j in range(1, d + 1)]
    counted = sparse.join(both, ks(d)).join(other, n).where(square(d) <= spec.eps * spec.eps).groupBy("point_id").agg(F.count(F.lit(1)).alias("found")).where(F.col("found") >= spec.min_pts)
    flagged = placed.join(counted.select("point_id", F.lit(True).alias("counted")), "point_id", "left")
    flagged = durable(flagged.select("point_id", *xs(d), *ks(d), ((F.col("n_cell") >= spec.min_pts) | F.coalesce("counted", F.lit(False))).alias("is_core"), F.concat_ws(",", *ks(d)).alias("cell")))
    core = flagged.where("is_core")
    boxes = core.groupBy(*ks(d), "cell").agg(*[f(x).alias(f"{p}{x[1:]}") for x in xs(d) for p, f in (("lo", F.min), ("hi", F.max))])
    right = boxes.select(*[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)], F.col("cell").alias("cell_b"), *[F.col(f"{p}{j}").alias(f"{p}b{j}") for j in range(1, d + 1) for p in ("lo", "hi")])
    pairs = near.join(boxes, ks(d)).join(right, n).where("cell < cell_b")
    gap = [F.greatest(F.col(f"lo{j}") - F.col(f"hib{j}"), F.col(f"lob{j}") - F.col(f"hi{j}"), F.lit(0)) for j in range(1, d + 1)]
    far = [F.greatest(F.col(f"hi{j}") - F.col(f"lob{j}"), F.col(f"hib{j}") - F.col(f"lo{j}")) for j in range(1, d + 1)]
    add = lambda v: reduce(lambda a, b: a + b, [e * e for e in v])
    pairs = durable(pairs.where(add(gap) <= spec.eps**2).select(F.col("cell").alias("a"), F.col("cell_b").alias("b"), (add(far) <= spec.eps**2).alias("sure")))
    edges = pairs.where("sure").select("a", "b").unionByName(pair_edges(core, pairs.where("NOT sure").select("a", "b"), spec.eps))
    border = flagged.where("NOT is_core").join(both, ks(d)).join(core.select(*[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)], F.col("cell").alias("core_cell"), *[F.col(x).alias(f"y_{x}") for x in xs(d)]), n)
    border = durable(border.where(square(d) <= spec.eps**2).select("point_id", F.col("core_cell").alias("cell")).distinct())
    return ClusterResult(finish(flagged, edges, border), flagged, _no_counters(ps))


def pair_edges(core: DataFrame, pairs: DataFrame, eps: int, gap: str = "alternating_prune", cell: str = "cell") -> DataFrame:
    """The pairs (a, b) of cells whose core points come within eps: the two sides of a pair are co-grouped in one kernel."""
    d = dims(core)
    members = core.select(F.col(cell).alias("cell"), *xs(d))
    # both sides have names of their own, as they come from one table
    first = pairs.join(members, pairs["a"] == members["cell"]).select("a", "b", *xs(d))
    second = pairs.join(members, pairs["b"] == members["cell"]).select("a", "b", *xs(d)).toDF("of_a", "of_b", *[f"y_{x}" for x in xs(d)])
    matrix = lambda part, names: np.stack([part.column(c).to_numpy() for c in names], axis=1).astype(np.int64)

    def test(one: pa.Table, two: pa.Table) -> pa.Table:
        yes = one.num_rows and two.num_rows and gaptest.TESTS[gap](matrix(one, xs(d)), matrix(two, [f"y_{x}" for x in xs(d)]), eps).yes
        return one.select(["a", "b"]).slice(0, 1 if yes else 0)

    return first.groupBy("a", "b").cogroup(second.groupBy("of_a", "of_b")).applyInArrow(test, "a string, b string")


def _boxed(core: DataFrame, pairs: DataFrame, eps: int) -> DataFrame:
    """Pairs (a, b) of units whose boxes are within eps, with sure where their farthest corners are; only the others need points."""
    d = dims(core)
    boxes = core.groupBy("cell").agg(*[f(x).alias(f"{p}{x[1:]}") for x in xs(d) for p, f in (("lo", F.min), ("hi", F.max))])
    right = boxes.select(F.col("cell").alias("cell_b"), *[F.col(f"{p}{j}").alias(f"{p}b{j}") for j in range(1, d + 1) for p in ("lo", "hi")])
    both = pairs.join(boxes, pairs["a"] == boxes["cell"]).join(right, F.col("b") == F.col("cell_b"))
    add = lambda v: reduce(lambda x, y: x + y, [e * e for e in v])
    gap = [F.greatest(F.col(f"lo{j}") - F.col(f"hib{j}"), F.col(f"lob{j}") - F.col(f"hi{j}"), F.lit(0)) for j in range(1, d + 1)]
    far = [F.greatest(F.col(f"hi{j}") - F.col(f"lob{j}"), F.col(f"hib{j}") - F.col(f"lo{j}")) for j in range(1, d + 1)]
    return durable(both.where(add(gap) <= eps**2).select("a", "b", (add(far) <= eps**2).alias("sure")))


def _half_balls(ps: DataFrame, spec: ClusterSpec) -> DataFrame:
    """point_id and centre of the points that balls of radius eps / 2 absorb.

    A centre has ``min_pts`` points in its ball and lies in no ball picked
    before. Blocks are coloured so that those of one colour are more than half
    of eps apart; colours take turns, and inside a block candidates are picked
    one after another, so no pair of points leaves a kernel. The number of turns
    is that of the colours, whatever the number of balls.
    """
    d = dims(ps)
    # twice the coordinates, so that half of eps stays an integer
    wide = ps.select("point_id", *[(F.col(x) * 2).alias(x) for x in xs(d)])
    flagged, plan = mark_core(wide, spec)
    dense = durable(flagged.select("point_id", *xs(d), *ks(d), "is_core"))
    turns = plan.colours(d)
    taken = dense.sparkSession.createDataFrame([], "point_id bigint, centre bigint")
    dealt = durable(blocks.to_blocks(dense, plan))

    def pick(part: pa.Table) -> pa.Table:
        column = lambda c: part.column(c).combine_chunks().to_numpy(zero_copy_only=False)
        c = blocks.Cells(part, d)
        may = (column("is_core") & column("home") & ~column("absorbed"))[c.order]
        centre = np.full(len(c.ids), -1, np.int64)
        free = ~column("absorbed")[c.order]
        for cell in np.unique(c.cell[may]):
            near = c.tree.query(c.grid[[cell]], spec.reach(d), with_self=True)[1]
            around = np.concatenate([np.arange(c.first[o], c.first[o] + c.count[o]) for o in near])
            for p in range(c.first[cell], c.first[cell] + c.count[cell]):
                if may[p] and free[p]:
                    diff = c.x[around] - c.x[p]
                    ball = around[(np.einsum("ij,ij->i", diff, diff) <= spec.eps**2) & free[around]]
                    centre[ball], free[ball] = c.ids[p], False
        hit = centre >= 0
        return pa.table({"point_id": pa.array(c.ids[hit]), "centre": pa.array(centre[hit])})

    for blocks_of_turn in turns:
        own = dealt.where(F.col("block").isin([int(b) for b in blocks_of_turn])) if len(turns) > 1 else dealt
        now = own.join(taken.select("point_id", F.lit(True).alias("absorbed")), "point_id", "left").withColumn("absorbed", F.coalesce("absorbed", F.lit(False)))
        found = now.groupBy("block").applyInArrow(pick, "point_id bigint, centre bigint")
        # blocks of a turn may reach one point from two sides
        taken = durable(taken.unionByName(found.groupBy("point_id").agg(F.min("centre").alias("centre"))))
    return taken


def centre_pairs(centres: DataFrame, radius: int, search: str = "index") -> tuple[DataFrame, DataFrame]:
    """(i, j), i < j, of centres at most ``radius`` apart, and a row with the number of pairs looked at.

    ``linear`` compares every centre with every other, ``index`` those in
    neighbouring bins of the radius.
    """
    d = dims(centres)
    left, right = centres.select(F.col("point_id").alias("i"), *xs(d)), _others(centres, "j")
    if search == "linear":
        n = centres.agg((F.count(F.lit(1)) * (F.count(F.lit(1)) - 1) / 2).cast("bigint").alias("looked_at"))
        return left.join(right, (F.col("i") < F.col("j")) & (square(d) <= radius * radius)).select("i", "j"), n
    binned = range(1, min(d, 3) + 1)
    for j in binned:
        left = left.withColumn(f"g{j}", F.floor(F.col(f"x{j}") / radius))
        right = right.withColumn(f"g{j}", F.explode(F.sequence(F.floor(F.col(f"y_x{j}") / radius) - 1, F.floor(F.col(f"y_x{j}") / radius) + 1)))
    both = left.join(right, [f"g{j}" for j in binned]).where("i < j")
    return both.where(square(d) <= radius * radius).select("i", "j"), both.agg(F.count(F.lit(1)).alias("looked_at"))


def ball_block(ps: DataFrame, spec: ClusterSpec, gap: str = "pingpong", search: str = "linear") -> ClusterResult:
    """Blocks are balls of radius eps / 2 with enough points; blocks with near centres are merged by a gap test.

    Points outside of balls are core by their own count. With ``pingpong``
    blocks may stay apart wrongly and an outer core point joins one cluster
    only; with an exact gap test outer points are blocks of one and the result
    is exact. ``search`` says how centres find each other: every one against
    every other, or by an index. Counters have the pairs of centres looked at
    as ``checks``.
    """
    exact, d = gap in gaptest.EXACT, dims(ps)
    absorbed = _half_balls(ps, spec)
    own = mark_core(ps, spec)[0].select(F.col("point_id").alias("id"), "is_core")
    named = ps.select("point_id", *xs(d)).join(absorbed, "point_id", "left").join(own, F.col("point_id") == F.col("id"))
    flagged = durable(named.select("point_id", *xs(d), (F.col("centre").isNotNull() | F.col("is_core")).alias("is_core"), F.coalesce("centre", F.col("point_id")).cast("string").alias("cell"), F.col("centre").isNotNull().alias("inner_core")))
    core = flagged.where("is_core")
    mid = core.where("inner_core").select(F.col("cell").cast("bigint").alias("point_id")).distinct().join(ps.select("point_id", *xs(d)), "point_id")
    near, looked = centre_pairs(mid, 2 * spec.eps, search)
    boxed = _boxed(core, near.select(F.col("i").cast("string").alias("a"), F.col("j").cast("string").alias("b")), spec.eps)
    sure = boxed.where("sure").select("a", "b")
    edges = sure.unionByName(pair_edges(core, boxed.where("NOT sure").select("a", "b"), spec.eps, gap)) if exact else pair_edges(core, boxed.select("a", "b"), spec.eps, gap)
    # only outer core points and points that are no core ask for their neighbours
    reach = within(core.where("NOT inner_core").select(F.col("cell").alias("a"), *xs(d)), core.select(F.col("cell").alias("b"), F.col("inner_core").alias("inner"), *[F.col(x).alias(f"y_{x}") for x in xs(d)]), spec.eps).where("a <> b")
    if exact:
        outer = reach.select("a", "b").distinct()
    else:
        outer = reach.groupBy("a").agg(F.min(F.struct(~F.col("inner"), F.col("b"))).alias("m")).select("a", F.col("m.b").alias("b"))
    border = within(flagged.where("NOT is_core").select("point_id", *xs(d)), core.select("cell", *[F.col(x).alias(f"y_{x}") for x in xs(d)]), spec.eps).select("point_id", "cell").distinct()
    counters = looked.select(F.lit("centres").alias("kind"), F.lit(None).cast("bigint").alias("point_id"), *[F.lit(None).cast("string").alias(c) for c in "ab"], F.col("looked_at").alias("checks"), *[F.lit(0).cast("bigint").alias(c) for c in ("skipped", "kappa", "distances", "pruned_triangle", "pruned_angle")])
    return ClusterResult(finish(flagged, durable(edges.unionByName(outer)), durable(border)), flagged, counters, eps=spec.eps)


def ball_block_exact(ps: DataFrame, spec: ClusterSpec, search: str = "index") -> ClusterResult:
    return ball_block(ps, spec, gap="alternating_prune", search=search)


def block_profile(result: ClusterResult) -> DataFrame:
    """Blocks, points that they absorb, and outer core points."""
    return result.flagged.agg(F.count_distinct(F.when(F.col("inner_core"), F.col("cell"))).alias("blocks"), F.count_if("inner_core").alias("absorbed"), F.count_if(F.col("is_core") & ~F.col("inner_core")).alias("outer_cores"))


def local_ball(ps: DataFrame, spec: ClusterSpec) -> ClusterResult:
    """A ball of 2 eps around one point of each cell holds the neighbours of all points of the cell: searches stay inside it; exact."""
    d = dims(ps)
    placed = durable(assign_cells(ps.select("point_id", *xs(d)), spec.eps).withColumn("cell", F.concat_ws(",", *ks(d))).select("point_id", *xs(d), "cell"))
    centre = placed.groupBy("cell").agg(F.min(F.struct("point_id", *xs(d))).alias("m")).select(F.col("cell").alias("ball"), *[F.col(f"m.{x}").alias(x) for x in xs(d)])
    balls = lambda points: within(centre, points, 2 * spec.eps).select("ball", "id", "cell", "is_core", *[f"y_{x}" for x in xs(d)])
    right = lambda df, flag: df.select(F.col("point_id").alias("id"), "cell", flag.alias("is_core"), *[F.col(x).alias(f"y_{x}") for x in xs(d)])

    def read(part: pa.Table) -> tuple:
        x = np.stack([part.column(f"y_{c}").to_numpy() for c in xs(d)], axis=1).astype(np.int64)
        cell = np.array(part.column("cell").to_pylist(), object)
        return x, part.column("id").to_numpy(), cell, cell == part.column("ball")[0].as_py()

    def count(part: pa.Table) -> pa.Table:
        x, ids, _, home = read(part)
        n = [int((np.square(x - x[p]).sum(axis=1) <= spec.eps**2).sum()) for p in np.flatnonzero(home)]
        return pa.table({"id": pa.array(ids[home]), "core": pa.array([k >= spec.min_pts for k in n], pa.bool_())})

    def reach(part: pa.Table) -> pa.Table:
        x, ids, cell, home = read(part)
        core, out = part.column("is_core").to_numpy(zero_copy_only=False), set()
        for p in np.flatnonzero(home):
            near = core & (np.square(x - x[p]).sum(axis=1) <= spec.eps**2)
            out |= {(None, cell[p], c) for c in cell[near] if c > cell[p]} if core[p] else {(int(ids[p]), c, None) for c in cell[near]}
        rows = sorted(out, key=str)
        return pa.table({"point_id": pa.array([r[0] for r in rows], pa.int64()), "a": pa.array([r[1] for r in rows], pa.string()), "b": pa.array([r[2] for r in rows], pa.string())})

    flags = balls(right(placed, F.lit(False))).groupBy("ball").applyInArrow(count, "id bigint, core boolean")
    flagged = durable(placed.join(flags, F.col("point_id") == F.col("id")).select("point_id", *xs(d), "cell", F.col("core").alias("is_core")))
    found = durable(balls(right(flagged, F.col("is_core"))).groupBy("ball").applyInArrow(reach, "point_id bigint, a string, b string"))
    border = found.where("b IS NULL").select("point_id", F.col("a").alias("cell"))
    return ClusterResult(finish(flagged, found.where("b IS NOT NULL").select("a", "b"), border), flagged, _no_counters(ps), eps=spec.eps)


def sampled_expansion(ps: DataFrame, spec: ClusterSpec, reps: int = 4) -> ClusterResult:
    """Only ``reps`` points of a cell, the smallest ids, ask for their neighbours.

    A sampled point with enough neighbours is core and takes them into its
    cluster, sampled core points near each other share one; all others never
    ask. May miss core points and links, never joins what is apart.
    """
    d = dims(ps)
    at = durable(collapse_duplicates(ps))
    placed = assign_cells(ps.select("point_id", *xs(d)), spec.eps)
    asked = durable(placed.withColumn("r", F.row_number().over(W.partitionBy(*ks(d)).orderBy("point_id"))).where(F.col("r") <= reps).select(F.col("point_id").alias("i"), *xs(d)))
    # asked points are the few, so places come in their bins
    pairs = durable(within(asked, _others(at, "j", "weight").hint("merge"), spec.eps).select("i", "j", "weight"))
    core = durable(pairs.groupBy("i").agg(F.sum("weight").alias("n")).where(F.col("n") >= spec.min_pts).select("i"))
    # pairs and members grow with the table, so none of them is broadcast, whatever a plan takes their size for
    taken = pairs.join(core.hint("merge"), "i", "left_semi").select("i", "j")
    both = members(asked.join(core, "i", "left_semi").withColumnRenamed("i", "point_id"), at).select(F.col("place").alias("j"), F.col("point_id").alias("k"))
    found = star_components(taken.join(both.hint("merge"), "j").where("i < k").select(F.col("i").alias("a"), F.col("k").alias("b")))
    part = durable(core.join(found, F.col("i") == F.col("vertex"), "left").select("i", F.coalesce("component", "i").alias("component")))
    reached = taken.join(part.hint("merge"), "i").select("j", "component").distinct()
    border = _spread(ps, at, reached.withColumnRenamed("j", "point_id"), "point_id").join(core.hint("merge"), F.col("point_id") == F.col("i"), "left_anti").select("point_id", F.col("component").cast("string").alias("cell"))
    flagged = ps.select("point_id", *xs(d)).join(part.hint("merge"), F.col("point_id") == F.col("i"), "left")
    flagged = durable(flagged.select("point_id", *xs(d), F.col("component").isNotNull().alias("is_core"), F.coalesce("component", "point_id").cast("string").alias("cell")))
    # components are joined already
    return ClusterResult(finish(flagged, flagged.sparkSession.createDataFrame([], "a string, b string"), durable(border)), flagged, _no_counters(ps), eps=spec.eps)
