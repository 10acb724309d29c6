"""Blocks of cells with a halo: one shuffle brings every block what its own cells need.

A block is a box of cells. Boxes come from counts: the cells are counted on a
grid that the driver can hold, coarse where cells are many, boxes of too many
points are cut at the median of a dimension, and what a coarse cell alone makes
too large is counted anew on a finer grid, down to single cells. So the number
of blocks follows the number of points, and a dense region is cut as often as it
needs. Points are copied to the blocks within the reach of their cell, and each
block's kernel answers for its own ("home") cells only.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import gaptest
from .components import UnionFind
from .prefixtree import PrefixTree, RectTree
from .spec import ClusterSpec, dims, ks, xs

#: Rows of a count that travel to the driver, and fewest points worth a block of their own.
PLAN_ROWS, LEAST = 200_000, 1_000
#: Share of a box that a cut may copy if nothing but the number of tasks asks for it.
CHEAP = 0.3
#: Nodes of a tree that one call of a query looks at, and coordinates of pairs of points compared at once, about.
LOOKED, COMPARED = 1 << 19, 1 << 21


class BlockPlan:
    """A binary tree of cuts over cells; its leaves are the blocks. Node 0 is the root, a leaf has dimension -1."""

    def __init__(self, halo: int):
        self.halo = halo
        self.dim, self.at, self.low, self.block = [], [], [], []
        self.n_blocks = 0

    def leaf(self, node: int) -> None:
        self.dim[node], self.block[node] = -1, self.n_blocks
        self.n_blocks += 1

    def node(self) -> int:
        for values in (self.dim, self.at, self.low, self.block):
            values.append(-1)
        return len(self.dim) - 1

    def cut(self, node: int, dim: int, at: int) -> tuple[int, int]:
        """Cells below ``at`` go to the first child, the others to the second, which stands behind it."""
        self.dim[node], self.at[node] = dim, at
        first, second = self.node(), self.node()
        self.low[node] = first
        return first, second

    def assign(self, keys: np.ndarray, halo: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Row, block and whether the block is the row's own, for each block within ``halo`` cells of each row."""
        h = self.halo if halo is None else halo
        dim, at, low, block = (np.array(v, np.int64) for v in (self.dim, self.at, self.low, self.block))
        row, node, home = np.arange(len(keys)), np.zeros(len(keys), np.int64), np.ones(len(keys), bool)
        done: list[tuple] = []
        while len(row):
            end = dim[node] < 0
            done.append((row[end], block[node[end]], home[end]))
            row, node, home = row[~end], node[~end], home[~end]
            k, cut = keys[row, dim[node]], at[node]
            left, right = k < cut + h, k >= cut - h
            row, home, node = np.r_[row[left], row[right]], np.r_[home[left] & (k < cut)[left], home[right] & (k >= cut)[right]], np.r_[low[node[left]], low[node[right]] + 1]
        return tuple(np.concatenate(v) for v in zip(*done, strict=True)) if done else (row, node, home)


    def boxes(self, d: int) -> tuple[np.ndarray, np.ndarray]:
        """Lowest and highest cell of each block; open sides are very large numbers."""
        far = 1 << 60
        low, high = np.zeros((self.n_blocks, d), np.int64), np.zeros((self.n_blocks, d), np.int64)
        stack = [(0, np.full(d, -far), np.full(d, far))]
        while stack:
            node, a, b = stack.pop()
            if self.dim[node] < 0:
                low[self.block[node]], high[self.block[node]] = a, b
                continue
            j, at = self.dim[node], self.at[node]
            left, right = b.copy(), a.copy()
            left[j], right[j] = at - 1, at
            stack += [(self.low[node], a, left), (self.low[node] + 1, right, b)]
        return low, high

    def colours(self, d: int) -> list[np.ndarray]:
        """Groups of blocks no two of which lie within the halo of each other."""
        low, high = self.boxes(d)
        colour = np.full(self.n_blocks, -1)
        for k in range(self.n_blocks):
            near = ((low[:k] <= high[k] + self.halo) & (high[:k] >= low[k] - self.halo)).all(axis=1)
            used = set(colour[:k][near].tolist())
            colour[k] = next(c for c in range(len(used) + 1) if c not in used)
        return [np.flatnonzero(colour == c) for c in range(colour.max(initial=-1) + 1)]


def _counted(cells: DataFrame, level: int, inside: DataFrame | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Lowest cells of the boxes of 2 ** level cells a side that hold points, and their counts."""
    d = cell_dims(cells)
    boxes = cells.select(*[F.shiftright(k, level).alias(k) for k in ks(d)]) if inside is None else inside
    rows = boxes.groupBy(*ks(d)).agg(F.count(F.lit(1)).alias("n")).toArrow()
    keys = np.stack([rows.column(k).to_numpy() for k in ks(d)], axis=1).astype(np.int64) if rows.num_rows else np.empty((0, d), np.int64)
    return keys << level, rows.column("n").to_numpy().astype(np.int64)


def cell_dims(cells: DataFrame) -> int:
    return sum(1 for c in cells.columns if c[0] == "k" and c[1:].isdigit())


def plan_blocks(cells: DataFrame, spec: ClusterSpec) -> BlockPlan:
    """Blocks of ``block_points`` home points at most where a cut is left, and of fewer where cuts are cheap.

    Of all cuts that leave a fifth on either side, the one with the fewest points
    within its halo is taken, so cuts go through gaps. A box of one cell stays
    whole, and a box is not cut below twice the reach in all dimensions, as its
    halo would hold most of what it sheds. Down to an eighth of all points,
    boxes are cut for the sake of more tasks, but only where the halo is less
    than ``CHEAP`` of the box. At most ``PLAN_ROWS`` counts of a level reach the
    driver at once.
    """
    d = cell_dims(cells)
    levels = range(0, 21, 3)
    sketch = cells.agg(F.count(F.lit(1)).alias("n"), *[F.approx_count_distinct(F.struct(*[F.shiftright(k, s) for k in ks(d)])).alias(f"l{s}") for s in levels]).first()
    level = next((s for s in levels if sketch[f"l{s}"] <= PLAN_ROWS * 0.9), levels[-1])
    most = spec.block_points, min(spec.block_points, max(sketch["n"] / 8, LEAST))
    plan, reach = BlockPlan(spec.reach(d)), spec.reach(d)
    keys, count = _counted(cells, level)
    open_ = [(plan.node(), keys, count, level)]
    while open_:
        finer = []
        for node, keys, count, level in open_:
            finer += _cut(plan, node, keys, count, level, most, reach)
        open_ = []
        # boxes of one coarse cell that hold too much are counted anew, a bounded number at a time
        for k in range(0, len(finer), 512):
            part = finer[k : k + 512]
            step = 1 if d > 5 else 2
            listed = cells.sparkSession.createDataFrame([(i, *map(int, keys[0] >> level)) for i, (_, keys, _, level) in enumerate(part)], "__i bigint, " + ", ".join(f"__{k} bigint" for k in ks(d)))
            level = part[0][3]
            to = max(0, level - step)
            match = [F.shiftright(k, level) == F.col(f"__{k}") for k in ks(d)]
            rows = cells.select(*ks(d)).join(F.broadcast(listed), match).groupBy("__i", *[F.shiftright(k, to).alias(k) for k in ks(d)]).agg(F.count(F.lit(1)).alias("n")).toArrow()
            which, n = rows.column("__i").to_numpy(), rows.column("n").to_numpy().astype(np.int64)
            fine = np.stack([rows.column(k).to_numpy() for k in ks(d)], axis=1).astype(np.int64) << to
            open_ += [(node, fine[which == i], n[which == i], to) for i, (node, *_) in enumerate(part)]
    return plan


def _cut(plan: BlockPlan, node: int, keys: np.ndarray, count: np.ndarray, level: int, most: tuple[float, float], reach: int) -> list[tuple]:
    """Cuts the box of a node until its parts are small; returns the parts that need a finer count."""
    stack, finer = [(node, np.arange(len(keys)))], []
    while stack:
        node, rows = stack.pop()
        whole = int(count[rows].sum())
        if whole <= most[1]:
            plan.leaf(node)
            continue
        if len(rows) == 1 and level:
            if whole > most[0]:
                finer.append((node, keys[rows], count[rows], level))
            else:
                plan.leaf(node)
            continue
        wide, found, least = keys[rows].max(axis=0) - keys[rows].min(axis=0) + (1 << level), None, None
        for j in np.flatnonzero(wide > max(2 * reach, 1 << level)):
            order = np.argsort(keys[rows, j], kind="stable")
            v, total = keys[rows[order], j], np.cumsum(count[rows[order]])
            edge = np.flatnonzero(v[1:] != v[:-1])
            fair = edge[(total[edge] >= whole / 5) & (total[edge] <= whole * 4 / 5)]
            fair = fair if len(fair) else edge[[np.abs(total[edge] - whole / 2).argmin()]]
            before = np.r_[0, total]
            copied = before[np.searchsorted(v, v[fair + 1] + reach)] - before[np.searchsorted(v, v[fair + 1] - reach)]
            k = int(copied.argmin())
            if least is None or copied[k] < least:
                least, found = int(copied[k]), (int(j), int(v[fair[k] + 1]))
        if found is None or (whole <= most[0] and least > CHEAP * whole):
            plan.leaf(node)
            continue
        low, high = plan.cut(node, *found)
        below = keys[rows, found[0]] < found[1]
        stack += [(low, rows[below]), (high, rows[~below])]
    return finer


def to_blocks(df: DataFrame, plan: BlockPlan, halo: int | None = None) -> DataFrame:
    """``df`` with block and home; a row of cell k is copied to the blocks that lie within ``halo`` cells of it."""
    columns, shared = df.columns, df.sparkSession.sparkContext.broadcast(plan)  # a few numbers for each block
    where = [columns.index(k) for k in ks(cell_dims(df))]

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = np.stack([batch.column(j).to_numpy(zero_copy_only=False) for j in where], axis=1).astype(np.int64)
            row, block, home = shared.value.assign(keys, halo)
            taken = batch.take(pa.array(row))
            yield pa.RecordBatch.from_arrays([*taken.columns, pa.array(block), pa.array(home)], names=[*columns, "block", "home"])

    return df.mapInArrow(deal, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + ", block bigint, home boolean")


class Cells:
    """The points of a block by cell, in lexicographic order of cells, with the prefix tree over these."""

    def __init__(self, part: pa.Table, d: int, tree: str = "prefix"):
        column = lambda c: part.column(c).combine_chunks().to_numpy(zero_copy_only=False)
        keys = np.stack([column(k) for k in ks(d)], axis=1).astype(np.int64)
        ids = column("point_id")
        order = np.lexsort((ids, *[keys[:, j] for j in range(d - 1, -1, -1)]))
        self.d, self.order = d, order
        self.keys, self.ids = keys[order], ids[order]
        self.x = np.stack([column(x) for x in xs(d)], axis=1).astype(np.int64)[order]
        self.home = column("home")[order]
        self.weight = column("weight").astype(np.int64)[order] if "weight" in part.column_names else np.ones(len(order), np.int64)
        cut = np.r_[True, (self.keys[1:] != self.keys[:-1]).any(axis=1)][: len(order)]
        self.first = np.flatnonzero(cut)
        self.count = np.diff(np.r_[self.first, len(order)])
        self.mass = np.add.reduceat(self.weight, self.first) if len(order) else self.count
        self.cell = np.cumsum(cut) - 1
        self.grid = self.keys[self.first]
        self.own = self.home[self.first]
        self.tree = PrefixTree(self.grid) if tree == "prefix" else RectTree(self.grid)

    def neighbours(self, cells: np.ndarray, reach: int):
        """Cell, neighbour (itself included) and offset, in chunks of queries."""
        for part, q, other, off in queries(self.tree, self.grid, cells, reach):
            yield part[q], other, off


def queries(tree: PrefixTree | RectTree, grid: np.ndarray, cells: np.ndarray, reach: int) -> Iterator[tuple[np.ndarray, ...]]:
    """For stretches of ``cells`` (rows of ``grid``): the stretch and its answer. Stretches follow the nodes that the one before looked at, as cells of many dimensions have thousands of neighbours."""
    k, size = 0, 64
    while k < len(cells):
        part, before = cells[k : k + size], tree.visited
        yield part, *tree.query(grid[part], reach, with_self=True)
        k += len(part)
        size = max(1, min(2 * size, 8192, len(part) * LOOKED // max(1, tree.visited - before)))


def spread(first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For stretches: the number of the stretch and each position in it."""
    n = count.sum()
    of = np.repeat(np.arange(len(first)), count)
    return of, np.repeat(first, count) + np.arange(n) - np.repeat(np.cumsum(count) - count, count)


def core_kernel(spec: ClusterSpec, d: int, tree: str = "prefix") -> Callable[[pa.Table], pa.Table]:
    """Home points with is_core. Cells of enough points are core; other points count in neighbour cells, nearest offsets first."""

    def run(part: pa.Table) -> pa.Table:
        c = Cells(part, d, tree)
        core = c.mass[c.cell] >= spec.min_pts
        sparse = np.flatnonzero(c.own & (c.mass < spec.min_pts))
        distances = 0
        for cell, other, off in c.neighbours(sparse, spec.reach(d)):
            order = np.argsort(off, kind="stable")
            cell, other, off = cell[order], other[order], off[order]
            found = np.zeros(len(c.ids), np.int64)
            for o in np.unique(off):
                wave = off == o
                # pairs of a point and a cell, of points that still need neighbours
                of, point = spread(c.first[cell[wave]], c.count[cell[wave]])
                where = other[wave][of]
                if spec.early_stop:
                    need = found[point] < spec.min_pts
                    point, where = point[need], where[need]
                for a, b in _stretches(c.count[where], COMPARED // d):
                    i, y = spread(c.first[where[a:b]], c.count[where[a:b]])
                    x = point[a:b][i]
                    distances += len(x)
                    diff = c.x[x] - c.x[y]
                    near = np.einsum("ij,ij->i", diff, diff) <= spec.eps * spec.eps
                    np.add.at(found, x[near], c.weight[y[near]])
            core |= found >= spec.min_pts
        keep = c.home
        out = {"point_id": c.ids[keep], **{f"x{j + 1}": c.x[keep, j] for j in range(d)}, **{f"k{j + 1}": c.keys[keep, j] for j in range(d)}, "is_core": core[keep], "n_cell": c.mass[c.cell][keep]}
        out["distances"] = np.where(np.arange(keep.sum()) == 0, distances, 0)
        return pa.table({k: pa.array(v) for k, v in out.items()})

    return run


def _stretches(sizes: np.ndarray, most: int):
    """Cuts of a list so that the sizes of a piece add up to about ``most``."""
    total = np.cumsum(sizes)
    a = 0
    while a < len(sizes):
        b = int(np.searchsorted(total, (total[a - 1] if a else 0) + most, side="right"))
        b = max(a + 1, b)
        yield a, b
        a = b


def core_schema(d: int) -> str:
    return "point_id bigint, " + ", ".join(f"x{j} bigint" for j in range(1, d + 1)) + ", " + ", ".join(f"k{j} bigint" for j in range(1, d + 1)) + ", is_core boolean, n_cell bigint, distances bigint"


LINKS = "kind string, point_id bigint, a string, b string, checks bigint, skipped bigint, kappa bigint, distances bigint, pruned_triangle bigint, pruned_angle bigint"


def merge_kernel(spec: ClusterSpec, d: int, gap: str = "alternating_prune", order: str = "graph", boxes: bool = True, slack: float = 0, rho: float = 0, tree: str = "prefix", trace: bool = False) -> Callable[[pa.Table], pa.Table]:
    """Core cells of a component in the block as a star, and components that border points reach, by their smallest cell.

    ``graph`` searches from each cell that has no component yet, neighbours by
    ascending offset, and tests a neighbour only while it has none; so a pair
    whose cells are both classified is left out. ``sparse_first`` goes through
    the cells by ascending number of core points and leaves out pairs that are
    joined. A pair belongs to the block of its smaller cell and is tested once.
    ``boxes`` answers pairs by their boxes where these decide. With ``trace`` a
    row tells the iterations and distances of each test.
    """

    def test(a: np.ndarray, b: np.ndarray) -> gaptest.GapVerdict:
        if boxes and not rho and gap in gaptest.EXACT:
            a, b = gaptest.clip(a, b, spec.eps + slack)
            if not len(a) or not len(b):
                return gaptest.GapVerdict(False)
        if rho:
            return gaptest.rho_count(a, b, spec.eps, rho)
        if slack:
            return gaptest.delta(a, b, spec.eps, slack)
        return gaptest.TESTS[gap](a, b, spec.eps)

    def run(part: pa.Table) -> pa.Table:
        is_core = part.column("is_core").combine_chunks().to_numpy(zero_copy_only=False)
        core = Cells(part.filter(pa.array(is_core)), d, tree)
        rest = part.filter(pa.array(~is_core))
        rows: list[tuple] = []
        tests: list[tuple] = []
        name = lambda k: ",".join(map(str, core.grid[k]))
        forest = UnionFind(len(core.grid))
        total = np.zeros(6, np.int64)
        if len(core.grid):
            low, high = np.minimum.reduceat(core.x, core.first), np.maximum.reduceat(core.x, core.first)
            tell = boxes and not rho and not slack and gap != "pingpong"
            found = [(np.empty((0, 2), np.int32), np.empty(0, np.int8), np.empty(0, np.int8))]
            # pairs that the boxes rule out are dropped where they are met
            for cell, other, off in core.neighbours(np.flatnonzero(core.own), spec.reach(d)):
                later = other > cell
                cell, other, off = cell[later], other[later], off[later]
                sure = gaptest.box_test(low[cell], high[cell], low[other], high[other], spec.eps) if tell else np.zeros(len(cell), int)
                open_ = sure >= 0
                found.append((np.stack([cell[open_], other[open_]], axis=1).astype(np.int32), off[open_].astype(np.int8), sure[open_].astype(np.int8)))
            pairs, offs, known = (np.concatenate(v) for v in zip(*found, strict=True))
            del found

            def joined(i: int, j: int, sure: bool) -> bool:
                """Whether the cells hold a pair within eps; counted unless the boxes tell."""
                if not sure:
                    v = test(*(core.x[core.first[s] : core.first[s] + core.count[s]] for s in (i, j)))
                    total[[0, 3, 4, 5]] += (1, v.distances, v.pruned_triangle, v.pruned_angle)
                    total[2] = max(total[2], v.iterations)
                    if trace:
                        tests.append((name(i), name(j), v.iterations, v.distances, v.pruned_triangle, v.pruned_angle))
                    if not v.yes:
                        return False
                forest.join(i, j)
                return True

            if order == "graph":
                _search(len(core.grid), pairs, offs, known, joined)
            else:
                rank = np.empty(len(core.grid), np.int64)
                rank[np.lexsort((np.arange(len(core.grid)), core.count))] = np.arange(len(core.grid))
                early, late = (f(rank[pairs[:, 0]], rank[pairs[:, 1]]) for f in (np.minimum, np.maximum))
                # what the boxes answer comes first, as it is free
                for k in np.lexsort((late, offs, early, -known)):
                    i, j = int(pairs[k, 0]), int(pairs[k, 1])
                    if forest.find(i) != forest.find(j):
                        joined(i, j, known[k] == 1)
            total[1] = len(pairs) - int((known == 1).sum()) - total[0]
            # a star for each component of the block: paths of many cells would take the joining of blocks many rounds
            rows += [("edge", None, name(forest.find(k)), name(k)) for k in range(len(core.grid)) if forest.find(k) != k]
            if rest.num_rows:
                rows += _border(spec, d, core, Cells(rest, d), forest, name)
        counters = ("counters", None, None, None, *map(int, total))
        rows = [(*r, 0, 0, 0, 0, 0, 0) for r in rows] + [("test", None, a, b, 1, 0, *v) for a, b, *v in tests] + [counters]
        kinds = (pa.string(), pa.int64(), pa.string(), pa.string(), *[pa.int64()] * 6)
        names = [f.split()[0] for f in LINKS.split(", ")]
        return pa.table({n: pa.array(list(v), t) for n, v, t in zip(names, zip(*rows, strict=True), kinds, strict=True)})

    return run


def _search(n: int, pairs: np.ndarray, offs: np.ndarray, known: np.ndarray, joined: Callable[[int, int, bool], bool]) -> None:
    """Breadth-first from the smallest cell without a component, over both directions of the pairs."""
    first, last = (np.concatenate([pairs[:, a], pairs[:, b]]) for a, b in ((0, 1), (1, 0)))
    order = np.lexsort((last, np.r_[offs, offs], first))
    start = np.r_[0, np.cumsum(np.bincount(first, minlength=n))]
    last, sure = last[order], np.r_[known, known][order] == 1
    del first, order
    seen = np.zeros(n, bool)
    for s in range(n):
        if seen[s] or start[s] == start[s + 1]:
            continue
        seen[s], queue = True, deque([s])
        while queue:
            c = queue.popleft()
            for k in range(start[c], start[c + 1]):
                o = int(last[k])
                if not seen[o] and joined(min(c, o), max(c, o), bool(sure[k])):
                    seen[o] = True
                    queue.append(o)


def _border(spec: ClusterSpec, d: int, core: Cells, rest: Cells, forest: UnionFind, name) -> list[tuple]:
    """For each home point that is no core, each local component that it reaches, named by its smallest cell."""
    own, root = np.flatnonzero(rest.own), np.array([forest.find(k) for k in range(len(core.grid))], np.int64)
    hits = [np.empty(0, np.int64)]
    for part, q, other, _ in queries(core.tree, rest.grid, own, spec.reach(d)):
        cell = part[q]
        of, point = spread(rest.first[cell], rest.count[cell])
        where = other[of]
        for a, b in _stretches(core.count[where], COMPARED // d):
            i, y = spread(core.first[where[a:b]], core.count[where[a:b]])
            diff = rest.x[point[a:b][i]] - core.x[y]
            ok = np.einsum("ij,ij->i", diff, diff) <= spec.eps * spec.eps
            hits.append(np.unique(point[a:b][i][ok] * len(root) + root[core.cell[y[ok]]]))
    return [("border", int(rest.ids[p]), name(c), None) for p, c in zip(*map(np.ndarray.tolist, np.divmod(np.unique(np.concatenate(hits)), len(root))), strict=True)]
