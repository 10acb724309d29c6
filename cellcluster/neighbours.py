"""Neighbour cells of every non-empty cell, by five strategies with one answer.

``cells`` has distinct identifiers k1, k2, .... The answer has the identifiers of
a cell, those of a neighbour as n1, n2, ..., and the offset (a lower bound on the
distance in cell sides, squared; below d). The cell itself is left out.
"""

from __future__ import annotations

from functools import reduce
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import blocks
from .prefixtree import PrefixTree, RectTree
from .spec import ClusterSpec, ks

#: Most cells whose identifiers travel to every executor, and dimensions a template is emitted for.
BROADCAST_CELLS, TEMPLATE_DIMS = 2_000_000, 5


def cell_dims(cells: DataFrame) -> int:
    return sum(1 for c in cells.columns if c[0] == "k" and c[1:].isdigit())


def template(d: int) -> list[tuple[tuple[int, ...], int]]:
    """Steps to every cell that can hold a point within eps, with their offsets; the step to itself included."""
    reach = ClusterSpec(1, 1).reach(d)
    gap = [max(abs(k) - 1, 0) ** 2 for k in range(-reach, reach + 1)]
    out: list[tuple[tuple[int, ...], int]] = [((), 0)]
    for _ in range(d):
        out = [((*s, k), o + gap[k + reach]) for s, o in out for k in range(-reach, reach + 1) if o + gap[k + reach] < d]
    return out


def _named(d: int) -> list[str]:
    return [*ks(d), *[f"n{j}" for j in range(1, d + 1)], "offset"]


def by_template(cells: DataFrame) -> DataFrame:
    """Each cell is moved by all steps, and those that exist are looked up. Refused where the steps outnumber any real neighbourhood."""
    d = cell_dims(cells)
    if d > TEMPLATE_DIMS:
        raise ValueError(f"{len(template(d))} steps a cell in {d} dimensions; use prefix or block")
    steps = [s for s in template(d) if any(s[0])]
    listed = F.array(*[F.struct(*[F.lit(v).alias(f"s{j}") for j, v in enumerate(s, 1)], F.lit(o).alias("offset")) for s, o in steps]) if len(steps) <= 200 else None
    own = cells.select(*ks(d)).distinct()
    if listed is not None:
        moved = own.withColumn("step", F.explode(listed))
        step = lambda j: F.col(f"step.s{j}")
        off = F.col("step.offset")
    else:
        size = 2 * ClusterSpec(1, 1).reach(d) + 1
        r = size // 2
        # the steps by arithmetic: one number names a step
        moved = own.withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(size**d - 1))))
        step = lambda j: (F.floor(F.col("step") / size ** (j - 1)) % size - r).cast("int")
        gaps = [F.greatest(F.abs(step(j)) - 1, F.lit(0)) for j in range(1, d + 1)]
        off = reduce(lambda a, b: a + b, [g * g for g in gaps])
    moved = moved.select(*ks(d), *[(F.col(f"k{j}") + step(j)).alias(f"n{j}") for j in range(1, d + 1)], off.cast("int").alias("offset"))
    same = reduce(lambda a, b: a & b, [F.col(f"n{j}") == F.col(f"k{j}") for j in range(1, d + 1)])
    there = own.select(*[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)])
    return moved.where((F.col("offset") < d) & ~same).join(there, [f"n{j}" for j in range(1, d + 1)], "left_semi").select(_named(d))


def build_levels(cells: DataFrame) -> list[DataFrame]:
    """Level j of the prefix tree: the distinct prefixes of j components, each level made from the one below it."""
    d = cell_dims(cells)
    level, out = cells.select(*ks(d)).distinct(), []
    for j in range(d, 0, -1):
        level = level.select(*ks(j)).distinct()
        out.append(level)
    return out[::-1]


def by_prefix(cells: DataFrame, levels: list[DataFrame] | None = None) -> DataFrame:
    """The tree as d equality joins: at each level the keys within reach become probes, offsets add up, and d is cut."""
    d = cell_dims(cells)
    levels = build_levels(cells) if levels is None else levels
    r = ClusterSpec(1, 1).reach(d)
    front = cells.select(*ks(d)).distinct().withColumn("offset", F.lit(0).cast("bigint"))
    for j in range(1, d + 1):
        # the number of keys within reach is at most 2 r + 1
        front = front.withColumn(f"n{j}", F.explode(F.sequence(F.greatest(F.col(f"k{j}") - r, F.lit(0)), F.col(f"k{j}") + r)))
        gap = F.greatest(F.abs(F.col(f"n{j}") - F.col(f"k{j}")) - 1, F.lit(0))
        front = front.withColumn("offset", F.col("offset") + gap * gap).where(F.col("offset") < d)
        front = front.join(levels[j - 1].select(*[F.col(f"k{i}").alias(f"n{i}") for i in range(1, j + 1)]), [f"n{i}" for i in range(1, j + 1)])
    same = reduce(lambda a, b: a & b, [F.col(f"n{j}") == F.col(f"k{j}") for j in range(1, d + 1)])
    return front.where(~same).select(*ks(d), *[f"n{j}" for j in range(1, d + 1)], F.col("offset").cast("int").alias("offset"))


def _table(keys: np.ndarray, tree, own: np.ndarray, reach: int) -> pa.Table:
    d = keys.shape[1]
    q, other, off = tree.query(own, reach)
    out = {f"k{j + 1}": own[q, j] for j in range(d)} | {f"n{j + 1}": keys[other, j] for j in range(d)} | {"offset": off.astype(np.int32)}
    return pa.table({k: pa.array(v) for k, v in out.items()})


def _schema(d: int) -> str:
    return ", ".join(f"{c} bigint" for c in _named(d)[:-1]) + ", offset int"


def by_broadcast(cells: DataFrame, limit: int = BROADCAST_CELLS) -> DataFrame:
    """The whole tree on every executor, behind a check of its size; beyond the limit the block strategy answers."""
    d = cell_dims(cells)
    own = cells.select(*ks(d)).distinct()
    rows = own.limit(limit + 1).toArrow() if own.limit(limit + 1).count() <= limit else None
    if rows is None:
        return by_block(cells)
    keys = np.stack([rows.column(k).to_numpy() for k in ks(d)], axis=1).astype(np.int64) if rows.num_rows else np.empty((0, d), np.int64)
    keys = keys[np.lexsort([keys[:, j] for j in range(d - 1, -1, -1)])]
    shared = cells.sparkSession.sparkContext.broadcast(keys)
    reach = ClusterSpec(1, 1).reach(d)

    def run(batches):
        tree = PrefixTree(shared.value)
        for batch in batches:
            part = np.stack([batch.column(j).to_numpy() for j in range(d)], axis=1).astype(np.int64)
            for k in range(0, len(part), 4096):
                yield from _table(shared.value, tree, part[k : k + 4096], reach).to_batches()

    return own.select(*[F.col(k).cast("bigint") for k in ks(d)]).mapInArrow(run, _schema(d))


def in_blocks(cells: DataFrame, block_cells: int = 60_000) -> tuple[DataFrame, int]:
    """Distinct cells with block and home, copied to the blocks within the reach, and the reach."""
    d = cell_dims(cells)
    own = cells.select(*[F.col(k).cast("bigint") for k in ks(d)]).distinct()
    spec = ClusterSpec(1, 1, block_points=block_cells)
    reach = spec.reach(d)
    return blocks.to_blocks(own, blocks.plan_blocks(own, spec)), reach


def block_keys(part: pa.Table, d: int) -> tuple[np.ndarray, np.ndarray]:
    """The cells of a block in lexicographic order, and which of them are home."""
    keys = np.stack([part.column(k).to_numpy() for k in ks(d)], axis=1).astype(np.int64)
    order = np.lexsort([keys[:, j] for j in range(d - 1, -1, -1)])
    return keys[order], part.column("home").to_numpy()[order]


def by_block(cells: DataFrame, tree: str = "prefix", block_cells: int = 60_000) -> DataFrame:
    """One exchange: blocks of cells with a halo of the reach, a tree for each block, home cells ask."""
    d = cell_dims(cells)
    dealt, reach = in_blocks(cells, block_cells)

    def run(part: pa.Table) -> pa.Table:
        keys, home = block_keys(part, d)
        index = PrefixTree(keys) if tree == "prefix" else RectTree(keys)
        asked = keys[home]
        return pa.concat_tables([_table(keys, index, asked[k : k + 4096], reach) for k in range(0, max(1, len(asked)), 4096)])

    return dealt.groupBy("block").applyInArrow(run, _schema(d))


def by_pairs(cells: DataFrame) -> DataFrame:
    """All pairs of cells: the definition, for small data and tests only."""
    d = cell_dims(cells)
    own = cells.select(*ks(d)).distinct()
    other = own.select(*[F.col(f"k{j}").alias(f"n{j}") for j in range(1, d + 1)])
    gaps = [F.greatest(F.abs(F.col(f"n{j}") - F.col(f"k{j}")) - 1, F.lit(0)) for j in range(1, d + 1)]
    off = reduce(lambda a, b: a + b, [g * g for g in gaps])
    differ = reduce(lambda a, b: a | b, [F.col(f"n{j}") != F.col(f"k{j}") for j in range(1, d + 1)])
    return own.join(other, (off < d) & differ).withColumn("offset", off.cast("int")).select(_named(d))


STRATEGIES = {"template": by_template, "prefix": by_prefix, "broadcast": by_broadcast, "block": by_block, "rtree": lambda c: by_block(c, tree="rect"), "pairwise": by_pairs}


def neighbour_cells(cells: DataFrame, method: str = "block") -> DataFrame:
    return STRATEGIES[method](cells)


def neighbour_lists(cells: DataFrame, method: str = "block") -> DataFrame:
    """For each cell with a neighbour the array of (offset, neighbour), ascending."""
    d = cell_dims(cells)
    return neighbour_cells(cells, method).groupBy(*ks(d)).agg(F.array_sort(F.collect_list(F.struct("offset", *[f"n{j}" for j in range(1, d + 1)]))).alias("nbrs"))


def choose(cells: DataFrame, budget: int = 50_000_000) -> str:
    """Template where its rows are few, the broadcast tree where the cells are few, else blocks."""
    d, n = cell_dims(cells), cells.count()
    if d <= 3 and len(template(d)) * n <= budget:
        return "template"
    return "broadcast" if n <= BROADCAST_CELLS // 8 else "block"
