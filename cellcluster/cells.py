"""Cells of side eps / sqrt(d): exact identifiers, the table of non-empty cells, its order and extent."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .spec import dims, ks, xs


def exact_cell(t: Column, eps: int, parts: int) -> Column:
    """The largest k with k² eps² <= t² parts, for t >= 0; a rounded guess is put right by integer comparison.

    With ``parts = d`` the side of a cell is eps / sqrt(d).
    """
    guess = F.floor(t.cast("double") * (math.sqrt(parts) / eps)).cast("bigint")
    square, e2 = t * t * parts, eps * eps
    return F.when((guess + 1) * (guess + 1) * e2 <= square, guess + 1).when(guess * guess * e2 > square, guess - 1).otherwise(guess)


def origin(ps: DataFrame) -> list[int]:
    row = ps.agg(*[F.min(x).alias(x) for x in xs(dims(ps))]).first()
    return [row[x] or 0 for x in xs(dims(ps))]


def assign_cells(ps: DataFrame, eps: int, side: str = "sqrt_d", at: list[int] | None = None) -> DataFrame:
    """``ps`` with cell identifiers k1, k2, ...; the origin is the smallest coordinate of each dimension.

    ``sqrt_d`` gives cells whose diagonal is eps, ``sqrt2`` the same in the
    plane only, ``double`` cells of side 2 eps, ``eps`` of side eps.
    """
    d = dims(ps)
    if side == "sqrt2" and d != 2:
        raise ValueError("sqrt2 is a side for the plane")
    eps_, parts = {"sqrt_d": (eps, d), "sqrt2": (eps, 2), "double": (2 * eps, 1), "eps": (eps, 1)}[side]
    at = origin(ps) if at is None else at
    return ps.withColumns({f"k{j}": exact_cell(F.col(f"x{j}") - F.lit(at[j - 1]), eps_, parts) for j in range(1, d + 1)})


def offset(a: str, b: str, d: int) -> Column:
    """Sum over dimensions of max(|difference| - 1, 0) squared; cells from d on are farther apart than eps."""
    one = lambda j: F.greatest(F.abs(F.col(f"{a}k{j}") - F.col(f"{b}k{j}")) - 1, F.lit(0))
    return reduce(lambda x, y: x + y, [one(j) * one(j) for j in range(1, d + 1)])


def cell_summary(cells: DataFrame, core: str | None = None) -> DataFrame:
    """The non-empty cells with their count and box, aggregated before the shuffle."""
    d = dims(cells)
    more = [F.count_if(F.col(core)).alias("n_core")] if core else []
    return cells.groupBy(*ks(d)).agg(F.count(F.lit(1)).alias("n_pts"), *more, *[f(x).alias(f"{n}{x[1:]}") for x in xs(d) for n, f in (("lo", F.min), ("hi", F.max))])


def extent(cells: DataFrame) -> int:
    """The largest component of any identifier."""
    return cells.agg(F.max(F.greatest(*[F.col(k) for k in ks(dims(cells))], F.lit(0)))).first()[0] or 0


def partition_cells(cells: DataFrame, order: str = "range") -> DataFrame:
    """Points of a cell side by side: sorted ranges of identifiers (tight file statistics), or hashed."""
    k = ks(dims(cells))
    return cells.repartitionByRange(*k).sortWithinPartitions(*k) if order == "range" else cells.repartition(*k)


def check_cell_order(ordered: DataFrame) -> DataFrame:
    """Rows of an ordered result, as its partitions hold them, that stand behind a larger cell; empty if the order holds.

    Rows are compared with the one before in their partition, first rows with
    the largest cell of any partition before.
    """
    key = F.struct(*ks(dims(ordered)))
    rows = ordered.select(key.alias("k"), F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at"))
    inside = rows.withColumn("before", F.lag("k").over(W.partitionBy("part").orderBy("at")))
    # one row a partition
    ends = rows.groupBy("part").agg(F.min("k").alias("first"), F.max("k").alias("last"))
    across = ends.withColumn("before", F.max("last").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)))
    return inside.where("before > k").select("part", "k").unionByName(across.where("before > first").select("part", F.col("first").alias("k")))


def radix_order(keys: np.ndarray) -> np.ndarray:
    """Row order after stable passes from the last dimension to the first, each a counting sort."""
    order = np.arange(len(keys))
    for j in range(keys.shape[1] - 1, -1, -1):
        order = order[np.argsort(keys[order, j], kind="stable")]
    return order
