"""Joins that Spark lacks, as equality joins on bins with a residual, and skew-safe forms."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Values of a list that travels as one row, tasks over which pairs of lists are dealt, and lists of one side that stay together then.
PACK, DEALT, STRIPE = 512, 96, 4


def band_join(a: DataFrame, b: DataFrame, left: str, right: str, width: float) -> DataFrame:
    """Rows with |left - right| <= width: the right side is copied to three bins."""
    x = a.withColumn("__bin", F.floor(F.col(left) / width))
    near = F.sequence(F.floor(F.col(right) / width) - 1, F.floor(F.col(right) / width) + 1)
    y = b.withColumn("__bin", F.explode(near))
    return x.join(y, "__bin").where(F.abs(F.col(left) - F.col(right)) <= width).drop("__bin")


def eps_join(a: DataFrame, b: DataFrame, eps: float, left: list[str], right: list[str], how: str = "inner") -> DataFrame:
    """Rows within Euclidean distance ``eps``; ``semi`` and ``anti`` keep rows of ``a``. Bins of eps in up to three dimensions."""
    k = min(len(left), 3)
    bins = [f"__g{j}" for j in range(k)]
    x = a.withColumns({g: F.floor(F.col(c) / eps) for g, c in zip(bins, left, strict=False)})
    y = b
    for g, c in zip(bins, right, strict=False):
        y = y.withColumn(g, F.explode(F.sequence(F.floor(F.col(c) / eps) - 1, F.floor(F.col(c) / eps) + 1)))
    near = reduce(lambda s, t: s + t, [(F.col(c) - F.col(e)) * (F.col(c) - F.col(e)) for c, e in zip(left, right, strict=True)]) <= eps * eps
    if how == "inner":
        return x.join(y, bins).where(near).drop(*bins)
    renamed = y.withColumnsRenamed({g: f"__r{g}" for g in bins})
    same = reduce(lambda s, t: s & t, [F.col(g) == F.col(f"__r{g}") for g in bins])
    return x.join(renamed, same & near, f"left_{how}").drop(*bins)


def interval_join(a: DataFrame, b: DataFrame, a_ends: tuple[str, str], b_ends: tuple[str, str], bin_width: float) -> DataFrame:
    """Rows whose closed intervals overlap: distinct intervals are copied to the bins they touch, a pair is kept in the first common one, and the rows of both come in last."""
    spread = lambda df, ends, n: df.select(*ends).distinct().withColumn(n, F.explode(F.sequence(F.floor(F.col(ends[0]) / bin_width), F.floor(F.col(ends[1]) / bin_width))))
    # the side with the bins may be far larger than its plan says, so it is not broadcast
    both = spread(a, a_ends, "__bin").join(spread(b, b_ends, "__bin").hint("merge"), "__bin")
    first = F.greatest(F.floor(F.col(a_ends[0]) / bin_width), F.floor(F.col(b_ends[0]) / bin_width))
    pairs = both.where((F.col(a_ends[0]) <= F.col(b_ends[1])) & (F.col(b_ends[0]) <= F.col(a_ends[1])) & (F.col("__bin") == first)).drop("__bin")
    # few intervals may be those of many rows, so these meet as lists that are unfolded last; a null is kept inside of its struct
    more = lambda df, ends: [c for c in df.columns if c not in ends]
    rows = lambda df, ends, n: packs(df.select(*ends, F.struct(*[F.col(c) for c in more(df, ends)] or [F.lit(0)]).alias(n)), list(ends), n, f"{n}s")
    left, right = rows(a, a_ends, "__a"), rows(b, b_ends, "__b")
    met = dealt_lists(pairs.join(left.hint("merge"), list(a_ends)), right, list(b_ends), "__bs_no")
    pick = lambda df, ends, n: [F.col(c) if c in ends else F.col(f"{n}.`{c}`") for c in df.columns]
    return unfold(met, ("__as", "__a"), ("__bs", "__b"), *a_ends, *b_ends).select(*pick(a, a_ends, "__a"), *pick(b, b_ends, "__b"))


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str], values: list[str]) -> DataFrame:
    """For each row of ``left`` the values of the last row of ``right`` with the same keys at or before its time."""
    cols = [c for c in left.columns]
    l_ = left.select(*cols, *[F.lit(None).cast(right.schema[v].dataType).alias(f"last_{v}") for v in values], F.lit(1).alias("__side"), F.struct(*[F.lit(True).alias("own")]).alias("__own"))
    r_ = right.select(*[F.col(c) if c in (on, *by) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], *[F.col(v).alias(f"last_{v}") for v in values], F.lit(0).alias("__side"), F.lit(None).cast("struct<own:boolean>").alias("__own"))
    both = l_.unionByName(r_)
    w = W.partitionBy(*by).orderBy(on, "__side").rowsBetween(W.unboundedPreceding, W.currentRow)
    # values of one row travel together, so a null among them is not filled from an older row
    last = F.last(F.when(F.col("__side") == 0, F.struct(*[f"last_{v}" for v in values])), ignorenulls=True).over(w)
    return both.withColumn("__last", last).where(F.col("__own").isNotNull()).select(*cols, *[F.col(f"__last.last_{v}").alias(f"last_{v}") for v in values])


def knn_join(a: DataFrame, b: DataFrame, k: int, left: list[str], right: list[str], a_id: str, b_id: str, cell: float, most: int = 40) -> DataFrame:
    """The k nearest rows of ``b`` for each row of ``a`` (squared distance, then id): rings of cells grow until the k-th is surely inside."""
    from cellcluster.components import durable

    # rows of one place share their distances: places search, and of a place of b the k smallest ids can be among the nearest
    square = reduce(lambda s, t: s + t, [(F.col(c) - F.col(e)) * (F.col(c) - F.col(e)) for c, e in zip(left, right, strict=True)])
    rank = F.row_number().over(W.partitionBy(*left).orderBy("sq", b_id))
    total = b.limit(k).count()
    few = b.select(b_id, *right).withColumn("__r", F.row_number().over(W.partitionBy(*right).orderBy(b_id))).where(F.col("__r") <= k)
    at = durable(few.groupBy(*right).agg(F.collect_list(b_id).alias("__ids")))
    out, open_, reach = None, durable(a.select(*left).distinct()), 1
    for _ in range(most):
        near = eps_join(open_, at, cell * reach, left, right).withColumn("sq", square)
        best = near.select(*left, "sq", F.explode("__ids").alias(b_id)).withColumn("rank", rank).where(F.col("rank") <= k)
        best = durable(best)
        done = best.groupBy(*left).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= total).select(*left)
        found = best.join(done, left, "left_semi")
        out = found if out is None else out.unionByName(found)
        open_ = durable(open_.join(done, left, "left_anti"))
        if open_.isEmpty():
            return a.select(a_id, *left).join(out, left).select(a_id, b_id, "sq", "rank")
        reach *= 2
    raise RuntimeError("some rows have no neighbour within the widest ring")


def salted_join(big: DataFrame, small: DataFrame, keys: list[str], salts: int, how: str = "inner") -> DataFrame:
    """An equality join whose frequent keys are dealt over ``salts`` partitions: the small side is copied to each."""
    spread = F.pmod(F.xxhash64(*big.columns), F.lit(salts)).cast("int")
    return big.withColumn("__salt", spread).join(small.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))), [*keys, "__salt"], how).drop("__salt")


def packs(df: DataFrame, by: list[str], col: str, out: str, size: int = PACK) -> DataFrame:
    """The values of ``col`` of rows with equal ``by``, ascending, in lists of ``size`` at most; ``out``_no numbers the lists."""
    turn = F.row_number().over(W.partitionBy(*by).orderBy(col))
    return df.select(*by, col).withColumn(f"{out}_no", F.floor((turn - 1) / size)).groupBy(*by, f"{out}_no").agg(F.array_sort(F.collect_list(col)).alias(out))


def unfold(df: DataFrame, first: tuple[str, str], second: tuple[str, str], *more: str) -> DataFrame:
    """All pairs of the values of two lists of each row: (list, name of a value) twice, and further columns."""
    return df.select(F.explode(first[0]).alias(first[1]), second[0], *more).select(first[1], F.explode(second[0]).alias(second[1]), *more)


def packed_join(a: DataFrame, b: DataFrame, keys: list[str], left: str, right: str, dealt: int = DEALT) -> DataFrame:
    """``keys``, ``left`` and ``right`` of all rows of equal keys, where these are few and frequent: lists meet, and pairs of lists are dealt over tasks before they are unfolded."""
    return unfold(dealt_lists(packs(a, keys, left, "__a"), packs(b, keys, right, "__b"), keys, "__b_no", dealt), ("__a", left), ("__b", right), *keys)


def dealt_lists(a: DataFrame, b: DataFrame, keys: list[str], no: str, dealt: int = DEALT) -> DataFrame:
    """Pairs of lists of equal keys, made in the tasks that unfold them: lists of ``a`` are copied to each stripe of ``STRIPE`` lists (``no``) of ``b``, so no pair is written.

    Tasks go through one stripe after another, so writers meet few values at a time.
    """
    dealt = max(dealt, int(a.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    b = b.withColumn("__stripe", F.floor(F.col(no) / STRIPE))
    stripes = b.select(*keys, "__stripe").distinct()
    a = a.join(stripes.hint("merge"), keys)
    return a.repartition(dealt, *keys, "__stripe").join(b.repartition(dealt, *keys, "__stripe").hint("merge"), [*keys, "__stripe"]).drop("__stripe")


def gap_sessions(df: DataFrame, by: list[str], col: str, gap: int, order: list[str]) -> DataFrame:
    """Session number within the keys: a new one starts where the gap to the row before exceeds ``gap``."""
    w = W.partitionBy(*by).orderBy(col, *order)
    new = F.coalesce((F.col(col) - F.lag(col).over(w)) > gap, F.lit(True)).cast("int")
    return df.withColumn("__new", new).withColumn("session", F.sum("__new").over(w.rowsBetween(W.unboundedPreceding, W.currentRow))).drop("__new")


def metric(a: list[Column], b: list[Column], kind: str = "euclid2") -> Column:
    diff = [x - y for x, y in zip(a, b, strict=True)]
    add = lambda v: reduce(lambda s, t: s + t, v)
    if kind == "euclid2":
        return add([e * e for e in diff])
    if kind == "manhattan":
        return add([F.abs(e) for e in diff])
    if kind == "chebyshev":
        return F.greatest(*[F.abs(e) for e in diff]) if len(diff) > 1 else F.abs(diff[0])
    dot, na, nb = add([x * y for x, y in zip(a, b, strict=True)]), add([x * x for x in a]), add([y * y for y in b])
    return 1 - dot / F.sqrt(na * nb)
