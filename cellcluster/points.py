"""Point sets: features of tables, integer coordinates, rejected rows, collapsed duplicates."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .components import durable
from .spec import dims, xs

DOMAIN = 100_000


def from_table(df: DataFrame, point_id: str | Column, features: dict[str, Column] | list[Column]) -> DataFrame:
    """point_id and raw features f1, f2, ... as doubles, from any table."""
    columns = list(features.values()) if isinstance(features, dict) else features
    own = F.col(point_id) if isinstance(point_id, str) else point_id
    return df.select(own.cast("bigint").alias("point_id"), *[c.cast("double").alias(f"f{j}") for j, c in enumerate(columns, 1)])


def raw_dims(df: DataFrame) -> int:
    return sum(1 for c in df.columns if c[0] == "f" and c[1:].isdigit())


def reject_invalid(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows with finite features and an id, and the others."""
    fine = [F.col("point_id").isNotNull()]
    for j in range(1, raw_dims(df) + 1):
        f = F.col(f"f{j}")
        fine.append(f.isNotNull() & ~F.isnan(f) & (F.abs(f) < float("inf")))
    good = F.coalesce(reduce(lambda a, b: a & b, fine), F.lit(False))
    return df.where(good), df.where(~good)


def bounds(df: DataFrame) -> list[tuple[float, float]]:
    """Smallest and largest value of each feature: two numbers a dimension for the driver."""
    d = raw_dims(df)
    row = df.agg(*[f(f"f{j}").alias(f"{n}{j}") for j in range(1, d + 1) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return [(row[f"lo{j}"], row[f"hi{j}"]) for j in range(1, d + 1)]


def normalise(df: DataFrame, domain: int = DOMAIN, given: list[tuple[float, float]] | None = None, on_invalid: str = "reject") -> DataFrame:
    """Integer coordinates x1, x2, ... in [0, domain]; a constant feature becomes 0.

    The bounds of the table join in as one row of numbers, or are given. Rows
    with nulls, NaN or infinities are left out, or raise with ``fail``.
    """
    good, bad = reject_invalid(df)
    if on_invalid == "fail" and not bad.isEmpty():
        raise ValueError("null, NaN or infinite features")
    lo_hi = bounds(good) if given is None else given

    def scaled(j: int, lo: float | None, hi: float | None) -> Column:
        if lo is None or hi is None or hi == lo:
            return F.lit(0).cast("bigint").alias(f"x{j}")
        return F.floor((F.col(f"f{j}") - F.lit(lo)) * F.lit(float(domain)) / (F.lit(hi) - F.lit(lo)) + 0.5).cast("bigint").alias(f"x{j}")

    return good.select("point_id", *[scaled(j, *b) for j, b in enumerate(lo_hi, 1)])


def denormalise(ps: DataFrame, lo_hi: list[tuple[float, float]], domain: int = DOMAIN) -> DataFrame:
    """Feature values at the middle of what rounds to each coordinate."""
    return ps.select("point_id", *[(F.col(f"x{j}") * ((hi - lo) / domain) + F.lit(lo)).alias(f"f{j}") for j, (lo, hi) in enumerate(lo_hi, 1)])


def within_box(ps: DataFrame, low: list[int], high: list[int]) -> DataFrame:
    return ps.where(reduce(lambda a, b: a & b, [F.col(f"x{j}").between(a, b) for j, (a, b) in enumerate(zip(low, high, strict=True), 1)]))


def within_ball(ps: DataFrame, centre: list[int], radius: int) -> DataFrame:
    """Points within ``radius``; the box around the ball is a filter that a scan can use."""
    inside = within_box(ps, [c - radius for c in centre], [c + radius for c in centre])
    return inside.where(reduce(lambda a, b: a + b, [(F.col(f"x{j}") - c) * (F.col(f"x{j}") - c) for j, c in enumerate(centre, 1)]) <= radius * radius)


def collapse_duplicates(ps: DataFrame) -> DataFrame:
    """One row for each place: the smallest point_id and the number of points as weight, which core counts honour."""
    return ps.groupBy(*xs(dims(ps))).agg(F.min("point_id").alias("point_id"), F.count(F.lit(1)).alias("weight")).select("point_id", *xs(dims(ps)), "weight")


def expand_duplicates(membership: DataFrame, ps: DataFrame, collapsed: DataFrame) -> DataFrame:
    """The membership of all points of ``ps`` from that of the places in ``collapsed``; clusters keep their names, as a place is named by its smallest point."""
    place = collapsed.select(F.col("point_id").alias("at"), *xs(dims(ps)))
    return ps.join(place, xs(dims(ps))).select("point_id", "at").join(membership.withColumnRenamed("point_id", "at"), "at").select("point_id", "cluster_id", "role")


def planning_sample(df: DataFrame, one_in: int, key: str = "point_id") -> DataFrame:
    """A repeatable share of the rows, for planning only."""
    return df.where(F.pmod(F.col(key), F.lit(one_in)) == 0)


def global_rank(df: DataFrame, keys: list[str], out: str = "point_id") -> DataFrame:
    """Row number in the order of ``keys``, from range partitions and their counts: no single task sees all rows."""
    ranged = durable(df.repartitionByRange(*keys).withColumn("__part", F.spark_partition_id()))
    sizes = ranged.groupBy("__part").count().orderBy("__part").collect()  # one number a partition
    before, total = {}, 0
    for r in sizes:
        before[r["__part"]], total = total, total + r["count"]
    if not before:
        return ranged.withColumn(out, F.lit(0).cast("bigint")).drop("__part")
    start = F.create_map(*[F.lit(v) for kv in before.items() for v in kv])
    own = F.row_number().over(W.partitionBy("__part").orderBy(*keys))
    return ranged.withColumn(out, (own + F.element_at(start, F.col("__part"))).cast("bigint")).drop("__part")


def check_unique_ids(ps: DataFrame) -> DataFrame:
    """Ids that occur more than once; empty for a valid point set."""
    return ps.groupBy("point_id").count().where("count > 1")
