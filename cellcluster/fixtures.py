"""Point sets over the given tables, as SQL that Spark and DuckDB read alike, with default parameters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .points import collapse_duplicates, global_rank, normalise
from .spec import xs


@dataclass(frozen=True)
class PointSet:
    table: str
    key: str
    features: tuple[str, ...]
    eps: int
    min_pts: int
    duck: tuple[tuple[str, str], ...] = ()  # what DuckDB spells otherwise

    @property
    def d(self) -> int:
        return len(self.features)


def _count(text: str, what: str) -> str:
    return f"length({text}) - length(replace({text}, {what}, ''))"


_MICROS = "timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)"
_DAYS = "datediff(o_orderdate, DATE'1995-01-01')"
_LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
_P5 = ("l_extendedprice", "l_discount", "l_tax", "l_linenumber", "CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END")
_NEWLINE = (("'\\n'", "chr(10)"),)

SETS = {
    "part": PointSet("part", "p_partkey", ("p_size", "p_retailprice"), 2500, 5),
    "cust": PointSet("customer", "c_custkey", ("c_acctbal", "c_nationkey"), 2500, 6),
    "orders": PointSet("orders", "o_orderkey", ("o_totalprice", _DAYS), 1000, 8, ((_DAYS, "date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))"),)),
    "events": PointSet("events", "event_id", (_MICROS, "value"), 1000, 10, ((_MICROS, "epoch_us(ts)"),)),
    "conv": PointSet("conversations", "conv_id * 100 + turn", ("turn", "length(text)"), 1000, 10),
    "docs": PointSet("documents", "doc_id", ("n_chars", _count("text", "' '"), _count("text", "'\\n'")), 500, 10, _NEWLINE),
    "pages": PointSet("pages", "page_id", ("length(html)", _count("html", "'<'"), "length(url)"), 3000, 5),
    "line3": PointSet("lineitem", "", ("l_extendedprice", "l_discount", "l_tax"), 500, 10),
    "embed4": PointSet("embeddings", "vec_id", tuple(f"embedding[{k}]" for k in range(4)), 12000, 5, tuple((f"embedding[{k}]", f"embedding[{k + 1}]") for k in range(3, -1, -1))),
    "line5": PointSet("lineitem", "", _P5, 4000, 10),
    "line7": PointSet("lineitem", "", (*_P5, "CASE WHEN l_returnflag = 'A' THEN 1 ELSE 0 END", "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END"), 5000, 5),
    "docs7": PointSet("documents", "doc_id", ("n_chars", _count("text", "' '"), _count("text", "'\\n'"), _count("text", "'.'"), _count("text", "','"), _count("lower(text)", "'e'"), _count("lower(text)", "'a'")), 2000, 10, _NEWLINE),
}


def raw(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """point_id and raw features; line items are ranked, as they have no key."""
    s = SETS[name]
    df = spark.read.parquet(f"{sf_dir}/{s.table}.parquet")
    if not s.key:
        df = global_rank(df.select(*_LINE_KEY, *[c for c in ("l_discount", "l_tax", "l_linestatus", "l_returnflag")]), list(_LINE_KEY))
    return df.select(F.expr(s.key or "point_id").cast("bigint").alias("point_id"), *[F.expr(f).cast("double").alias(f"f{j}") for j, f in enumerate(s.features, 1)])


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return normalise(raw(spark, sf_dir, name))


def places(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The places of a set with their numbers of points as weight; those of line items are ranked themselves, as their points have no key."""
    s = SETS[name]
    if s.key:
        return collapse_duplicates(points(spark, sf_dir, name))
    df = spark.read.parquet(f"{sf_dir}/{s.table}.parquet")
    at = normalise(df.select(F.lit(0).cast("bigint").alias("point_id"), *[F.expr(f).cast("double").alias(f"f{j}") for j, f in enumerate(s.features, 1)]))
    at = at.groupBy(*xs(s.d)).agg(F.count(F.lit(1)).alias("weight"))
    return global_rank(at, xs(s.d)).select("point_id", *xs(s.d), "weight")


def points_sql(name: str) -> str:
    """Common table expressions that end in p(point_id, x1, ...)."""
    s = SETS[name]

    def duck(e: str) -> str:
        for a, b in s.duck:
            e = e.replace(a, b)
        return e

    key = s.key or f"row_number() OVER (ORDER BY {', '.join(_LINE_KEY)})"
    d = range(1, s.d + 1)
    features = ", ".join(f"CAST({duck(f)} AS DOUBLE) AS f{j}" for j, f in enumerate(s.features, 1))
    ends = ", ".join(f"min(f{j}) AS lo{j}, max(f{j}) AS hi{j}" for j in d)
    scaled = ", ".join(f"CAST(CASE WHEN hi{j} = lo{j} THEN 0 ELSE floor((f{j} - lo{j}) * CAST(100000.0 AS DOUBLE) / (hi{j} - lo{j}) + 0.5) END AS BIGINT) AS x{j}" for j in d)
    return f"raw AS (SELECT CAST({key} AS BIGINT) AS point_id, {features} FROM {s.table}), ends AS (SELECT {ends} FROM raw), p AS MATERIALIZED (SELECT point_id, {scaled} FROM raw, ends)"


def near_sql(d: int, eps: int, source: str = "p") -> str:
    """near(i, j): pairs within eps, each point with itself, by bins of eps in up to two dimensions; ``source`` has point_id and x1, ...."""
    binned = range(1, min(d, 2) + 1)
    bins = ", ".join(f"x{j} // {eps} AS g{j}" for j in binned)
    moved = ", ".join(f"g{j} + o{j}.o AS g{j}" for j in binned)
    steps = ", ".join(f"(SELECT unnest([-1, 0, 1]) AS o) o{j}" for j in binned)
    keys = ", ".join(f"g{j}" for j in binned)
    square = " + ".join(f"(a.x{j} - b.x{j}) * (a.x{j} - b.x{j})" for j in range(1, d + 1))
    own = ", ".join(f"x{j}" for j in range(1, d + 1))
    return (
        f"binned AS MATERIALIZED (SELECT point_id, {own}, {bins} FROM {source}), "
        f"probe AS (SELECT point_id, {own}, {moved} FROM binned, {steps}), "
        f"near AS MATERIALIZED (SELECT a.point_id AS i, b.point_id AS j FROM probe a JOIN binned b USING ({keys}) WHERE {square} <= {eps * eps})"
    )


def cluster_sql(eps: int, min_pts: int, d: int, prefix: str) -> str:
    """WITH ... that ends in membership(point_id, cluster_id, role), from the definitions, point by point."""
    return (
        f"WITH RECURSIVE {prefix}, {near_sql(d, eps)}, "
        f"core AS MATERIALIZED (SELECT i FROM near GROUP BY i HAVING count(*) >= {min_pts}), "
        "link AS MATERIALIZED (SELECT i, j FROM near WHERE i IN (SELECT i FROM core) AND j IN (SELECT i FROM core) AND i <> j), "
        "lab(i, c) USING KEY (i) AS (SELECT i, i FROM core UNION SELECT link.i, min(lab.c) FROM lab JOIN link ON link.j = lab.i JOIN recurring.lab AS r ON r.i = link.i WHERE lab.c < r.c GROUP BY link.i), "
        "edge AS (SELECT DISTINCT near.i, lab.c FROM near JOIN lab ON lab.i = near.j WHERE near.i NOT IN (SELECT i FROM core)), "
        "membership AS (SELECT i AS point_id, c AS cluster_id, 'core' AS role FROM lab UNION ALL SELECT i, c, 'border' FROM edge "
        "UNION ALL SELECT point_id, NULL, 'noise' FROM p WHERE point_id NOT IN (SELECT i FROM core) AND point_id NOT IN (SELECT i FROM edge)) "
    )


def membership_sql(name: str, eps: int | None = None, min_pts: int | None = None) -> str:
    s = SETS[name]
    return cluster_sql(eps or s.eps, min_pts or s.min_pts, s.d, points_sql(name)) + "SELECT point_id, cluster_id, role FROM membership"
