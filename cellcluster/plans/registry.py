"""Registered queries of the clustering engine, with the SQL that checks them.

Every result has only integers, strings and exact doubles, so both engines give
the same rows. Queries without SQL are listed in the README with their tests.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cellcluster import baselines, cells, cluster, fixtures, gaptest, measures, merge, neighbours
from cellcluster.components import durable
from cellcluster.functions.surface import cell_of, register_functions
from cellcluster.operators import joins
from cellcluster.points import collapse_duplicates, from_table, normalise, planning_sample, within_box
from cellcluster.sources import generators
from cellcluster.sources.tables import register, table
from cellcluster.spec import ClusterSpec, dims, ks, xs
from cellcluster.streaming import events as streaming

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def spec_of(name: str) -> ClusterSpec:
    s = fixtures.SETS[name]
    return ClusterSpec(s.eps, s.min_pts)


def _member(method: Callable[..., cluster.ClusterResult], name: str, **how) -> Query:
    return lambda spark, d: method(fixtures.points(spark, d, name), spec_of(name), **how).membership


# --- whole methods: one answer, point by point in SQL -------------------------------------------------
for _n in fixtures.SETS:
    add(f"membership_{_n}", _member(cluster.cell_exact, _n), fixtures.membership_sql(_n))
for _method, _sets in (
    (cluster.cell_exact_ldf, ("part", "events", "docs7")), (baselines.ball_block_exact, ("part", "docs")), (baselines.hash_grid_exact, ("part", "docs")), (baselines.grid_bcp, ("docs", "embed4")),
    (baselines.centre_filter_grid, ("pages",)), (baselines.plane_grid, ("part", "cust")), (baselines.planar_front, ("part", "events")), (baselines.pointwise, ("part", "pages")), (baselines.local_ball, ("cust",)),
):
    for _n in _sets:
        add(f"{_method.__name__}_{_n}", _member(_method, _n), fixtures.membership_sql(_n))


def _with(name: str, tail: str) -> str:
    s = fixtures.SETS[name]
    return fixtures.cluster_sql(s.eps, s.min_pts, s.d, fixtures.points_sql(name)) + tail


def _result(spark: SparkSession, d: str, name: str) -> cluster.ClusterResult:
    return cluster.cell_exact(fixtures.points(spark, d, name), spec_of(name))


add("cluster_sizes_events", lambda s, d: measures.cluster_sizes(_result(s, d, "events").membership), _with("events", "SELECT cluster_id, count(*) AS n_points, count(*) FILTER (role = 'core') AS n_core FROM membership WHERE cluster_id IS NOT NULL GROUP BY 1"))
add("role_counts_part", lambda s, d: measures.role_counts(_result(s, d, "part").membership), _with("part", "SELECT role, count(*) AS n_points, count(*) FILTER (n > 1) AS n_multi FROM (SELECT point_id, role, count(*) AS n FROM membership GROUP BY 1, 2) GROUP BY 1"))
add("n_clusters_docs", lambda s, d: measures.n_clusters(_result(s, d, "docs").membership), _with("docs", "SELECT count(DISTINCT cluster_id) AS clusters FROM membership"))
add("labels_part", lambda s, d: _result(s, d, "part").labels(), _with("part", "SELECT point_id, min(cluster_id) AS cluster_id, any_value(role) AS role FROM membership GROUP BY 1"))
add("noise_part", lambda s, d: _result(s, d, "part").membership.where("role = 'noise'").select("point_id"), _with("part", "SELECT point_id FROM membership WHERE role = 'noise'"))
add("top_clusters_events", lambda s, d: measures.cluster_sizes(_result(s, d, "events").membership).orderBy(F.desc("n_points"), "cluster_id").limit(5), _with("events", "SELECT cluster_id, count(*) AS n_points, count(*) FILTER (role = 'core') AS n_core FROM membership WHERE cluster_id IS NOT NULL GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 5"))


def _cluster_by_region(s: SparkSession, d: str) -> DataFrame:
    m = _result(s, d, "cust").labels()
    c = table(s, d, "customer", ["c_custkey", "c_nationkey"])
    n, r = table(s, d, "nation", ["n_nationkey", "n_regionkey"]), table(s, d, "region")  # two small dimension tables; the engine checks their size
    full = m.join(c, m.point_id == c.c_custkey).join(n, F.col("c_nationkey") == n.n_nationkey).join(r, F.col("n_regionkey") == r.r_regionkey)
    return full.groupBy("r_name", "role").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("cluster_id").alias("clusters"))


_LABEL = "l AS (SELECT point_id, min(cluster_id) AS cluster_id, any_value(role) AS role FROM membership GROUP BY 1) "
add("cluster_by_region", _cluster_by_region, _with("cust", ", " + _LABEL + "SELECT r_name, role, count(*) AS n, count(DISTINCT cluster_id) AS clusters FROM l JOIN customer ON point_id = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2"))


def _role_cube(s: SparkSession, d: str) -> DataFrame:
    m, c = _result(s, d, "cust").labels(), table(s, d, "customer", ["c_custkey", "c_mktsegment"])
    return m.join(c, m.point_id == c.c_custkey).cube("c_mktsegment", "role").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("gid"))


add("role_cube_segment", _role_cube, _with("cust", ", " + _LABEL + "SELECT c_mktsegment, role, count(*) AS n, CAST(grouping_id(c_mktsegment, role) AS INT) AS gid FROM l JOIN customer ON point_id = c_custkey GROUP BY CUBE (c_mktsegment, role)"))


def _toxicity(s: SparkSession, d: str) -> DataFrame:
    m = _result(s, d, "docs").labels()
    l_ = table(s, d, "labels", ["doc_id", "toxic"])
    return m.join(l_, m.point_id == l_.doc_id).groupBy("cluster_id").agg(F.count(F.lit(1)).alias("labelled"), F.sum("toxic").alias("toxic"))


add("doc_cluster_toxicity", _toxicity, _with("docs", ", " + _LABEL + "SELECT cluster_id, count(*) AS labelled, sum(toxic) AS toxic FROM l JOIN labels ON point_id = doc_id GROUP BY 1"))


# --- points, cells, index ------------------------------------------------------------------------------
def _p(name: str, tail: str) -> str:
    return f"WITH {fixtures.points_sql(name)} {tail}"


def _cell_sql(name: str) -> str:
    """p with exact identifiers; the guess is corrected by integer comparison as in the definition."""
    s = fixtures.SETS[name]
    lows = ", ".join(f"min(x{j}) AS m{j}" for j in range(1, s.d + 1))
    t = lambda j: f"((x{j} - m{j}) * (x{j} - m{j}) * {s.d})"
    g = lambda j: f"CAST(floor(sqrt(CAST({t(j)} AS DOUBLE)) / {s.eps}) AS BIGINT)"
    k = ", ".join(f"CASE WHEN ({g(j)} + 1) * ({g(j)} + 1) * {s.eps**2} <= {t(j)} THEN {g(j)} + 1 WHEN {g(j)} * {g(j)} * {s.eps**2} > {t(j)} THEN {g(j)} - 1 ELSE {g(j)} END AS k{j}" for j in range(1, s.d + 1))
    return f"WITH {fixtures.points_sql(name)}, low AS (SELECT {lows} FROM p), c AS MATERIALIZED (SELECT p.*, {k} FROM p, low)"


def _placed(s: SparkSession, d: str, name: str) -> DataFrame:
    return cells.assign_cells(fixtures.points(s, d, name), fixtures.SETS[name].eps)


add("normalise_events", lambda s, d: fixtures.points(s, d, "events"), _p("events", "SELECT * FROM p"))
add("features_docs", lambda s, d: fixtures.raw(s, d, "docs7"), _p("docs7", "SELECT * FROM raw"))
add("points_line3", lambda s, d: fixtures.points(s, d, "line3"), _p("line3", "SELECT * FROM p"))
add("cells_events", lambda s, d: _placed(s, d, "events"), _cell_sql("events") + " SELECT * FROM c")
add("cells_embed4", lambda s, d: _placed(s, d, "embed4"), _cell_sql("embed4") + " SELECT * FROM c")
add("cell_table_events", lambda s, d: cells.cell_summary(_placed(s, d, "events")), _cell_sql("events") + " SELECT k1, k2, count(*) AS n_pts, min(x1) AS lo1, max(x1) AS hi1, min(x2) AS lo2, max(x2) AS hi2 FROM c GROUP BY 1, 2")
add("cell_extent_events", lambda s, d: s.createDataFrame([(cells.extent(_placed(s, d, "events")),)], "eta bigint"), _cell_sql("events") + " SELECT max(greatest(k1, k2)) AS eta FROM c")
add("dense_cells_events", lambda s, d: cells.cell_summary(_placed(s, d, "events")).where("n_pts >= 10").select("k1", "k2", "n_pts"), _cell_sql("events") + " SELECT k1, k2, count(*) AS n_pts FROM c GROUP BY 1, 2 HAVING count(*) >= 10")
add("distinct_cells_events", lambda s, d: _placed(s, d, "events").agg(F.count_distinct("k1", "k2").alias("cells"), F.count_distinct("k1").alias("columns")), _cell_sql("events") + " SELECT count(DISTINCT (k1, k2)) AS cells, count(DISTINCT k1) AS columns FROM c")


def _levels(s: SparkSession, d: str) -> DataFrame:
    return measures.index_profile(_placed(s, d, "part"), 5).select("level", "nodes", "indexed")


add("levels_part", _levels, _cell_sql("part") + ", a AS (SELECT DISTINCT k1 FROM c), b AS (SELECT k1, count(DISTINCT k2) AS n FROM c GROUP BY 1) SELECT 1 AS level, count(*) AS nodes, CASE WHEN count(*) > 5 THEN count(*) ELSE 0 END AS indexed FROM a UNION ALL SELECT 2, sum(n)::BIGINT, coalesce(sum(n) FILTER (n > 5), 0)::BIGINT FROM b")
_NEAR = ", u AS (SELECT DISTINCT {k} FROM c) SELECT {k}, {n}, CAST(offs AS INT) AS \"offset\" FROM (SELECT {ak}, {bn}, {off} AS offs FROM u a, u b WHERE {differ}) WHERE offs < {d}"


def _near_sql(name: str) -> str:
    d = fixtures.SETS[name].d
    r = range(1, d + 1)
    gap = " + ".join(f"greatest(abs(a.k{j} - b.k{j}) - 1, 0) * greatest(abs(a.k{j} - b.k{j}) - 1, 0)" for j in r)
    return _cell_sql(name) + _NEAR.format(k=", ".join(f"k{j}" for j in r), n=", ".join(f"n{j}" for j in r), ak=", ".join(f"a.k{j}" for j in r), bn=", ".join(f"b.k{j} AS n{j}" for j in r), off=gap, differ=" OR ".join(f"a.k{j} <> b.k{j}" for j in r), d=d)


for _m in ("template", "prefix", "broadcast", "block", "rtree", "pairwise"):
    add(f"neighbours_part_{_m}", lambda s, d, m=_m: neighbours.neighbour_cells(_placed(s, d, "part"), m), _near_sql("part"))
for _m in ("prefix", "block"):
    add(f"neighbours_embed4_{_m}", lambda s, d, m=_m: neighbours.neighbour_cells(_placed(s, d, "embed4"), m), _near_sql("embed4"))
add("eps_pairs_part", lambda s, d: baselines.eps_pairs(fixtures.points(s, d, "part"), 2500), f"WITH {fixtures.points_sql('part')}, {fixtures.near_sql(2, 2500)} SELECT i, j FROM near")
add("eps_pairs_theta_cust", lambda s, d: baselines.eps_pairs(fixtures.points(s, d, "cust"), 2500, "theta"), f"WITH {fixtures.points_sql('cust')}, {fixtures.near_sql(2, 2500)} SELECT i, j FROM near")


def _core(s: SparkSession, d: str, name: str, early: bool = True) -> DataFrame:
    spec = ClusterSpec(fixtures.SETS[name].eps, fixtures.SETS[name].min_pts, early_stop=early)
    return cluster.mark_core(fixtures.points(s, d, name), spec)[0].select("point_id", "is_core")


_FLAGS = "SELECT point_id, point_id IN (SELECT i FROM core) AS is_core FROM p"
for _n in ("part", "line3", "docs7"):
    add(f"core_{_n}", lambda s, d, n=_n: _core(s, d, n), _with(_n, _FLAGS))
add("core_no_early_stop_part", lambda s, d: _core(s, d, "part", False), _with("part", _FLAGS))
add("core_pointwise_part", lambda s, d: baselines.core_pointwise(fixtures.points(s, d, "part"), spec_of("part")), f"WITH {fixtures.points_sql('part')}, {fixtures.near_sql(2, 2500)} SELECT i AS point_id, count(*) AS n FROM near GROUP BY 1 HAVING count(*) >= 5")


def _core_cells(s: SparkSession, d: str, name: str) -> DataFrame:
    return cluster.mark_core(fixtures.points(s, d, name), spec_of(name))[0].groupBy(*ks(fixtures.SETS[name].d)).agg(F.count_if("is_core").alias("n_core")).where("n_core > 0")


def _merge_edges(s: SparkSession, d: str) -> DataFrame:
    """Pairs of core cells with a core pair within eps, from every exact gap test where all agree."""
    spec = spec_of("part")
    flagged = durable(cluster.mark_core(fixtures.points(s, d, "part"), spec)[0])
    core = flagged.where("is_core").withColumn("cell", F.concat_ws(",", *ks(2)))
    near = neighbours.neighbour_cells(core.select(*ks(2)).distinct(), "block")
    pairs = durable(near.select(F.concat_ws(",", "k1", "k2").alias("a"), F.concat_ws(",", "n1", "n2").alias("b")).where("a < b"))
    found = None
    for gap in ("alternating_prune", "brute", "closest_pair", "nn_index", "centre_filter", "planar_front"):
        edges = baselines.pair_edges(core, pairs, spec.eps, gap).withColumn("gap", F.lit(gap))
        found = edges if found is None else found.unionByName(edges)
    return found.groupBy("a", "b").agg(F.count(F.lit(1)).alias("tests_that_say_yes"))


_MERGE = _cell_sql("part").replace("WITH ", "WITH RECURSIVE ", 1) + f", {fixtures.near_sql(2, 2500)}, core AS (SELECT i FROM near GROUP BY i HAVING count(*) >= 5), w AS (SELECT point_id, k1 || ',' || k2 AS cell FROM c WHERE point_id IN (SELECT i FROM core)) "
add("core_cells_part", lambda s, d: _core_cells(s, d, "part"), _cell_sql("part") + f", {fixtures.near_sql(2, 2500)}, core AS (SELECT i FROM near GROUP BY i HAVING count(*) >= 5) SELECT k1, k2, count(*) AS n_core FROM c WHERE point_id IN (SELECT i FROM core) GROUP BY 1, 2")
add("merge_edges_part", _merge_edges, _MERGE + "SELECT a.cell AS a, b.cell AS b, CAST(6 AS BIGINT) AS tests_that_say_yes FROM near JOIN w a ON near.i = a.point_id JOIN w b ON near.j = b.point_id WHERE a.cell < b.cell GROUP BY 1, 2")


def _gap_distance(s: SparkSession, d: str) -> DataFrame:
    """Least squared distance of neighbouring core cells, as a join and an aggregate."""
    flagged = durable(cluster.mark_core(fixtures.points(s, d, "part"), spec_of("part"))[0]).where("is_core")
    near = neighbours.neighbour_cells(flagged.select(*ks(2)).distinct(), "template").where("k1 < n1 OR (k1 = n1 AND k2 < n2)")
    right = flagged.select(F.col("k1").alias("n1"), F.col("k2").alias("n2"), *[F.col(x).alias(f"y_{x}") for x in xs(2)])
    return near.join(flagged, ks(2)).join(right, ["n1", "n2"]).groupBy("k1", "k2", "n1", "n2").agg(F.min(baselines.square(2)).alias("least"))


add("gap_min_distance_part", _gap_distance, _cell_sql("part") + f", {fixtures.near_sql(2, 2500)}, core AS (SELECT i FROM near GROUP BY i HAVING count(*) >= 5), w AS (SELECT * FROM c WHERE point_id IN (SELECT i FROM core)) SELECT a.k1, a.k2, b.k1 AS n1, b.k2 AS n2, min((a.x1 - b.x1) ** 2 + (a.x2 - b.x2) ** 2)::BIGINT AS least FROM w a JOIN w b ON (a.k1 < b.k1 OR (a.k1 = b.k1 AND a.k2 < b.k2)) AND b.k1 - a.k1 <= 2 AND abs(a.k2 - b.k2) <= 2 AND greatest(abs(a.k1 - b.k1) - 1, 0) ** 2 + greatest(abs(a.k2 - b.k2) - 1, 0) ** 2 < 2 GROUP BY 1, 2, 3, 4")


# --- statements that must hold: nothing is found -------------------------------------------------------
_ZERO = "SELECT CAST(0 AS BIGINT) AS violations"
_count = lambda df: df.agg(F.count(F.lit(1)).alias("violations"))


def _axioms(s: SparkSession, d: str) -> DataFrame:
    ps = durable(fixtures.points(s, d, "part"))
    return _count(measures.check_axioms(cluster.cell_exact(ps, spec_of("part")), ps, spec_of("part")))


def _sandwich(kind: str) -> Query:
    def query(s: SparkSession, d: str) -> DataFrame:
        ps, spec = durable(fixtures.points(s, d, "part")), spec_of("part")
        wide = spec.eps + 250
        mid = baselines.rho_grid(ps, spec, 0.1) if kind == "rho" else cluster.cell_delta(ps, spec, 250)
        return _count(measures.check_sandwich(cluster.cell_exact(ps, spec), mid, cluster.cell_exact(ps, ClusterSpec(wide, spec.min_pts))))

    return query


def _orders_agree(s: SparkSession, d: str) -> DataFrame:
    ps, spec = durable(fixtures.points(s, d, "docs")), spec_of("docs")
    return _count(measures.same_clustering(cluster.cell_exact(ps, spec).membership, cluster.cell_exact_ldf(ps, spec, tree="rect").membership))


add("axioms_part", _axioms, _ZERO)
add("sandwich_rho_part", _sandwich("rho"), _ZERO)
add("sandwich_delta_part", _sandwich("delta"), _ZERO)
add("orders_agree_docs", _orders_agree, _ZERO)


def _kappa(s: SparkSession, d: str) -> DataFrame:
    """Runs whose gap tests took more than 11 iterations."""
    profile = cluster.cell_exact(fixtures.points(s, d, "events"), spec_of("events"), boxes=False).merge_profile()
    return _count(profile.where("kappa > 11"))


add("kappa_events", _kappa, _ZERO)
# rows only: what depends on the order of a baseline's choices
add("ball_block_part", _member(baselines.ball_block, "part"))
add("sampled_expansion_part", _member(baselines.sampled_expansion, "part"))
add("rho_grid_part", _member(baselines.rho_grid, "part"))
add("merge_profile_events", lambda s, d: cluster.cell_exact(fixtures.points(s, d, "events"), spec_of("events")).merge_profile())
add("merge_profile_ldf_events", lambda s, d: cluster.cell_exact_ldf(fixtures.points(s, d, "events"), spec_of("events")).merge_profile())
add("block_profile_part", lambda s, d: baselines.block_profile(baselines.ball_block_exact(fixtures.points(s, d, "part"), spec_of("part"))))
add("grid_profile_events", lambda s, d: measures.grid_profile(_placed(s, d, "events")))
add("pca_embed4", lambda s, d: generators.pca_points(table(s, d, "embeddings"), "embedding", "vec_id", 4))

# --- generators ----------------------------------------------------------------------------------------
_walk = lambda s, d, name, key, *a, **how: generators.walk_over(table(s, d, name), key, *a, **how)
add("generator_even_2d", lambda s, d: _walk(s, d, "events", "event_id", 20_000, 2, kind="even"), generators.walk_sql(20_000, 2, "events", "event_id", kind="even"))
add("generator_varied_3d", lambda s, d: _walk(s, d, "orders", "o_orderkey", 20_000, 3, kind="varied", seed=5), generators.walk_sql(20_000, 3, "orders", "o_orderkey", kind="varied", seed=5))
add("membership_walk_2d", lambda s, d: cluster.cell_exact(_walk(s, d, "customer", "c_custkey", 5_000, 2, kind="varied"), ClusterSpec(1000, 10)).membership, fixtures.cluster_sql(1000, 10, 2, f"p AS MATERIALIZED ({generators.walk_sql(5_000, 2, 'customer', 'c_custkey', kind='varied')})") + "SELECT point_id, cluster_id, role FROM membership")
add("membership_walk_7d", lambda s, d: cluster.cell_exact_ldf(_walk(s, d, "customer", "c_custkey", 5_000, 7, kind="even"), ClusterSpec(4500, 10)).membership, fixtures.cluster_sql(4500, 10, 7, f"p AS MATERIALIZED ({generators.walk_sql(5_000, 7, 'customer', 'c_custkey', kind='even')})") + "SELECT point_id, cluster_id, role FROM membership")

# --- scans, filters, scalar functions ------------------------------------------------------------------
add("scan_part_pruned", lambda s, d: table(s, d, "part", ["p_partkey", "p_retailprice"], "p_size BETWEEN 10 AND 20"), "SELECT p_partkey, p_retailprice FROM part WHERE p_size BETWEEN 10 AND 20")
add("box_filter_orders", lambda s, d: within_box(fixtures.points(s, d, "orders"), [20000, 20000], [40000, 60000]), _p("orders", "SELECT * FROM p WHERE x1 BETWEEN 20000 AND 40000 AND x2 BETWEEN 20000 AND 60000"))
add("hash_sample_orders", lambda s, d: planning_sample(fixtures.points(s, d, "orders"), 7), _p("orders", "SELECT * FROM p WHERE point_id % 7 = 0"))
add("dup_collapse_docs", lambda s, d: collapse_duplicates(fixtures.points(s, d, "docs")), _p("docs", "SELECT min(point_id) AS point_id, x1, x2, x3, count(*) AS weight FROM p GROUP BY x1, x2, x3"))
add("text_predicates_docs", lambda s, d: table(s, d, "documents").where(F.col("text").like("%the%") & F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 3000)).select("doc_id", F.when(F.col("n_chars") > 1000, "long").otherwise("short").alias("size")), "SELECT doc_id, CASE WHEN n_chars > 1000 THEN 'long' ELSE 'short' END AS size FROM documents WHERE text LIKE '%the%' AND lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 3000")
add("string_features_docs", lambda s, d: table(s, d, "documents").select("doc_id", F.length("text").cast("bigint").alias("n"), F.upper(F.substring("source", 1, 3)).alias("s"), F.concat_ws("-", "lang", "source").alias("tag"), F.levenshtein("lang", "source").cast("bigint").alias("lev")), "SELECT doc_id, length(text) AS n, upper(substr(source, 1, 3)) AS s, concat_ws('-', lang, source) AS tag, levenshtein(lang, source) AS lev FROM documents")
add("url_parts_pages", lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", "://([^/?#]+)", 1).alias("host"), F.size(F.split("url", "/")).cast("bigint").alias("parts")), "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host, CAST(len(string_split(url, '/')) AS BIGINT) AS parts FROM pages")
add("date_features_orders", lambda s, d: table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"), F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM-dd").alias("first")), "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first FROM orders")
add("json_props_events", lambda s, d: table(s, d, "events").select("event_id", F.length(F.get_json_object("props", "$.page")).isNotNull().alias("has_page"), F.length("props").cast("bigint").alias("n")), "SELECT event_id, json_extract_string(props, '$.page') IS NOT NULL AS has_page, length(props) AS n FROM events")
add("array_ops_embed", lambda s, d: table(s, d, "embeddings").select("vec_id", F.size("embedding").cast("bigint").alias("n"), F.size(F.filter("embedding", lambda v: v > 0)).cast("bigint").alias("positive"), F.exists("embedding", lambda v: v > 2).alias("any_large")), "SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda v: v > 0)) AS positive, len(list_filter(embedding, lambda v: v > 2)) > 0 AS any_large FROM embeddings")
add("math_cells", lambda s, d: _placed(s, d, "part").select("point_id", F.pmod("k1", F.lit(3)).alias("m"), F.greatest("k1", "k2").alias("g"), F.shiftleft("k1", 2).alias("sl"), (F.col("k1") * F.col("k1") + F.col("k2")).alias("q")), _cell_sql("part") + " SELECT point_id, k1 % 3 AS m, greatest(k1, k2) AS g, k1 * 4 AS sl, k1 * k1 + k2 AS q FROM c")
add("pair_metrics_supp", lambda s, d: (lambda a, b: joins.packed_join(a, b.withColumnRenamed("c_nationkey", "s_nationkey"), ["s_nationkey"], "s_suppkey", "c_custkey").select("s_suppkey", "c_custkey", joins.metric([F.col("s_suppkey")], [F.col("c_custkey")], "manhattan").alias("l1"), joins.metric([F.col("s_suppkey"), F.col("s_nationkey").cast("bigint")], [F.col("c_custkey"), F.lit(3).cast("bigint")], "chebyshev").alias("linf")))(table(s, d, "supplier"), table(s, d, "customer")), "SELECT s_suppkey, c_custkey, abs(s_suppkey - c_custkey) AS l1, greatest(abs(s_suppkey - c_custkey), abs(s_nationkey - 3)) AS linf FROM supplier JOIN customer ON s_nationkey = c_nationkey")


def _map_roles(s: SparkSession, d: str) -> DataFrame:
    m = _result(s, d, "part").labels().where("cluster_id IS NOT NULL").groupBy("cluster_id", "role").agg(F.count(F.lit(1)).alias("n"))
    roles = m.groupBy("cluster_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("roles"))
    return roles.select("cluster_id", F.coalesce(F.element_at("roles", F.lit("core")), F.lit(0)).alias("core"), F.coalesce(F.element_at("roles", F.lit("border")), F.lit(0)).alias("border"), F.size("roles").cast("bigint").alias("kinds"))


add("map_roles_part", _map_roles, _with("part", ", " + _LABEL + "SELECT cluster_id, count(*) FILTER (role = 'core') AS core, count(*) FILTER (role = 'border') AS border, count(DISTINCT role) AS kinds FROM l WHERE cluster_id IS NOT NULL GROUP BY 1"))

# --- joins ----------------------------------------------------------------------------------------------
add("band_join_supp_cust", lambda s, d: joins.band_join(table(s, d, "supplier", ["s_suppkey", "s_acctbal"]), table(s, d, "customer", ["c_custkey", "c_acctbal"]), "s_acctbal", "c_acctbal", 50.0).select("s_suppkey", "c_custkey"), "SELECT s_suppkey, c_custkey FROM supplier JOIN customer ON abs(s_acctbal - c_acctbal) <= 50.0")


def _two(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    a = table(s, d, "supplier").select("s_suppkey", F.floor("s_acctbal").alias("ax"), (F.col("s_nationkey") * 100).cast("bigint").alias("ay"))
    b = table(s, d, "customer").select("c_custkey", F.floor("c_acctbal").alias("bx"), (F.col("c_nationkey") * 100).cast("bigint").alias("by"))
    return a, b


_TWO = "WITH a AS (SELECT s_suppkey, CAST(floor(s_acctbal) AS BIGINT) AS ax, s_nationkey * 100 AS ay FROM supplier), b AS (SELECT c_custkey, CAST(floor(c_acctbal) AS BIGINT) AS bx, c_nationkey * 100 AS \"by\" FROM customer), j AS (SELECT s_suppkey, c_custkey, (ax - bx) * (ax - bx) + (ay - \"by\") * (ay - \"by\") AS sq FROM a, b) "
for _how in ("inner", "semi", "anti"):
    add(f"eps_join_{_how}", lambda s, d, how=_how: (lambda t: joins.eps_join(*t, 300, ["ax", "ay"], ["bx", "by"], how).select("s_suppkey", *(["c_custkey"] if how == "inner" else [])))(_two(s, d)), _TWO + {"inner": "SELECT s_suppkey, c_custkey FROM j WHERE sq <= 90000", "semi": "SELECT DISTINCT s_suppkey FROM j WHERE sq <= 90000", "anti": "SELECT s_suppkey FROM a WHERE s_suppkey NOT IN (SELECT s_suppkey FROM j WHERE sq <= 90000)"}[_how])
add("knn_supp_cust", lambda s, d: (lambda t: joins.knn_join(*t, 3, ["ax", "ay"], ["bx", "by"], "s_suppkey", "c_custkey", 300))(_two(s, d)).select("s_suppkey", "c_custkey", "sq", F.col("rank").cast("bigint").alias("rank")), _TWO + "SELECT * FROM (SELECT s_suppkey, c_custkey, sq, row_number() OVER (PARTITION BY s_suppkey ORDER BY sq, c_custkey) AS rank FROM j) WHERE rank <= 3")


def _asof(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").select("event_id", "ts", "user_id", "event_type")
    left = e.where("event_type <> 'click'").select("event_id", "ts", "user_id")
    right = e.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("event"))
    return joins.asof_join(left, right, "ts", ["user_id"], ["event"]).select("event_id", "last_event")


add("asof_events", _asof, "WITH r AS (SELECT user_id, ts, max(event_id) AS event FROM events WHERE event_type = 'click' GROUP BY 1, 2) SELECT e.event_id, r.event AS last_event FROM (SELECT * FROM events WHERE event_type <> 'click') e ASOF LEFT JOIN r ON e.user_id = r.user_id AND e.ts >= r.ts")


def _intervals(s: SparkSession, d: str) -> DataFrame:
    part = table(s, d, "part")
    side = lambda n, m: part.where(F.col("p_partkey") % 2 == m).select(F.col("p_partkey").alias(f"{n}_id"), (F.col("p_size") * 10).cast("bigint").alias(f"{n}_lo"), (F.col("p_size") * 10 + F.col("p_partkey") % 15).cast("bigint").alias(f"{n}_hi"))
    return joins.interval_join(side("a", 0), side("b", 1), ("a_lo", "a_hi"), ("b_lo", "b_hi"), 25).select("a_id", "b_id")


add("interval_all_parts", _intervals, "WITH i AS (SELECT p_partkey AS id, p_size * 10 AS lo, p_size * 10 + p_partkey % 15 AS hi FROM part) SELECT a.id AS a_id, b.id AS b_id FROM i a JOIN i b ON a.id % 2 = 0 AND b.id % 2 = 1 AND a.lo <= b.hi AND b.lo <= a.hi")
add("orders_lineitem_smj", lambda s, d: table(s, d, "lineitem", ["l_orderkey", "l_linenumber"]).join(table(s, d, "orders", ["o_orderkey", "o_orderstatus"]).hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("salted_join_orders", lambda s, d: joins.salted_join(table(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_suppkey"]), table(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), ["l_orderkey"], 4).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")), "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
add("labels_full_outer", lambda s, d: table(s, d, "documents", ["doc_id"]).withColumn("d", F.lit(1)).join(table(s, d, "labels", ["doc_id", "quality"]), "doc_id", "full").groupBy("quality").agg(F.count("d").alias("docs")), "SELECT quality, count(d) AS docs FROM (SELECT doc_id, 1 AS d FROM documents) FULL JOIN labels USING (doc_id) GROUP BY 1")
add("grid_product", lambda s, d: table(s, d, "region", ["r_regionkey"]).crossJoin(table(s, d, "nation", ["n_nationkey"])), "SELECT r_regionkey, n_nationkey FROM region CROSS JOIN nation")


def _lateral(s: SparkSession, d: str) -> DataFrame:
    register(s, d, ("nation", "customer"))
    return s.sql("SELECT n_nationkey, c_custkey, c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")


add("lateral_topk", _lateral, "SELECT n_nationkey, c_custkey, c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")

# --- aggregates, windows, sets --------------------------------------------------------------------------
add("cell_members_part", lambda s, d: _placed(s, d, "part").groupBy("k1", "k2").agg(F.concat_ws(",", F.array_sort(F.collect_list("point_id")).cast("array<string>")).alias("members")), _cell_sql("part") + " SELECT k1, k2, string_agg(CAST(point_id AS VARCHAR), ',' ORDER BY point_id) AS members FROM c GROUP BY 1, 2")
add("cell_percentiles_events", lambda s, d: cells.cell_summary(_placed(s, d, "events")).agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY n_pts)").cast("bigint").alias("p50"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY n_pts)").cast("bigint").alias("p90"), F.max("n_pts").alias("top")), _cell_sql("events") + ", n AS (SELECT count(*) AS n_pts FROM c GROUP BY k1, k2) SELECT quantile_disc(n_pts, 0.5) AS p50, quantile_disc(n_pts, 0.9) AS p90, max(n_pts) AS top FROM n")
add("ldf_order_part", lambda s, d: _core_cells(s, d, "part").withColumn("turn", F.row_number().over(W.partitionBy("k1").orderBy("n_core", "k2")).cast("bigint")).select("k1", "k2", "n_core", "turn"), _cell_sql("part") + f", {fixtures.near_sql(2, 2500)}, core AS (SELECT i FROM near GROUP BY i HAVING count(*) >= 5), n AS (SELECT k1, k2, count(*) AS n_core FROM c WHERE point_id IN (SELECT i FROM core) GROUP BY 1, 2) SELECT k1, k2, n_core, row_number() OVER (PARTITION BY k1 ORDER BY n_core, k2) AS turn FROM n")
add("cell_runs_part", lambda s, d: _placed(s, d, "part").select("k1", "k2").distinct().withColumn("starts", F.coalesce(F.col("k2") - F.lag("k2").over(W.partitionBy("k1").orderBy("k2")) > 1, F.lit(True))), _cell_sql("part") + " SELECT k1, k2, coalesce(k2 - lag(k2) OVER (PARTITION BY k1 ORDER BY k2) > 1, true) AS starts FROM (SELECT DISTINCT k1, k2 FROM c)")
add("neighbours_1d_range", lambda s, d: table(s, d, "customer").select("c_custkey", "c_nationkey", F.floor("c_acctbal").alias("x")).select("c_custkey", F.count(F.lit(1)).over(W.partitionBy("c_nationkey").orderBy("x").rangeBetween(-200, 200)).alias("n")), "SELECT c_custkey, count(*) OVER (PARTITION BY c_nationkey ORDER BY CAST(floor(c_acctbal) AS BIGINT) RANGE BETWEEN 200 PRECEDING AND 200 FOLLOWING) AS n FROM customer")
add("sessions_1d", lambda s, d: joins.gap_sessions(table(s, d, "events").select("event_id", "user_id", F.expr("unix_seconds(CAST(ts AS TIMESTAMP))").alias("t")), ["user_id"], "t", 3600, ["event_id"]).groupBy("user_id").agg(F.max("session").alias("sessions")), "SELECT user_id, sum(n)::BIGINT AS sessions FROM (SELECT user_id, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) > 3600 IS NOT FALSE THEN 1 ELSE 0 END AS n FROM (SELECT user_id, event_id, epoch_us(ts) // 1000000 AS t FROM events)) GROUP BY 1")
for _op, _word in (("unionByName", "UNION ALL"), ("intersect", "INTERSECT"), ("exceptAll", "EXCEPT ALL")):
    add(f"setops_{_op}", lambda s, d, op=_op: getattr(table(s, d, "customer").select(F.col("c_nationkey").alias("n")), op)(table(s, d, "supplier").select(F.col("s_nationkey").alias("n"))), f"SELECT c_nationkey AS n FROM customer {_word} SELECT s_nationkey FROM supplier")
add("rollup_orders", lambda s, d: table(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
add("pivot_events", lambda s, d: table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view")), "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")

# --- functions for SQL, streams (batch forms of the same operators) -------------------------------------


def _udtf(s: SparkSession, d: str) -> DataFrame:
    register_functions(s)
    fixtures.points(s, d, "cust").join(table(s, d, "customer").select(F.col("c_custkey").alias("point_id"), F.col("c_nationkey").cast("bigint").alias("g")), "point_id").select("g", "point_id", "x1", "x2").createOrReplaceTempView("udtf_points")
    return s.sql("SELECT * FROM density_cluster(TABLE(udtf_points) PARTITION BY (g), 2500, 3)")


_GROUPED = _p("cust", ", q AS (SELECT point_id, c_nationkey AS g, x1 FROM p JOIN customer ON point_id = c_custkey), near AS (SELECT a.g, a.point_id AS i, b.point_id AS j FROM q a JOIN q b ON a.g = b.g AND abs(a.x1 - b.x1) <= 2500), core AS (SELECT g, i FROM near GROUP BY 1, 2 HAVING count(*) >= 3) SELECT g, i AS point_id FROM core")
add("udtf_density_cluster", lambda s, d: _udtf(s, d).where("role = 'core'").select("g", "point_id"), _GROUPED)
add("udf_cell_of_part", lambda s, d: (lambda p: p.select("point_id", F.concat_ws(",", cell_of(F.array("x1", "x2"), F.array(F.lit(0).cast("bigint"), F.lit(0).cast("bigint")), F.lit(2500)).cast("array<string>")).alias("cell")))(fixtures.points(s, d, "part")), _cell_sql("part") + " SELECT point_id, k1 || ',' || k2 AS cell FROM c")
_ts = lambda s, d: streaming.timed(table(s, d, "events"))
_EPOCH = "CAST(epoch_us({}) // 1000000 AS BIGINT)"
add("events_tumbling", lambda s, d: streaming.windowed_counts(_ts(s, d), "1 day").withColumn("start", F.unix_seconds("start")), f"SELECT {_EPOCH.format('ts')} // 86400 * 86400 AS start, event_type, count(*) AS n, count(value) AS n_values FROM events GROUP BY 1, 2")
add("events_sliding", lambda s, d: streaming.windowed_counts(_ts(s, d), "6 hours", "1 hour").withColumn("start", F.unix_seconds("start")), f"SELECT ({_EPOCH.format('ts')} // 3600 - o) * 3600 AS start, event_type, count(*) AS n, count(value) AS n_values FROM events, (SELECT unnest(range(6)) AS o) GROUP BY 1, 2")
add("events_session", lambda s, d: streaming.session_counts(_ts(s, d), "30 minutes").select(F.unix_micros("start").alias("start"), "user_id", "n"), "SELECT min(t) AS start, user_id, count(*) AS n FROM (SELECT user_id, t, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS k FROM (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, k")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: cluster labels of the event points."""
    return cluster.cell_exact(fixtures.points(spark, sf_dir, "events"), ClusterSpec(2000, 5)).labels()


def _counts(s: SparkSession, d: str) -> DataFrame:
    from cellcluster.workloads import cluster_counts

    return s.createDataFrame([tuple(r.values()) for r in cluster_counts(s, d)], "kind string, eps bigint, exact bigint, approximate bigint, flagship bigint, adjusted_rand double")


def _ablation(s: SparkSession, d: str) -> DataFrame:
    from cellcluster.workloads import merge_ablation

    return s.createDataFrame([(r["set"], r["order"], r["gap"], r["components"], r["checks"], r["kappa"], r["distances"]) for r in merge_ablation(s, d)], "name string, turn string, gap string, components bigint, checks bigint, kappa bigint, distances bigint")


def _index(s: SparkSession, d: str) -> DataFrame:
    from cellcluster.workloads import index_ablation

    return s.createDataFrame([(r["set"], r["eps"], r["tree"], r["cells"], float(r["mean_nbr"]), r["visited"]) for r in (*index_ablation(s, d), *index_ablation(s, d, ("embed4",), (12000,)))], "name string, eps bigint, tree string, cells bigint, mean_nbr double, visited bigint")


add("workload_w3_cluster_counts", _counts)
add("workload_w9_index", _index)
add("workload_w10_merge_orders", _ablation)

from cellcluster.plans import surface  # noqa: E402, F401  it adds its queries to the two tables
