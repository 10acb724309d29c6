"""More registered queries: the definitions as relations, choices of the methods, loads of blocks, and relational forms around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cellcluster import baselines, cells, cluster, fixtures, measures, neighbours, points, workloads
from cellcluster.components import durable
from cellcluster.operators import joins
from cellcluster.plans import registry
from cellcluster.plans.registry import add, spec_of
from cellcluster.sources.tables import table
from cellcluster.spec import ClusterSpec
from cellcluster.streaming import events as streaming

_with, _p, _cell_sql, _placed = registry._with, registry._p, registry._cell_sql, registry._placed

# --- definitions and choices of the methods -------------------------------------------------------------
_REACH = ", m AS (SELECT DISTINCT lab.c, near.j AS q FROM near JOIN lab ON near.i = lab.i) "
add("direct_reach_cust", lambda s, d: baselines.direct_reach(fixtures.points(s, d, "cust"), spec_of("cust")), _with("cust", "SELECT near.i AS p, near.j AS q FROM near JOIN core USING (i)"))
add("reach_closure_cust", lambda s, d: baselines.reach_closure(fixtures.points(s, d, "cust"), spec_of("cust")), _with("cust", _REACH + "SELECT lab.i AS p, m.q FROM lab JOIN m USING (c)"))
add("connected_pairs_cust", lambda s, d: baselines.connected_pairs(fixtures.points(s, d, "cust"), spec_of("cust")), _with("cust", _REACH + "SELECT DISTINCT a.q AS p, b.q FROM m a JOIN m b ON a.c = b.c AND a.q < b.q"))
for _n in ("part", "events", "docs7"):
    add(f"membership_{_n}_no_boxes", registry._member(cluster.cell_exact, _n, boxes=False), fixtures.membership_sql(_n))
    add(f"membership_{_n}_small_blocks", lambda s, d, n=_n: cluster.cell_exact(fixtures.points(s, d, n), ClusterSpec(fixtures.SETS[n].eps, fixtures.SETS[n].min_pts, block_points=500)).membership, fixtures.membership_sql(_n))


def _collapsed(s: SparkSession, d: str, name: str) -> DataFrame:
    ps = durable(fixtures.points(s, d, name))
    places = durable(points.collapse_duplicates(ps))
    return points.expand_duplicates(cluster.cell_exact(places, spec_of(name)).membership, ps, places)


add("membership_docs_collapsed", lambda s, d: _collapsed(s, d, "docs"), fixtures.membership_sql("docs"))
add("membership_conv_collapsed", lambda s, d: _collapsed(s, d, "conv"), fixtures.membership_sql("conv"))
add(
    "labels_nearest_core_part", lambda s, d: registry._result(s, d, "part").labels("nearest_core"),
    _with("part", ", s AS (SELECT near.i, lab.c, min((a.x1 - b.x1) * (a.x1 - b.x1) + (a.x2 - b.x2) * (a.x2 - b.x2)) AS sq FROM near JOIN lab ON lab.i = near.j JOIN p a ON a.point_id = near.i JOIN p b ON b.point_id = near.j GROUP BY 1, 2), "
          "o AS (SELECT i, arg_min(c, (sq, c)) AS c FROM s GROUP BY 1) SELECT point_id, CASE role WHEN 'border' THEN o.c ELSE cluster_id END AS cluster_id, role FROM (SELECT DISTINCT point_id, role, CASE role WHEN 'core' THEN cluster_id END AS cluster_id FROM membership) LEFT JOIN o ON o.i = point_id"),
)
add("cells_sqrt2_events", lambda s, d: cells.assign_cells(fixtures.points(s, d, "events"), fixtures.SETS["events"].eps, side="sqrt2"), _cell_sql("events") + " SELECT * FROM c")
add("cell_order_written_events", lambda s, d: registry._count(cells.check_cell_order(cells.partition_cells(_placed(s, d, "events")))), registry._ZERO)
add(
    "neighbour_lists_part", lambda s, d: neighbours.neighbour_lists(_placed(s, d, "part")).select("k1", "k2", F.array_join(F.transform("nbrs", lambda n: F.concat_ws(":", n["offset"], n["n1"], n["n2"])), " ").alias("nbrs")),
    registry._near_sql("part").replace("SELECT k1, k2, n1, n2, CAST(offs AS INT) AS \"offset\" FROM", "SELECT k1, k2, string_agg(offs || ':' || n1 || ':' || n2, ' ' ORDER BY offs, n1, n2) AS nbrs FROM") + " GROUP BY 1, 2",
)


def _load(s: SparkSession, d: str) -> DataFrame:
    """Home points of all blocks, and blocks of more home rows than twice the limit; points of one place are one row with a weight, as no cut can part them."""
    load = measures.block_load(durable(fixtures.places(s, d, "events")), ClusterSpec(1000, 10, block_points=500))
    return load.agg(F.sum("home").alias("home"), F.count_if(F.col("rows") > 1000).alias("too_large"))


add("block_load_events", _load, "SELECT count(*) AS home, CAST(0 AS BIGINT) AS too_large FROM events")


def _rand(s: SparkSession, d: str) -> DataFrame:
    m = registry._result(s, d, "part").membership
    strips = fixtures.points(s, d, "part").select("point_id", F.floor(F.col("x1") / 20000).alias("cluster_id"))
    return measures.rand_scores(m, strips).select(F.round("rand", 9).alias("rand"), F.round("adjusted_rand", 9).alias("adjusted_rand"))


_PAIRS = "(SELECT sum(n * (n - 1) / 2) FROM (SELECT count(*) AS n FROM both_ GROUP BY {}))"
add("rand_strips_part", _rand, _with("part", ", a AS (SELECT point_id, coalesce(min(cluster_id), -point_id - 1) AS ca FROM membership GROUP BY 1), both_ AS (SELECT ca, x1 // 20000 AS cb FROM a JOIN p USING (point_id)), "
    f"t AS (SELECT {_PAIRS.format('ca, cb')} AS both_n, {_PAIRS.format('ca')} AS in_a, {_PAIRS.format('cb')} AS in_b, (SELECT count(*) * (count(*) - 1) / 2 FROM both_) AS total) "
    "SELECT round((total + 2 * both_n - in_a - in_b) / total, 9) AS rand, round((both_n - in_a * in_b / total) / ((in_a + in_b) / 2 - in_a * in_b / total), 9) AS adjusted_rand FROM t"))  # fmt: skip

# --- relational forms -----------------------------------------------------------------------------------
add("eps_join_anti_near", lambda s, d: joins.eps_join(*registry._two(s, d), 25, ["ax", "ay"], ["bx", "by"], "anti").select("s_suppkey"), registry._TWO.split(" SELECT s_suppkey")[0] + " SELECT s_suppkey FROM a WHERE NOT EXISTS (SELECT 1 FROM b WHERE (ax - bx) * (ax - bx) + (ay - \"by\") * (ay - \"by\") <= 625)")
add("labels_right_outer", lambda s, d: table(s, d, "labels", ["doc_id", "quality"]).join(table(s, d, "documents", ["doc_id", "lang"]), "doc_id", "right").groupBy("lang").agg(F.count("quality").alias("labelled"), F.count(F.lit(1)).alias("docs")), "SELECT lang, count(quality) AS labelled, count(*) AS docs FROM labels RIGHT JOIN documents USING (doc_id) GROUP BY 1")


def _null_safe(s: SparkSession, d: str) -> DataFrame:
    docs = table(s, d, "documents", ["doc_id", "lang"]).join(table(s, d, "labels", ["doc_id", "quality"]), "doc_id", "left")
    seen = docs.select(F.col("quality").alias("q")).distinct()
    return docs.join(seen, docs["quality"].eqNullSafe(seen["q"])).groupBy("quality").agg(F.count(F.lit(1)).alias("docs"))


add("null_safe_join_labels", _null_safe, "SELECT quality, count(*) AS docs FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")


def _grouping_sets(s: SparkSession, d: str) -> DataFrame:
    table(s, d, "orders").createOrReplaceTempView("grouped_orders")
    return s.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM grouped_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


add("grouping_sets_orders", _grouping_sets, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
add("unpivot_cells_part", lambda s, d: _placed(s, d, "part").unpivot("point_id", ["k1", "k2"], "dim", "k"), _cell_sql("part") + " SELECT point_id, 'k1' AS dim, k1 AS k FROM c UNION ALL SELECT point_id, 'k2', k2 FROM c")


def _sketches(s: SparkSession, d: str) -> DataFrame:
    """Whether a merged sketch, an approximate distinct count and an approximate percentile are within their bounds of the exact answers."""
    rows = _placed(s, d, "events").select(F.concat_ws(",", "k1", "k2").alias("cell"), "k2", (F.col("point_id") % 4).alias("part"))
    merged = rows.groupBy("part").agg(F.hll_sketch_agg("cell", F.lit(12)).alias("h")).agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("merged"))
    direct = rows.agg(F.count_distinct("cell").alias("exact"), F.approx_count_distinct("cell", 0.02).alias("approx"), F.count_if(F.col("k2") <= 0).alias("none"), F.percentile_approx("k2", 0.9, 1000).alias("p90"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY k2)").alias("q90"))
    near = lambda a, b, share: F.abs(F.col(a) - F.col(b)) <= share * F.col(b) + 1
    return merged.crossJoin(direct).select(near("merged", "exact", 0.08).alias("merged"), near("approx", "exact", 0.08).alias("distinct"), near("p90", "q90", 0.02).alias("percentile"))  # two one-row tables


add("sketches_events", _sketches, "SELECT TRUE AS merged, TRUE AS \"distinct\", TRUE AS percentile")
add("decimal_interval_orders", lambda s, d: table(s, d, "orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(14,2)")).cast("decimal(18,2)").cast("string").alias("total"), F.max(F.expr("CAST(o_orderdate AS DATE) + INTERVAL '1' MONTH")).cast("string").alias("due")), "SELECT o_orderstatus, CAST(CAST(sum(CAST(o_totalprice AS DECIMAL(14,2))) AS DECIMAL(18,2)) AS VARCHAR) AS total, CAST(CAST(max(CAST(o_orderdate AS DATE) + INTERVAL 1 MONTH) AS DATE) AS VARCHAR) AS due FROM orders GROUP BY 1")


def _ranks(s: SparkSession, d: str) -> DataFrame:
    w = W.partitionBy("c_nationkey").orderBy("c_mktsegment")
    t = W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    c = table(s, d, "customer")
    return c.select("c_custkey", F.rank().over(w).cast("bigint").alias("r"), F.dense_rank().over(w).cast("bigint").alias("dr"), F.ntile(4).over(t).cast("bigint").alias("quarter"), F.lead("c_custkey").over(t).alias("next"), F.first("c_custkey").over(t).alias("lowest"), F.nth_value("c_custkey", 2).over(t.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("second"))


add("ranks_customer", _ranks, "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER t AS quarter, lead(c_custkey) OVER t AS next, first_value(c_custkey) OVER t AS lowest, nth_value(c_custkey, 2) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment), t AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)")
add("cell_modes_part", lambda s, d: _placed(s, d, "part").groupBy("k1").agg(F.max_by("point_id", F.struct("k2", "point_id")).alias("top"), F.count_if(F.col("k2") > 10).alias("high"), F.min_by("point_id", F.struct("k2", "point_id")).alias("low")), _cell_sql("part") + " SELECT k1, arg_max(point_id, (k2, point_id)) AS top, count(*) FILTER (k2 > 10) AS high, arg_min(point_id, (k2, point_id)) AS low FROM c GROUP BY 1")
add("global_rank_orders", lambda s, d: points.global_rank(table(s, d, "orders", ["o_orderdate", "o_orderkey"]), ["o_orderdate", "o_orderkey"], "turn").select("o_orderkey", "turn"), "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS turn FROM orders")
add("within_ball_orders", lambda s, d: points.within_ball(fixtures.points(s, d, "orders"), [50000, 50000], 20000), _p("orders", "SELECT * FROM p WHERE (x1 - 50000) * (x1 - 50000) + (x2 - 50000) * (x2 - 50000) <= 400000000"))
add("denormalised_cust", lambda s, d: (lambda raw: points.denormalise(points.normalise(raw), points.bounds(raw)).select("point_id", F.round("f1", 3).alias("f1"), F.round("f2", 3).alias("f2")))(fixtures.raw(s, d, "cust")), _p("cust", "SELECT point_id, round(x1 * ((hi1 - lo1) / 100000) + lo1, 3) AS f1, round(x2 * ((hi2 - lo2) / 100000) + lo2, 3) AS f2 FROM p, ends"))



def _expiring(s: SparkSession, d: str) -> DataFrame:
    at = table(s, d, "events", ["event_id", "ts"])
    ps = fixtures.points(s, d, "events").join(at, F.col("point_id") == F.col("event_id"))
    return streaming.expiring_cells(ps, 1000, "6 hours", "2 hours").select(F.unix_seconds("start").alias("start"), "k1", "k2", "n_pts")


add("expiring_cells_events", _expiring, _cell_sql("events") + " SELECT (CAST(epoch_us(ts) // 1000000 AS BIGINT) // 7200 - o) * 7200 AS start, k1, k2, count(*) AS n_pts FROM c JOIN events ON event_id = point_id, (SELECT unnest(range(3)) AS o) GROUP BY 1, 2, 3")

# --- workloads ------------------------------------------------------------------------------------------
for _w in ("W1", "W2", "W4", "W5", "W6", "W7", "W8"):
    add(f"workload_{_w.lower()}_counts", lambda s, d, w=_w: workloads.counted(s, d, w), workloads.counted_sql(_w))
add("workload_w11_kappa", workloads.kappa_rows, "SELECT name, CAST(0 AS BIGINT) AS beyond FROM (VALUES ('part'), ('cust'), ('docs'), ('pages'), ('conv'), ('embed4'), ('docs7'), ('events')) AS t(name)")
