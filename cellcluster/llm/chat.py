"""Chat formatting: cumulative snapshots of a conversation collapse to the longest.

A row of a conversation hashes to 128 bits from its turn, role and text. The
rolling hash of a prefix is the exclusive or of its rows, which is built in two
levels: over blocks of turns, and inside a block, so a conversation with very
many turns is dealt over many tasks. A conversation whose full hash is the hash
of a proper prefix of another is a snapshot and goes (anti-join); of equal ones
the smallest conv_id stays. Only then are the texts read again and rendered, a
part of ``BLOCK`` turn numbers to a row. All steps are DataFrame expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import table

BLOCK = 512


def _turn(df: DataFrame) -> Column:
    return F.coalesce(df["turn"].cast("bigint"), F.lit(-1))


def _usable(conversations: DataFrame) -> DataFrame:
    rows = conversations.where("conv_id IS NOT NULL")
    return rows.select("conv_id", _turn(rows).alias("turn"), rows["role"].cast("string").alias("role"), rows["text"].cast("string").alias("text"))


def _hashed(rows: DataFrame) -> DataFrame:
    parts = ["turn", F.col("role").isNull(), "role", F.col("text").isNull(), "text"]
    return rows.select("conv_id", "turn", F.floor(F.col("turn") / BLOCK).alias("block"), F.xxhash64(F.lit(1), *parts).alias("h1"), F.xxhash64(F.lit(2), *parts).alias("h2")).distinct()


def maximal(conversations: DataFrame) -> DataFrame:
    """conv_id and n_copies of the conversations that no other continues.

    A conversation is the set of its rows (turn, role, text); repeated rows
    count once. It is a snapshot of another if it equals the other's rows up to
    some turn and the other has more. A null turn comes before all others, null
    roles and texts differ from empty ones, and rows without conv_id are left out.
    """
    rows = _hashed(_usable(conversations))
    whole = W.partitionBy("conv_id")
    earlier = whole.orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    blocks = rows.groupBy("conv_id", "block").agg(F.bit_xor("h1").alias("b1"), F.bit_xor("h2").alias("b2"), F.count(F.lit(1)).alias("n"))
    blocks = blocks.select(
        "conv_id", "block",
        *[F.coalesce(F.bit_xor(b).over(earlier), F.lit(0)).alias(f"p{b}") for b in ("b1", "b2")],
        F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"), F.sum("n").over(whole).alias("total"),
    )
    upto = W.partitionBy("conv_id", "block").orderBy("turn").rangeBetween(W.unboundedPreceding, W.currentRow)
    prefixes = rows.join(blocks, ["conv_id", "block"]).select(
        "conv_id", "total", (F.col("before") + F.count(F.lit(1)).over(upto)).alias("n"),
        F.col("pb1").bitwiseXOR(F.bit_xor("h1").over(upto)).alias("x1"), F.col("pb2").bitwiseXOR(F.bit_xor("h2").over(upto)).alias("x2"),
    )
    # of copies one stands for all before any join, so a frequent conversation is one row
    full = prefixes.where("n = total").groupBy("n", "x1", "x2").agg(F.min("conv_id").alias("conv_id"), F.count_distinct("conv_id").alias("n_copies"))
    proper = prefixes.where("n < total").select("n", "x1", "x2").distinct()
    return full.join(proper, ["n", "x1", "x2"], "left_anti").select("conv_id", "n_copies")


def render(conversations: DataFrame, open_mark: str = "<|", close_mark: str = "|>", end: str = "<|end|>") -> DataFrame:
    """conv_id, part, n_turns and text of each part, turns in order; ties by role and text, null text as empty, null role as ``unknown``."""
    rows = _usable(conversations).distinct()
    one = lambda r: F.concat(F.lit(open_mark), F.coalesce(r["role"], F.lit("unknown")), F.lit(close_mark + "\n"), F.coalesce(r["text"], F.lit("")), F.lit(end + "\n"))
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    return (
        rows.groupBy("conv_id", F.floor(F.col("turn") / BLOCK).cast("bigint").alias("part")).agg(turns.alias("turns"))
        .select("conv_id", "part", F.size("turns").cast("bigint").alias("n_turns"), F.concat_ws("", F.transform("turns", one)).alias("text"))
    )


def format_chats(conversations: DataFrame, **marks: str) -> DataFrame:
    """Maximal conversations, rendered; an empty table gives no row."""
    kept = maximal(conversations)
    return render(conversations.join(kept, "conv_id", "left_semi"), **marks).join(kept, "conv_id").select("conv_id", "part", "n_turns", "n_copies", "text")


def op8_snapshot_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_chats(table(spark, sf_dir, "conversations"))


ORACLE = r"""
WITH r AS (SELECT DISTINCT conv_id, coalesce(turn, -1) AS turn, role, text FROM conversations WHERE conv_id IS NOT NULL),
c AS (SELECT conv_id, list({'t': turn, 'r': role, 'x': text} ORDER BY turn, role NULLS FIRST, text NULLS FIRST) AS w FROM r GROUP BY 1),
e AS (SELECT w, min(conv_id) AS conv_id, count(*) AS n_copies FROM c GROUP BY w),
p AS (SELECT DISTINCT w[1:i] AS w FROM (SELECT w, unnest(range(1, len(w))) AS i FROM e) WHERE w[i].t <> w[i + 1].t),
m AS (SELECT conv_id, n_copies FROM e WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.w = e.w))
SELECT conv_id, CAST(floor(turn / 512) AS BIGINT) AS part, count(*) AS n_turns, any_value(n_copies) AS n_copies,
  string_agg('<|' || coalesce(role, 'unknown') || '|>' || chr(10) || coalesce(text, '') || '<|end|>' || chr(10), '' ORDER BY turn, role NULLS FIRST, text NULLS FIRST) AS text
FROM r JOIN m USING (conv_id) GROUP BY 1, 2
"""
