"""Connected components of an undirected graph by alternating star operations.

Large-star hangs the larger neighbours of every vertex on its smallest
neighbour; small-star does so with the smaller ones. The pair is repeated until
nothing changes, which leaves one star for each component, centred on its
smallest vertex. A vertex of very many edges is aggregated before the shuffle.
A graph of few edges, whose number is known once they are written, is joined by
union-find in one task instead. Vertices of one edge stay out of the rounds.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most edges that one task joins; some ten megabytes.
FEW = 200_000


def durable(df: DataFrame) -> DataFrame:
    """The rows, written to the shared folder of ``spark.checkpoint.dir``; only where none is set, to a temporary one."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="cellcluster-"))
    return df.checkpoint(eager=True)


class UnionFind:
    """Sets of numbers with path halving; the smallest number names a set."""

    def __init__(self, n: int):
        self.parent = list(range(n))

    def find(self, x: int) -> int:
        p = self.parent
        while p[x] != x:
            p[x] = p[p[x]]
            x = p[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        self.parent[max(x, y)] = min(x, y)
        return True


def _in_one_task(e: DataFrame) -> DataFrame:
    kind = e.schema["a"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = list(batches)
        if not sum(p.num_rows for p in parts):
            return
        a, b = (pa.concat_arrays([p.column(k) for p in parts]) for k in (0, 1))
        vertices = pc.unique(pa.concat_arrays([a, b]))
        vertices = vertices.take(pc.sort_indices(vertices))
        sets = UnionFind(len(vertices))
        for x, y in zip(pc.index_in(a, vertices).to_pylist(), pc.index_in(b, vertices).to_pylist(), strict=True):
            sets.join(x, y)
        least = np.array([sets.find(k) for k in range(len(vertices))])
        yield pa.RecordBatch.from_arrays([vertices, vertices.take(pa.array(least))], names=["vertex", "component"])

    return e.select("a", "b").coalesce(1).mapInArrow(run, f"vertex {kind}, component {kind}")


def _roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest vertex of the component of each: roots hang on smaller ones until no edge joins two."""
    root = np.arange(n)
    while len(a):
        x, y = root[a], root[b]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
    return root


def task_forest(edges: DataFrame, most: int = 1 << 20) -> DataFrame:
    """Edges (a, b) of numbers that join what ``edges`` joins, at most one for each vertex of a task and ``most`` edges met: sets are joined as the rows come."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, held = np.empty((0, 2), np.int64), []

        def join() -> np.ndarray:
            pairs = np.concatenate([kept, *held])
            ids, at = np.unique(pairs, return_inverse=True)
            at = at.reshape(pairs.shape)
            star = np.stack([ids[_roots(len(ids), at[:, 0], at[:, 1])], ids], axis=1)
            return star[star[:, 0] != star[:, 1]]

        size = 0
        for b in batches:
            held.append(np.stack([b.column(k).to_numpy() for k in (0, 1)], axis=1))
            size += b.num_rows
            if size >= most:
                kept, held, size = join(), [], 0
        if held:
            kept = join()
        yield pa.RecordBatch.from_arrays([pa.array(kept[:, 0]), pa.array(kept[:, 1])], names=["a", "b"])

    return edges.select("a", "b").mapInArrow(run, "a bigint, b bigint")


def star_components(edges: DataFrame, a: str = "a", b: str = "b", most: int = 60, keep: Callable[[DataFrame], DataFrame] = durable, few: int = FEW) -> DataFrame:
    """vertex and component (the smallest vertex) for each vertex of ``edges``; loops and repeated edges do no harm."""
    e = edges.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).where("a < b").distinct()
    e = keep(e)
    if e.count() <= few:
        return _in_one_task(e)
    # vertices of one edge follow the other end of it, so only the rest goes through the rounds
    ends = e.select(F.explode(F.array("a", "b")).alias("u")).groupBy("u").agg(F.count(F.lit(1)).alias("n"))
    ends = keep(ends)
    marked = e.join(ends.toDF("a", "na").hint("merge"), "a").join(ends.toDF("b", "nb").hint("merge"), "b")
    marked = keep(marked.select("a", "b", "na", "nb"))
    found = _rounds(keep(marked.where("na > 1 AND nb > 1").select("a", "b")), most, keep, few)
    alone = marked.where("na = 1 OR nb = 1").select(F.expr("if(nb = 1, a, b)").alias("at"), F.expr("if(nb = 1, b, a)").alias("leaf"))
    hung = keep(alone.join(found.hint("merge"), F.col("at") == F.col("vertex"), "left").select("at", "leaf", "component"))
    each = found.unionByName(hung.select(F.col("leaf").alias("vertex"), F.coalesce("component", "at").alias("component")))
    each = keep(each.unionByName(hung.where("component IS NULL").select(F.col("at").alias("vertex"), F.col("at").alias("component")).distinct()))
    named = each.groupBy("component").agg(F.min("vertex").alias("least"))
    return each.join(named.hint("merge"), "component").select("vertex", F.col("least").alias("component"))


def _rounds(e: DataFrame, most: int, keep: Callable[[DataFrame], DataFrame], few: int) -> DataFrame:
    before = None
    for _ in range(most):
        state = e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first()
        if state[0] <= few:
            return _in_one_task(e)
        if state == before:
            break
        before = state
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(e.select(F.col("b").alias("u"), F.col("a").alias("v")))
        # written, so the rows of a vertex of very many edges can be split by the join
        least = keep(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = keep(both.where("v > u").join(least, "u").select(F.col("m").alias("a"), F.col("v").alias("b")).distinct())
        lower = keep(large.groupBy("b").agg(F.min("a").alias("m")))
        small = large.join(lower, "b")
        e = keep(small.select(F.col("m").alias("a"), F.explode(F.array("a", "b")).alias("b")).where("a < b").distinct())
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("b").alias("vertex"), F.col("a").alias("component")).unionByName(e.select(F.col("a").alias("vertex"), F.col("a").alias("component")).distinct())
