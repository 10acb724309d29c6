"""Exact deduplication with counting quotient filters.

Every task builds a filter over the 64-bit fingerprints of its documents: the
high bits of a fingerprint (the quotient) name a run, the low bits (the
remainder) are stored in order inside the run, and a counter stands beside each.
As quotient and remainder hold the whole fingerprint, two filters merge without
loss by merging their sorted runs and adding the counters. The filters travel in
ranges of quotients, so a range is merged by one task whatever the number of
documents, and a fingerprint that a third of all documents share arrives once
from each task.

A counter of one proves that a text is alone. Texts of larger counters are read
again and compared byte by byte: distinct rows of fingerprint, digest and bytes
are formed with a map-side combine, so copies do not travel.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import add_columns, durable, field, table
from .wordhash import WHITE

#: Fingerprints a range holds on average, and a task keeps before it hands a filter on.
RANGE, HELD = 1 << 15, 1 << 20
#: Most bits of the map of counted-twice fingerprints; 2 ** 27 bits are 16 MB.
MAP_BITS = 27
_CONTINUED = bytes(range(0x80, 0xC0))


class CountingQuotientFilter:
    """Sorted remainders by quotient with counters; ``q`` bits of quotient, ``64 - q`` of remainder."""

    def __init__(self, q: int, starts: np.ndarray, remainders: np.ndarray, counts: np.ndarray):
        self.q, self.starts, self.remainders, self.counts = q, starts, remainders, counts

    @classmethod
    def of(cls, fingerprints: np.ndarray, counts: np.ndarray, q: int) -> CountingQuotientFilter:
        """From fingerprints in any order; equal ones add up."""
        order = np.argsort(fingerprints, kind="stable")  # sorted runs are merged, not sorted anew
        x, c = fingerprints[order], counts[order]
        first = np.flatnonzero(np.r_[True, x[1:] != x[:-1]]) if len(x) else np.empty(0, np.int64)
        x, c = x[first], np.add.reduceat(c, first) if len(first) else c
        quotient = (x >> np.uint64(64 - q)).astype(np.int64) if q else np.zeros(len(x), np.int64)
        starts = np.searchsorted(quotient, np.arange((1 << q) + 1))
        return cls(q, starts, x & np.uint64((1 << (64 - q)) - 1), c)

    def run(self, quotient: int) -> tuple[np.ndarray, np.ndarray]:
        a, b = self.starts[quotient], self.starts[quotient + 1]
        return self.remainders[a:b], self.counts[a:b]

    def fingerprints(self) -> np.ndarray:
        quotient = np.repeat(np.arange(1 << self.q, dtype=np.uint64), np.diff(self.starts))
        return (quotient << np.uint64(64 - self.q) if self.q else np.uint64(0)) | self.remainders

    def merge(self, *others: CountingQuotientFilter) -> CountingQuotientFilter:
        all_ = (self, *others)
        return self.of(np.concatenate([f.fingerprints() for f in all_]), np.concatenate([f.counts for f in all_]), self.q)

    def count(self, fingerprint: int) -> int:
        rest, counts = self.run(fingerprint >> (64 - self.q) if self.q else 0)
        at = int(np.searchsorted(rest, np.uint64(fingerprint & ((1 << (64 - self.q)) - 1))))
        return int(counts[at]) if at < len(rest) and int(rest[at]) == fingerprint & ((1 << (64 - self.q)) - 1) else 0


def normalised(raw: bytes) -> bytes:
    """Without any character of [\\x20\\x09-\\x0D]."""
    return raw.translate(None, WHITE)


def fingerprint(norm: bytes) -> int:
    return xxhash.xxh3_64_intdigest(norm)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _facts(docs: DataFrame, text: str) -> DataFrame:
    def make():
        def work(texts):
            for raw in texts:
                norm = normalised(raw)
                yield _signed(fingerprint(norm)), hashlib.sha256(norm).digest(), len(raw.translate(None, _CONTINUED))

        return work

    return add_columns(docs, text, [field("fp", "bigint"), field("sha", "binary"), field("n_points", "bigint")], make, ["doc_id"])


def _merged(facts: DataFrame, n: int) -> tuple[DataFrame, int, int]:
    """A row for each range of quotients: the fingerprints counted more than once, and a bit map of them; bits of the quotient and of the map inside a range."""
    q = max(0, min(30, (max(n, 1) // RANGE).bit_length()))
    bits = max(q + 3, min(MAP_BITS, max(n, 1).bit_length() + 6))

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def hand_on() -> Iterator[pa.RecordBatch]:
            x = np.concatenate(held) if held else np.empty(0, np.uint64)
            f = CountingQuotientFilter.of(x, np.ones(len(x), np.int64), q)
            rows = [(k, *f.run(k)) for k in np.flatnonzero(np.diff(f.starts))]
            yield pa.RecordBatch.from_arrays([pa.array([int(k) for k, _, _ in rows], pa.int64()), pa.array([r.tobytes() for _, r, _ in rows], pa.binary()), pa.array([c.tobytes() for _, _, c in rows], pa.binary())], names=["quotient", "remainders", "counts"])

        for batch in batches:
            held.append(batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            size += len(held[-1])
            if size >= HELD:
                yield from hand_on()
                held, size = [], 0
        if size:
            yield from hand_on()

    def merge(part: pa.Table) -> pa.Table:
        k = part.column("quotient")[0].as_py()
        rest = np.concatenate([np.frombuffer(x, np.uint64) for x in part.column("remainders").to_pylist()])
        counts = np.concatenate([np.frombuffer(x, np.int64) for x in part.column("counts").to_pylist()])
        f = CountingQuotientFilter.of(rest, counts, 0)  # one run: its remainders alone
        many = f.counts > 1
        found = f.remainders[many]
        at = (found >> np.uint64(64 - bits)).astype(np.int64)  # the quotient's own bits are not in it
        area = np.zeros(1 << max(0, bits - q), np.uint8)
        area[at] = 1
        full = (found | (np.uint64(k) << np.uint64(64 - q)) if q else found).view(np.int64)
        return pa.table({"quotient": [k], "fps": pa.array([full.tolist()], pa.list_(pa.int64())), "area": pa.array([zlib.compress(np.packbits(area).tobytes(), 1)], pa.binary())})

    rows = facts.select("fp").mapInArrow(build, "quotient bigint, remainders binary, counts binary")
    return rows.groupBy("quotient").applyInArrow(merge, "quotient bigint, fps array<bigint>, area binary"), q, bits - q


def group_copies(docs: DataFrame, text: str = "text") -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 and n_points for each document.

    Texts are equal if the same bytes stay without white space; null counts as
    empty, and empty texts are equal. Of equal texts the longest original in
    code points stays, then the smallest doc_id, nulls last. Rows repeated with
    the same doc_id and text are one document and give one row. No row is
    returned for an empty table. Other columns of ``docs`` are not read.
    """
    spark = docs.sparkSession
    facts = durable(_facts(docs.select("doc_id", F.col(text).alias("text")), "text").dropDuplicates())
    merged, q, span = _merged(facts, facts.count())
    merged = durable(merged)
    areas = spark.sparkContext.broadcast({r.quotient: zlib.decompress(r.area) for r in merged.select("quotient", "area").collect()})  # MAP_BITS at most

    def suspects():
        area = areas.value

        def work(texts):
            for raw in texts:
                norm = normalised(raw)
                x = fingerprint(norm)
                own = area.get(x >> (64 - q) if q else 0)
                at = (x & ((1 << (64 - q)) - 1)) >> (64 - q - span)
                if own is not None and own[at >> 3] >> (7 - (at & 7)) & 1:
                    yield _signed(x), hashlib.sha256(norm).digest(), norm
                else:
                    yield None, None, None

        return work

    fields = [field("fp", "bigint"), field("sha", "binary"), field("norm", "binary")]
    doubtful = add_columns(docs.select(F.col(text).alias("text")), "text", fields, suspects, []).where("fp IS NOT NULL")
    twice = merged.select(F.explode("fps").alias("fp"))
    # equal bytes meet in one row here, so a second row of a digest is another text
    verified = (
        doubtful.distinct().groupBy("fp", "sha").agg(F.count(F.lit(1)).alias("n_texts"))
        .join(twice, "fp", "left_semi")
        .withColumn("n_texts", F.when(F.col("n_texts") == 1, 1).otherwise(F.raise_error(F.lit("two texts have one digest"))))
    )
    # the least in this order: the longest, an id before none, the smallest id of any type
    best = F.min(F.struct((-F.col("n_points")).alias("less"), F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("keep")))
    sizes = facts.groupBy("fp", "sha").agg(F.count(F.lit(1)).alias("group_size"), best.alias("best")).where("group_size > 1")
    groups = sizes.join(verified, ["fp", "sha"]).where("n_texts = 1").select("fp", "sha", "group_size", F.col("best.keep").alias("keep"), (-F.col("best.less")).alias("keep_points"))
    # written first, so the join has nothing but the two reads before it and the rows of a large group can be split
    out = facts.join(durable(groups), ["fp", "sha"], "left")
    keep = F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep"))
    return out.select(
        "doc_id", keep.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("bigint").alias("group_size"),
        (keep.eqNullSafe(F.col("doc_id")) & (F.col("n_points") == F.coalesce("keep_points", "n_points"))).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"), "n_points",
    )


def drop_copies(docs: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; repeated rows of a document become one."""
    groups = durable(group_copies(docs, text))
    if docs.count() > groups.count():
        docs = docs.dropDuplicates(["doc_id", text])
    white = "".join(map(chr, WHITE))
    if groups.groupBy("doc_id").count().where("count > 1").isEmpty():
        gone = groups.where(~F.col("kept")).select(F.col("doc_id").alias("__gone"))
        return docs.join(gone, docs["doc_id"].eqNullSafe(gone["__gone"]), "left_anti").select(docs.columns)
    # one doc_id with several texts: the digest tells them apart
    sha = F.sha2(F.translate(F.coalesce(F.col(text), F.lit("")), white, ""), 256)
    points = groups.where(~F.col("kept")).select(F.col("doc_id").alias("id"), F.col("text_sha256").alias("own"), F.col("n_points").alias("n"))
    marked = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), sha.alias("sha"), F.length(F.coalesce(F.col(text), F.lit(""))).cast("bigint").alias("points"))
    gone = F.col("row.doc_id").eqNullSafe(F.col("id")) & (F.col("sha") == F.col("own")) & (F.col("points") == F.col("n"))
    return marked.join(points, gone, "left_anti").select("row.*")


def op9_counting_quotient(spark: SparkSession, sf_dir: str) -> DataFrame:
    return group_copies(table(spark, sf_dir, "documents")).drop("n_points")


ORACLE = r"""
WITH d AS (SELECT doc_id, length(coalesce(text, '')) AS n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS s FROM documents)
SELECT doc_id, first_value(doc_id) OVER w AS keep_id, count(*) OVER (PARTITION BY s) AS group_size,
  doc_id = first_value(doc_id) OVER w AS kept, sha256(s) AS text_sha256
FROM d WINDOW w AS (PARTITION BY s ORDER BY n DESC, doc_id)
"""
