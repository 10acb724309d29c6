"""Near-duplicate groups by min-max hashing of word shingles.

A document is the set of its distinct five-word shingles. Under each of 64
permutations both the smallest and the largest value are kept, so 64 hash
evaluations of a shingle give 128 unbiased sketch values; four of them make a
band, and documents that agree on one of 32 bands are candidates. A pair at the
threshold of 0.75 misses all bands with a probability of 5e-6.

Links are confirmed on the full sets, and no group is expanded into its pairs:

* documents of one set become one vertex;
* members of a bucket are compared with two leaders of it, the same in all buckets
  that hold them, and the components of these links are formed;
* buckets that still hold several components are settled exactly. A shingle that
  no other open document has proves how far any similarity can reach; documents
  that cannot reach the threshold drop out, and of the others each one outside
  the largest component of a bucket is compared with the rest of the bucket, in
  blocks of bounded size, once for each pair. Only links come out of a block.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellcluster.components import star_components

from .common import add_columns, durable, field, only_marked, table
from .wordhash import SPACED, mix, shingles, word_hashes

WIDTH, PERMUTATIONS, ROWS = 5, 64, 4
BANDS = 2 * PERMUTATIONS // ROWS
#: The threshold as hundredths, and members and shingles of a block on either side.
PERCENT, BLOCK, BLOCK_SHINGLES = 75, 256, 1 << 19
#: Buckets in which a pair at the threshold meets with a probability of 0.9995.
LIKELY = 3

_rng = np.random.Generator(np.random.PCG64(20))
_A = _rng.integers(0, 2**32, PERMUTATIONS, dtype=np.uint32) | np.uint32(1)
_B = _rng.integers(0, 2**32, PERMUTATIONS, dtype=np.uint32)


def shingle_set(raw: bytes) -> np.ndarray:
    return shingles(word_hashes(raw, SPACED), WIDTH)


def min_max(fingerprints: np.ndarray) -> np.ndarray:
    """Rows of smallest and largest value under each permutation."""
    x = (fingerprints >> np.uint64(32)).astype(np.uint32)
    low, high = None, None
    with np.errstate(over="ignore"):
        for k in range(0, len(x), 2048):
            y = x[k : k + 2048, None] * _A + _B
            a, b = y.min(axis=0), y.max(axis=0)
            low, high = (a, b) if low is None else (np.minimum(low, a), np.maximum(high, b))
    return np.stack([low, high], axis=1)


def bands(fingerprints: np.ndarray) -> np.ndarray:
    """A 64-bit key for each band; the number of the band is part of it."""
    values = min_max(fingerprints).reshape(BANDS, ROWS).astype(np.uint64)
    key = np.arange(BANDS, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(ROWS):
            key = mix(key * np.uint64(0x9E3779B97F4A7C15) + values[:, k] + np.uint64(1))
    return key.view(np.int64)


def _digest(fingerprints: np.ndarray) -> bytes:
    return hashlib.blake2b(fingerprints.tobytes(), digest_size=16).digest()


def _sketches(docs: DataFrame, text: str) -> DataFrame:
    def make():
        def work(texts):
            for raw in texts:
                s = shingle_set(raw)
                yield len(s), _digest(s) if len(s) else None, bands(s) if len(s) else None

        return work

    return add_columns(docs, text, [field("n_shingles", "bigint"), field("v", "binary"), field("bands", "array<bigint>")], make, ["doc_id"])


def _payload(docs: DataFrame, text: str, active: DataFrame) -> DataFrame:
    """v (whole and as two numbers), n, set and bands of the active vertices, from one document of each."""
    def make():
        def work(texts):
            for raw in texts:
                s = shingle_set(raw)
                v = _digest(s)
                yield v, *np.frombuffer(v, np.int64).tolist(), len(s), s.view(np.int64), bands(s) if len(s) else np.empty(0, np.int64)

        return work

    rows = only_marked(docs.select("doc_id", F.col(text).alias("text")), "doc_id", active, active.count()).join(active.select("doc_id").distinct(), "doc_id")
    fields = [field("v", "binary"), *[field(c, "bigint") for c in ("v1", "v2", "n")], field("set", "array<bigint>"), field("bands", "array<bigint>")]
    return add_columns(rows, "text", fields, make, ["doc_id"]).join(active, ["doc_id", "v"]).dropDuplicates(["v"]).drop("doc_id")


def _similar(inter, a, b, percent: int):
    return 100 * inter >= percent * (a + b - inter)


def _leader_links(buckets: DataFrame, payload: DataFrame, percent: int) -> DataFrame:
    """Links between members and leaders that meet in ``LIKELY`` buckets at least; what this leaves apart is settled later."""
    sets = payload.select("v", "n", "set")
    met = buckets.select("v", F.explode(F.array_distinct(F.array("first", "second"))).alias("w")).where("v <> w")
    pairs = met.groupBy("v", "w").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= LIKELY).select(F.least("v", "w").alias("a"), F.greatest("v", "w").alias("b")).distinct()
    both = pairs.join(sets.toDF("a", "na", "sa"), "a").join(sets.toDF("b", "nb", "sb"), "b")
    # the sizes alone bound the similarity
    both = both.where((100 * F.col("na") >= percent * F.col("nb")) & (100 * F.col("nb") >= percent * F.col("na")))
    return both.where(_similar(F.size(F.array_intersect("sa", "sb")), F.col("na"), F.col("nb"), percent)).select("a", "b")


def _open(rows: DataFrame) -> DataFrame:
    """Rows (key, v, comp, w) of the keys with several components, with the largest of these and how many rows and shingles (w) there are in all and outside it."""
    each = rows.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("w"))
    most = F.max(F.struct("n", "comp", "w"))
    keys = each.groupBy("key").agg(most.alias("most"), F.sum("n").alias("size"), F.sum("w").alias("weight"), F.count(F.lit(1)).alias("comps")).where("comps > 1")
    keys = keys.select("key", F.col("most.comp").alias("largest"), "size", "weight", (F.col("size") - F.col("most.n")).alias("minor"), (F.col("weight") - F.col("most.w")).alias("minor_weight"))
    # the counts are few rows of their own, so a frequent key can be split by the join
    return rows.join(durable(keys), "key")


def _block_links(percent: int):
    def links(part: pa.Table) -> pa.Table:
        column = lambda c: part.column(c).combine_chunks()
        number = lambda c: column(c).to_numpy(zero_copy_only=False)
        lists = column("set")
        ends, flat_sets = lists.offsets.to_numpy() - lists.offsets[0].as_py(), lists.flatten().to_numpy()
        sets = [flat_sets[a:b] for a, b in zip(ends, ends[1:], strict=False)]
        own = column("bands").flatten().to_numpy().reshape(-1, BANDS)
        n, c, minor, band = number("n"), number("common"), number("minor_row"), column("band")[0].as_py()
        comp = np.array(column("comp").to_pylist(), object)
        member = np.flatnonzero(~minor)
        out: set[tuple[bytes, bytes]] = set()
        if len(member):
            big = number("in_largest")[member]
            v = np.array(column("v").to_pylist(), object)
            flat = np.concatenate([sets[k] for k in member])
            begin = np.concatenate([[0], np.cumsum([len(sets[k]) for k in member])[:-1]])
            for x in np.flatnonzero(minor):
                most = np.minimum(c[x], c[member])
                ok = _similar(most, n[x], n[member], percent) & (comp[member] != comp[x])
                # two outsiders meet twice in the grid; a pair of several bands is left to the first
                ok &= big | (v[member] > v[x])
                ok &= (own[member] == own[x]).argmax(axis=1) == band
                if ok.any():
                    inter = np.add.reduceat(np.isin(flat, sets[x]).astype(np.int64), begin)
                    for y in member[ok & _similar(inter, n[x], n[member], percent)]:
                        out.add((comp[x], comp[y]))
        return pa.table({"a": pa.array([a for a, _ in out], pa.binary()), "b": pa.array([b for _, b in out], pa.binary())})

    return links


def _settle(buckets: DataFrame, labels: DataFrame, payload: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between components, for all pairs of the buckets that no earlier step compared or joined."""
    rows = _open(buckets.join(labels, "v").select("key", "band", "v", "comp", F.lit(1).cast("bigint").alias("w"))).select("key", "band", "v", "comp")
    rows = durable(rows)
    still = payload.join(rows.select("v").distinct(), "v", "left_semi")
    # of a shingle that occurs once, the exclusive or of its owners is its owner
    owners = still.select("v1", "v2", F.explode("set").alias("s")).groupBy("s").agg(F.count(F.lit(1)).alias("k"), F.bit_xor("v1").alias("v1"), F.bit_xor("v2").alias("v2"))
    alone = owners.where("k = 1").groupBy("v1", "v2").agg(F.count(F.lit(1)).alias("alone"))
    common = still.select("v", "v1", "v2", "n").join(alone, ["v1", "v2"], "left").select("v", "n", (F.col("n") - F.coalesce("alone", F.lit(0))).alias("common"))
    able = durable(common.where(100 * F.col("common") >= percent * F.col("n")).select("v", "common", F.col("n").alias("w")))
    rows = _open(durable(rows.join(able, "v").select("key", "band", "v", "comp", "common", "w")))
    parts = lambda count, weight: F.ceil(F.greatest(F.col(count) / BLOCK, F.col(weight) / BLOCK_SHINGLES)).cast("int")
    rows = rows.withColumns({"in_largest": F.col("comp") == F.col("largest"), "wide": parts("size", "weight"), "high": parts("minor", "minor_weight")})
    spot = lambda n, seed: F.pmod(F.xxhash64(F.lit(seed), F.col("v")), F.col(n)).cast("int")
    upto = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    fields = ("key", "band", "v", "comp", "common", "in_largest")
    members = rows.select(*fields, F.lit(False).alias("minor_row"), spot("wide", 1).alias("i"), F.explode(upto("high")).alias("j"))
    minors = rows.where("NOT in_largest").select(*fields, F.lit(True).alias("minor_row"), F.explode(upto("wide")).alias("i"), spot("high", 2).alias("j"))
    grid = members.unionByName(minors).join(payload.select("v", "n", "set", "bands"), "v")
    return grid.groupBy("key", "i", "j").applyInArrow(_block_links(percent), "a binary, b binary").distinct()


def near_groups(docs: DataFrame, text: str = "text", percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for each document.

    Documents are linked from a similarity of ``percent`` hundredths on; the
    component is named by the smallest doc_id reachable, which is kept. A text
    of one to four words is one shingle; null, empty and blank texts have none,
    are linked with nothing and are kept. Rows repeated with the same doc_id and
    set are one document and give one row. Other columns are not read.
    """
    return _groups(docs, text, percent).drop("v")


def _groups(docs: DataFrame, text: str, percent: int) -> DataFrame:
    """The same with v, the digest of the set, null for an empty one."""
    docs = docs.select("doc_id", F.col(text).alias("text"))
    each = durable(_sketches(docs, "text").dropDuplicates(["doc_id", "v"]))
    vertices = durable(each.where("v IS NOT NULL").groupBy("v").agg(F.min("doc_id").alias("doc_id"), F.first("bands").alias("bands")))
    keyed = vertices.select("v", F.posexplode("bands").alias("band", "key"))
    second = F.min_by("v", F.xxhash64("v"))
    shared = durable(keyed.groupBy("key").agg(F.min("v").alias("first"), second.alias("second"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n"))
    buckets = keyed.join(shared, "key")  # both sides are read from files, so the rows of a frequent key can be split
    buckets = durable(buckets.select("key", "band", "v", "first", "second"))
    active = vertices.select("v", "doc_id").join(buckets.select("v").distinct(), "v", "left_semi")
    payload = durable(_payload(docs, "text", active))
    links = _leader_links(buckets, payload, percent)
    joined = durable(star_components(links, keep=durable))
    labels = durable(active.select("v").join(joined.select(F.col("vertex").alias("v"), "component"), "v", "left").select("v", F.coalesce("component", "v").alias("comp")))
    # what joins by component is written first, so the members of a large one can be split
    later = durable(star_components(_settle(buckets, labels, payload, percent), keep=durable).select(F.col("vertex").alias("comp"), "component"))
    labels = labels.join(later, "comp", "left").select("v", F.coalesce("component", "comp").alias("comp"))
    own = vertices.select("v", "doc_id").join(labels, "v", "left").select("v", "doc_id", F.coalesce("comp", "v").alias("comp"))
    own = durable(own)
    least = durable(own.groupBy("comp").agg(F.min("doc_id").alias("component_id")))
    named = own.join(least, "comp").select("v", "component_id")
    out = each.join(named, "v", "left")
    component = F.when(F.col("v").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), "v")


def drop_near(docs: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns.

    Where a doc_id (or null) occurs with several texts, the digest of the set
    tells its rows apart, so a unique text stays whatever its id; rows repeated
    with the same doc_id and set become one.
    """
    groups = durable(_groups(docs, text, PERCENT))
    if docs.count() == groups.select("doc_id").distinct().count():
        gone = groups.where(~F.col("kept")).select(F.col("doc_id").alias("__gone"))
        return docs.join(gone, docs["doc_id"].eqNullSafe(gone["__gone"]), "left_anti").select(docs.columns)

    def make():
        def work(texts):
            for raw in texts:
                s = shingle_set(raw)
                yield (_digest(s) if len(s) else None,)

        return work

    whole = docs.select("doc_id", F.col(text).alias("text"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"))
    marked = add_columns(whole, "text", [field("__v", "binary")], make, ["doc_id", "__row"])
    stay = groups.where("kept").select(F.col("doc_id").alias("__id"), F.col("v").alias("__kept"))
    return marked.dropDuplicates(["doc_id", "__v"]).join(stay, F.col("doc_id").eqNullSafe(F.col("__id")) & F.col("__v").eqNullSafe(F.col("__kept")), "left_semi").select("__row.*")


def op3_min_max(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(table(spark, sf_dir, "documents"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
i AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM i JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * k >= 75 * (a.n + b.n - k)),
r AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x)
SELECT d.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, c AS component_id, d.doc_id = c AS kept
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT x AS doc_id, min(y) AS c FROM r GROUP BY 1) USING (doc_id)
"""
