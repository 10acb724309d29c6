"""Benchmark decontamination by multi-pattern search with block shift tables.

The patterns are runs of 13 consecutive words of a benchmark item. The search
slides a window over the words of a document and looks at the last two words of
it: a pair that ends no pattern, and lies nearest to the end of one at distance
``s``, proves that the next ``s - 1`` positions cannot end an occurrence, and the
window jumps over them. Where the pair does end patterns, the bucket of that
pair holds the candidates and a direct comparison of the words decides.

An ordinary word pair allows a jump of 12 words, so about a twelfth of the pairs
of a text is looked up. Patterns travel to the executors in blocks of a fixed
number of bytes; more blocks mean more passes over a row inside the same stage,
never a larger broadcast, and no pass shuffles.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import add_columns, field, table
from .wordhash import ALNUM

WINDOW = 13
#: Bytes of benchmark text that one pass carries to the executors.
BLOCK_BYTES = 8 << 20


class ShiftTables:
    """Search tables for patterns of words; each pattern carries the ids of its items."""

    def __init__(self, patterns: dict[tuple[bytes, ...], tuple[str, ...]], block: int = 2):
        self.groups = []
        lengths = {len(p) for p in patterns}
        # full windows allow the longest jumps; shorter items get tables of their own
        for own in ([n for n in lengths if n >= WINDOW], [n for n in lengths if block <= n < WINDOW], [n for n in lengths if n < block]):
            if own:
                self.groups.append(self._build({p: i for p, i in patterns.items() if len(p) in own}, min(own), min(block, min(own))))

    @staticmethod
    def _build(patterns: dict, shortest: int, block: int) -> tuple:
        shift: dict[tuple, int] = {}
        bucket: dict[tuple, dict[int, dict]] = defaultdict(dict)
        for p, items in patterns.items():
            # the last `shortest` words of a pattern serve as its anchor
            tail = p[len(p) - shortest :]
            for end in range(block, shortest + 1):
                key = tail[end - block : end]
                shift[key] = min(shift.get(key, shortest), shortest - end)
            # the patterns of a bucket by length and words, so a frequent ending is one look-up for each length
            bucket[tail[shortest - block :]].setdefault(len(p), {})[p] = items
        return shortest, block, shortest - block + 1, shift, dict(bucket)

    def find(self, words: list[bytes]) -> list[tuple[int, int, tuple[str, ...]]]:
        """Every occurrence: first word, word after the last, item ids."""
        out = []
        n = len(words)
        for shortest, block, most, shift, bucket in self.groups:
            at = shortest - 1
            get = shift.get
            while at < n:
                key = (words[at - 1], words[at]) if block == 2 else tuple(words[at - block + 1 : at + 1])
                jump = get(key, most)
                if jump:
                    at += jump
                    continue
                for length, held in bucket[key].items():
                    first = at + 1 - length
                    items = held.get(tuple(words[first : at + 1])) if first >= 0 else None
                    if items:
                        out.append((first, at + 1, items))
                at += 1
        return out


def words_of(raw: bytes) -> list[bytes]:
    return raw.translate(ALNUM).split()


def windows(items: list[tuple[str, bytes]], width: int = WINDOW) -> dict[tuple[bytes, ...], tuple[str, ...]]:
    out: dict[tuple[bytes, ...], set[str]] = defaultdict(set)
    for item, raw in items:
        words = words_of(raw)
        for k in range(max(1, len(words) - width + 1) if words else 0):
            out[tuple(words[k : k + width])].add(item)
    return {p: tuple(sorted(i)) for p, i in out.items()}


def _blocks(benchmark: DataFrame, block_bytes: int):
    """The items in blocks of about ``block_bytes``; one item is never split."""
    held, size = [], 0
    for item, raw in benchmark.select(F.col("item_id").cast("string"), F.encode(F.coalesce(F.col("text"), F.lit("")), "UTF-8")).toLocalIterator():
        if item is None:
            continue
        held.append((item, bytes(raw)))
        size += len(raw)
        if size >= block_bytes:
            yield held
            held, size = [], 0
    yield held


def find_contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", width: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``docs`` with n_words, n_hit, n_items, items (sorted as strings) and contaminated.

    A word is hit if it lies inside any occurrence of any window of any item; a
    document is contaminated if at least one word in twenty is hit. Null and
    empty texts have no words and are clean; an item without words has no
    window, one without an id is skipped; repeated items count once, and ids of
    any type are taken as text. Without any item all documents are clean; an
    empty table of documents gives no row. Columns of ``docs`` with the names of
    the results are replaced, all others kept whatever their names.
    """
    made = ("n_words", "n_hit", "n_items", "items", "contaminated")
    kept = [c for c in docs.columns if c not in made]
    out = docs.select(F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row"), F.col(f"`{text}`").cast("string").alias("text"))
    first = True
    for items in _blocks(benchmark, block_bytes):
        patterns = windows(items, width)
        if not first and not patterns:
            continue
        out = _search(out, patterns, first)
        first = False
    return out.select(
        "row.*", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), F.array_sort("items").alias("items"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
    )


def _search(docs: DataFrame, patterns: dict, first: bool) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(patterns)

    def make():
        tables = ShiftTables(shared.value)

        def work(texts, spans=None, ids=None):
            for k, raw in enumerate(texts):
                words = words_of(raw)
                hit = bytearray(spans[k]) if spans and spans[k] else bytearray(len(words))
                items = set(ids[k]) if ids else set()
                for a, b, found in tables.find(words):
                    hit[a:b] = b"\1" * (b - a)
                    items.update(found)
                n = hit.count(1)
                yield len(words), n, sorted(items), bytes(hit) if n else b""

        return work

    fields = [field("n_words", "bigint"), field("n_hit", "bigint"), field("items", "array<string>"), field("spans", "binary")]
    return add_columns(docs, "text", fields, make, ["row", "text"], also=() if first else ("spans", "items"))


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


def op2_wu_manber(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return digest(find_contamination(docs, table(spark, sf_dir, "benchmark")))


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
p AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[i : i + least(13, len(w)) - 1], ' ') AS s
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
ns AS (SELECT DISTINCT n FROM p),
q AS (SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS s
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, ns WHERE len(w) >= n)),
h AS (SELECT doc_id, q.n, i, item_id FROM q JOIN p USING (n, s)),
k AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS j FROM h) GROUP BY 1),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS s FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM h) GROUP BY 1)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN k USING (doc_id) LEFT JOIN t USING (doc_id)
"""
