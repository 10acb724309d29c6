"""Helpers that the corpus operators share."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellcluster.components import durable  # noqa: F401

#: Bytes of text that a worker turns into Python objects at a time.
PART_BYTES = 4 << 20
#: Bytes and rows that travel to a worker at a time; the session's own settings count where they are smaller.
BATCH_BYTES, BATCH_ROWS = 8 << 20, 2_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def as_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """UTF-8 of each text as it is stored; null counts as empty."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def add_columns(df: DataFrame, text: str, fields: list[T.StructField], make: Callable[[], Callable[..., Iterable[tuple]]], keep: list[str] | None = None, also: tuple[str, ...] = ()) -> DataFrame:
    """``df`` (or its columns ``keep``) with columns computed from the bytes of ``text``, row by row, with no shuffle.

    ``make`` runs once a task and returns the function that maps a list of texts
    to one tuple of values each; what it builds lives as long as the task, and
    its attribute ``done``, if it has one, is called at the end. The
    values of the columns ``also`` are given to it as further lists. A column of
    ``df`` with the name of a new one is replaced.
    """
    new = {f.name for f in fields}
    kept = [c for c in (df.columns if keep is None else keep) if c not in new]
    schema = T.StructType([df.schema[c] for c in kept] + fields)
    arrow = [(f.name, _ARROW[f.dataType.simpleString()]) for f in fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        try:
            for batch in batches:
                # a few thousand texts at a time, fewer if long
                for a, b in runs(batch.column(len(kept)), PART_BYTES):
                    part = batch.slice(a, b - a)
                    more = [part.column(len(kept) + 1 + k).to_pylist() for k in range(len(also))]
                    rows = list(work(as_bytes(part.column(len(kept))), *more))
                    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in arrow]
                    yield pa.RecordBatch.from_arrays(
                        [part.column(k) for k in range(len(kept))] + [_column(v, t) for v, (_, t) in zip(columns, arrow, strict=True)],
                        names=kept + [name for name, _ in arrow],
                    )
        finally:
            getattr(work, "done", lambda: None)()
            pa.default_memory_pool().release_unused()  # the worker lives on

    bounded_batches(df.sparkSession)
    return df.select(*[F.col(f"`{c}`") for c in kept], F.col(f"`{text}`").cast("string").alias("__text"), *[F.col(c).alias(f"__also{k}") for k, c in enumerate(also)]).mapInArrow(run, schema)


def bounded_batches(spark: SparkSession) -> None:
    """Lower the session's bounds on Arrow batches, which hold whole texts on both sides of the pipe to a worker."""
    for name, most in (("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES), ("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)):
        now = spark.conf.get(name).rstrip("b")
        if not now.isdigit() or int(now) > most or int(now) <= 0:
            spark.conf.set(name, most)


def runs(texts: pa.Array, most: int) -> Iterator[tuple[int, int]]:
    """Stretches of the texts that hold about ``most`` bytes; a longer text is one by itself."""
    total = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    a = 0
    while a < len(total):
        b = max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + most, side="right")))
        yield a, b
        a = b


def _column(values: Sequence, kind: pa.DataType) -> pa.Array:
    """An Arrow column; lists that are NumPy arrays are joined without a Python object for each number."""
    if not pa.types.is_list(kind) or not any(isinstance(v, np.ndarray) for v in values):
        return pa.array(list(values), kind)
    ends = np.cumsum([0] + [0 if v is None else len(v) for v in values]).astype(np.int32)
    flat = np.concatenate([v for v in values if v is not None])
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, kind.value_type), mask=pa.array([v is None for v in values]))


_ARROW = {
    "bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string(), "binary": pa.binary(),
    "array<bigint>": pa.list_(pa.int64()), "array<string>": pa.list_(pa.string()), "array<int>": pa.list_(pa.int32()),
}


def only_marked(df: DataFrame, key: str, wanted: DataFrame, n: int, most: int = 27) -> DataFrame:
    """Rows of ``df`` whose key may be among those of ``wanted``, for a join that follows; no row of a wanted key is lost.

    A bit map over hashes of the ``n`` wanted keys, 64 bits a key and 2 ** ``most``
    (16 MB) at most, goes to the executors; only rows that it lets through travel on.
    """
    bits = max(10, min(most, max(n, 1).bit_length() + 6))
    slot = lambda d: F.shiftrightunsigned(F.xxhash64(d[key]), 64 - bits)

    def area(part: pa.Table) -> pa.Table:
        held = np.zeros(1 << min(bits, 16), np.uint8)
        held[part.column("low").to_numpy()] = 1
        return pa.table({"high": part.column("high").slice(0, 1), "area": pa.array([zlib.compress(np.packbits(held).tobytes(), 1)], pa.binary())})

    slots = wanted.select(slot(wanted).alias("slot")).distinct()
    parts = slots.select(F.shiftright("slot", 16).alias("high"), F.col("slot").bitwiseAND(0xFFFF).alias("low")).groupBy("high").applyInArrow(area, "high bigint, area binary")
    shared = df.sparkSession.sparkContext.broadcast({r.high: zlib.decompress(r.area) for r in parts.collect()})

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = np.zeros((1 << bits) // 8, np.uint8)
        for high, packed in shared.value.items():
            own = np.frombuffer(packed, np.uint8)
            whole[high * 8192 : high * 8192 + len(own)] = own
        for batch in batches:
            s = batch.column(batch.num_columns - 1).to_numpy()
            yield batch.filter(pa.array((whole[s >> 3] >> (7 - (s & 7)).astype(np.uint8) & 1).astype(bool))).select(range(batch.num_columns - 1))

    return df.select("*", slot(df).alias("__slot")).mapInArrow(pick, df.schema)


def field(name: str, kind: str) -> T.StructField:
    return T.StructField(name, T._parse_datatype_string(kind))
