"""Reading and writing: pruned scans, explicit schemas, streams, partitioned and bucketed sinks, stored cells."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellcluster.spec import dims, ks

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A scan that reads only ``cols``, with ``where`` pushed to the files."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where else df
    return df.select(*cols) if cols else df


def points_schema(d: int) -> T.StructType:
    return T.StructType([T.StructField("point_id", T.LongType(), False), *[T.StructField(f"x{j}", T.LongType()) for j in range(1, d + 1)]])


def points(spark: SparkSession, path: str, fmt: str, d: int, **options) -> DataFrame:
    """Points from CSV, JSON, ORC, Parquet or any registered format, under a declared schema; ``text`` takes comma-separated lines."""
    schema = points_schema(d)
    if fmt == "text":
        parts = F.split("value", ",")
        return spark.read.text(path).select(*[F.element_at(parts, k + 1).cast("bigint").alias(f.name) for k, f in enumerate(schema)])
    return spark.read.format(fmt).options(**options).schema(schema).load(path)


def stream(spark: SparkSession, path: str, schema: T.StructType, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def rate(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def write(df: DataFrame, path: str, by: list[str] | None = None, mode: str = "overwrite") -> None:
    """Parquet, partitioned by columns if given, sorted by cell where there are cells so file statistics are tight."""
    k = [c for c in df.columns if c[0] == "k" and c[1:].isdigit()]
    out = df.sortWithinPartitions(*k) if k else df
    writer = out.write.mode(mode)
    (writer.partitionBy(*by) if by else writer).parquet(path)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> None:
    df.write.mode("overwrite").format("parquet").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)


def save_cells(cells: DataFrame, path: str) -> None:
    """Points with their cells, range-sorted: runs that differ in min_pts only need no new index."""
    cells.repartitionByRange(*ks(dims(cells))).sortWithinPartitions(*ks(dims(cells))).write.mode("overwrite").parquet(path)


def load_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = NAMES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
