"""Walk generators: clusters of points around moving locations, by integer arithmetic on the row number.

Row ``id`` belongs to cluster ``id mod clusters`` or, for one in ``noise`` rows,
to none. The location of a cluster starts anywhere and drifts by one stride each
``n / (clusters * steps)`` rows; points lie around it within a radius that is
equal for all clusters (``even``) or grows with the number of the cluster
(``varied``). Every number comes from a multiplicative congruence, so any engine
rebuilds the same rows from the row numbers, however they are partitioned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

DOMAIN = 100_000
#: A prime below 2 ** 31: products of two residues fit 64 bits.
PRIME = 2_147_483_629
#: Fewest tasks that make the columns of a walk over a table.
WALKERS = 24


def draw_sql(key: str, salt: int) -> str:
    """A residue below PRIME for an integer expression, spelt alike for all engines."""
    once = f"((({key}) % {PRIME}) * 48271 + {salt % PRIME}) % {PRIME}"
    return f"(({once}) * 69621 + 12345) % {PRIME} * 16807 % {PRIME}"


def walk_columns(n: int, d: int, kind: str = "even", clusters: int = 10, steps: int = 20, radius: int = 1500, stride: int = 1200, noise: int = 50, seed: int = 1) -> list[str]:
    """SQL of x1, ..., xd over a column ``id``."""
    if kind not in ("even", "varied"):
        raise ValueError("kind is even or varied")
    own = f"(id % {clusters})"
    step = f"((id // {clusters}) * {steps} // {max(1, n // clusters)})"
    reach = f"({radius} * ({own} + 1) * 2 // {clusters + 1} + 1)" if kind == "varied" else str(radius)
    out = []
    for j in range(1, d + 1):
        salt = seed * 7919 + j * 104729
        start = f"{draw_sql(own + f' * 31 + {j}', salt)} % {DOMAIN}"
        way = f"({draw_sql(own + f' * 17 + {j}', salt + 7)} % {2 * stride + 1} - {stride})"
        shake = f"({draw_sql(f'id * 13 + {j}', salt + 11)} % (2 * {reach} + 1) - {reach})"
        inside = f"(({start}) + {way} * {step} + {shake})"
        # a walk that leaves the domain comes back in from the border
        folded = f"abs({inside} - {2 * DOMAIN} * CAST(floor(CAST({inside} + {DOMAIN} AS DOUBLE) / {2 * DOMAIN}) AS BIGINT))"
        alone = f"{draw_sql(f'id * 19 + {j}', salt + 13)} % {DOMAIN}"
        out.append(f"CAST(CASE WHEN id % {noise} = {noise - 1} THEN {alone} ELSE {folded} END AS BIGINT) AS x{j}")
    return out


def gen_walk(spark: SparkSession, n: int, d: int, partitions: int | None = None, **settings) -> DataFrame:
    rows = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    columns = [c.replace("//", "div") for c in walk_columns(n, d, **settings)]
    return rows.selectExpr("id AS point_id", *columns)


def walk_over(df: DataFrame, key: str, n: int, d: int, **settings) -> DataFrame:
    """A walk whose rows are those of a table, numbered by its key: it goes one stride further every ``n / steps`` rows, however many there are.

    Keys are few bytes in a file or two, so they are dealt over tasks before the columns are made.
    """
    tasks = max(WALKERS, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return df.selectExpr(f"CAST({key} AS BIGINT) AS id").repartition(tasks, "id").selectExpr("id AS point_id", *[c.replace("//", "div") for c in walk_columns(n, d, **settings)])


def walk_sql(n: int, d: int, table: str = "", key: str = "", **settings) -> str:
    rows = f"SELECT CAST({key} AS BIGINT) AS id FROM {table}" if table else f"SELECT CAST(unnest(range({n})) AS BIGINT) AS id"
    return f"SELECT id AS point_id, {', '.join(walk_columns(n, d, **settings))} FROM ({rows})"


class _Part(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class WalkReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.d, self.parts = int(options.get("n", 1000)), int(options.get("d", 2)), int(options.get("partitions", 4))

    def partitions(self):
        cut = [self.n * k // self.parts for k in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(cut, cut[1:], strict=False)]

    def read(self, partition: _Part):
        for k in range(partition.low, partition.high):
            yield (k, *[k * (48271 + 2 * j) % PRIME * 16807 % PRIME % DOMAIN for j in range(self.d)])


class PointSource(DataSource):
    """``spark.read.format("cell_points").option("n", ...).option("d", ...)``: scattered points, made where they are read."""

    @classmethod
    def name(cls) -> str:
        return "cell_points"

    def schema(self) -> str:
        return "point_id bigint, " + ", ".join(f"x{j} bigint" for j in range(1, int(self.options.get("d", 2)) + 1))

    def reader(self, schema) -> WalkReader:
        return WalkReader(dict(self.options))


def pca_points(df: DataFrame, array: str, point_id: str, k: int) -> DataFrame:
    """Scores on the first k principal components of an array column, as raw features f1, ..., fk."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    rows = df.select(F.col(point_id).cast("bigint").alias("point_id"), array_to_vector(F.col(array).cast("array<double>")).alias("v"))
    scores = PCA(k=k, inputCol="v", outputCol="s").fit(rows).transform(rows).withColumn("s", vector_to_array("s"))
    return scores.select("point_id", *[F.col("s")[j].alias(f"f{j + 1}") for j in range(k)])
