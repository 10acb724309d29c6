"""A training corpus in five stages: quality, exact and near duplicates, benchmark passages, tokens.

All stages but the last return the columns of their input, whatever their names
and whatever others stand beside doc_id and text. Texts are read whole; null
counts as empty; an empty table passes through as an empty table.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellcluster.llm import bytebpe, decontaminate, exactdup, neardup, quality
from cellcluster.llm.common import table


def _decide(docs: DataFrame, judged, keep: str) -> DataFrame:
    """Rows of ``docs`` whose judgement holds; their own columns pass through untouched."""
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), F.col("text"))
    return judged(whole).where(keep).select("__row.*")


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject.

    Each row is judged by its text alone, so repeated rows stay or go together;
    empty texts have the score of the bias. Without labels every score is one
    half and all rows stay.
    """
    weights = quality.fit_quality(docs, table(spark, sf_dir, "labels"))
    return _decide(docs, lambda d: quality.score(d, weights), f"score >= {quality.THRESHOLD}")


def drop_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts that are equal without white space.

    The longest original stays, of ties the smallest doc_id, null last; empty
    texts are one group; rows repeated with id and text become one.
    """
    return exactdup.drop_copies(docs)


def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one of the smallest doc_id.

    Texts without a word are near nothing and stay. Rows of one doc_id with
    several texts are told apart by their shingles; rows repeated with id and
    shingles become one.
    """
    return neardup.drop_near(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which fewer than one word in twenty lies in a benchmark passage.

    Each row is judged by its text alone; texts without words stay, and without
    a benchmark item all rows do.
    """
    benchmark = table(spark, sf_dir, "benchmark")
    return _decide(docs, lambda d: decontaminate.find_contamination(d, benchmark), "NOT contaminated")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and the token ids of each row; an empty text has no tokens, repeated rows repeat."""
    return bytebpe.add_tokens(docs, *bytebpe.production(), keep=["doc_id"])


STAGES = [
    ("quality classifier", keep_quality),
    ("exact dedup", drop_exact),
    ("min-max near-dedup", drop_near),
    ("benchmark decontamination", drop_benchmark),
    ("byte-level BPE", encode),
]

#: Training a classifier, near-duplicate search and encoding are not SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage is written as Parquet to the shared folder of ``spark.checkpoint.dir``, and the next one reads that."""
    docs = table(spark, sf_dir, "documents")
    root = f"{spark.conf.get('spark.checkpoint.dir', None) or tempfile.mkdtemp(prefix='corpus-')}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{k}")
        docs = spark.read.parquet(f"{root}/{k}")
    return docs
