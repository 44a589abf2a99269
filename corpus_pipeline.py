"""A training corpus in five stages, each written and read again.

Every stage works on all rows that its predecessor kept. The first three drop
documents, the fourth masks secrets, the last packs what is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from canopy.llm import cotraining, overlap, packing, secrets, simhash, tiling
from canopy.storage import stage


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the co-trained classifier rejects; rows without an id stay."""
    model = cotraining.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return cotraining.keep(docs, model)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each SimHash group, then no two of similarity 0.8 on five words.

    The groups are those of op1 and take copies cheaply; the overlap pass is exact on what they leave. Only ids
    are written; rows without an id and texts without words stay, but for the groups of equal empty texts.
    """
    gone = simhash.stood_for(docs)
    more = overlap.similar_to_smaller(docs.join(gone, "doc_id", "left_anti"))
    return docs.join(gone.union(more), "doc_id", "left_anti").select(docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that cover a benchmark item."""
    return tiling.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks the secrets found in any document."""
    return secrets.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in full sequences."""
    return packing.pack(docs)


STAGES = [
    ("quality_classifier", quality),
    ("simhash_near_dedup", near_duplicates),
    ("benchmark_decontamination", decontamination),
    ("secret_scans", secret_scan),
    ("packing", pack),
]

#: The classifier, the fingerprints and the packing have no SQL form; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES:
        docs = stage(step(spark, docs, sf_dir), name)
    return docs
