"""The corpus pipeline: quality rules, SimHash near-duplicates, secrets, mixing, byte-level BPE.

Every stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; ``run`` writes each result as
Parquet into the folder that the cluster shares and reads it again as the next one's ``docs``.

Nulls and empty texts fail the quality rules and go; null ids, sources and languages stay as they are. Of repeated rows
one stays, until the mix may repeat it. Very long texts go through whole; ties among equal ids are settled by a hash of
the row. Columns beyond those of ``documents`` pass until the last stage. An empty table gives an empty result.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from slicegrad.llm import bpe, mixing, quality, secrets, simhash

#: Expectation-maximisation, fingerprints and BPE merges have no SQL form; tests/llm/test_pipeline.py holds every stage and
#: ``run`` against brute force.
ORACLE_SQL = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose posterior quality is too low go."""
    return quality.quality_filter(docs)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: 5-word shingles, a similarity of 0.8 or more."""
    return simhash.near_dedup(docs, shingle=5, similarity=0.8)


def secret_scans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Live-looking secrets are replaced in the text; every document stays."""
    return secrets.redact_secrets(docs, length="n_chars")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.mix(docs)


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids in place of the text."""
    import public_tokenizers

    return bpe.bpe_encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, carry=["doc_id", "lang", "source"], decoded=None)


STAGES = [
    ("quality rules", quality_rules),
    ("SimHash near-dedup", simhash_near_dedup),
    ("secret scans", secret_scans),
    ("mixing sources", mix_sources),
    ("byte-level BPE", encode_bytes),
]


def shared_folder(spark: SparkSession) -> str:
    """A new folder beside the checkpoints."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        where = tempfile.mkdtemp(prefix="slicegrad-pipeline-")
    return f"{where.rstrip('/')}/pipeline-{uuid.uuid4().hex}"


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    folder = shared_folder(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
