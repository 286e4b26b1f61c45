"""From raw documents to a training mix: language ID, near-duplicate removal, decontamination, secret redaction, mixing.

Each stage takes (spark, docs, sf_dir), works on everything its predecessor kept, and returns a table with the columns of
`documents`; the last adds what the mix decided.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from navgraph.llm import decontaminate, jaccard, langid, mixing, secrets
from navgraph.session import written


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, of which no language can be told, go."""
    return langid.keep_known(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents linked by similarity of word shingles, the one with the least doc_id stays."""
    return jaccard.keep_one(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten consecutive words of a benchmark item (or a whole shorter item) go."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text"))


def redacted(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay; secrets in their text are replaced."""
    return secrets.redact(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix takes, with size, source_size, target and taken (words, repeats counted)."""
    return mixing.mix(docs).filter("taken > 0")


STAGES = [
    ("language id", known_language),
    ("n-gram jaccard join", one_of_each),
    ("benchmark decontamination", decontaminated),
    ("secret scans", redacted),
    ("mixing sources", mixed),
]

#: A recurrent network can't be written as SQL; tests/llm compares run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return docs
