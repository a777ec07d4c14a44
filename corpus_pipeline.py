"""A corpus pipeline: each stage works on what the one before has kept.

Every stage keeps all columns of ``documents`` and any others, whatever their names;
the last one returns ids, sources and tokens. Empty tables stay empty through all stages.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sieve.llm import bpe, mixing, neardup, quality, substrings
from sieve.plans.scratch import materialize

VOCABULARY = "byte_bpe_multi_50k.tiktoken"


def _counted(docs: DataFrame) -> DataFrame:
    """``n_chars``, where there is such a column, made to say the text's code points."""
    if "n_chars" not in docs.columns:
        return docs
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass every rule; columns as they came.

    Null and empty texts have too few words and go; repeated rows share their verdict;
    texts of any length are judged whole.
    """
    return quality.passing(docs, quality.order_rules(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: the one of least id.

    Of rows that repeat an id one stays; rows with a null id all stay, as do texts without words.
    """
    return neardup.drop_near_duplicates(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages that occur earlier; n_chars follows the text.

    Earlier is by id, then by place; null ids come first. A row that loses every word
    goes; a null text stays null, with null n_chars.
    """
    return _counted(substrings.strip_substrings(docs))


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture: documents drawn once, twice or not at all, towards source targets.

    A null source is a source of its own; repeated rows are drawn each on its own; one
    row a source at most is cut to its first words.
    """
    return _counted(mixing.mix(docs))


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document of the mixture, and the digest of what they decode to.

    A null or empty text has no ids; a row drawn twice gives two rows.
    """
    path = public_tokenizers.path(VOCABULARY)
    ids = bpe.encode(docs, path, public_tokenizers.PATTERN, keep=("doc_id", "source"), decoded="decoded_sha256")
    return ids.select("doc_id", "source", F.size("ids").cast("long").alias("n_tokens"), "ids", "decoded_sha256")


STAGES = [
    ("quality rules", quality_rules),
    ("minhash near-dedup", near_dedup),
    ("substring dedup", substring_dedup),
    ("mixing sources to target weights", source_mixing),
    ("byte-level BPE", byte_bpe),
]

#: Mixing draws by seeded hashes and BPE follows a rank file: neither is expressible in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name.split()[0]}")
    return docs
