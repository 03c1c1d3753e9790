"""A corpus pipeline of the operators in sparse_release.llm: quality rules, near-duplicates, secrets, mixing, packing.

Each stage works on all that the one before kept. Quality rules drop what the policy rejects; of each group of near-duplicates the document with the smallest id
stays; secrets are masked in place, so their documents stay; mixing repeats or drops documents to meet the sources' targets; packing lays the rest out in
sequences. Rows with a null id are no group's representative, so one of theirs stays only where a whole group has none.

Every stage takes nulls in any column, empty and very long texts, repeated rows and an empty table; what each gives is said with it. All but the last return the columns
that they got, whatever else these are and however they are called.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparse_release.llm import near_dup, packing, quality_rules, secret_scan, source_mixing
from sparse_release.llm.common import documents, durable_table
from sparse_release.llm.queries import vocabulary

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that policy v1 keeps. A null or empty text has no words and goes; repeated rows are judged each for itself; an empty table stays empty."""
    return quality_rules.apply_policy(docs, "v1")


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that links of similarity 0.8 or more (Jaccard, five-word shingles) connect: the smallest id, and of rows that share it the one whose text has the smallest hash.
    Candidates are those of the byte-position index over 64-bit fingerprints, checked by their whole sets; links between fingerprints beyond its reach are added by shingle_join.
    Texts without words (null, empty, blank) are one group; of rows that are equal in id and text one stays; an empty table stays empty."""
    return near_dup.representatives(docs, width=5, similarity=0.8)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with secrets masked and n_chars (if there is one) the new text's length. A null text stays null, with a null length; repeated rows stay."""
    masked = secret_scan.masked(docs)
    return masked.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else masked


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as the mix takes them, none over twice. A null source is one of its own; texts without words have size 0 and are not taken; of equal rows the mix takes
    what their number allows; an empty table stays empty."""
    return source_mixing.mixed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all rows, one row each: a null or empty text is its closing token; repeated rows are packed each; an empty table gives none."""
    pieces = packing.pack_documents(docs, vocabulary())
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "tier", "step")


STAGES: list[tuple[str, Stage]] = [
    ("quality_rules", quality),
    ("near_duplicates", distinct),
    ("secret_scan", secrets),
    ("source_mixing", mix),
    ("packing", pack),
]

#: Fingerprints and tokens are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every stage over all that the one before kept; each but the last is written as Parquet in the shared folder and read again."""
    docs = documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = durable_table(docs)
    return docs
