"""A training corpus from raw documents, in five stages, each written as Parquet and read again for the next.

Quality rules, line dedup, near-duplicates, benchmark decontamination, best-fit packing. Each stage judges what the
stage before it has kept; all but the last return the columns of `documents`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quadinv.llm import decontaminate, jaccard, line_dedup, packing, quality_rules, simhash
from quadinv.llm.common import shared_folder, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules keep."""
    return quality_rules.accepted(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their repeated lines; n_chars follows the text. Documents left without a word go."""
    left = line_dedup.deduplicated(docs)
    return left.filter((F.col("removed_lines") == 0) | F.col("text").rlike(r"[^\x20\x09-\x0D]")).select(*[F.length("text").cast(docs.schema["n_chars"].dataType).alias(c) if c == "n_chars" else c for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more.

    BK-trees over SimHash fingerprints give candidates, min-hashes those beyond the trees' reach; whole shingle sets decide.
    """
    return simhash.one_of_each(docs, find=jaccard.near_duplicates)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of a test item occurs."""
    return decontaminate.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def bins(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document lies."""
    return packing.packed(docs)


STAGES = [("quality_rules", quality), ("line_dedup", lines), ("simhash_near_dedup", near_duplicates), ("benchmark_decontamination", leaks), ("best_fit_packing", bins)]

#: The first stage is an expectation-maximisation, the third needs XXH64 and the last is sequential: SQL expresses none of them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, folder = table(spark, sf_dir, "documents"), shared_folder(spark, "corpus")
    for k, (name, stage) in enumerate(STAGES):
        path = f"{folder}/{k}-{name}"
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(path)
        docs = spark.read.parquet(path)
    return docs
