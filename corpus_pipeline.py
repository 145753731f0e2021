"""The corpus pipeline: documents in, encoded documents out, five stages.

Rows are documents, whatever their doc_id: null or repeated ids are judged row by row. A null text counts as empty,
so the first stage rejects it; texts of any length are taken whole. Ties and repeated rows: the third stage keeps one
row of each group of copies, chosen as ``simhash.one_per_group`` says. Empty tables pass as empty tables. All
columns but text and n_chars are carried unchanged up to the last stage, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from levelrank.llm import bpe, leaks, linededup, quality, simhash
from levelrank.llm.common import table
from levelrank.plans.staging import materialise


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or their language's perplexity band reject go."""
    return quality.keep_good(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten or more documents are cut from every text; documents stay."""
    return linededup.drop_frequent_lines(docs)


def simhash_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the smallest doc_id."""
    return simhash.one_per_group(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of a benchmark item go."""
    return leaks.drop_leaking(docs, table(spark, sf_dir, "benchmark"))


def bpe_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, and the hash of the text that the ids decode to."""
    return bpe.encoded(docs)


STAGES = [("quality rules", quality_rules), ("line dedup", line_dedup), ("simhash near-dedup", simhash_near_dedup), ("benchmark decontamination", benchmark_decontamination), ("byte-level BPE encoding", bpe_encoding)]

#: Perplexities, fingerprints and merges are past SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each one's result is written and read again as the next one's documents."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
