"""Corpus preparation in stages; each reads what the one before it kept.

Rejected texts go first, then all but one of each group of near copies, then texts with benchmark passages; what is
left is mixed to the sources' target weights and written as token files, which the last stage reads back.

All stages judge rows, not ids: ids may be null or repeat. An empty table gives an empty one, and all stages but the
last keep every column of their input, whatever its name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pdpview.llm import decontaminate, mixing, quality, registry, setjoin, texts, token_files


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that pass the rules. Null, empty and short texts go; equal rows get equal verdicts; null languages are judged by
    the base rules alone."""
    return quality.keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies: that of its smallest id, then of the least fingerprint. Texts without words are
    alone and stay; of rows with equal id and text one stays."""
    return setjoin.keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without a word of a benchmark window. Null and empty texts have none and stay; an empty benchmark drops nothing."""
    return decontaminate.drop_contaminated(docs, registry.table(spark, sf_dir, "benchmark"))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix as rows: a document comes once for each pass that takes any of it. Null and empty texts are never taken; a
    null source is a source; equal rows are mixed one by one."""
    return mixing.mixed_documents(docs)


def token_output(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of each row, read back from the files. Null texts hold the end id alone; null
    ids come first; equal ids are ordered by text."""
    return token_files.round_trip(docs, registry.tokenizer_path())


STAGES = [
    ("quality rules", quality_rules),
    ("near duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("source mix", source_mix),
    ("token output", token_output),
]

#: Histogram distances and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = registry.table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = texts.stored(docs, f"stage-{k}")
    return docs
