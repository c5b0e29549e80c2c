"""A corpus pipeline: quality, near-duplicates, decontamination, personal data, packing. Part of subpackage llm."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphsieve.llm.common import materialize, table, tokenizer_path
from graphsieve.llm.decontaminate import drop_contaminated
from graphsieve.llm.near_copies import keep_one_similar
from graphsieve.llm.packing import pack_documents
from graphsieve.llm.pii import redact
from graphsieve.llm.quality import score_quality, train_quality


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier (learnt from the labelled ones among them) rejects at its own threshold go."""
    weights = train_quality(docs, table(spark, sf_dir, "labels"))
    return score_quality(docs, weights).filter("predicted = 1").select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8 or more) stays, that of the smallest doc_id."""
    return keep_one_similar(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a window of a benchmark item go."""
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data gives way to its kind; n_chars fits the new text."""
    return redact(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts as pieces in sequences of at most 2048 tokens."""
    return pack_documents(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("personal_data", personal_data), ("packing", packing)]
#: Classifier, similarity and tokenizer cannot be told in SQL; tests/llm/test_pipeline.py holds the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again before the next."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs, f"stage-{name}")
    return docs
