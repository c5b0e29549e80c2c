"""Queries over the whole tables, one for each operator of this subpackage."""

from __future__ import annotations

from graphsieve.llm.common import table, tokenizer_path


def op1_html_extraction(spark, sf_dir):
    from graphsieve.llm.html_text import extraction_report

    return extraction_report(table(spark, sf_dir, "pages"))


def op2_pii(spark, sf_dir):
    from graphsieve.llm.pii import pii_report

    return pii_report(table(spark, sf_dir, "documents"))


def op3_token_output(spark, sf_dir):
    from graphsieve.llm.token_output import token_output

    return token_output(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op4_lm_scoring(spark, sf_dir):
    from graphsieve.llm.gru_lm import lm_scores

    return lm_scores(table(spark, sf_dir, "documents"))


def op5_quality(spark, sf_dir):
    from graphsieve.llm.quality import quality_scores

    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_token_counts(spark, sf_dir):
    from graphsieve.llm.token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op7_packing(spark, sf_dir):
    from graphsieve.llm.packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op8_simhash(spark, sf_dir):
    from graphsieve.llm.simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_merkle(spark, sf_dir):
    from graphsieve.llm.merkle import edit_report

    return edit_report(table(spark, sf_dir, "documents"))


def op10_decontamination(spark, sf_dir):
    from graphsieve.llm.decontaminate import contamination_report

    return contamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_html_extraction, op2_pii, op3_token_output, op4_lm_scoring, op5_quality, op6_token_counts, op7_packing, op8_simhash, op9_merkle, op10_decontamination, pipeline)}

#: Equivalent SQL where it can be told in SQL. Lists are compared by their digests.
ORACLES: dict[str, str] = {}
