"""Exact histogram of encoded lengths; suffix sums answer every question about context limits."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsieve.llm.common import PieceEncoder, materialize

_BLOCK = 256


def length_histogram(docs: DataFrame, tokenizer: str, kind: str = "byte") -> DataFrame:
    """Rows ``(length, n_docs)``: documents by the number of their ids. Null text is empty (length 0); no document, no row."""

    def counted(batches):
        from collections import Counter

        import pyarrow as pa

        encoder, seen = PieceEncoder.get(tokenizer, kind), Counter()
        for batch in batches:
            for text in batch["text"]:
                seen[len(encoder.encode(text.as_py() or "")) // 4] += 1
        yield pa.RecordBatch.from_pydict({"length": pa.array(list(seen), pa.int64()), "n_docs": pa.array(list(seen.values()), pa.int64())})

    return docs.select("text").mapInArrow(counted, "length long, n_docs long").groupBy("length").agg(F.sum("n_docs").alias("n_docs"))


def suffix_sums(histogram: DataFrame) -> DataFrame:
    """For every length that occurs: documents and tokens above it, what is left when texts are cut there, and its quantile.

    Sums run inside blocks of lengths; one row per block is then summed up, so no task gets all lengths.
    """
    h = materialize(histogram, "length-histogram").withColumn("block", F.expr(f"length div {_BLOCK}")).withColumn("tokens", F.col("length") * F.col("n_docs"))
    blocks = h.groupBy("block").agg(F.sum("n_docs").alias("bd"), F.sum("tokens").alias("bt"))
    above = Window.orderBy(F.col("block").desc()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    blocks = blocks.select("block", F.coalesce(F.sum("bd").over(above), F.lit(0)).alias("ad"), F.coalesce(F.sum("bt").over(above), F.lit(0)).alias("at"), F.sum("bd").over(whole).alias("all_docs"), F.sum("bt").over(whole).alias("all_tokens"))
    inner = Window.partitionBy("block").orderBy(F.col("length").desc()).rowsBetween(Window.unboundedPreceding, -1)
    s = h.join(blocks, "block").withColumns({
        "docs_longer": F.coalesce(F.sum("n_docs").over(inner), F.lit(0)) + F.col("ad"),
        "tokens_longer": F.coalesce(F.sum("tokens").over(inner), F.lit(0)) + F.col("at"),
    })
    return s.select(
        "length", "n_docs", "docs_longer", "tokens_longer", "all_docs", "all_tokens",
        (F.col("all_tokens") - F.col("tokens_longer") + F.col("length") * F.col("docs_longer")).alias("truncated_total"),
        ((F.col("all_docs") - F.col("docs_longer")) / F.col("all_docs")).alias("quantile"),
    )


def truncated_total(sums: DataFrame, limit: int) -> int:
    """Tokens that remain when every document is cut at ``limit``, for any limit; 0 for an empty table."""
    at = sums.filter(F.col("length") <= limit).orderBy(F.desc("length")).first()
    if at:
        return at.all_tokens - at.tokens_longer + limit * at.docs_longer
    any_row = sums.first()
    return limit * any_row.all_docs if any_row else 0


def length_quantile(sums: DataFrame, q: float) -> int | None:
    """Smallest length that at least a share q of the documents does not exceed."""
    at = sums.filter(F.col("quantile") >= q).orderBy("length").first()
    return at.length if at else None


def token_counts(docs: DataFrame, tokenizer: str, kind: str = "byte") -> DataFrame:
    return suffix_sums(length_histogram(docs, tokenizer, kind))
