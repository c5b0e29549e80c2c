"""Kept graphs written for later joins: bucketed by source vertex, or partitioned by the kind of vertex."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import new_path


def bucketed(edges: DataFrame, buckets: int = 8) -> DataFrame:
    """Edges as a table bucketed and sorted by ``src``: joins and aggregates on ``src`` of two such tables need no exchange.

    The files lie in the shared folder; the table's name is theirs.
    """
    path = new_path(edges.sparkSession, "bucketed")
    name = path.rsplit("/", 1)[1].replace("-", "_")
    edges.write.bucketBy(buckets, "src").sortBy("src").option("path", path).saveAsTable(name)
    return edges.sparkSession.table(name)


def partitioned(edges: DataFrame) -> DataFrame:
    """Edges in a folder for each kind of source vertex (the bits above the key), so that a scan for one label's kind skips the rest."""
    path = new_path(edges.sparkSession, "partitioned")
    edges.withColumn("kind", F.shiftright("src", 40).cast("int")).write.partitionBy("kind").parquet(path)
    return edges.sparkSession.read.parquet(path)
