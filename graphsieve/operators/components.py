"""Connected components of an edge table, without ever gathering it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import discard, materialize, written


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """Rows ``(node, component)`` for every node of ``edges``; the component is its smallest node.

    Alternates two contractions until the edges form stars. Each hangs neighbours on the smallest node in reach: first
    those above a node, then those below it. Work per round follows the number of edges, rounds its logarithm. A hub's
    rows are spread by the skew handling of the join: both sides are plain shuffles, as its other side is a written table.
    Self-loops keep their node; nulls are dropped; an empty table gives an empty result.
    """
    pairs = edges.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b")).dropna()
    nodes = materialize(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "cc-nodes")
    links = materialize(pairs.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "cc-links")
    before = None
    for _ in range(max_rounds):
        above = materialize(_above(links), "cc-above")
        discard(links)
        links, seen = written(_below(above), "cc-below", mixed=F.pmod(F.xxhash64("a", "b"), F.lit(1 << 32)))
        discard(above)
        if seen == before:
            break
        before = seen
    else:
        raise RuntimeError(f"components have not settled after {max_rounds} rounds")
    return nodes.join(links.withColumnRenamed("a", "node"), "node", "left").select("node", F.coalesce("b", "node").alias("component"))


def _above(links: DataFrame) -> DataFrame:
    """Every neighbour above a node is hung on the smallest of the node and its neighbours."""
    least = materialize(links.select(F.explode(F.array(F.struct(F.col("a").alias("n"), F.col("b").alias("m")), F.struct(F.col("b").alias("n"), F.col("b").alias("m")))).alias("x")).select("x.*").groupBy("n").agg(F.min("m").alias("m")), "cc-least")
    hung = links.join(least, links.b == least.n).select("a", F.col("m").alias("b"))
    return hung.distinct()


def _below(links: DataFrame) -> DataFrame:
    """A node's neighbours below it are hung on the smallest of them; so is the node."""
    least = materialize(links.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "n"), "cc-least")
    hung = links.join(least, links.a == least.n)
    own = least.select(F.col("n").alias("a"), F.col("m").alias("b"))
    return hung.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(own).distinct()
