"""Where rows lie: snapshots, rebalancing, smaller deployments and hubs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsieve.functions.storage import materialize
from graphsieve.operators.reduce import State
from graphsieve.plans.template import Template


def save(state: State, path: str) -> None:
    """A state as files, from which a search goes on, also on another cluster."""
    spark = state.edges.sparkSession
    state.edges.write.mode("overwrite").parquet(f"{path}/edges")
    state.masks.write.mode("overwrite").parquet(f"{path}/masks")
    spark.createDataFrame([(state.template.to_json(), state.rows)], "template string, rows long").coalesce(1).write.mode("overwrite").json(f"{path}/told")


def load(spark: SparkSession, path: str) -> State:
    told = spark.read.schema("template string, rows long").json(f"{path}/told").first()
    t = Template.from_json(told.template)
    return State(t, spark.read.parquet(f"{path}/edges"), told.rows, spark.read.parquet(f"{path}/masks") if t.n == 1 else None, [], borrowed=True)


def rebalance(state: State, partitions: int | None = None) -> State:
    """The pruned state dealt evenly by source, so that what survived on few partitions is worked on by all."""
    e = state.edges.repartition(partitions, "src") if partitions else state.edges.hint("rebalance", "src")
    return State(state.template, materialize(e, "rebalanced"), state.rows, state.alone, state.trace)


def consolidate(state: State, rows_per_partition: int = 1_000_000) -> State:
    """The state in as few partitions as its rows ask for, for a smaller deployment."""
    n = max(1, -(-state.rows // rows_per_partition))
    return State(state.template, materialize(state.edges.coalesce(n), "small"), state.rows, state.alone, state.trace)


def partition_loads(edges: DataFrame, partitions: int = 64, by: str = "src") -> DataFrame:
    """Rows ``(part, edges, sources)`` of the partitions that ``edges`` fall into when dealt by ``by``: counted in the partitions themselves."""
    dealt = edges.repartition(partitions, by).withColumn("part", F.spark_partition_id())
    return dealt.groupBy("part").agg(F.count("*").alias("edges"), F.count_distinct("src").alias("sources"))


def spread_hubs(edges: DataFrame, threshold: int, salts: int = 16) -> DataFrame:
    """Edges with a ``salt``: those of vertices above the threshold are spread over ``salts`` keys, others keep salt 0."""
    hubs = edges.groupBy("src").agg(F.count("*").alias("d")).filter(F.col("d") >= threshold).select("src", F.lit(True).alias("hub"))
    return edges.join(hubs, "src", "left").withColumn("salt", F.when(F.col("hub"), F.pmod(F.xxhash64("dst"), F.lit(salts))).otherwise(F.lit(0))).drop("hub")


def salted_degrees(edges: DataFrame, threshold: int) -> DataFrame:
    """Degrees in two steps, so that no hub is counted by one task."""
    return spread_hubs(edges, threshold).groupBy("src", "salt").agg(F.count("*").alias("n")).groupBy("src").agg(F.sum("n").alias("degree"))
