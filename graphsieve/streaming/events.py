"""Windows, deduplication, interval joins and micro-batch matching over a stream of events. Each has a batch twin."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphsieve.functions.storage import new_path
from graphsieve.operators.reduce import LabeledGraph, State, compatible, role_mask, symmetric
from graphsieve.operators.walks import extend
from graphsieve.plans.rules import WalkPlan
from graphsieve.plans.template import Template

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files: int = 8) -> DataFrame:
    """Event files as a stream, so many of them a batch; ``ts`` becomes a timestamp, which watermarks ask for."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, late: str = "1 hour", size: str = "1 hour") -> DataFrame:
    e = events.withWatermark("ts", late) if events.isStreaming else events
    return e.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, late: str = "1 hour", size: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    e = events.withWatermark("ts", late) if events.isStreaming else events
    return e.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, late: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    e = events.withWatermark("ts", late) if events.isStreaming else events
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def clicks_to_purchases(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Purchases within 30 minutes after a click of the same user."""
    e = events.withWatermark("ts", late) if events.isStreaming else events
    c = e.filter("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("cts"), F.col("event_id").alias("click"))
    p = e.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    return c.join(p, F.expr("cu = user_id and ts >= cts and ts <= cts + interval 30 minutes")).select("user_id", "click", "purchase")


def following_edges(events: DataFrame) -> DataFrame:
    """Edges from every event to its user's next one, ``(a, b)``: the last event of a user is state that outlives the micro-batch.

    Events of a user must come in the order of ``(ts, event_id)`` from batch to batch; within one they are sorted.
    """

    def linked(user: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids = pd.concat(list(frames)).sort_values(["ts", "event_id"])["event_id"].tolist()
        if state.exists:
            ids.insert(0, state.get[0])
        state.update((ids[-1],))
        yield pd.DataFrame({"a": ids[:-1], "b": ids[1:]}, dtype="int64")

    return events.select("user_id", "ts", "event_id").groupBy("user_id").applyInPandasWithState(linked, "a long, b long", "last long", "append", GroupStateTimeout.NoTimeout)


def late_rows(stream: DataFrame, late: str = "1 hour", size: str = "1 hour") -> tuple[DataFrame, dict]:
    """Tumbling counts under a watermark, and how many rows came and how many were dropped as too late (from the query's progress).

    What is counted as dropped are rows of the partial sums, of which a batch has one for each window and type.
    """
    spark = stream.sparkSession
    where, state = new_path(spark, "stream-out"), new_path(spark, "stream-state")
    counts = tumbling(stream, late, size)
    run = counts.writeStream.format("parquet").option("path", where).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    seen = {"rows": 0, "dropped": 0, "batches": 0}
    for p in run.recentProgress:
        seen["rows"] += p["numInputRows"]
        seen["dropped"] += sum(o["numRowsDroppedByWatermark"] for o in p["stateOperators"])
        seen["batches"] += 1
    return spark.read.schema(counts.schema).parquet(where), seen


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run what is there now into files (append) or a memory table (complete), and read the result."""
    spark = stream.sparkSession
    where, state = new_path(spark, "stream-out"), new_path(spark, "stream-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", where).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(where)
    rows = {}

    def keep(batch, _id):
        batch.write.mode("overwrite").parquet(where)
        rows["schema"] = batch.schema

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(rows["schema"]).parquet(where)


def new_matches(vertices: DataFrame, edges: DataFrame, fresh: DataFrame, t: Template) -> DataFrame:
    """Embeddings with at least one fresh edge, from walks that start at one: for every template edge, the fresh edge plays it and earlier
    template edges are not fresh, so each match comes once."""
    mask = vertices.filter(F.col("label").isin(list(t.by_label))).select("vid", role_mask(t).alias("mask"))

    def masked(e):
        return e.join(mask.select(F.col("vid").alias("src"), F.col("mask").alias("smask")), "src").join(mask.select(F.col("vid").alias("dst"), F.col("mask").alias("dmask")), "dst").filter(compatible(t))

    active, new, out = masked(edges), masked(fresh).select("src", "dst", "smask", "dmask"), None
    for a, b in t.edges:
        plan = WalkPlan(t, t.edges, a)
        first = new.filter(F.col("smask").bitwiseAND(F.lit(1 << a)) != 0).filter(F.col("dmask").bitwiseAND(F.lit(1 << b)) != 0)
        tokens = first.select(F.col("src").alias(f"p{a}"), F.col("dst").alias(f"p{b}"))
        bound = {a, b}
        for step in plan.steps:
            if step.chord or step.to not in bound:
                tokens = extend(tokens, active, step, t)
                bound.add(step.to)
            elif (min(step.at, step.to), max(step.at, step.to)) != (a, b):
                e = active.select(F.col("src").alias(f"p{step.at}"), F.col("dst").alias(f"p{step.to}"))
                tokens = tokens.join(e, [f"p{step.at}", f"p{step.to}"], "left_semi")
        for x in range(t.n):
            for y in range(x):
                if t.labels[x] == t.labels[y]:
                    tokens = tokens.filter(F.col(f"p{x}") != F.col(f"p{y}"))
        for c, d in t.edges:
            if (c, d) < (a, b):
                tokens = tokens.join(new.select(F.col("src").alias(f"p{c}"), F.col("dst").alias(f"p{d}")), [f"p{c}", f"p{d}"], "left_anti")
        tokens = tokens.select(*[F.col(f"p{q}").alias(f"r{q}") for q in range(t.n)])
        out = tokens if out is None else out.unionByName(tokens)
    return out


def match_stream(batches: list[DataFrame], vertices: DataFrame, t: Template) -> DataFrame:
    """Matches of growing edges, batch by batch: what ``foreachBatch`` runs. The union equals the batch answer on all edges."""
    from graphsieve.functions.storage import materialize

    seen, out = None, None
    for pairs in batches:
        fresh = symmetric(pairs)
        if seen is not None:
            fresh = fresh.join(seen, ["src", "dst"], "left_anti")
        fresh = materialize(fresh, "fresh")
        seen = materialize(fresh if seen is None else seen.unionByName(fresh), "seen")
        found = materialize(new_matches(vertices, seen, fresh, t), "found")
        out = found if out is None else out.unionByName(found)
    return out


__all__ = ["LabeledGraph", "State", "clicks_to_purchases", "deduplicated", "following_edges", "late_rows", "match_stream", "new_matches", "read_events", "run_to_table", "sessions", "sliding", "tumbling"]
