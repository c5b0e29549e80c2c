"""Measures over graphs and answers."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsieve.functions.storage import discard, materialize, written
from graphsieve.operators.components import connected_components
from graphsieve.operators.layout import partition_loads
from graphsieve.operators.reduce import LabeledGraph, with_end_labels
from graphsieve.operators.sieve import Solution, enumerate_matches
from graphsieve.plans.template import Template


def degree_stats(edges: DataFrame) -> DataFrame:
    d = edges.groupBy("src").agg(F.count("*").alias("d"))
    return d.agg(F.count("*").alias("vertices"), F.sum("d").alias("directed_edges"), F.max("d").alias("d_max"), F.round(F.avg("d"), 6).alias("d_avg"), F.round(F.stddev_pop("d"), 6).alias("d_std"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


def label_pairs(g: LabeledGraph) -> DataFrame:
    """Directed edges by the labels of their ends; read off the edges where they carry them."""
    e = g.edges if "slabel" in g.edges.columns else with_end_labels(g.edges, g.vertices)
    return e.filter("slabel is not null and dlabel is not null").groupBy(F.col("slabel").alias("a"), F.col("dlabel").alias("b")).agg(F.count("*").alias("n"))


def label_coverage(g: LabeledGraph, t: Template) -> DataFrame:
    inside = F.col("label").isin(list(t.by_label))
    return g.vertices.agg(F.count("*").alias("vertices"), F.sum(inside.cast("long")).alias("covered"))


def solution_size(s: Solution) -> DataFrame:
    v = s.state.vertices.agg(F.count("*").alias("v_star"))
    return v.crossJoin(s.state.edges.agg(F.count("*").alias("e_star")))


def precision_recall(kept: DataFrame, truth: DataFrame, keys: list[str]) -> dict:
    side = lambda df, a, b: df.select(*keys, F.lit(a).alias("_kept"), F.lit(b).alias("_truth"))
    each = side(kept, 1, 0).unionByName(side(truth, 0, 1)).groupBy(*keys).agg(F.max("_kept").alias("k"), F.max("_truth").alias("t"))
    both, nk, nt = each.agg(*[F.coalesce(F.sum(c), F.lit(0)) for c in (F.col("k") * F.col("t"), F.col("k"), F.col("t"))]).first()
    return {"kept": nk, "truth": nt, "precision": both / nk if nk else 1.0, "recall": both / nt if nt else 1.0}


def reduction(g: LabeledGraph, s: Solution) -> dict:
    """How many times fewer vertices and edges the answer has, and the edges left after every stage as a share of the graph's."""
    v, e, _ = s.state.counts()
    whole = g.edges.count()
    return {"vertices": g.vertices.count() / max(1, v), "edges": whole / max(1, e), "stages": [(x["stage"], x["e"] / max(1, whole)) for x in s.trace]}


def imbalance(edges: DataFrame, partitions: int = 64) -> DataFrame:
    """Kept edges of the partitions that hold any, largest first, with the running share: how few hold half of them."""
    order = Window.orderBy(F.desc("edges"), "part")  # one row per partition
    p = partition_loads(edges, partitions)
    whole = F.sum("edges").over(Window.partitionBy())
    running = F.sum("edges").over(order.rowsBetween(Window.unboundedPreceding, 0))
    return p.select("part", "edges", "sources", F.row_number().over(order).alias("rank"), F.round(running / whole, 6).alias("share"))


def imbalance_summary(edges: DataFrame, matches: DataFrame | None = None, partitions: int = 64) -> DataFrame:
    """Partitions in all, with edges, and holding half of them; with ``matches`` (``vid``, ``n``) also the most matches through one vertex."""
    p = imbalance(edges, partitions)
    out = p.agg(F.lit(partitions).alias("partitions"), F.count("*").alias("occupied"), (F.sum((F.col("share") < 0.5).cast("int")) + 1).alias("half"), F.max("edges").alias("most_edges"))
    return out if matches is None else out.crossJoin(matches.agg(F.max("n").alias("most_matches")))


def state_bytes(s: Solution) -> dict:
    """Bytes of the masks, of the edge rows, and of the largest number of tokens that one rule had in flight."""
    v, e, _ = s.state.counts()
    return {"masks": 8 * v, "edges": 32 * e, "tokens": 8 * s.template.n * max((x.get("tokens", 0) for x in s.trace), default=0)}


def solution_components(s: Solution) -> DataFrame:
    """``(component, vertices, matches)`` of the answer; a match lies in one component, that of its first vertex."""
    parts = materialize(connected_components(s.edges), "components")
    found = enumerate_matches(s).select(F.col("r0").alias("node")).join(parts, "node").groupBy("component").agg(F.count("*").alias("matches"))
    return parts.groupBy("component").agg(F.count("*").alias("vertices")).join(found, "component", "left").select("component", "vertices", F.coalesce("matches", F.lit(0)).alias("matches"))


def phase_seconds(s: Solution) -> list[tuple[int, str, str, int, int, int, int, int, float]]:
    """The trace as rows: stage, rule, rounds, vertices, edges, messages, tokens, seconds."""
    return [(k, x["stage"], str(x["rule"]), int(x["rounds"]), int(x["v"]), int(x["e"]), int(x["messages"]), int(x.get("tokens", 0)), float(x.get("seconds", 0.0))) for k, x in enumerate(s.trace)]


def timed(run, times: int = 10) -> dict:
    """Seconds of ``run()``, the mean of so many times, and the least and the most. Loading is the caller's, so it is left out."""
    each = []
    for _ in range(times):
        at = time.time()
        run()
        each.append(time.time() - at)
    return {"mean": sum(each) / len(each), "least": min(each), "most": max(each), "times": times}


def scaling_report(run, partitions: list[int], spark, cores: int | None = None) -> list[dict]:
    """``run(partitions)`` for each number of shuffle partitions: seconds, speedup over the first, and CPU seconds of all tasks (their run time,
    from the status store), as they are and against the first."""
    key, out = "spark.sql.shuffle.partitions", []
    before = spark.conf.get(key)
    try:
        for n in partitions:
            spark.conf.set(key, str(n))
            busy, at = task_seconds(spark), time.time()
            run(n)
            spent = time.time() - at
            out.append({"partitions": n, "seconds": spent, "speedup": out[0]["seconds"] / spent if out else 1.0, "cpu_hours": (task_seconds(spark) - busy) / 3600})
    finally:
        spark.conf.set(key, before)
    for r in out:
        r["cpu_hours_relative"] = r["cpu_hours"] / max(1e-12, out[0]["cpu_hours"])
    return out


def task_seconds(spark) -> float:
    """Run time of all tasks so far, over all executors."""
    rows = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(rows.apply(k).totalDuration() for k in range(rows.size())) / 1000


def dataset_bytes(spark, path: str) -> int:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


def k_core(edges: DataFrame, k: int) -> DataFrame:
    """Vertices of the k-core, by peeling until nothing goes."""
    e, seen = written(edges.select("src", "dst"), "core")
    before = -1
    while seen["rows"] and seen["rows"] != before:
        before = seen["rows"]
        keep = e.groupBy("src").count().filter(F.col("count") >= k).select("src")
        new, seen = written(e.join(keep, "src", "left_semi").join(keep.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), "core")
        discard(e)
        e = new
    return e.select(F.col("src").alias("vid")).distinct()


def bfs_levels(edges: DataFrame, sources: DataFrame, most: int | None = None) -> DataFrame:
    """``(vid, level)`` of everything that the sources reach; with ``most``, within so many hops. Edges must run both ways: a neighbour of a level is
    then on it, before it or after it, so that only two levels need to be looked at."""
    frontier, seen = written(sources.select("vid").distinct().withColumn("level", F.lit(0)), "bfs")
    parts, level = [frontier], 0
    while seen["rows"] and (most is None or level < most):
        level += 1
        known = reduce(DataFrame.unionByName, [p.select("vid") for p in parts[-2:]])
        new = frontier.join(edges, frontier.vid == edges.src).select(F.col("dst").alias("vid")).distinct().join(known, "vid", "left_anti")
        frontier, seen = written(new.withColumn("level", F.lit(level)), "bfs")
        parts.append(frontier)
    return reduce(DataFrame.unionByName, parts)
