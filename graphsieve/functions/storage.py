"""Tables that cut lineage, in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_KEY = "spark.checkpoint.dir"


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir. Where the setting is missing: a temporary one if the master is local (tests), else an error."""
    sc = spark.sparkContext
    root = spark.conf.get(_KEY, None) or sc.getConf().get(_KEY, None)
    if not root:
        there = sc._jsc.sc().getCheckpointDir()
        root = there.get() if there.isDefined() else None
    if not root:
        if not sc.master.startswith("local"):
            raise RuntimeError(f"{_KEY} must name a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="graphsieve-")
        sc.setCheckpointDir(root)
    return root.rstrip("/")


def _place(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder; it goes when the session's JVM ends."""
    path = f"{shared_dir(spark)}/graphsieve/{name}-{uuid.uuid4().hex}"
    fs, where = _place(spark, path)
    fs.deleteOnExit(where)
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    fs, where = _place(spark, path)
    fs.delete(where, True)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write once, read back: the result has no lineage to replay and outlives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def written(df: DataFrame, name: str, keep: Column | None = None, **measures: Column) -> tuple[DataFrame, dict]:
    """``materialize`` the rows to ``keep``, and sums over all rows that come for free while they are written; ``rows`` counts them."""
    seen = Observation()
    df = df.observe(seen, F.count(F.lit(1)).alias("rows"), *[F.coalesce(F.sum(c.cast("long")), F.lit(0)).alias(k) for k, c in measures.items()])
    out = materialize(df if keep is None else df.filter(keep), name)
    return out, {k: int(v or 0) for k, v in seen.get.items()}


def discard(df: DataFrame | None) -> None:
    """Frees a materialized table that nothing reads any more."""
    path = getattr(df, "_stored_at", None)
    if path:
        drop_path(df.sparkSession, path)
