"""Intermediate tables in the cluster's shared folder, and connected components over an edge table.

``keep`` writes a DataFrame as Parquet below ``spark.checkpoint.dir`` and reads it again: lineage is cut, every
executor can read the files, and a lost executor costs nothing.  A folder of our own is set only where the session
names none and runs in one process (tests); on a cluster that is an error.
"""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    at = spark.sparkContext._jsc.sc().getCheckpointDir()
    if at.isDefined():
        return at.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="tilesketch-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


def keep(df: DataFrame, *parts: str) -> DataFrame:
    """The same rows, read back from a table in the shared folder."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/kept-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*parts) if parts else writer).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._kept_path = path
    return out


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffle files of plans that nothing refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def drop(*tables: DataFrame) -> None:
    """Remove tables that ``keep`` wrote and that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_kept_path", None)
        if path:
            jvm = df.sparkSession.sparkContext._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def by_key(rows: DataFrame, per_key: DataFrame, *keys: str) -> DataFrame:
    """``rows`` joined with ``per_key``, a kept table of one row a key with the number ``c`` of the key's rows.

    Keys with more rows than a quarter of an even share of the partitions are joined where their rows lie; as their counts
    add up to the rows, there are at most four for each partition to broadcast.  All other keys are shuffled."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    share = (per_key.agg(F.sum("c")).first()[0] or 0) / (4 * parts)
    hot, cold = per_key.where(F.col("c") > share), per_key.where(F.col("c") <= share)
    near = rows.join(F.broadcast(hot), list(keys))
    rest = rows.join(F.broadcast(hot.select(*keys)), list(keys), "left_anti")
    return near.unionByName(rest.join(cold, list(keys)))


def components(edges: DataFrame, rounds: int = 200) -> DataFrame:
    """Smallest reachable id of every vertex of the undirected ``edges(a LONG, b LONG)``: ``(id, component)``.

    Each round gives a vertex the least label among its neighbours and then follows labels of labels, so the number of
    rounds grows with the logarithm of the diameter.  Rounds end when no label moves.  Edges and labels stay distributed.
    """
    both = keep(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
                .where("a <> b").groupBy("a", "b").agg(F.lit(1).alias("one")).drop("one"))
    label = keep(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m"))
                 .select("id", F.least("id", "m").alias("component")))
    for _ in range(rounds):
        near = both.join(label.select(F.col("id").alias("b"), "component"), "b").groupBy(F.col("a").alias("id")).agg(F.min("component").alias("m"))
        step = label.join(near, "id").select("id", F.least("component", "m").alias("m"), F.col("component").alias("was"))
        jump = step.join(label.select(F.col("id").alias("m"), F.col("component").alias("mm")), "m")
        new = keep(jump.select("id", F.least("m", "mm").alias("component"), "was"))
        moved = new.where("component <> was").limit(1).count()
        drop(label)
        label = new
        if not moved:
            break
    else:
        raise RuntimeError("labels still move after the last round")
    drop(both)
    kept = label.select("id", "component")
    kept._kept_path = label._kept_path
    return kept
