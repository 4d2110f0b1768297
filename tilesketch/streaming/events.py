"""Streaming: cells and running bottom-k lists over ``events``.  A list only grows by insertion, so late data within the
watermark merge into it; nothing is ever taken out of one."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tilesketch.functions.hashing import Family, affine, cell
from tilesketch.session import shared_dir


def events(spark: SparkSession, path: str, max_files: int = 1) -> DataFrame:
    """Parquet files of events below ``path``, a few files a batch."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def with_lateness(df: DataFrame, delay: str = "2 hours") -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def unique_cells(df: DataFrame, row: str, col: str) -> DataFrame:
    """Each cell once within the watermark."""
    return df.dropDuplicatesWithinWatermark([row, col])


def windowed_counts(df: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events and approximate users in each window."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return df.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n_events"), F.approx_count_distinct("user_id").alias("n_users")).select("w.start", "w.end", "n_events", "n_users")


def sessions(df: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return df.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", "w.start", "w.end", "n")


def with_dim(df: DataFrame, dim: DataFrame, on: str) -> DataFrame:
    """A stream joined with a table; whether the table is broadcast is left to its size."""
    return df.join(dim, on)


def running_sketch(df: DataFrame, key: str, row: str, col: str, fam: Family, k: int) -> DataFrame:
    """``key, hashes array<bigint>`` of the first map of the family: the bottom-k list of the cells seen so far."""
    ar, br, ac, bc = fam.maps[0]
    h = df.select(F.col(key).alias("key"), cell(affine(F.col(row), ar, br, fam.prime), affine(F.col(col), ac, bc, fam.prime), fam.prime).alias("h"))

    def merge(at: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = set(state.get[0]) if state.exists else set()
        for b in batches:
            held.update(b["h"].tolist())
        low = sorted(held)[:k]
        state.update((low,))
        yield pd.DataFrame({"key": [at[0]], "hashes": [low]})

    kind = df.schema[key].dataType.simpleString()
    return h.groupBy("key").applyInPandasWithState(merge, f"key {kind}, hashes array<bigint>", "hashes array<bigint>", "update", GroupStateTimeout.NoTimeout)


def run_once(df: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> str:
    """Run over everything there is and stop; the name of the in-memory result, or of the query when ``each`` takes the
    batches."""
    name = f"stream_{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{shared_dir(df.sparkSession)}/{name}").trigger(availableNow=True)
    writer = writer.foreachBatch(each) if each else writer.format("memory").queryName(name)
    writer.start().awaitTermination()
    return name


def reselect(df: DataFrame, choose: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None]) -> None:
    """After each batch, select again on all cells so far.  Each batch's cells are a part of one table in the shared folder,
    written over when a batch is run again; ``choose`` gets the distinct cells of all parts."""
    spark = df.sparkSession
    folder = f"{shared_dir(spark)}/cells-{uuid.uuid4().hex}"

    def each(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch={i}")
        every = batch.sparkSession.read.schema(batch.schema).option("basePath", folder).parquet(folder)
        sink(choose(every.select(*batch.columns).distinct()), i)

    run_once(df, each=each)


def hourly_counts(spark: SparkSession, sf_dir: str, path: str | None = None, max_files: int | None = None) -> DataFrame:
    """``hour, n_events, n_users`` of the stream of cells hour by user.  Each batch leaves its counts of cells as a part of one
    table in the shared folder, written over when the batch is run again, so neither a state nor the driver holds the cells;
    a cell that several batches meet is summed at the end."""
    path = path or f"{sf_dir}/events.parquet"
    source = spark.readStream.schema(spark.read.parquet(path).schema)
    src = (source.option("maxFilesPerTrigger", max_files) if max_files else source).parquet(f"{path}*")
    cells = src.select(F.floor(F.unix_timestamp("ts") / 3600).alias("hour"), "user_id")
    folder = f"{shared_dir(spark)}/cells-{uuid.uuid4().hex}"
    schema = cells.schema.add("n", "long", False)

    def each(batch: DataFrame, i: int) -> None:
        batch.groupBy("hour", "user_id").agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{folder}/batch={i}")

    run_once(cells, each=each)
    # no batch ran over an empty input: then there is no folder
    parts = spark.read.schema(schema).option("basePath", folder).parquet(f"{folder}/batch=*") if _exists(spark, folder) else spark.createDataFrame([], schema)
    whole = parts.groupBy("hour", "user_id").agg(F.sum("n").alias("n"))
    return whole.groupBy("hour").agg(F.sum("n").alias("n_events"), F.count(F.lit(1)).alias("n_users"))


def _exists(spark: SparkSession, path: str) -> bool:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)
