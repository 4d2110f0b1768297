"""Measures over matrices, pools and traces."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tilesketch.functions import estimate, hashing
from tilesketch.model import Matrix, Pool
from tilesketch.operators import sketch


def density(matrix: Matrix) -> DataFrame:
    """One row: ``n_rows, n_cols, n_ones, density``."""
    n = matrix.ones.agg(F.count(F.lit(1)).alias("n_ones"))
    return n.select(F.lit(matrix.n_rows).cast("long").alias("n_rows"), F.lit(matrix.n_cols).cast("long").alias("n_cols"), "n_ones", (F.col("n_ones") / F.lit(matrix.cells)).alias("density"))


def jaccard(both: Column, left: Column, right: Column) -> Column:
    return both / (left + right - both)


def support(matrix: Matrix, pool: Pool) -> DataFrame:
    """``tile_id, n_r, support``: rows of each pattern over all rows of the matrix."""
    rows = pool.tile_rows if pool.tile_rows is not None else pool.tile_cells.select("tile_id", "row_id").distinct()
    return rows.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_r")).withColumn("support", F.col("n_r") / F.lit(matrix.n_rows))


def best_prefix(trace: DataFrame) -> DataFrame:
    """One row: ``best_step, best_error``, the least error on the path and the first step that has it."""
    return trace.agg(F.min(F.struct("error", "step")).alias("m")).select(F.col("m.step").alias("best_step"), F.col("m.error").alias("best_error"))


def marginal_gain(trace: DataFrame) -> DataFrame:
    """``step, error, lowered`` by each pick."""
    w = Window.partitionBy(F.lit(0)).orderBy("step")
    return trace.select("step", "error", (F.lag("error").over(w) - F.col("error")).alias("lowered"))


def average_runs(runs: DataFrame, *config: str) -> DataFrame:
    return runs.groupBy(*config).agg(F.count(F.lit(1)).alias("n_runs"), F.avg("rel_error").alias("mean_error"), F.stddev_samp("rel_error").alias("sd_error"))


def coverage_ratio(trace: DataFrame, total: int, optimum_error: int) -> DataFrame:
    """One row: covered ones over those of the optimum."""
    return trace.agg(F.min("error").alias("error")).select(((F.lit(total) - F.col("error")) / F.lit(total - optimum_error)).alias("ratio"))


def planted_precision(trace: DataFrame, originals: DataFrame) -> DataFrame:
    """One row: ``n_picks, n_planted, share`` of picks that are planted originals (``originals(tile_id)``)."""
    hit = trace.join(originals.withColumn("o", F.lit(1)), "tile_id", "left")
    return hit.agg(F.count(F.lit(1)).alias("n_picks"), F.count("o").alias("n_planted")).withColumn("share", F.col("n_planted") / F.col("n_picks"))


def union_size(lists: DataFrame, k: int, reps: int, prime: int = hashing.PRIME) -> DataFrame:
    """One row: the estimated number of cells of the union of all listed patterns; lists merge as a distributed top-k."""
    h = lists.select(F.posexplode("hashes").alias("rep", "h")).select("rep", F.explode("h").alias("h")).distinct()
    low = h.withColumn("n", F.row_number().over(Window.partitionBy("rep").orderBy("h"))).where(F.col("n") <= k)
    each = low.groupBy("rep").agg(F.array_sort(F.collect_list("h")).alias("hashes"))
    return each.select(estimate.size(F.col("hashes"), k, prime).alias("e")).agg(F.median("e").alias("estimate"))


def estimate_accuracy(pool: Pool, k: int = 30, reps: int = 10, seed: int = 42, strategy: str | None = None) -> DataFrame:
    """``tile_id, estimate, size, ratio`` for each pattern alone."""
    lists = sketch.build(pool, hashing.family(reps, seed), k, strategy)
    own = lists.select("tile_id", estimate.median_of(F.transform("hashes", lambda h: estimate.size(h, k))).alias("estimate"))
    return own.join(pool.tiles().select("tile_id", "size"), "tile_id").withColumn("ratio", F.col("estimate") / F.col("size"))


def builtin_sizes(pool: Pool, kind: str = "hll", **more: str) -> DataFrame:
    """``tile_id, estimate`` by Spark's own sketches over the cells; ``more`` names further columns and their kinds, made in
    the same pass."""
    cells = pool.cells().select("tile_id", F.xxhash64("row_id", "col_id").alias("key"))
    key = F.col("key")
    make = {"approx": F.approx_count_distinct(key).cast("double"), "hll": F.hll_sketch_estimate(F.hll_sketch_agg(key)).cast("double"), "theta": F.theta_sketch_estimate(F.theta_sketch_agg(key)).cast("double")}
    return cells.groupBy("tile_id").agg(make[kind].alias("estimate"), *(make[k].alias(name) for name, k in more.items()))
