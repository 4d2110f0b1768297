"""Exact counts: what patterns cover of a matrix, alone and together."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesketch.model import Matrix, Pool


def hits(ones: DataFrame, pool: Pool) -> DataFrame:
    """``(tile_id, row_id, col_id)`` of the cells of ``ones`` that a pattern covers; zeros are never enumerated."""
    if pool.tile_cells is not None:
        return pool.tile_cells.join(ones, ["row_id", "col_id"]).select("tile_id", "row_id", "col_id")
    return pool.tile_cols.join(ones, "col_id").join(pool.tile_rows, ["tile_id", "row_id"]).select("tile_id", "row_id", "col_id")


def profile(matrix: Matrix, pool: Pool) -> DataFrame:
    """The catalogue: ``tile_id, n_r, n_c, size, ones, zeros``."""
    t = pool.tiles()
    if pool.dominated:
        return t.select("*", F.col("size").alias("ones"), F.lit(0).cast("long").alias("zeros"))
    n = hits(matrix.ones, pool).groupBy("tile_id").agg(F.count(F.lit(1)).alias("ones"))
    return t.join(n, "tile_id", "left").withColumn("ones", F.coalesce("ones", F.lit(0)).cast("long")).withColumn("zeros", F.col("size") - F.col("ones"))


def covered(pool: Pool) -> DataFrame:
    """Distinct cells of the union of all patterns of the pool."""
    return pool.cells().select("row_id", "col_id").distinct()


def error_parts(matrix: Matrix, pool: Pool) -> DataFrame:
    """One row: ``uncovered_ones, covered_zeros``."""
    both = matrix.ones.withColumn("d", F.lit(1)).join(covered(pool).withColumn("c", F.lit(1)), ["row_id", "col_id"], "full_outer")
    return both.agg(F.count_if(F.col("c").isNull()).alias("uncovered_ones"), F.count_if(F.col("d").isNull()).alias("covered_zeros"))


def error(matrix: Matrix, pool: Pool) -> DataFrame:
    """One row: ``error`` (wrong cells) and ``rel_error``."""
    e = error_parts(matrix, pool).select((F.col("uncovered_ones") + F.col("covered_zeros")).alias("error"))
    return e.select("error", (F.col("error") / F.lit(matrix.cells)).alias("rel_error"))


def exact_error(matrix: Matrix, pool: Pool) -> DataFrame:
    """One row: ``error``, the ones that no pattern covers (patterns inside the matrix)."""
    return matrix.ones.join(covered(pool), ["row_id", "col_id"], "left_anti").agg(F.count(F.lit(1)).alias("error"))


def dominated(matrix: Matrix, pool: Pool) -> DataFrame:
    """``tile_id, is_dominated``: whether a pattern holds no zero."""
    return profile(matrix, pool).select("tile_id", (F.col("zeros") == 0).alias("is_dominated"))


def coverable(matrix: Matrix, pool: Pool) -> DataFrame:
    """One row: ``missing`` ones that no pattern covers, and ``coverable``."""
    return exact_error(matrix, pool).select(F.col("error").alias("missing"), (F.col("error") == 0).alias("coverable"))


def error_path(matrix: Matrix, pool: Pool, order: DataFrame) -> DataFrame:
    """``step, error, rel_error`` after each of ``order(step, tile_id)``: every cell counts at the first step that covers
    it, so the whole path is one aggregation."""
    steps = order.select("step", "tile_id")
    first = pool.cells().join(steps, "tile_id").groupBy("row_id", "col_id").agg(F.min("step").alias("step"))
    gain = first.join(matrix.ones.withColumn("d", F.lit(1)), ["row_id", "col_id"], "left").groupBy("step").agg(F.sum(F.when(F.col("d") == 1, 1).otherwise(-1)).alias("gain"))
    total = matrix.ones.count()
    per = steps.select("step").join(gain, "step", "left").withColumn("gain", F.coalesce("gain", F.lit(0)))
    w = Window.partitionBy(F.lit(0)).orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return per.select("step", (F.lit(total) - F.sum("gain").over(w)).cast("long").alias("error")).withColumn("rel_error", F.col("error") / F.lit(matrix.cells))


def overlap(pool: Pool) -> DataFrame:
    """``tile_a, tile_b, shared`` cells of every pair that shares any: rows in common times columns in common."""
    pairs = lambda df, x: df.select(F.col("tile_id").alias("tile_a"), x).join(df.select(F.col("tile_id").alias("tile_b"), x), x).where("tile_a < tile_b").groupBy("tile_a", "tile_b").agg(F.count(F.lit(1)).alias(f"n_{x}"))
    return pairs(pool.tile_rows, "row_id").join(pairs(pool.tile_cols, "col_id"), ["tile_a", "tile_b"]).select("tile_a", "tile_b", (F.col("n_row_id") * F.col("n_col_id")).alias("shared"))
