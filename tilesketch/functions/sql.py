"""SQL functions for the sketch, visible to the optimiser, and a lateral table function for cells."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from tilesketch.functions.hashing import PRIME



def bottom_k(df: DataFrame, value: str, k: int, *by: str) -> DataFrame:
    """``by..., lowest``: the k smallest distinct values of each group, ascending; null is no value.  Values are made
    distinct first, which spreads a hot group, and the rank limit is applied before the second shuffle too, so no task
    sees more than k values of a group from each task before it."""
    distinct = df.where(F.col(value).isNotNull()).select(*by, value).distinct()
    place = F.row_number().over(Window.partitionBy(*by).orderBy(value))
    low = distinct.withColumn("__place", place).where(F.col("__place") <= k)
    return low.groupBy(*by).agg(F.array_sort(F.collect_list(value)).alias("lowest"))


def register(spark: SparkSession) -> None:
    """``tile_hash(row, col, a_row, b_row, a_col, b_col)``, ``sketch_merge(a, b, k)``, ``sketch_estimate(a, k)`` and
    ``tile_cells(rows, cols)``, and ``query_pair_cells(rows_left, cols_left, rows_right, cols_right, offset)``: rows of both
    queries, columns of either, those of the right view moved by ``offset``."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tile_hash(r BIGINT, c BIGINT, ar BIGINT, br BIGINT, ac BIGINT, bc BIGINT) RETURNS BIGINT RETURN pmod((ar * r + br) % {PRIME} - (ac * c + bc) % {PRIME}, {PRIME})")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sketch_merge(a ARRAY<BIGINT>, b ARRAY<BIGINT>, k INT) RETURNS ARRAY<BIGINT> RETURN slice(array_sort(array_union(a, b)), 1, k)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_estimate(a ARRAY<BIGINT>, k INT) RETURNS DOUBLE RETURN CASE WHEN size(a) < k THEN cast(size(a) AS DOUBLE) ELSE cast(k AS DOUBLE) / ((try_element_at(a, k) + 1) / cast({PRIME} AS DOUBLE)) END")

    class TileCells:
        def eval(self, rows: list, cols: list):
            for r in rows:
                for c in cols:
                    yield r, c

    class QueryPairCells:
        def eval(self, rows_left: list, cols_left: list, rows_right: list, cols_right: list, offset: int):
            cols = sorted(set(cols_left or []) | {c + offset for c in cols_right or []})
            for r in sorted(set(rows_left or []) & set(rows_right or [])):
                for c in cols:
                    yield r, c

    spark.udtf.register("query_pair_cells", udtf(QueryPairCells, returnType="row_id: bigint, col_id: bigint"))
    spark.udtf.register("tile_cells", udtf(TileCells, returnType="row_id: bigint, col_id: bigint"))
