"""Schemas of the internal tables and the two holders that selectors take: ``Matrix`` and ``Pool``."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import types as T


def _schema(*columns: tuple[str, T.DataType]) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in columns])


L, I, D, S = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType()
SCHEMAS = {
    "ones": _schema(("row_id", L), ("col_id", L)),
    "tiles": _schema(("tile_id", L), ("n_r", L), ("n_c", L), ("size", L)),
    "tile_rows": _schema(("tile_id", L), ("row_id", L)),
    "tile_cols": _schema(("tile_id", L), ("col_id", L)),
    "tile_cells": _schema(("tile_id", L), ("row_id", L), ("col_id", L)),
    "sketch": _schema(("tile_id", L), ("hashes", T.ArrayType(T.ArrayType(L)))),
    "selection": _schema(("step", I), ("tile_id", L), ("estimate", D), ("gain", L), ("error", L), ("rel_error", D), ("n_checked", I), ("elapsed_ms", L), ("n_cells", L), ("n_hashes", L)),
}


def require(df: DataFrame, name: str) -> DataFrame:
    """``df`` cut to the columns of the named schema, cast to its types; a missing column is an error."""
    wanted = SCHEMAS[name]
    missing = [f.name for f in wanted if f.name not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {', '.join(missing)}")
    return df.select(*(df[f.name].cast(f.dataType).alias(f.name) for f in wanted))


@dataclass
class Matrix:
    """A 0/1 matrix: its ones, and its shape, which counts empty rows and columns too."""

    ones: DataFrame
    n_rows: int
    n_cols: int
    cache: dict = field(default_factory=dict, repr=False)  # tables made from the ones that several steps read

    @property
    def cells(self) -> int:
        return self.n_rows * self.n_cols

    def transposed(self) -> Matrix:
        turned = self.ones.selectExpr("col_id as row_id", "row_id as col_id")
        return Matrix(turned, self.n_cols, self.n_rows)


@dataclass
class Pool:
    """Candidate patterns: outer products of rows and columns, or, with ``tile_cells``, any sets of cells."""

    tile_rows: DataFrame | None = None
    tile_cols: DataFrame | None = None
    tile_cells: DataFrame | None = None
    labels: DataFrame | None = None  # (tile_id, label) where a generator names its patterns
    dominated: bool = False  # known to hold no zero of the matrix
    cache: dict = field(default_factory=dict, repr=False)

    def cells(self) -> DataFrame:
        """Every cell of every pattern; only for enumeration and tests at small sizes."""
        if self.tile_cells is not None:
            return self.tile_cells
        return self.tile_rows.join(self.tile_cols, "tile_id").select("tile_id", "row_id", "col_id")

    def tiles(self) -> DataFrame:
        """``tile_id, n_r, n_c, size``."""
        from pyspark.sql import functions as F

        if self.tile_cells is not None:
            return self.tile_cells.groupBy("tile_id").agg(F.countDistinct("row_id").alias("n_r"), F.countDistinct("col_id").alias("n_c"), F.count(F.lit(1)).alias("size"))
        r = self.tile_rows.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_r"))
        c = self.tile_cols.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_c"))
        return r.join(c, "tile_id").select("tile_id", "n_r", "n_c", (F.col("n_r") * F.col("n_c")).alias("size"))

    def largest_id(self) -> int:
        """The largest row or column id."""
        from pyspark.sql import functions as F

        sides = [(self.tile_cells, "row_id"), (self.tile_cells, "col_id")] if self.tile_cells is not None else [(self.tile_rows, "row_id"), (self.tile_cols, "col_id")]
        return max(df.agg(F.max(c)).first()[0] or 0 for df, c in sides)

    def only(self, tile_ids: DataFrame) -> Pool:
        """The patterns of ``tile_ids(tile_id)``."""
        keep = lambda df: None if df is None else df.join(tile_ids, "tile_id", "left_semi")
        return Pool(keep(self.tile_rows), keep(self.tile_cols), keep(self.tile_cells), keep(self.labels), self.dominated)
