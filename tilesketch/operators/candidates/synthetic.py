"""Planted patterns: originals with Bernoulli row and column vectors, copies with some ones moved, and noise.

Every draw is a function of the seed and of keys, so SQL can draw the same."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilesketch.functions.hashing import draw, uniform
from tilesketch.model import Matrix, Pool
from tilesketch.session import cut


def keys(df: DataFrame, name: str, n: int) -> DataFrame:
    """The first ``n`` ids of a key column."""
    return df.select(F.col(name).cast("long").alias("id")).distinct().orderBy("id").limit(n)


def vectors(ids: DataFrame, n_tiles: int, p: float, seed: int, side: str) -> DataFrame:
    """``tile_id, id`` of Bernoulli(p) vectors for tiles 0 to ``n_tiles`` - 1."""
    tiles = ids.sparkSession.range(n_tiles).select(F.col("id").alias("tile_id"))
    return F.broadcast(tiles).join(ids, F.lit(True), "inner").where(uniform(seed, F.lit(side), "tile_id", "id") < p)


def moved(original: DataFrame, ids: DataFrame, n_tiles: int, copies: int, move: float, seed: int, side: str) -> DataFrame:
    """``tile_id, id`` of the copies: of each vector round(move * ones) ones go, and as many former zeros come.  Copy c of
    tile t has the id ``n_tiles + t * copies + c - 1``."""
    spark = ids.sparkSession
    every = F.broadcast(spark.range(n_tiles).select(F.col("id").alias("t"))).join(ids, F.lit(True), "inner").join(original.select(F.col("tile_id").alias("t"), "id", F.lit(1).alias("one")), ["t", "id"], "left")
    size = original.groupBy(F.col("tile_id").alias("t")).agg(F.count(F.lit(1)).alias("n"))
    drawn = every.join(size, "t").join(F.broadcast(spark.range(1, copies + 1).select(F.col("id").alias("c"))), F.lit(True), "inner").withColumn("u", uniform(seed, F.lit(side + "m"), "t", "c", "id"))
    place = F.row_number().over(Window.partitionBy("t", "c", "one").orderBy("u", "id"))
    k = F.floor(F.col("n") * move + 0.5)
    kept = drawn.withColumn("place", place).where((F.col("one").isNotNull() & (F.col("place") > k)) | (F.col("one").isNull() & (F.col("place") <= k)))
    return kept.select((F.lit(n_tiles) + F.col("t") * copies + F.col("c") - 1).alias("tile_id"), "id")


def calibrated(density: float, n_tiles: int) -> float:
    """The Bernoulli parameter whose ``n_tiles`` independent tiles cover the given share of cells."""
    return (1 - (1 - density) ** (1 / n_tiles)) ** 0.5


def calibrate(density: float, n_orig: int, copies: int, move: float, use: str = "orig", draws: int = 9, shape: tuple[int, int] = (200, 200), seed: int = 7) -> float:
    """The parameter for originals in closed form, and for all tiles by bisection on small drawn matrices."""
    if use == "orig":
        return calibrated(density, n_orig)

    def reached(p: float) -> float:
        rng = np.random.default_rng(seed)
        out = np.zeros(shape, bool)
        for _ in range(n_orig):
            u, v = (rng.random(n) < p for n in shape)
            out |= np.outer(u, v)
            for _ in range(copies):
                pair = []
                for x in (u, v):
                    y, k = x.copy(), int(move * x.sum() + 0.5)
                    y[rng.permutation(np.flatnonzero(x))[:k]] = False
                    y[rng.permutation(np.flatnonzero(~x))[:k]] = True
                    pair.append(y)
                out |= np.outer(*pair)
        return out.mean()

    low, high = 0.0, 1.0
    for _ in range(draws):
        mid = (low + high) / 2
        low, high = (mid, high) if reached(mid) < density else (low, mid)
    return (low + high) / 2


def drawn_cells(rows: DataFrame, cols: DataFrame, rate: float, seed: int) -> DataFrame:
    """``row_id, col_id`` of cells drawn with probability ``rate`` at the cost of the drawn ones: each row draws how many
    columns (a binomial) and which, as places that a join turns into ids.  A row's draw depends on the seed and its id
    alone, so a task that runs again draws the same."""
    at = cut(cols.select(F.col("id").alias("col_id")).distinct())
    placed = cut(numbered(at, "col_id"))
    n = placed.count()

    def draw_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.column(0).to_pylist():
                rng = np.random.Generator(np.random.Philox(key=[seed, row & (2**64 - 1)]))
                places = rng.choice(n, rng.binomial(n, rate), replace=False, shuffle=False)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(places), row)), pa.array(places.astype(np.int64))], names=["row_id", "place"])

    drawn = rows.select(F.col("id").cast("long").alias("row_id")).distinct().mapInArrow(draw_rows, "row_id long, place long")
    return drawn.join(placed, "place").select("row_id", "col_id")


def numbered(df: DataFrame, key: str) -> DataFrame:
    """``key, place``: dense places from 0 in the order of the key, by ranges: only the sizes of the ranges meet the driver."""
    parts = cut(df.select(key).repartitionByRange(key).withColumn("part", F.spark_partition_id()))
    sizes = sorted(parts.groupBy("part").count().collect())
    starts = {p: sum(r["count"] for r in sizes[:i]) for i, p in enumerate(r.part for r in sizes)}
    first = F.create_map(*(F.lit(v) for pair in starts.items() for v in pair)) if starts else F.create_map(F.lit(0), F.lit(0))
    place = F.row_number().over(Window.partitionBy("part").orderBy(key)) - 1 + F.element_at(first, F.col("part"))
    return parts.select(key, place.cast("long").alias("place"))


def flip(matrix: Matrix, rows: DataFrame, cols: DataFrame, rate: float, seed: int, how: str = "crossed") -> Matrix:
    """Each cell changed with probability ``rate``: the symmetric difference with the drawn cells.  ``how`` "crossed" looks
    at every cell, with draws that SQL can repeat; "drawn" makes the changed cells alone, for large matrices."""
    if how == "crossed":
        crossed = rows.select(F.col("id").alias("row_id")).join(cols.select(F.col("id").alias("col_id")), F.lit(True), "inner")
        drawn = crossed.where(uniform(seed, F.lit("n"), "row_id", "col_id") < rate)
    elif how == "drawn":
        drawn = drawn_cells(rows, cols, rate, seed)
    else:
        raise ValueError("how is 'crossed' or 'drawn'")
    both = matrix.ones.withColumn("d", F.lit(1)).join(drawn.withColumn("f", F.lit(1)), ["row_id", "col_id"], "full_outer").where("d is null or f is null").select("row_id", "col_id")
    return Matrix(cut(both), matrix.n_rows, matrix.n_cols)


def planted(rows: DataFrame, cols: DataFrame, n_orig: int = 100, copies: int = 5, density: float = 0.3, move: float = 0.1, use: str = "orig", noise: float = 0.0, seed: int = 1, p: float | None = None, how: str = "crossed") -> tuple[Matrix, Pool]:
    """Tiles 0 to ``n_orig`` - 1 are originals.  ``use`` "orig" builds the matrix from them, "all" from every tile; then
    noise flips cells (``how`` as in ``flip``).  With "all" and no noise every tile lies inside the matrix."""
    p = calibrate(density, n_orig, copies, move, use) if p is None else p
    rows, cols = cut(rows), cut(cols)
    n_rows, n_cols = rows.count(), cols.count()
    u, v = cut(vectors(rows, n_orig, p, seed, "r")), cut(vectors(cols, n_orig, p, seed, "c"))
    tile_rows = cut(u.unionByName(moved(u, rows, n_orig, copies, move, seed, "r")).withColumnRenamed("id", "row_id"))
    tile_cols = cut(v.unionByName(moved(v, cols, n_orig, copies, move, seed, "c")).withColumnRenamed("id", "col_id"))
    whole = (tile_rows.select("tile_id").intersect(tile_cols.select("tile_id"))).distinct()
    pool = Pool(cut(tile_rows.join(whole, "tile_id", "left_semi")), cut(tile_cols.join(whole, "tile_id", "left_semi")), dominated=use == "all" and not noise)
    used = pool if use == "all" else pool.only(whole.where(F.col("tile_id") < n_orig))
    matrix = Matrix(cut(used.cells().select("row_id", "col_id").distinct()), n_rows, n_cols)
    return (flip(matrix, rows, cols, noise, seed, how) if noise else matrix), pool


def grid(spark: SparkSession, sf_dir: str, n_rows: int, n_cols: int) -> tuple[DataFrame, DataFrame]:
    """Row ids from order keys and column ids from part keys."""
    return keys(spark.read.parquet(f"{sf_dir}/orders.parquet"), "o_orderkey", n_rows), keys(spark.read.parquet(f"{sf_dir}/part.parquet"), "p_partkey", n_cols)


__all__ = ["calibrate", "calibrated", "draw", "drawn_cells", "flip", "grid", "keys", "moved", "numbered", "planted", "vectors"]
