"""Patterns from the association matrix and from random walks with restart."""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.model import Matrix, Pool
from tilesketch.operators.baskets import TABLE, _entries, baskets
from tilesketch.operators.packed import PackedPool
from tilesketch.session import cut

WIDE = 40_000  # columns from which on pairs are counted by a join
FEW = 2_000  # columns up to which the driver holds a table of their pairs
COUNTS = 16_000_000  # counts of pairs that a task holds at once


def _pair_counts(matrix: Matrix) -> tuple[DataFrame, np.ndarray] | None:
    """``place, cols, n``: rows with both columns, as partial lists of places, one of each part of the rows, and the columns.  A task adds the pairs of
    its rows up in a table of counts, a block of tiles at a time; None where there are too many columns for that."""
    if matrix.n_cols > WIDE:
        return None
    if "pair counts" in matrix.cache:
        return matrix.cache["pair counts"]
    cols = np.sort(matrix.ones.select("col_id").distinct().toArrow().column(0).to_numpy().astype(np.int64))
    block = max(1, COUNTS // max(1, len(cols)))

    def count(batches):
        held = []
        for b in batches:
            row, at = _entries(b.column(0), cols)
            held += np.split(at.astype(np.int32), np.flatnonzero(np.diff(row)) + 1) if len(row) else []
        for low in range(0, len(cols), block) if held else ():
            n = np.zeros((min(block, len(cols) - low), len(cols)), np.int32)
            for items in held:
                a, b = np.searchsorted(items, [low, low + len(n)])
                if a < b:
                    n[np.ix_(items[a:b] - low, items)] += 1
            for a in range(0, len(n), 256):
                part = n[a : a + 256]
                tile, col = np.nonzero(part)
                ends = np.searchsorted(tile, np.arange(len(part) + 1)).astype(np.int32)
                lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(x)) for x in (col.astype(np.int32), part[tile, col])]
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(low + a, low + a + len(part))), *lists], ["place", "cols", "n"])

    parts = matrix.ones.sparkSession.sparkContext.defaultParallelism
    counted = baskets(matrix).select("items").repartition(parts).mapInArrow(count, "place long, cols array<int>, n array<int>").where(F.size("cols") > 0)
    if len(cols) > FEW:
        return counted, cols
    matrix.cache["pair counts"] = cut(counted), cols  # few, and wanted for each threshold
    return matrix.cache["pair counts"]


def association_columns(matrix: Matrix, tau: float) -> DataFrame:
    """``tile_id, col_id``: for each column i the columns j whose confidence, rows with both over rows with i, is at least
    ``tau``.  The tile's id is i."""
    counted = _pair_counts(matrix)
    if counted is not None:
        parts, cols = counted

        def strong(table: pa.Table) -> pa.Table:
            n = np.zeros(len(cols), np.int64)
            for c, x in zip(table.column("cols"), table.column("n"), strict=True):
                n[np.asarray(c.values)] += np.asarray(x.values)
            i = table.column("place")[0].as_py()
            kept = np.flatnonzero((n > 0) & (n / n[i] >= tau))
            return pa.table({"tile_id": np.full(len(kept), cols[i]), "col_id": cols[kept]})

        return parts.groupBy("place").applyInArrow(strong, "tile_id long, col_id long")
    ones = matrix.ones
    both = ones.select("row_id", F.col("col_id").alias("tile_id")).join(ones, "row_id").groupBy("tile_id", "col_id").agg(F.count(F.lit(1)).alias("n"))
    support = ones.groupBy(F.col("col_id").alias("tile_id")).agg(F.count(F.lit(1)).alias("s"))
    return both.join(support, "tile_id").where(F.col("n") / F.col("s") >= tau).select("tile_id", "col_id")


def rows_for(matrix: Matrix, columns: DataFrame, rule: str = "majority") -> DataFrame:
    """``tile_id, row_id`` for column vectors: "majority" takes rows where ones outnumber zeros in the tile's columns,
    "all" rows that hold every column, "item" rows that hold the seed column."""
    if rule == "item":
        return columns.select("tile_id").distinct().join(matrix.ones, F.col("tile_id") == F.col("col_id")).select("tile_id", "row_id")
    if columns.count() <= 4 * COUNTS:
        return _rows_by_counts(matrix, columns, rule)
    size = columns.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_c"))
    hits = columns.join(matrix.ones, "col_id").groupBy("tile_id", "row_id").agg(F.count(F.lit(1)).alias("hits")).join(size, "tile_id")
    return hits.where("2 * hits > n_c" if rule == "majority" else "hits = n_c").select("tile_id", "row_id")


def _rows_by_counts(matrix: Matrix, columns: DataFrame, rule: str) -> DataFrame:
    return _members(matrix, columns, rule).select(F.explode("tiles").alias("tile_id"), "row_id")


def _members(matrix: Matrix, columns: DataFrame, rule: str) -> DataFrame:
    """``row_id, tiles`` for column vectors: a task adds up, for each of its rows, the tiles of the columns that the row holds."""
    got = columns.select(F.col("tile_id").cast("long"), F.col("col_id").cast("long")).toArrow()
    tile, col = (got.column(i).to_numpy() for i in range(2))
    ids, cols = np.unique(tile), np.unique(col)
    order = np.argsort(col, kind="stable")
    tiles = np.searchsorted(ids, tile[order]).astype(np.int32)
    start = np.searchsorted(col[order], np.concatenate([cols, [np.iinfo(np.int64).max]]))
    size = np.bincount(tiles, minlength=len(ids))

    def rows(batches):
        for b in batches:
            row, at = _entries(b.column(1), cols)
            row_id, found = b.column(0).to_numpy(zero_copy_only=False), []
            edges = np.concatenate([[0], np.flatnonzero(np.diff(row)) + 1, [len(row)]]) if len(row) else np.zeros(1, np.int64)
            held = 0
            for x, y in zip(edges, edges[1:], strict=False):
                n = np.bincount(np.concatenate([tiles[start[c] : start[c + 1]] for c in at[x:y]]), minlength=len(ids))
                inside = np.flatnonzero(2 * n > size if rule == "majority" else n == size)
                if len(inside):
                    found.append((row_id[row[x]], ids[inside]))
                held += len(inside)
                if held > 1_000_000:
                    yield _batch(found)
                    found, held = [], 0
            if found:
                yield _batch(found)

    return baskets(matrix).mapInArrow(rows, "row_id long, tiles array<long>")


def _batch(found: list) -> pa.RecordBatch:
    ends = np.concatenate([[0], np.cumsum([len(t) for _, t in found])]).astype(np.int32)
    tiles = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([t for _, t in found])))
    return pa.RecordBatch.from_arrays([pa.array([r for r, _ in found], pa.int64()), tiles], ["row_id", "tiles"])


def as_pool(matrix: Matrix, columns: DataFrame, rule: str = "majority") -> Pool:
    """The patterns of column vectors; where rows are found by counts they are kept as lists of each row's patterns."""
    if rule != "item" and columns.count() <= 4 * COUNTS:
        members = cut(_members(matrix, columns, rule))
        held = members.select(F.explode("tiles").alias("tile_id")).distinct()
        return PackedPool(members, cut(columns.join(held, "tile_id", "left_semi")), dominated=rule == "all", whole=True)
    rows = cut(rows_for(matrix, columns, rule))
    cols = columns.join(rows.select("tile_id").distinct(), "tile_id", "left_semi")
    return Pool(rows, cut(cols), dominated=rule == "all")


def association(matrix: Matrix, tau: float, rule: str = "majority", axis: str = "cols") -> Pool:
    """One tile for each column, or with ``axis`` "rows" for each row: the same on the transposed matrix."""
    if axis == "cols":
        return as_pool(matrix, cut(association_columns(matrix, tau)), rule)
    if axis != "rows":
        raise ValueError("axis is 'cols' or 'rows'")
    pool = association(matrix.transposed(), tau, rule)
    turn = lambda df, a, b: df.withColumnRenamed(a, b)
    return Pool(turn(pool.tile_cols, "col_id", "row_id"), turn(pool.tile_rows, "row_id", "col_id"), dominated=pool.dominated)


def restart_walk_columns(matrix: Matrix, restart: float = 0.15, steps: int = 4, keep: int = 8, least: float = 1e-4) -> DataFrame:
    """``tile_id, col_id``: power iteration of a walk column - row - column that returns to its seed column with
    probability ``restart``; the ``keep`` heaviest columns of each seed.  Mass under ``least`` is not walked on."""
    from pyspark.sql import Window

    if 0 < matrix.n_cols <= FEW:
        return _walked_on_driver(matrix, restart, steps, keep, least)
    ones = matrix.ones
    by_row = ones.join(ones.groupBy("row_id").agg(F.count(F.lit(1)).alias("d")), "row_id").select("row_id", "col_id", (1 / F.col("d")).alias("p"))
    by_col = ones.groupBy("col_id").agg(F.count(F.lit(1)).alias("d"))
    step = ones.join(by_col, "col_id").select(F.col("col_id").alias("from"), "row_id", (1 / F.col("d")).alias("q")).join(by_row, "row_id").groupBy("from", "col_id").agg(F.sum(F.col("p") * F.col("q")).alias("p"))
    step = cut(step)
    seeds = by_col.select(F.col("col_id").alias("tile_id"), "col_id", F.lit(1.0).alias("m"))
    mass = seeds
    for _ in range(steps):
        walked = mass.where(F.col("m") >= least).select("tile_id", F.col("col_id").alias("from"), "m").join(step, "from").select("tile_id", "col_id", (F.col("m") * F.col("p") * (1 - restart)).alias("m"))
        mass = cut(walked.unionByName(seeds.withColumn("m", F.lit(restart))).groupBy("tile_id", "col_id").agg(F.sum("m").alias("m")))
    top = Window.partitionBy("tile_id").orderBy(F.desc(F.round("m", 9)), "col_id")
    return mass.withColumn("n", F.row_number().over(top)).where(F.col("n") <= keep).select("tile_id", "col_id")


def _walked_on_driver(matrix: Matrix, restart: float, steps: int, keep: int, least: float) -> DataFrame:
    """The same where columns are few: tasks add up the steps from column to column of their rows, the driver walks."""
    cols = np.sort(matrix.ones.select("col_id").distinct().toArrow().column(0).to_numpy().astype(np.int64))
    n, size = len(cols), max(1, TABLE // max(1, len(cols)))

    def steps_of(batches):
        total = np.zeros((n, n))
        for batch in batches:
            for x in range(0, batch.num_rows, size):
                row, at = _entries(batch.column(0).slice(x, size), cols)
                held = np.zeros((min(size, batch.num_rows - x), n))
                held[row, at] = 1
                total += held.T @ (held / np.maximum(1, held.sum(1, keepdims=True)))
        if total.any():
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(list(total), pa.list_(pa.float64()))], ["place", "p"])

    spark = matrix.ones.sparkSession
    parts = baskets(matrix).select("items").coalesce(spark.sparkContext.defaultParallelism).mapInArrow(steps_of, "place long, p array<double>")
    got, step = parts.toArrow(), np.zeros((n, n))
    for i, p in zip(got.column(0).to_pylist(), got.column(1), strict=True):
        step[i] += np.asarray(p.values)
    support = step.sum(1)  # a row's shares add up to one
    step /= np.maximum(support, 1e-300)[:, None]
    mass = np.eye(n)
    for _ in range(steps):
        mass = (1 - restart) * (np.where(mass >= least, mass, 0) @ step) + restart * np.eye(n)
    order = np.argsort(-np.round(mass, 9), axis=1, kind="stable")[:, :keep]
    seed, place = np.repeat(np.arange(n), order.shape[1]), order.reshape(-1)
    reached = mass[seed, place] > 0
    return spark.createDataFrame(pa.table({"tile_id": cols[seed[reached]], "col_id": cols[place[reached]]}))


def restart_walk(matrix: Matrix, rule: str = "majority", **options) -> Pool:
    return as_pool(matrix, cut(restart_walk_columns(matrix, **options)), rule)


def joined(*pools: Pool) -> Pool:
    """Pools side by side; the ids of pool i are moved by i times 2^40."""
    move = lambda df, i: df.withColumn("tile_id", F.col("tile_id") + F.lit(i << 40))
    if pools and all(isinstance(p, PackedPool) and len(p.parts) == 1 for p in pools):
        parts = [(p.members.select("row_id", F.expr(f"transform(tiles, x -> x + {i << 40})").alias("tiles")), move(p.tile_cols, i)) for i, p in enumerate(pools)]
        both = [functools.reduce(DataFrame.unionByName, x) for x in zip(*parts, strict=True)]
        return PackedPool(*both, dominated=all(p.dominated for p in pools), whole=True, parts=parts)
    rows, cols = None, None
    for i, p in enumerate(pools):
        r, c = move(p.tile_rows, i), move(p.tile_cols, i)
        rows, cols = (r, c) if rows is None else (rows.unionByName(r), cols.unionByName(c))
    return Pool(rows, cols, dominated=all(p.dominated for p in pools))
