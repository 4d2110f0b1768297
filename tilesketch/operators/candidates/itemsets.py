"""Frequent and closed itemsets as patterns: items are columns, supporting transactions are rows."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.model import Matrix, Pool
from tilesketch.operators.baskets import FEW_COLUMNS, ItemsetPool, baskets, classes, few_classes, limited
from tilesketch.session import cut

FEW_PAIRS = 8_000_000  # pairs of sets and elements that the driver takes as they are
MOST_READ = 1_000_000_000  # cells that the driver looks at before tasks do the mining


def itemsets(matrix: Matrix, min_support: float, max_len: int | None = None) -> DataFrame:
    """``tile_id, items array<long> (ascending), support`` of the itemsets in at least ``min_support`` of the rows."""
    from pyspark.ml.fpm import FPGrowth

    held = baskets(matrix).select("items")
    need = math.ceil(min_support * matrix.n_rows - 1e-9)
    often = held.select(F.explode("items").alias("col_id")).groupBy("col_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= need).select("col_id")
    cols = often.limit(FEW_COLUMNS + 1).toArrow().column(0).to_numpy()
    if len(cols) <= FEW_COLUMNS:
        held = cut(limited(held, np.sort(cols)))  # the others are in no frequent set
    present = held.count()
    found = FPGrowth(itemsCol="items", minSupport=min(1.0, max(0.0, need - 0.5) / max(1, present)), minConfidence=1.0).fit(held).freqItemsets
    found = found.where(F.col("freq") >= need).select(F.array_sort("items").alias("items"), F.col("freq").alias("support"))
    if max_len is not None:
        found = found.where(F.size("items") <= max_len)
    return cut(found.select(tile_key("items").alias("tile_id"), "items", "support"))


def level_itemsets(matrix: Matrix, min_support: float, max_len: int | None = 2) -> DataFrame:
    """The same rows as ``itemsets`` up to a length (None: until a level is empty), level by level with joins over the distinct
    baskets; no model is built.  Where these are few, the driver counts them."""
    need = math.ceil(min_support * matrix.n_rows - 1e-9)
    few = few_classes(matrix)
    found = None if few is None else _mined(*few, need, max_len)
    if found:
        items, support = zip(*found, strict=True)
        sets = matrix.ones.sparkSession.createDataFrame(pa.table({"items": pa.array(items, pa.list_(pa.int64())), "support": pa.array(support, pa.int64())}))
        return sets.select(tile_key("items").alias("tile_id"), "items", "support")
    ones = cut(classes(matrix).select(F.monotonically_increasing_id().alias("row_id"), "n", "items")).select("row_id", "n", F.explode("items").alias("col_id"))
    freq = cut(ones.groupBy("col_id").agg(F.sum("n").alias("support")).where(F.col("support") >= need))
    ones = ones.join(F.broadcast(freq.select("col_id")), "col_id", "left_semi")
    held = ones.select("row_id", "col_id")
    out = freq.select(F.array("col_id").alias("items"), "support")
    rows = ones.select("row_id", "n", F.array("col_id").alias("items"))
    size = 1
    while max_len is None or size < max_len:
        rows = rows.join(held, "row_id").where(F.col("col_id") > F.element_at("items", -1)).select("row_id", "n", F.concat("items", F.array("col_id")).alias("items"))
        level = cut(rows.groupBy("items").agg(F.sum("n").alias("support")).where(F.col("support") >= need))
        if level.isEmpty():
            break
        rows = cut(rows.join(level.select("items"), "items", "left_semi"))
        out = out.unionByName(level)
        size += 1
    return cut(out.select(tile_key("items").alias("tile_id"), "items", "support"))


def _mined(weight: np.ndarray, lists: pa.Array, need: int, max_len: int | None) -> list[tuple[list[int], int]] | None:
    """The frequent itemsets and their supports, from classes of rows; None when there is too much to look at."""
    row = np.repeat(np.arange(len(lists)), np.asarray(lists.value_lengths()).astype(np.int64))
    cols, at = np.unique(np.asarray(lists.flatten()).astype(np.int64), return_inverse=True)
    held = np.zeros((len(lists), len(cols)), bool)
    held[row, at] = True
    out, read, todo = [], 0, [((), np.arange(len(lists)))]
    while todo:
        items, rows = todo.pop()
        low = items[-1] + 1 if items else 0
        read += len(rows) * (len(cols) - low)
        if read > MOST_READ:
            return None
        inside, n = held[rows, low:], np.zeros(len(cols) - low, np.int64)
        for a in range(0, len(rows), 65_536):
            n += weight[rows[a : a + 65_536]] @ inside[a : a + 65_536]
        for j in np.flatnonzero(n >= max(1, need)).tolist():
            more = (*items, low + j)
            out.append((cols[list(more)].tolist(), int(n[j])))
            if max_len is None or len(more) < max_len:
                todo.append((more, rows[inside[:, j]]))
    return out


def tile_key(items):
    """An id of an itemset: for up to three items below 10^5 their digits, else a hash."""
    items = F.col(items) if isinstance(items, str) else items
    digits = F.aggregate(items, F.lit(0).cast("long"), lambda s, x: s * 100_000 + x + 1)
    small = (F.size(items) <= 3) & F.forall(items, lambda x: x < 99_999)
    return F.when(small, digits).otherwise(-F.abs(F.xxhash64(items)))


def as_pool(matrix: Matrix, sets: DataFrame) -> Pool:
    """Rows by relational division: a row supports a set when it holds as many of its items as the set has.  It is done over
    the distinct baskets, and rows are listed only for those who ask for them."""
    return ItemsetPool(matrix, cut(sets.select("tile_id", F.explode("items").alias("col_id"))))


def closed(sets: DataFrame) -> DataFrame:
    """The sets without a superset of one more item and equal support."""
    n = F.size("items")
    sub = sets.where(n > 1).select("support", F.explode(F.transform("items", lambda x: F.array_remove(F.col("items"), x))).alias("items")).distinct()
    return sets.join(sub, ["items", "support"], "left_anti").select("tile_id", "items", "support")


def maximal(sets: DataFrame) -> DataFrame:
    """The sets without a frequent superset of one more item."""
    sub = sets.where(F.size("items") > 1).select(F.explode(F.transform("items", lambda x: F.array_remove(F.col("items"), x))).alias("items")).distinct()
    return sets.join(sub, "items", "left_anti").select("tile_id", "items", "support")


def add_singletons(pool: Pool, matrix: Matrix) -> Pool:
    """The pool with one pattern for each column (ids -1, -2, ... by column), so that a full cover exists."""
    rows = matrix.ones.select((-F.col("col_id") - 1).alias("tile_id"), "row_id")
    cols = matrix.ones.select((-F.col("col_id") - 1).alias("tile_id"), "col_id").distinct()
    return Pool(pool.tile_rows.unionByName(rows), pool.tile_cols.unionByName(cols), dominated=pool.dominated)


def _few_pairs(sets: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """The distinct pairs by set and element on the driver; None where they are many or some are null."""
    if sets.count() > FEW_PAIRS:
        return None
    got = sets.select(F.col("set_id").cast("long"), F.col("element").cast("long")).toArrow()
    if not got.num_rows or got.column(0).null_count or got.column(1).null_count:
        return None
    tile, row = (got.column(i).to_numpy() for i in range(2))
    order = np.lexsort((row, tile))
    tile, row = tile[order], row[order]
    first = np.ones(len(row), bool)
    first[1:] = (tile[1:] != tile[:-1]) | (row[1:] != row[:-1])
    return tile[first], row[first]


def from_sets(sets: DataFrame, elements: DataFrame | None = None) -> tuple[Matrix, Pool]:
    """Set cover as one column: ``sets(set_id, element)`` become column vectors.  With ``elements(element, positive)``, the
    positive ones are the matrix and the others are zeros.  Few pairs come to the driver once, and repeats go there."""
    one = F.lit(0).cast("long").alias("col_id")
    few = _few_pairs(sets) if elements is None else None
    if few is not None:
        held = sets.select(F.col("set_id").alias("tile_id"), F.col("element").alias("row_id"))  # for those who ask for tables
        pool = Pool(held.distinct(), held.select("tile_id", one).distinct(), dominated=True, cache={"pairs": few})
        return Matrix(held.select("row_id", one).distinct(), len(np.unique(few[1])), 1, {"sets": pool}), pool
    held = cut(sets.select(F.col("set_id").alias("tile_id"), F.col("element").alias("row_id")).distinct())  # the source is read once
    names, inside = cut(held.select("tile_id").distinct()), held.select("row_id").distinct()
    if elements is None:
        every = cut(inside)
        size = every.count()
    else:
        every = elements.where("positive").select(F.col("element").alias("row_id"))
        size = elements.select(F.col("element").alias("row_id")).union(inside).distinct().count()
    pool = Pool(held, names.select("tile_id", one), dominated=elements is None)
    known = elements is None and held.where("tile_id is null or row_id is null").isEmpty()
    return Matrix(every.select("row_id", one), size, 1, {"sets": pool} if known else {}), pool
