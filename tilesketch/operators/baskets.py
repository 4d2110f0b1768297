"""Rows by the items they hold: baskets, classes of equal baskets, and what follows from them for itemset patterns.

A row belongs to an itemset when it holds all of its items, so rows with the same items lie in the same patterns.  Exact counts
look at one row of each class, weighted; the rows of a pattern are never listed.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.functions import hashing
from tilesketch.functions.hashing import Family
from tilesketch.model import Matrix, Pool
from tilesketch.session import cut

FEW_COLUMNS = 10_000  # column ids that one expression names
TABLE = 4_000_000  # entries of a table that a task makes at once
SMALL = 40_000_000  # entries of the table of classes by columns, or by patterns, up to which the driver counts by itself
PART = 3_000_000  # items of low cells that are looked at in one group, by estimate


def baskets(matrix: Matrix) -> DataFrame:
    """``row_id, items`` (ascending), made once for a matrix."""
    if "baskets" not in matrix.cache:
        matrix.cache["baskets"] = cut(matrix.ones.groupBy("row_id").agg(F.array_sort(F.collect_list("col_id")).alias("items")))
    return matrix.cache["baskets"]


def classes(matrix: Matrix) -> DataFrame:
    """``items, n``: the distinct baskets and their numbers of rows."""
    if "classes" not in matrix.cache:
        n = F.count(F.lit(1)).alias("n")
        if "marks" in matrix.cache:  # one number stands for the items of a row
            rows, items = matrix.cache["marks"]
            matrix.cache["classes"] = cut(rows.groupBy("mark").agg(n).select(items, "n"))
        else:
            matrix.cache["classes"] = cut(baskets(matrix).groupBy("items").agg(n))
    return matrix.cache["classes"]


def few_classes(matrix: Matrix) -> tuple[np.ndarray, pa.Array] | None:
    """``n`` and ``items`` of the classes on the driver, where the table of classes by columns is small."""
    if "few classes" not in matrix.cache:
        few = classes(matrix).count() * max(1, matrix.n_cols) <= SMALL
        matrix.cache["few classes"] = _weighted(classes(matrix)) if few else None
    return matrix.cache["few classes"]


def _weighted(held: DataFrame) -> tuple[np.ndarray, pa.Array]:
    got = held.select("n", "items").toArrow()
    return got.column(0).to_numpy().astype(np.int64), got.column(1).combine_chunks()


def n_ones(matrix: Matrix) -> int:
    if "n_ones" not in matrix.cache:
        few = few_classes(matrix) if {"classes", "few classes"} & matrix.cache.keys() else None
        if few is not None:
            matrix.cache["n_ones"] = int(few[0] @ np.asarray(few[1].value_lengths()).astype(np.int64))
        else:
            matrix.cache["n_ones"] = int(baskets(matrix).agg(F.sum(F.size("items"))).first()[0] or 0)
    return matrix.cache["n_ones"]


class ItemsetPool(Pool):
    """Itemsets as patterns.  ``tile_rows`` is made when something asks for it; the selectors work on classes of rows."""

    def __init__(self, matrix: Matrix, tile_cols: DataFrame, whole: Pool | None = None):
        self.matrix, self.whole, self._rows = matrix, whole, None
        super().__init__(None, tile_cols, dominated=True)

    @property
    def tile_rows(self) -> DataFrame:
        if self._rows is None:
            made = self.whole.tile_rows.join(self.tile_cols.select("tile_id").distinct(), "tile_id", "left_semi") if self.whole is not None and self.whole._rows is not None else self._listed()
            self._rows = made if self.whole is not None else cut(made)
        return self._rows

    @tile_rows.setter
    def tile_rows(self, value) -> None:
        """Set by the base class; the rows follow from the matrix."""

    def _listed(self) -> DataFrame:
        """Relational division over the distinct baskets, then their rows."""
        held = cut(classes(self.matrix).select(F.monotonically_increasing_id().alias("class_id"), "items"))
        size = self.tile_cols.groupBy("tile_id").agg(F.count(F.lit(1)).alias("size"))
        met = held.select("class_id", F.explode("items").alias("col_id")).join(self.tile_cols, "col_id").groupBy("tile_id", "class_id").agg(F.count(F.lit(1)).alias("c"))
        inside = met.join(F.broadcast(size), "tile_id").where("c = size").groupBy("class_id").agg(F.collect_list("tile_id").alias("tiles"))
        tiles = held.join(inside, "class_id").select("items", "tiles")
        return baskets(self.matrix).join(tiles, "items").select(F.explode("tiles").alias("tile_id"), "row_id")

    def only(self, tile_ids: DataFrame) -> ItemsetPool:
        return ItemsetPool(self.matrix, self.tile_cols.join(tile_ids, "tile_id", "left_semi"), self)

    def largest_id(self) -> int:
        if "largest" not in self.matrix.cache:
            self.matrix.cache["largest"] = baskets(self.matrix).agg(F.max("row_id")).first()[0] or 0
        return max(self.matrix.cache["largest"], int(self.sides()[1].max(initial=0)))

    def sides(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``tile_id`` ascending, the columns used ascending, and which tile has which column [column, tile]."""
        if "sides" not in self.cache:
            got = self.tile_cols.select(F.col("tile_id").cast("long"), F.col("col_id").cast("long")).toArrow()
            tile, col = (got.column(i).to_numpy() for i in range(2))
            ids, cols = np.unique(tile), np.unique(col)
            has = np.zeros((len(cols), len(ids)), bool)
            has[np.searchsorted(cols, col), np.searchsorted(ids, tile)] = True
            self.cache["sides"] = ids, cols, has
        return self.cache["sides"]

    def _whole(self) -> bool:
        """Whether the classes are those of the matrix."""
        _, cols, _ = self.sides()
        return not (0 < len(cols) < self.matrix.n_cols and len(cols) <= FEW_COLUMNS)

    def used(self) -> DataFrame:
        """``items, n``: the classes by the columns that the patterns use."""
        if "used" not in self.cache:
            _, cols, _ = self.sides()
            if not self._whole():
                held = classes(self.matrix) if "classes" in self.matrix.cache else baskets(self.matrix).withColumn("n", F.lit(1).cast("long"))
                self.cache["used"] = cut(limited(held, cols, "n").groupBy("items").agg(F.sum("n").alias("n")))
            else:
                self.cache["used"] = classes(self.matrix)
        return self.cache["used"]

    def n_used(self) -> int:
        if "n_used" not in self.cache:
            few = few_classes(self.matrix) if self._whole() else None
            self.cache["n_used"] = len(few[0]) if few is not None else self.used().count()
        return self.cache["n_used"]

    def _few(self) -> bool:
        """Whether the driver counts by itself."""
        ids, cols, _ = self.sides()
        return self.n_used() * max(1, len(ids), len(cols)) <= SMALL

    def class_tables(self, cut) -> tuple[DataFrame, DataFrame]:
        """``row_id, col_id, n`` and ``tile_id, row_id`` with a number of each class in place of its rows."""
        held = cut(self.used().select(F.monotonically_increasing_id().alias("row_id"), "n", "items"))
        ones = cut(held.select("row_id", F.explode("items").alias("col_id"), "n"))
        size = self.tile_cols.groupBy("tile_id").agg(F.count(F.lit(1)).alias("size"))
        met = ones.join(self.tile_cols, "col_id").groupBy("tile_id", "row_id").agg(F.count(F.lit(1)).alias("c"))
        return ones, cut(met.join(F.broadcast(size), "tile_id").where("c = size").select("tile_id", "row_id"))

    def collected(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of the classes: weights, and for each entry its class and the place of its column among those used."""
        if "collected" in self.cache:
            return self.cache["collected"]
        _, cols, _ = self.sides()
        few = few_classes(self.matrix) if self._whole() else None
        weight, lists = few if few is not None else _weighted(self.used())
        got = weight, *_entries(lists, cols)
        if self._few():
            self.cache["collected"] = got
        return got

    def tiles(self) -> DataFrame:
        """Sizes by classes; tables of rows are not made for them."""
        ids, cols, has = self.sides()
        n_c = has.sum(0)
        n_r = self.supports()
        spark = self.matrix.ones.sparkSession
        table = pa.table({"tile_id": ids, "n_r": n_r, "n_c": n_c.astype(np.int64), "size": n_r * n_c})
        out = spark.createDataFrame(table) if len(ids) else spark.createDataFrame([], "tile_id long, n_r long, n_c long, size long")
        return out.where("n_r > 0")

    def column_counts(self) -> np.ndarray:
        """Ones of each column used."""
        if "column_counts" not in self.cache:
            _, cols, _ = self.sides()
            if self._few():
                weight, row, at = self.collected()
                self.cache["column_counts"] = np.rint(np.bincount(at, weight[row], len(cols))).astype(np.int64)
                return self.cache["column_counts"]
            got = self.used().select("n", F.explode("items").alias("col_id")).groupBy("col_id").agg(F.sum("n").alias("n")).toArrow()
            col, n = (got.column(i).to_numpy() for i in range(2))
            out, at = np.zeros(len(cols), np.int64), np.searchsorted(cols, col)
            good = cols[np.minimum(at, len(cols) - 1)] == col if len(cols) else np.zeros(len(col), bool)
            out[at[good]] = n[good]
            self.cache["column_counts"] = out
        return self.cache["column_counts"]

    def supports(self) -> np.ndarray:
        """Rows of each pattern."""
        if "supports" not in self.cache:
            ids, cols, has = self.sides()
            need = has.sum(0).astype(np.float32)

            def count(batches):
                for b in batches:
                    row, at = _entries(b.column(0), cols)
                    n, out = b.column(1).to_numpy(zero_copy_only=False), np.zeros(len(ids), np.int64)
                    for a, held in _blocks(row, at, len(n), len(cols), max(1, TABLE // max(1, len(ids)))):
                        out += (n[a : a + len(held)] @ ((held @ has) == need)).astype(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(ids))), pa.array(out)], ["place", "n"])

            out = np.zeros(len(ids), np.int64)
            if len(ids) and self._few():
                weight, row, at = self.collected()
                for a, held in _blocks(row, at, len(weight), len(cols), max(1, TABLE // len(ids))):
                    out += weight[a : a + len(held)] @ ((held @ has.astype(np.float32)) == need)
            elif len(ids):
                for r in self.used().mapInArrow(count, "place long, n long").groupBy("place").agg(F.sum("n").alias("n")).collect():
                    out[r.place] = r.n
            self.cache["supports"] = out
        return self.cache["supports"]


def limited(held: DataFrame, cols: np.ndarray, *more: str) -> DataFrame:
    """``items`` of some columns only, and other columns of the table; rows without any of them go."""
    return held.select(F.array_intersect("items", _ids(cols)).alias("items"), *more).where(F.size("items") > 0)


def _ids(cols: np.ndarray):
    return F.array(*(F.lit(int(c)).cast("long") for c in cols))


def _entries(lists, cols: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of a list array: the list and the place among ``cols`` of each value that is one of them."""
    row = np.repeat(np.arange(len(lists)), np.asarray(lists.value_lengths()).astype(np.int64))
    value = np.asarray(lists.flatten()).astype(np.int64)
    at = np.searchsorted(cols, value)
    good = cols[np.minimum(at, len(cols) - 1)] == value if len(cols) else np.zeros(len(value), bool)
    return row[good], at[good]


def _blocks(row: np.ndarray, at: np.ndarray, n: int, n_cols: int, step: int):
    """0/1 tables of ``step`` lists at a time, with the first list of each; ``row`` ascends."""
    for a in range(0, n, step):
        lo, hi = np.searchsorted(row, [a, a + step])
        held = np.zeros((min(step, n - a), n_cols), np.float32)
        held[row[lo:hi] - a, at[lo:hi]] = 1
        yield a, held


def lists(pool: ItemsetPool, fam: Family, k: int, cutoff: int | None = None, slack: float = 2.0) -> DataFrame:
    """The bottom-k lists of itemset patterns.  A list of a pattern of size s needs the hashes under about ``slack * k / s``
    of the range only, so tasks hash the ones of their rows once, whatever the number of patterns, and pass on the few low
    ones with their baskets.  Those of a repetition, or of a part of its range, are then met with the patterns in ascending
    order, and a pattern leaves when its list is full.  Patterns that come out short are searched again under four times the
    bound."""
    ids, cols, has = pool.sides()
    p, size = fam.prime, pool.supports() * has.sum(0)
    top = p if cutoff is None else min(cutoff, p)
    need = has.sum(0).astype(np.float32)
    col_hash = [hashing.np_affine(cols, ac, bc, p) for _, _, ac, bc in fam.maps]
    maps = fam.maps
    source = baskets(pool.matrix)
    spark, ones = source.sparkSession, pool.column_counts()
    out = None
    bound = np.where(size > 0, np.minimum(np.ceil(slack * k * float(p) / np.maximum(size, 1)), float(top)).astype(np.int64), 0)
    bound = np.minimum(bound, top)
    live = np.flatnonzero(size > 0)
    while len(live):
        mine, at_most = has[:, live], bound[live]
        reach = np.where(mine, at_most[None, :], 0).max(1)  # of each column: the widest bound of its patterns
        wanted, names = need[live], ids[live]
        entries = (ones * (reach / p)).sum() * ones.sum() / max(1, ones.max(initial=0))  # no row has fewer ones on average
        width = -(-top // max(1, int(np.ceil(entries / PART))))  # of the parts of the range

        def low(batches, reach=reach, width=width):
            for b in batches:
                row, at = _entries(b.column(1), cols)
                row_id = b.column(0).to_numpy(zero_copy_only=False)
                first = np.searchsorted(row, np.arange(len(row_id) + 1))
                for r, (ar, br, _, _) in enumerate(maps):
                    h = (hashing.np_affine(row_id, ar, br, p)[row] - col_hash[r][at]) % p
                    use = np.flatnonzero(h < reach[at])
                    for x in range(0, len(use), 10_000):
                        u = use[x : x + 10_000]
                        n = first[row[u] + 1] - first[row[u]]
                        ends = np.concatenate([[0], np.cumsum(n)])
                        items = at[np.repeat(first[row[u]] - ends[:-1], n) + np.arange(ends[-1])]
                        held = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(items.astype(np.int32)))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(u), r, np.int32)), pa.array(h[u] // width), pa.array(h[u]), pa.array(at[u].astype(np.int32)), held], ["rep", "part", "h", "at", "items"])

        parts = min(fam.reps * -(-top // width), 4 * spark.sparkContext.defaultParallelism)  # the few rows of a group are long work
        found = source.mapInArrow(low, "rep int, part long, h long, at int, items array<int>").repartition(int(parts), "rep", "part").groupBy("rep", "part").applyInArrow(_fullest(mine, at_most, wanted, names, k), "tile_id long, rep int, hashes array<long>")
        each = found.groupBy("tile_id", "rep").agg(F.slice(F.array_sort(F.flatten(F.collect_list("hashes"))), 1, k).alias("hashes"))
        held = each.groupBy("tile_id").agg(F.map_from_entries(F.collect_list(F.struct("rep", "hashes"))).alias("m"))
        done = cut(held.select("tile_id", F.array(*(F.coalesce(F.try_element_at("m", F.lit(r)), F.array().cast("array<bigint>")) for r in range(fam.reps))).alias("hashes")))
        got = done.select("tile_id", F.array_min(F.transform("hashes", F.size)).alias("n")).toArrow()
        have = np.zeros(len(live), np.int64)
        have[np.searchsorted(names, got.column(0).to_numpy())] = got.column(1).to_numpy()
        short = (have < np.minimum(k, size[live])) & (at_most < top)
        again = live[short]
        if len(again):
            gone = spark.createDataFrame(pa.table({"tile_id": ids[again]}))
            done = done.join(F.broadcast(gone), "tile_id", "left_anti")
        out = done if out is None else out.unionByName(done)
        bound[again] = np.where(bound[again] > top // 4, top, bound[again] * 4)
        live = again
    return out if out is not None else spark.createDataFrame([], "tile_id long, hashes array<array<bigint>>")


def _from(row: np.ndarray, at: np.ndarray, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
    """The entries of the lists a to b, numbered from 0."""
    lo, hi = np.searchsorted(row, [a, b])
    return row[lo:hi] - a, at[lo:hi]


def _fullest(mine: np.ndarray, at_most: np.ndarray, wanted: np.ndarray, names: np.ndarray, k: int):
    """Of the low cells of one repetition, or of a part of its range, the ``k`` lowest hashes in each pattern."""

    def smallest(cells: pa.Table) -> pa.Table:
        rep = cells.column("rep")[0].as_py()
        cells = cells.sort_by("h")
        h, at = (cells.column(c).to_numpy() for c in ("h", "at"))
        items = cells.column("items").combine_chunks()
        row, place = np.repeat(np.arange(len(h)), np.asarray(items.value_lengths())), np.asarray(items.flatten())
        left, found = np.flatnonzero(at_most > h[0]), []
        n, last = np.zeros(len(names), np.int64), np.full(len(names), -1, np.int64)
        a, step = 0, max(1, TABLE // max(1, len(left)))
        while a < len(h) and len(left):
            _, held = next(_blocks(*_from(row, place, a, a + step), min(step, len(h) - a), len(mine), step))
            b, some = a + len(held), mine[:, left]
            inside = (held @ some.astype(np.float32)) == wanted[left]
            inside &= some[at[a:b]]
            t, i = np.nonzero(inside.T)
            value, t = h[a + i], left[t]
            good = value < at_most[t]
            t, value = t[good], value[good]
            new = np.ones(len(t), bool)
            new[1:] = (t[1:] != t[:-1]) | (value[1:] != value[:-1])
            new &= value != last[t]
            t, value = t[new], value[new]
            count = np.bincount(t, minlength=len(names))
            place_in = np.arange(len(t)) - (np.cumsum(count) - count)[t] + n[t]
            first = place_in < k
            found.append((t[first], value[first]))
            last[t] = value  # ascending, so the largest stays
            n += count
            a = b
            left = left[(n[left] < k) & (at_most[left] > h[min(a, len(h) - 1)])]
            step = max(1, TABLE // max(1, len(left)))
        t, value = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 2
        order = np.argsort(t, kind="stable")
        some, start = np.unique(t[order], return_index=True)
        kept = pa.ListArray.from_arrays(pa.array(np.concatenate([start, [len(t)]]).astype(np.int32)), pa.array(value[order].astype(np.int64)))
        return pa.table({"tile_id": pa.array(names[some]), "rep": pa.array(np.full(len(some), rep, np.int32)), "hashes": kept})

    return smallest
