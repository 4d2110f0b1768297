"""Selectors: hashed, exact-gain greedy, static rank, brute force, random order.

Every selector returns a trace: one row a pick with estimate, gain, error after it, candidates verified and time.  Choosing
is sequential, so a driver loop runs; what a step touches is distributed.  A problem whose matrix, patterns and lists are
counted first and fit ``local_cells`` is worked on in NumPy on the driver instead; beyond that, tables stay distributed and
the driver sees only the few verified candidates of a step.  Both ways give the same picks.
"""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tilesketch.functions import estimate, hashing
from tilesketch.model import SCHEMAS, Matrix, Pool
from tilesketch.operators import cover, packed, sketch
from tilesketch.operators.baskets import ItemsetPool, baskets, n_ones
from tilesketch.operators.packed import PackedPool
from tilesketch.session import cut, tables

LOCAL_CELLS = 60_000_000
BLOCK = 8_000_000  # entries of a table that a step makes at once
BITS = 1 << 17  # words of 64 bits that are counted at once


# --- state of the exact counts ------------------------------------------------------------------------------------------


class LocalState:
    """Weights of the cells (+1 uncovered one, -1 uncovered zero, 0 covered) as one matrix, and of each tile its rows and
    columns, or its cells where it is no outer product.  Cells of outer products are never listed."""

    def __init__(self, matrix: Matrix, pool: Pool):
        def flat(df: DataFrame, *c: str) -> list[np.ndarray]:
            got = df.select(*(F.col(x).cast("long") for x in c)).toArrow()
            return [got.column(i).to_numpy() for i in range(len(c))]

        self.loose, pairs = pool.tile_cells is not None, _pairs(matrix, pool)
        if pairs is not None:  # every element of a set is a one
            ones, names = np.unique(pairs[1]), np.unique(pairs[0])
            ones, sides = [ones, np.zeros_like(ones)], (pairs, (names, np.zeros_like(names)))
        else:
            ones = flat(matrix.ones, "row_id", "col_id")
            cells = flat(pool.tile_cells, "tile_id", "row_id", "col_id") if self.loose else []
            sides = (cells[:2], cells[::2]) if self.loose else (flat(pool.tile_rows, "tile_id", "row_id"), flat(pool.tile_cols, "tile_id", "col_id"))
        self.ids = np.unique(sides[0][0])
        self.row_ids, self.col_ids = (np.union1d(ones[i], s[1]) for i, s in enumerate(sides))
        self.w = np.full((len(self.row_ids), len(self.col_ids)), -1, np.int8)
        self.w[np.searchsorted(self.row_ids, ones[0]), np.searchsorted(self.col_ids, ones[1])] = 1
        self.error = len(ones[0])
        del ones

        def split(side, values):
            tile = np.searchsorted(self.ids, side[0]).astype(np.int32)
            place = np.searchsorted(values, side[1]).astype(np.int32)
            order = np.argsort(tile, kind="stable")
            return np.split(place[order], np.cumsum(np.bincount(tile, minlength=len(self.ids)))[:-1])

        self.rows, self.cols = split(sides[0], self.row_ids), split(sides[1], self.col_ids)
        self.size = np.array([len(r) * (1 if self.loose else len(c)) for r, c in zip(self.rows, self.cols, strict=True)], np.int64)
        self.begin()

    def begin(self) -> None:
        self.read = 0  # cells that exact gains have looked at
        self.members: tuple | None = None
        self.alone = self.all_gains()
        self.zeros = (self.size - self.alone) // 2

    def start(self):
        """The weights before any pick, for ``restart``."""
        return self.w.copy()

    def restart(self, start) -> None:
        self.w[:] = start

    def lists(self, fam: hashing.Family, k: int, cutoff: int | None) -> np.ndarray:
        return sketch.local_lists(self.rows, self.cols, self.row_ids, self.col_ids, fam, k, cutoff, self.loose)

    def at(self, i: int):
        return (self.rows[i], self.cols[i]) if self.loose else np.ix_(self.rows[i], self.cols[i])

    def all_gains(self) -> np.ndarray:
        """The gain of every tile: cell by cell, or, where patterns are large, by products of blocks of the weights."""
        if self.loose or self.w.size * len(self.ids) > 2000 * self.size.sum():
            return np.array([self.gain(i) for i in range(len(self.ids))], np.int64)
        self.read += int(self.size.sum())
        self.prepare()
        out, every = np.zeros(len(self.ids)), np.arange(self.w.shape[1])
        for a in range(0, len(self.w), 4096):
            part = self.weights(a, a + 4096)
            out += self.lost(np.arange(a, a + len(part)), every, part)
        return np.rint(out).astype(np.int64)

    def weights(self, a: int, b: int) -> np.ndarray:
        """What the cells of the rows a to b count."""
        return self.w[a:b].astype(np.float32)

    def gain(self, i: int) -> int:
        self.read += int(self.size[i])
        return int(self.w[self.at(i)].sum(dtype=np.int64))

    def pick(self, i: int) -> np.ndarray:
        """Take a tile; the weights that its cells had."""
        before = self.w[self.at(i)]
        self.error -= int(before.sum(dtype=np.int64))
        self.w[self.at(i)] = 0
        return before

    def prepare(self) -> None:
        """What ``losses`` looks tiles up in: those of each row as lists, and which tile has which column as a table."""
        if self.members is None and not self.loose:
            n = np.array([len(r) for r in self.rows], np.int64)
            row = np.concatenate(self.rows) if len(n) else np.zeros(0, np.int32)
            order = np.argsort(row, kind="stable")
            self.members = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=self.w.shape[0]))]), np.repeat(np.arange(len(n), dtype=np.int32), n)[order], self.column_table()

    def column_table(self) -> np.ndarray:
        has = np.zeros((self.w.shape[1], len(self.ids)), np.float32)
        for j, c in enumerate(self.cols):
            has[c, j] = 1
        return has

    def lost(self, r: np.ndarray, c: np.ndarray, before: np.ndarray) -> np.ndarray:
        """For each tile the sum of ``before`` over its cells among rows r and columns c."""
        start, tiles, has = self.members
        n = start[r + 1] - start[r]
        has, out = has[c].astype(before.dtype, copy=False), np.zeros(len(self.ids))
        if n.sum() * len(c) <= len(r) * len(self.ids):  # few tiles a row: one by one
            ends = np.cumsum(n)
            for a, b in _parts(n, BLOCK // max(1, len(c))):
                at = np.repeat(start[r[a:b]] - (ends[a:b] - n[a:b]), n[a:b]) + np.arange(ends[a] - n[a], ends[b - 1])
                t = tiles[at]
                out += np.bincount(t, (before[np.repeat(np.arange(a, b), n[a:b])] * has[:, t].T).sum(1, dtype=np.float64), len(out))
            return out
        step = max(1, BLOCK // max(1, len(self.ids)))
        for a in range(0, len(r), step):
            b = min(len(r), a + step)
            inside = np.zeros((b - a, len(self.ids)), before.dtype)
            for j, row in enumerate(r[a:b]):
                inside[j, tiles[start[row] : start[row + 1]]] = 1
            out += ((before[a:b].T @ inside) * has).sum(0, dtype=np.float64)
        return out

    def losses(self, i: int, before: np.ndarray) -> np.ndarray:
        """What each tile's gain loses by the cells that tile i has newly covered: only those rows and columns are looked
        at, as sums of the changed weights over the tiles that hold them."""
        if self.loose:
            changed = np.zeros_like(self.w)
            changed[self.at(i)] = before
            return np.array([changed[self.at(j)].sum(dtype=np.int64) for j in range(len(self.ids))], np.int64)
        self.prepare()
        live_rows, live_cols = (before != 0).any(1), (before != 0).any(0)
        before = before[np.ix_(live_rows, live_cols)]
        before = before.astype(np.float32 if np.abs(before).sum(dtype=np.int64) < 1 << 24 else np.float64)
        self.read += before.size
        return np.rint(self.lost(self.rows[i][live_rows], self.cols[i][live_cols], before)).astype(np.int64)


def _parts(n: np.ndarray, most: int):
    """Ranges of places whose ``n`` add up to about ``most``."""
    group = (np.cumsum(n) - 1) // max(1, most) if len(n) else n
    edges = np.concatenate([[0], np.flatnonzero(np.diff(group)) + 1, [len(n)]]) if len(n) else [0]
    return [(int(a), int(b)) for a, b in zip(edges, edges[1:], strict=False)]


class _Holding:
    """Rows of each itemset: the classes that hold all of its columns, found when asked for."""

    def __init__(self, held: np.ndarray, cols: list[np.ndarray]):
        self.held, self.cols = held, cols

    def __len__(self) -> int:
        return len(self.cols)

    def __getitem__(self, i: int) -> np.ndarray:
        return np.flatnonzero(np.logical_and.reduce(self.held[self.cols[i]], axis=0))


class ItemsetState(LocalState):
    """The counts of itemset patterns over classes of rows with the same items, each weighted by its number of rows."""

    def __init__(self, matrix: Matrix, pool: ItemsetPool):
        self.loose = False
        ids, self.col_ids, has = pool.sides()
        some = pool.supports() > 0
        self.ids, self.has = ids[some], has[:, some]
        self.weight, row, at = pool.collected()
        self.row_ids = np.arange(len(self.weight))
        self.held = np.zeros((len(self.col_ids), len(self.weight)), bool)
        self.held[at, row] = True
        self.w = np.where(self.held.T, np.int8(1), np.int8(-1))
        self.error = n_ones(matrix)
        self.cols = [np.flatnonzero(self.has[:, i]) for i in range(len(self.ids))]
        self.rows = _Holding(self.held, self.cols)
        self.size = pool.supports()[some] * self.has.sum(0)
        self.begin()

    def begin(self) -> None:
        self.read, self.members = int(self.size.sum()), None
        self.alone, self.zeros = self.size.copy(), np.zeros(len(self.ids), np.int64)  # no zero lies in an itemset's cells

    def weights(self, a: int, b: int) -> np.ndarray:
        return self.w[a:b] * self.weight[a:b, None].astype(np.float64)

    def gain(self, i: int) -> int:
        r, c = self.rows[i], self.cols[i]
        self.read += int(self.size[i])
        return int(self.weight[r] @ self.w[np.ix_(r, c)].sum(1, dtype=np.int64))

    def pick(self, i: int) -> np.ndarray:
        r, c = self.rows[i], self.cols[i]
        before = self.w[np.ix_(r, c)] * self.weight[r, None]
        self.error -= int(before.sum())
        self.w[np.ix_(r, c)] = 0
        return before

    def prepare(self) -> None:
        if self.members is None:
            self.members = self.held.T.astype(np.float32), self.has.astype(np.float32), self.has.sum(0).astype(np.float32)

    def lost(self, r: np.ndarray, c: np.ndarray, before: np.ndarray) -> np.ndarray:
        held, has, need = self.members
        out, step = np.zeros(len(self.ids)), max(1, BLOCK // max(1, len(self.ids)))
        for a in range(0, len(r), step):
            inside = ((held[r[a : a + step]] @ has) == need).astype(before.dtype)
            out += ((before[a : a + step].T @ inside) * has[c]).sum(0, dtype=np.float64)
        return out


class PackedState(LocalState):
    """The counts of patterns whose rows are bits, over the matrix that they make together: what is open is a bitmap of each
    column, and gains are numbers of common bits."""

    def __init__(self, matrix: Matrix, pool: PackedPool):
        self.loose = False
        self.row_ids, self.ids, self.col_ids, self.cols, self.bits = pool.collected()
        self.open = np.zeros((len(self.col_ids), self.bits.shape[1]), np.uint8)
        for i, c in enumerate(self.cols):
            self.open[c] |= self.bits[i]
        self.error = packed.count(self.open)
        self.size = np.array([packed.count(b) * len(c) for b, c in zip(self.bits, self.cols, strict=True)], np.int64)
        self.begin()

    def begin(self) -> None:
        self.read, self.alone, self.zeros = int(self.size.sum()), self.size.copy(), np.zeros(len(self.ids), np.int64)

    def all_gains(self) -> np.ndarray:
        return np.array([self.gain(i) for i in range(len(self.ids))], np.int64)

    def gain(self, i: int) -> int:
        self.read += int(self.size[i])
        return packed.count(self.open[self.cols[i]] & self.bits[i])

    def pick(self, i: int) -> np.ndarray:
        """Take a tile; the bits of its columns that it newly covers."""
        before = self.open[self.cols[i]] & self.bits[i]
        self.error -= packed.count(before)
        self.open[self.cols[i]] &= ~self.bits[i]
        return before

    def losses(self, i: int, before: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.ids), np.int64)
        for j, c in enumerate(self.cols):
            out[j] = packed.count(before[np.isin(self.cols[i], c)] & self.bits[j])
        self.read += int(self.size[i])
        return out

    def lists(self, fam: hashing.Family, k: int, cutoff: int | None) -> np.ndarray:
        return packed.lists(self.row_ids, self.col_ids, self.cols, self.bits, self.size, fam, k, cutoff)


class BitState(LocalState):
    """The counts of patterns whose rows are bits, over any matrix: of each column the open ones and the open zeros are bits of
    the rows that lie in a pattern.  Other rows only count in the error."""

    def __init__(self, matrix: Matrix, pool: PackedPool):
        self.loose = False
        self.row_ids, self.ids, self.col_ids, self.cols, bits = pool.collected()
        self.bits = bits.view(np.uint64)
        self.error = n_ones(matrix)
        self.open = packed.of_columns(baskets(matrix), self.row_ids, self.col_ids).view(np.uint64)
        every = np.zeros(bits.shape[1], np.uint8)
        whole = np.packbits(np.ones(len(self.row_ids), bool))
        every[: len(whole)] = whole
        self.every = every.view(np.uint64)
        self.shut = self.every & ~self.open
        self.size = np.array([packed.count(b) * len(c) for b, c in zip(self.bits, self.cols, strict=True)], np.int64)
        self.begin()

    def begin(self) -> None:
        self.read, self.members = int(self.size.sum()), None
        ones = np.array([self.common(self.open, i) for i in range(len(self.ids))], np.int64)
        self.zeros = self.size - ones
        self.alone = ones - self.zeros

    def start(self):
        return self.open.copy()

    def restart(self, start) -> None:
        self.open[:] = start
        self.shut = self.every & ~start

    def common(self, table: np.ndarray, i: int) -> int:
        """Bits of the tile's columns in its rows, some columns at once."""
        c, b = self.cols[i], self.bits[i]
        step = max(1, BITS // max(1, len(b)))
        return sum(packed.count(table[c[a : a + step]] & b) for a in range(0, len(c), step))

    def all_gains(self) -> np.ndarray:
        return np.array([self.gain(i) for i in range(len(self.ids))], np.int64)

    def gain(self, i: int) -> int:
        self.read += int(self.size[i])
        return self.common(self.open, i) - self.common(self.shut, i)

    def pick(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Take a tile; the open ones and zeros of its columns that it newly covers."""
        c, b = self.cols[i], self.bits[i]
        before = self.open[c] & b, self.shut[c] & b
        self.error -= packed.count(before[0]) - packed.count(before[1])
        self.open[c] &= ~b
        self.shut[c] &= ~b
        return before

    def prepare(self) -> None:
        """Tiles and columns as pairs, in which ``losses`` looks up who has a column."""
        if self.members is None:
            n = np.array([len(c) for c in self.cols], np.int64)
            self.members = np.repeat(np.arange(len(n)), n), np.concatenate([*self.cols, np.zeros(0, np.int64)]).astype(np.int64)

    def losses(self, i: int, before: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        """What each tile's gain loses: products of bits of rows and changed weights, some rows at once."""
        self.prepare()
        tile, col = self.members
        either = before[0] | before[1]
        live = either.any(1)
        ones, zeros = (x[live].view(np.uint8) for x in before)
        rows = np.bitwise_or.reduce(either[live], axis=0) if live.any() else np.zeros(0, np.uint64)
        self.read += packed.count(rows) * int(live.sum())
        some = np.flatnonzero(rows.view(np.uint8))  # bytes with a row that changed
        place = np.full(len(self.col_ids), -1)
        place[self.cols[i][live]] = np.arange(live.sum())
        known = place[col] >= 0
        has = np.zeros((len(self.ids), int(live.sum())), np.float32)
        has[tile[known], place[col[known]]] = 1
        out, bits = np.zeros(len(self.ids)), self.bits.view(np.uint8)
        step = max(1, BLOCK // max(1, 8 * len(self.ids)))
        for a in range(0, len(some), step):
            b = some[a : a + step]
            changed = np.unpackbits(ones[:, b], axis=1).astype(np.float32) - np.unpackbits(zeros[:, b], axis=1)
            inside = np.unpackbits(bits[:, b], axis=1).astype(np.float32)
            out += ((inside @ changed.T) * has).sum(1, dtype=np.float64)
        return np.rint(out).astype(np.int64)

    def lists(self, fam: hashing.Family, k: int, cutoff: int | None) -> np.ndarray:
        return packed.walked_lists(self.row_ids, self.col_ids, self.cols, self.bits.view(np.uint8), fam, k, cutoff)


class SetState(LocalState):
    """The counts of sets over one column of ones: the elements of each set, numbered, and which elements are open."""

    def __init__(self, matrix: Matrix, pool: Pool):
        self.loose = False
        self.row_ids = np.sort(matrix.ones.select(F.col("row_id").cast("long")).toArrow().column(0).to_numpy())
        sent = matrix.ones.sparkSession.sparkContext.broadcast(self.row_ids)

        def number(batches):
            for b in batches:
                ends = np.concatenate([[0], np.cumsum(np.asarray(b.column(1).value_lengths()))]).astype(np.int32)
                at = np.searchsorted(sent.value, np.asarray(b.column(1).flatten())).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(at))], ["tile_id", "places"])

        lists = pool.tile_rows.select(F.col("tile_id").cast("long"), F.col("row_id").cast("long")).groupBy("tile_id").agg(F.collect_list("row_id").alias("rows"))
        got = lists.mapInArrow(number, "tile_id long, places array<int>").toArrow()
        names, n = got.column(0).to_numpy(), np.concatenate([np.asarray(x.value_lengths()) for x in got.column(1).chunks] + [np.zeros(0, np.int32)]).astype(np.int64)
        order = np.argsort(names)
        self.ids, self.size = names[order], n[order]
        self.first = np.concatenate([[0], np.cumsum(self.size)])
        self.flat, to, i = np.empty(self.first[-1], np.int32), np.empty(len(n), np.int64), 0
        to[order] = self.first[:-1]
        for chunk in got.column(1).chunks:
            values, ends = np.asarray(chunk.flatten()), np.cumsum(np.asarray(chunk.value_lengths()))
            for a, b in zip(np.concatenate([[0], ends[:-1]]) if len(ends) else [], ends, strict=True):
                self.flat[to[i] : to[i] + b - a] = values[a:b]
                i += 1
        del got
        self.rows, self.cols = np.split(self.flat, self.first[1:-1]), [np.zeros(1, np.int64)] * len(self.ids)
        self.col_ids, self.open, self.error = np.zeros(1, np.int64), np.ones(len(self.row_ids), bool), len(self.row_ids)
        self.begin()

    def begin(self) -> None:
        self.read, self.members = int(self.size.sum()), None
        self.alone, self.zeros = self.size.copy(), np.zeros(len(self.ids), np.int64)

    def start(self):
        return self.open.copy()

    def restart(self, start) -> None:
        self.open[:] = start

    def all_gains(self) -> np.ndarray:
        return np.array([self.gain(i) for i in range(len(self.ids))], np.int64)

    def gain(self, i: int) -> int:
        self.read += int(self.size[i])
        return int(np.count_nonzero(self.open[self.rows[i]]))

    def pick(self, i: int) -> np.ndarray:
        """Take a set; the elements that it newly covers."""
        new = self.rows[i][self.open[self.rows[i]]]
        self.open[new] = False
        self.error -= len(new)
        return new

    def prepare(self) -> None:
        """The sets of each element, made for a range of elements at a time."""
        if self.members is not None:
            return
        n = np.zeros(len(self.row_ids), np.int64)
        for a in range(0, len(self.flat), BLOCK):
            n += np.bincount(self.flat[a : a + BLOCK], minlength=len(n))
        ends, sets = np.concatenate([[0], np.cumsum(n)]), np.empty(len(self.flat), np.int32)
        for a, b in _parts(n, BLOCK // 4):
            at = np.concatenate([x + np.flatnonzero((part >= a) & (part < b)) for x in range(0, len(self.flat), BLOCK) for part in [self.flat[x : x + BLOCK]]])
            order = np.argsort(self.flat[at], kind="stable")
            sets[ends[a] : ends[b]] = (np.searchsorted(self.first, at, "right") - 1)[order]
        self.members = ends, sets

    def losses(self, i: int, before: np.ndarray) -> np.ndarray:
        self.prepare()
        ends, sets = self.members
        self.read += len(before)
        n = ends[before + 1] - ends[before]
        at = np.repeat(ends[before] - np.cumsum(n) + n, n) + np.arange(n.sum())
        return np.bincount(sets[at], minlength=len(self.ids))


def _pairs(matrix: Matrix, pool: Pool) -> tuple[np.ndarray, np.ndarray] | None:
    """Sets and elements that the driver holds already, where the matrix is made of them."""
    return pool.cache.get("pairs") if matrix.cache.get("sets") is pool else None


def _is_packed(matrix: Matrix, pool: Pool) -> bool:
    return isinstance(pool, PackedPool) and matrix.cache.get("union of") is pool


def _state(matrix: Matrix, pool: Pool) -> LocalState:
    if _is_packed(matrix, pool):
        return PackedState(matrix, pool)
    if isinstance(pool, PackedPool):
        return BitState(matrix, pool)
    if matrix.cache.get("sets") is pool and "pairs" not in pool.cache:
        return SetState(matrix, pool)
    return (ItemsetState if isinstance(pool, ItemsetPool) else LocalState)(matrix, pool)


class SparkState:
    """The same counts on tables: uncovered ones, covered zeros, and the catalogue.  Each cell stands for ``n`` cells: for
    itemsets those of a class of rows, else one."""

    def __init__(self, matrix: Matrix, pool: Pool, cut: Callable[[DataFrame], DataFrame]):
        self.matrix, self.pool, self.picks, self.cut = matrix, pool, 0, cut
        if isinstance(pool, ItemsetPool):
            self.catalogue = cut(pool.tiles().select("*", F.col("size").alias("ones"), F.lit(0).cast("long").alias("zeros")))
            held, inside = pool.class_tables(cut)
            self.pool, self.open = Pool(inside, pool.tile_cols, dominated=True), held
            self.error = n_ones(matrix)
        else:
            self.catalogue = cut(cover.profile(matrix, pool))
            self.open = cut(matrix.ones.withColumn("n", F.lit(1).cast("long")))
            self.error = self.open.count()
        self.paid = self.open.limit(0)

    def gains(self, ids: list[int]) -> dict[int, int]:
        some = self.pool.only(self.open.sparkSession.createDataFrame([(i,) for i in ids], "tile_id long"))
        own = self.catalogue.where(F.col("tile_id").isin(ids)).select("tile_id", "zeros")
        n = lambda df, name: self.met(df, some).groupBy("tile_id").agg(F.sum("n").alias(name))
        got = own.join(n(self.open, "new"), "tile_id", "left").join(n(self.paid, "old"), "tile_id", "left")
        return {r.tile_id: (r.new or 0) - (r.zeros - (r.old or 0)) for r in got.collect()}

    def met(self, cells: DataFrame, pool: Pool) -> DataFrame:
        """``cells`` that the patterns hold, with ``tile_id``."""
        if pool.tile_cells is not None:
            return pool.tile_cells.join(cells, ["row_id", "col_id"])
        return pool.tile_cols.join(cells, "col_id").join(pool.tile_rows, ["tile_id", "row_id"])

    def pick(self, i: int, gain: int) -> DataFrame:
        """Take a tile; returns the cells that it newly covers, with their weights."""
        one = self.pool.only(self.open.sparkSession.createDataFrame([(i,)], "tile_id long"))
        cells = one.cells().select("row_id", "col_id").distinct()
        changed = self.open.join(cells, ["row_id", "col_id"], "left_semi").withColumn("weight", F.col("n"))
        if not self.pool.dominated:
            zero = cells.join(self.matrix.ones, ["row_id", "col_id"], "left_anti").join(self.paid, ["row_id", "col_id"], "left_anti")
            changed = changed.unionByName(zero.withColumn("n", F.lit(1).cast("long")).withColumn("weight", F.lit(-1).cast("long")))
        changed = self.cut(changed)
        self.open = self.open.join(changed.where("weight > 0").select("row_id", "col_id"), ["row_id", "col_id"], "left_anti")
        self.paid = self.paid.unionByName(changed.where("weight < 0").drop("weight"))
        self.picks += 1
        self.error -= gain
        if self.picks % 10 == 0:
            self.open, self.paid = self.cut(self.open), self.cut(self.paid)
        return changed


def _fits(matrix: Matrix, pool: Pool, local_cells: int) -> bool:
    """Whether the matrix, the entries of the patterns and the table of their columns stay within the bound; for itemsets,
    whether the classes of rows do."""
    if not local_cells:
        return False
    if isinstance(pool, ItemsetPool):
        _, cols, has = pool.sides()
        return pool.n_used() * max(1, len(cols)) <= 4 * local_cells and has.size <= 4 * local_cells
    if _is_packed(matrix, pool):
        return pool.bytes() <= 4 * local_cells
    if isinstance(pool, PackedPool):  # bits of patterns, and of columns those of ones, zeros and a step's work
        return pool.tile_cols.count() <= local_cells // 4 and pool.bytes(3) <= 4 * local_cells
    if matrix.cells > 4 * local_cells:
        return False
    if pool.tile_cells is not None:
        return pool.tile_cells.count() <= local_cells
    pairs = _pairs(matrix, pool)
    if pairs is not None:
        n = len(np.unique(pairs[0]))
        return n <= 4 * local_cells and len(pairs[0]) + n <= local_cells
    n = pool.tile_cols.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("tile_id").alias("t")).first()
    return n.t * matrix.n_cols <= 4 * local_cells and pool.tile_rows.count() + n.n <= local_cells


def _trace(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """The rows as Arrow, so that no Python worker has to start for them."""
    schema = SCHEMAS["selection"]
    kinds = {"integer": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    columns = list(zip(*rows, strict=True)) or [()] * len(schema)
    return spark.createDataFrame(pa.table({f.name: pa.array(c, kinds[f.dataType.typeName()]) for f, c in zip(schema, columns, strict=True)}), schema)


class _Log:
    """Rows of the trace.  ``n_cells`` and ``n_hashes`` count the work of a step: cells read for exact gains and hash values
    compared for estimates (null where tables are distributed)."""

    def __init__(self, matrix: Matrix):
        self.rows, self.cells, self.began = [], matrix.cells, time.time()
        self.at: list[float] = []  # when each pick was made

    def add(self, tile: int, score: float | None, gain: int, error: int, checked: int, n_cells: int | None = None, n_hashes: int | None = None) -> None:
        self.at.append(time.monotonic())
        took = int(1000 * (time.time() - self.began))
        self.rows.append((len(self.rows) + 1, int(tile), None if score is None else float(score), int(gain), int(error), error / self.cells, checked, took, n_cells, n_hashes))


def _feasible(matrix: Matrix, pool: Pool) -> None:
    if not pool.dominated and cover.dominated(matrix, pool).where("not is_dominated").limit(1).count():
        raise ValueError("full cover asks for patterns that hold no zero of the matrix")


# --- the hashed selector ------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Rules:
    """How the hashed selector estimates, verifies and stops."""

    max_tiles: int | None = 200
    sketch_k: int = 30
    max_checks: int = 30
    mode: str = "exact"
    small: str = "exact"
    merge: str = "union"
    tie: str = "gain"
    on_fail: str = "next"
    verify: bool = True
    estimator: str = "k"


def zero_lists(matrix: Matrix, pool: Pool, fam: hashing.Family, k: int) -> DataFrame:
    """``tile_id, hashes`` over the zeros of each pattern; patterns without a zero have no row."""
    zeros = pool.cells().join(matrix.ones, ["row_id", "col_id"], "left_anti").select("tile_id", "row_id", "col_id")
    return sketch.build(Pool(tile_cells=zeros), fam, k)


def hashed(matrix: Matrix, pool: Pool, max_tiles: int | None = 200, sketch_k: int = 30, reps: int = 10, max_checks: int = 30, seed: int = 42, mode: str = "exact", small: str = "exact", merge: str = "union", tie: str = "gain", on_fail: str = "next", verify: bool = True, goal: str = "budget", estimator: str = "k", strategy: str | None = None, cutoff: int | None = None, prime: int | None = None, lists: DataFrame | None = None, local_cells: int = LOCAL_CELLS, zero_penalty: str = "own") -> DataFrame:
    """Picks by estimated joint size, verified on the best ``max_checks`` candidates of a step.

    ``mode`` "inexact" subtracts a tile's own zeros from its score.  ``on_fail`` "next" goes on to the next candidate when
    one doesn't lower the error, "stop" ends there.  ``zero_penalty`` "sketched", in the inexact case, charges a zero that
    several patterns share once: a second list over the zeros of each pattern gives the joint number of zeros in place of a
    pattern's own.  ``goal`` "cover" runs without a budget until no one is left.  Without
    a ``prime`` the modulus follows the largest id.
    """
    if goal == "cover":
        _feasible(matrix, pool)
        max_tiles = None
    if zero_penalty not in ("own", "sketched"):
        raise ValueError("zero_penalty is 'own' or 'sketched'")
    shared = mode == "inexact" and zero_penalty == "sketched"
    rules = Rules(max_tiles, sketch_k, max_checks, mode, small, merge, tie, on_fail, verify, estimator)
    log = _Log(matrix)
    if _fits(matrix, pool, local_cells):
        state = _state(matrix, pool)
        by_class = isinstance(pool, ItemsetPool)
        largest = pool.largest_id() if by_class else max(state.row_ids.max(initial=0), state.col_ids.max(initial=0))
        fam = hashing.family(reps, seed, prime or hashing.prime_for(largest))
        if lists is None and strategy is None and not by_class:
            held = state.lists(fam, sketch_k, cutoff)
        else:
            held = sketch.as_array(lists if lists is not None else sketch.build(pool, fam, sketch_k, strategy, cutoff), state.ids, fam, sketch_k)
        zeros = sketch.as_array(zero_lists(matrix, pool, fam, sketch_k), state.ids, fam, sketch_k) if shared else None
        hashed_local(state, held, log, rules, fam.prime, zeros)
        return _trace(matrix.ones.sparkSession, log.rows)
    with tables() as cut:
        fam = hashing.family(reps, seed, prime or hashing.prime_for(pool.largest_id()))
        lists = cut(lists if lists is not None else sketch.build(pool, fam, sketch_k, strategy, cutoff))
        zeros = cut(zero_lists(matrix, pool, fam, sketch_k)) if shared else None
        _hashed_spark(matrix, pool, lists, log, rules, fam, cut, zeros)
    return _trace(matrix.ones.sparkSession, log.rows)


def hashed_local(state: LocalState, held: np.ndarray, log: _Log, rules: Rules, prime: int, zeros: np.ndarray | None = None) -> None:
    """The loop on the driver; ``held`` holds the lists as [tile, repetition, place], padded with the prime, ``zeros`` those
    of the patterns' zeros."""
    left = np.ones(len(state.ids), bool)
    first = int(np.lexsort((state.ids, -state.alone))[0]) if len(state.ids) else -1
    if first < 0 or state.alone[first] <= 0:
        return
    joint = estimate.Joint(held, first, rules.sketch_k, prime, rules.merge, rules.small, rules.estimator)
    shared = None if zeros is None else estimate.Joint(zeros, first, rules.sketch_k, prime, "union", "exact", rules.estimator)
    left[first] = False
    gain = int(state.alone[first])
    state.pick(first)
    log.add(state.ids[first], None, gain, state.error, 1, int(state.size.sum()), 0)
    while (rules.max_tiles is None or len(log.rows) < rules.max_tiles) and left.any() and state.error:
        at, read = np.flatnonzero(left), state.read
        score = joint.scores()[at]
        if rules.mode == "inexact":
            score = score - (state.zeros[at] if shared is None else shared.scores()[at])
        score = np.where(np.isnan(score), -np.inf, score)
        order = np.lexsort((state.ids[at], -state.alone[at], -score) if rules.tie == "gain" else (state.ids[at], -score))
        if rules.small == "discard":
            order = order[np.isfinite(score[order])]
        found = None
        for checked, o in enumerate(order[: rules.max_checks if rules.verify else 1], 1):
            gain = state.gain(int(at[o]))
            if gain > 0 or not rules.verify:
                found = int(at[o]), float(score[o]), gain, checked
                break
            if rules.on_fail == "stop":
                break
        if found is None:
            return
        i, value, gain, checked = found
        state.pick(i)
        left[i] = False
        compared = joint.add(i) + (0 if shared is None else shared.add(i))
        log.add(state.ids[i], value, gain, state.error, checked if rules.verify else 0, state.read - read, compared)


def _hashed_spark(matrix: Matrix, pool: Pool, lists: DataFrame, log: _Log, rules: Rules, fam: hashing.Family, cut: Callable, zeros: DataFrame | None = None) -> None:
    spark, k, reps, prime = matrix.ones.sparkSession, rules.sketch_k, fam.reps, fam.prime
    max_tiles, max_checks, mode, merge, tie, on_fail, verify = rules.max_tiles, rules.max_checks, rules.mode, rules.merge, rules.tie, rules.on_fail, rules.verify
    how = {"small": rules.small, "estimator": rules.estimator}
    state = SparkState(matrix, pool, cut)
    held = lists.join(state.catalogue.select("tile_id", (F.col("ones") - F.col("zeros")).alias("alone"), "zeros"), "tile_id")
    if zeros is not None:
        none = F.array(*(F.array().cast("array<bigint>") for _ in range(reps)))
        held = held.join(zeros.withColumnRenamed("hashes", "zero_hashes"), "tile_id", "left").withColumn("zero_hashes", F.coalesce("zero_hashes", none))
    held = held.repartition("tile_id").persist()
    first = state.catalogue.select("tile_id", (F.col("ones") - F.col("zeros")).alias("alone")).orderBy(F.desc("alone"), "tile_id").first()
    if first is None or first.alone <= 0:
        return
    taken = [first.tile_id]
    both = ["hashes"] + (["zero_hashes"] if zeros is not None else [])
    row = held.where(F.col("tile_id") == first.tile_id).select(*both).first()
    chosen = [list(h) for h in row.hashes] if row else [[] for _ in range(reps)]
    shared = [list(h) for h in row.zero_hashes] if row and zeros is not None else [[] for _ in range(reps)]
    state.pick(first.tile_id, first.alone)
    log.add(first.tile_id, None, first.alone, state.error, 1)
    while (max_tiles is None or len(log.rows) < max_tiles) and state.error:
        value = estimate.score(_literal(chosen), F.col("hashes"), k, prime, how=merge, **how)
        charge = F.lit(0) if mode != "inexact" else F.col("zeros")
        if zeros is not None:
            charge = estimate.score(_literal(shared), F.col("zero_hashes"), k, prime, estimator=rules.estimator)
        ranked = _without(held, taken).select("tile_id", "alone", *both, (value - charge).alias("score")).where("score is not null")
        ties = [F.desc("alone"), F.col("tile_id")] if tie == "gain" else [F.col("tile_id")]
        best = ranked.orderBy(F.desc("score"), *ties).limit(max_checks if verify else 1).collect()
        if not best:
            break
        gains = state.gains([r.tile_id for r in best])
        found = None
        for checked, r in enumerate(best, 1):
            if gains[r.tile_id] > 0 or not verify:
                found = r, checked
                break
            if on_fail == "stop":
                break
        if found is None:
            break
        r, checked = found
        state.pick(r.tile_id, gains[r.tile_id])
        taken.append(r.tile_id)
        chosen = [sorted(set(a) | set(b))[:k] if merge == "union" else sorted([*a, *b])[:k] for a, b in zip(chosen, r.hashes, strict=True)]
        if zeros is not None:
            shared = [sorted(set(a) | set(b))[:k] for a, b in zip(shared, r.zero_hashes, strict=True)]
        log.add(r.tile_id, r.score, gains[r.tile_id], state.error, checked if verify else 0)
    held.unpersist()


def _literal(lists: list[list[int]]) -> Column:
    """Lists, one a repetition, as an array column."""
    return F.array(*(F.array(*(F.lit(v).cast("long") for v in h)).cast("array<bigint>") for h in lists))


def _without(tiles: DataFrame, taken: list[int]) -> DataFrame:
    """The tiles that are not taken; the picks go to every task, eight bytes each."""
    gone = tiles.sparkSession.createDataFrame([(int(i),) for i in taken], "tile_id long")
    return tiles.join(F.broadcast(gone), "tile_id", "left_anti")


def restarts(matrix: Matrix, pool: Pool, seeds: list[int], **options) -> DataFrame:
    """``seed, n_picks, error, rel_error`` of the last step for several hash seeds."""
    out = None
    for s, lists in zip(seeds, _lists_of_seeds(matrix, pool, seeds, **options), strict=True):
        end = hashed(matrix, pool, seed=s, **options | lists).agg(F.max("step").alias("n_picks"), F.max_by("error", "step").alias("error"), F.max_by("rel_error", "step").alias("rel_error")).select(F.lit(s).alias("seed"), "*")
        out = end if out is None else out.unionByName(end)
    return out


def _lists_of_seeds(matrix: Matrix, pool: Pool, seeds: list[int], sketch_k: int = 30, reps: int = 10, prime: int | None = None, cutoff: int | None = None, **options) -> list[dict]:
    """For itemset patterns the lists of all seeds, made in one pass over the rows."""
    if not isinstance(pool, ItemsetPool) or options.get("lists") is not None or options.get("strategy") is not None:
        return [{}] * len(seeds)
    maps = [hashing.family(reps, s, prime or hashing.prime_for(pool.largest_id())) for s in seeds]
    every = sketch.build(pool, hashing.Family(tuple(m for f in maps for m in f.maps), maps[0].prime), sketch_k, None, cutoff)
    return [{"lists": every.select("tile_id", F.slice("hashes", 1 + i * reps, reps).alias("hashes"))} for i in range(len(seeds))]


# --- baselines ------------------------------------------------------------------------------------------------------------


def greedy(matrix: Matrix, pool: Pool, max_tiles: int | None = 200, goal: str = "budget", incremental: bool = True, lazy: bool = False, local_cells: int = LOCAL_CELLS) -> DataFrame:
    """The best true decrease of the error at each step, until no tile lowers it.

    ``incremental`` updates gains by the newly covered cells only; otherwise every tile is scored anew.  ``lazy`` keeps
    stale gains as bounds, which holds for patterns inside the matrix.
    """
    if goal == "cover":
        _feasible(matrix, pool)
        max_tiles = None
    log = _Log(matrix)
    if _fits(matrix, pool, local_cells):
        state = _state(matrix, pool)
        if lazy and (state.zeros > 0).any():
            raise ValueError("stale gains are bounds for patterns inside the matrix only")
        greedy_local(state, log, max_tiles, incremental, lazy)
        return _trace(matrix.ones.sparkSession, log.rows)
    with tables() as cut:
        _greedy_spark(matrix, pool, log, max_tiles, cut)
    return _trace(matrix.ones.sparkSession, log.rows)


def greedy_local(state: LocalState, log: _Log, max_tiles: int | None, incremental: bool, lazy: bool) -> None:
    """The loop on the driver."""
    gains, left = state.alone.copy(), np.ones(len(state.ids), bool)
    lowest = np.iinfo(np.int64).min
    while (max_tiles is None or len(log.rows) < max_tiles) and left.any():
        checked, read = int(left.sum()), state.read
        if lazy:
            checked = 0
            while True:
                i = int(np.argmax(np.where(left, gains, lowest)))
                now = state.gain(i)
                checked += 1
                if now == gains[i]:
                    break
                gains[i] = now
        elif not incremental and log.rows:
            gains = state.all_gains()
        i = int(np.argmax(np.where(left, gains, lowest)))
        if gains[i] <= 0:
            break
        g = int(gains[i])
        before = state.pick(i)
        left[i] = False
        if incremental and not lazy:
            gains = gains - state.losses(i, before)
        log.add(state.ids[i], None, g, state.error, checked, state.read - read, 0)


def static_local(state: LocalState, log: _Log, max_tiles: int) -> None:
    for i in np.lexsort((state.ids, -state.alone))[:max_tiles].tolist():
        state.pick(i)
        log.add(state.ids[i], None, state.alone[i], state.error, 0, int(state.size[i]), 0)


def _greedy_spark(matrix: Matrix, pool: Pool, log: _Log, max_tiles: int | None, cut: Callable) -> None:
    state = SparkState(matrix, pool, cut)
    gains = state.catalogue.select("tile_id", (F.col("ones") - F.col("zeros")).alias("gain"))
    taken: list[int] = []
    while max_tiles is None or len(taken) < max_tiles:
        best = _without(gains, taken).orderBy(F.desc("gain"), "tile_id").first()
        if best is None or best.gain <= 0:
            break
        changed = state.pick(best.tile_id, best.gain)
        taken.append(best.tile_id)
        log.add(best.tile_id, None, best.gain, state.error, 0)
        loss = state.met(changed, state.pool).groupBy("tile_id").agg(F.sum("weight").alias("loss"))
        gains = cut(gains.join(loss, "tile_id", "left").select("tile_id", (F.col("gain") - F.coalesce("loss", F.lit(0))).alias("gain")))


def _path(matrix: Matrix, pool: Pool, order: DataFrame) -> DataFrame:
    path = cover.error_path(matrix, pool.only(order.select("tile_id")), order)
    return order.join(path, "step").select("step", "tile_id", "gain", "error", "rel_error")


def static_rank(matrix: Matrix, pool: Pool, max_tiles: int = 200, local_cells: int = LOCAL_CELLS) -> DataFrame:
    """Tiles by their standalone gain, never scored again, never stopped: ``step, tile_id, gain, error, rel_error``."""
    if _fits(matrix, pool, local_cells):
        state = _state(matrix, pool)
        log = _Log(matrix)
        static_local(state, log, max_tiles)
        return _trace(matrix.ones.sparkSession, log.rows).select("step", "tile_id", "gain", "error", "rel_error")
    best = cover.profile(matrix, pool).select("tile_id", (F.col("ones") - F.col("zeros")).alias("gain")).orderBy(F.desc("gain"), "tile_id").limit(max_tiles)
    return _path(matrix, pool, cut(_numbered(best, F.desc("gain"), "tile_id")))


def _numbered(best: DataFrame, *order) -> DataFrame:
    """A bounded number of rows with ``step`` from 1."""
    from pyspark.sql import Window

    return best.withColumn("step", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*order)))


def random_order(matrix: Matrix, pool: Pool, max_tiles: int = 200, seed: int = 1) -> DataFrame:
    """Tiles in a reproducible random order (a sanity baseline)."""
    r = hashing.uniform(seed, "tile_id")
    best = cover.profile(matrix, pool).select("tile_id", (F.col("ones") - F.col("zeros")).alias("gain"), r.alias("r")).orderBy("r", "tile_id").limit(max_tiles)
    return _path(matrix, pool, cut(_numbered(best, "r", "tile_id").drop("r")))


def brute_force(matrix: Matrix, pool: Pool, size: int, most: int = 15) -> DataFrame:
    """``n_picks, tiles, error`` of the best set of at most ``size`` tiles; pools of at most ``most`` only."""
    state = (ItemsetState if isinstance(pool, ItemsetPool) else LocalState)(matrix, pool)
    if len(state.ids) > most:
        raise ValueError(f"brute force takes at most {most} tiles")
    weight = state.weight if isinstance(state, ItemsetState) else np.ones(len(state.row_ids), np.int64)
    best = (state.error, ())
    for n in range(1, min(size, len(state.ids)) + 1):
        for some in itertools.combinations(range(len(state.ids)), n):
            hit = np.zeros(state.w.shape, bool)
            for i in some:
                hit[state.at(i)] = True
            best = min(best, (state.error - int(weight @ (state.w * hit).sum(1, dtype=np.int64)), tuple(int(state.ids[i]) for i in some)), key=lambda b: (b[0], len(b[1]), b[1]))
    return matrix.ones.sparkSession.createDataFrame([(len(best[1]), ",".join(map(str, best[1])), best[0])], "n_picks int, tiles string, error long")
