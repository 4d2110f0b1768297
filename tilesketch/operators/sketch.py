"""Bottom-k lists of patterns by three strategies that give the same lists.

``band`` (default): a cell's hash lies under w exactly when the row hash lies in the cyclic interval of length w that starts
at the column hash, so buckets of width w turn the search into an equi-join that examines about ``slack * k`` pairs a tile.
``walk``: one NumPy pass over sorted row and column hashes of a tile.  ``enumerate``: all cells; the only way for patterns
that are no outer product.  Itemset patterns are sketched by ``baskets.lists`` unless a strategy is named.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesketch.functions import hashing
from tilesketch.functions.hashing import Family
from tilesketch.model import Pool
from tilesketch.operators import packed
from tilesketch.operators.baskets import ItemsetPool
from tilesketch.operators.baskets import lists as itemset_lists
from tilesketch.session import cut


def _nest(values: DataFrame, k: int, reps: int) -> DataFrame:
    """``(tile_id, rep, h)`` to one row a tile: the k smallest distinct hashes of each repetition."""
    w = Window.partitionBy("tile_id", "rep").orderBy("h")
    low = values.distinct().withColumn("n", F.row_number().over(w)).where(F.col("n") <= k)
    each = low.groupBy("tile_id", "rep").agg(F.array_sort(F.collect_list("h")).alias("hashes"))
    held = each.groupBy("tile_id").agg(F.map_from_entries(F.collect_list(F.struct("rep", "hashes"))).alias("m"))
    empty = F.array().cast("array<bigint>")
    return held.select("tile_id", F.array(*(F.coalesce(F.try_element_at("m", F.lit(r)), empty) for r in range(reps))).alias("hashes"))


def _hashed(df: DataFrame, fam: Family, what: str) -> DataFrame:
    a, b, name = ("ar", "br", "row_id") if what == "row" else ("ac", "bc", "col_id")
    return df.select("tile_id", name, F.explode(hashing.maps_column(fam)).alias("m")).select("tile_id", F.col("m.rep").alias("rep"), hashing.affine(F.col(name), F.col(f"m.{a}"), F.col(f"m.{b}"), fam.prime).alias("h"))


def enumerated(pool: Pool, fam: Family, k: int, cutoff: int | None = None) -> DataFrame:
    cells = pool.cells().select("tile_id", "row_id", "col_id", F.explode(hashing.maps_column(fam)).alias("m"))
    h = hashing.cell(hashing.affine(F.col("row_id"), F.col("m.ar"), F.col("m.br"), fam.prime), hashing.affine(F.col("col_id"), F.col("m.ac"), F.col("m.bc"), fam.prime), fam.prime)
    values = cells.select("tile_id", F.col("m.rep").alias("rep"), h.alias("h"))
    return _nest(values if cutoff is None else values.where(F.col("h") < cutoff), k, fam.reps)


def banded(pool: Pool, fam: Family, k: int, cutoff: int | None = None, slack: float = 4.0) -> DataFrame:
    p = fam.prime
    top = p if cutoff is None else min(cutoff, p)
    todo = pool.tiles().select("tile_id", "size", F.least(F.ceil(F.lit(slack * k * p) / F.col("size")), F.lit(top)).cast("long").alias("w"))
    done = None
    while True:
        todo = cut(todo.withColumn("nb", F.greatest(F.lit(1), F.floor(F.lit(p) / F.col("w"))).cast("long")).withColumn("bw", F.ceil(F.lit(p) / F.col("nb")).cast("long")))
        at = ((F.col("h") - F.col("h") % F.col("bw")) / F.col("bw")).cast("long")
        rows = _hashed(pool.tile_rows, fam, "row").join(todo.select("tile_id", "nb", "bw", "w"), "tile_id").select("tile_id", "rep", at.alias("bucket"), F.col("h").alias("hr"), "w")
        cols = _hashed(pool.tile_cols, fam, "col").join(todo.select("tile_id", "nb", "bw"), "tile_id").select("tile_id", "rep", F.col("h").alias("hc"), F.explode(F.array_distinct(F.array(*((at + i) % F.col("nb") for i in range(3))))).alias("bucket"))
        met = rows.join(cols, ["tile_id", "rep", "bucket"]).select("tile_id", "rep", hashing.cell(F.col("hr"), F.col("hc"), p).alias("h"), "w").where("h < w").drop("w")
        lists = cut(_nest(met, k, fam.reps))
        short = todo.join(lists, "tile_id", "left").where((F.col("w") < top) & (F.coalesce(F.array_min(F.transform("hashes", F.size)), F.lit(0)) < F.least(F.lit(k), F.col("size"))))
        again = cut(short.select("tile_id", "size", F.least(F.col("w") * 4, F.lit(top)).cast("long").alias("w")))
        good = lists.join(again, "tile_id", "left_anti")
        done = good if done is None else done.unionByName(good)
        if again.isEmpty():
            return done
        todo = again


def walked(pool: Pool, fam: Family, k: int, cutoff: int | None = None) -> DataFrame:
    maps, p = fam.maps, fam.prime
    top = p if cutoff is None else cutoff

    def walk(table: pa.Table) -> pa.Table:
        ids = np.asarray(table["tile_id"])
        r, c = (np.array(table[n][0].as_py(), np.int64) for n in ("r", "c"))
        out = []
        for ar, br, ac, bc in maps:
            hr, hc = np.sort(hashing.np_affine(r, ar, br, p)), np.sort(hashing.np_affine(c, ac, bc, p))
            bound, found = top, np.zeros(0, np.int64)
            twice = np.concatenate([hr, hr + p])
            for i in range(0, len(hc), 256):
                part = hc[i : i + 256]
                a, b = np.searchsorted(twice, part), np.searchsorted(twice, np.minimum(part + bound, part + p))
                n = b - a
                at = np.repeat(a - np.cumsum(n) + n, n) + np.arange(n.sum())
                found = np.unique(np.concatenate([found, twice[at] - np.repeat(part, n)]))[:k]
                if len(found) == k:
                    bound = min(bound, int(found[-1]))
            out.append(found.tolist())
        return pa.table({"tile_id": ids[:1], "hashes": pa.array([out], pa.list_(pa.list_(pa.int64())))})

    sides = pool.tile_rows.groupBy("tile_id").agg(F.collect_list("row_id").alias("r")).join(pool.tile_cols.groupBy("tile_id").agg(F.collect_list("col_id").alias("c")), "tile_id")
    return sides.groupBy("tile_id").applyInArrow(walk, "tile_id long, hashes array<array<long>>")


def local_lists(rows: list[np.ndarray], cols: list[np.ndarray], row_ids: np.ndarray, col_ids: np.ndarray, fam: Family, k: int, cutoff: int | None = None, loose: bool = False) -> np.ndarray:
    """The lists of patterns that the driver holds, as [tile, repetition, place] padded with the prime.  ``rows`` and
    ``cols`` are places in the ids; ids are hashed and ranked once for each repetition, whatever the number of patterns.
    ``loose``: rows and columns are those of single cells."""
    p = fam.prime
    top = p if cutoff is None else min(cutoff, p)
    out = np.full((len(rows), fam.reps, k), p, np.int64)
    for j, (ar, br, ac, bc) in enumerate(fam.maps):
        hr, hc = hashing.np_affine(row_ids, ar, br, p), hashing.np_affine(col_ids, ac, bc, p)
        for i, (r, c) in enumerate(zip(rows, cols, strict=True)):
            if loose:
                low = (hr[r] - hc[c]) % p
                low = np.unique(low[low < top])[:k]
            else:
                low = packed.smallest(np.sort(hr[r]), np.sort(hc[c]), k, top, p)
            out[i, j, : len(low)] = low
    return out


def as_array(lists: DataFrame, ids: np.ndarray, fam: Family, k: int) -> np.ndarray:
    """The lists of the tiles ``ids`` in the form of ``local_lists``."""
    out = np.full((len(ids), fam.reps, k), fam.prime, np.int64)
    got = lists.select("tile_id", F.posexplode("hashes").alias("rep", "h")).select("tile_id", "rep", F.posexplode("h").alias("place", "h")).toArrow()
    tile, rep, place, h = (got.column(i).to_numpy() for i in range(4))
    out[np.searchsorted(ids, tile), rep, place] = h
    return out


def build(pool: Pool, fam: Family, k: int = 30, strategy: str | None = None, cutoff: int | None = None) -> DataFrame:
    """``(tile_id, hashes)``: for each repetition the k smallest distinct hashes, ascending."""
    if strategy is None and isinstance(pool, ItemsetPool):
        return itemset_lists(pool, fam, k, cutoff)
    strategy = strategy or ("enumerate" if pool.tile_cells is not None else "band")
    if pool.tile_cells is not None and strategy != "enumerate":
        raise ValueError("patterns given by cells are sketched by enumeration only")
    return {"band": banded, "walk": walked, "enumerate": enumerated}[strategy](pool, fam, k, cutoff)


def suggest_k(pool: Pool, share: float = 0.1, low: int = 10, high: int = 100) -> int:
    """k from the sizes: a low quantile, clamped."""
    q = pool.tiles().agg(F.percentile_approx("size", share)).first()[0]
    return int(max(low, min(high, q or low)))
