"""Applications: a generator, a selector and a report."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.model import Matrix, Pool
from tilesketch.operators.candidates import association, itemsets, redescriptions
from tilesketch.plans import select
from tilesketch.session import cut


def choose(matrix: Matrix, pool: Pool, method: str = "hashed", max_tiles: int | None = 200, mode: str = "exact", goal: str = "budget", **options) -> DataFrame:
    if method == "hashed":
        return select.hashed(matrix, pool, max_tiles, mode=mode, goal=goal, **options)
    if method == "greedy":
        return select.greedy(matrix, pool, max_tiles, goal, **options)
    return select.static_rank(matrix, pool, max_tiles, **options)


def tiling(matrix: Matrix, min_support: float, max_tiles: int | None = 200, closed: bool = False, singletons: bool = False, max_len: int | None = None, goal: str = "budget", method: str = "hashed", **options) -> tuple[DataFrame, Pool]:
    """Tile a transaction database with (closed) frequent itemsets."""
    sets = itemsets.itemsets(matrix, min_support, max_len)
    pool = itemsets.as_pool(matrix, itemsets.closed(sets) if closed else sets)
    if singletons:
        pool = itemsets.add_singletons(pool, matrix)
    return choose(matrix, pool, method, max_tiles, "exact", goal, **options), pool


def factorize(matrix: Matrix, rank: int, taus: tuple[float, ...] = (0.5,), walks: bool = True, rule: str = "majority", method: str = "hashed", **options) -> tuple[DataFrame, Pool]:
    """Approximate Boolean factorisation: the picks' rows and columns are the factors."""
    pools = [association.association(matrix, t, rule) for t in taus] + ([association.restart_walk(matrix, rule)] if walks else [])
    pool = association.joined(*pools) if len(pools) > 1 else pools[0]
    trace = choose(matrix, pool, method, rank, "inexact", **options)
    return trace, pool.only(trace.select("tile_id"))


def boolean_product(left: DataFrame, right: DataFrame) -> DataFrame:
    """``row_id, col_id`` of the Boolean product of the factors ``(tile_id, row_id)`` and ``(tile_id, col_id)``."""
    return left.join(right, "tile_id").select("row_id", "col_id").distinct()


def boolean_rank_bound(matrix: Matrix, pool: Pool, **options) -> DataFrame:
    """One row: ``rank_bound``, the number of patterns of a full cover."""
    return select.greedy(matrix, pool, goal="cover", **options).agg(F.count(F.lit(1)).alias("rank_bound"))


def redescription_set(left: DataFrame, right: DataFrame, columns: DataFrame, n_rows: int, n_cols: int, min_jaccard: float, min_support: int, most: int | None = None, max_tiles: int | None = 200, method: str = "hashed", **options) -> tuple[DataFrame, Matrix, Pool]:
    """A small set of redescriptions that covers the matrix that all of them make; the trace carries both queries.  Every pair
    that reaches both floors is a candidate, unless ``most`` asks for the best ones only."""
    both = redescriptions.met(left, right)
    pairs = cut(redescriptions.best_pairs(redescriptions.redescriptions(left, right, min_jaccard, min_support, both), most))
    pool = redescriptions.as_pool(pairs, left, right, columns, both)
    matrix = redescriptions.union_matrix(pool, n_rows, n_cols)
    trace = choose(matrix, pool, method, max_tiles, "exact", **options)
    return trace.join(pairs.select("tile_id", "q_left", "q_right"), "tile_id"), matrix, pool
