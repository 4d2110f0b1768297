"""Redescriptions: pairs of predicates over two views of the same entities, and the patterns that they stand for."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.model import Matrix, Pool
from tilesketch.operators.packed import PackedPool
from tilesketch.plans.metrics import jaccard
from tilesketch.session import cut

PAIRS = 1_000_000  # pairs of predicates that a task counts at once
TABLE = 4_000_000  # entries of a table that a task makes at once


def predicates(df: DataFrame, entity: str, numeric: dict[str, list[float]] | None = None, categorical: tuple[str, ...] = ()) -> DataFrame:
    """``pred, entity_id`` where a predicate holds: value at or over each cut, value under it, category equal."""
    made = []
    for name, cuts in (numeric or {}).items():
        for c in cuts:
            made += [(f"{name} >= {c:g}", F.col(name) >= c), (f"{name} < {c:g}", F.col(name) < c)]
    out = df.select(F.col(entity).cast("long").alias("entity_id"), F.explode(F.array(*(F.when(cond, F.lit(text)) for text, cond in made), *(F.concat(F.lit(f"{c} = "), F.col(c).cast("string")) for c in categorical))).alias("pred"))
    return out.where("pred is not null").select("pred", "entity_id").distinct()


def conjunctions(preds: DataFrame) -> DataFrame:
    """The predicates with the ANDs of every two."""
    a, b = preds.select(F.col("pred").alias("p"), "entity_id"), preds.select(F.col("pred").alias("q"), "entity_id")
    both = a.join(b, "entity_id").where("p < q").select(F.concat_ws(" AND ", "p", "q").alias("pred"), "entity_id")
    return preds.unionByName(both)


def met(left: DataFrame, right: DataFrame) -> DataFrame:
    """``entity_id, l, r``: the predicates of both views that hold for each entity of any, made once.  A view is
    ``pred, entity_id`` or ``preds, entity_id`` with lists."""
    def gathered(view: DataFrame, name: str) -> DataFrame:
        if "preds" in view.columns:
            return view.where("entity_id is not null").groupBy("entity_id").agg(F.array_distinct(F.flatten(F.collect_list("preds"))).alias(name))
        return view.where("entity_id is not null").groupBy("entity_id").agg(F.collect_set("pred").alias(name))

    return cut(gathered(left, "l").join(gathered(right, "r"), "entity_id", "full_outer").select(F.col("entity_id").cast("long"), "l", "r"))


def _held(lists: pa.Array, names: pa.Array) -> np.ndarray:
    """Which list has which name, as a table; a null list has none."""
    words = lists.flatten()
    out = np.zeros((len(lists), len(names) + 1), np.float32)  # the last for other names
    n = np.asarray(pc.fill_null(lists.value_lengths(), 0))
    out[np.repeat(np.arange(len(lists)), n), np.asarray(pc.index_in(words, value_set=names.cast(words.type)).fill_null(len(names)))] = 1
    return out[:, :-1]


def _names(both: DataFrame, side: str, most: int) -> pa.Array:
    got = both.select(F.explode(side).alias("pred")).where("pred is not null").distinct().limit(most + 1)
    return got.orderBy("pred").toArrow().column(0).combine_chunks()


def redescriptions(left: DataFrame, right: DataFrame, min_jaccard: float, min_support: int, both: DataFrame | None = None) -> DataFrame:
    """``q_left, q_right, supp_left, supp_right, supp_both, jaccard`` of the pairs that reach both floors.  A task adds the
    pairs of its entities up in a table of counts; where there are too many pairs for that, they are joined."""
    both = met(left, right) if both is None else both
    p, q = (_names(both, side, PAIRS) for side in ("l", "r"))
    if len(p) * len(q) <= PAIRS:
        found = _counted(both, p, q).where((F.col("supp_both") >= min_support) & (F.col("supp_both") > 0))
    else:
        one = lambda side, name: both.select("entity_id", F.explode(side).alias(name))
        count = lambda side, name, n: one(side, name).groupBy(name).agg(F.count(F.lit(1)).alias(n))
        pairs = one("l", "q_left").join(one("r", "q_right"), "entity_id").groupBy("q_left", "q_right").agg(F.count(F.lit(1)).alias("supp_both")).where(F.col("supp_both") >= min_support)
        found = pairs.join(count("l", "q_left", "supp_left"), "q_left").join(count("r", "q_right", "supp_right"), "q_right")
    return found.withColumn("jaccard", jaccard(F.col("supp_both"), F.col("supp_left"), F.col("supp_right"))).where(F.col("jaccard") >= min_jaccard).select("q_left", "q_right", "supp_left", "supp_right", "supp_both", "jaccard")


def _counted(both: DataFrame, p: pa.Array, q: pa.Array) -> DataFrame:
    """Every pair with its counts."""

    def add(batches):
        n, a, b = np.zeros((len(p), len(q))), np.zeros(len(p)), np.zeros(len(q))
        step = max(1, TABLE // max(1, len(p) + len(q)))
        for batch in batches:
            for x in range(0, batch.num_rows, step):
                some = batch.slice(x, step)
                l, r = _held(some.column("l"), p), _held(some.column("r"), q)  # noqa: E741
                n, a, b = n + l.T @ r, a + l.sum(0, dtype=np.float64), b + r.sum(0, dtype=np.float64)
        i, j = (x.reshape(-1) for x in np.indices(n.shape))
        whole = lambda x: pa.array(x.astype(np.int64))
        if len(i):
            yield pa.RecordBatch.from_arrays([p.take(pa.array(i)).cast(pa.string()), q.take(pa.array(j)).cast(pa.string()), whole(a[i]), whole(b[j]), whole(n[i, j])], ["q_left", "q_right", "supp_left", "supp_right", "supp_both"])

    parts = both.mapInArrow(add, "q_left string, q_right string, supp_left long, supp_right long, supp_both long")
    return parts.groupBy("q_left", "q_right").agg(*(F.sum(c).alias(c) for c in ("supp_left", "supp_right", "supp_both")))


def best_pairs(found: DataFrame, most: int | None = None) -> DataFrame:
    """The ``most`` best by Jaccard, or all, numbered from 1 as ``tile_id``."""
    from pyspark.sql import Window

    top = found if most is None else found.orderBy(F.desc("jaccard"), "q_left", "q_right").limit(most)
    return top.withColumn("tile_id", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("jaccard"), "q_left", "q_right")).cast("long"))


def as_pool(pairs: DataFrame, left: DataFrame, right: DataFrame, columns: DataFrame, both: DataFrame | None = None) -> Pool:
    """Rows where both predicates hold, columns of both predicates.  ``columns(pred, col_id)`` gives a predicate's
    attributes, those of the right view moved past the left ones."""
    both = met(left, right) if both is None else both
    chosen = pairs.select(F.col("tile_id").cast("long"), "q_left", "q_right").orderBy("tile_id").toArrow()
    ids = chosen.column(0).to_numpy()
    p, q = (chosen.column(i).combine_chunks() for i in (1, 2))
    some_p, some_q = p.unique(), q.unique()
    at_p, at_q = (np.asarray(pc.index_in(x, value_set=y)) for x, y in ((p, some_p), (q, some_q)))

    def inside(batches):
        step = max(1, TABLE // max(1, len(ids)))
        for batch in batches:
            for x in range(0, batch.num_rows, step):
                some = batch.slice(x, step)
                held = (_held(some.column("l"), some_p)[:, at_p] * _held(some.column("r"), some_q)[:, at_q]) > 0
                row, tile = np.nonzero(held)
                at, n = np.unique(row, return_counts=True)
                ends = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([some.column("entity_id").take(pa.array(at)), pa.ListArray.from_arrays(pa.array(ends), pa.array(ids[tile]))], ["row_id", "tiles"])

    members = cut(both.where("l is not null and r is not null").mapInArrow(inside, "row_id long, tiles array<long>"))
    cols = pairs.select("tile_id", F.explode(F.array("q_left", "q_right")).alias("pred")).join(columns, "pred").select("tile_id", "col_id").distinct()
    labels = pairs.select("tile_id", F.concat_ws(" ~ ", "q_left", "q_right").alias("label"))
    return PackedPool(members, cut(cols), labels=labels)


def from_query_pair(left: DataFrame, q_left: str, cols_left: list[int], right: DataFrame, q_right: str, cols_right: list[int], entity: str, tile_id: int = 1, offset: int = 0) -> Pool:
    """The pattern of one pair of queries, each a SQL predicate over its view: rows are the entities for which both hold,
    columns those of both queries, the right view's moved by ``offset``.  No row holds both: an empty pool."""
    rows = left.where(q_left).select(F.col(entity).cast("long").alias("row_id")).distinct()
    rows = rows.join(right.where(q_right).select(F.col(entity).cast("long").alias("row_id")), "row_id", "left_semi")
    rows = rows.where("row_id is not null").select(F.lit(tile_id).cast("long").alias("tile_id"), "row_id")
    cols = sorted(set(cols_left) | {c + offset for c in cols_right})
    spark = left.sparkSession
    cols = spark.createDataFrame([(tile_id, c) for c in cols], "tile_id long, col_id long").join(rows.select("tile_id").distinct(), "tile_id", "left_semi")
    labels = spark.createDataFrame([(tile_id, f"{q_left} ~ {q_right}")], "tile_id long, label string")
    return Pool(rows, cols, labels=labels)


def union_matrix(pool: Pool, n_rows: int, n_cols: int) -> Matrix:
    """The matrix that all patterns of the pool make together."""
    return Matrix(pool.cells().select("row_id", "col_id").distinct(), n_rows, n_cols, {"union of": pool})
