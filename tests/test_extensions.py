"""Shared zeros, sparse noise, lowest values, query pairs, orientation, and a pool on which greedy does badly."""

import pytest
from pyspark.sql import functions as F

from tilesketch.functions import sql
from tilesketch.model import Matrix, Pool
from tilesketch.operators.candidates import association, redescriptions, synthetic
from tilesketch.plans import metrics, select


def matrix(spark, cells, n_rows, n_cols):
    return Matrix(spark.createDataFrame(cells, "row_id long, col_id long"), n_rows, n_cols)


def pool(spark, tiles):
    rows = [(t, r) for t, (rs, _) in tiles.items() for r in rs]
    cols = [(t, c) for t, (_, cs) in tiles.items() for c in cs]
    return Pool(spark.createDataFrame(rows, "tile_id long, row_id long"), spark.createDataFrame(cols, "tile_id long, col_id long"))


@pytest.mark.parametrize("local", [0, 10_000])
def test_shared_zeros_are_charged_once(spark, local):
    # tiles 1 and 2 share the zeros of row 0, tile 3 has two zeros and four ones of its own
    ones = [(r, 0) for r in (1, 2, 3, 4, 5)] + [(r, 0) for r in (6, 7, 8)] + [(r, 1) for r in (10, 11, 12, 13)]
    m = matrix(spark, ones, 20, 3)
    p = pool(spark, {1: ([0, 20, 21, 1, 2, 3, 4, 5], [0]), 2: ([0, 20, 21, 6, 7, 8], [0]), 3: ([10, 11, 12, 13, 14, 15], [1])})
    picks = lambda penalty: [(r.tile_id, r.estimate) for r in select.hashed(m, p, 3, sketch_k=50, reps=3, mode="inexact", zero_penalty=penalty, local_cells=local).orderBy("step").collect()]
    assert picks("own") == [(1, None), (3, 14 - 2), (2, 17 - 3)]
    # joint size less joint zeros: 11 - 3 for tile 2 against 14 - 5 for tile 3, then 17 - 5
    assert picks("sketched") == [(1, None), (3, 14 - 5), (2, 17 - 5)]


def test_shared_zeros_local_equals_distributed(spark):
    rows, cols = (spark.range(n).select(F.col("id")) for n in (30, 40))
    m, p = synthetic.planted(rows, cols, 5, 2, 0.3, 0.2, "orig", 0.1, 3, p=0.25)
    run = lambda local: [(r.tile_id, r.gain, r.error) for r in select.hashed(m, p, 6, sketch_k=10, reps=3, mode="inexact", zero_penalty="sketched", local_cells=local).orderBy("step").collect()]
    assert run(0) == run(1_000_000)


def test_sparse_noise_is_a_draw_at_the_rate_that_repeats(spark):
    rows, cols = spark.range(200).select(F.col("id")), spark.range(0, 9000, 30).select(F.col("id"))
    draws = [sorted(map(tuple, synthetic.drawn_cells(r, cols, 0.1, 5).collect())) for r in (rows, rows.repartition(7))]
    assert draws[0] == draws[1]
    assert len(set(draws[0])) == len(draws[0])
    assert {c for _, c in draws[0]} <= set(range(0, 9000, 30))
    assert abs(len(draws[0]) - 6000) < 5 * (60000 * 0.1 * 0.9) ** 0.5
    assert synthetic.drawn_cells(rows, cols, 0.0, 5).count() == 0
    assert synthetic.drawn_cells(rows, cols, 1.0, 5).count() == 60000


def test_sparse_noise_flips(spark):
    rows, cols = spark.range(50).select(F.col("id")), spark.range(60).select(F.col("id"))
    m = matrix(spark, [(r, c) for r in range(50) for c in range(0, 60, 2)], 50, 60)
    flipped = {tuple(x) for x in synthetic.flip(m, rows, cols, 0.2, 9, "drawn").ones.collect()}
    drawn = {tuple(x) for x in synthetic.drawn_cells(rows, cols, 0.2, 9).collect()}
    assert flipped == {tuple(x) for x in m.ones.collect()} ^ drawn
    with pytest.raises(ValueError):
        synthetic.flip(m, rows, cols, 0.2, 9, "other")


def test_places_are_dense_and_in_order(spark):
    df = spark.range(0, 1000, 3).select(F.col("id")).repartition(5)
    assert [tuple(r) for r in synthetic.numbered(df, "id").orderBy("id").collect()] == [(v, i) for i, v in enumerate(range(0, 1000, 3))]
    assert synthetic.numbered(df.where("id < 0"), "id").count() == 0


def test_lowest_values(spark):
    df = spark.createDataFrame([("a", 5), ("a", 1), ("a", 1), ("a", 3), ("b", 2), ("b", None), ("c", None)], "g string, v long")
    assert {r.g: r.lowest for r in sql.bottom_k(df, "v", 2, "g").collect()} == {"a": [1, 3], "b": [2]}
    assert sql.bottom_k(df, "v", 3).first().lowest == [1, 2, 3]


def test_pair_of_queries(spark):
    left = spark.createDataFrame([(1, 10), (2, 20), (3, 30), (4, 40), (5, None)], "id long, x long")
    right = spark.createDataFrame([(1, True), (2, True), (3, False), (4, True), (5, True), (4, True)], "id long, y boolean")
    p = redescriptions.from_query_pair(left, "x >= 20", [0, 2], right, "y", [1], "id", offset=10)
    cells = sorted((r.row_id, r.col_id) for r in p.cells().collect())
    assert cells == [(2, 0), (2, 2), (2, 11), (4, 0), (4, 2), (4, 11)]
    sql.register(spark)
    got = spark.sql("SELECT * FROM query_pair_cells(array(2L, 3L, 4L), array(0L, 2L), array(1L, 2L, 4L, 5L), array(1L), 10)").collect()
    assert sorted(map(tuple, got)) == cells
    assert redescriptions.from_query_pair(left, "x > 99", [0], right, "y", [1], "id").cells().count() == 0
    assert sorted(map(tuple, spark.sql("SELECT * FROM tile_cells(array(1L, 2L), array(7L))").collect())) == [(1, 7), (2, 7)]


def test_association_of_rows_is_that_of_columns_of_the_transposed(spark):
    m = matrix(spark, [(0, 0), (0, 1), (1, 0), (1, 1), (2, 2), (3, 2), (3, 1)], 4, 3)
    p, t = association.association(m, 0.5, axis="rows"), association.association(m.transposed(), 0.5)
    assert sorted((r.tile_id, r.row_id, r.col_id) for r in p.cells().collect()) == sorted((r.tile_id, r.col_id, r.row_id) for r in t.cells().collect())
    with pytest.raises(ValueError):
        association.association(m, 0.5, axis="other")


def test_support(spark):
    m = matrix(spark, [(0, 0), (1, 0), (2, 0)], 4, 1)
    assert [(r.n_r, r.support) for r in metrics.support(m, pool(spark, {1: ([0, 1, 2], [0])})).collect()] == [(3, 0.75)]


@pytest.mark.parametrize("local", [0, 10_000])
def test_inexact_greedy_can_miss_everything(spark, local):
    # every tile alone adds two zeros for one one, and all share the two zeros: together they are right but for those
    n = 8
    m = matrix(spark, [(i, 0) for i in range(n)], n + 2, 1)
    p = pool(spark, {i: ([i, n, n + 1], [0]) for i in range(n)})
    assert select.greedy(m, p, local_cells=local).count() == 0
    best = select.brute_force(m, p, n)
    assert best.first().error == 2
