"""Hand fixtures, brute force and invariants of sketches, covers and selectors."""

import pytest
from pyspark.sql import functions as F

from tilesketch.functions import estimate, hashing
from tilesketch.model import Matrix, Pool
from tilesketch.operators import cover, sketch
from tilesketch.operators.candidates import itemsets, synthetic
from tilesketch.plans import metrics, select


def matrix(spark, cells, n_rows, n_cols):
    return Matrix(spark.createDataFrame(cells, "row_id long, col_id long"), n_rows, n_cols)


def pool(spark, tiles, dominated=False):
    rows = [(t, r) for t, (rs, _) in tiles.items() for r in rs]
    cols = [(t, c) for t, (_, cs) in tiles.items() for c in cs]
    return Pool(spark.createDataFrame(rows, "tile_id long, row_id long"), spark.createDataFrame(cols, "tile_id long, col_id long"), dominated=dominated)


def path(trace):
    return [(r.tile_id, r.gain, r.error) for r in trace.orderBy("step").collect()]


@pytest.fixture(scope="module")
def random_case(spark):
    rows, cols = (spark.range(n).select(F.col("id")) for n in (40, 50))
    return synthetic.planted(rows, cols, 6, 1, 0.3, 0.2, "orig", 0.1, 3, p=0.25)


@pytest.mark.parametrize("local", [0, 10_000])
def test_identity_needs_every_tile(spark, local):
    m = matrix(spark, [(i, i) for i in range(3)], 3, 3)
    p = pool(spark, {i: ([i], [i]) for i in range(3)}, True)
    assert [e for _, _, e in path(select.greedy(m, p, local_cells=local))] == [2, 1, 0]
    assert [e for _, _, e in path(select.hashed(m, p, sketch_k=2, reps=3, local_cells=local))] == [2, 1, 0]


@pytest.mark.parametrize("local", [0, 10_000])
def test_halves_beat_the_middle(spark, local):
    m = matrix(spark, [(r, c) for r in range(4) for c in range(4)], 4, 4)
    p = pool(spark, {0: (range(4), [0, 1]), 1: (range(4), [2, 3]), 2: (range(4), [1, 2])}, True)
    assert path(select.greedy(m, p, local_cells=local)) == [(0, 8, 8), (1, 8, 0)]


def test_set_cover_is_greedy(spark):
    sets = [(1, x) for x in (1, 2, 3, 4)] + [(2, x) for x in (1, 2, 5)] + [(3, x) for x in (3, 4, 6)]
    m, p = itemsets.from_sets(spark.createDataFrame(sets, "set_id long, element long"))
    assert [t for t, _, _ in path(select.greedy(m, p))] == [1, 2, 3]
    best = select.brute_force(m, p, 3).first()
    assert (best.n_picks, best.error) == (2, 0) or best.error == 0


def test_a_zero_is_charged_once(spark):
    sets = spark.createDataFrame([(1, 1), (1, 2), (1, 4), (2, 3), (2, 4)], "set_id long, element long")
    signs = spark.createDataFrame([(1, True), (2, True), (3, True), (4, False)], "element long, positive boolean")
    m, p = itemsets.from_sets(sets, signs)
    assert cover.error(m, p).first().error == 1
    assert path(select.greedy(m, p)) == [(1, 1, 2), (2, 1, 1)]


def test_empty_cases(spark):
    m = matrix(spark, [(0, 0)], 1, 1)
    bad = pool(spark, {1: ([0, 1], [1, 2])})
    assert path(select.greedy(m, bad)) == [] and path(select.hashed(m, bad, mode="inexact", sketch_k=2, reps=2)) == []
    assert path(select.greedy(m, bad, max_tiles=0)) == []
    with pytest.raises(ValueError):
        select.greedy(m, bad, goal="cover")


def test_three_sketch_strategies_agree(spark, random_case):
    _, p = random_case
    fam = hashing.family(4, 5)
    got = [sorted((r.tile_id, [list(h) for h in r.hashes]) for r in sketch.build(p, fam, 12, s).collect()) for s in ("band", "walk", "enumerate")]
    assert got[0] == got[1] == got[2]
    sizes = {r.tile_id: r["size"] for r in p.tiles().collect()}
    assert all(h == sorted(set(h)) and len(h) == min(12, sizes[t]) and all(0 <= x < hashing.PRIME for x in h) for t, hs in got[0] for h in hs)


def test_lists_merge_to_the_list_of_the_union(spark, random_case):
    _, p = random_case
    fam = hashing.family(2, 9)
    ids = [r.tile_id for r in p.tiles().select("tile_id").orderBy("tile_id").limit(2).collect()]
    two = p.only(spark.createDataFrame([(i,) for i in ids], "tile_id long"))
    a, b = (r.hashes for r in sketch.build(two, fam, 10).orderBy("tile_id").collect())
    union = Pool(tile_cells=two.cells().select(F.lit(1).cast("long").alias("tile_id"), "row_id", "col_id").distinct())
    whole = sketch.build(union, fam, 10).first().hashes
    assert [sorted(set(x) | set(y))[:10] for x, y in zip(a, b)] == [list(h) for h in whole]


def test_column_and_array_estimates_agree(spark):
    import numpy as np

    lists = [[5, 7, 11, 2_000_000], [5, 9], [1, 2, 3, 4]]
    got = [r.e for r in spark.createDataFrame([(x,) for x in lists], "h array<long>").select(estimate.size(F.col("h"), 4).alias("e")).collect()]
    padded = np.array([x + [hashing.PRIME] * (4 - len(x)) for x in lists])
    assert got == list(estimate.np_size(padded, 4))


@pytest.mark.parametrize("mode", ["exact", "inexact"])
def test_both_ways_pick_alike_and_errors_are_true(spark, random_case, mode):
    m, p = random_case
    options = {"max_tiles": 4, "sketch_k": 8, "reps": 3, "mode": mode}
    a, b = select.hashed(m, p, **options), select.hashed(m, p, **options, local_cells=0)
    assert path(a) == path(b)
    order = a.select("step", "tile_id")
    assert [r.error for r in cover.error_path(m, p.only(order.select("tile_id")), order).orderBy("step").collect()] == [e for _, _, e in path(a)]
    assert path(select.greedy(m, p, 5)) == path(select.greedy(m, p, 5, local_cells=0)) == path(select.greedy(m, p, 5, incremental=False))


def test_greedy_reaches_its_bound(spark):
    rows, cols = (spark.range(n).select(F.col("id")) for n in (20, 20))
    m, p = synthetic.planted(rows, cols, 4, 1, 0.3, 0.3, "all", 0.0, 2, p=0.3)
    total = m.ones.count()
    best = select.brute_force(m, p, 3).first().error
    trace = select.greedy(m, p, 3, lazy=True)
    assert path(trace) == path(select.greedy(m, p, 3))
    assert metrics.coverage_ratio(trace, total, best).first().ratio >= 0.632


def test_planted_copies_keep_their_length(spark):
    rows, cols = (spark.range(n).select(F.col("id")) for n in (60, 60))
    m, p = synthetic.planted(rows, cols, 5, 2, move=0.25, use="all", seed=4, p=0.3)
    size = {r.tile_id: {x for x in r.v} for r in p.tile_rows.groupBy("tile_id").agg(F.collect_list("row_id").alias("v")).collect()}
    for t in range(5):
        for c in range(2):
            copy = size[5 + 2 * t + c]
            assert len(copy) == len(size[t]) and len(copy & size[t]) == len(size[t]) - int(0.25 * len(size[t]) + 0.5)
    assert cover.coverable(m, p).first().coverable


def test_methods_order_on_planted_data(spark):
    rows, cols = (spark.range(n).select(F.col("id")) for n in (100, 120))
    m, p = synthetic.planted(rows, cols, 20, 5, 0.3, 0.1, "orig", 0.1, 1)
    end = lambda t: t.agg(F.max_by("error", "step").alias("e")).first().e
    greedy, hashed, static = end(select.greedy(m, p, 40)), end(select.hashed(m, p, 40, mode="inexact")), end(select.static_rank(m, p, 40))
    assert greedy <= hashed <= static
