"""Streams against their batch results, readers and stores, ids and modulus."""

import datetime as dt
import json
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from tilesketch.functions import hashing
from tilesketch.model import Matrix, Pool
from tilesketch.operators import sketch
from tilesketch.plans import select, timing
from tilesketch.sources import tables
from tilesketch.streaming import events

BASE = dt.datetime(2024, 1, 1)


@pytest.fixture()
def stream(spark, tmp_path):
    """Four files in order; the last one holds a row that is two days late.  (A watermark counts from the next batch but one.)"""

    def write(hours, name):
        rows = [(i, BASE + dt.timedelta(hours=h), i % 3) for i, h in hours]
        there = set((tmp_path / "in").glob("*.parquet"))
        spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        for f in set((tmp_path / "in").glob("*.parquet")) - there:
            os.utime(f, (1_700_000_000 + 60 * name,) * 2)  # files are read by their age

    write([(i, i / 4) for i in range(8)], 1)
    write([(i, 48 + i / 4) for i in range(8)], 2)
    write([(101, 60), (101, 60)], 3)
    write([(100, 0.1)], 4)
    return str(tmp_path / "in")


def test_late_rows_are_left_out_of_windows(spark, stream):
    src = events.with_lateness(events.events(spark, stream), "2 hours")
    name = events.run_once(events.windowed_counts(src, "1 hour"), "append")
    got = {r.start: r.n_events for r in spark.table(name).collect()}
    assert got[BASE] == 4 and got[BASE + dt.timedelta(hours=48)] == 4  # the late row is not counted
    every = events.windowed_counts(spark.read.parquet(stream), "1 hour").where(F.col("start") == F.lit(BASE)).first()
    assert every.n_events == 5


def test_sliding_windows_equal_the_batch(spark, stream):
    name = events.run_once(events.windowed_counts(events.events(spark, stream), "2 hours", "1 hour"), "complete")
    want = events.windowed_counts(spark.read.parquet(stream), "2 hours", "1 hour")
    assert sorted(spark.table(name).collect()) == sorted(want.collect())


def test_sessions_equal_the_batch(spark, stream):
    name = events.run_once(events.sessions(events.events(spark, stream), "50 minutes"), "complete")
    assert sorted(spark.table(name).collect()) == sorted(events.sessions(spark.read.parquet(stream), "50 minutes").collect())


def test_each_cell_once_within_the_watermark(spark, stream):
    src = events.with_lateness(events.events(spark, stream), "100 hours")
    name = events.run_once(events.unique_cells(src, "event_id", "user_id"))
    assert sorted(r.event_id for r in spark.table(name).collect()) == [*range(8), 100, 101]


def test_stream_with_a_table(spark, stream):
    dim = spark.createDataFrame([(0, "x"), (1, "y")], "user_id long, name string")
    name = events.run_once(events.with_dim(events.events(spark, stream), dim, "user_id"))
    assert spark.table(name).count() == events.with_dim(spark.read.parquet(stream), dim, "user_id").count()


def test_selection_is_made_anew_on_all_cells_so_far(spark, stream):
    cells = events.events(spark, stream).select(F.col("event_id").alias("row_id"), F.col("user_id").alias("col_id"))
    seen = []

    def choose(every):
        ones = every.select("row_id", "col_id")
        pool = Pool(ones.select(F.col("col_id").alias("tile_id"), "row_id"), ones.select(F.col("col_id").alias("tile_id"), "col_id").distinct(), dominated=True)
        return select.greedy(Matrix(ones, 200, 3), pool, goal="cover").agg(F.sum("gain").alias("n"), F.min("error").alias("error"))

    events.reselect(cells, choose, lambda out, i: seen.append(tuple(out.first())))
    assert len(seen) >= 2 and [n for n, _ in seen] == sorted(n for n, _ in seen)
    assert seen[-1] == (10, 0) == tuple(choose(spark.read.parquet(stream).select(F.col("event_id").alias("row_id"), F.col("user_id").alias("col_id")).distinct()).first())


def test_readers(spark, tmp_path):
    df = spark.createDataFrame([(1, 2), (3, 4)], "row_id long, col_id long")
    for fmt, options in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("parquet", {})):
        df.write.options(**options).format(fmt).save(str(tmp_path / fmt))
        got = tables.read(spark, str(tmp_path / fmt), fmt, "row_id long, col_id long", **options)
        assert sorted(tuple(r) for r in got.collect()) == [(1, 2), (3, 4)]
    (tmp_path / "edges.txt").write_text("1,2\n1,2\nx,3\n3,4\n")
    assert sorted(tuple(r) for r in tables.edges(spark, str(tmp_path / "edges.txt")).collect()) == [(1, 2), (3, 4)]
    (tmp_path / "baskets.txt").write_text("a b  c\n\nb\n")
    m, names = tables.from_labels(tables.baskets(spark, str(tmp_path / "baskets.txt")), "row", "item")
    assert (m.n_rows, m.n_cols, m.ones.count()) == (2, 3, 4) and names.count() == 3


def test_pool_store(spark, tmp_path):
    rows = spark.createDataFrame([(1, 5), (1, 6), (2, 5)], "tile_id long, row_id long")
    cols = spark.createDataFrame([(1, 0), (2, 0), (2, 1)], "tile_id long, col_id long")
    tables.save_pool(Pool(rows, cols), str(tmp_path / "pool"))
    back = tables.load_pool(spark, str(tmp_path / "pool"))
    for one, other in ((rows, back.tile_rows), (cols, back.tile_cols)):
        assert sorted(tuple(r) for r in one.collect()) == sorted(tuple(r) for r in other.select(*one.columns).collect())


def test_ids_of_any_size_hash_as_in_sql(spark):
    ids = [0, 1, 2**31 - 2, 2**31 - 1, 6_000_000_000, 2**60 + 12345, 2**61 - 2]
    df = spark.createDataFrame([(i,) for i in ids], "id long")
    for prime, some in ((hashing.PRIME, ids), (hashing.LARGE, ids)):
        a, b = prime - 2, prime - 3
        got = [r.h for r in df.select("id", hashing.affine(F.col("id"), a, b, prime).alias("h")).orderBy("id").collect()]
        sql = duckdb.sql(f"SELECT ({a}::HUGEINT * (id::HUGEINT % {prime}) + {b}) % {prime} FROM (SELECT unnest({some}) AS id) ORDER BY id").fetchall()
        assert got == [int(r[0]) for r in sql]
        if prime == hashing.LARGE:
            assert hashing.np_affine(np.array(ids), a, b, prime).tolist() == got
    assert hashing.prime_for(2**31 - 2) == hashing.PRIME and hashing.prime_for(2**31 - 1) == hashing.LARGE


def test_large_ids_give_the_same_picks_both_ways(spark):
    rng = np.random.default_rng(1)
    shift = 6_000_000_000
    rows = [(t, int(r) + shift) for t in range(8) for r in rng.choice(60, 25, False)]
    cols = [(t, int(c)) for t in range(8) for c in rng.choice(40, 12, False)]
    pool = Pool(spark.createDataFrame(rows, "tile_id long, row_id long"), spark.createDataFrame(cols, "tile_id long, col_id long"), dominated=True)
    m = Matrix(pool.cells().select("row_id", "col_id").distinct(), 60, 40)
    local, far = (select.hashed(m, pool, 4, sketch_k=10, reps=3, local_cells=n).select("step", "tile_id", "estimate", "error").collect() for n in (select.LOCAL_CELLS, 0))
    assert local == far and len(local) == 4
    fam = hashing.family(3, 42, hashing.LARGE)
    lists = [sketch.as_array(sketch.build(pool, fam, 10, s), np.arange(8), fam, 10) for s in ("band", "enumerate")]
    assert (lists[0] == lists[1]).all()


def test_race_of_the_methods(spark):
    from tests.test_oracles import SF
    from tilesketch import workloads

    times = workloads._race(spark, SF, budgets=(5,))
    by = {r.method: r for r in times.collect()}
    assert by["greedy"].rel_error == by["recompute"].rel_error and by["hashed"].n_picks <= 5
    assert by["hashed"].n_cells < by["recompute"].n_cells
    assert timing.speed_up(times, slow="recompute").count() == 1
    json.dumps([r.asDict() for r in times.collect()])
