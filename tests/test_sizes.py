"""Queries that failed at larger sizes: what they hold on the driver, and cases that only larger keys meet."""

from pyspark.sql import functions as F

from tests.test_oracles import SF


def test_hours_of_a_stream_leave_no_cells_on_the_driver(spark, tmp_path):
    from tilesketch.streaming.events import hourly_counts

    e = spark.read.parquet(f"{SF}/events.parquet")
    e.repartition(4).write.parquet(str(tmp_path / "events.parquet"))
    want = {tuple(r) for r in e.groupBy(F.floor(F.unix_timestamp("ts") / 3600).alias("h")).agg(F.count(F.lit(1)), F.countDistinct("user_id")).collect()}
    held = {t.name for t in spark.catalog.listTables()}
    assert {tuple(r) for r in hourly_counts(spark, str(tmp_path)).collect()} == want
    assert {t.name for t in spark.catalog.listTables()} == held
    assert {tuple(r) for r in hourly_counts(spark, str(tmp_path), max_files=1).collect()} == want


def test_bitmap_of_keys_in_several_buckets(spark):
    from tilesketch.relational import _bitmap

    pairs = spark.createDataFrame([(1, 5), (1, 5 + 32768), (1, 5 + 65536), (1, 5), (2, 0), (2, 32767), (2, 32768)], "l_suppkey long, l_partkey long")
    assert {(r.l_suppkey, r.parts) for r in _bitmap(pairs).collect()} == {(1, 3), (2, 3)}


def test_itemsets_are_chosen_by_classes_of_rows(spark):
    from tilesketch import workloads
    from tilesketch.functions import hashing
    from tilesketch.model import Pool
    from tilesketch.operators import sketch
    from tilesketch.operators.candidates import itemsets
    from tilesketch.plans import select

    m, pool = workloads._brand_full(spark, SF)
    rows = pool.tile_rows.count()
    plain = Pool(pool.tile_rows, pool.tile_cols, dominated=True)
    fam = hashing.family(2, 7)
    lists = lambda df: {r.tile_id: r.hashes for r in df.collect()}
    assert lists(sketch.build(pool, fam, 5)) == lists(sketch.build(plain, fam, 5, "enumerate"))
    assert lists(sketch.build(pool, fam, 5, cutoff=1000)) == lists(sketch.build(plain, fam, 5, "enumerate", 1000))
    assert {tuple(r) for r in pool.tiles().collect()} == {tuple(r) for r in plain.tiles().collect()}
    picks = lambda t: [tuple(r) for r in t.select("step", "tile_id", "estimate", "gain", "error", "rel_error", "n_checked").orderBy("step").collect()]
    want = picks(select.greedy(m, plain))
    for o in ({}, {"incremental": False}, {"lazy": True}):
        assert [x[:6] for x in picks(select.greedy(m, pool, **o))] == [x[:6] for x in want]
    assert picks(select.greedy(m, pool, 3, local_cells=0)) == [(*x[:6], 0) for x in want[:3]]
    for o in ({}, {"merge": "concat"}, {"tie": "id"}):
        assert picks(select.hashed(m, pool, 8, 10, 3, **o)) == picks(select.hashed(m, plain, 8, 10, 3, strategy="band", **o))
    # what the exact state holds is one row of each class, here and in a copy of the table with many times the rows
    state = select._state(m, pool)
    assert len(state.row_ids) == m.ones.groupBy("row_id").agg(F.array_sort(F.collect_list("col_id")).alias("i")).select("i").distinct().count()
    assert sum(len(r) for r in state.rows) < rows and select._fits(m, pool, 200_000)
    few = itemsets.as_pool(m, itemsets.level_itemsets(m, 0.05, 1).where("support < 10000").orderBy("tile_id").limit(3))
    assert few.tile_rows.count() == sum(r.n_r for r in few.tiles().collect())
    assert picks(select.greedy(m, few, 2))[0][4] == m.ones.count() - max(r.size for r in few.tiles().collect())


def test_builtin_sketches_take_one_pass(spark):
    from tilesketch import workloads
    from tilesketch.plans import metrics

    _, pool = workloads._brand(spark, SF)
    both = {r.tile_id: r.theta for r in metrics.builtin_sizes(pool, "hll", theta="theta").collect()}
    assert both == {r.tile_id: r.estimate for r in metrics.builtin_sizes(pool, "theta").collect()}


def test_many_sets_fit_the_driver_by_their_entries(spark):
    import numpy as np

    from tilesketch.operators.candidates import itemsets
    from tilesketch.plans import select

    rng = np.random.default_rng(3)
    pairs = {(int(s), int(e)) for s, e in zip(rng.integers(0, 400, 1200), rng.integers(0, 400, 1200), strict=True)}
    m, pool = itemsets.from_sets(spark.createDataFrame(sorted(pairs), "set_id long, element long"))
    assert select._fits(m, pool, 2000)
    got = select.greedy(m, pool, goal="cover", local_cells=2000).orderBy("step").collect()
    held, open_ = {}, {e for _, e in pairs}
    for s, e in pairs:
        held.setdefault(s, set()).add(e)
    for r in got:
        best = min(held, key=lambda s: (-len(held[s] & open_), s))
        assert (r.tile_id, r.gain) == (best, len(held[best] & open_))
        open_ -= held[best]
    assert not open_


def test_losses_by_lists_and_by_tables_are_the_gains(spark):
    import numpy as np

    from tilesketch.model import Matrix, Pool
    from tilesketch.plans import select

    rng = np.random.default_rng(5)
    frame = lambda a, names: spark.createDataFrame([tuple(map(int, x)) for x in a], ", ".join(f"{n} long" for n in names))
    for share in (0.05, 0.6):
        m = Matrix(frame(np.argwhere(rng.random((30, 12)) < 0.5), ("row_id", "col_id")), 30, 12)
        rows, cols = rng.random((20, 30)) < share, rng.random((20, 12)) < 0.5
        rows[:, 0] = cols[:, 0] = True
        state = select.LocalState(m, Pool(frame(np.argwhere(rows), ("tile_id", "row_id")), frame(np.argwhere(cols), ("tile_id", "col_id"))))
        gains = state.alone.copy()
        for i in (3, 7, 11):
            gains = gains - state.losses(i, state.pick(i))
            assert gains.tolist() == state.all_gains().tolist()


def test_association_by_counts_is_the_join(spark, monkeypatch):
    from tilesketch.model import Matrix
    from tilesketch.operators.candidates import association
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "embed_high")
    got = lambda df: {tuple(r) for r in df.collect()}
    plans = []
    for wide, counts in ((association.WIDE, 200), (0, 0)):
        monkeypatch.setattr(association, "WIDE", wide)
        monkeypatch.setattr(association, "COUNTS", counts)
        cols = association.association_columns(Matrix(m.ones, m.n_rows, m.n_cols), 0.2).cache()
        n = cols.count()
        monkeypatch.setattr(association, "COUNTS", n if counts else 0)
        rows = [association.rows_for(Matrix(m.ones, m.n_rows, m.n_cols), cols, rule) for rule in ("majority", "all")]
        plans.append((got(cols), *map(got, rows)))
    assert plans[0] == plans[1] and plans[0][1] and "MapInArrow" in association._rows_by_counts(m, cols, "all")._jdf.queryExecution().toString()


def test_race_runs_once_to_the_largest_budget(spark):
    from tilesketch.operators.candidates import association
    from tilesketch.plans import select, timing
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "embed_high")
    pool = association.association(m, 0.2)
    rows = {(r.method, r.budget): r for r in timing.race(m, pool, (2, 6)).collect()}
    for budget in (2, 6):
        want = select.greedy(m, pool, budget).orderBy("step").collect()
        for method in ("greedy", "recompute"):
            assert (rows[method, budget].n_picks, rows[method, budget].rel_error) == (len(want), want[-1].rel_error)
    assert all(rows[x, 2].select_s <= rows[x, 6].select_s and rows[x, 2].n_cells <= rows[x, 6].n_cells for x, _ in rows)


def test_labelled_pairs_are_run_once(spark, tmp_path):
    from tilesketch.sources import tables

    (tmp_path / "runs").mkdir()

    def noted(batches, at=str(tmp_path / "runs")):
        import uuid

        open(f"{at}/{uuid.uuid4().hex}", "w").close()
        yield from batches

    rows = [(1, "b"), (1, "a"), (1, "a"), (2, "c"), (None, "d"), (3, None), (2, "ä")]
    pairs = spark.createDataFrame(rows, "r long, item string").coalesce(1).mapInArrow(noted, "r long, item string")
    m, names = tables.from_labels(pairs, "r", "item")
    assert sorted(map(tuple, names.collect())) == [(0, "a"), (1, "b"), (2, "c"), (3, "d"), (4, "ä")]
    assert sorted(map(tuple, m.ones.collect())) == [(1, 0), (1, 1), (2, 2), (2, 4)] and (m.n_rows, m.n_cols) == (2, 4)
    assert len(list((tmp_path / "runs").iterdir())) == 1


def test_lists_of_many_itemsets_come_from_their_low_cells(spark, monkeypatch):
    from tilesketch.functions import hashing
    from tilesketch.model import Pool
    from tilesketch.operators import baskets, sketch
    from tilesketch.operators.candidates import itemsets
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "doc_term_all")
    sets = itemsets.itemsets(m, 0.4)
    assert {(tuple(r["items"]), r.support) for r in sets.collect()} == {(tuple(r["items"]), r.support) for r in itemsets.level_itemsets(m, 0.4, None).collect()}
    pool = itemsets.as_pool(m, sets)
    assert sets.count() > 20 and max(len(r["items"]) for r in pool.used().collect()) <= pool.sides()[1].size < m.n_cols
    fam = hashing.family(3, 5)
    lists = lambda df: {r.tile_id: r.hashes for r in df.collect()}
    want = lists(sketch.build(Pool(pool.tile_rows, pool.tile_cols, dominated=True), fam, 6, "enumerate"))
    assert lists(sketch.build(pool, fam, 6)) == want
    cells = spark.sparkContext.accumulator(0)
    whole = baskets._fullest
    monkeypatch.setattr(baskets, "_fullest", lambda *a: (lambda f: lambda t: (cells.add(t.num_rows), f(t))[1])(whole(*a)))
    assert lists(sketch.build(pool, fam, 6)) == want and 0 < cells.value < 3 * 6 * sets.count()
    monkeypatch.setattr(baskets, "_fullest", whole)
    monkeypatch.setattr(baskets, "PART", 40)
    monkeypatch.setattr(baskets, "TABLE", 50)
    assert lists(baskets.lists(pool, fam, 6, slack=0.5)) == want


def test_recomputed_gains_weigh_equal_rows(spark):
    from tilesketch.model import Matrix
    from tilesketch.operators.candidates import itemsets
    from tilesketch.plans import select

    pairs = [(r, c) for r in range(60) for c in ((0, 1, 2) if r % 3 else (1, 3))]
    m = Matrix(spark.createDataFrame(pairs, "row_id long, col_id long"), 60, 4)
    state = select._state(m, itemsets.as_pool(m, itemsets.level_itemsets(m, 0.1, None)))
    assert state.all_gains().tolist() == state.alone.tolist() == [state.gain(i) for i in range(len(state.ids))]
    state.pick(0)
    assert state.all_gains().tolist() == [state.gain(i) for i in range(len(state.ids))]


def test_redescriptions_are_chosen_by_bitmaps(spark, monkeypatch):
    from tilesketch import workloads
    from tilesketch.model import Matrix, Pool
    from tilesketch.operators.candidates import redescriptions
    from tilesketch.plans import select

    left, right = workloads._views(spark, SF)
    both = redescriptions.met(left, right)
    found = redescriptions.redescriptions(left, right, 0.4, 20, both)
    pairs = redescriptions.best_pairs(found, 30).cache()
    pool = redescriptions.as_pool(pairs, left, right, workloads._pred_names(left, right), both)
    m = redescriptions.union_matrix(pool, 200, 1000)
    plain_pool = Pool(pool.tile_rows, pool.tile_cols, dominated=True)
    plain_matrix = Matrix(m.ones, m.n_rows, m.n_cols)
    assert isinstance(select._state(m, pool), select.PackedState) and not isinstance(select._state(plain_matrix, plain_pool), select.PackedState)
    picks = lambda t: [tuple(r) for r in t.select("step", "tile_id", "estimate", "gain", "error", "rel_error", "n_checked").orderBy("step").collect()]
    for o in ({}, {"sketch_k": 5, "reps": 3, "cutoff": 10**8}, {"merge": "concat"}):
        assert picks(select.hashed(m, pool, **o)) == picks(select.hashed(plain_matrix, plain_pool, **o))
    for o in ({}, {"incremental": False}, {"lazy": True}):
        assert picks(select.greedy(m, pool, **o)) == picks(select.greedy(plain_matrix, plain_pool, **o))
    # rows beyond what a table of rows and columns may take still fit as bits
    assert select._fits(m, pool, 2000) and not select._fits(plain_matrix, plain_pool, 2000)
    exploded = right.select(F.explode("preds").alias("pred"), "entity_id")
    want = sorted(map(tuple, found.collect()))
    monkeypatch.setattr(redescriptions, "PAIRS", 100)
    assert sorted(map(tuple, redescriptions.redescriptions(left, exploded, 0.4, 20).collect())) == want and want


def test_labels_of_few_keys_are_the_bits_of_a_row(spark, monkeypatch):
    from tilesketch.operators.baskets import classes, few_classes
    from tilesketch.sources import tables

    facts = spark.createDataFrame([(1, 10), (1, 11), (1, 10), (2, 12), (2, 13), (3, 99), (4, None), (None, 14), (5, 14), (5, 10), (6, 10), (7, 10)], "row_id long, key int")
    few = [(10, "b"), (10, "b"), (11, "a"), (12, "é"), (13, None), (14, "a"), (15, "unused"), (None, "c")]
    stray = [(10, "b"), (11, "a"), (12, "d"), (14, "null row only"), (14, "a")]
    many = [(10 + i % 5, f"x{i}") for i in range(70)]
    classed = lambda m: {(tuple(r["items"]), r.n) for r in classes(m).collect()}
    for keys in (few, stray, many, []):
        keys = spark.createDataFrame(keys, "key int, item string")
        want, names = tables.from_labels(facts.join(keys, "key").select("row_id", "item"), "row_id", "item")
        for small in (tables.SMALL, 0):
            monkeypatch.setattr(tables, "SMALL", small)
            got, named = tables.from_keys(facts, keys)
            assert (got.n_rows, got.n_cols) == (want.n_rows, want.n_cols)
            assert sorted(got.ones.collect()) == sorted(want.ones.collect())
            assert {tuple(r) for r in named.collect()} == {tuple(r) for r in names.collect()}
            assert classed(got) == classed(want)
            n, held = few_classes(got)
            assert {(tuple(x), int(k)) for x, k in zip(held.to_pylist(), n, strict=True)} == classed(want)
        monkeypatch.undo()


def test_few_classes_are_mined_by_the_driver(spark, monkeypatch):
    from tilesketch.operators import baskets
    from tilesketch.operators.candidates import itemsets
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "order_brand")
    got = lambda **o: {(r.tile_id, tuple(r["items"]), r.support) for r in itemsets.level_itemsets(m, 0.004, **o).collect()}
    asked = []
    monkeypatch.setattr(itemsets, "_mined", lambda *a, mined=itemsets._mined: asked.append(a) or mined(*a))
    whole, pairs = got(max_len=None), got(max_len=2)
    pool = itemsets.as_pool(m, itemsets.level_itemsets(m, 0.004, None))
    supports, ones = pool.supports(), pool.column_counts()
    assert len(asked) == 3 and "classes" not in m.cache  # no table of classes, no worker
    assert {s for _, i, s in whole if len(i) == 1} == set(ones.tolist()) and sorted(supports) == sorted(s for _, _, s in whole)
    monkeypatch.setattr(itemsets, "MOST_READ", 0)
    assert got(max_len=None) == whole
    monkeypatch.setattr(baskets, "SMALL", 0)
    m = tables.matrix(spark, SF, "order_brand")[0]
    m.cache.pop("few classes")
    assert got(max_len=None) == whole and got(max_len=2) == pairs
    plain = itemsets.as_pool(m, itemsets.level_itemsets(m, 0.004, None))
    assert plain.supports().tolist() == supports.tolist() and plain.column_counts().tolist() == ones.tolist()


def test_restarts_sketch_all_seeds_in_one_pass(spark, monkeypatch):
    from tilesketch import workloads
    from tilesketch.operators import sketch
    from tilesketch.plans import select

    m, pool = workloads._brand(spark, SF)
    ends = {s: select.hashed(m, pool, 4, 10, 3, seed=s).orderBy("step").collect()[-1] for s in (1, 2, 3)}
    passes = []
    monkeypatch.setattr(sketch, "itemset_lists", lambda *a, made=sketch.itemset_lists: passes.append(a) or made(*a))
    got = select.restarts(m, pool, [1, 2, 3], max_tiles=4, sketch_k=10, reps=3).collect()
    assert {(r.seed, r.n_picks, r.error, r.rel_error) for r in got} == {(s, r.step, r.error, r.rel_error) for s, r in ends.items()}
    assert len(passes) == 1


def test_sets_are_not_read_for_each_count(spark, monkeypatch):
    from tilesketch.operators.candidates import itemsets
    from tilesketch.plans import select

    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    sets = spark.createDataFrame([(s, e) for s in range(20) for e in range(s, 100, s + 1) for _ in range(1 + e % 2)], "set_id long, element long")
    n, got = sets.count(), []
    for few in (itemsets.FEW_PAIRS, 0):
        monkeypatch.setattr(itemsets, "FEW_PAIRS", few)
        before = read.value
        m, pool = itemsets.from_sets(sets.mapInArrow(counted, sets.schema))
        got.append([r[:6] for r in select.greedy(m, pool, goal="cover").orderBy("step").collect()])
        assert read.value - before <= 2 * n  # once to count, once to read
        assert m.n_rows == m.ones.count() == 100 and pool.tile_cols.count() == 20
        assert {tuple(r) for r in pool.tile_rows.collect()} == {tuple(r) for r in sets.distinct().collect()}
        assert [r[:6] for r in select.greedy(m, pool, 3, local_cells=0).orderBy("step").collect()] == got[-1][:3]
    assert got[0] == got[1] and got[0][-1][4] == 0


def test_every_redescription_is_a_candidate(spark):
    from tilesketch.plans import apps

    n = 170
    views = [spark.createDataFrame([(f"{side}{i}", 2 * i + x) for i in range(n) for x in (0, 1)], "pred string, entity_id long") for side in "lr"]
    names = spark.createDataFrame([(f"{side}{i}", i + n * (side == "r")) for side in "lr" for i in range(n)], "pred string, col_id long")
    trace, m, _ = apps.redescription_set(*views, names, 2 * n, 2 * n, 0.4, 2)
    steps = trace.orderBy("step").collect()
    assert {(r.q_left, r.q_right) for r in steps} == {(f"l{i}", f"r{i}") for i in range(n)} and steps[-1].error == 0
    assert m.ones.count() == sum(r.gain for r in steps) == 4 * n


def test_association_tiles_are_chosen_by_bitmaps(spark):
    from tilesketch.model import Pool
    from tilesketch.operators.candidates import association
    from tilesketch.plans import select
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "embed_high")
    picks = lambda t: [tuple(r) for r in t.select("step", "tile_id", "estimate", "gain", "error", "rel_error", "n_checked", "n_cells").orderBy("step").collect()]
    one = association.association(m, 0.2)
    for pool in (one, association.joined(one, association.association(m, 0.3), association.restart_walk(m))):
        plain = Pool(pool.tile_rows, pool.tile_cols)
        state, want = select._state(m, pool), select.LocalState(m, plain)
        assert isinstance(state, select.BitState) and state.ids.tolist() == want.ids.tolist()
        # bits of rows, and of the ones and zeros of columns; no table of rows by columns, no entry of a pattern
        words = -(-len(state.row_ids) // 64)
        assert sum(x.nbytes for x in (state.bits, state.open, state.shut)) == 8 * words * (len(state.ids) + 2 * len(state.col_ids)) and not hasattr(state, "w")
        assert (state.alone.tolist(), state.zeros.tolist(), state.size.tolist()) == (want.alone.tolist(), want.zeros.tolist(), want.size.tolist())
        for o in ({}, {"sketch_k": 5, "reps": 3, "cutoff": 10**8}, {"merge": "concat"}):
            assert picks(select.hashed(m, pool, 8, mode="inexact", **o)) == picks(select.hashed(m, plain, 8, mode="inexact", **o))
        gains = state.alone.copy()
        for i in (2, 5, 11):
            lost = state.losses(i, state.pick(i))
            assert lost.tolist() == want.losses(i, want.pick(i)).tolist() and state.error == want.error
            gains = gains - lost
            assert gains.tolist() == state.all_gains().tolist()
        assert select._fits(m, pool, 60_000) and not select._fits(m, plain, 7_000)


def test_walks_over_few_columns_are_the_joins(spark, monkeypatch):
    from tilesketch.operators.candidates import association
    from tilesketch.sources import tables

    for name in ("embed_high", "user_typehour"):
        m, _ = tables.matrix(spark, SF, name)
        few = association.restart_walk_columns(m)
        assert not any(x in few._jdf.queryExecution().toString() for x in ("Join", "Window"))
        monkeypatch.setattr(association, "FEW", 0)
        want = association.restart_walk_columns(m)
        assert {tuple(r) for r in few.collect()} == {tuple(r) for r in want.collect()} and few.count()
        monkeypatch.undo()
    assert association.association_columns(m, 0.2).count() and association._pair_counts(m) is association._pair_counts(m)


def test_many_sets_are_numbered_lists(spark, monkeypatch):
    import numpy as np

    from tilesketch.operators.candidates import itemsets
    from tilesketch.plans import select

    rng = np.random.default_rng(11)
    pairs = {(int(s) * 7 - 90, int(e) * 10**10) for s, e in zip(rng.integers(0, 60, 900), rng.integers(0, 300, 900), strict=True)}
    sets = spark.createDataFrame(sorted(pairs) * 2, "set_id long, element long")
    picks = lambda t: [(r.step, r.tile_id, r.estimate, r.gain, r.error, r.n_checked) for r in t.orderBy("step").collect()]
    runs = []
    for few, block in ((itemsets.FEW_PAIRS, select.BLOCK), (0, select.BLOCK), (0, 100)):
        monkeypatch.setattr(itemsets, "FEW_PAIRS", few)
        monkeypatch.setattr(select, "BLOCK", block)
        m, pool = itemsets.from_sets(sets)
        state = select._state(m, pool)
        assert isinstance(state, select.SetState) == (not few)
        if not few:  # four bytes an entry, and as many for the sets of each element
            state.prepare()
            assert state.flat.nbytes == state.members[1].nbytes == 4 * len(pairs)
        runs.append([picks(select.greedy(m, pool, goal="cover", **o)) for o in ({}, {"lazy": True}, {"incremental": False})] + [picks(select.hashed(m, pool, 6, 5, 3))])
    assert runs[0] == runs[1] == runs[2] and runs[0][0][-1][4] == 0


def test_race_holds_bitmaps(spark, monkeypatch):
    from tilesketch.operators.candidates import association
    from tilesketch.plans import select, timing
    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "embed_high")
    pool = association.association(m, 0.3)
    want = select.LocalState(m, pool)
    log = select._Log(m)
    select.greedy_local(want, log, 5, True, False)
    monkeypatch.setattr(select.LocalState, "__init__", lambda *a: (_ for _ in ()).throw(MemoryError("rows by columns")))
    rows = {r.method: r for r in timing.race(m, pool, (5,)).collect()}
    assert rows["greedy"].rel_error == rows["recompute"].rel_error == log.rows[-1][5] and set(rows) == {"hashed", "greedy", "recompute", "static"}
