"""Queries over whole pools, full budgets and full lengths."""

import duckdb
import pytest

import __spark_entry__ as entry
from tests.test_oracles import SF, TABLES, plain


@pytest.mark.parametrize("name", ["err_exact_pool", "err_inexact_pool", "err_parts_pool", "rel_error_pool", "error_path_pool"])
def test_measures_of_whole_pools(spark, name):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    ours, theirs = entry.queries()[name](spark, SF), c.sql(entry.oracle_sql()[name])
    at = [theirs.columns.index(x) for x in ours.columns]
    got = ours.collect()
    assert sorted(tuple(map(plain, r)) for r in got) == sorted(tuple(plain(r[i]) for i in at) for r in theirs.fetchall())
    if name == "error_path_pool":
        assert len(got) == len(entry.queries()["itemsets"](spark, SF).collect())


def test_brute_force_takes_the_largest_tiles(spark):
    from tilesketch import workloads
    from tilesketch.plans import select

    m, pool = workloads._brand(spark, SF)
    lowest = select.brute_force(m, workloads._first_picks(pool, 10), 3).first()
    assert entry.queries()["brute_force"](spark, SF).first().error < lowest.error


def test_itemsets_of_every_length(spark):
    from itertools import combinations
    from math import ceil

    from tilesketch.sources import tables

    m, _ = tables.matrix(spark, SF, "order_brand")
    held = {}
    for r in m.ones.collect():
        held.setdefault(r.row_id, []).append(r.col_id)
    count = {}
    for items in held.values():
        for n in range(1, len(items) + 1):
            for some in combinations(sorted(items), n):
                count[some] = count.get(some, 0) + 1
    want = {(",".join(map(str, k)), v) for k, v in count.items() if v >= ceil(0.01 * m.n_rows - 1e-9)}
    assert any(k.count(",") == 2 for k, _ in want)
    for name in ("itemsets_full", "itemsets_levels_full"):
        assert {(r["items"], r.support) for r in entry.queries()[name](spark, SF).collect()} == want


def test_full_budgets_go_on_after_four_picks(spark):
    whole = [r.tile_id for r in entry.queries()["greedy_inexact_full"](spark, SF).orderBy("step").collect()]
    assert len(whole) > 4 and whole[:4] == [r.tile_id for r in entry.queries()["greedy_inexact"](spark, SF).orderBy("step").collect()]
    assert entry.queries()["hashed_inexact_full"](spark, SF).count() > 4
    left = entry.queries()["setcover_full"](spark, SF).orderBy("step").collect()
    assert left[-1].error == 0
    assert {f"w{i}_" for i in range(1, 11)} <= {n[: n.index("_") + 1] for n in entry.queries() if n[0] == "w" and "_" in n}
