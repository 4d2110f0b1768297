"""``queries`` and their SQL: methods, variants, baselines, measures and experiment workloads on the given tables."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilesketch import oracles as sql
from tilesketch.functions import estimate, hashing
from tilesketch.functions.sql import bottom_k
from tilesketch.model import Matrix, Pool
from tilesketch.operators import cover, sketch
from tilesketch.operators.candidates import association, itemsets, redescriptions, synthetic
from tilesketch.plans import apps, metrics, select, timing
from tilesketch.session import cut
from tilesketch.sources import tables

K, REPS, SUPPORT, TAU = 10, 3, 0.01, 0.2
FAM = hashing.family(REPS, 42)
SEEDS = [1, 2, 3]
Query = Callable[[SparkSession, str], DataFrame]
TRACE = ("step", "tile_id", "estimate", "gain", "error", "rel_error", "n_checked")


def _brand(spark: SparkSession, d: str) -> tuple[Matrix, Pool]:
    m, _ = tables.matrix(spark, d, "order_brand")
    return m, itemsets.as_pool(m, itemsets.level_itemsets(m, SUPPORT, 2))


def _brand_full(spark: SparkSession, d: str) -> tuple[Matrix, Pool]:
    """Itemsets of every length."""
    m, _ = tables.matrix(spark, d, "order_brand")
    return m, itemsets.as_pool(m, itemsets.level_itemsets(m, SUPPORT, None))


def _embed(spark: SparkSession, d: str, rule: str = "majority") -> tuple[Matrix, Pool]:
    m, _ = tables.matrix(spark, d, "embed_high")
    return m, association.association(m, TAU, rule)


BRAND = [*sql.matrix("order_brand"), *sql.pair_pool(SUPPORT)]
EMBED = [*sql.matrix("embed_high"), *sql.association_pool(TAU)]
EMBED_ALL = [*sql.matrix("embed_high"), *sql.association_pool(TAU, "all")]


def _with(head: list[str], tail: str, *more: str) -> str:
    return f"WITH {', '.join([*head, *more])} {tail}"


def _first_picks(pool: Pool, n: int) -> Pool:
    ids = pool.tile_rows.select("tile_id").distinct().orderBy("tile_id").limit(n)
    return pool.only(ids)


def _grid(spark: SparkSession, d: str, use: str = "orig", noise: float = 0.1, density: float = 0.3, move: float = 0.1, shape: tuple[int, int] = (100, 120), seed: int = 1, originals: int = 20, how: str = "crossed") -> tuple[Matrix, Pool]:
    rows, cols = synthetic.grid(spark, d, *shape)
    return synthetic.planted(rows, cols, originals, 5, density, move, use, noise, seed, how=how)


def _grid_sql(use: str = "orig", noise: float = 0.1, density: float = 0.3, move: float = 0.1, seed: int = 1, originals: int = 20) -> list[str]:
    p = synthetic.calibrate(density, originals, 5, move, use)
    return sql.planted(100, 120, originals, 5, p, move, use, noise, seed)


def _views(spark: SparkSession, d: str):
    docs = tables.table(spark, d, "documents", "doc_id", "lang", "source", "n_chars")
    left = redescriptions.predicates(docs, "doc_id", {"n_chars": [500.0, 1000.0, 2000.0, 4000.0]}, ("lang", "source"))
    terms, band = tables.doc_band(spark, d, 0.05, 0.6)
    if band is not None:
        return left, terms.select("row_id", F.explode("items").alias("item")).join(band, "item", "left_semi").select(F.concat(F.lit("has "), "item").alias("pred"), F.col("row_id").alias("entity_id"))
    return left, cut(terms.select(F.transform("items", lambda x: F.concat(F.lit("has "), x)).alias("preds"), F.col("row_id").alias("entity_id")))


def _pred_names(left: DataFrame, right: DataFrame) -> DataFrame:
    """``col_id, pred`` of both views."""
    own = right.select("pred") if "pred" in right.columns else right.select(F.explode("preds").alias("pred"))
    return tables.dictionary(left.select("pred").unionByName(own), "pred", "col_id")


_LEFT = "lefts AS (SELECT doc_id AS entity_id, unnest(list_filter([{0}], lambda x: x IS NOT NULL)) AS pred FROM documents)".format(", ".join([*(f"CASE WHEN n_chars {op} {c} THEN 'n_chars {op} {c}' END" for c in (500, 1000, 2000, 4000) for op in (">=", "<")), "'lang = ' || lang", "'source = ' || source"]))
_REDESC = [*sql.matrix("doc_term_mid")[:1], _LEFT, "rights AS (SELECT DISTINCT row_id AS entity_id, 'has ' || item AS pred FROM pairs)", "sl AS (SELECT pred, count(*) AS n FROM lefts GROUP BY pred)", "sr AS (SELECT pred, count(*) AS n FROM rights GROUP BY pred)", "found AS (SELECT l.pred AS q_left, r.pred AS q_right, any_value(sl.n) AS supp_left, any_value(sr.n) AS supp_right, count(*) AS supp_both FROM lefts l JOIN rights r USING (entity_id) JOIN sl ON sl.pred = l.pred JOIN sr ON sr.pred = r.pred GROUP BY ALL)"]


def _redescriptions(spark: SparkSession, d: str) -> DataFrame:
    return redescriptions.redescriptions(*_views(spark, d), 0.4, 20)


def _redescription_set(spark: SparkSession, d: str, method: str = "hashed", most: int | None = None) -> DataFrame:
    left, right = _views(spark, d)
    left = left.unionByName(redescriptions.predicates(tables.table(spark, d, "labels", "doc_id", "quality", "toxic"), "doc_id", {}, ("quality", "toxic")))
    names = _pred_names(left, right)
    n_rows, n_cols = tables.table(spark, d, "documents").count(), names.count()
    trace, _, _ = apps.redescription_set(left, right, names, n_rows, n_cols, 0.4, 50, most, None, method)
    return trace


def _union_matrix(spark: SparkSession, d: str) -> DataFrame:
    left, right = _views(spark, d)
    names = _pred_names(left, right)
    both = redescriptions.met(left, right)
    pool = redescriptions.as_pool(cut(redescriptions.best_pairs(redescriptions.redescriptions(left, right, 0.4, 20, both), 40)), left, right, names, both)
    return metrics.density(redescriptions.union_matrix(pool, tables.table(spark, d, "documents").count(), names.count()))


def _sketch_rows(lists: DataFrame) -> DataFrame:
    return lists.select("tile_id", F.posexplode("hashes").alias("rep", "h")).select("tile_id", "rep", F.posexplode("h").alias("place", "h"))


_SKETCH_SQL = _with([*BRAND, *sql.CELLS], "SELECT tile_id, CAST(rep AS INTEGER) AS rep, CAST(row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) - 1 AS INTEGER) AS place, h FROM low", sql.lists(FAM, K))


def _sweep(values: list, one: Callable[[object], DataFrame], name: str) -> DataFrame:
    out = None
    for v in values:
        df = one(v).select(F.lit(str(v)).alias(name), "*")
        out = df if out is None else out.unionByName(df)
    return out


def _compare(m: Matrix, pool: Pool, inexact: bool, budget: int = 200) -> DataFrame:
    """The last error of the three methods, and static's best."""
    mode = "inexact" if inexact else "exact"
    end = lambda t, name: t.agg(F.lit(name).alias("method"), F.count(F.lit(1)).alias("n_picks"), F.max_by("rel_error", "step").alias("rel_error"), F.min("rel_error").alias("best_error"))
    hashed = end(select.hashed(m, pool, budget, mode=mode), "hashed")
    return hashed.unionByName(end(select.greedy(m, pool, budget), "greedy")).unionByName(end(select.static_rank(m, pool, budget), "static"))


FULL = {"shape": (1000, 1200), "originals": 100}
SIZES = [1000, 2000, 3000, 4000]
INEXACT = ("inexact_orig", "inexact_all")
CASES = {"inexact_orig": ("orig", 0.1, True), "inexact_all": ("all", 0.1, True), "exact_all": ("all", 0.0, False)}


def _experiment(spark: SparkSession, d: str, name: str, values: list, cases=("inexact_orig", "inexact_all", "exact_all")) -> DataFrame:
    out = None
    for case in cases:
        use, noise, inexact = CASES[case]
        for v in values:
            given = FULL | {"use": use, "noise": noise} | ({"shape": (int(v), int(v) + 200)} if name == "size" else {name: v})
            df = _compare(*_grid(spark, d, **given), inexact).select(F.lit(case).alias("case"), F.lit(float(v)).alias(name), "*")
            out = df if out is None else out.unionByName(df)
    return out


def _hyper(spark: SparkSession, d: str) -> DataFrame:
    m, pool = _grid(spark, d, use="all", noise=0.1, density=0.06, **FULL)
    grid = [("sketch_k", v) for v in (5, 10, 20, 30, 50, 100)] + [("reps", v) for v in (1, 3, 5, 10, 20, 30)] + [("max_checks", v) for v in (1, 5, 10, 30, 50, 100)]
    out = None
    for name, v in grid:
        began = time.monotonic()
        t = select.hashed(m, pool, 200, mode="inexact", **{name: v})
        took = time.monotonic() - began
        t = t.agg(F.lit(name).alias("parameter"), F.lit(v).alias("value"), F.count(F.lit(1)).alias("n_picks"), F.max_by("rel_error", "step").alias("rel_error"), F.lit(took).alias("seconds"))
        out = t if out is None else out.unionByName(t)
    return out


def _times(spark: SparkSession, d: str, budgets=(10, 25, 50, 100, 200), sizes=SIZES) -> DataFrame:
    """Seconds of the three methods against the number of picks and against the size of the matrix."""
    made = {}
    out = []
    for axis, v in [("picks", b) for b in budgets] + [("size", x) for x in sizes]:
        x = v if axis == "size" else 1000
        if x not in made:
            made = {x: _grid(spark, d, **(FULL | {"shape": (x, x + 200)}))}
        m, pool = made[x]
        budget = v if axis == "picks" else 200
        for name, run in (("hashed", lambda: select.hashed(m, pool, budget, mode="inexact")), ("greedy", lambda: select.greedy(m, pool, budget)), ("static", lambda: select.static_rank(m, pool, budget))):
            began = time.monotonic()
            n = len(run().collect())
            out.append((axis, v, name, n, time.monotonic() - began))
    return spark.createDataFrame(out, "axis string, value int, method string, n_picks int, seconds double")


def _race(spark: SparkSession, d: str, name: str = "embed_high", tau: float = 0.3, budgets: tuple[int, ...] = (50, 200)) -> DataFrame:
    """The three methods and the greedy one that scores every tile anew, over one prepared state."""
    m, _ = tables.matrix(spark, d, name)
    return timing.race(m, association.association(m, tau), budgets)


def _wider(spark: SparkSession, d: str) -> Matrix:
    """Terms of at least five documents."""
    return tables.from_labels(tables.doc_term_band(spark, d, 0.0, 1.0, 5), "row_id", "item")[0]


def full_queries() -> dict[str, Query]:
    """The methods with every itemset, the default budget of 200 picks and the default sketches; too slow for SQL."""
    hashed = lambda make, **o: lambda s, d: select.hashed(*make(s, d), **o).select(*TRACE)
    greedy = lambda make, **o: lambda s, d: select.greedy(*make(s, d), **o).select("step", "tile_id", "gain", "error", "rel_error")
    brand = lambda s, d: tables.matrix(s, d, "order_brand")[0]
    return {
        "hashed_exact_full": hashed(_brand_full),
        "hashed_exact_distributed_full": hashed(_brand_full, local_cells=0),
        "hashed_inexact_full": hashed(_embed, mode="inexact"),
        "hashed_stop_full": hashed(_embed, mode="inexact", on_fail="stop"),
        "hashed_noverify_full": hashed(_brand_full, verify=False),
        "hashed_small_modulus_full": hashed(_embed, mode="inexact", prime=10007),
        "hashed_tie_id_full": hashed(_brand_full, tie="id"),
        "hashed_cover_full": hashed(_nations, goal="cover"),
        "hashed_concat_full": hashed(_brand_full, merge="concat"),
        "hashed_discard_full": hashed(_embed, mode="inexact", small="discard"),
        "hashed_shared_zeros_full": hashed(_embed, mode="inexact", zero_penalty="sketched"),
        "hashed_cells_full": hashed(lambda s, d: (_embed(s, d)[0], _union_pool(_embed(s, d)[1])), mode="inexact"),
        "restarts_full": lambda s, d: select.restarts(*_brand_full(s, d), seeds=[1, 2, 3]),
        "greedy_exact_full": greedy(_brand_full),
        "greedy_exact_distributed_full": greedy(_brand_full, local_cells=0),
        "greedy_recompute_full": greedy(_brand_full, incremental=False),
        "greedy_lazy_full": greedy(_brand_full, lazy=True),
        "greedy_inexact_full": greedy(_embed),
        "setcover_full": lambda s, d: _setcover(s, d, goal="cover"),
        "itemsets_full": lambda s, d: _itemset_rows(itemsets.itemsets(brand(s, d), SUPPORT)),
        "itemsets_levels_full": lambda s, d: _itemset_rows(itemsets.level_itemsets(brand(s, d), SUPPORT, None)),
        "itemset_rows_full": lambda s, d: _brand_full(s, d)[1].tile_rows.select("tile_id", "row_id"),
        "closed_itemsets_full": lambda s, d: _itemset_rows(itemsets.closed(itemsets.itemsets(brand(s, d), SUPPORT))),
        "maximal_itemsets_full": lambda s, d: _itemset_rows(itemsets.maximal(itemsets.itemsets(brand(s, d), SUPPORT))),
    }


def queries() -> dict[str, Query]:
    q: dict[str, Query] = {}
    for name in tables.BINARIZERS:
        q[f"{name}_density"] = lambda s, d, name=name: metrics.density(tables.matrix(s, d, name)[0])
    q["density"] = q["embed_high_density"]
    trace = lambda t: t.select(*TRACE)
    plain = lambda t: t.select("step", "tile_id", "gain", "error", "rel_error")
    small = {"max_tiles": 4, "sketch_k": K, "reps": REPS}
    q |= {
        "hashed_exact": lambda s, d: trace(select.hashed(*_brand(s, d), **small)),
        "hashed_exact_distributed": lambda s, d: trace(select.hashed(*_brand(s, d), **small, local_cells=0)),
        "hashed_inexact": lambda s, d: trace(select.hashed(*_embed(s, d), **small, mode="inexact")),
        "sel_inexact_budget": lambda s, d: trace(select.hashed(*_embed(s, d), **(small | {"max_tiles": 2}), mode="inexact")),
        "hashed_stop": lambda s, d: trace(select.hashed(*_embed(s, d), **small, mode="inexact", on_fail="stop")),
        "hashed_noverify": lambda s, d: trace(select.hashed(*_brand(s, d), **small, verify=False)),
        "hashed_small_modulus": lambda s, d: trace(select.hashed(*_embed(s, d), **small, mode="inexact", prime=10007)),
        "hashed_tie_id": lambda s, d: trace(select.hashed(*_brand(s, d), **small, tie="id")),
        "hashed_cover": lambda s, d: plain(select.hashed(*_nations(s, d), sketch_k=K, reps=REPS, goal="cover")),
        "hashed_concat": lambda s, d: trace(select.hashed(*_brand(s, d), **small, merge="concat")),
        "hashed_discard": lambda s, d: trace(select.hashed(*_embed(s, d), **small, mode="inexact", small="discard")),
        "hashed_cells": lambda s, d: trace(_hashed_cells(s, d, **small)),
        "restarts": lambda s, d: select.restarts(*_brand(s, d), seeds=SEEDS, **small),
        "greedy_exact": lambda s, d: plain(select.greedy(*_brand(s, d), max_tiles=4)),
        "greedy_exact_distributed": lambda s, d: plain(select.greedy(*_brand(s, d), max_tiles=4, local_cells=0)),
        "greedy_recompute": lambda s, d: plain(select.greedy(*_brand(s, d), max_tiles=4, incremental=False)),
        "greedy_lazy": lambda s, d: plain(select.greedy(*_brand(s, d), max_tiles=4, lazy=True)),
        "greedy_inexact": lambda s, d: plain(select.greedy(*_embed(s, d), max_tiles=4)),
        "greedy_cover": lambda s, d: plain(select.greedy(*_nations(s, d), goal="cover")),
        "full_cover": lambda s, d: select.greedy(*_nations(s, d), goal="cover").agg(F.count(F.lit(1)).alias("n_picks"), F.min("error").alias("error")),
        "rank_bound": lambda s, d: apps.boolean_rank_bound(*_nations(s, d)),
        "static_exact": lambda s, d: select.static_rank(*_brand(s, d), max_tiles=20),
        "static_inexact": lambda s, d: select.static_rank(*_embed(s, d), max_tiles=10),
        "static_best": lambda s, d: metrics.best_prefix(select.static_rank(*_embed(s, d), max_tiles=10)),
        "marginal_gain": lambda s, d: metrics.marginal_gain(select.static_rank(*_brand(s, d), max_tiles=20)),
        "random_order": lambda s, d: select.random_order(*_embed(s, d), max_tiles=5),
        "brute_force": lambda s, d: _brute(s, d),
        "setcover": lambda s, d: _setcover(s, d),
        "err_exact": lambda s, d: _on_first(s, d, _brand, cover.exact_error),
        "err_inexact": lambda s, d: _on_first(s, d, _embed, cover.error),
        "err_parts": lambda s, d: _on_first(s, d, _embed, cover.error_parts),
        "rel_error": lambda s, d: _on_first(s, d, _brand, cover.error),
        "err_exact_pool": lambda s, d: cover.exact_error(*_brand(s, d)),
        "err_inexact_pool": lambda s, d: cover.error(*_embed(s, d)),
        "err_parts_pool": lambda s, d: cover.error_parts(*_embed(s, d)),
        "rel_error_pool": lambda s, d: cover.error(*_brand(s, d)),
        "error_path_pool": lambda s, d: _error_path_pool(s, d),
        "dominated": lambda s, d: cover.dominated(*_embed(s, d)),
        "coverable": lambda s, d: cover.coverable(*_brand(s, d)),
        "profile": lambda s, d: cover.profile(*_embed(s, d)),
        "overlap": lambda s, d: cover.overlap(_embed(s, d)[1]),
        "singletons": lambda s, d: _singletons(s, d),
        "cells_pool": lambda s, d: _cells_pool(s, d),
        "error_path": lambda s, d: _error_path(s, d),
        "itemsets": lambda s, d: _itemset_rows(itemsets.itemsets(tables.matrix(s, d, "order_brand")[0], SUPPORT, 2)),
        "itemsets_levels": lambda s, d: _itemset_rows(itemsets.level_itemsets(tables.matrix(s, d, "order_brand")[0], SUPPORT, 2)),
        "itemset_rows": lambda s, d: _brand(s, d)[1].tile_rows.select("tile_id", "row_id"),
        "closed_itemsets": lambda s, d: _itemset_rows(itemsets.closed(itemsets.level_itemsets(tables.matrix(s, d, "order_brand")[0], SUPPORT, 2))),
        "maximal_itemsets": lambda s, d: _itemset_rows(itemsets.maximal(itemsets.level_itemsets(tables.matrix(s, d, "order_brand")[0], SUPPORT, 2))),
        "closed_itemsets_pages": lambda s, d: _itemset_rows(itemsets.closed(itemsets.level_itemsets(tables.matrix(s, d, "page_token")[0], 0.3, 2))),
        "maximal_itemsets_pages": lambda s, d: _itemset_rows(itemsets.maximal(itemsets.level_itemsets(tables.matrix(s, d, "page_token")[0], 0.3, 2))),
        "itemset_support": lambda s, d: metrics.support(*_brand(s, d)),
        "assoc_tiles_all_pages": lambda s, d: association.association(tables.matrix(s, d, "page_token")[0], 0.8, "all").tile_rows.select("tile_id", "row_id"),
        "assoc_rows": lambda s, d: association.association(tables.matrix(s, d, "nation_region")[0], 0.5, axis="rows").tile_cols.select("tile_id", "col_id"),
        "assoc_cols": lambda s, d: association.association_columns(tables.matrix(s, d, "embed_high")[0], TAU),
        "assoc_tiles": lambda s, d: _embed(s, d)[1].tile_rows.select("tile_id", "row_id"),
        "assoc_tiles_all": lambda s, d: _embed(s, d, "all")[1].tile_rows.select("tile_id", "row_id"),
        "walk_tiles": lambda s, d: association.restart_walk(tables.matrix(s, d, "embed_high")[0]).tile_cols.select("tile_id", "col_id"),
        "redesc_pairs": _redescriptions,
        "union_matrix": _union_matrix,
        "query_pair": lambda s, d: _query_pair(s, d),
        "bottom_k": lambda s, d: _bottom_k(s, d),
        "redesc_tiles": lambda s, d: redescriptions.best_pairs(_redescriptions(s, d), 40),
        "hash_axis": lambda s, d: tables.matrix(s, d, "nation_region")[0].ones.select("row_id", "col_id", *(hashing.affine(F.col("row_id"), ar, br).alias(f"r{i}") for i, (ar, br, _, _) in enumerate(FAM.maps))),
        "hash_cell": lambda s, d: tables.matrix(s, d, "nation_region")[0].ones.select("row_id", "col_id", *(hashing.cell(hashing.affine(F.col("row_id"), ar, br), hashing.affine(F.col("col_id"), ac, bc)).alias(f"h{i}") for i, (ar, br, ac, bc) in enumerate(FAM.maps))),
        "sketch_band": lambda s, d: _sketch_rows(sketch.build(_brand(s, d)[1], FAM, K, "band")),
        "sketch_walk": lambda s, d: _sketch_rows(sketch.build(_brand(s, d)[1], FAM, K, "walk")),
        "sketch_enum": lambda s, d: _sketch_rows(sketch.build(_brand(s, d)[1], FAM, K, "enumerate")),
        "sketch_cells": lambda s, d: _sketch_rows(sketch.build(_union_pool(_embed(s, d)[1]), FAM, K)),
        "sketch_cutoff": lambda s, d: _sketch_rows(sketch.build(_brand(s, d)[1], FAM, K, "band", 10_000_000)),
        "est_tile": lambda s, d: _estimates(s, d, "k"),
        "est_km1": lambda s, d: _estimates(s, d, "k-1"),
        "est_median": lambda s, d: _spread(s, d),
        "est_union": lambda s, d: metrics.union_size(sketch.build(_brand(s, d)[1], FAM, K), K, REPS),
        "est_joint": lambda s, d: _joint(s, d),
        "score_inexact": lambda s, d: _inexact_scores(s, d),
        "small_tiles": lambda s, d: _small(s, d),
        "suggest_k": lambda s, d: s.createDataFrame([(sketch.suggest_k(_brand(s, d)[1]),)], "k int"),
        "est_accuracy": lambda s, d: metrics.estimate_accuracy(_brand(s, d)[1]),
        "est_builtin": lambda s, d: metrics.builtin_sizes(_brand(s, d)[1], "hll", theta="theta"),
        "bool_product": lambda s, d: _product(s, d),
        "syn_tiles": lambda s, d: _syn(s, d),
        "syn_copies": lambda s, d: _grid(s, d, noise=0.0)[1].tile_rows.groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_r")),
        "syn_noise": lambda s, d: metrics.density(_grid(s, d)[0]),
        "syn_noise_drawn": lambda s, d: metrics.density(_grid(s, d, how="drawn")[0]),
        "syn_density": lambda s, d: metrics.density(_grid(s, d, noise=0.0)[0]),
        "syn_exact": lambda s, d: cover.coverable(*_grid(s, d, use="all", noise=0.0)),
        "planted_hits": lambda s, d: metrics.planted_precision(select.greedy(*_grid(s, d), max_tiles=20), s.range(20).select(F.col("id").alias("tile_id"))),
        "avg_runs": lambda s, d: metrics.average_runs(_sweep([1, 2, 3], lambda v: select.greedy(*_grid(s, d, seed=v), max_tiles=20).agg(F.lit("greedy").alias("method"), F.min("rel_error").alias("rel_error")), "seed"), "method"),
        "w1_hyperparameters": _hyper,
        "w2_overlap": lambda s, d: _experiment(s, d, "move", [0.05, 0.1, 0.25, 0.5]),
        "w3_density": lambda s, d: _experiment(s, d, "density", [0.06, 0.1, 0.15, 0.2, 0.25, 0.3, 0.4]),
        "w4_noise": lambda s, d: _experiment(s, d, "noise", [0.05, 0.1, 0.2, 0.3], INEXACT),
        "w5_size": lambda s, d: _experiment(s, d, "size", SIZES, INEXACT),
        "w6_time": _times,
        "w6_race": _race,
        "w6_race_terms": lambda s, d: _race(s, d, "doc_term_mid", 0.5),
        "w6_race_wide": lambda s, d: _race(s, d, "doc_term_wide", 0.5),
        "w6_speed_up": lambda s, d: timing.speed_up(_race(s, d), slow="recompute"),
        "cost_counters": lambda s, d: timing.costs(select.hashed(*_embed(s, d), mode="inexact")),
        "w7_redesc": lambda s, d: _redescription_set(s, d).select("step", "q_left", "q_right", "gain", "error"),
        "w8_tiling": lambda s, d: plain(apps.tiling(tables.matrix(s, d, "doc_term_all")[0], 0.3, 1000)[0]),
        "w8_tiling_brand": lambda s, d: plain(apps.tiling(tables.matrix(s, d, "order_brand")[0], SUPPORT, 1000)[0]),
        "w9_bmf": lambda s, d: plain(apps.factorize(tables.matrix(s, d, "embed_high")[0], 200, (0.3, 0.5, 0.7, 0.9))[0]),
        "w9_bmf_terms": lambda s, d: plain(apps.factorize(tables.matrix(s, d, "doc_term_mid")[0], 200, (0.3, 0.5, 0.7, 0.9))[0]),
        "w10_sparse_corpus": lambda s, d: plain(apps.factorize(tables.matrix(s, d, "doc_term_wide")[0], 200, (0.5,), walks=False)[0]),
        "w10_sparse_corpus_larger": lambda s, d: plain(apps.factorize(_wider(s, d), 200, (0.5,), walks=False)[0]),
        "w12_contamination": lambda s, d: tables.matrix(s, d, "bench_shingle")[0].ones.groupBy("col_id").agg(F.count(F.lit(1)).alias("n_items")),
    }
    from tilesketch.relational import queries as more

    return q | full_queries() | more()


def _on_first(spark, d, make, measure):
    m, pool = make(spark, d)
    return measure(m, _first_picks(pool, 3))


def _nations(spark, d):
    m, _ = tables.matrix(spark, d, "nation_region")
    return m, itemsets.as_pool(m, itemsets.level_itemsets(m, 0.0, 1))


def _brute(spark, d):
    """The best three of the 15 tiles that cover most alone, the most that brute force takes."""
    m, pool = _brand(spark, d)
    return select.brute_force(m, pool.only(select.static_rank(m, pool, 15).select("tile_id")), 3)


def _hashed_cells(spark, d, **options):
    m, pool = _embed(spark, d)
    return select.hashed(m, _union_pool(pool), mode="inexact", **options)


def _query_pair(spark, d):
    """Rows and columns of one pair of queries: long documents, and those that labels call good."""
    docs, labels = tables.table(spark, d, "documents", "doc_id", "n_chars"), tables.table(spark, d, "labels", "doc_id", "quality")
    return redescriptions.from_query_pair(docs, "n_chars >= 1000", [0], labels, "quality = 1", [0], "doc_id", offset=1).cells()


def _bottom_k(spark, d):
    """The lowest hashes of the users of each type of event."""
    ar, br, _, _ = FAM.maps[0]
    e = tables.table(spark, d, "events", "event_type", "user_id").select("event_type", hashing.affine(F.col("user_id"), ar, br).alias("h"))
    return bottom_k(e, "h", K, "event_type").select("event_type", F.array_join(F.transform("lowest", lambda h: h.cast("string")), ",").alias("lowest"))


def _setcover(spark, d, **options):
    s = tables.table(spark, d, "lineitem", "l_suppkey", "l_partkey").select(F.col("l_suppkey").alias("set_id"), F.col("l_partkey").alias("element"))
    return select.greedy(*itemsets.from_sets(s), **(options or {"max_tiles": 4})).select("step", "tile_id", "gain", "error")


def _singletons(spark, d):
    m, pool = _embed(spark, d)
    both = itemsets.add_singletons(pool, m)
    return both.tiles().where("tile_id < 0").select("tile_id", "n_r", "size")


def _union_pool(pool: Pool) -> Pool:
    """Patterns that are no outer product: the cells of tile i and of the next id together."""
    cells = pool.cells()
    moved = cells.select((F.col("tile_id") - 1).alias("tile_id"), "row_id", "col_id").join(cells.select("tile_id").distinct(), "tile_id", "left_semi")
    return Pool(tile_cells=cells.unionByName(moved).distinct())


def _cells_pool(spark, d):
    m, pool = _embed(spark, d)
    return cover.profile(m, _union_pool(pool)).select("tile_id", "size", "ones", "zeros")


def _error_path(spark, d):
    m, pool = _brand(spark, d)
    order = pool.tile_rows.select("tile_id").distinct().where("tile_id < 100").select("tile_id", F.col("tile_id").cast("int").alias("step"))
    return cover.error_path(m, pool.only(order.select("tile_id")), order)


def _error_path_pool(spark, d):
    """The path over the whole pool, in the order of ids."""
    m, pool = _brand(spark, d)
    ids = pool.tile_rows.select("tile_id").distinct()
    return cover.error_path(m, pool, ids.select("tile_id", F.row_number().over(Window.orderBy("tile_id")).alias("step")))


def _itemset_rows(sets):
    return sets.select("tile_id", F.array_join(F.transform("items", lambda x: x.cast("string")), ",").alias("items"), "support")


def _estimates(spark, d, kind):
    lists = sketch.build(_brand(spark, d)[1], FAM, K)
    return lists.select("tile_id", estimate.median_of(F.transform("hashes", lambda h: estimate.size(h, K, estimator=kind))).alias("estimate"))


def _spread(spark, d):
    """The median over the repetitions beside the extremes that it is robust to."""
    sizes = F.transform("hashes", lambda h: estimate.size(h, K))
    return sketch.build(_brand(spark, d)[1], FAM, K).select("tile_id", F.array_min(sizes).alias("least"), estimate.median_of(sizes).alias("median"), F.array_max(sizes).alias("most"))


def _inexact_scores(spark, d):
    """Each tile's joint size with the tile of the least id, less the zeros of its own."""
    m, pool = _embed(spark, d)
    lists = sketch.build(pool, FAM, K)
    first = lists.agg(F.min_by("hashes", "tile_id").alias("q"), F.min("tile_id").alias("first"))
    zeros = cover.profile(m, pool).select("tile_id", "zeros")
    return lists.join(zeros, "tile_id").join(F.broadcast(first), F.col("tile_id") > F.col("first")).select("tile_id", (estimate.score(F.col("q"), F.col("hashes"), K) - F.col("zeros")).alias("score"))


def _joint(spark, d):
    lists = sketch.build(_brand(spark, d)[1], FAM, K)
    first = lists.where("tile_id = 1").select(F.col("hashes").alias("q"))
    return lists.where("tile_id <> 1").join(F.broadcast(first), F.lit(True)).select("tile_id", estimate.score(F.col("q"), F.col("hashes"), K).alias("estimate"))


def _small(spark, d):
    m, _ = tables.matrix(spark, d, "nation_region")
    lists = sketch.build(itemsets.as_pool(m, itemsets.level_itemsets(m, 0.0, 1)), FAM, K)
    one = lambda kind: estimate.median_of(F.transform("hashes", lambda h: estimate.size(h, K, small=kind)))
    return lists.select("tile_id", one("exact").alias("exact"), one("discard").alias("discard"))


def _product(spark, d):
    _, pool = _embed(spark, d)
    return apps.boolean_product(pool.tile_rows, pool.tile_cols).agg(F.count(F.lit(1)).alias("n_cells"), F.countDistinct("row_id").alias("n_rows"))


def _syn(spark, d):
    rows, cols = synthetic.grid(spark, d, 100, 120)
    u = synthetic.vectors(rows, 20, 0.13, 1, "r").groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_r"))
    return u.join(synthetic.vectors(cols, 20, 0.13, 1, "c").groupBy("tile_id").agg(F.count(F.lit(1)).alias("n_c")), "tile_id", "full").select("tile_id", "n_r", "n_c")


def oracle_sql() -> dict[str, str]:
    """SQL for the queries above."""
    o = {f"{name}_density": sql.density(name) for name in sql.PAIRS}
    brand3 = "three AS (SELECT * FROM cells WHERE tile_id IN (SELECT DISTINCT tile_id FROM trows ORDER BY tile_id LIMIT 3))"
    union = "u AS (SELECT DISTINCT row_id, col_id, w FROM cells)"
    union3 = "u AS (SELECT DISTINCT row_id, col_id, w FROM three)"
    parts = "SELECT (SELECT n_ones FROM shape) - count_if(w = 1) AS uncovered_ones, count_if(w = -1) AS covered_zeros FROM u"
    whole = "SELECT uncovered_ones + covered_zeros AS error, (uncovered_ones + covered_zeros) / (SELECT n_rows * n_cols FROM shape) AS rel_error FROM ({})"
    nations = [*sql.matrix("nation_region"), *sql.pair_pool(0.0, False)]
    est = lambda k: f"SELECT tile_id, median(e) AS estimate FROM (SELECT tile_id, rep, CASE WHEN count(*) < {K} THEN count(*)::DOUBLE ELSE {float(k)}::DOUBLE / ((max(h) + 1) / {float(FAM.prime)}::DOUBLE) END AS e FROM low GROUP BY tile_id, rep) GROUP BY tile_id"
    hash_at = lambda side, i: f"({FAM.maps[i][0 if side == 'r' else 2]}::BIGINT * {'row_id' if side == 'r' else 'col_id'} + {FAM.maps[i][1 if side == 'r' else 3]}) % {FAM.prime}"
    sets = "SELECT tile_id, i || CASE WHEN j IS NULL THEN '' ELSE ',' || j END AS items, support FROM sets"
    o |= {
        "hashed_exact": sql.hashed(BRAND, FAM, K, 4, 30, False),
        "hashed_inexact": sql.hashed(EMBED, FAM, K, 4, 30, True),
        "sel_inexact_budget": sql.hashed(EMBED, FAM, K, 2, 30, True),
        "hashed_stop": sql.hashed(EMBED, FAM, K, 4, 1, True),
        "greedy_exact": sql.greedy(BRAND, 4),
        "greedy_inexact": sql.greedy(EMBED, 4),
        "static_exact": sql.static(BRAND, 20),
        "static_inexact": sql.static(EMBED, 10),
        "static_best": f"SELECT CAST(step AS INTEGER) AS best_step, error AS best_error FROM ({sql.static(EMBED, 10)}) ORDER BY error, step LIMIT 1",
        "marginal_gain": f"SELECT step, error, lag(error) OVER (ORDER BY step) - error AS lowered FROM ({sql.static(BRAND, 20)})",
        "greedy_cover": sql.greedy(nations, 5),
        "full_cover": f"SELECT count(*) AS n_picks, min(error) AS error FROM ({sql.greedy(nations, 5)})",
        "rank_bound": f"SELECT count(*) AS rank_bound FROM ({sql.greedy(nations, 5)})",
        "setcover": f"SELECT step, tile_id, gain, error FROM ({sql.greedy(['ones AS (SELECT DISTINCT l_partkey AS row_id, 0 AS col_id FROM lineitem)', 'shape AS (SELECT count(*) AS n_rows, 1 AS n_cols, count(*) AS n_ones FROM ones)', 'trows AS (SELECT DISTINCT l_suppkey AS tile_id, l_partkey AS row_id FROM lineitem)', 'tcols AS (SELECT DISTINCT l_suppkey AS tile_id, 0 AS col_id FROM lineitem)'], 4)})",
        "err_exact": _with([*BRAND, *sql.CELLS], "SELECT (SELECT n_ones FROM shape) - count(*) AS error FROM u", brand3, union3),
        "err_parts": _with([*EMBED, *sql.CELLS], parts, brand3, union3),
        "err_inexact": _with([*EMBED, *sql.CELLS], whole.format(parts), brand3, union3),
        "rel_error": _with([*BRAND, *sql.CELLS], whole.format(parts), brand3, union3),
        "err_exact_pool": _with([*BRAND, *sql.CELLS], "SELECT (SELECT n_ones FROM shape) - count(*) AS error FROM u", union),
        "err_parts_pool": _with([*EMBED, *sql.CELLS], parts, union),
        "err_inexact_pool": _with([*EMBED, *sql.CELLS], whole.format(parts), union),
        "rel_error_pool": _with([*BRAND, *sql.CELLS], whole.format(parts), union),
        "error_path_pool": _with([*BRAND, *sql.CELLS], "SELECT CAST(step AS INTEGER) AS step, error::BIGINT AS error, error / (SELECT n_rows * n_cols FROM shape) AS rel_error FROM (SELECT step, (SELECT n_ones FROM shape) - sum(coalesce(g, 0)) OVER (ORDER BY step) AS error FROM steps LEFT JOIN gains USING (tile_id))", "steps AS (SELECT tile_id, row_number() OVER (ORDER BY tile_id) AS step FROM (SELECT DISTINCT tile_id FROM trows))", "gains AS (SELECT tile_id, sum(w) AS g FROM (SELECT min(tile_id) AS tile_id, any_value(w) AS w FROM cells GROUP BY row_id, col_id) GROUP BY tile_id)"),
        "dominated": _with([*EMBED, *sql.CELLS], "SELECT tile_id, zeros = 0 AS is_dominated FROM alone"),
        "coverable": _with([*BRAND, *sql.CELLS], "SELECT n AS missing, n = 0 AS coverable FROM (SELECT count(*) AS n FROM ones ANTI JOIN cells USING (row_id, col_id))"),
        "profile": _with([*EMBED, *sql.CELLS], "SELECT tile_id, count(DISTINCT row_id) AS n_r, count(DISTINCT col_id) AS n_c, count(*) AS size, count_if(w = 1) AS ones, count_if(w = -1) AS zeros FROM cells GROUP BY tile_id"),
        "overlap": _with([*EMBED, *sql.CELLS], "SELECT a.tile_id AS tile_a, b.tile_id AS tile_b, count(*) AS shared FROM cells a JOIN cells b USING (row_id, col_id) WHERE a.tile_id < b.tile_id GROUP BY ALL"),
        "singletons": _with(sql.matrix("embed_high"), "SELECT -col_id - 1 AS tile_id, count(*) AS n_r, count(*) AS size FROM ones GROUP BY col_id"),
        "cells_pool": _with([*EMBED, *sql.CELLS], "SELECT tile_id, count(*) AS size, count_if(w = 1) AS ones, count_if(w = -1) AS zeros FROM (SELECT tile_id, row_id, col_id, w FROM cells UNION SELECT tile_id - 1, row_id, col_id, w FROM cells WHERE tile_id - 1 IN (SELECT tile_id FROM cells)) GROUP BY tile_id"),
        "error_path": _with([*BRAND, *sql.CELLS], "SELECT CAST(tile_id AS INTEGER) AS step, ((SELECT n_ones FROM shape) - sum(coalesce(g, 0)) OVER (ORDER BY tile_id))::BIGINT AS error, ((SELECT n_ones FROM shape) - sum(coalesce(g, 0)) OVER (ORDER BY tile_id)) / (SELECT n_rows * n_cols FROM shape) AS rel_error FROM (SELECT DISTINCT tile_id FROM trows WHERE tile_id < 100) LEFT JOIN (SELECT tile_id, sum(w) AS g FROM (SELECT min(tile_id) AS tile_id, any_value(w) AS w FROM cells WHERE tile_id < 100 GROUP BY row_id, col_id) GROUP BY tile_id) USING (tile_id)"),
        "itemsets": _with(BRAND, sets),
        "itemsets_levels": _with(BRAND, sets),
        "itemset_rows": _with(BRAND, "SELECT tile_id, row_id FROM trows"),
        "closed_itemsets": _with(BRAND, sets + " s WHERE j IS NOT NULL OR NOT EXISTS (SELECT 1 FROM sets t WHERE t.j IS NOT NULL AND (t.i = s.i OR t.j = s.i) AND t.support = s.support)"),
        "maximal_itemsets": _with(BRAND, sets + " s WHERE j IS NOT NULL OR NOT EXISTS (SELECT 1 FROM sets t WHERE t.j IS NOT NULL AND (t.i = s.i OR t.j = s.i))"),
        "assoc_cols": _with(EMBED, "SELECT tile_id, col_id FROM acols"),
        "assoc_tiles": _with(EMBED, "SELECT tile_id, row_id FROM trows"),
        "assoc_tiles_all": _with(EMBED_ALL, "SELECT tile_id, row_id FROM trows"),
        "redesc_pairs": _with(_REDESC, "SELECT *, supp_both / (supp_left + supp_right - supp_both) AS jaccard FROM found WHERE supp_both >= 20 AND supp_both / (supp_left + supp_right - supp_both) >= 0.4"),
        "redesc_tiles": _with(_REDESC, "SELECT *, supp_both / (supp_left + supp_right - supp_both) AS jaccard, row_number() OVER (ORDER BY supp_both / (supp_left + supp_right - supp_both) DESC, q_left, q_right) AS tile_id FROM found WHERE supp_both >= 20 AND supp_both / (supp_left + supp_right - supp_both) >= 0.4 QUALIFY tile_id <= 40"),
        "hash_axis": _with(sql.matrix("nation_region"), f"SELECT row_id, col_id, {', '.join(f'{hash_at("r", i)} AS r{i}' for i in range(REPS))} FROM ones"),
        "hash_cell": _with(sql.matrix("nation_region"), f"SELECT row_id, col_id, {', '.join(f'({hash_at("r", i)} - {hash_at("c", i)} + {FAM.prime}) % {FAM.prime} AS h{i}' for i in range(REPS))} FROM ones"),
        "sketch_band": _SKETCH_SQL,
        "sketch_walk": _SKETCH_SQL,
        "sketch_enum": _SKETCH_SQL,
        "sketch_cutoff": _with([*BRAND, *sql.CELLS], "SELECT tile_id, CAST(rep AS INTEGER) AS rep, CAST(row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) - 1 AS INTEGER) AS place, h FROM low", sql.lists(FAM, K, 10_000_000)),
        "est_tile": _with([*BRAND, *sql.CELLS], est(K), sql.lists(FAM, K)),
        "est_km1": _with([*BRAND, *sql.CELLS], est(K - 1), sql.lists(FAM, K)),
        "est_union": _with([*BRAND, *sql.CELLS], f"SELECT median(e) AS estimate FROM (SELECT rep, {sql._size(K, FAM.prime)} AS e FROM (SELECT *, row_number() OVER (PARTITION BY rep ORDER BY h) AS n FROM (SELECT DISTINCT rep, h FROM low)) WHERE n <= {K} GROUP BY rep)", sql.lists(FAM, K)),
        "est_joint": _with([*BRAND, *sql.CELLS], f"SELECT tile_id, median(e) AS estimate FROM (SELECT tile_id, rep, {sql._size(K, FAM.prime)} AS e FROM (SELECT *, row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) AS n FROM (SELECT tile_id, rep, h FROM low WHERE tile_id <> 1 UNION SELECT t.tile_id, q.rep, q.h FROM (SELECT DISTINCT tile_id FROM low WHERE tile_id <> 1) t CROSS JOIN (SELECT rep, h FROM low WHERE tile_id = 1) q)) WHERE n <= {K} GROUP BY tile_id, rep) GROUP BY tile_id", sql.lists(FAM, K)),
        "small_tiles": _with([*nations, *sql.CELLS], f"SELECT tile_id, size::DOUBLE AS exact, CASE WHEN size < {K} THEN NULL::DOUBLE END AS discard FROM alone"),
        "bool_product": _with([*EMBED, *sql.CELLS], "SELECT count(*) AS n_cells, count(DISTINCT row_id) AS n_rows FROM (SELECT DISTINCT row_id, col_id FROM cells)"),
        "syn_tiles": "WITH r AS (SELECT DISTINCT o_orderkey AS id FROM orders ORDER BY 1 LIMIT 100), c AS (SELECT DISTINCT p_partkey AS id FROM part ORDER BY 1 LIMIT 120), t AS (SELECT range AS tile_id FROM range(20)), u AS (SELECT tile_id, count(*) AS n_r FROM t CROSS JOIN r WHERE ('0x' || substr(md5('1|r|' || tile_id || '|' || id), 1, 13))::BIGINT / 4503599627370496.0::DOUBLE < 0.13 GROUP BY 1), v AS (SELECT tile_id, count(*) AS n_c FROM t CROSS JOIN c WHERE ('0x' || substr(md5('1|c|' || tile_id || '|' || id), 1, 13))::BIGINT / 4503599627370496.0::DOUBLE < 0.13 GROUP BY 1) SELECT tile_id, n_r, n_c FROM u FULL JOIN v USING (tile_id)",
        "w12_contamination": _with(sql.matrix("bench_shingle"), "SELECT col_id, count(*) AS n_items FROM ones GROUP BY col_id"),
    }
    top = f"top AS ({o['redesc_tiles'].split(_REDESC[-1], 1)[1].strip()})"
    per_rep = f"SELECT tile_id, rep, {sql._size(K, FAM.prime)} AS e FROM low GROUP BY tile_id, rep"
    wide = hashing.family(10, 42)
    hashed_cells = sql.lists(FAM, K).replace("FROM cells CROSS JOIN", "FROM joined CROSS JOIN")
    joined = "joined AS (SELECT tile_id, row_id, col_id FROM cells UNION SELECT tile_id - 1, row_id, col_id FROM cells WHERE tile_id - 1 IN (SELECT tile_id FROM cells))"
    o |= {
        "density": o["embed_high_density"],
        "hashed_tie_id": sql.hashed(BRAND, FAM, K, 4, 30, False, tie=""),
        "hashed_noverify": sql.hashed(BRAND, FAM, K, 4, 1, False, verify=False),
        "hashed_small_modulus": sql.hashed(EMBED, hashing.family(REPS, 42, 10007), K, 4, 30, True),
        "hashed_cover": f"SELECT step, tile_id, gain, error, rel_error FROM ({sql.hashed(nations, FAM, K, 5, 30, False)})",
        "random_order": sql.static(EMBED, 5, "('0x' || substr(md5('1|' || tile_id), 1, 13))::BIGINT, tile_id"),
        "sketch_cells": _with([*EMBED, *sql.CELLS], "SELECT tile_id, CAST(rep AS INTEGER) AS rep, CAST(row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) - 1 AS INTEGER) AS place, h FROM low", joined, hashed_cells),
        "est_median": _with([*BRAND, *sql.CELLS], f"SELECT tile_id, min(e) AS least, median(e) AS median, max(e) AS most FROM ({per_rep}) GROUP BY tile_id", sql.lists(FAM, K)),
        "est_accuracy": _with([*BRAND, *sql.CELLS], f"SELECT tile_id, estimate, size, estimate / size AS ratio FROM (SELECT tile_id, median(e) AS estimate FROM (SELECT tile_id, rep, {sql._size(30, wide.prime)} AS e FROM low GROUP BY tile_id, rep) GROUP BY tile_id) JOIN alone USING (tile_id)", sql.lists(wide, 30)),
        "score_inexact": _with([*EMBED, *sql.CELLS], f"SELECT tile_id, median(e) - any_value(zeros) AS score FROM (SELECT tile_id, rep, {sql._size(K, FAM.prime)} AS e FROM (SELECT *, row_number() OVER (PARTITION BY tile_id, rep ORDER BY h) AS n FROM (SELECT tile_id, rep, h FROM low WHERE tile_id > f UNION SELECT t.tile_id, q.rep, q.h FROM (SELECT DISTINCT tile_id FROM low WHERE tile_id > f) t CROSS JOIN (SELECT rep, h FROM low WHERE tile_id = f) q)) WHERE n <= {K} GROUP BY tile_id, rep) JOIN alone USING (tile_id) GROUP BY tile_id".replace("tile_id > f", "tile_id > (SELECT min(tile_id) FROM low)").replace("tile_id = f", "tile_id = (SELECT min(tile_id) FROM low)"), sql.lists(FAM, K)),
        "union_matrix": _with(_REDESC, "SELECT n_rows, n_cols, n_ones, n_ones / (n_rows * n_cols) AS density FROM (SELECT (SELECT count(*) FROM documents) AS n_rows, (SELECT count(*) FROM (SELECT pred FROM lefts UNION SELECT pred FROM rights)) AS n_cols, count(*) AS n_ones FROM both_hold)", top, "both_hold AS (SELECT DISTINCT l.entity_id, unnest([q_left, q_right]) AS pred FROM top JOIN lefts l ON l.pred = q_left JOIN rights r ON r.pred = q_right AND r.entity_id = l.entity_id)"),
    }
    noisy, clean = _grid_sql(), _grid_sql(noise=0.0)
    shown = "SELECT n_rows, n_cols, n_ones, n_ones / (n_rows * n_cols) AS density FROM shape"
    pages = [*sql.matrix("page_token"), *sql.pair_pool(0.3)]
    ends = [sql.hashed(BRAND, hashing.family(REPS, s), K, 4, 30, False) for s in SEEDS]
    runs = " UNION ALL ".join(f"SELECT min(rel_error) AS rel_error FROM ({sql.greedy(_grid_sql(seed=s), 20)})" for s in SEEDS)
    one_item = " s WHERE j IS NOT NULL OR NOT EXISTS (SELECT 1 FROM sets t WHERE t.j IS NOT NULL AND (t.i = s.i OR t.j = s.i)"
    o |= {
        "hashed_concat": sql.hashed(BRAND, FAM, K, 4, 30, False, union=False),
        "hashed_discard": sql.hashed(EMBED, FAM, K, 4, 30, True, discard=True),
        "hashed_cells": sql.hashed(EMBED, FAM, K, 4, 30, True, cells=sql.union_cells()),
        "restarts": " UNION ALL ".join(f"SELECT {s} AS seed, max(step) AS n_picks, max_by(error, step) AS error, max_by(rel_error, step) AS rel_error FROM ({end})" for s, end in zip(SEEDS, ends, strict=True)),
        "closed_itemsets_pages": _with(pages, sets + one_item + " AND t.support = s.support)"),
        "maximal_itemsets_pages": _with(pages, sets + one_item + ")"),
        "itemset_support": _with(BRAND, "SELECT tile_id, count(*) AS n_r, count(*) / any_value(n_rows) AS support FROM trows CROSS JOIN shape GROUP BY tile_id"),
        "assoc_tiles_all_pages": _with([*sql.matrix("page_token"), *sql.association_pool(0.8, "all")], "SELECT tile_id, row_id FROM trows"),
        "assoc_rows": _with([sql.matrix("nation_region")[0], sql.matrix("nation_region")[1], "real AS (SELECT row_id, col_id FROM pairs JOIN dict USING (item))", "ones AS (SELECT col_id AS row_id, row_id AS col_id FROM real)", *sql.association_pool(0.5)], "SELECT tile_id, row_id AS col_id FROM trows"),
        "query_pair": "SELECT 1::BIGINT AS tile_id, doc_id AS row_id, c AS col_id FROM documents CROSS JOIN (SELECT unnest([0, 1])::BIGINT AS c) WHERE n_chars >= 1000 AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)",
        "bottom_k": f"SELECT event_type, string_agg(h, ',' ORDER BY h) AS lowest FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY h) AS n FROM (SELECT DISTINCT event_type, ({FAM.maps[0][0]}::BIGINT * user_id + {FAM.maps[0][1]}) % {FAM.prime} AS h FROM events)) WHERE n <= {K} GROUP BY event_type",
        "suggest_k": _with([*BRAND, *sql.CELLS], "SELECT CAST(greatest(10, least(100, quantile_disc(size, 0.1))) AS INTEGER) AS k FROM alone"),
        "syn_copies": _with(clean, "SELECT tile_id, count(*) AS n_r FROM trows GROUP BY tile_id"),
        "syn_noise": _with(noisy, shown),
        "syn_density": _with(clean, shown),
        "syn_exact": _with([*_grid_sql("all", 0.0), *sql.CELLS], "SELECT n AS missing, n = 0 AS coverable FROM (SELECT count(*) AS n FROM ones ANTI JOIN cells USING (row_id, col_id))"),
        "planted_hits": f"SELECT count(*) AS n_picks, count_if(tile_id < 20) AS n_planted, count_if(tile_id < 20) / count(*) AS share FROM ({sql.greedy(noisy, 20)})",
        "avg_runs": f"SELECT 'greedy' AS method, count(*) AS n_runs, avg(rel_error) AS mean_error, stddev_samp(rel_error) AS sd_error FROM ({runs})",
    }
    o["hashed_exact_distributed"] = o["hashed_exact"]
    o |= {f"greedy_{x}": o["greedy_exact"] for x in ("exact_distributed", "recompute", "lazy")}
    from tilesketch.relational import oracle_sql as more

    return o | more()
