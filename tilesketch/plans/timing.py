"""Seconds of the selectors, preparation and selection apart, and the speed-up of one over another."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilesketch.functions import hashing
from tilesketch.model import Matrix, Pool
from tilesketch.operators.packed import PackedPool
from tilesketch.plans import select

SCHEMA = "method string, budget int, n_picks int, prepare_s double, select_s double, rel_error double, n_cells long, n_hashes long"


def timed(run) -> tuple[object, float]:
    began = time.monotonic()
    out = run()
    return out, time.monotonic() - began


def race(matrix: Matrix, pool: Pool, budgets: tuple[int, ...] = (50, 200), mode: str = "inexact", sketch_k: int = 30, reps: int = 10, max_checks: int = 30, methods: tuple[str, ...] = ("hashed", "greedy", "recompute", "static")) -> DataFrame:
    """The selectors over the same prepared state, one row a method and budget.  ``prepare_s`` is what a method needs before
    its first pick besides the gain of every tile alone, which all of them start from: lists for the hashed one, tables of
    members for the incremental greedy one.  "recompute" is the greedy one that scores every tile at every pick.  Picks don't depend on the budget, so a method
    runs once, to the largest one, and a smaller budget ends at the time of its last pick."""
    state = (select.BitState if isinstance(pool, PackedPool) else select.LocalState)(matrix, pool)
    fam = hashing.family(reps, 42, hashing.prime_for(max(state.row_ids.max(initial=0), state.col_ids.max(initial=0))))
    start, error = state.start(), state.error
    spark, out = matrix.ones.sparkSession, []
    for method in methods:
        held, prepared = None, 0.0
        if method == "hashed":
            held, prepared = timed(lambda: state.lists(fam, sketch_k, None))
        state.restart(start)
        state.error, state.read = error, 0
        log, most = select._Log(matrix), max(budgets)
        if method == "greedy":
            state.members = None
            _, prepared = timed(state.prepare)
        elif method == "recompute":
            state.prepare()
        began = time.monotonic()
        if method == "hashed":
            select.hashed_local(state, held, log, select.Rules(most, sketch_k, max_checks, mode), fam.prime)
        elif method == "static":
            select.static_local(state, log, most)
        else:
            select.greedy_local(state, log, most, method == "greedy", False)
        ended = time.monotonic()
        for budget in budgets:
            rows = log.rows[:budget]
            took = (log.at[budget - 1] if len(log.rows) >= budget else ended) - began
            end = rows[-1] if rows else (0, 0, None, 0, error, error / matrix.cells, 0, 0, 0, 0)
            work = [sum(r[i] or 0 for r in rows) for i in (8, 9)]
            out.append((method, budget, len(rows), prepared, took, float(end[5]), *map(int, np.array(work, np.int64))))
    return spark.createDataFrame(out, SCHEMA)


def speed_up(times: DataFrame, fast: str = "hashed", slow: str = "greedy") -> DataFrame:
    """``budget, select_speed_up, whole_speed_up``: seconds of the slow method over those of the fast one, without and with
    preparation."""
    side = lambda m, x: times.where(F.col("method") == m).select("budget", F.col("select_s").alias(f"{x}s"), (F.col("select_s") + F.col("prepare_s")).alias(f"{x}w"))
    both = side(fast, "f").join(side(slow, "s"), "budget")
    return both.select("budget", (F.col("ss") / F.col("fs")).alias("select_speed_up"), (F.col("sw") / F.col("fw")).alias("whole_speed_up"))


def costs(trace: DataFrame) -> DataFrame:
    """``step, n_checked, n_cells, n_hashes`` of a trace, summed up to each step."""
    w = Window.partitionBy(F.lit(0)).orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return trace.select("step", *(F.sum(c).over(w).alias(c) for c in ("n_checked", "n_cells", "n_hashes")))
