"""Queries against their SQL at the smallest scale, and the stream against the batch."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["order_brand_density", "doc_term_mid_density", "bench_shingle_density", "hashed_exact", "hashed_inexact", "greedy_exact", "greedy_inexact", "static_exact", "static_inexact", "profile", "overlap", "error_path", "itemsets", "closed_itemsets", "assoc_tiles", "sketch_band", "est_joint", "est_union", "syn_tiles", "err_parts", "redesc_pairs", "density", "hashed_tie_id", "hashed_noverify", "hashed_small_modulus", "hashed_cover", "random_order", "sketch_cells", "est_median", "est_accuracy", "score_inexact", "union_matrix", *(n for n in entry.oracle_sql() if n.startswith(("ops_", "stream_")))]


@pytest.fixture(scope="module")
def db():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def plain(v):
    return "nan" if isinstance(v, float) and math.isnan(v) else repr(v)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, db, name):
    ours = entry.queries()[name](spark, SF)
    theirs = db.sql(entry.oracle_sql()[name])
    columns = sorted(ours.columns)
    assert columns == sorted(theirs.columns)
    at = [theirs.columns.index(c) for c in columns]
    assert sorted(tuple(plain(r[c]) for c in columns) for r in ours.collect()) == sorted(tuple(plain(r[i]) for i in at) for r in theirs.fetchall())


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() > 0


def test_running_sketch_equals_the_batch(spark, tmp_path):
    from pyspark.sql import functions as F

    from tilesketch.functions import hashing
    from tilesketch.streaming import events as ev

    spark.read.parquet(f"{SF}/events.parquet").repartition(4).write.parquet(str(tmp_path / "events"))
    fam = hashing.family(1, 3)
    out = {}

    def sink(batch, _):
        out.update({r.key: list(r.hashes) for r in batch.collect()})

    src = ev.events(spark, str(tmp_path / "events")).withColumn("hour", F.floor(F.unix_timestamp("ts") / 3600))
    q = ev.running_sketch(src, "event_type", "hour", "user_id", fam, 5).writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).foreachBatch(sink).start()
    q.awaitTermination()
    ar, br, ac, bc = fam.maps[0]
    batch = spark.read.parquet(f"{SF}/events.parquet").select("event_type", hashing.cell(hashing.affine(F.floor(F.unix_timestamp("ts") / 3600), ar, br), hashing.affine(F.col("user_id"), ac, bc)).alias("h")).groupBy("event_type").agg(F.slice(F.array_sort(F.collect_set("h")), 1, 5).alias("l"))
    assert out == {r.event_type: list(r.l) for r in batch.collect()}
