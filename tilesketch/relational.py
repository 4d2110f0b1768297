"""Relational operators around the methods, one query each, with the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilesketch.sources.tables import table


def range_join(left: DataFrame, right: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """Rows of ``left`` with ``low <= value < high`` of ``right``, as an equi-join on buckets of ``width`` and a filter."""
    at = left.withColumn("__b", F.floor(F.col(value) / width).cast("long"))
    spread = right.withColumn("__b", F.explode(F.sequence(F.floor(F.col(low) / width).cast("long"), F.floor((F.col(high) - 1) / width).cast("long"))))
    return at.join(spread, "__b").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__b")


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str, out: str) -> DataFrame:
    """Each row of ``left(key, time, ...)`` with the last ``value`` of ``right`` at or before it: a union and a window, so
    no pairs are made."""
    every = left.select(key, time, F.struct(*left.columns).alias("__l"), F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__o")).unionByName(right.select(key, time, F.lit(None).cast(left.schema).alias("__l"), F.col(value).alias("__v"), F.lit(0).alias("__o")))
    w = Window.partitionBy(key).orderBy(time, "__o").rowsBetween(Window.unboundedPreceding, 0)
    return every.withColumn(out, F.last("__v", ignorenulls=True).over(w)).where("__l is not null").select("__l.*", out)


def _o(s: SparkSession, d: str, *c: str) -> DataFrame:
    return table(s, d, "orders", *c)


def _ops() -> dict[str, tuple]:
    li = lambda s, d, *c: table(s, d, "lineitem", *c)
    ev = lambda s, d, *c: table(s, d, "events", *c)
    cu = lambda s, d, *c: table(s, d, "customer", *c)
    w = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    n = lambda: F.count(F.lit(1)).alias("n")
    return {
        "ops_project": (lambda s, d: li(s, d, "l_orderkey", "l_quantity", "l_discount").select("l_orderkey", (F.col("l_quantity") * 2).alias("twice"), F.col("l_quantity").cast("long").alias("q")), "SELECT l_orderkey, l_quantity * 2 AS twice, CAST(l_quantity AS BIGINT) AS q FROM lineitem"),
        "ops_filter": (lambda s, d: li(s, d, "l_orderkey", "l_partkey", "l_quantity", "l_returnflag").where("l_quantity >= 45 AND l_returnflag = 'R'"), "SELECT l_orderkey, l_partkey, l_quantity, l_returnflag FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'"),
        "ops_join_hash": (lambda s, d: li(s, d, "l_orderkey").join(_o(s, d, "o_orderkey", "o_orderstatus").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(n()), "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
        "ops_join_merge": (lambda s, d: li(s, d, "l_orderkey").join(_o(s, d, "o_orderkey", "o_custkey").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(n()), "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
        "ops_join_broadcast": (lambda s, d: cu(s, d, "c_custkey", "c_nationkey").join(F.broadcast(table(s, d, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(n()), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"),
        "ops_join_loop": (lambda s, d: table(s, d, "documents", "doc_id", "n_chars").join(F.broadcast(s.createDataFrame([(500,), (2000,), (8000,)], "cut long")), F.col("n_chars") >= F.col("cut")).groupBy("cut").agg(n()), "SELECT cut, count(*) AS n FROM documents JOIN (VALUES (500), (2000), (8000)) t(cut) ON n_chars >= cut GROUP BY 1"),
        "ops_join_range": (lambda s, d: range_join(table(s, d, "documents", "doc_id", "n_chars"), s.range(20).select((F.col("id") * 700).alias("low"), (F.col("id") * 700 + 1000).alias("high")), "n_chars", "low", "high", 500).groupBy("low").agg(n()), "SELECT low, count(*) AS n FROM documents JOIN (SELECT range * 700 AS low, range * 700 + 1000 AS high FROM range(20)) ON n_chars >= low AND n_chars < high GROUP BY 1"),
        "ops_semi": (lambda s, d: _o(s, d, "o_orderkey").join(li(s, d, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi"), "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)"),
        "ops_anti": (lambda s, d: _o(s, d, "o_orderkey").join(li(s, d, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)"),
        "ops_left": (lambda s, d: cu(s, d, "c_custkey").join(_o(s, d, "o_custkey").groupBy("o_custkey").agg(n()), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n")), "SELECT c_custkey, count(o_custkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1"),
        "ops_full": (lambda s, d: table(s, d, "documents", "doc_id").join(table(s, d, "labels", "doc_id", "toxic"), "doc_id", "full").agg(n(), F.count("toxic").alias("labelled")), "SELECT count(*) AS n, count(toxic) AS labelled FROM documents FULL JOIN labels USING (doc_id)"),
        "ops_asof": (lambda s, d: as_of(ev(s, d, "event_id", "user_id", "ts").where("event_id % 2 = 0"), ev(s, d, "user_id", "ts", "value").where("event_id % 2 = 1"), "user_id", "ts", "value", "last_value").select("event_id", "last_value"), "SELECT l.event_id, r.value AS last_value FROM (SELECT * FROM events WHERE event_id % 2 = 0) l ASOF LEFT JOIN (SELECT * FROM events WHERE event_id % 2 = 1) r ON l.user_id = r.user_id AND l.ts >= r.ts"),
        "ops_interval": (lambda s, d: _interval(s, d), "SELECT a.event_id AS a, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000 GROUP BY 1"),
        "ops_agg": (lambda s, d: li(s, d, "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.sum("l_quantity").alias("total"), n(), F.min("l_quantity").alias("low"), F.max("l_quantity").alias("high")), "SELECT l_returnflag, sum(l_quantity) AS total, count(*) AS n, min(l_quantity) AS low, max(l_quantity) AS high FROM lineitem GROUP BY 1"),
        "ops_distinct_agg": (lambda s, d: li(s, d, "l_suppkey", "l_partkey", "l_orderkey").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1"),
        "ops_rollup": (lambda s, d: _brand_segment(s, d).rollup("p_brand", "c_mktsegment").agg(n()), f"SELECT p_brand, c_mktsegment, count(*) AS n FROM ({_BRAND_SEGMENT}) GROUP BY ROLLUP (p_brand, c_mktsegment)"),
        "ops_cube": (lambda s, d: _brand_segment(s, d).cube("p_brand", "c_mktsegment").agg(n(), F.grouping_id().cast("long").alias("g")), f"SELECT p_brand, c_mktsegment, count(*) AS n, CAST(GROUPING(p_brand, c_mktsegment) AS BIGINT) AS g FROM ({_BRAND_SEGMENT}) GROUP BY CUBE (p_brand, c_mktsegment)"),
        "ops_gsets": (lambda s, d: _brand_segment(s, d).groupingSets([[F.col("p_brand")], [F.col("c_mktsegment")]], "p_brand", "c_mktsegment").agg(n()), f"SELECT p_brand, c_mktsegment, count(*) AS n FROM ({_BRAND_SEGMENT}) GROUP BY GROUPING SETS ((p_brand), (c_mktsegment))"),
        "ops_collect": (lambda s, d: li(s, d, "l_orderkey", "l_partkey").groupBy("l_orderkey").agg(F.array_join(F.transform(F.array_sort(F.collect_set("l_partkey")), lambda x: x.cast("string")), ",").alias("basket")), "SELECT l_orderkey, array_to_string(list_sort(list_distinct(list(l_partkey))), ',') AS basket FROM lineitem GROUP BY 1"),
        "ops_order_stats": (lambda s, d: li(s, d, "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.median("l_quantity").alias("mid"), F.percentile("l_quantity", F.lit(0.25)).alias("q1")), "SELECT l_returnflag, median(l_quantity) AS mid, quantile_cont(l_quantity, 0.25) AS q1 FROM lineitem GROUP BY 1"),
        "ops_arg_best": (lambda s, d: _o(s, d, "o_custkey", "o_orderkey", "o_totalprice").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best")), "SELECT o_custkey, arg_max(o_orderkey, {'a': o_totalprice, 'b': o_orderkey}) AS best FROM orders GROUP BY 1"),
        "ops_rank": (lambda s, d: _o(s, d, "o_custkey", "o_orderkey", "o_orderdate").select("o_orderkey", F.row_number().over(w()).alias("i"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderdate")).alias("r"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderdate")).alias("dr")).where("i <= 3"), "SELECT * FROM (SELECT o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS INTEGER) AS i, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS INTEGER) AS r, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS INTEGER) AS dr FROM orders) WHERE i <= 3"),
        "ops_frames": (lambda s, d: _o(s, d, "o_custkey", "o_orderkey", "o_orderdate").select("o_orderkey", F.lag("o_orderkey").over(w()).alias("before"), F.lead("o_orderkey").over(w()).alias("after"), F.count(F.lit(1)).over(w().rowsBetween(-2, 0)).alias("near")), "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"),
        "ops_topk": (lambda s, d: _o(s, d, "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
        "ops_union": (lambda s, d: cu(s, d, "c_nationkey").withColumnRenamed("c_nationkey", "k").unionByName(table(s, d, "supplier", "s_nationkey").withColumnRenamed("s_nationkey", "k")).distinct(), "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier"),
        "ops_intersect": (lambda s, d: cu(s, d, "c_nationkey").intersect(table(s, d, "supplier", "s_nationkey")).withColumnRenamed("c_nationkey", "k"), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier"),
        "ops_except": (lambda s, d: _o(s, d, "o_orderkey").withColumnRenamed("o_orderkey", "k").exceptAll(li(s, d, "l_orderkey").distinct()), "SELECT o_orderkey AS k FROM orders EXCEPT ALL SELECT DISTINCT l_orderkey FROM lineitem"),
        "ops_pivot": (lambda s, d: li(s, d, "l_returnflag", "l_linestatus").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o")), "SELECT l_returnflag, count_if(l_linestatus = 'F') AS f, count_if(l_linestatus = 'O') AS o FROM lineitem GROUP BY 1"),
        "ops_unpivot": (lambda s, d: table(s, d, "labels", "doc_id", "quality", "toxic").unpivot("doc_id", ["quality", "toxic"], "name", "value"), "SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels"),
        "ops_explode": (lambda s, d: table(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("pos", "x")).where("x > 0.3").select("vec_id", "pos"), "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE x > 0.3::FLOAT"),
        "ops_sample": (lambda s, d: _o(s, d, "o_orderkey").where(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 1) == "0"), "SELECT o_orderkey FROM orders WHERE substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 1) = '0'"),
        "ops_string": (lambda s, d: table(s, d, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.upper(F.substring("url", 1, 5)).alias("head"), F.length("url").cast("long").alias("n")), "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, upper(substr(url, 1, 5)) AS head, length(url) AS n FROM pages"),
        "ops_date": (lambda s, d: _o(s, d, "o_orderdate").select(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).groupBy("y", "m").agg(n()), "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY ALL"),
        "ops_math": (lambda s, d: table(s, d, "part", "p_partkey", "p_size").select("p_partkey", F.pmod(F.col("p_partkey"), F.lit(7)).alias("m"), F.floor(F.col("p_size") / 4).alias("f"), F.greatest("p_size", F.lit(10)).alias("g")), "SELECT p_partkey, p_partkey % 7 AS m, CAST(floor(p_size / 4) AS BIGINT) AS f, greatest(p_size, 10) AS g FROM part"),
        "ops_json": (lambda s, d: ev(s, d, "event_id", "props").select("event_id", F.from_json("props", "k int").getField("k").alias("k"), F.get_json_object("props", "$.k").alias("t")), "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, json_extract_string(props, '$.k') AS t FROM events"),
        "ops_map": (lambda s, d: table(s, d, "nation", "n_regionkey", "n_name").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", F.length("n_name").alias("l")))).alias("m")).select("n_regionkey", F.size(F.map_filter("m", lambda k, v: v > 6)).cast("long").alias("long_names")), "SELECT n_regionkey, count_if(length(n_name) > 6) AS long_names FROM nation GROUP BY 1"),
        "ops_array": (lambda s, d: li(s, d, "l_orderkey", "l_partkey").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("a")).select("l_orderkey", F.size(F.filter("a", lambda x: x % 2 == 0)).cast("long").alias("even"), F.aggregate("a", F.lit(0).cast("long"), lambda t, x: t + x).alias("total")), "SELECT l_orderkey, count(DISTINCT l_partkey) FILTER (WHERE l_partkey % 2 = 0) AS even, sum(DISTINCT l_partkey)::BIGINT AS total FROM lineitem GROUP BY 1"),
        "ops_bits": (lambda s, d: li(s, d, "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.bit_or(F.expr("shiftleft(1L, cast(l_partkey % 60 as int))")).alias("b")).select("l_suppkey", F.bit_count("b").cast("long").alias("bits")), "SELECT l_suppkey, CAST(bit_count(bit_or(1::BIGINT << CAST(l_partkey % 60 AS INTEGER))) AS BIGINT) AS bits FROM lineitem GROUP BY 1"),
        "ops_bitmap": (lambda s, d: _bitmap(li(s, d, "l_suppkey", "l_partkey")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1"),
        "ops_sql_functions": (lambda s, d: _sql_functions(s, d), "SELECT n_nationkey, ((17 * CAST(n_nationkey AS BIGINT) + 3) % 2147483647 - (29 * CAST(n_regionkey AS BIGINT) + 5) % 2147483647 + 2147483647) % 2147483647 AS h FROM nation"),
        "stream_windows": (lambda s, d: _stream_windows(s, d), "SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, count(*) AS n_events, count(DISTINCT user_id) AS n_users FROM events GROUP BY 1"),
    }


_BRAND_SEGMENT = "SELECT p_brand, c_mktsegment FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"


def _brand_segment(s: SparkSession, d: str) -> DataFrame:
    li, p = table(s, d, "lineitem", "l_orderkey", "l_partkey"), table(s, d, "part", "p_partkey", "p_brand")
    o, c = table(s, d, "orders", "o_orderkey", "o_custkey"), table(s, d, "customer", "c_custkey", "c_mktsegment")
    return li.join(p, F.col("l_partkey") == F.col("p_partkey")).join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).select("p_brand", "c_mktsegment")


def _interval(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("x"), F.explode(F.array(*((F.floor(F.col("us") / hour) + i) for i in (-1, 0, 1)))).alias("b"))
    b = e.select(F.col("event_id").alias("other"), "user_id", F.col("us").alias("y"), F.floor(F.col("us") / hour).alias("b"))
    return a.join(b, ["user_id", "b"]).where((F.col("a") != F.col("other")) & (F.abs(F.col("x") - F.col("y")) <= hour)).groupBy("a").agg(F.count(F.lit(1)).alias("n"))


def _bitmap(pairs: DataFrame) -> DataFrame:
    """Distinct parts of each supplier; one bitmap holds 32,768 bits, so there is one for each bucket of keys."""
    key = F.col("l_partkey") + 1
    each = pairs.groupBy("l_suppkey", F.bitmap_bucket_number(key).alias("bucket")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position(key))).alias("n"))
    return each.groupBy("l_suppkey").agg(F.sum("n").alias("parts"))


def _sql_functions(s: SparkSession, d: str) -> DataFrame:
    from tilesketch.functions.sql import register

    register(s)
    table(s, d, "nation", "n_nationkey", "n_regionkey").createOrReplaceTempView("tilesketch_nation")
    return s.sql("SELECT n_nationkey, tile_hash(n_nationkey, n_regionkey, 17, 3, 29, 5) AS h FROM tilesketch_nation")


def _stream_windows(s: SparkSession, d: str) -> DataFrame:
    from tilesketch.streaming.events import hourly_counts

    return hourly_counts(s, d)


def queries():
    return {k: v[0] for k, v in _ops().items()}


def oracle_sql() -> dict[str, str]:
    return {k: v[1] for k, v in _ops().items()}
