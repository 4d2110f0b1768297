"""Reading tables, baskets and edge lists, and the matrices that the workloads build from the given tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tilesketch.model import Matrix, Pool, require
from tilesketch.session import cut

WORD = r"[^\p{L}]+"
FEW_LABELS = 10_000  # labels that are looked for in lists
MANY_LABELS = 1_000_000  # labels beyond which rows are numbered by a join
BITS = 63  # labels that the bits of one number stand for
SMALL = 40_000_000  # entries of the table of classes by labels up to which the driver gets them
SENT_KEYS = 2_000_000  # keys with a label that go to every task


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str | None = None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def edges(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """``ones`` from a text file with one ``row,col`` pair a line; lines that are no pair of numbers are passed over."""
    parts = F.split("value", sep)
    return require(spark.read.text(path).select(F.get(parts, F.lit(0)).try_cast("long").alias("row_id"), F.get(parts, F.lit(1)).try_cast("long").alias("col_id")).dropna().distinct(), "ones")


def baskets(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """``(row, item)`` from a text file with one transaction a line; rows are numbered by hash of content and place."""
    lines = spark.read.text(path).select(F.monotonically_increasing_id().alias("row"), F.split("value", sep).alias("items"))
    return lines.select("row", F.explode("items").alias("item")).where("item <> ''")


def dictionary(df: DataFrame, label: str, id_name: str) -> DataFrame:
    """Dense ids of the distinct labels in their order, without a global window: each part of a range sort numbers its own
    rows, and the parts' offsets are summed."""
    labels = df.select(label).where(F.col(label).isNotNull()).distinct().repartitionByRange(F.col(label)).sortWithinPartitions(label)
    numbered = labels.select(label, F.spark_partition_id().alias("__p"), F.monotonically_increasing_id().alias("__m"))
    numbered = cut(numbered)  # ids of partitions hold for one run of a plan only
    numbered = numbered.withColumn("__i", F.col("__m").bitwiseAND(F.lit((1 << 33) - 1)))
    counts = sorted((r["__p"], r["n"]) for r in numbered.groupBy("__p").agg(F.count(F.lit(1)).alias("n")).collect())
    base, total = {}, 0
    for p, n in counts:
        base[p] = total
        total += n
    if not base:
        return numbered.select(F.lit(0).cast("long").alias(id_name), label)
    offset = F.create_map(*(F.lit(x) for kv in base.items() for x in kv))[F.col("__p")]
    return numbered.select((F.col("__i") + offset).cast("long").alias(id_name), label)


def from_pairs(pairs: DataFrame, n_rows: int | None = None, n_cols: int | None = None) -> Matrix:
    """A matrix from ``(row_id, col_id)`` pairs: nulls out, duplicates once; a shape not given is the number of ids met."""
    ones = require(pairs.where("row_id is not null and col_id is not null").distinct(), "ones")
    if n_rows is None or n_cols is None:
        met = ones.agg(F.countDistinct("row_id").alias("r"), F.countDistinct("col_id").alias("c")).first()
        n_rows, n_cols = n_rows if n_rows is not None else met.r, n_cols if n_cols is not None else met.c
    return Matrix(ones, int(n_rows), int(n_cols))


def from_labels(pairs: DataFrame, row: str, col: str) -> tuple[Matrix, DataFrame]:
    """A matrix whose columns have labels, and the dictionary ``(col_id, label)``.  ``pairs`` is run once: the labels of each row
    are gathered and kept, and dictionary, shape, baskets and ones follow from them."""
    held = cut(pairs.where(F.col(col).isNotNull()).groupBy(F.col(row).cast("long").alias("row_id")).agg(F.array_sort(F.collect_set(col)).alias("labels")))
    names = dictionary(held.select(F.explode("labels").alias(col)), col, "col_id").cache()
    n_cols, stray = names.count(), not held.where("row_id is null").isEmpty()
    if n_cols > MANY_LABELS:
        ones = held.where("row_id is not null").select("row_id", F.explode("labels").alias(col)).join(names, col).select("row_id", "col_id")
        return from_pairs(ones), names.select("col_id", F.col(col).alias("label"))
    baskets = cut(_numbered(held.where("row_id is not null"), names.orderBy("col_id").select(col).toArrow().column(0).combine_chunks()))
    ones = baskets.select("row_id", F.explode("items").alias("col_id"))
    n_cols = ones.agg(F.countDistinct("col_id")).first()[0] if stray else n_cols  # a label may come without a row only
    return Matrix(ones, baskets.count(), n_cols, {"baskets": baskets}), names.select("col_id", F.col(col).alias("label"))


def from_keys(facts: DataFrame, keys: DataFrame) -> tuple[Matrix, DataFrame]:
    """The same as ``from_labels`` for ``facts(row_id, key)`` whose labels are those of ``keys(key, item)``.  Where the labels are
    few, those of a row are gathered as the bits of one number; else the tables are joined and go there."""
    keys = keys.where("key is not null and item is not null")
    found = {r.item: r["count"] for r in keys.groupBy("item").count().limit(BITS + 1).collect()}
    known = sorted(found, key=str.encode)
    if not known or len(known) > BITS:
        return from_labels(facts.join(keys, "key").select("row_id", "item"), "row_id", "item")
    place = F.array_position(F.array(*(F.lit(x) for x in known)), F.col("item")) - 1
    marked = keys.select("key", F.call_function("shiftleft", F.lit(1).cast("long"), place.cast("int")).alias("mark"))
    if sum(found.values()) <= SENT_KEYS:
        marked = F.broadcast(marked)
    held = cut(facts.join(marked, "key").groupBy(F.col("row_id").cast("long").alias("row_id")).agg(F.bit_or("mark").alias("mark")))
    few = SMALL // len(known)
    stray, n = F.col("row_id").isNull().alias("stray"), F.count(F.lit(1)).alias("n")
    met = held.groupBy("mark", stray).agg(n).limit(few + 1).toArrow()
    few = met.num_rows <= few
    if not few:
        met = held.groupBy(stray).agg(F.bit_or("mark").alias("mark"), n).toArrow()
    mark, mine, n = met["mark"].to_numpy(), ~met["stray"].to_numpy(), met["n"].to_numpy()
    every, inside = (int(np.bitwise_or.reduce(x, initial=0)) for x in (mark, mark[mine]))
    bits = [i for i in range(len(known)) if every >> i & 1]  # a label's id is its place among those met
    items = F.array_remove(F.array(*(F.when(F.col("mark").bitwiseAND(F.lit(1 << b).cast("long")) != 0, F.lit(i).cast("long")).otherwise(F.lit(-1).cast("long")) for i, b in enumerate(bits))), F.lit(-1).cast("long")).alias("items")
    held = held.where("row_id is not null")
    baskets = held.select("row_id", items)
    names = facts.sparkSession.createDataFrame([(i, known[b]) for i, b in enumerate(bits)], "col_id long, label string")
    m = Matrix(baskets.select("row_id", F.explode("items").alias("col_id")), int(n[mine].sum()), inside.bit_count(), {"baskets": baskets, "marks": (held, items)})
    if few:
        row, at = np.nonzero((mark[mine, None] >> np.array(bits, np.int64)) & 1)
        ends = np.searchsorted(row, np.arange(mine.sum() + 1)).astype(np.int32)
        m.cache["few classes"] = n[mine].astype(np.int64), pa.ListArray.from_arrays(pa.array(ends), pa.array(at.astype(np.int64)))
    return m, names


def _numbered(held: DataFrame, labels: pa.Array) -> DataFrame:
    """``row_id, items`` from ``row_id, labels``: the place of each label among ``labels``, which ascend as those of a row do."""
    sent = held.sparkSession.sparkContext.broadcast(labels)

    def number(batches):
        for b in batches:
            lists = b.column(1)
            words = lists.flatten()
            ends = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()))]).astype(np.int32)
            at = pc.index_in(words, value_set=sent.value.cast(words.type)).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(ends), at)], ["row_id", "items"])

    return held.mapInArrow(number, "row_id long, items array<long>")


# --- matrices from the given tables: (row, item) pairs; items are strings, so that SQL can name them alike --------------


def order_brand(spark: SparkSession, d: str) -> DataFrame:
    facts, keys = order_brand_keys(spark, d)
    return facts.join(keys, "key").select("row_id", "item")


def order_brand_keys(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    li, p = table(spark, d, "lineitem", "l_orderkey", "l_partkey"), table(spark, d, "part", "p_partkey", "p_brand")
    return li.select(F.col("l_orderkey").alias("row_id"), F.col("l_partkey").alias("key")), p.select(F.col("p_partkey").alias("key"), F.col("p_brand").alias("item"))


def cust_typesize(spark: SparkSession, d: str) -> DataFrame:
    li, p = table(spark, d, "lineitem", "l_orderkey", "l_partkey"), table(spark, d, "part", "p_partkey", "p_type", "p_size")
    o = table(spark, d, "orders", "o_orderkey", "o_custkey")
    return li.join(p, F.col("l_partkey") == F.col("p_partkey")).join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("row_id"), F.concat_ws("/", "p_type", F.col("p_size").cast("string")).alias("item"))


def embed_high(spark: SparkSession, d: str, cut: float = 0.125) -> DataFrame:
    e = table(spark, d, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("row_id"), F.posexplode("embedding").alias("pos", "x"))
    return e.where(F.col("x") > cut).select("row_id", F.col("pos").cast("string").alias("item"))


def doc_terms(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents", "doc_id", "text")
    return docs.select(F.col("doc_id").alias("row_id"), F.explode(F.array_distinct(F.split(F.lower("text"), WORD))).alias("item")).where("item <> ''")


def doc_band(spark: SparkSession, d: str, low: float, high: float, least: int = 0) -> tuple[DataFrame, DataFrame | None]:
    """``row_id, items`` with the distinct terms of each document, found once, and ``item`` of those whose document frequency
    lies between shares of all documents; None where the others are gone from ``items`` already."""
    docs = table(spark, d, "documents", "doc_id", "text")
    terms = cut(docs.select(F.col("doc_id").alias("row_id"), F.array_distinct(F.split(F.lower("text"), WORD)).alias("items")))
    n = terms.count()
    df = terms.select(F.explode("items").alias("item")).where("item <> ''").groupBy("item").agg(F.count(F.lit(1)).alias("df"))
    band = cut(df.where((F.col("df") >= max(least, low * n)) & (F.col("df") <= high * n)).select("item"))
    if band.count() > FEW_LABELS:
        return terms, band
    return terms.where("items is not null").mapInArrow(_only(spark, band.toArrow().column(0).combine_chunks()), "row_id long, items array<string>"), None


def _only(spark: SparkSession, labels: pa.Array):
    """Lists cut to some labels; empty ones go."""
    sent = spark.sparkContext.broadcast(labels)

    def few(batches):
        for b in batches:
            lists = b.column(1)
            words = lists.flatten()
            good = np.asarray(pc.is_in(words, value_set=sent.value.cast(words.type)))
            row = np.repeat(np.arange(len(lists)), np.asarray(lists.value_lengths()))[good]
            at, n = np.unique(row, return_counts=True)
            ends = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.ListArray.from_arrays(pa.array(ends), words.filter(pa.array(good)))], ["row_id", "items"])

    return few


def doc_term_band(spark: SparkSession, d: str, low: float, high: float, least: int = 0) -> DataFrame:
    """Terms whose document frequency lies between shares of all documents."""
    terms, band = doc_band(spark, d, low, high, least)
    terms = terms.select("row_id", F.explode("items").alias("item"))
    return terms if band is None else terms.join(band, "item", "left_semi").select("row_id", "item")


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem", "l_orderkey", "l_partkey").select(F.col("l_orderkey").alias("row_id"), F.col("l_partkey").cast("string").alias("item"))


def hour_user(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "ts", "user_id").select(F.floor(F.unix_timestamp("ts") / 3600).alias("row_id"), F.col("user_id").cast("string").alias("item"))


def user_typehour(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events", "ts", "user_id", "event_type").select(F.col("user_id").alias("row_id"), F.concat_ws("/", "event_type", F.hour("ts").cast("string")).alias("item"))


def part_nation(spark: SparkSession, d: str) -> DataFrame:
    li, s = table(spark, d, "lineitem", "l_partkey", "l_suppkey"), table(spark, d, "supplier", "s_suppkey", "s_nationkey")
    return li.join(s, F.col("l_suppkey") == F.col("s_suppkey")).select(F.col("l_partkey").alias("row_id"), F.col("s_nationkey").cast("string").alias("item"))


def page_token(spark: SparkSession, d: str) -> DataFrame:
    pages = table(spark, d, "pages", "page_id", "html")
    return pages.select(F.col("page_id").alias("row_id"), F.explode(F.regexp_extract_all("html", F.lit("<([a-z0-9]+)"), F.lit(1))).alias("item"))


def conv_term(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "conversations", "conv_id", "role", "text")
    return c.select(F.col("conv_id").alias("row_id"), "role", F.explode(F.split(F.lower("text"), WORD)).alias("t")).where("t <> ''").select("row_id", F.concat_ws("/", "role", "t").alias("item"))


def bench_shingle(spark: SparkSession, d: str, k: int = 5) -> DataFrame:
    w = table(spark, d, "benchmark", "item_id", "text").select(F.col("item_id").alias("row_id"), F.filter(F.split(F.lower("text"), WORD), lambda x: x != "").alias("w"))
    w = w.where(F.size("w") >= k)
    return w.select("row_id", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), lambda i: F.array_join(F.slice("w", i, k), " "))).alias("item"))


def nation_region(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "nation", "n_nationkey", "n_regionkey").select(F.col("n_nationkey").cast("long").alias("row_id"), F.col("n_regionkey").cast("string").alias("item"))


BINARIZERS = {
    "order_brand": order_brand,
    "cust_typesize": cust_typesize,
    "embed_high": embed_high,
    "doc_term_mid": lambda s, d: doc_term_band(s, d, 0.05, 0.6),
    "doc_term_wide": lambda s, d: doc_term_band(s, d, 0.01, 0.6, 5),
    "doc_term_all": doc_terms,
    "order_part": order_part,
    "hour_user": hour_user,
    "user_typehour": user_typehour,
    "part_nation": part_nation,
    "page_token": page_token,
    "conv_term": conv_term,
    "bench_shingle": bench_shingle,
    "nation_region": nation_region,
}
KEYED = {"order_brand": order_brand_keys}  # those whose labels come from a key


def matrix(spark: SparkSession, sf_dir: str, name: str) -> tuple[Matrix, DataFrame]:
    """The named matrix and its column dictionary."""
    if name in KEYED:
        return from_keys(*KEYED[name](spark, sf_dir))
    return from_labels(BINARIZERS[name](spark, sf_dir), "row_id", "item")


def save_pool(pool: Pool, path: str, blocks: int = 64) -> None:
    """Rows and columns as Parquet, partitioned by a block of tiles so that a few tiles read a few files."""
    for name in ("tile_rows", "tile_cols", "tile_cells", "labels"):
        df = getattr(pool, name)
        if df is not None:
            df.withColumn("tile_block", F.pmod(F.xxhash64("tile_id"), F.lit(blocks)).cast("int")).repartition("tile_block").write.mode("overwrite").partitionBy("tile_block").parquet(f"{path}/{name}")


def load_pool(spark: SparkSession, path: str, names: tuple[str, ...] = ("tile_rows", "tile_cols"), dominated: bool = False) -> Pool:
    return Pool(**{n: spark.read.parquet(f"{path}/{n}").drop("tile_block") for n in names}, dominated=dominated)
