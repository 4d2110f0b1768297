"""Embedding near-duplicates by an epsilon grid order join.

Unit vectors with a cosine of at least ``t`` lie within ``eps = sqrt(2 - 2 t)``.  All vectors are rotated onto leading
principal directions, laid on a grid of cells of side ``eps`` and sorted by label and cell; the sequence is cut into blocks
of one label, numbered without gaps.  Intervals of the sequence are joined recursively: an interval of level l holds
``FAN ** l`` blocks, the one interval of the top level is paired with itself, and a pair of intervals is split into the
pairs of their parts until blocks are reached.  So there are as many levels as the number of blocks asks for.  A pair whose
bounding boxes lie further apart than ``eps`` is skipped with all that it holds; boxes are kept for each label of an
interval, so pairs are spread over tasks by interval, however frequent a label is.

Pairs of blocks that are left are compared exactly, as cosines in double precision.  A block is sent once to every
``FAN ** 2`` consecutive partners, which follow it one by one.  Each comparison returns counts, and for each vector the
smallest id it is linked with inside the two blocks, so a dense group yields rows in proportion to its size and blocks.

Equal vectors of one label are one class with a count.

Defined results: a row whose label or vector is null, whose vector is empty, zero, or holds null or non-finite numbers is
linked with nothing and is its own component; vectors of unequal length are never linked; rows of equal ``vec_id`` have a
row each, with the largest count and the least component of them; rows without a ``vec_id`` have a row of nulls each; other columns are ignored; no rows give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.scratch import components, keep, release

DIRECTIONS, FAN = 12, 8


def _matrices(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row numbers and values of the lists of each length."""
    offs = column.offsets.to_numpy()
    flat = column.values.to_numpy(zero_copy_only=False)
    size = np.diff(offs)
    for d in np.unique(size).tolist():
        rows = np.flatnonzero(size == d)
        yield rows, flat[offs[rows][:, None] + np.arange(d)]


def _moments(batches):
    for b in batches:
        for _, x in _matrices(b.column(0)):
            x = x.astype(float)
            d = x.shape[1]
            x = np.hstack([np.ones((len(x), 1)), x / np.sqrt((x * x).sum(1, keepdims=True))])
            s = (x.T @ x).reshape(-1)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(s.size, d)), pa.array(np.arange(s.size)), pa.array(s)], names=["d", "i", "s"])


def principal_directions(vectors: DataFrame, count: int = DIRECTIONS) -> dict[int, np.ndarray]:
    """Leading eigenvectors of the covariance of all unit vectors, for each vector length; sums are made on executors."""
    sums = vectors.select("v").mapInArrow(_moments, "d long, i long, s double")
    got = sums.groupBy("d", "i").agg(F.sum("s").alias("s")).toArrow()
    ds, at, s = (got.column(i).to_numpy() for i in range(3))
    out = {}
    for d in np.unique(ds).tolist():
        m = np.zeros((d + 1) ** 2)
        m[at[ds == d]] = s[ds == d]
        m = m.reshape(d + 1, d + 1)
        mean = m[0, 1:] / m[0, 0]
        _, vec = np.linalg.eigh(m[1:, 1:] / m[0, 0] - np.outer(mean, mean))
        out[d] = vec[:, ::-1][:, : min(count, d)]
    return out


def _listed(x: np.ndarray, kind: pa.DataType) -> pa.Array:
    """A matrix as a column of lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.reshape(-1), kind))


def _place(axes: dict[int, np.ndarray], eps: float):
    """Adds the cell and the coordinates on the principal directions."""

    def run(batches):
        for b in batches:
            for rows, x in _matrices(b.column(b.schema.get_field_index("v"))):
                x = x.astype(float)
                at = (x / np.sqrt((x * x).sum(1, keepdims=True))) @ axes[x.shape[1]]
                cells = np.floor(at / eps).astype(np.int32)
                some = b.take(pa.array(rows))
                yield pa.RecordBatch.from_arrays([*some.columns, _listed(cells, pa.int32()), _listed(at, pa.float64())], names=[*b.schema.names, "cell", "at"])

    return run


_BLOCK = pa.schema([("part", pa.int32()), ("number", pa.int64()), ("label", pa.int64()), ("d", pa.int32()), ("ids", pa.list_(pa.int64())), ("copies", pa.list_(pa.int64())), ("vectors", pa.binary()), ("low", pa.list_(pa.float64())), ("high", pa.list_(pa.float64()))])
_BLOCK_SQL = "part int, number long, label long, d int, ids array<long>, copies array<long>, vectors binary, low array<double>, high array<double>"


def _blocks(size: int):
    """Blocks of at most ``size`` rows of one label and length, in the order of the sorted rows."""

    def run(batches):
        from pyspark import TaskContext

        part, number, held = TaskContext.get().partitionId(), 0, None

        def block(t: pa.Table) -> pa.RecordBatch:
            t = t.combine_chunks()
            one = lambda name: t.column(name).chunk(0)
            _, at = next(_matrices(one("at")))
            _, v = next(_matrices(one("v")))
            row = (part, number, t["label"][0].as_py(), t["d"][0].as_py(), one("id").to_numpy(), one("copies").to_numpy(), v.tobytes(), at.min(0), at.max(0))
            return pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip(row, _BLOCK, strict=True)], schema=_BLOCK)

        for b in batches:
            t = pa.Table.from_batches([b])
            key = np.stack([b.column(b.schema.get_field_index(x)).to_numpy() for x in ("label", "d")])
            turns = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(0)) + 1
            for i, j in zip([0, *turns.tolist()], [*turns.tolist(), b.num_rows], strict=True):
                if i == j:
                    continue
                if held is not None and (held["label"][0].as_py(), held["d"][0].as_py()) != (int(key[0, i]), int(key[1, i])):
                    yield block(held)
                    number, held = number + 1, None
                held = t.slice(i, j - i) if held is None else pa.concat_tables([held, t.slice(i, j - i)])
                while held.num_rows >= size:
                    yield block(held.slice(0, size))
                    number, held = number + 1, held.slice(size) if held.num_rows > size else None
                    if held is None:
                        break
        if held is not None:
            yield block(held)

    return run


def numbered(blocks: DataFrame) -> DataFrame:
    """``blocks`` with ``block``, their number in the sequence without gaps; the driver sums one count for each partition."""
    counts = blocks.groupBy("part").agg((F.max("number") + 1).alias("n")).toArrow().sort_by("part")
    base, total = {}, 0
    for p, n in zip(counts["part"].to_pylist(), counts["n"].to_pylist(), strict=True):
        base[p], total = total, total + n
    spark = blocks.sparkSession
    first = spark.createDataFrame(list(base.items()) or [(-1, 0)], "part int, base long")
    return blocks.join(F.broadcast(first), "part").withColumn("block", F.col("base") + F.col("number")).drop("part", "number", "base")


def _near(eps: float) -> Column:
    """Whether the boxes a and b may hold points within ``eps`` (with room for rounding)."""
    gap = F.zip_with(F.zip_with("alow", "bhigh", lambda x, y: x - y), F.zip_with("blow", "ahigh", lambda x, y: x - y), lambda x, y: F.greatest(x, y, F.lit(0.0)))
    return F.aggregate(gap, F.lit(0.0), lambda s, x: s + x * x) <= eps * eps + 1e-9


def _boxes(blocks: DataFrame, level: int) -> DataFrame:
    """``label, d, node, low, high`` of the intervals of a level."""
    key = ["label", "d", "node"]
    box = blocks.select("label", "d", F.floor(F.col("block") / FAN**level).alias("node"), "low", "high")
    if not level:
        return box
    side = box.select(*key, F.posexplode(F.arrays_zip("low", "high"))).groupBy(*key, "pos").agg(F.min("col.low").alias("l"), F.max("col.high").alias("h"))
    made = side.groupBy(*key).agg(F.array_sort(F.collect_list(F.struct("pos", "l", "h"))).alias("x"))
    return made.select(*key, F.transform("x", lambda c: c["l"]).alias("low"), F.transform("x", lambda c: c["h"]).alias("high"))


def block_pairs(blocks: DataFrame, eps: float) -> DataFrame:
    """Pairs of blocks ``(a, b)``, a <= b, that recursion over the intervals leaves."""
    top = blocks.agg(F.max("block").alias("m")).first().m or 0
    level = 0
    while FAN**level <= top:
        level += 1
    pairs = blocks.select("label", "d", F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b")).distinct()
    while level:
        level -= 1
        box = keep(_boxes(blocks, level))
        side = lambda x: box.select("label", "d", F.floor(F.col("node") / FAN).alias(x), F.col("node").alias(f"{x}node"), F.col("low").alias(f"{x}low"), F.col("high").alias(f"{x}high"))  # noqa: E731, B023
        met = pairs.join(side("a"), ["label", "d", "a"]).join(side("b"), ["label", "d", "b"]).where((F.col("anode") <= F.col("bnode")) & _near(eps))
        pairs = keep(met.select("label", "d", F.col("anode").alias("a"), F.col("bnode").alias("b")))
    return pairs.select("a", "b")



def _linked(ids: list[np.ndarray], hit: np.ndarray, same: bool) -> list[np.ndarray]:
    """For each vector of both sides the smallest id that it reaches by the hits."""
    rows, cols = np.nonzero(hit)
    mine = [ids[0].copy(), ids[1].copy()]
    while True:
        before = [z.copy() for z in mine]
        np.minimum.at(mine[1], cols, mine[0][rows])
        if same:
            np.minimum(mine[0], mine[1], out=mine[0])
        np.minimum.at(mine[0], rows, mine[1][cols])
        if all((p == q).all() for p, q in zip(before, mine, strict=True)):
            return mine


def _compare(least: float, kind: type):
    """Rows sorted by block and part: the block itself (``other`` -1), then its partners.  One block is held at a time."""

    def sides(b: pa.RecordBatch):
        col = {n: b.column(i) for i, n in enumerate(b.schema.names)}
        for i in range(b.num_rows):
            ids, copies = (col[x][i].values.to_numpy() for x in ("ids", "copies"))
            x = np.frombuffer(col["vectors"][i].as_buffer(), kind).reshape(len(ids), -1).astype(float)
            yield col["block"][i].as_py(), col["other"][i].as_py(), (ids, copies, x, np.sqrt((x * x).sum(1)))

    def run(batches):
        held = None
        for batch in batches:
            for block, other, side in sides(batch):
                if other == -1:
                    held = side
                    continue
                same = block == other
                (xi, xn, x, xl), (yi, yn, y, yl) = held, side
                hit = (x @ y.T) / (xl[:, None] * yl[None, :]) >= least
                if same:
                    np.fill_diagonal(hit, False)
                if not hit.any():
                    continue
                mine = _linked([xi, yi], hit, same)
                for ids, n, low in ((xi, hit @ yn, mine[0]), *([] if same else [(yi, hit.T @ xn, mine[1])])):
                    use = np.flatnonzero(n)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[use]), pa.array(n[use].astype(np.int64)), pa.array(low[use])], names=["id", "n", "least"])

    return run


def compared(blocks: DataFrame, pairs: DataFrame, least: float, kind: type) -> DataFrame:
    """``id, n, least``: what each pair of blocks links, with the copies behind each link."""
    data = [F.col(x) for x in ("ids", "copies", "vectors")]
    part = F.floor(F.col("b") / FAN**2)
    own = pairs.select("a", part.alias("part")).distinct().join(blocks, F.col("a") == F.col("block")).select(F.col("a").alias("block"), "part", F.lit(-1).cast("long").alias("other"), *data)
    theirs = pairs.join(blocks, F.col("b") == F.col("block")).select(F.col("a").alias("block"), part.alias("part"), F.col("b").alias("other"), *data)
    spread = int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = own.unionByName(theirs).repartition(spread, "block", "part").sortWithinPartitions("block", "part", "other")
    return dealt.mapInArrow(_compare(least, kind), "id long, n long, least long")


def near_vectors(vectors: DataFrame, least: float = 0.93, size: int = 512) -> DataFrame:
    """One row per row of ``vectors(vec_id, label, embedding)``: ``vec_id, n_links, component_id, kept``."""
    eps = float(np.sqrt(2 - 2 * least))
    single = vectors.schema["embedding"].dataType.elementType.simpleString() == "float"  # the compared doubles are the same
    v = F.col("embedding").cast("array<float>" if single else "array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    sound = F.coalesce(F.col("label").isNotNull() & (F.size("embedding") > 0) & finite & F.exists(v, lambda x: x != 0), F.lit(False))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding"), sound.alias("sound"))
    live = rows.where("sound and vec_id is not null").select("vec_id", "label", v.alias("v"), F.xxhash64("embedding").alias("k1"), F.xxhash64(F.lit(7), F.reverse("embedding")).alias("k2"), F.size("embedding").alias("d"))
    key = ["label", "d", "k1", "k2"]
    classes = keep(live.groupBy(*key).agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("copies"), F.first("v").alias("v")))
    axes = principal_directions(classes)
    inner = "float" if single else "double"
    placed = classes.select("id", "copies", "label", "d", "v").mapInArrow(_place(axes, eps), f"id long, copies long, label long, d int, v array<{inner}>, cell array<int>, at array<double>")
    blocks = numbered(keep(placed.orderBy("label", "d", "cell", "id").mapInArrow(_blocks(size), _BLOCK_SQL)))
    pairs = block_pairs(blocks.drop("ids", "copies", "vectors"), eps)
    found = keep(compared(blocks, pairs, least, np.float32 if single else np.float64))
    release(vectors.sparkSession)
    count = found.groupBy("id").agg(F.sum("n").alias("n"))
    label = components(found.where("id <> least").select(F.col("id").alias("a"), F.col("least").alias("b")))
    known = classes.select("id", "copies", *key).join(count, "id", "left").join(label, "id", "left")
    known = known.select(*key, (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "id").alias("component"))
    out = live.select("vec_id", *key).join(known, key).groupBy("vec_id").agg(F.max("n_links").alias("n_links"), F.min("component").alias("component"))
    every = rows.select("vec_id").join(out, "vec_id", "left")
    return every.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id")).withColumn("kept", F.col("vec_id") == F.col("component_id"))
