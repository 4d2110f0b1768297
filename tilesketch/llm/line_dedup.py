"""Line deduplication with overlapping three-line windows.

Lines are the parts of a text between line feeds; each counts by its bytes without the white space around it, and blank
lines are passed over.  Every window of three consecutive lines is hashed to 128 bits of BLAKE2 over its lines, so that
windows of one hash are equal in every byte; windows that occur more than once are found over all texts, and the lines
that any later occurrence covers are removed.  The order of occurrences is ``doc_id``, then
place in the text.  Every removed line still stands at an earlier place.

Defined results: null texts stay null; texts with fewer than three lines that are not blank have no window and stay;
rows without a ``doc_id`` stay as they are; rows of equal ``doc_id`` are one place and don't remove each other's lines;
other columns pass through; no rows give no rows.  A very long text costs about 40 bytes of memory a byte.
"""

from __future__ import annotations

from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import SPACE, blocks, mapped, runs
from tilesketch.llm.scratch import by_key, drop, keep

_WINDOW_SQL = "doc_id long, place int, l0 int, l1 int, l2 int, h long, g long"


def full_lines(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of the lines that are not blank: start and end without the white space around, text number and line number."""
    s, e, doc = runs(data != 10, offs)
    ws, we, _ = runs(~mapped(SPACE, data), offs)
    a, b = np.searchsorted(ws, s), np.searchsorted(we, e, "right")
    full = np.flatnonzero(b > a)
    s, e, doc = ws[a[full]], we[b[full] - 1], doc[full]
    feeds = np.flatnonzero(data == 10)
    return s, e, doc, np.searchsorted(feeds, s) - np.searchsorted(feeds, offs[:-1])[doc]


def digests(data: np.ndarray, s: np.ndarray, e: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Two 64-bit halves of the digest of each window of three lines that starts at one of the lines ``at``."""
    raw = data.tobytes()
    line = [blake2b(raw[i:j], digest_size=16).digest() for i, j in zip(s.tolist(), e.tolist(), strict=True)]
    made = b"".join(blake2b(line[i] + line[i + 1] + line[i + 2], digest_size=16).digest() for i in at.tolist())
    return np.frombuffer(made, np.int64).reshape(-1, 2) if made else np.zeros((0, 2), np.int64)


def _windows(batches):
    for part, data, offs in blocks(batches):
        ids = part.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
        s, e, doc, number = full_lines(data, offs)
        at = np.flatnonzero(doc[:-2] == doc[2:])
        first = np.searchsorted(doc, doc[at])
        h = digests(data, s, e, at)
        cols = [ids[doc[at]], (at - first).astype(np.int32), *(number[at + i].astype(np.int32) for i in range(3)), *np.ascontiguousarray(h.T)]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["doc_id", "place", "l0", "l1", "l2", "h", "g"])


def later_lines(docs: DataFrame) -> DataFrame:
    """``(doc_id, lines)``: the sorted numbers of the lines that later occurrences of a repeated window cover."""
    text = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    every = keep(text.mapInArrow(_windows, _WINDOW_SQL))
    first = keep(every.groupBy("h", "g").agg(F.min(F.struct("doc_id", "place")).alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1"))
    later = by_key(every, first, "h", "g").where(F.struct("doc_id", "place") != F.col("first"))
    lines = later.select("doc_id", F.explode(F.array("l0", "l1", "l2")).alias("line")).groupBy("doc_id").agg(F.array_sort(F.collect_set("line")).alias("lines"))
    out = keep(lines)
    drop(every, first)
    return out


def _without(name: str, lines: str):
    def run(batches):
        for batch in batches:
            at = batch.schema.get_field_index(name)
            gone = batch.column(batch.schema.get_field_index(lines))
            hit = np.flatnonzero(np.asarray(gone.is_valid()))
            if len(hit):
                text = batch.column(at)
                texts = np.array(text.to_pylist(), dtype=object)
                for i in hit:
                    if texts[i] is not None:
                        out = set(gone[int(i)].as_py())
                        texts[i] = "\n".join(x for j, x in enumerate(texts[i].split("\n")) if j not in out)
                batch = batch.set_column(at, batch.schema.field(at), pa.array(texts.tolist(), text.type))
            yield batch

    return run


def dedup_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with the lines of later occurrences taken out of ``text``, and ``n_removed_lines``."""
    gone = later_lines(docs).select(F.col("doc_id").alias("__id"), F.col("lines").alias("__lines"))
    both = docs.join(gone.hint("shuffle_hash"), docs["doc_id"].cast("long") == F.col("__id"), "left").drop("__id")
    out = both.mapInArrow(_without("text", "__lines"), both.schema)
    return out.withColumn("n_removed_lines", F.coalesce(F.size("__lines"), F.lit(0)).cast("long")).drop("__lines")
