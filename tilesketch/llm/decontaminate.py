"""Benchmark decontamination by template windows.

A text becomes template tokens: numbers, units after a number, and capitalised words inside a sentence become typed
placeholders, every other word its lower-case form; punctuation and spacing don't count.  A capitalised word that opens a
sentence may be a name or not, so windows that hold one are made twice: with openers as plain words (``PLAIN``) and with
openers as names (``TYPED``).  An item matches by either, so neither renamed persons at the start of sentences nor a
sentence that is quoted within another one escape.

Windows of eight template tokens (a shorter item: the whole item) with at least ``literals`` plain words are hash-joined
with those of the benchmark.  An item without any such window, dense in numbers and names, is compared by its words
as they stand, in lower case (``VERBATIM``): its copies are found, its re-parameterised forms are not.

Windows that lie on one diagonal (same distance between place in text and place in item) are one passage.  A passage
counts when it covers half of the item's windows, or thirteen tokens, and its slots are consistent in both directions:
equal values of the item stand against equal values of the text, and different ones against different ones.  So an item
with other names and numbers is caught, a clash of unrelated slots is not.

The benchmark's window hashes go to every task while they number at most ``small`` (8 bytes each); beyond that, all windows
of the texts are joined with those of the benchmark by a shuffle.

Defined results: null and empty texts and items match nothing; rows without an id are left out; rows of equal ``doc_id``
count as one document; other columns are ignored; no rows on either side give no rows.  A very long text costs about 150
bytes of memory a byte.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import LETTER, LOWER, U, blocks, hashes, lists, mapped, runs, signed, windows
from tilesketch.llm.scratch import keep

# fixed values: units of measure that become a placeholder after a number
UNITS = "mm cm m km in ft yd mi mg g kg t lb oz ml l s sec secs second seconds min mins minute minutes h hr hrs hour hours day days week weeks month months year years percent c f k w kw v a hz khz mhz ghz b kb mb gb tb usd eur dollars euros cents meters metres kilometers kilometres miles feet inches grams kilograms pounds liters litres degrees".split()

NUMBER, NAME, UNIT = (np.array([x], U) for x in (0xA1, 0xB2, 0xC3))
PLAIN, TYPED, VERBATIM = 0, 1, 2
_TURN = np.array([0, 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F], U)  # windows of different kinds have different hashes
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_END = np.zeros(256, bool)
_END[[10, 33, 46, 63]] = True


def _word_hashes(texts: list[str]) -> np.ndarray:
    raw = [x.encode() for x in texts]
    ends = np.cumsum([len(x) for x in raw])
    return hashes(np.frombuffer(b"".join(raw), np.uint8), ends - [len(x) for x in raw], ends)


def template(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Template tokens of a block of texts: token hash with openers as plain words, value hash, whether the token is a
    placeholder, whether it is a capitalised opener, and text number."""
    digit = mapped(_DIGIT, data)
    number = digit.copy()
    if len(data) > 2:
        number[1:-1] |= ((data[1:-1] == 46) | (data[1:-1] == 44)) & digit[:-2] & digit[2:]
    s1, e1, d1 = runs(mapped(LETTER, data), offs)
    s2, e2, d2 = runs(number, offs)
    order = np.argsort(np.concatenate([s1, s2]), kind="stable")
    s, e, doc = (np.concatenate(x)[order] for x in ((s1, s2), (e1, e2), (d1, d2)))
    is_number = order >= len(s1)
    value = hashes(mapped(LOWER, data), s, e)
    if not len(s):
        return value, value, is_number, is_number, doc
    ends = np.concatenate([[0], np.cumsum(mapped(_END, data))])
    opens = np.ones(len(s), bool)
    opens[1:] = (doc[1:] != doc[:-1]) | (ends[s[1:]] > ends[e[:-1]])
    lead = data[s]
    follow = data[np.minimum(s + 1, len(data) - 1)]
    capital = (((lead >= 65) & (lead <= 90)) | ((lead == 0xC3) & (follow >= 0x80) & (follow <= 0x9E))) & ~is_number
    unit = np.zeros(len(s), bool)
    near = np.flatnonzero(is_number[:-1] & ~is_number[1:] & (doc[1:] == doc[:-1]) & (s[1:] - e[:-1] <= 1)) + 1
    unit[near] = np.isin(value[near], _word_hashes(UNITS))
    name = capital & ~opens & ~unit
    token = np.where(is_number, NUMBER, np.where(unit, UNIT, np.where(name, NAME, value)))
    return token, value, is_number | unit | name, capital & opens & ~unit, doc


_HIT = "id long, kind int, place int, size int, h long, slots array<long>"


class Wanted:
    """The window hashes of the benchmark, with a table of their low bits that passes over most others."""

    def __init__(self, keys: np.ndarray):
        self.keys, self.near = np.sort(keys), np.zeros(1 << 20, bool)
        self.near[(keys & U((1 << 20) - 1)).astype(np.int64)] = True

    def among(self, h: np.ndarray) -> np.ndarray:
        """Places of the hashes that are wanted."""
        at = np.flatnonzero(self.near[(h & U((1 << 20) - 1)).astype(np.int64)])
        return at[np.isin(h[at], self.keys)] if len(self.keys) else at[:0]


def _rows(wanted_sizes: list[tuple[int, int]], wanted: Wanted | None, items: bool, literals: int):
    """Windows of the given kinds and sizes.  ``items``: a text of fewer tokens than the largest size gives one window,
    itself, and verbatim windows count only where a text has no others."""

    def windows_of(kind, size, token, value, slot, opener, doc):
        if kind == TYPED:
            token, slot = np.where(opener, NAME, token), slot | opener
        elif kind == VERBATIM:
            token, slot = value, np.zeros(len(value), bool)
        h, at = windows(token, doc, size)
        h = h ^ _TURN[kind]
        many = np.concatenate([[0], np.cumsum(~slot)])
        good = many[at + size] - many[at] >= min(literals, size)
        if kind == TYPED:
            some = np.concatenate([[0], np.cumsum(opener)])
            good &= some[at + size] > some[at]
        return h[good], at[good], np.where(slot, value, U(0))

    def run(batches):
        largest = max((size for _, size in wanted_sizes), default=0)
        for part, data, offs in blocks(batches):
            ids = part.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            made = template(data, offs)
            doc = made[-1]
            count = np.bincount(doc, minlength=len(ids))
            first = np.searchsorted(doc, np.arange(len(ids)))
            templated = np.zeros(len(ids), bool)
            for kind, size in wanted_sizes:
                h, at, slots = windows_of(kind, size, *made)
                if items:
                    stays = count[doc[at]] == size if size < largest else np.ones(len(at), bool)
                    if kind == VERBATIM:
                        stays &= ~templated[doc[at]]
                    h, at = h[stays], at[stays]
                    templated[doc[at]] = True
                if wanted is not None:
                    few = wanted.among(h)
                    h, at = h[few], at[few]
                if len(h):
                    n = len(h)
                    whole = slots[at[:, None] + np.arange(size)].reshape(-1)
                    cols = [ids[doc[at]], np.full(n, kind, np.int32), (at - first[doc[at]]).astype(np.int32), np.full(n, size, np.int32), signed(h)]
                    yield pa.RecordBatch.from_arrays([*map(pa.array, cols), lists(whole, np.full(n, size))], names=["id", "kind", "place", "size", "h", "slots"])

    return run


def contaminated(docs: DataFrame, benchmark: DataFrame, size: int = 8, literals: int = 4, share: float = 0.5, tokens: int = 13, small: int = 4_000_000) -> DataFrame:
    """One row per document and item that it holds: ``doc_id, item_id, n_windows, n_item_windows, exact`` (no slot
    differs)."""

    def ids(df: DataFrame, name: str) -> DataFrame:
        return df.where(f"{name} is not null").select(F.col(name).cast("long").alias("id"), F.col("text").cast("string").alias("text"))

    every = [(kind, n) for kind in (PLAIN, TYPED, VERBATIM) for n in range(1, size + 1)]
    items = keep(ids(benchmark, "item_id").mapInArrow(_rows(every, None, True, literals), _HIT))
    found = sorted((r["kind"], r["size"]) for r in items.select("kind", "size").distinct().collect())
    distinct = items.select("h").distinct()
    wanted = Wanted(distinct.toArrow()["h"].to_numpy().view(U)) if distinct.count() <= small else None
    hits = ids(docs, "doc_id").mapInArrow(_rows(found, wanted, False, literals), _HIT)

    total = items.groupBy(F.col("id").alias("item_id")).agg(F.countDistinct("place").alias("n_item_windows"), F.max("size").alias("size"))
    its = items.select(F.col("id").alias("item_id"), "kind", F.col("place").alias("at"), "size", "h", F.col("slots").alias("its"))
    pair = hits.select(F.col("id").alias("doc_id"), "kind", "place", "size", "h", "slots").join(its, ["h", "kind", "size"])
    slots = F.filter(F.arrays_zip(F.col("its").alias("i"), F.col("slots").alias("d")), lambda x: (x["i"] != 0) | (x["d"] != 0))
    line = pair.groupBy("doc_id", "item_id", (F.col("place") - F.col("at")).alias("shift"))
    line = line.agg(F.countDistinct("at").alias("n"), F.array_distinct(F.flatten(F.collect_set(slots))).alias("slots"))
    values = lambda side: F.size(F.array_distinct(F.transform("slots", lambda x: x[side])))
    line = line.withColumn("consistent", (values("i") == F.size("slots")) & (values("d") == F.size("slots"))).withColumn("exact", F.forall("slots", lambda x: x["i"] == x["d"]))
    judged = line.join(total, "item_id").where(F.col("consistent") & ((F.col("n") >= share * F.col("n_item_windows")) | (F.col("n") + F.col("size") - 1 >= tokens)))
    best = judged.groupBy("doc_id", "item_id").agg(F.max(F.struct("n", "exact")).alias("best"), F.max("n_item_windows").alias("n_item_windows"))
    return best.select("doc_id", "item_id", F.col("best.n").alias("n_windows"), "n_item_windows", F.col("best.exact").alias("exact"))
