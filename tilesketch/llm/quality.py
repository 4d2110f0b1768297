"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each text gives a fixed vector of statistics, shares through the arc sine of the square root, sizes through the logarithm.
The class means and covariances come from sums over all labelled training rows; each covariance is shrunk towards the
pooled one and then towards a multiple of the identity.  Scores are the logistic of the difference of Mahalanobis
log-densities; the Cholesky factors and their inverses are made once for a model, so a score costs one triangular product.

Defined results: null and empty texts have the statistics of an empty text and a score like any other; a class without
training rows takes the pooled moments, and without any labels every score is 0.5; rows of equal ``doc_id`` each have a
row; other columns pass by; tables without rows give no rows.  A very long text costs about 60 bytes of memory a byte, in a
block of its own.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import LETTER, LOWER, SPACE, blocks, lists, mapped, ranged, runs, sums
from tilesketch.llm.scratch import drop, keep

NAMES = ("words", "bytes", "word_length", "letters", "capitals", "digits", "marks", "stops", "symbol_words", "distinct", "repeats", "short", "capital_words", "lines", "longest_word", "shout_words")


def _table(codes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(codes)] = True
    return out


_UPPER, _DIGIT, _STOP = _table(range(65, 91)), _table(range(48, 58)), _table(b".,")
_MARK = _table(c for c in range(33, 127) if not chr(c).isalnum() and chr(c) not in ".,")


def statistics(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """One row of transformed statistics for each text of a block."""
    n = len(offs) - 1
    s, e, doc = runs(~mapped(SPACE, data), offs)
    h = ranged(sums(mapped(LOWER, data)), s, e)
    count = np.bincount(doc, minlength=n).astype(float)
    size = np.diff(offs).astype(float)
    some, full = np.maximum(count, 1), np.maximum(size, 1)

    def total(inside: np.ndarray) -> np.ndarray:
        c = np.concatenate([[0], np.cumsum(inside, dtype=np.int64)])
        return (c[offs[1:]] - c[offs[:-1]]).astype(float)

    def per_word(x: np.ndarray) -> np.ndarray:
        return np.bincount(doc, x, minlength=n) / some

    length = (e - s).astype(float)
    symbol = _MARK[data[np.maximum(e - 1, 0)]] if len(s) else np.zeros(0, bool)
    upper = _UPPER[data[s]] if len(s) else np.zeros(0, bool)
    second = _UPPER[data[np.minimum(s + 1, e - 1)]] & (e - s > 1) if len(s) else np.zeros(0, bool)
    again = np.zeros(len(h), bool)
    again[1:] = (h[1:] == h[:-1]) & (doc[1:] == doc[:-1])
    order = np.argsort(h, kind="stable")
    order = order[np.argsort(doc[order], kind="stable")]
    new = np.ones(len(h), bool)
    new[1:] = (h[order][1:] != h[order][:-1]) | (doc[order][1:] != doc[order][:-1])
    distinct = np.bincount(doc[order][new], minlength=n)
    longest = np.zeros(n)
    np.maximum.at(longest, doc, length)
    share = lambda x: np.arcsin(np.sqrt(np.clip(x, 0, 1)))
    columns = [
        np.log1p(count),
        np.log1p(size),
        np.log1p(per_word(length)),
        share(total(mapped(LETTER, data)) / full),
        share(total(mapped(_UPPER, data)) / full),
        share(total(mapped(_DIGIT, data)) / full),
        share(total(mapped(_MARK, data)) / full),
        share(total(mapped(_STOP, data)) / some),
        share(per_word(symbol.astype(float))),
        np.log1p(distinct) / np.log(np.maximum(some, 1) + 1),
        share(per_word(again.astype(float))),
        share(per_word((length <= 3).astype(float))),
        share(per_word(upper.astype(float))),
        np.log1p(total(data == 10)),
        np.log1p(longest),
        share(per_word((upper & second).astype(float))),
    ]
    return np.stack(columns, 1)


def _rows(batches):
    for part, data, offs in blocks(batches):
        x = statistics(data, offs)
        yield pa.RecordBatch.from_arrays([part.column(0), lists(x.reshape(-1), np.full(len(x), x.shape[1]))], names=["doc_id", "stats"])


def document_statistics(docs: DataFrame) -> DataFrame:
    """``(doc_id, stats array<double>)`` of every row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_rows, "doc_id long, stats array<double>")


@dataclass
class Discriminant:
    """Means, Cholesky factors, log determinants and log priors of the two classes."""

    mean: np.ndarray
    factor: np.ndarray
    logdet: np.ndarray
    prior: np.ndarray

    def __post_init__(self):
        self.inverse = np.tril(np.linalg.inv(self.factor))

    @classmethod
    def fit(cls, count: np.ndarray, first: np.ndarray, second: np.ndarray, towards_pooled: float, towards_identity: float) -> Discriminant:
        """From the class counts, sums and sums of products."""
        d = first.shape[1]
        if count.sum() == 0:
            return cls(np.zeros((2, d)), np.stack([np.eye(d)] * 2), np.zeros(2), np.zeros(2))
        middle = first.sum(0) / count.sum()
        mean = np.where(count[:, None] > 0, first / np.maximum(count, 1)[:, None], middle)
        scatter = [second[c] - count[c] * np.outer(mean[c], mean[c]) for c in (0, 1)]
        pooled = (scatter[0] + scatter[1]) / count.sum()
        factor = []
        for c in (0, 1):
            own = scatter[c] / count[c] if count[c] else pooled
            own = (1 - towards_pooled) * own + towards_pooled * pooled
            own = (1 - towards_identity) * own + towards_identity * np.eye(d) * (max(np.trace(own) / d, 1e-6))
            factor.append(np.linalg.cholesky(own))
        factor = np.stack(factor)
        return cls(mean, factor, 2 * np.log(np.diagonal(factor, axis1=1, axis2=2)).sum(1), np.log((count + 1) / (count.sum() + 2)))

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of class 1."""
        z = [self.inverse[c] @ (x - self.mean[c]).T for c in (0, 1)]
        own = [self.prior[c] - 0.5 * (self.logdet[c] + (z[c] ** 2).sum(0)) for c in (0, 1)]
        return 1 / (1 + np.exp(-np.clip(own[1] - own[0], -500, 500)))


def fit(stats: DataFrame, towards_pooled: float = 0.1, towards_identity: float = 0.001) -> Discriminant:
    """From ``(stats, label)``: the sums go through one aggregation over all rows."""
    d = len(NAMES)

    def sums_of(batches):
        for b in batches:
            y = b.column(1).to_numpy(zero_copy_only=False)
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            for c in (0, 1):
                m = x[y == c]
                if len(m):
                    m1 = np.hstack([np.ones((len(m), 1)), m])
                    s = m1.T @ m1
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(s.size, c)), pa.array(np.arange(s.size)), pa.array(s.reshape(-1))], names=["c", "i", "s"])

    got = stats.where("label in (0, 1)").select("stats", F.col("label").cast("long")).mapInArrow(sums_of, "c long, i long, s double").groupBy("c", "i").agg(F.sum("s").alias("s")).collect()
    m = np.zeros((2, (d + 1) ** 2))
    for r in got:
        m[r.c, r.i] = r.s
    m = m.reshape(2, d + 1, d + 1)
    return Discriminant.fit(m[:, 0, 0], m[:, 0, 1:], m[:, 1:, 1:], towards_pooled, towards_identity)


def apply(stats: DataFrame, model: Discriminant) -> DataFrame:
    """``stats`` with ``score`` in place of the statistics."""
    d = len(NAMES)

    def scores(batches):
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(x))], names=["doc_id", "score"])

    return stats.select("doc_id", "stats").mapInArrow(scores, "doc_id long, score double")


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def _fit_on(stats: DataFrame, labels: DataFrame, name: str) -> Discriminant:
    known = labels.where(~held_out()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(name).alias("label"))
    return fit(stats.join(known, "doc_id").select("stats", "label"))


def fit_on_labels(docs: DataFrame, labels: DataFrame, name: str = "quality", bound: int = 200_000) -> Discriminant:
    """The model of the labelled documents outside the held-out fifth, of at most ``bound`` of them by hash of their id:
    statistics are made of those alone.  Their ids, eight bytes each, go to every task."""
    known = labels.where(~held_out() & F.col(name).isin(0, 1)).select(F.col("doc_id").cast("long").alias("__id"), F.col(name).alias("label"))
    part = min(1.0, 0.95 * bound / max(1, known.count()))
    known = known.where(F.pmod(F.xxhash64("__id"), F.lit(1 << 20)) < int(part * (1 << 20))).limit(bound)
    chosen = docs.join(F.broadcast(known.select("__id").distinct()), docs["doc_id"].cast("long") == F.col("__id"), "left_semi")
    return fit(document_statistics(chosen).join(F.broadcast(known), F.col("doc_id") == F.col("__id")).select("stats", "label"))


def accepted(docs: DataFrame, model: Discriminant, least: float) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is at least ``least``."""

    def run(batches):
        for part, data, offs in blocks(batches):
            stays = model.score(statistics(data, offs)) >= least
            if stays.any():
                yield part.filter(pa.array(stays))

    return docs.mapInArrow(run, docs.schema)


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, held_out, score, predicted``: fitted on the labels outside the held-out fifth."""
    stats = keep(document_statistics(docs))
    model = _fit_on(stats, labels, "quality")
    return apply(stats, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
