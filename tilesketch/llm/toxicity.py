"""Toxic spans by a linear-chain conditional random field of two states over the words of a text.

Words are runs of letters (any byte from 0x80 counts as one).  The chain is cut at sentence ends, line feeds and after 64
words; every word of a text is in one piece.  A word's features are its lower-case form, its first four, five and six
bytes, and the words before and after it in its piece, each hashed to one of ``BUCKETS`` weights; features of fewer than
``least`` training documents have none.

Labels belong to documents, so the labels of words are hidden: in a clean document every word is clean, in a toxic one at
least one word is toxic.  Training climbs the likelihood of just that.  Paths are scored against the clean path, so the
chance that a piece is clean is one over its sum Z over all paths, and that of a document the product over its pieces.  The
expectation step is forward-backward: of a toxic document it gives the expected features of all paths but the clean one.
Climbing starts where words and prefixes weigh
what their documents say of them, so that it settles on common causes and not on rare words.  In closed form a document's gradient is its expected features times -1 if it is clean, and times ``p / (1 - p)``, p being
the chance that all of it is clean, if it is toxic.

A logistic curve over the largest marginal and the expected number of toxic words, fitted on the same sample, gives the
document's score; runs of words over one half are its spans (code points, end exclusive).

The sample is of at most ``bound`` labelled documents and ``most`` bytes; both are taken by hash of the id, whole texts.

Defined results: null and empty texts get the score of a text without words; without labels of both classes every score is
that of the prior; other columns are ignored; repeated rows each have a row; no rows give no rows.  A very long text costs
about 150 bytes of memory a byte.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import LETTER, LOWER, U, blocks, mapped, mix, ranged, runs, sums

PIECE = 64
PREFIXES = (4, 5, 6)
BUCKETS = 1 << 20
OWN, WIDTH = 1 + len(PREFIXES), 3 + len(PREFIXES)
_CUT = np.zeros(256, bool)
_CUT[[10, 33, 46, 63]] = True


def tokens(data: np.ndarray, offs: np.ndarray):
    """Start, end, text number and piece number of each word, and its features as buckets (one row each; 0: none)."""
    data = mapped(LOWER, data)
    s, e, doc = runs(mapped(LETTER, data), offs)
    total = sums(data)
    feats = np.zeros((WIDTH, len(s)), np.int32)
    if not len(s):
        return s, e, doc, doc, feats
    cuts = np.concatenate([[0], np.cumsum(mapped(_CUT, data))])
    new = np.ones(len(s), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (cuts[s[1:]] > cuts[e[:-1]])
    start = np.maximum.accumulate(np.where(new, np.arange(len(s)), 0))
    new |= (np.arange(len(s)) - start) % PIECE == 0
    bucket = lambda h: (h % U(BUCKETS - 1)).astype(np.int32) + 1
    word = ranged(total, s, e)
    feats[0] = bucket(word)
    for i, size in enumerate(PREFIXES):
        long = np.flatnonzero(e - s > size)
        feats[1 + i, long] = bucket(ranged(total, s[long], s[long] + size) ^ U(0x5851F42D4C957F2D + size))
    inner = np.flatnonzero(~new)
    feats[OWN, inner] = bucket(mix(word[inner - 1] ^ U(0x0B)))
    feats[OWN + 1, inner - 1] = bucket(mix(word[inner] ^ U(0x0A)))
    return s, e, doc, np.cumsum(new) - 1, feats


def marginals(theta: np.ndarray, piece: np.ndarray, chain: np.ndarray, pairs: bool = False):
    """Forward-backward over all pieces at once.  ``theta`` is each word's score of the toxic state over the clean one;
    ``chain`` holds the scores of a toxic start and of the moves clean to toxic, toxic to clean and toxic to toxic.
    ``piece`` ascends without gaps.  Gives each word's marginal and each piece's log Z; with ``pairs`` also the expected
    number of each of the four for each piece."""
    lens = np.bincount(piece)
    order = np.argsort(-lens, kind="stable")
    first = (np.cumsum(lens) - lens)[order]
    live = [int(x) for x in np.searchsorted(-lens[order], -np.arange(lens.max(initial=0)), "left")]
    emit = np.exp(np.clip(theta, -30, 30))
    begin, up, down, stay = np.exp(chain)
    seen, log_z = np.zeros(len(theta)), np.zeros(len(lens))
    for t, n in enumerate(live):
        at = first[:n] + t
        f = seen[at - 1] if t else None
        clean = 1 - f + f * down if t else 1.0
        toxic = emit[at] * ((1 - f) * up + f * stay if t else begin)
        z = clean + toxic
        seen[at] = toxic / z
        log_z[order[:n]] += np.log(z)
    out, moves = seen.copy(), np.zeros((4, len(lens)))
    after = np.ones(len(lens))  # of each piece: how much better the rest goes from the toxic state than from the clean one
    for t in range(len(live) - 2, -1, -1):
        n = live[t + 1]
        at = first[:n] + t
        f, w = seen[at], emit[at + 1] * after[:n]
        if pairs:
            each = (1 - f) * up * w, f * down, f * stay * w
            whole = 1 - f + each[0] + each[1] + each[2]
            for i in range(3):
                moves[1 + i, order[:n]] += each[i] / whole
        after[:n] = (down + stay * w) / (1 + up * w)
        out[at] = f * after[:n] / (f * after[:n] + 1 - f)
    if not pairs:
        return out, log_z
    moves[0, order] = out[first]
    return out, log_z, moves


@dataclass
class Tagger:
    """Weights by bucket (those that are not zero), the chain's scores and the curve over a document's summary."""

    buckets: np.ndarray
    weights: np.ndarray
    bias: float
    chain: np.ndarray
    curve: np.ndarray

    def dense(self) -> np.ndarray:
        out = np.zeros(BUCKETS, np.float32)
        out[self.buckets] = self.weights
        return out

    def tag(self, data: np.ndarray, offs: np.ndarray, dense: np.ndarray):
        """Per text: largest marginal and expected number; and the words over one half (start, end, text number, number)."""
        n = len(offs) - 1
        s, e, doc, piece, feats = tokens(data, offs)
        top, mass = np.zeros(n), np.zeros(n)
        if len(s):
            m, _ = marginals(self.bias + scores(dense, feats), piece, self.chain)
            np.maximum.at(top, doc, m)
            mass = np.bincount(doc, m, minlength=n)
        else:
            m = np.zeros(0)
        bad = np.flatnonzero(m >= 0.5)
        return top, mass, (s[bad], e[bad], doc[bad], bad)

    def score(self, top: np.ndarray, mass: np.ndarray) -> np.ndarray:
        x = summary(top, mass) @ self.curve
        return 1 / (1 + np.exp(-np.clip(x, -500, 500)))


def scores(dense: np.ndarray, feats: np.ndarray) -> np.ndarray:
    out = np.zeros(feats.shape[1])
    for row in feats:
        out += dense[row]
    return out


def summary(top: np.ndarray, mass: np.ndarray) -> np.ndarray:
    return np.stack([np.ones_like(top), top, np.log1p(mass)], 1)


def counts(parts: list, toxic: np.ndarray, batch: int) -> np.ndarray:
    """How many clean and how many toxic texts hold each bucket; batches are gone through one at a time."""
    out = np.zeros((2, BUCKETS), np.int64)
    for i, (_, _, doc, _, feats) in enumerate(parts):
        for row in feats:
            key = np.unique(doc.astype(np.int64) * BUCKETS + row)
            is_toxic = toxic[i * batch + key // BUCKETS] == 1
            for c in (0, 1):
                out[c] += np.bincount(key[is_toxic == c] % BUCKETS, minlength=BUCKETS)
    out[:, 0] = 0
    return out


def first_guess(held: np.ndarray, toxic: np.ndarray) -> np.ndarray:
    """Where expectation starts: the lower bound of each feature's log odds in toxic over clean documents, if positive."""
    odds = np.log((held[1] + 0.5) / (held[0] + 0.5)) - np.log((toxic.sum() + 0.5) / ((1 - toxic).sum() + 0.5))
    return np.maximum(0.0, odds - 1.64 * np.sqrt(1 / (held[0] + 0.5) + 1 / (held[1] + 0.5)))


def fit(texts: list[str], toxic: np.ndarray, epochs: int = 12, batch: int = 64, rate: float = 0.02, ridge: float = 1e-4, least: int = 10, start: float = 1.0, context: bool = True, linked: bool = True) -> Tagger:
    """Train on whole texts with their labels; equal texts count once.  ``context`` and ``linked`` switch off the features
    of neighbours and the moves of the chain, to show what they add."""
    seen: dict[str, int] = {}
    for t, y in zip(texts, toxic, strict=True):
        seen.setdefault(t or "", int(y))
    texts, toxic = list(seen), np.array(list(seen.values()), float)
    prior = float(np.clip(toxic.mean() if len(toxic) else 0.5, 1e-3, 1 - 1e-3))
    flat = Tagger(np.zeros(0, np.int64), np.zeros(0, np.float32), -8.0, np.zeros(4), np.array([np.log(prior / (1 - prior)), 0.0, 0.0]))
    if not len(texts) or toxic.min() == toxic.max():
        return flat

    rng = np.random.default_rng(7)
    order = rng.permutation(len(texts))
    texts, toxic = [texts[i] for i in order], toxic[order]
    batches = []
    for i in range(0, len(texts), batch):
        _, data, offs = next(iter(blocks([pa.record_batch({"text": pa.array(texts[i : i + batch], pa.large_string())})], 1 << 40)))
        made = tokens(data, offs)
        if not context:
            made[-1][OWN:] = 0
        batches.append(made)
    held = counts(batches, toxic, batch)
    own = np.zeros(BUCKETS, bool)
    for *_, feats in batches:
        own[feats[:OWN]] = True
    names, inverse = np.flatnonzero(held.sum(0) >= least), np.zeros(BUCKETS, np.int32)
    inverse[names] = np.arange(1, len(names) + 1)
    batches = [(doc, piece, inverse[feats]) for _, _, doc, piece, feats in batches]

    k = len(names) + 1
    w = np.zeros(k + 5)  # weights, then the bias and the chain; number 0 stands for no feature
    w[1:k] = start * first_guess(held[:, names], toxic) * own[names]
    w[k : k + 2] = -6.0, -1.0
    w[k + 2 :] = -1.0, 0.0, 0.0
    fixed = np.zeros(k + 5, bool)
    fixed[0] = True
    if not linked:
        w[k + 1 :], fixed[k + 1 :] = 0.0, True
    m1, m2, step = np.zeros_like(w), np.zeros_like(w), 0
    for _ in range(epochs):
        for b in rng.permutation(len(batches)):
            doc, piece, feats = batches[b]
            y = toxic[b * batch : (b + 1) * batch]
            if not len(doc):
                continue
            marginal, log_z, moves = marginals(w[k] + scores(w, feats), piece, w[k + 1 :], True)
            owner = doc[np.flatnonzero(np.diff(piece, prepend=-1))]
            some = np.maximum(-np.expm1(-np.bincount(owner, log_z, minlength=len(y))), 1e-9)
            pull = np.where(y == 1, (1 - some) / some, -1.0)
            each = pull[doc] * marginal
            grad = np.zeros_like(w)
            for row in feats:
                grad[:k] += np.bincount(row, each, minlength=k)
            grad[k] = each.sum()
            grad[k + 1 :] = (moves * pull[owner]).sum(1)
            grad = grad / len(y) - ridge * w
            grad[fixed] = 0
            step += 1
            m1, m2 = 0.9 * m1 + 0.1 * grad, 0.99 * m2 + 0.01 * grad**2
            w += rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.99**step)) + 1e-8)

    keep = np.abs(w[1:k]) > 1e-3
    tagger = Tagger(names[keep], w[1:k][keep].astype(np.float32), float(w[k]), w[k + 1 :].copy(), flat.curve)
    top, mass = np.zeros(len(texts)), np.zeros(len(texts))
    for b, (doc, piece, feats) in enumerate(batches):
        m, _ = marginals(w[k] + scores(w, feats), piece, w[k + 1 :]) if len(doc) else (np.zeros(0), None)
        np.maximum.at(top, doc + b * batch, m)
        mass += np.bincount(doc + b * batch, m, minlength=len(texts))
    x, curve = summary(top, mass), np.zeros(3)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ curve, -500, 500)))
        curve += np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 0.01 * np.eye(3), x.T @ (toxic - p) - 0.01 * curve)
    tagger.curve = curve
    return tagger


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_sample(docs: DataFrame, labels: DataFrame, bound: int, most: int = 24 << 20) -> tuple[list[str], np.ndarray]:
    """At most ``bound`` labelled documents outside the held-out fifth, of at most ``most`` bytes together, by hash of
    their id, and their labels.  Only sizes come to the driver first."""
    known = labels.where(~held_out() & F.col("toxic").isin(0, 1)).select(F.col("doc_id").cast("long").alias("id"), F.col("toxic").alias("y"))
    part = min(1.0, 0.95 * bound / max(1, known.count()))
    chosen = known.where(F.pmod(F.xxhash64("id"), F.lit(1 << 20)) < int(part * (1 << 20))).limit(bound)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    there = docs.select(F.col("doc_id").cast("long").alias("id"), text.alias("text")).join(F.broadcast(chosen), "id")
    sizes = there.select("id", F.xxhash64("id").alias("h"), F.octet_length("text").alias("size")).limit(2 * bound).toArrow().sort_by("h")
    inside = np.cumsum(sizes["size"].to_numpy().astype(np.int64)) <= most
    ids = docs.sparkSession.createDataFrame([(i,) for i in set(sizes["id"].filter(pa.array(inside)).to_pylist())], "id long")
    rows = there.join(F.broadcast(ids), "id", "left_semi").limit(2 * bound).toArrow().sort_by([("id", "ascending"), ("text", "ascending")])
    return rows["text"].to_pylist(), rows["y"].to_numpy().astype(float)


def apply(docs: DataFrame, tagger: Tagger) -> DataFrame:
    """``doc_id, score, spans`` (``start:end`` of runs of toxic words, comma-joined)."""

    def run(batches):
        dense = tagger.dense()
        for part, data, offs in blocks(batches):
            top, mass, (s, e, doc, at) = tagger.tag(data, offs, dense)
            spans = [""] * len(top)
            if len(s):
                points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
                join = (at[1:] == at[:-1] + 1) & (doc[1:] == doc[:-1])
                first, last = np.flatnonzero(np.concatenate([[True], ~join])), np.flatnonzero(np.concatenate([~join, [True]]))
                base = points[offs[doc[first]]]
                for d, a, b in zip(doc[first].tolist(), (points[s[first]] - base).tolist(), (points[e[last]] - base).tolist(), strict=True):
                    spans[d] += f"{',' if spans[d] else ''}{a}:{b}"
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(tagger.score(top, mass)), pa.array(spans)], names=["doc_id", "score", "spans"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double, spans string")


def toxicity_scores(docs: DataFrame, labels: DataFrame, bound: int = 4_000) -> DataFrame:
    """``doc_id, held_out, score, predicted, spans``; trained on at most ``bound`` labelled documents and 24 MB of
    them."""
    tagger = fit(*training_sample(docs, labels, bound))
    return apply(docs, tagger).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "spans")
