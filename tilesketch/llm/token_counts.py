"""Token counts of a unigram vocabulary by dynamic programming over a trie of distinct pre-tokens.

Texts are normalised as the model says: a marker for every space and one before the text; other white space stays.  The
text is cut before each run of markers, and on both sides of a run of line feeds, tabs and the like that stand in no
piece; no piece crosses such a place, so the best segmentation of the whole text is that of its parts, the pre-tokens.  A
vocabulary with a marker inside of a piece has whole texts as pre-tokens.  The distinct pre-tokens of a block are sorted,
so those with a common prefix stand together and each node of their trie, one for each distinct prefix, is one entry of its
level.  The best score of a node is the best of its ancestors' scores plus that of the piece between, so a shared prefix is
scored once; what stands at a pre-token's last node is its number of tokens, and that is stored.  Counts that a worker has
stored serve its later blocks; the store is emptied when it grows over a bound.

A pre-token of more than ``LONG`` bytes (text without spaces, or a blob) is first cut wherever no occurrence of a piece
reaches over the place: all occurrences are found together, by extending every start by a byte while what it spells begins
some piece.  What is cut so goes through the trie like any other pre-token; a stretch that is still longer than ``LONG``
is scored over the occurrences that were found in it.

Of equal scores the fewer tokens win.  A character without a piece scores ten below the lowest piece and counts as many
tokens as it has bytes (byte fallback).

Defined results: null and empty texts have 0 pre-tokens and 0 tokens; white space counts; other columns are ignored; repeated
rows each have a row; no rows give no rows.  A very long text costs about 60 bytes of memory a byte.  Pre-tokens are told
apart by a 64-bit hash: among the 2^20 that a worker stores, two with one hash have a chance of 2^-22.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import U, blocks, hashes, ranged, sums
from tilesketch.llm.sentencepiece_codec import MARK, NORMAL, USER, parse

LONG = 256
BITS = U((1 << 20) - 1)


class Vocabulary:
    """Piece scores by bytes and by hash, and the stored counts of pre-tokens."""

    def __init__(self, scores: dict[str, float], store: int = 1 << 20):
        by_bytes = {t.encode(): s for t, s in scores.items()}
        raw = list(by_bytes)
        ends = np.cumsum([len(x) for x in raw])
        keys = hashes(np.frombuffer(b"".join(raw), np.uint8), ends - [len(x) for x in raw], ends)
        order = np.argsort(keys)
        self.keys, self.scores = keys[order], np.array(list(by_bytes.values()))[order]
        self.near = np.zeros(1 << 20, bool)
        self.near[(keys & BITS).astype(np.int64)] = True
        self.lengths = sorted({len(x) for x in raw})
        total, start, size = sums(np.frombuffer(b"".join(raw), np.uint8)), ends - [len(x) for x in raw], np.array([len(x) for x in raw])
        self.begins = np.unique(np.concatenate([ranged(total, start[size >= k], start[size >= k] + k) for k in range(1, self.lengths[-1] + 1)]))
        self.begun = np.zeros(1 << 20, bool)
        self.begun[(self.begins & BITS).astype(np.int64)] = True
        self.unknown = float(min(self.scores)) - 10
        self.cuts = not any(MARK in t.lstrip(MARK) for t in scores)
        self.breaks = np.zeros(256, bool)
        self.breaks[[x for x in range(9, 14) if not any(chr(x) in t for t in scores)]] = True
        self.prefix, self.squeeze, self.normal = True, False, None
        self.store, self.known, self.counts = store, np.zeros(0, U), np.zeros(0, np.int64)

    def occurrences(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start, length and score of every occurrence of a piece in a text of UTF-8."""
        total = sums(data)
        live = np.flatnonzero((data & 0xC0) != 0x80)
        found = []
        for k in range(1, self.lengths[-1] + 1):
            live = live[live + k <= len(data)]
            key = ranged(total, live, live + k)
            near = np.flatnonzero(self.begun[(key & BITS).astype(np.int64)])
            live, key = live[near], key[near]
            at = np.minimum(np.searchsorted(self.begins, key), len(self.begins) - 1)
            good = self.begins[at] == key
            live, key = live[good], key[good]
            if not len(live):
                break
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            good = np.flatnonzero(self.keys[at] == key)
            found.append((live[good], np.full(len(good), k), self.scores[at[good]]))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))

    def parts(self, word: bytes) -> tuple[list[bytes], int]:
        """A long pre-token as parts of at most ``LONG`` bytes that no piece joins, and the tokens of its longer stretches."""
        data = np.frombuffer(word, np.uint8)
        start, size, score = self.occurrences(data)
        over = np.zeros(len(data) + 1, np.int64)
        np.add.at(over, start + 1, 1)
        np.add.at(over, start + size, -1)
        whole = np.append((data & 0xC0) != 0x80, True)
        cut = np.flatnonzero((np.cumsum(over) == 0) & whole)
        out, tokens = [], 0
        for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            if j - i <= LONG:
                out.append(word[i:j])
        long = np.flatnonzero(np.diff(cut) > LONG)
        if len(long):
            order = np.argsort(start, kind="stable")
            start, size, score = start[order], size[order], score[order]
        for c in long.tolist():
            i, j = int(cut[c]), int(cut[c + 1])
            a, b = np.searchsorted(start, [i, j])
            tokens += self.stretch(word[i:j], start[a:b] - i, size[a:b], score[a:b])
        return out, tokens

    def stretch(self, word: bytes, start: np.ndarray, size: np.ndarray, score: np.ndarray) -> int:
        """Tokens of the best way through the occurrences, by start."""
        n = len(word)
        best, count = [float("-inf")] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        steps, at = list(zip(start.tolist(), (start + size).tolist(), score.tolist(), strict=True)), 0
        for i in range(n):
            here, so_far = best[i], count[i]
            if here == float("-inf"):
                while at < len(steps) and steps[at][0] == i:
                    at += 1
                continue
            c = word[i]
            width = 1 if c < 0x80 else 2 if c < 0xE0 else 3 if c < 0xF0 else 4
            to, value, tokens = min(n, i + width), here + self.unknown, so_far + width
            if value > best[to] or (value == best[to] and tokens < count[to]):
                best[to], count[to] = value, tokens
            while at < len(steps) and steps[at][0] == i:
                _, to, value = steps[at]
                value += here
                if value > best[to] or (value == best[to] and so_far + 1 < count[to]):
                    best[to], count[to] = value, so_far + 1
                at += 1
        return count[n]

    def trie(self, pre: list[bytes]) -> np.ndarray:
        """Tokens of each of the sorted distinct pre-tokens, by one pass over the levels of their trie."""
        size = np.array([len(x) for x in pre], np.int64)
        data = np.frombuffer(b"".join(pre), np.uint8)
        start = np.cumsum(size) - size
        total = sums(data)
        out = np.zeros(len(pre), np.int64)
        node = [np.zeros(len(pre), np.int32)]
        best, count = [np.zeros(1)], [np.zeros(1, np.int64)]
        for d in range(1, int(size.max(initial=0)) + 1):
            live = np.flatnonzero(size >= d)
            h = ranged(total, start[live], start[live] + d)
            new = np.ones(len(live), bool)
            new[1:] = h[1:] != h[:-1]
            mine = np.zeros(len(pre), np.int32)
            mine[live] = np.cumsum(new) - 1
            rep = live[new]
            b, c = np.full(len(rep), -np.inf), np.zeros(len(rep), np.int64)

            def offer(to, score, tokens, b=b, c=c):
                wins = (score > b[to]) | ((score == b[to]) & (tokens < c[to]))
                b[to[wins]], c[to[wins]] = score[wins], tokens[wins]

            for k in self.lengths:
                if k > d:
                    break
                key = ranged(total, start[rep] + d - k, start[rep] + d)
                hit = np.flatnonzero(self.near[(key & BITS).astype(np.int64)])
                at = np.minimum(np.searchsorted(self.keys, key[hit]), len(self.keys) - 1)
                good = self.keys[at] == key[hit]
                hit, at = hit[good], at[good]
                up = node[d - k][rep[hit]]
                offer(hit, best[d - k][up] + self.scores[at], count[d - k][up] + 1)
            for k in (1, 2, 3, 4):
                if k <= d:
                    first = data[start[rep] + d - k]
                    width = np.where(first < 0x80, 1, np.where(first < 0xC0, 0, np.where(first < 0xE0, 2, np.where(first < 0xF0, 3, 4))))
                    hit = np.flatnonzero(width == k)
                    up = node[d - k][rep[hit]]
                    offer(hit, best[d - k][up] + self.unknown, count[d - k][up] + k)
            node.append(mine)
            best.append(b)
            count.append(c)
            done = np.flatnonzero(size == d)
            out[done] = c[mine[done]]
        return out

    def tokens(self, key: np.ndarray, raw) -> np.ndarray:
        """Counts of distinct pre-tokens by hash; ``raw(i)`` gives the bytes of number i, and is called for new ones only."""
        at = np.minimum(np.searchsorted(self.known, key), max(0, len(self.known) - 1))
        have = self.known[at] == key if len(self.known) else np.zeros(len(key), bool)
        out = np.zeros(len(key), np.int64)
        out[have] = self.counts[at[have]]
        fresh = np.flatnonzero(~have)
        if len(fresh):
            count, own, pre = np.zeros(len(fresh), np.int64), [], []
            for i, number in enumerate(fresh.tolist()):
                x = raw(number).replace(b" ", MARK.encode())
                some, count[i] = ([x], 0) if len(x) <= LONG else self.parts(x)
                pre += some
                own += [i] * len(some)
            distinct = sorted(set(pre))
            place = dict(zip(distinct, range(len(distinct)), strict=True))
            if pre:
                count += np.bincount(own, self.trie(distinct)[[place[x] for x in pre]], minlength=len(fresh)).astype(np.int64)
            out[fresh] = count
            if len(self.known) + len(fresh) > self.store:
                self.known, self.counts = np.zeros(0, U), np.zeros(0, np.int64)
            known = np.concatenate([self.known, key[fresh]])
            order = np.argsort(known)
            self.known, self.counts = known[order], np.concatenate([self.counts, out[fresh]])[order]
        return out


    def normalised(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes and offsets of the normalised texts, with a space for each marker."""
        mark = MARK.encode()
        if self.normal is not None or self.squeeze or mark in data.tobytes():
            texts = [data[a:b].tobytes() for a, b in zip(offs[:-1], offs[1:], strict=True)]
            if self.normal is not None:
                texts = [self.normal.normalize_str(x.decode()).encode() for x in texts]
            if self.squeeze:
                texts = [re.sub(b" {2,}", b" ", x).strip(b" ") for x in texts]
            texts = [x.replace(mark, b" ") for x in texts]
            data, offs = np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)])
        if self.prefix:
            full = offs[1:] > offs[:-1]
            data = np.insert(data, offs[:-1][full], 32)
            offs = offs + np.concatenate([[0], np.cumsum(full)])
        return data, offs

    def pretokens(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and text numbers of the pre-tokens of normalised texts."""
        first = np.zeros(len(data), bool)
        first[offs[:-1][offs[1:] > offs[:-1]]] = True
        if self.cuts:
            space, apart = data == 32, self.breaks[data]
            first[1:] |= (space[1:] & ~space[:-1]) | (apart[1:] != apart[:-1])
        s = np.flatnonzero(first)
        return s, np.append(s[1:], len(data))[: len(s)], np.searchsorted(offs, s, "right") - 1


def vocabulary(model: bytes) -> Vocabulary:
    m = parse(model)
    if m["suffix"] or not m["escape"]:
        raise ValueError("models with the marker as a suffix or without markers are not supported")
    out = Vocabulary({t: s for t, s, kind in m["pieces"] if kind in (NORMAL, USER)})
    out.prefix, out.squeeze = m["dummy_prefix"], m["squeeze"]
    if m["map"]:
        from tokenizers import normalizers

        out.normal = normalizers.Precompiled(m["map"])
    return out


_made: dict[int, Vocabulary] = {}


def token_counts(docs: DataFrame, model: bytes) -> DataFrame:
    """``doc_id, n_pretokens, n_tokens`` of every row."""

    def run(batches):
        key = hash(model)
        if key not in _made:
            _made[key] = vocabulary(model)
        vocab = _made[key]
        for part, data, offs in blocks(batches):
            n = len(offs) - 1
            data, offs = vocab.normalised(data, offs)
            s, e, doc = vocab.pretokens(data, offs)
            h = hashes(data, s, e)
            distinct, first, which = np.unique(h, return_index=True, return_inverse=True)
            counts = vocab.tokens(distinct, lambda i, s=s, e=e, first=first, data=data: data[s[first[i]] : e[first[i]]].tobytes())
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.bincount(doc, minlength=n).astype(np.int64)), pa.array(np.bincount(doc, counts[which], minlength=n).astype(np.int64))], names=["doc_id", "n_pretokens", "n_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_pretokens long, n_tokens long")
