"""N-gram Jaccard join by prefix filters under several global token orders.

Tokens are the distinct k-word shingles of a text.  Two texts whose Jaccard similarity reaches the threshold share at
least ``need(n) = ceil(t * n)`` tokens, ``n`` being the size of either set, so under *every* global order of the tokens
their first ``n - need(n) + 1`` tokens have one in common.  Three orders are used:

* rarest first: tokens that one text alone holds come first, so a text with more than ``n - need(n)`` of them is out at
  once; of the rest, the prefixes are joined;
* by hash, ascending, and by hash, descending: a joined pair must also share a token of both prefixes before its full
  sets are compared.

Which tokens are shared is counted over all texts: each task sorts the tokens of about two million, packs them by range
of the hash into byte planes, and one task for each range finds the tokens that more than one text holds.  The number of
ranges follows the size of the input: a range holds the tokens of about ``RANGE`` bytes of it up to 8 GB, 64 MB at 8 TB
and 400 MB at 100 TB.  A token that is frequent in a task is sent once from it, however many
texts hold it.  Texts are read twice, and what the two readings send is matched by a fingerprint of the texts it came from;
an input that is more than a scan of files is written to a table first, and a fingerprint without its texts is an error.

A token is a 64-bit hash.  Two different tokens of equal hash can make a similarity too large by one token of a set; among
10^13 tokens about 10^7 pairs are expected, so of unlike texts none is linked by them.

Equal sets are one class.  Inside a group of classes that share a prefix token, every member is first compared with
pivots.  Members that still lie in different components are compared with each other: pair by pair in groups of up to
``crowd``, and in larger groups block by block, as products of incidence matrices, so that rows grow with the number of
pairs of blocks.  No pair that could link two components is left out.

Defined results: null, empty and white-space texts have 0 shingles and stand alone; a text shorter than k words has one
shingle; rows of equal ``doc_id`` count as one document; rows without a ``doc_id`` are left out; other columns are ignored;
no rows give no rows.  A very long text is in one task with about 60 bytes of memory a byte.
"""

from __future__ import annotations

from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import U, blocks, lists, shingle_sets, trim
from tilesketch.llm.scratch import by_key, components, drop, keep, release

FLUSH, RANGE = 1 << 21, 1 << 21
_ANY = (1 << 32) - 1  # stands for a token that several texts of one task hold


def _pack(x: np.ndarray) -> bytes:
    """Byte planes: those that are all zero compress to nothing."""
    return np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes()


def _unpack(b: bytes, kind: type) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).reshape(-1).view(kind)


def _steps(x: np.ndarray) -> np.ndarray:
    return np.diff(x, prepend=x.dtype.type(0))


_SENT = pa.schema([("bucket", pa.int32()), ("task", pa.int64()), ("tokens", pa.binary()), ("owners", pa.binary()), ("ids", pa.binary()), ("sizes", pa.binary())])
_SENT_SQL = "bucket int, task long, tokens binary, owners binary, ids binary, sizes binary"


def _send(k: int, bits: int, local: bool):
    """For each task: its tokens by range of the hash (``local`` False), or its texts and the tokens that two or more of
    them share (True)."""

    def flush(toks, owners, ids, sizes):
        tok, owner = np.concatenate(toks), np.concatenate(owners).astype(np.uint32)
        toks.clear(), owners.clear()
        ids, sizes = np.concatenate(ids), np.concatenate(sizes).astype(np.uint32)
        task = int.from_bytes(blake2b(ids.tobytes() + sizes.tobytes() + np.bitwise_xor.reduce(tok, initial=U(0)).tobytes(), digest_size=8).digest(), "little", signed=True)
        order = np.argsort(tok, kind="stable")
        tok, owner = tok[order], owner[order]
        del order
        again = np.zeros(len(tok), bool)
        again[1:] = tok[1:] == tok[:-1]
        both = again.copy()
        both[:-1] |= again[1:]
        if local:
            at = np.flatnonzero(both)
            return pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((0, task, _pack(_steps(tok[at])), _pack(owner[at]), _pack(_steps(ids)), _pack(sizes)), _SENT, strict=True)], schema=_SENT)
        owner[both] = _ANY
        tok, owner = tok[~again], owner[~again]
        cut = np.searchsorted(tok, np.arange(1, 1 << bits, dtype=U) << U(64 - bits))
        rows = [(i, task, _pack(_steps(t)), _pack(o), None, None) for i, (t, o) in enumerate(zip(np.split(tok, cut), np.split(owner, cut), strict=True)) if len(t)]
        return pa.RecordBatch.from_pylist([dict(zip(_SENT.names, r, strict=True)) for r in rows], schema=_SENT)

    def run(batches):
        held, texts, total = ([], [], [], []), 0, 0
        for part, data, offs in blocks(batches):
            tok, owner, size = shingle_sets(data, offs, k)
            for box, x in zip(held, (tok, owner + texts, part.column(0).to_numpy(zero_copy_only=False).astype(np.int64), size), strict=True):
                box.append(x)
            texts, total = texts + len(size), total + len(tok)
            if total >= FLUSH:
                yield flush(*held)
                held, texts, total = ([], [], [], []), 0, 0
                trim()
        if texts:
            yield flush(*held)

    return run


def _find_shared(table: pa.Table) -> pa.Table:
    """Of one range of the hash: the tokens that more than one text holds, back to the tasks whose texts hold them."""
    toks = [np.cumsum(_unpack(b, U), dtype=U) for b in table["tokens"].to_pylist()]
    owners = [_unpack(b, np.uint32) for b in table["owners"].to_pylist()]
    tasks = table["task"].to_pylist()
    tok = np.concatenate(toks)
    order = np.argsort(tok, kind="stable")
    again = tok[order][1:] == tok[order][:-1]
    shared = np.zeros(len(tok), bool)
    shared[order[1:][again]] = shared[order[:-1][again]] = True
    del tok, order, again
    out, at = [], 0
    for task, t, o in zip(tasks, toks, owners, strict=True):
        mine = shared[at : at + len(t)] & (o != _ANY)
        at += len(t)
        if mine.any():
            out.append((0, task, _pack(_steps(t[mine])), _pack(o[mine]), None, None))
    del toks, owners
    trim()
    return pa.Table.from_pylist([dict(zip(_SENT.names, r, strict=True)) for r in out], schema=_SENT)


def _gather(percent: int):
    def run(table: pa.Table) -> pa.Table:
        tok = np.concatenate([np.cumsum(_unpack(b, U), dtype=U) for b in table["tokens"].to_pylist()])
        owner = np.concatenate([_unpack(b, np.uint32) for b in table["owners"].to_pylist()]).astype(np.int64)
        texts = [(np.cumsum(_unpack(i, np.int64)), _unpack(n, np.uint32).astype(np.int64)) for i, n in zip(table["ids"].to_pylist(), table["sizes"].to_pylist(), strict=True) if i is not None]
        if not texts:
            raise RuntimeError("the two readings of the input gave different texts")
        ids, n = texts[0]  # a fingerprint that occurs twice is of rows that are equal throughout
        held = np.bincount(owner, minlength=len(n))
        stays = (held * 100 >= percent * n) & (n > 0)
        mine = stays[owner]
        tok, owner = tok[mine], owner[mine]
        order = np.argsort(tok.view(np.int64), kind="stable")
        order = order[np.argsort(owner[order], kind="stable")]
        trim()
        return pa.table({"doc_id": ids, "n": n, "stays": stays, "toks": lists(tok[order], np.where(stays, held, 0))})

    return run


def _scans_only(docs: DataFrame) -> bool:
    """Whether a table comes straight from files, so that it can be read twice with the same rows in each task."""
    plan = docs._jdf.queryExecution().optimizedPlan()
    while plan.nodeName() in ("Project", "Filter"):
        plan = plan.children().head()
    return plan.nodeName().startswith("LogicalRelation") or plan.nodeName().startswith("Relation")


def ranges(docs: DataFrame) -> int:
    """The number of ranges of the hash, a power of two, by the size of the files: one for each ``RANGE`` bytes up to 2^12
    ranges, and beyond that as the square root, so that what a task sends to a range does not get too small."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    bits = max(6, (size // RANGE).bit_length())
    return 1 << (bits if bits <= 12 else min(18, 12 + (bits - 12) // 2))


def shared_tokens(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """Per document: ``n`` distinct shingles, whether enough of them are shared for any link (``stays``), and if so the
    hashes of the shared ones, ascending."""
    docs = docs if _scans_only(docs) else keep(docs.select("doc_id", "text"))
    texts = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    bits = ranges(texts).bit_length() - 1
    local = texts.mapInArrow(_send(k, bits, True), _SENT_SQL)
    sent = texts.mapInArrow(_send(k, bits, False), _SENT_SQL)
    found = sent.groupBy("bucket").applyInArrow(_find_shared, _SENT_SQL)
    return local.unionByName(found).groupBy("task").applyInArrow(_gather(percent), "doc_id long, n long, stays boolean, toks array<long>")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs ``(a, b)`` whose prefixes meet under the two hash orders and whose sets reach the threshold."""
    spare = (F.col("n") - F.ceil(F.col("n") * percent / 100) + 1).cast("int")
    side = lambda x: sets.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("toks").alias(f"t{x}"), F.slice("toks", 1, spare).alias(f"low{x}"), F.slice("toks", F.greatest(F.size("toks") - spare + 1, F.lit(1)), spare).alias(f"high{x}"))
    met = pairs.join(side("a"), "a").join(side("b"), "b").where(F.arrays_overlap("lowa", "lowb") & F.arrays_overlap("higha", "highb"))
    both = F.size(F.array_intersect("ta", "tb"))
    return met.where(100 * both >= percent * (F.col("na") + F.col("nb") - both)).select("a", "b")


def _incidence(rows: np.ndarray, toks: np.ndarray, n: int, vocab: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(vocab, toks), len(vocab) - 1)
    use = vocab[at] == toks
    out = np.zeros((n, len(vocab)), np.float32)
    out[rows[use], at[use]] = 1
    return out


def _meets(x: tuple, y: tuple, nx: int, ny: int, step: int = 8192) -> np.ndarray:
    """How many tokens each row of x shares with each row of y; a side is (row numbers, tokens)."""
    out = np.zeros((nx, ny), np.float32)
    vocab = np.intersect1d(x[1], y[1])
    for i in range(0, len(vocab), step):
        part = vocab[i : i + step]
        out += _incidence(*x, nx, part) @ _incidence(*y, ny, part).T
    return out


def _compare(percent: int):
    """Pairs of blocks of sets: filters under both hash orders, full counts where any pair is left, and for each linked
    set the smallest id it is linked with inside the two blocks."""

    def side(r, x):
        sets = r[x]
        n = np.array([s["n"] for s in sets], np.int64)
        toks = [np.array(s["toks"], np.int64) for s in sets]
        spare = n + (-percent * n) // 100 + 1
        rows = lambda parts: (np.repeat(np.arange(len(parts)), [len(t) for t in parts]), np.concatenate(parts))
        return np.array([s["id"] for s in sets], np.int64), n, rows(toks), rows([t[:k] for t, k in zip(toks, spare, strict=True)]), rows([t[max(0, len(t) - k) :] for t, k in zip(toks, spare, strict=True)])

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                (xi, xn, *x), (yi, yn, *y) = side(r, "xs"), side(r, "ys")
                size = len(xi), len(yi)
                if not ((_meets(x[1], y[1], *size) > 0) & (_meets(x[2], y[2], *size) > 0)).any():
                    continue
                both = _meets(x[0], y[0], *size).astype(np.int64)
                rows, cols = np.nonzero(100 * both >= percent * (xn[:, None] + yn[None, :] - both))
                least = {}
                for i in np.unique(np.concatenate([xi[rows], yi[cols]])).tolist():
                    least[i] = i

                def top(i, least=least):
                    while least[i] != i:
                        least[i] = i = least[least[i]]
                    return i

                for i, j in zip(xi[rows].tolist(), yi[cols].tolist(), strict=True):
                    i, j = top(i), top(j)
                    least[max(i, j)] = min(i, j)
                found = [(i, top(i)) for i in least if top(i) != i]
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array([f[1] for f in found], pa.int64()), pa.array([f[0] for f in found], pa.int64())], names=["a", "b"])

    return run


def block_links(posts: DataFrame, sets: DataFrame, percent: int, block: int = 256) -> DataFrame:
    """Links among the sets of ``posts(tok, id)`` that share a token, found by comparing blocks of about ``block`` sets:
    rows grow with the number of pairs of blocks, not of sets.  Sets with the same most common token lie together."""
    common = keep(posts.groupBy("tok").agg(F.count(F.lit(1)).alias("c")))
    lead = by_key(posts, common, "tok").groupBy("id").agg(F.max(F.struct("c", "tok")).alias("lead"))
    crowd = lead.groupBy("lead").agg(F.ceil(F.count(F.lit(1)) / block).alias("parts"))
    placed = keep(lead.join(crowd, "lead").select("id", F.xxhash64("lead.tok", F.pmod(F.xxhash64("id"), "parts")).alias("block")))
    at = posts.join(placed, "id").select("tok", "block").distinct()
    pairs = at.select("tok", F.col("block").alias("x")).join(at.select("tok", F.col("block").alias("y")), "tok").where("x <= y").select("x", "y").distinct()
    packed = keep(placed.join(sets, "id").groupBy("block").agg(F.collect_list(F.struct("id", "n", "toks")).alias("sets")))
    side = lambda x: packed.select(F.col("block").alias(x), F.col("sets").alias(f"{x}s"))
    spread = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return pairs.join(side("x"), "x").join(side("y"), "y").repartition(spread, "x", "y").mapInArrow(_compare(percent), "a long, b long")


def links(sets: DataFrame, percent: int = 80, pivots: int = 2, crowd: int = 64) -> DataFrame:
    """Components of the distinct sets ``(id, n, toks)``: ``(id, component)`` of every set with a link."""
    held = sets.select("id", "n", F.explode("toks").alias("tok"))
    df = held.groupBy("tok").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    ranked = held.join(df, "tok").groupBy("id", "n").agg(F.array_sort(F.collect_list(F.struct("df", "tok"))).alias("ranked"))
    need = F.ceil(F.col("n") * percent / 100)
    ranked = ranked.where(F.size("ranked") >= need)
    first = ranked.select("id", "n", F.explode(F.slice("ranked", 1, (F.size("ranked") - need + 1).cast("int"))).alias("x")).select("id", "n", F.col("x.tok").alias("tok"))
    posts = keep(first)
    release(sets.sparkSession)
    done, edges, label = None, None, None
    temporary = [posts]
    for turn in range(pivots + 1):
        at = posts.withColumn("label", F.col("id")) if label is None else keep(posts.join(label, "id", "left").withColumn("label", F.coalesce("component", "id")).drop("component"))
        few = F.count(F.lit(1)).alias("c"), F.min("label").alias("low"), F.max("label").alias("high")
        pivot = F.min(F.struct(F.xxhash64("id", F.lit(turn)), "id", "n", "label")).alias("pivot")
        span = keep(at.groupBy("tok").agg(*few, pivot).where("low < high").drop("low", "high"))
        temporary += [span] if label is None else [at, span]
        open_ = by_key(at, span, "tok")
        if turn < pivots:
            met = open_.where("label <> pivot.label").select("id", "n", F.col("pivot.id").alias("other"), F.col("pivot.n").alias("m"))
        else:
            few, many = open_.where(F.col("c") <= crowd), open_.where(F.col("c") > crowd)
            met = few.join(few.select("tok", F.col("id").alias("other"), F.col("n").alias("m"), F.col("label").alias("its")), "tok").where("label < its")
        pairs = met.where((100 * F.least("n", "m")) >= percent * F.greatest("n", "m")).select(F.least("id", "other").alias("a"), F.greatest("id", "other").alias("b")).distinct()
        pairs = keep(pairs if done is None else pairs.join(done, ["a", "b"], "left_anti"))
        temporary.append(pairs)
        done = pairs if done is None else done.unionByName(pairs)
        new = verified(pairs, sets, percent)
        new = keep(new if turn < pivots else new.unionByName(block_links(many.select("tok", "id"), sets, percent)))
        temporary.append(new)
        edges = new if edges is None else edges.unionByName(new)
        if turn and new.isEmpty():
            continue
        if label is not None:
            temporary.append(label)
        label = components(edges)
    drop(*temporary)
    return label


def ngram_components(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """One row per document: ``doc_id``, ``n_shingles`` and ``component_id``, the smallest ``doc_id`` reachable by links
    (Jaccard of the shingle sets at least ``percent`` of 100)."""
    sets = keep(shared_tokens(docs, k, percent))
    release(docs.sparkSession)
    live = sets.where("stays")
    whole = F.size("toks") == F.col("n")
    keyed = live.select("doc_id", "n", "toks", F.when(whole, F.xxhash64("toks")).otherwise(F.col("doc_id")).alias("k1"), F.when(whole, F.xxhash64(F.lit(1), F.reverse("toks"))).otherwise(F.lit(0)).alias("k2"), whole.alias("whole"))
    key = ["k1", "k2", "whole", "n"]
    classes = keep(keyed.groupBy(*key).agg(F.min("doc_id").alias("id"), F.min_by("toks", "doc_id").alias("toks")))
    release(docs.sparkSession)
    label = links(classes.select("id", "n", "toks"), percent)
    members = keyed.select("doc_id", *key).join(classes.select("id", *key), key).join(label, "id", "left").select("doc_id", F.coalesce("component", "id").alias("component"))
    members = members.groupBy("doc_id").agg(F.min("component").alias("component"))
    sizes = sets.groupBy("doc_id").agg(F.max("n").alias("n_shingles"))
    return sizes.join(members, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
