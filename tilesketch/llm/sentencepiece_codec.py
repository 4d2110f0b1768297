"""SentencePiece encoding and decoding on the ``tokenizers`` library, rebuilt from the model file.

The model's protocol buffer is read field by field: pieces with scores and kinds, the model kind, byte fallback and the
normaliser's settings.  From these come the normaliser (its compiled map, white-space rules, the dummy prefix and the
metaspace marker), the model (unigram scores, or merges ranked by the scores of the pieces they make), byte fallback and
the decoder.  Where no piece has a marker after another character, texts are cut before each run of markers: no merge and
no piece can cross such a place, so ids stay the same and repeated words come from the cache.

``parity`` holds a codec's ids against the ``sentencepiece`` library's own.  Texts are encoded in batches on as many
threads as a task has cores (``spark.task.cpus``), or as asked for.  Ids are decoded by a gather from the bytes of all pieces, which gives what the library's
decoder gives (tested) in a tenth of its time.

Defined results: null counts as empty; an empty text has no ids.  Decoding gives the normalised text; null ids count as
none, ids outside the model are an error, and bytes that are no UTF-8 become U+FFFD; repeated rows each have a row; other
columns are ignored.  A very long text is a batch of its own and costs about 100 bytes of memory a token.
"""

from __future__ import annotations

import hashlib
import os
import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.bytewise import trim

MARK = "▁"
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
# fixed values: kinds of pieces and of models in the file format
NORMAL, UNKNOWN, CONTROL, USER, BYTE = 1, 2, 3, 4, 6
UNIGRAM, BPE = 1, 2


def _fields(b: bytes):
    """(number, value) of each field of a message: integers, 4-byte floats and byte strings."""
    at = 0

    def varint():
        nonlocal at
        x = shift = 0
        while True:
            c = b[at]
            at += 1
            x |= (c & 127) << shift
            shift += 7
            if c < 128:
                return x

    while at < len(b):
        key = varint()
        kind = key & 7
        if kind == 0:
            value = varint()
        elif kind == 5:
            value = struct.unpack("<f", b[at : at + 4])[0]
            at += 4
        elif kind == 1:
            value = b[at : at + 8]
            at += 8
        else:
            n = varint()
            value = b[at : at + n]
            at += n
        yield key >> 3, value


def parse(model: bytes) -> dict:
    """Pieces ``(text, score, kind)`` and the settings that encoding needs."""
    out = {"pieces": [], "kind": UNIGRAM, "byte_fallback": False, "map": b"", "dummy_prefix": True, "squeeze": True, "escape": True, "suffix": False}
    for number, value in _fields(model):
        if number == 1:
            f = dict(_fields(value))
            out["pieces"].append((f.get(1, b"").decode(), float(f.get(2, 0.0)), f.get(3, NORMAL)))
        elif number == 2:
            f = dict(_fields(value))
            out |= {"kind": f.get(3, UNIGRAM), "byte_fallback": bool(f.get(35, 0)), "suffix": bool(f.get(24, 0))}
        elif number == 3:
            f = dict(_fields(value))
            out |= {"map": f.get(2, b""), "dummy_prefix": bool(f.get(3, 1)), "squeeze": bool(f.get(4, 1)), "escape": bool(f.get(5, 1))}
    return out


def build(model: bytes):
    """A ``tokenizers.Tokenizer`` with the model's behaviour."""
    from tokenizers import Regex, Tokenizer, decoders, models, normalizers, pre_tokenizers

    m = parse(model)
    if m["suffix"]:
        raise ValueError("models with the marker as a suffix are not supported")
    pieces = m["pieces"]
    unknown = next(i for i, (_, _, kind) in enumerate(pieces) if kind == UNKNOWN)
    if m["kind"] == UNIGRAM:
        usable = [(t if kind in (NORMAL, USER, BYTE) else "\U0010ffff" + t, s if kind != BYTE else -1e9) for t, s, kind in pieces]
        core = models.Unigram(usable, unk_id=unknown, byte_fallback=m["byte_fallback"])
    elif m["kind"] == BPE:
        vocab = {t: i for i, (t, _, _) in enumerate(pieces)}
        joined = {t: s for t, s, kind in pieces if kind in (NORMAL, USER)}
        merges = []
        for t, s in joined.items():
            for cut in range(1, len(t)):
                if t[:cut] in joined and t[cut:] in joined:
                    merges.append((-s, vocab[t], vocab[t[:cut]], vocab[t[cut:]], t[:cut], t[cut:]))
        merges.sort()
        core = models.BPE(vocab, [x[4:] for x in merges], unk_token=pieces[unknown][0], fuse_unk=True, byte_fallback=m["byte_fallback"])
    else:
        raise ValueError(f"model kind {m['kind']} is not supported")
    out = Tokenizer(core)
    steps = [normalizers.Precompiled(m["map"])] if m["map"] else []
    if m["squeeze"]:
        steps += [normalizers.Replace(Regex(" {2,}"), " "), normalizers.Strip()]
    if m["dummy_prefix"]:
        steps.append(normalizers.Prepend(" "))
    if m["escape"]:
        steps.append(normalizers.Replace(" ", MARK))
    if steps:
        out.normalizer = normalizers.Sequence(steps)
    if not any(MARK in t.lstrip(MARK) for t, _, kind in pieces if kind in (NORMAL, USER)):
        out.pre_tokenizer = pre_tokenizers.Split(Regex(f"{MARK}*[^{MARK}]+|{MARK}+"), "isolated")
    tail = [decoders.Strip(" ", 1, 0)] if m["dummy_prefix"] else []
    out.decoder = decoders.Sequence([decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse(), *tail])
    return out


def parity(model: bytes, texts: list[str]) -> list[int]:
    """Numbers of the texts whose ids differ from the ``sentencepiece`` library's."""
    import sentencepiece

    theirs = sentencepiece.SentencePieceProcessor(model_proto=model).encode(texts, num_threads=1)
    ours = build(model).encode_batch(texts, add_special_tokens=False)
    return [i for i, (a, b) in enumerate(zip(ours, theirs, strict=True)) if a.ids != b]


class Decoder:
    """The bytes that ids stand for."""

    def __init__(self, model: bytes):
        m = parse(model)
        parts = [bytes([int(t[3:5], 16)]) if kind == BYTE else t.replace(MARK, " ").encode() for t, _, kind in m["pieces"]]
        self.size = np.array([len(p) for p in parts], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.pool = np.frombuffer(b"".join(parts), np.uint8)
        self.prefix = m["dummy_prefix"]

    def _joined(self, ids: np.ndarray) -> bytes:
        size = self.size[ids]
        ends = np.cumsum(size)
        return self.pool[np.repeat(self.start[ids] - ends + size, size) + np.arange(size.sum())].tobytes()

    def decode(self, ids: np.ndarray, offs: np.ndarray, step: int = 1 << 18) -> list[bytes]:
        """One byte string for each range of the concatenated ids."""
        if len(ids) and not 0 <= ids.min() <= ids.max() < len(self.size):
            raise ValueError("ids outside the model")
        raw = b"".join(self._joined(ids[i : i + step]) for i in range(0, len(ids), step))
        at = np.concatenate([[0], np.cumsum(self.size[ids])])[offs].tolist()
        texts = [raw[i:j] for i, j in zip(at[:-1], at[1:], strict=True)]
        return [x[1:] if x[:1] == b" " else x for x in texts] if self.prefix else texts


_coders: dict[str, tuple] = {}


def set_threads(threads: int | None = None) -> int:
    """Threads of the library in this process: as given, else the cores of the running task.  Counts before its first batch
    only."""
    from pyspark import TaskContext

    task = TaskContext.get()
    n = threads or (task.cpus() if task else 1)
    os.environ["RAYON_NUM_THREADS"] = os.environ["RAYON_RS_NUM_CPUS"] = str(n)
    os.environ["TOKENIZERS_PARALLELISM"] = "true"
    return n


def _coder(model: bytes):
    key = hashlib.sha256(model).hexdigest()
    if key not in _coders:
        _coders[key] = build(model), Decoder(model)
    return _coders[key]


def encoded(docs: DataFrame, model: bytes, size: int = 1 << 20, threads: int | None = None) -> DataFrame:
    """``doc_id, ids array<int>, n_tokens, round_trip``: whether decoding gives back the text; ``ids_sha256`` is of the
    ids as little-endian 4-byte numbers."""

    def run(batches):
        set_threads(threads)
        coder, decoder = _coder(model)
        for b in batches:
            ids, texts = b.column(0), b.column(1)
            at = 0
            while at < len(texts):
                part, total = [], 0
                while at + len(part) < len(texts) and (not part or total < size):
                    part.append(texts[at + len(part)].as_py() or "")
                    total += len(part[-1])
                got = [np.array(x.ids, np.int32) for x in coder.encode_batch_fast(part, add_special_tokens=False)]
                lens = np.array([len(x) for x in got], np.int64)
                offs = np.concatenate([[0], np.cumsum(lens)]).astype(np.int32)
                flat = np.concatenate(got) if got else np.zeros(0, np.int32)
                back = decoder.decode(flat, offs)
                yield pa.RecordBatch.from_arrays([ids.slice(at, len(part)), pa.ListArray.from_arrays(pa.array(offs), pa.array(flat)), pa.array(lens), pa.array([x.encode() == y for x, y in zip(part, back, strict=True)]), pa.array([hashlib.sha256(x.tobytes()).hexdigest() for x in got])], names=["doc_id", "ids", "n_tokens", "round_trip", "ids_sha256"])
                at += len(part)
            trim()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>, n_tokens long, round_trip boolean, ids_sha256 string")


def decoded(encodings: DataFrame, model: bytes) -> DataFrame:
    """``doc_id, text`` of the rows ``(doc_id, ids)``."""

    def run(batches):
        decoder = _coder(model)[1]
        for b in batches:
            lists = b.column(1).fill_null([]) if b.column(1).null_count else b.column(1)
            offs = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
            back = decoder.decode(lists.flatten().to_numpy(zero_copy_only=False), offs)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.decode(errors="replace") for x in back], pa.string())], names=["doc_id", "text"])
            trim()

    return encodings.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("ids").cast("array<int>").alias("ids")).mapInArrow(run, "doc_id long, text string")


def model_bytes(path: str = DEFAULT_MODEL) -> bytes:
    with open(path, "rb") as f:
        return f.read()
