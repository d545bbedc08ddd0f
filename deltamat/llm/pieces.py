"""SentencePiece encoding and decoding on the tokenizers library.

The model file's protobuf is read field by field; normaliser, metaspace marker, scores and byte
fallback are rebuilt as a tokenizers pipeline (unigram, or merges for a BPE model), batches are
encoded by its threads, and its ids are held against the sentencepiece library's.
"""

from __future__ import annotations

import hashlib
import os
import re
import struct
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common

# The marker, field numbers and piece types of the public model format.
MARK = "▁"
PIECES, TRAINER, NORMALIZER = 1, 2, 3
UNKNOWN, CONTROL, USER_DEFINED, BYTE = 2, 3, 4, 6
UNIGRAM, BPE = 1, 2

MODEL = "/opt/tokenizers/piece_bpe_32k.model"


@dataclass
class Model:
    pieces: list[tuple[str, float, int]]
    kind: int
    charsmap: bytes
    dummy_prefix: bool
    squeeze: bool
    escape: bool

    @property
    def unknown(self) -> int:
        return next(k for k, p in enumerate(self.pieces) if p[2] == UNKNOWN)

    @property
    def byte_fallback(self) -> bool:
        return any(p[2] == BYTE for p in self.pieces)


def _varint(data: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = data[at]
        at += 1
        value |= (byte & 127) << shift
        shift += 7
        if byte < 128:
            return value, at


def proto(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field number, raw value) of a protobuf message."""
    at = 0
    while at < len(data):
        key, at = _varint(data, at)
        if key & 7 == 0:
            value, at = _varint(data, at)
        else:
            n, at = _varint(data, at) if key & 7 == 2 else ({5: 4, 1: 8}[key & 7], at)
            value, at = data[at : at + n], at + n
        yield key >> 3, value


def parse_model(data: bytes) -> Model:
    pieces, trainer, norm = [], {}, {}
    for number, value in proto(data):
        if number == PIECES:
            p = dict(proto(value))
            pieces.append((p[1].decode("utf-8"), struct.unpack("<f", p.get(2, bytes(4)))[0], p.get(3, 1)))
        elif number == TRAINER:
            trainer = dict(proto(value))
        elif number == NORMALIZER:
            norm = dict(proto(value))
    return Model(pieces, trainer.get(3, UNIGRAM), norm.get(2, b""), bool(norm.get(3, 1)), bool(norm.get(4, 1)), bool(norm.get(5, 1)))


def merges(model: Model) -> list[tuple[str, str]]:
    """Pairs of pieces that make a piece, best score first; equal scores in order of the pieces."""
    known = {p for p, _, kind in model.pieces if kind not in (CONTROL, UNKNOWN, BYTE)}
    ids = {p: k for k, (p, _, _) in enumerate(model.pieces)}
    ranked = []
    for piece, score, kind in model.pieces:
        if kind in (CONTROL, UNKNOWN, BYTE) or len(piece) < 2:
            continue
        for cut in range(1, len(piece)):
            left, right = piece[:cut], piece[cut:]
            if left in known and right in known:
                ranked.append((-score, ids[piece], ids[left], left, right))
    return [(left, right) for *_, left, right in sorted(ranked)]


def words_are_apart(model: Model) -> bool:
    """Whether no piece joins a marker to what stands before it: words can then be encoded alone."""
    return not any(re.search(f"[^{MARK}]{MARK}", p) for p, _, _ in model.pieces)


def build(model: Model):
    """The tokenizers pipeline of a SentencePiece model."""
    from tokenizers import AddedToken, Regex, Tokenizer, decoders, models, normalizers, pre_tokenizers

    if model.kind == UNIGRAM:
        core = models.Unigram([(p, s) for p, s, _ in model.pieces], model.unknown, model.byte_fallback)
    elif model.kind == BPE:
        vocab = {p: k for k, (p, _, _) in enumerate(model.pieces)}
        core = models.BPE(vocab, merges(model), unk_token=model.pieces[model.unknown][0], fuse_unk=True, byte_fallback=model.byte_fallback)
    else:
        raise ValueError(f"model type {model.kind} is neither unigram nor BPE")
    t = Tokenizer(core)
    steps = []
    if model.charsmap:
        steps.append(normalizers.Precompiled(model.charsmap))
    if model.squeeze:
        steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
    if model.dummy_prefix:
        steps.append(normalizers.Prepend(MARK if model.escape else " "))
    if model.escape:
        steps.append(normalizers.Replace(" ", MARK))
    t.normalizer = normalizers.Sequence(steps)
    if model.kind == BPE and words_are_apart(model):
        t.pre_tokenizer = pre_tokenizers.Split(Regex(f"{MARK}*[^{MARK}]+|{MARK}+"), "isolated")
    back = [decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()]
    t.decoder = decoders.Sequence(back + [decoders.Strip(" ", 1, 0)] * model.dummy_prefix)
    added = [AddedToken(p, normalized=False) for p, _, kind in model.pieces if kind == USER_DEFINED]
    if added:
        t.add_tokens(added)
    return t


WORD = re.compile(f"[ {MARK}]*[^ {MARK}]+|[ {MARK}]+")
KEPT_WORDS, KEPT_CHARS, ROW_WORDS = 500_000, 64, 1000


class Encoder:
    """Both libraries on one model.

    Where no piece crosses a word's start and texts are not normalised, a text's ids are its words'
    ids in a row: each distinct word is then encoded, held against the other library and decoded
    once, and kept (a bounded number of words); of each slice of texts the shortest is held against
    both libraries as a whole as well. Other models go text by text.
    """

    def __init__(self, data: bytes, threads: int):
        import sentencepiece

        self.model, self.threads = parse_model(data), threads
        self.fast = build(self.model)
        self.reference = sentencepiece.SentencePieceProcessor(model_proto=data)
        m = self.model
        self.apart = m.kind == BPE and words_are_apart(m) and m.dummy_prefix and m.escape and not m.squeeze and not m.charsmap
        self.starts = np.array([p.startswith(MARK) for p, _, _ in m.pieces])
        self.strings = ["\0" if kind == BYTE else p.replace(MARK, " ") for p, _, kind in m.pieces]
        self.known: dict[str, tuple[int, ...]] = {}
        self.differ: set[str] = set()
        self.lossy: set[str] = set()

    def both(self, texts: list[str]) -> tuple[list[list[int]], list[bool], list[bool]]:
        """The pipeline's ids of each text, whether sentencepiece has the same, whether decoding restores it."""
        ids = [g.ids for g in self.fast.encode_batch_fast(texts, add_special_tokens=False)]
        true = self.reference.encode(texts, num_threads=self.threads)
        back = self.fast.decode_batch(ids, skip_special_tokens=False)
        return ids, [x == t for x, t in zip(ids, true, strict=True)], [x == t for x, t in zip(back, texts, strict=True)]

    def learn(self, words: list[str]) -> None:
        """Encode distinct words in both libraries, many in a row: a piece with a marker starts a word.

        A row that the pipeline does not keep apart by words is encoded word by word.
        """
        plain = [w for w in words if w[0] == " " and len(w) > 1 and w[1] not in (" ", MARK)]
        odd = [w for w in words if not (w[0] == " " and len(w) > 1 and w[1] not in (" ", MARK))]
        rows = [plain[k : k + ROW_WORDS] for k in range(0, len(plain), ROW_WORDS)]
        texts = ["".join(r)[1:] for r in rows]
        got = self.fast.encode_batch_fast(texts, add_special_tokens=False)
        for row, g, t in zip(rows, got, self.reference.encode(texts, num_threads=self.threads), strict=True):
            mine, true = self.cut(g.ids), self.cut(t)
            if len(mine) != len(row) or len(true) != len(row):
                odd += row
                continue
            for w, ids, other in zip(row, mine, true, strict=True):
                self.keep(w, ids, other == ids)
        if odd:
            for w, ids, same, _ in zip(odd, *self.both([w[1:] for w in odd]), strict=True):
                self.keep(w, ids, same)

    def cut(self, ids: list[int]) -> list[tuple[int, ...]]:
        starts = np.flatnonzero(self.starts[np.array(ids, np.int32)]).tolist() if ids else []
        return [tuple(ids[a:b]) for a, b in zip(starts, [*starts[1:], len(ids)], strict=True)]

    def keep(self, word: str, ids: list[int], same: bool) -> None:
        self.known[word] = ids = tuple(ids)
        if not same:
            self.differ.add(word)
        text = "".join([self.strings[i] for i in ids])
        if text != word and (MARK in word or "\0" not in text or self.fast.decode(ids, skip_special_tokens=False) != word[1:]):
            self.lossy.add(word)

    def encode(self, texts: list[str]) -> tuple[list[list[int]], list[bool], list[bool]]:
        if not self.apart:
            return self.both(texts)
        words = [WORD.findall(f" {t}") if t else [] for t in texts]
        new = set().union(*words).difference(self.known)
        if len(self.known) + len(new) > KEPT_WORDS:
            self.known, self.differ, self.lossy = {}, set(), set()
            new = set().union(*words)
        if new:
            self.learn(list(new))
        ids = [list(chain.from_iterable(map(self.known.__getitem__, w))) for w in words]
        same = [self.differ.isdisjoint(w) for w in words] if self.differ else [True] * len(words)
        whole = [self.lossy.isdisjoint(w) for w in words] if self.lossy else [True] * len(words)
        if some := [k for k, t in enumerate(texts) if t]:
            k = min(some, key=lambda n: len(texts[n]))
            if self.both([texts[k]])[:2] != ([ids[k]], [True]):
                same[k] = False
        for w in new:
            if len(w) > KEPT_CHARS:
                del self.known[w]
        return ids, same, whole


_loaded: dict[bytes, Encoder] = {}


def loaded(data: bytes, threads: int = 2) -> Encoder:
    """The encoder of a model file, built once for a process."""
    key = hashlib.sha256(data).digest()
    if key not in _loaded:
        _loaded[key] = Encoder(data, threads)
    return _loaded[key]


SLICE_CHARS = 1 << 20


def encode(docs: DataFrame, model_path: str = MODEL, threads: int = 2) -> DataFrame:
    """(doc_id, ids, n_tokens, parity, round_trip) for every whole text of docs.

    ids are the rebuilt pipeline's; where sentencepiece has others, parity is false. round_trip says
    whether decode() gives the text back. Null and empty texts have no ids. Repeated rows give repeated rows; other columns are not looked at.
    """
    with open(model_path, "rb") as f:
        data = f.read()
    sent = docs.sparkSession.sparkContext.broadcast(data)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ.setdefault("RAYON_NUM_THREADS", str(threads))
        os.environ["TOKENIZERS_PARALLELISM"] = "true"
        encoder = loaded(sent.value, threads)
        for b in batches:
            at = 0
            for texts in common.slices(common.texts_of(b.column(1)), SLICE_CHARS):
                ids, same, whole = encoder.encode(texts)
                sizes = np.array([len(t) for t in ids], np.int32)
                flat = np.fromiter(chain.from_iterable(ids), np.int32, int(sizes.sum()))
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, sizes.cumsum()], pa.int32()), pa.array(flat))
                yield pa.record_batch({"doc_id": b.column(0).slice(at, len(texts)), "ids": lists, "n_tokens": pa.array(sizes), "parity": pa.array(same), "round_trip": pa.array(whole)})
                at += len(texts)

    return common.mapped(docs.select(F.col("doc_id").cast("long"), "text"), run, "doc_id long, ids array<int>, n_tokens int, parity boolean, round_trip boolean")


def decode(encoded: DataFrame, model_path: str = MODEL) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); null or no ids give an empty text."""
    with open(model_path, "rb") as f:
        data = f.read()
    sent = encoded.sparkSession.sparkContext.broadcast(data)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fast = loaded(sent.value).fast
        for b in batches:
            texts = fast.decode_batch([x or [] for x in b.column(1).to_pylist()], skip_special_tokens=False)
            yield pa.record_batch({"doc_id": b.column(0), "text": pa.array(texts, pa.string())})

    return common.mapped(encoded.select(F.col("doc_id").cast("long"), "ids"), run, "doc_id long, text string")


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(common.table(spark, sf_dir, "documents"))
