"""Quality scores by nearest-neighbour voting in a latent-semantic space.

A bounded sample of labelled texts gives the terms (words, and triples of character classes), their
weights and, by a truncated singular value decomposition, the latent space. The sample's vectors and
labels are broadcast; every document is placed in the space and compared with all of them in
blocks of exact cosine products, and its nearest neighbours vote with their similarity.
"""

from __future__ import annotations

import operator
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common


@dataclass(frozen=True)
class Settings:
    """sample: most labelled rows to learn from; sample_chars: longest text among them.

    marks: how many of the sample's commonest marks are character classes of their own; power: votes
    weigh the cosine to this power, so that the nearest of the neighbours count most.
    """

    sample: int = 3000
    sample_chars: int = 20_000
    words: int = 4096
    dims: int = 64
    neighbours: int = 24
    threshold: float = 0.7
    marks: int = 10
    power: int = 4
    seed: int = 11


#: Character classes before the marks: lower and upper case, digits, blanks, line ends. The last class is any other.
FIRST_MARK = 5
REPEATS = 12
_PLAIN = np.full(1 << 16, 255, np.uint8)
_PLAIN[[k for k in range(1 << 16) if chr(k).islower()]] = 0
_PLAIN[[k for k in range(1 << 16) if chr(k).isupper()]] = 1
_PLAIN[[k for k in range(1 << 16) if chr(k).isdigit()]] = 2
_PLAIN[[k for k in range(1 << 16) if chr(k).isspace()]] = 3
_PLAIN[0x0A] = 4


def classes(texts: list[str], marks: int) -> np.ndarray:
    """The class of each code point: the marks are those that occur in most of the texts."""
    seen = Counter(c for t in texts for c in set(t) if ord(c) < 1 << 16 and _PLAIN[ord(c)] == 255)
    table = np.where(_PLAIN == 255, np.uint8(FIRST_MARK + marks), _PLAIN)
    for k, (c, _) in enumerate(sorted(seen.items(), key=lambda x: (-x[1], x[0]))[:marks]):
        table[ord(c)] = FIRST_MARK + k
    return table


def shape_counts(text: str, table: np.ndarray, n: int) -> np.ndarray:
    """How often each triple of the n character classes occurs."""
    out = np.zeros(n**3, np.int64)
    for at in range(0, len(text), 1 << 20):
        c = np.frombuffer(text[max(0, at - 2) : at + (1 << 20)].encode("utf-32-le", "surrogatepass"), np.uint32)
        k = table[np.minimum(c, 0xFFFF)].astype(np.int32)
        if len(k) > 2:
            out += np.bincount((k[:-2] * n + k[1:-1]) * n + k[2:], minlength=n**3)
    return out


def repeats(words: list[str]) -> list[int]:
    """Terms for the share of words that repeat their neighbour, and of words that are new."""
    if len(words) < 2:
        return []
    echo = sum(map(operator.eq, words, words[1:])) / len(words)
    fresh = len(set(words)) / len(words)
    return [min(5, int(echo * 20)), 6 + min(5, int(fresh * 6))]


class Space:
    """Terms, weights and projection of the latent space; all fixed once fitted."""

    def __init__(self, settings: Settings):
        self.settings = settings
        self.table, self.classes = classes([], settings.marks), FIRST_MARK + settings.marks + 1
        self.vocab: dict[str, int] = {}
        self.idf = np.zeros(0, np.float32)
        self.axes = np.zeros((0, 0), np.float32)

    def terms(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """(term numbers, weights), each of the three kinds of term scaled to length one."""
        words = text.lower().split()
        ids = np.fromiter(map(self.vocab.get, words, repeat(-1)), np.int64, len(words))
        counts = np.bincount(ids[ids >= 0], minlength=1)
        shapes, again = shape_counts(text, self.table, self.classes), np.array(repeats(words), np.int64)
        n = len(self.vocab)
        found, values = [], []
        for base, at, tf in ((0, np.flatnonzero(counts), counts), (n, np.flatnonzero(shapes), shapes), (n + len(shapes), again, None)):
            if len(at):
                w = self.idf[base + at] * (1 if tf is None else np.log1p(tf[at]))
                found.append(base + at)
                values.append(w / max(float(np.linalg.norm(w)), 1e-9))
        if not found:
            return np.zeros(0, np.int64), np.zeros(0, np.float32)
        return np.concatenate(found), np.concatenate(values).astype(np.float32)

    def fit(self, texts: list[str]) -> np.ndarray:
        """Learn from the texts and return their unit vectors."""
        df: Counter = Counter()
        for t in texts:
            df.update(set(t.lower().split()))
        best = sorted((x for x in df.items() if x[1] > 1), key=lambda x: (-x[1], x[0]))[: self.settings.words]
        self.vocab = {w: k for k, (w, _) in enumerate(best)}
        self.table = classes(texts, self.settings.marks)
        size = len(self.vocab) + self.classes**3 + REPEATS
        self.idf = np.ones(size, np.float32)
        rows = [self.terms(t)[0] for t in texts]
        seen = np.bincount(np.concatenate([*rows, np.zeros(0, np.int64)]), minlength=size)
        self.idf = np.log((1 + len(texts)) / (1 + seen)).astype(np.float32) + np.float32(0.1)
        m = np.zeros((len(texts), size), np.float32)
        for k, t in enumerate(texts):
            at, w = self.terms(t)
            m[k, at] = w
        dims = min(self.settings.dims, *m.shape) if len(texts) else 0
        q = np.linalg.qr(m @ np.random.default_rng(self.settings.seed).standard_normal((size, dims + 8)).astype(np.float32))[0]
        for _ in range(3):
            q = np.linalg.qr(m @ np.linalg.qr(m.T @ q)[0])[0]
        self.axes = np.ascontiguousarray(np.linalg.svd(q.T @ m, full_matrices=False)[2][:dims].T)
        return self.place(texts)

    def place(self, texts: list[str]) -> np.ndarray:
        """Unit vectors of texts; a text without terms is the zero vector."""
        out = np.zeros((len(texts), self.axes.shape[1]), np.float32)
        for k, t in enumerate(texts):
            at, w = self.terms(t)
            out[k] = w @ self.axes[at]
        return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


#: Documents compared with all labelled vectors at a time.
BLOCK = 256


class Voter:
    """Scores from the labelled vectors."""

    def __init__(self, settings: Settings, texts: list[str], labels: list[int]):
        self.settings, self.space = settings, Space(settings)
        self.labels = np.array(labels, np.float64)
        self.prior = float(self.labels.mean()) if labels else 0.5
        self.vectors = np.ascontiguousarray(self.space.fit(texts).T.astype(np.float64)) if labels else None

    def scores(self, texts: list[str]) -> np.ndarray:
        """The similarity-weighted share of label 1 among the nearest; the prior where nothing is near."""
        if self.vectors is None:
            return np.full(len(texts), self.prior)
        place = self.space.place(texts).astype(np.float64)
        parts = [self.votes(place[k : k + BLOCK]) for k in range(0, len(place), BLOCK)]
        return np.concatenate(parts) if parts else np.zeros(0)

    def votes(self, place: np.ndarray) -> np.ndarray:
        """The votes on a block of unit vectors."""
        cos = np.round(place @ self.vectors, 9)
        k = min(self.settings.neighbours, cos.shape[1])
        cut = np.partition(cos, -k, axis=1)[:, -k:].min(1, keepdims=True)
        chosen = cos > cut
        even, room = cos == cut, k - chosen.sum(1)
        several = np.flatnonzero(even.sum(1) > room)  # of neighbours as near as the last, those learned first vote
        even[several] &= np.cumsum(even[several], axis=1, dtype=np.int32) <= room[several, None]
        chosen |= even
        weight = np.maximum(cos[chosen].reshape(-1, k), 0) ** self.settings.power
        labels = np.broadcast_to(self.labels, cos.shape)[chosen].reshape(-1, k)
        total = weight.sum(1)
        return np.where(total > 1e-12, (weight * labels).sum(1) / np.maximum(total, 1e-12), self.prior)


def fold(doc_id: Column, folds: int) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds))


def fit(docs: DataFrame, labels: DataFrame, settings: Settings = Settings()) -> Voter:
    """Learn from at most ``settings.sample`` labelled rows outside the held-out fold (crc32 mod 4 = 2).

    The rows are those of the smallest hash of doc_id; of several labels for one id the smallest holds.
    """
    own = labels.where("doc_id is not null and quality in (0, 1)").where(fold(F.col("doc_id"), 4) != 2)
    own = own.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality"))
    chosen = own.orderBy(F.xxhash64("doc_id"), "doc_id").limit(settings.sample)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.length("text") <= settings.sample_chars)
    rows = texts.join(F.broadcast(chosen), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", "text").limit(settings.sample).collect()
    return Voter(settings, [r["text"] for r in rows], [r["quality"] for r in rows])


SLICE_CHARS = 1 << 20


def _scored(voter: Voter, texts: list[str]) -> np.ndarray:
    parts = [voter.scores(p) for p in common.slices(texts, SLICE_CHARS)]
    return np.concatenate(parts) if parts else np.zeros(0)


def score(docs: DataFrame, voter: Voter) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs; only the text is looked at.

    Null and empty texts get the prior; repeated rows give repeated rows; a null doc_id is not held out.
    """
    sent = docs.sparkSession.sparkContext.broadcast(voter)
    threshold = voter.settings.threshold

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = np.clip(_scored(sent.value, common.texts_of(b.column(2))), 0.0, 1.0)
            yield pa.record_batch({"doc_id": b.column(0), "held_out": b.column(1), "score": pa.array(s, pa.float64()), "predicted": pa.array((s >= threshold).astype(np.int32))})

    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False))
    return common.mapped(docs.select(F.col("doc_id").cast("long"), held.alias("held_out"), "text"), run, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, voter: Voter) -> DataFrame:
    """docs without the rows predicted 0; all columns, in one pass.

    Rows are judged one by one, repeated ones alike; null and empty texts go by the prior; an empty
    table stays empty, and columns besides text are carried whatever their names.
    """
    sent = docs.sparkSession.sparkContext.broadcast(voter)
    where, threshold = docs.columns.index("text"), voter.settings.threshold

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(_scored(sent.value, common.texts_of(b.column(where))) >= threshold))

    return common.mapped(docs, run, docs.schema)


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    return score(docs, fit(docs, common.table(spark, sf_dir, "labels")))
