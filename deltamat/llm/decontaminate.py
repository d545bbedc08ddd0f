"""Benchmark decontamination: BM25 with block-max WAND, then overlap of question and answer.

Test items are indexed on the driver, in shards of a checked size, and broadcast. Every passage of
every text is a query: a window of words that overlaps the next by half. Scores are shares of the
score an item gives itself, so one threshold holds for all items. A set of passages is first
bounded block by block from each term's block maximum; only passages with a block whose bound
reaches the threshold walk their posting lists, pivot by pivot. Retrieved items are verified by
the share of their question's and of their answer's five-word shingles that the passage holds.
"""

from __future__ import annotations

import heapq
import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common
from deltamat.sources.scratch import discard, materialize

WORDS = re.compile(r"\w+")
K1, B = 1.2, 0.75
#: Characters of test items in one shard of the index.
MAX_INDEX_CHARS = 50_000_000


@dataclass(frozen=True)
class Settings:
    """threshold: share of an item's own score; overlap: least share of shingles; block: items."""

    threshold: float = 0.5
    overlap: float = 0.8
    shingle: int = 5
    block: int = 2
    light: float = 0.2


def words(text: str) -> list[str]:
    return WORDS.findall(text.lower())


def split_item(text: str) -> tuple[str, str]:
    """Question and answer: cut after the last question mark, else at the last line or sentence.

    Without any such mark, or with nothing after it, the text is all question.
    """
    for cut in (text.rfind("?"), text.rstrip().rfind("\n"), text.rstrip().rstrip(".!").rfind(". ")):
        if cut >= 0 and WORDS.search(text[cut + 1 :]) and WORDS.search(text[:cut]):
            return text[: cut + 1], text[cut + 1 :]
    return text, ""


def shingles(ws: list[str], n: int) -> set[tuple[str, ...]]:
    """n-word shingles; a shorter, non-empty sequence is one shingle."""
    return {tuple(ws[k : k + n]) for k in range(max(1, len(ws) - n + 1))} if ws else set()


class Corpus(NamedTuple):
    """What BM25 asks of all items together: their number, words and longest, and each term's items."""

    n: int
    words: int
    longest: int
    df: dict[str, int]


class BlockMaxIndex:
    """BM25 postings of the items, in blocks of item numbers, with each term's block maxima.

    corpus: the counts over all items where ``items`` are one shard of them.
    """

    def __init__(self, items: list[tuple[int, str]], settings: Settings, corpus: Corpus | None = None):
        self.settings = settings
        items = sorted(((i, words(t or ""), t or "") for i, t in items if i is not None), key=lambda x: (x[0], x[2]))
        items = [x for x in items if x[1]]
        self.ids = [i for i, _, _ in items]
        self.verify = []
        for _, _, t in items:
            q, a = split_item(t)
            self.verify.append((shingles(words(q), settings.shingle), shingles(words(a), settings.shingle), shingles(words(t), settings.shingle)))
        n = len(items)
        own = Counter(t for _, w, _ in items for t in set(w))
        corpus = corpus or Corpus(n, sum(len(w) for _, w, _ in items), max((len(w) for _, w, _ in items), default=1), own)
        mean, df = corpus.words / max(1, corpus.n), {t: corpus.df[t] for t in own}
        idf = {t: math.log(1 + (corpus.n - d + 0.5) / (d + 0.5)) for t, d in df.items()}
        self.longest = corpus.longest
        self.vocab: dict[str, int] = {t: k for k, t in enumerate(sorted(df))}
        postings: list[list[tuple[int, float]]] = [[] for _ in self.vocab]
        blocks = -(-n // settings.block)
        self.slack = np.zeros(blocks, np.float32)
        heavy: list[list[tuple[int, float]]] = [[] for _ in self.vocab]
        for k, (_, w, _) in enumerate(items):
            tf = Counter(w)
            raw = {t: idf[t] * c * (K1 + 1) / (c + K1 * (1 - B + B * len(w) / mean)) for t, c in tf.items()}
            own, light = sum(raw.values()), 0.0
            for t, s in sorted(raw.items(), key=lambda x: (-df[x[0]], x[0])):
                postings[self.vocab[t]].append((k, s / own))
                if light + s / own <= settings.light:
                    light += s / own
                else:
                    heavy[self.vocab[t]].append((k, s / own))
            self.slack[k // settings.block] = max(self.slack[k // settings.block], light)
        self.postings = [([k for k, _ in p], [s for _, s in p]) for p in postings]
        self.maxima = [self._blocks(p) for p in postings]
        self.best = [max(s for _, s in p) for p in postings]
        bounds = [sorted(self._blocks(p).items()) for p in heavy]
        self.at = np.r_[0, np.cumsum([len(x) for x in bounds])].astype(np.int64)
        self.block_of = np.array([b for x in bounds for b, _ in x], np.int64)
        self.bound_of = np.array([s for x in bounds for _, s in x], np.float32)

    def _blocks(self, posting: list[tuple[int, float]]) -> dict[int, float]:
        out: dict[int, float] = {}
        for k, s in posting:
            b = k // self.settings.block
            out[b] = max(out.get(b, 0.0), s)
        return out

    def windows(self, n_words: int) -> tuple[int, int]:
        """(step, number) of the windows of two steps over n_words; any item lies in one of them."""
        step = max(64, self.longest)
        return step, max(1, -(-n_words // step) - 1)

    def bounded(self, ids: np.ndarray, at: np.ndarray, total: int) -> np.ndarray:
        """Of ``total`` half-windows' passages: those with a block whose bound reaches the threshold.

        ids: term of each indexed word; at: its half-window. Terms that are common to many items
        count by the most they can add to a block (slack), the others where they occur.
        """
        pairs = np.unique(at * len(self.vocab) + ids)
        half, term = pairs // len(self.vocab), pairs % len(self.vocab)
        reps = self.at[term + 1] - self.at[term]
        flat = np.repeat(self.at[term] - np.r_[0, np.cumsum(reps)[:-1]], reps) + np.arange(int(reps.sum()))
        chosen = np.full(total, bool((self.slack >= self.settings.threshold - 1e-6).any()))
        if len(flat):
            # A half-window's bounds count for the window that starts with it and for the one before.
            n, at_half, block = len(self.slack), np.repeat(half, reps), self.block_of[flat]
            cell, inverse = np.unique(np.r_[at_half * n + block, (at_half - 1) * n + block], return_inverse=True)
            bound = np.bincount(inverse, np.tile(self.bound_of[flat], 2)) + self.slack[cell % n]
            hit = cell[bound >= self.settings.threshold - 1e-6] // n
            chosen[hit[hit >= 0]] = True
        return chosen

    def reaches(self, terms: np.ndarray) -> bool:
        """The same bound for one passage's distinct terms."""
        reps = self.at[terms + 1] - self.at[terms]
        flat = np.repeat(self.at[terms] - np.r_[0, np.cumsum(reps)[:-1]], reps) + np.arange(int(reps.sum()))
        bound = np.bincount(self.block_of[flat], self.bound_of[flat], len(self.slack)) + self.slack
        return bool((bound >= self.settings.threshold - 1e-6).any())

    def wand(self, terms: list[int]) -> list[tuple[int, float]]:
        """Every (item number, score) at or above the threshold for a query of distinct terms."""
        least, block = self.settings.threshold - 1e-9, self.settings.block
        cursors = [[self.postings[t][0][0], 0, t] for t in terms]
        heapq.heapify(cursors)
        found = []
        while cursors:
            live = sorted(cursors)
            bound, pivot = 0.0, None
            for k, (_, _, t) in enumerate(live):
                bound += self.best[t]
                if bound >= least:
                    pivot = k
                    break
            if pivot is None:
                break
            item = live[pivot][0]
            while pivot + 1 < len(live) and live[pivot + 1][0] == item:
                pivot += 1
            b = item // block
            most = sum(self.maxima[t].get(b, 0.0) for _, _, t in live[: pivot + 1])
            if most >= least and live[0][0] == item:
                score = sum(self.postings[t][1][k] for _, k, t in live[: pivot + 1])
                if score >= least:
                    found.append((item, score))
                target = item + 1
            elif most >= least:
                target = item
            else:
                target = min((b + 1) * block, live[pivot + 1][0] if pivot + 1 < len(live) else (b + 1) * block)
                target = max(target, item + 1)
            cursors = live[pivot + 1 :]
            for _, k, t in live[: pivot + 1]:
                docs = self.postings[t][0]
                while k < len(docs) and docs[k] < target:
                    k += 1
                if k < len(docs):
                    cursors.append([docs[k], k, t])
        return found

    def overlaps(self, item: int, ws: list[str]) -> tuple[float, float, bool]:
        """Shares of the item's question and answer shingles in the words, and the verdict."""
        q, a, whole = self.verify[item]
        have = shingles(ws, self.settings.shingle)
        if len(ws) >= 1:
            have |= {tuple(ws[k : k + n]) for n in {len(x) for x in q | a | whole} for k in range(len(ws) - n + 1)}
        share = lambda s: len(s & have) / len(s) if s else 1.0
        return share(q), share(a), share(q) >= self.settings.overlap and share(a) >= self.settings.overlap


def usable(items: DataFrame) -> DataFrame:
    return items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null")


def shards_of(items: DataFrame, settings: Settings) -> Iterator[BlockMaxIndex]:
    """The index of (item_id, text), one shard of about MAX_INDEX_CHARS characters after the other.

    One shard counts its terms itself. Several are dealt by the items' hashes and share the counts
    over all items, which Spark makes; the driver holds one shard and its terms' counts at a time.
    """
    items = usable(items)
    size = items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    shards = max(1, -(-size // MAX_INDEX_CHARS))
    if shards == 1:
        yield BlockMaxIndex([(r[0], r[1]) for r in items.collect()], settings)
        return

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = 0
            for part in common.slices(common.texts_of(b.column(1)), SLICE_CHARS):
                ws = [words(t) for t in part]
                yield pa.record_batch({"shard": b.column(0).slice(at, len(part)), "n": pa.array(list(map(len, ws)), pa.int64()), "terms": pa.array([sorted(set(w)) for w in ws], pa.list_(pa.string()))})
                at += len(part)

    dealt = items.withColumn("shard", F.pmod(F.xxhash64("item_id", "text"), F.lit(shards)).cast("int"))
    counted = materialize(common.mapped(dealt.select("shard", "text"), count, "shard int, n long, terms array<string>").where("n > 0"), "counted")
    n, total, longest = counted.agg(F.count("*"), F.sum("n"), F.max("n")).first()
    seen = counted.select("shard", F.explode("terms").alias("term"))
    df = materialize(seen.groupBy("term").agg(F.count("*").alias("n")), "df")
    for k in range(shards):
        rows = dealt.where(F.col("shard") == k).select("item_id", "text").collect()
        own = df.join(seen.where(F.col("shard") == k).select("term").distinct(), "term", "left_semi").collect()
        yield BlockMaxIndex([(r[0], r[1]) for r in rows], settings, Corpus(n, total, longest, {r[0]: r[1] for r in own}))
    discard(counted, df)


def search(index: BlockMaxIndex, texts: list[str]) -> Iterator[tuple[int, int, int, float, float, float]]:
    """(text number, item number, passage, score, question share, answer share) of verified hits.

    The best passage for each pair of text and item.
    """
    if not index.ids:
        return
    get, base, ids, at, docs = index.vocab.get, 0, [], [], []
    step = index.windows(0)[0]
    for n, text in enumerate(texts):
        ws = words(text)
        found = np.fromiter(map(get, ws, repeat(-1)), np.int64, len(ws))
        hit = np.flatnonzero(found >= 0)
        ids.append(found[hit])
        at.append(base + hit // step)
        halves = -(-len(ws) // step)
        docs.append((n, base, halves, found))
        base += halves + 1
    chosen = index.bounded(np.concatenate(ids), np.concatenate(at), base) if base else np.zeros(0, bool)
    for n, first, halves, found in docs:
        if not chosen[first : first + halves].any():
            continue
        ws, best = None, {}
        for p in np.flatnonzero(chosen[first : first + halves]).tolist():
            inside = found[p * step : (p + 2) * step]
            terms = np.unique(inside[inside >= 0])
            for item, score in index.wand(terms.tolist()) if index.reaches(terms) else ():
                ws = ws if ws is not None else words(texts[n])
                q, a, yes = index.overlaps(item, ws[p * step : (p + 2) * step])
                if yes and (item not in best or (-score, p) < (-best[item][1], best[item][0])):
                    best[item] = (p, score, q, a)
        for item, (p, score, q, a) in sorted(best.items()):
            yield n, item, p, score, q, a


SLICE_CHARS = 1 << 21


def contaminated(docs: DataFrame, items: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """(doc_id, item_id, passage, score, question_overlap, answer_overlap), a row for each pair found.

    Whole texts are searched; words are compared in lower case without punctuation. Null and empty
    texts or items match nothing; repeated rows of docs give repeated rows, repeated items with one
    id one row for each distinct text. Other columns are not looked at. Where the items take several
    shards, each is a pass of its own over docs, written before the next one.
    """
    schema = "doc_id long, item_id long, passage int, score double, question_overlap double, answer_overlap double"
    plain, found = docs.select(F.col("doc_id").cast("long"), "text"), []

    def one(index: BlockMaxIndex) -> DataFrame:
        sent = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            idx = sent.value
            for b in batches:
                at = 0
                for part in common.slices(common.texts_of(b.column(1)), SLICE_CHARS):
                    rows = [(b.column(0)[at + n].as_py(), idx.ids[k], p, s, q, a) for n, k, p, s, q, a in search(idx, part)]
                    at += len(part)
                    if rows:
                        cols = list(zip(*rows, strict=True))
                        types = [pa.int64(), pa.int64(), pa.int32(), pa.float64(), pa.float64(), pa.float64()]
                        yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["doc_id", "item_id", "passage", "score", "question_overlap", "answer_overlap"])

        return common.mapped(plain, run, schema)

    for index in shards_of(items, settings):
        found = [*found[:-1], *(materialize(x, "found") for x in found[-1:])]
        found.append(one(index))
    out = found[0]
    for x in found[1:]:
        out = out.unionByName(x)
    return out


def drop_contaminated(docs: DataFrame, items: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """docs without the rows whose text holds an item; all columns are kept, whatever their names.

    Null and empty texts stay, repeated rows go or stay alike, and without items all rows stay. One
    pass for each shard of the items, see contaminated().
    """
    where, out = docs.columns.index("text"), None

    def one(left: DataFrame, index: BlockMaxIndex) -> DataFrame:
        sent = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                keep, at = np.ones(b.num_rows, bool), 0
                for part in common.slices(common.texts_of(b.column(where)), SLICE_CHARS):
                    for n, *_ in search(sent.value, part):
                        keep[at + n] = False
                    at += len(part)
                yield b.filter(pa.array(keep))

        return common.mapped(left, run, docs.schema)

    for index in shards_of(items, settings):
        out = one(docs if out is None else materialize(out, "kept"), index)
    return out


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
