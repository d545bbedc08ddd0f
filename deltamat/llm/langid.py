"""Language identification by cross-parsing entropy.

For each language a suffix automaton of sample text gives longest-match lengths: a document is cut
greedily into the longest phrases that occur in the sample, and the language that needs the fewest
phrases (normalised by the sample's length and the document's) wins. The automata become one table
of next states, in which many stretches of text in all languages take a step at a time. A stretch is
parsed from the automaton's start first; where the stretch before it ended elsewhere, it is parsed
again from there until both ways meet, so the phrases are those of the whole text in one go.

The commonest letters are one symbol, any other letter of the samples is two, which tell 1281 classes
of code points apart: no script is thrown together, and the table stays narrow. Letters that no sample
has are one symbol that nothing matches.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamat.llm import common
from deltamat.llm.quality import fold


@dataclass(frozen=True)
class Settings:
    """rows, row_chars, chars: most sample rows for a language, most characters of one, of all.

    stretch: symbols of a text that are parsed side by side with others; it changes no result.
    """

    rows: int = 40
    row_chars: int = 4000
    chars: int = 30_000
    stretch: int = 512
    sharpness: float = 6.0


UNKNOWN = "und"
WIDTH, PAD, BLANK, OTHER = 64, 63, 62, 61
#: Symbols for common letters; the others up to OTHER lead the pairs that stand for rare letters.
COMMON = 40
RARE = 64
PAIRS = (OTHER - COMMON) * OTHER
FLAG, STATE = 1 << 30, (1 << 30) - 1
LETTER = np.array([chr(k).isalpha() for k in range(1 << 16)])
LOWER = np.array([ord(chr(k).lower()) if len(chr(k).lower()) == 1 else k for k in range(1 << 16)], np.uint32)
#: States kept of one group of stretches.
KEPT = 1 << 23


def automaton(text: np.ndarray) -> list[dict[int, int]]:
    """Transitions of the suffix automaton of a sequence of small numbers; state 0 is the start."""
    go: list[dict[int, int]] = [{}]
    link, size, last = [-1], [0], 0
    for c in text.tolist():
        new = len(go)
        go.append({})
        size.append(size[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in go[p]:
            go[p][c] = new
            p = link[p]
        if p >= 0:
            q = go[p][c]
            if size[p] + 1 == size[q]:
                link[new] = q
            else:
                copy = len(go)
                go.append(dict(go[q]))
                size.append(size[p] + 1)
                link.append(link[q])
                while p >= 0 and go[p].get(c) == q:
                    go[p][c] = copy
                    p = link[p]
                link[q] = link[new] = copy
        last = new
    return go


class Parser:
    """The automata of all languages as one table; samples: (language, text) pairs."""

    def __init__(self, samples: tuple[tuple[str, str], ...], settings: Settings):
        self.settings = settings
        self.langs = [lang for lang, _ in samples]
        seen = Counter("".join(t for _, t in samples).lower())
        letters = [c for c, _ in sorted(seen.items(), key=lambda x: (-x[1], x[0])) if c.isalpha() and ord(c) < 1 << 16][:COMMON]
        classes = {ord(c): k for k, c in enumerate(letters)}
        classes |= {ord(c): RARE for c in seen if ord(c) < 1 << 16 and ord(c) not in classes}
        self.table = np.array([classes.get(low, OTHER) if letter else BLANK for letter, low in zip(LETTER.tolist(), LOWER.tolist(), strict=True)], np.uint8)
        self.high = {ord(c) for c in seen if ord(c) >= 1 << 16}
        parts, base, self.bits = [], 0, []
        self.roots = []
        for _, text in samples:
            codes = self.codes(text)[0][: settings.chars]
            go = automaton(codes)
            t = np.zeros((len(go), WIDTH), np.int64)
            t[:] = base
            for c, s in go[0].items():
                t[:, c] = base + s * WIDTH
            t |= FLAG
            for s, nexts in enumerate(go[1:], 1):
                for c, to in nexts.items():
                    t[s, c] = base + to * WIDTH
            t[:, PAD] = base + np.arange(len(go)) * WIDTH
            self.roots.append(base)
            self.bits.append(np.log2(max(2, len(codes))))
            parts.append(t.reshape(-1))
            base += t.size
        if base > STATE:
            raise ValueError("the samples are too long for one table")
        self.next = np.concatenate(parts).astype(np.int32) if parts else np.zeros(0, np.int32)

    def codes(self, text: str) -> tuple[np.ndarray, bool]:
        """Symbols, runs of anything but letters taken as one blank; whether a letter is there."""
        c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        k = self.table[np.minimum(c, 0xFFFF)]
        high = np.flatnonzero(c > 0xFFFF)
        if len(high):
            k = k.copy()
            k[high] = [(RARE if x in self.high else OTHER) if chr(x).isalpha() else BLANK for x in c[high].tolist()]
        blank = k == BLANK
        keep = ~blank
        keep[1:] |= ~blank[:-1]
        k = k[keep]
        rare = k == RARE
        if rare.any():
            low = c[keep][rare]
            low = np.where(low < 1 << 16, LOWER[np.minimum(low, 0xFFFF)], low) % PAIRS
            first = np.flatnonzero(rare) + np.arange(len(low))
            k = np.repeat(k, 1 + rare)
            k[first], k[first + 1] = COMMON + low // OTHER, low % OTHER
        return k, not blank.all()

    def phrases(self, codes: list[np.ndarray]) -> np.ndarray:
        """Phrases for each sequence (rows) and language (columns)."""
        step = self.settings.stretch
        sizes = np.array([len(c) for c in codes], np.int64)
        n = -(-sizes // step)
        owner = np.repeat(np.arange(len(codes)), n)
        flat = np.concatenate([*codes, np.full(step, PAD, np.uint8)])
        starts = np.r_[0, np.cumsum(sizes)[:-1]]
        at = starts[owner] + (np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)) * step
        left = np.minimum(starts[owner] + sizes[owner] - at, step)
        follows = np.r_[False, owner[1:] == owner[:-1]]
        out = np.zeros((len(codes), len(self.langs)), np.int64)
        width = max(1, KEPT // (step * max(1, len(self.langs))))
        end = None
        for lo in range(0, len(owner), width):
            part = slice(lo, lo + width)
            grid = flat[at[None, part] + np.arange(int(left[part].max()))[:, None]]
            grid[np.arange(len(grid))[:, None] >= left[None, part]] = PAD
            count, end = self.parse(grid, follows[part], end)
            np.add.at(out, owner[part], count.T)
        return out

    def parse(self, grid: np.ndarray, follows: np.ndarray, before: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """(phrases by language and stretch, last states) of the stretches that are grid's columns.

        follows: stretches that go on where the one to their left ends; before: states in which the
        stretch left of the first one ended.
        """
        langs, n = len(self.langs), grid.shape[1]
        roots = np.array(self.roots, np.int32)
        start = np.repeat(roots[:, None], n, 1)
        if follows[0] and before is not None:
            start[:, 0] = before
        start = start.reshape(-1)
        seen = np.empty((len(grid), langs * n), np.int32)
        state = start.reshape(langs, n)
        for k, row in enumerate(grid):
            v = self.next[state + row]
            seen[k] = v.reshape(-1)
            state = v & STATE
        go_on = np.tile(follows & (np.arange(n) > 0), langs)
        while True:
            want = np.where(go_on, np.r_[0, seen[-1, :-1] & STATE], start).astype(np.int32)
            col = np.flatnonzero(want != start)
            if not len(col):
                return (seen >> 30).sum(0).reshape(langs, n), seen[-1].reshape(langs, n)[:, -1] & STATE
            start, state = want, want[col]
            for k in range(len(grid)):
                v = self.next[state + grid[k, col % n]]
                apart = v & STATE != seen[k, col] & STATE
                seen[k, col] = v
                col, state = col[apart], (v & STATE)[apart]
                if not len(col):
                    break

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """(language, score in 0..1) of each text; ``und`` and 0 where there is no letter."""
        pairs = [self.codes(t or "") for t in texts]
        langs, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
        some = [k for k, (_, yes) in enumerate(pairs) if yes]
        if some and self.langs:
            codes = [pairs[k][0] for k in some]
            h = self.phrases(codes) * np.array(self.bits) / np.array([len(c) for c in codes])[:, None]
            best = h.argmin(1)
            p = np.exp(-self.settings.sharpness * (h - h.min(1, keepdims=True)))
            for k, b, s in zip(some, best.tolist(), (p.max(1) / p.sum(1)).tolist(), strict=True):
                langs[k], scores[k] = self.langs[b], s
        return langs, scores


def sample(docs: DataFrame, settings: Settings) -> tuple[tuple[str, str], ...]:
    """(language, text) of the rows to learn from: those of the smallest hashes, a bounded number.

    Rows of the held-out fold (crc32 of doc_id mod 5 = 0), without lang or doc_id or text take no
    part. Texts up to ``row_chars`` come first; where a language has too few of them, longer ones give
    their first ``row_chars`` characters to the sample.
    """
    own = docs.where("lang is not null and doc_id is not null and text is not null").where(fold(F.col("doc_id"), 5) != 0)
    own = own.select("lang", "doc_id", (F.length("text") > settings.row_chars).alias("long"), F.substring("text", 1, settings.row_chars).alias("text"))
    by_hash = Window.partitionBy("lang").orderBy("long", F.xxhash64("doc_id"), "doc_id")
    chosen = own.select("lang", "doc_id", "long").withColumn("k", F.row_number().over(by_hash)).where(F.col("k") <= settings.rows).select("lang", "doc_id", "long").distinct()
    rows = own.join(F.broadcast(chosen), ["lang", "doc_id", "long"]).collect()
    texts: dict[str, list[str]] = {}
    for lang, _, text in sorted((r["lang"], (r["long"], md5_key(r["doc_id"]), r["doc_id"]), r["text"]) for r in rows):
        texts.setdefault(lang, []).append(text)
    return tuple((lang, " ".join(t)) for lang, t in sorted(texts.items()))


def md5_key(doc_id: int) -> bytes:
    return hashlib.md5(str(doc_id).encode()).digest()


_parsers: dict[bytes, Parser] = {}


def parser(samples: tuple[tuple[str, str], ...], settings: Settings) -> Parser:
    """The parser of the samples, built once for a process."""
    key = hashlib.sha256(repr((samples, settings)).encode("utf-8", "surrogatepass")).digest()
    if key not in _parsers:
        _parsers.clear()
        _parsers[key] = Parser(samples, settings)
    return _parsers[key]


SLICE_CHARS = 1 << 20


def identify(docs: DataFrame, samples: tuple[tuple[str, str], ...], settings: Settings = Settings()) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of docs, from its whole text alone.

    Null texts and texts without a letter are ``und`` with score 0; so is everything if there was
    nothing to learn from. Repeated rows give repeated rows; a null doc_id is not held out.
    """
    sent = docs.sparkSession.sparkContext.broadcast(samples)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = parser(sent.value, settings)
        for b in batches:
            at = 0
            for part in common.slices(common.texts_of(b.column(2)), SLICE_CHARS):
                langs, scores = p.predict(part)
                yield pa.record_batch({"doc_id": b.column(0).slice(at, len(part)), "held_out": b.column(1).slice(at, len(part)), "lang_pred": pa.array(langs, pa.string()), "score": pa.array(scores)})
                at += len(part)

    held = F.coalesce(fold(F.col("doc_id"), 5) == 0, F.lit(False))
    return common.mapped(docs.select(F.col("doc_id").cast("long"), held.alias("held_out"), "text"), run, "doc_id long, held_out boolean, lang_pred string, score double")


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    return identify(docs, sample(docs, Settings()))
