"""Pairs of documents by the exact Jaccard similarity of their sets of five-word shingles.

Words are those of the SimHash fingerprints. The bands, cells and the comparison are those of the
line deduplication, with whole texts in the place of lines.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.llm import common, lines
from deltamat.sources.scratch import discard, materialize

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
SETTINGS = lines.Settings(shingle=5, similarity=0.8)


def word_hashes(texts: list[str], k: int) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all k-word shingles and the number of them for each text (1 at least).

    A-Z are lower-cased, words are runs without ASCII white space; a text of fewer words is one shingle.
    """
    parts = [t.encode("utf-8", "surrogatepass").lower() for t in texts]
    raw = np.frombuffer(b" ".join(parts) + b" ", np.uint8)
    blank = SPACE[raw]
    starts = np.flatnonzero(~blank & np.r_[True, blank[:-1]])
    bounds = np.cumsum([0, *(len(p) + 1 for p in parts)])
    first = np.searchsorted(starts, bounds)
    n = np.diff(first)
    sizes = np.maximum(n, k)
    begin = np.r_[0, np.cumsum(sizes)[:-1]]
    w = np.zeros(int(sizes.sum()), np.uint64)
    if len(starts):
        place = np.arange(len(raw)) - starts[np.maximum(np.cumsum(~blank & np.r_[True, blank[:-1]]) - 1, 0)]
        place = np.where(blank, 0, place)
        power = np.cumprod(np.full(int(place.max()) + 1, lines._M[0], np.uint64))
        own = lines.mixed(np.add.reduceat(np.where(blank, np.uint64(0), (raw.astype(np.uint64) + np.uint64(1)) * power[place]), starts))
        w[np.repeat(begin - first[:-1], n) + np.arange(len(starts))] = own
    counts = sizes - k + 1
    at = np.repeat(begin - np.r_[0, np.cumsum(counts)[:-1]], counts) + np.arange(int(counts.sum()))
    h = np.zeros(len(at), np.uint64)
    for r in range(k):
        h = lines.mixed(h * lines._M + w[at + r])
    return h, counts


def whole_texts(texts: list[str]) -> dict[str, tuple[int, int]]:
    out: dict[str, tuple[int, int]] = {}
    for k, t in enumerate(texts):
        if t:
            out.setdefault(t, (k, 0))
    return out


def links(docs: DataFrame, s: lines.Settings = SETTINGS) -> DataFrame:
    """Edges (a, b) that connect the texts (by xxhash64) of Jaccard ``s.similarity`` or more."""
    plain = docs.select(*lines.key_columns(docs), "text")
    sigs = lines.signature_table(plain, s, whole_texts, word_hashes).drop("at")
    sigs = materialize(sigs.groupBy("node", "kind").agg(*[F.min(c).alias(c) for c in sigs.columns[2:]]), "signatures")
    own, stats = lines.buckets(sigs, s)
    wanted = own.select("node").distinct()
    texts = docs.select(F.xxhash64("text").alias("node"), F.col("text").alias("line")).join(wanted, "node", "left_semi").groupBy("node").agg(F.min("line").alias("line"))
    texts = materialize(texts, "texts")
    edges = materialize(common.link_buckets(own, stats, s.block, lines.linker(s, word_hashes), lambda cells: cells.join(texts, "node")).distinct(), "edges")
    discard(sigs, own, stats, texts)
    return edges
