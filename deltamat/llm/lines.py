"""Fuzzy line deduplication: MinHash of character shingles, bands, exact Jaccard, union-find.

Lines equal after trimming are one node. A node's signature has one minimum for each row of each
band; bands that agree bring nodes together, their shingle sets are compared exactly, and the
distributed components decide: of each component the first line (by doc_id, text, line number) stays.

Long lines take one hash of each shingle and share the shingles out over the signature's places;
short lines, whose places would stay empty, take one hash function for each place. Lines
between carry both. Length is the number of distinct shingles, since sets are compared: two similar
lines always have one kind in common, however often they repeat themselves.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common
from deltamat.sources.scratch import discard, materialize

BLANK = " \t\r"
SEED = 42
SLICE_CHARS = 1 << 19
COLUMNS = 1 << 15
SEEN = 1 << 10
#: Lines of a cell at most for its pairs to be compared one by one.
SMALL = 6
#: Characters rolled at a time, so that they stay in the processor's cache.
RUN = 1 << 14
#: Band keys, with their nodes, that a task sorts at a time.
PAGE_KEYS = 1 << 19
_M, _N = np.array([0x9E3779B97F4A7C15]), np.array([0xC2B2AE3D27D4EB4F])  # uint64; arrays wrap around in silence


@dataclass(frozen=True)
class Settings:
    """With 12 bands of 4 rows, lines at Jaccard 0.8 meet with probability 0.998, at 0.85 with 0.9999.

    Unrelated lines share few 7-character shingles, and four rows keep their chance meetings, which
    grow with the square of the lines, far below the lines that are alike.
    """

    shingle: int = 7
    bands: int = 12
    rows: int = 4
    similarity: float = 0.8
    long_from: int = 128
    block: int = 128


def mixed(h: np.ndarray) -> np.ndarray:
    return _mix(h.copy(), np.empty_like(h))


def _mix(h: np.ndarray, scratch: np.ndarray) -> np.ndarray:
    """Mixes h in place."""
    for n, factor in ((31, _N), (29, _M), (32, None)):
        np.right_shift(h, np.uint64(n), out=scratch)
        np.bitwise_xor(h, scratch, out=h)
        if factor is not None:
            np.multiply(h, factor, out=h)
    return h


Hashes = Callable[[list[str], int], tuple[np.ndarray, np.ndarray]]


def shingle_hashes(lines: list[str], k: int) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all k-character shingles and the number of them for each line (1 at least)."""
    padded = [s if len(s) >= k else s.ljust(k, "\0") for s in lines]
    c = np.frombuffer("".join(padded).encode("utf-32-le", "surrogatepass"), np.uint32)
    sizes = np.fromiter(map(len, padded), np.int64, len(padded))
    out = np.empty(max(len(c) - k + 1, 0), np.uint64)
    for lo in range(0, len(out), RUN):
        hi = min(lo + RUN, len(out))
        out[lo:hi] = _rolled(c[lo : hi + k - 1], k)
    inside = np.ones(len(out), bool)
    ends = np.cumsum(sizes)[:-1]
    for n in range(1, k):  # shingles that start in one line and end in the next
        inside[ends - n] = False
    return out[inside], sizes - k + 1


def _rolled(c: np.ndarray, k: int) -> np.ndarray:
    """Mixed hashes of all windows of k characters."""
    c = c.astype(np.uint64)
    c += np.uint64(1)
    h, width, power = c.copy(), 1, _M
    scratch = np.empty_like(h)
    for bit in bin(k)[3:]:  # doubles the width, and adds one character where k's bit is set
        n = len(h) - width
        np.multiply(h[:n], power, out=scratch[:n])
        h = np.add(scratch[:n], h[width:], out=scratch[:n])
        scratch = np.empty_like(h)
        width, power = 2 * width, power * power
        if bit == "1":
            h = h[: len(c) - width]
            np.multiply(h, _M, out=h)
            np.add(h, c[width:], out=h)
            width, power = width + 1, power * _M
    return _mix(h, np.empty_like(h))


def band_keys(values: np.ndarray, kind: int, s: Settings) -> np.ndarray:
    v = values.reshape(-1, s.bands, s.rows).astype(np.uint64)
    key = np.full(v.shape[:2], kind * 1000 + 1, np.uint64) + np.arange(s.bands, dtype=np.uint64)
    for r in range(s.rows):
        key = mixed(key * _M + v[:, :, r])
    return key.view(np.int64)


def distinct(h: np.ndarray) -> np.ndarray:
    h = np.sort(h)
    return h[np.concatenate(([True], h[1:] != h[:-1]))]


def set_sizes(h: np.ndarray, counts: np.ndarray, s: Settings) -> np.ndarray:
    """Distinct shingles of each line; a lower bound where that alone makes the line long only."""
    out, ends = counts.copy(), np.cumsum(counts)
    which = np.flatnonzero(counts >= s.long_from)
    # Twice what is asked for, from the line's beginning, is enough to tell; the last one stands in for those missing.
    at = np.minimum(np.arange(2 * s.long_from), counts[which, None] - 1) + (ends - counts)[which, None]
    place = (h[at] & np.uint64(SEEN - 1)).view(np.int64)
    place += np.arange(len(which))[:, None] * SEEN
    seen = np.zeros(len(which) * SEEN, bool)
    seen[place.reshape(-1)] = True
    out[which] = seen.reshape(-1, SEEN).sum(1)
    for k in which[out[which] < s.long_from / s.similarity].tolist():
        out[k] = len(distinct(h[ends[k] - counts[k] : ends[k]]))
    return out


def signatures(lines: list[str], s: Settings, hashes: Hashes = shingle_hashes) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(kind, numbers of lines, their band keys) for the kinds of signature."""
    h, counts = hashes(lines, s.shingle)
    places = s.bands * s.rows
    sizes = set_sizes(h, counts, s)
    long = sizes >= s.long_from
    if long.any():
        v = h if long.all() else h[np.repeat(long, counts)]
        place = v >> np.uint64(32)
        place *= np.uint64(places)
        place >>= np.uint64(32)
        place = place.view(np.int64)
        place += np.repeat(np.arange(int(long.sum())) * places, counts[long])
        least = np.full(int(long.sum()) * places, 0xFFFFFFFF, np.uint32)
        np.minimum.at(least, place, v.astype(np.uint32))
        yield 1, np.flatnonzero(long), band_keys(least, 1, s)
    short = sizes < s.long_from / s.similarity
    if short.any():
        v, n = h[np.repeat(short, counts)].astype(np.uint32), counts[short]
        starts = np.r_[0, np.cumsum(n)[:-1]]
        rng = np.random.default_rng(7)
        factors, terms = rng.integers(0, 1 << 31, places, np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 1 << 32, places, np.uint32)
        least = np.stack([np.minimum.reduceat(v * a + b, starts) for a, b in zip(factors, terms, strict=True)], 1)
        yield 0, np.flatnonzero(short), band_keys(least, 0, s)


Units = Callable[[list[str]], dict[str, tuple[int, int]]]


def distinct_lines(texts: list[str]) -> dict[str, tuple[int, int]]:
    """Each trimmed line that is not blank, with the number of the text and of the line where it is first."""
    found: dict[str, tuple[int, int]] = {}
    put = found.setdefault
    for k, t in enumerate(texts):
        for no, x in enumerate(t.split("\n")):
            put(x.strip(BLANK), (k, no))
    found.pop("", None)
    return found


def nodes_of(lines: Iterable[str]) -> np.ndarray:
    """The numbers that Spark's xxhash64 gives the lines."""
    digest = xxhash.xxh64_intdigest
    return np.array([digest(x.encode("utf-8", "surrogatepass"), SEED) for x in lines], np.uint64).view(np.int64)


AT = "at struct<_doc:long,_text:long,no:int>"


def packed(keys: np.ndarray) -> pa.Array:
    """Rows of 64-bit numbers as binary values: one value a row costs Spark much less than one for each number."""
    ends = np.arange(len(keys) + 1, dtype=np.int32) * np.int32(8 * keys.shape[1])
    return pa.Array.from_buffers(pa.binary(), len(keys), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(keys))])


def unpacked(b: pa.RecordBatch, at: int) -> list[np.ndarray]:
    """The numbers in the columns from ``at`` on, column by column; one binary column holds packed ones."""
    if not pa.types.is_binary(b.column(at).type) or not len(b):
        return [c.to_numpy() for c in b.columns[at:]] if len(b) else []
    c = b.column(at)
    ends = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1]
    return list(np.frombuffer(c.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(np.int64).reshape(len(c), -1).T)


def signature_table(docs: DataFrame, s: Settings, units: Units = distinct_lines, hashes: Hashes = shingle_hashes) -> DataFrame:
    """(node, kind, size, at, keys) for the distinct lines (or other units) of docs(_doc, _text, text).

    size: a line's characters; at: the first place where it stands; keys: its band keys, packed. Lines are told apart slice by slice
    of the documents, so one that many slices hold has a row for each. Blank lines are no nodes.
    """
    place = pa.struct([("_doc", pa.int64()), ("_text", pa.int64()), ("no", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            docs_, hashes_ = (b.column(k).to_numpy() for k in (0, 1))
            order = np.lexsort((hashes_, docs_))  # the first place in a batch is then the first that is met
            texts, at = common.texts_of(b.column(2).take(pa.array(order))), 0
            docs_, hashes_ = docs_[order], hashes_[order]
            for part in common.slices(texts, SLICE_CHARS):
                found = units(part)
                if found:
                    lines, nodes = list(found), nodes_of(found)
                    row, no = np.array(list(found.values()), np.int64).T
                    sizes = np.fromiter(map(len, lines), np.int64, len(lines))
                    for kind, which, keys in signatures(lines, s, hashes):
                        r = row[which] + at
                        first = pa.StructArray.from_arrays([pa.array(docs_[r]), pa.array(hashes_[r]), pa.array(no[which].astype(np.int32))], fields=list(place))
                        cols = [pa.array(nodes[which]), pa.array(np.full(len(which), kind, np.int32)), pa.array(sizes[which]), first, packed(keys)]
                        yield pa.record_batch(cols, names=["node", "kind", "size", "at", "keys"])
                at += len(part)

    return common.mapped(docs.select("_doc", "_text", "text"), run, f"node long, kind int, size long, {AT}, keys binary")


def shared_keys(keyed: DataFrame, page_keys: int = PAGE_KEYS, bands: int | None = None) -> DataFrame:
    """(key): the keys that stand beside two nodes or more in keyed(node, b0, b1, ...) or, packed, keyed(node, keys).

    Keys are hashes, nearly all of one node, so adding up rows saves nothing before they are exchanged.
    They travel packed instead: a task sorts about ``page_keys`` of them, leaves at most two nodes beside
    each and cuts them into pages by ranges of keys; of a range, all pages meet and are sorted again.
    """
    ranges = max(1, -(-keyed.count() * (bands or len(keyed.columns) - 1) // page_keys))
    cuts = np.array([(k << 64) // ranges - (1 << 63) for k in range(1, ranges)], np.int64)

    def ends(key: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Each key with its smallest and its largest node."""
        order = np.argsort(key)
        key, node = key[order], node[order]
        at = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        return key[at], np.minimum.reduceat(node, at), np.maximum.reduceat(node, at)

    def paged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def out() -> Iterator[pa.RecordBatch]:
            key, lo, hi = ends(np.concatenate([k for k, _ in held]), np.concatenate([n for _, n in held]))
            twice = 1 + (lo != hi)
            last = np.cumsum(twice) - 1
            key, node = np.repeat(key, twice), np.repeat(lo, twice)
            node[last] = hi
            at = np.r_[0, np.searchsorted(key, cuts), len(key)]
            for k in np.flatnonzero(np.diff(at)).tolist():
                cut = slice(at[k], at[k + 1])
                yield pa.record_batch({"part": pa.array([k], pa.int32()), "keys": pa.array([key[cut].tobytes()]), "nodes": pa.array([node[cut].tobytes()])})

        for b in batches:
            node = b.column(0).to_numpy()
            for keys in unpacked(b, 1):
                held.append((keys, node))
                size += len(node)
            if size >= page_keys:
                yield from out()
                held, size = [], 0
        if size:
            yield from out()

    def several(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def out() -> pa.RecordBatch:
            key, lo, hi = ends(*(np.concatenate([np.frombuffer(x[k], np.int64) for x in held]) for k in (0, 1)))
            return pa.record_batch({"key": pa.array(key[lo != hi])})

        for b in batches:
            for part, *page in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if part != now and held:
                    yield out()
                    held = []
                now = part
                held.append(page)
        if held:
            yield out()

    pages = common.mapped(keyed, paged, "part int, keys binary, nodes binary")
    return common.mapped(pages.repartition("part").sortWithinPartitions("part"), several, "key long")


def buckets(sigs: DataFrame, s: Settings) -> tuple[DataFrame, DataFrame]:
    """(own, stats) of the bands for common.link_buckets().

    Most bands are a line's alone. Those of several nodes are counted first; a bitmap of fixed size of
    them leaves out most others where the signatures stand, and a join the rest, at any size.
    """
    several = materialize(shared_keys(sigs.select("node", "keys"), bands=s.bands), "several")
    bits = common.bits_for(several.count())
    sent = sigs.sparkSession.sparkContext.broadcast(common.bitmap(several, "key", bits))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for keys in unpacked(b, 2):
                hit = np.flatnonzero(common.marked(sent.value, keys, bits))
                if len(hit):
                    yield pa.record_batch([pa.array(keys[hit]), b.column(0).take(hit), b.column(1).take(hit)], names=["key", "node", "size"])

    near = common.mapped(sigs.select("node", "size", "keys"), run, "key long, node long, size long").distinct()
    own = materialize(near.join(several.hint("merge"), "key"), "own")
    stats = materialize(common.bucket_stats(own), "stats")
    discard(several)
    return own.select("key", "node"), stats


def similar_pairs(h: np.ndarray, counts: np.ndarray, x: np.ndarray, y: np.ndarray, similarity: float) -> np.ndarray:
    """Whether the sets of lines x[k] and y[k] are similar, given all lines' hashes and their numbers.

    A pair's hashes are sorted together, their lowest bit telling the lines apart; the rest is done for all pairs at once.
    """
    if not len(x):
        return np.zeros(0, bool)
    row = np.stack([x, y], 1).reshape(-1)
    n = counts[row]
    ends, begin = np.cumsum(n), (np.cumsum(counts) - counts)[row]
    z = h[np.repeat(begin - (ends - n), n) + np.arange(ends[-1])] & np.uint64(2**64 - 2)
    z |= np.repeat(np.tile(np.array([0, 1], np.uint64), len(x)), n)
    starts = np.r_[0, ends[1::2]]
    for a, b in zip(starts[:-1].tolist(), starts[1:].tolist(), strict=True):
        z[a:b].sort()
    new = np.r_[True, z[1:] != z[:-1]]
    new[starts[:-1]] = True
    total = np.add.reduceat(new, starts[:-1], dtype=np.int64)
    z = z[new] >> np.uint64(1)
    twice = np.r_[False, z[1:] == z[:-1]]
    starts = np.r_[0, np.cumsum(total)[:-1]]
    twice[starts] = False
    both = np.add.reduceat(twice, starts, dtype=np.int64)
    return both >= similarity * (total - both) - 1e-9


def small_cells(h: np.ndarray, counts: np.ndarray, starts: np.ndarray, n: int, similarity: float) -> tuple[list[int], list[int]]:
    """Links that connect what is similar in the cells of n lines that begin at ``starts``."""
    i, j = np.triu_indices(n, 1)
    x, y = (starts[:, None] + i).reshape(-1), (starts[:, None] + j).reshape(-1)
    near = similar_pairs(h, counts, x, y, similarity)
    x, y = x[near].tolist(), y[near].tolist()
    if n == 2:
        return x, y
    up: dict[int, int] = {}
    a_out, b_out = [], []
    for a, b in zip(x, y, strict=True):
        u, v = a, b
        while u in up:
            u = up[u]
        while v in up:
            v = up[v]
        if u != v:
            up[v] = u
            a_out.append(a)
            b_out.append(b)
    return a_out, b_out


def linker(s: Settings, hashes: Hashes = shingle_hashes) -> common.Linker:
    def run(t: pa.Table, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Cells are taken in runs of about SLICE_CHARS characters, which bounds the hashes held."""
        ends = np.r_[starts[1:], t.num_rows]
        chars = np.r_[0, np.cumsum(pc.utf8_length(t.column("line")).to_numpy())]
        run_of = (chars[starts] // SLICE_CHARS).astype(np.int64)
        a_out, b_out = [], []
        for k in np.unique(run_of).tolist():
            own = np.flatnonzero(run_of == k)
            lo, hi = int(starts[own[0]]), int(ends[own[-1]])
            a, b = compared(t.slice(lo, hi - lo), starts[own] - lo)
            a_out.append(a)
            b_out.append(b)
        return np.concatenate(a_out), np.concatenate(b_out)

    def compared(t: pa.Table, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        node = t.column("node").to_numpy()
        h, counts = hashes(t.column("line").to_pylist(), s.shingle)
        cuts = np.r_[0, np.cumsum(counts)].tolist()
        side = t.column("side").to_numpy()
        ends = np.r_[starts[1:], len(node)]
        size, sided = ends - starts, np.logical_or.reduceat(side != 0, starts)
        a_out, b_out = [], []
        for n in range(2, SMALL + 1):
            a, b = small_cells(h, counts, starts[(size == n) & ~sided], n, s.similarity)
            a_out += node[a].tolist()
            b_out += node[b].tolist()
        rest = (size > SMALL) | sided & (size > 1)
        for lo, hi in zip(starts[rest].tolist(), ends[rest].tolist(), strict=True):
            own = [distinct(h[a:b]) for a, b in zip(cuts[lo:hi], cuts[lo + 1 : hi + 1], strict=True)]
            sizes = np.array([len(x) for x in own])
            _, at, n = np.unique(np.concatenate(own), return_inverse=True, return_counts=True)
            column = np.cumsum(n > 1) - 1
            shared = (n > 1)[at]
            row, column = np.repeat(np.arange(hi - lo), sizes)[shared], column[at[shared]]
            both = np.zeros((hi - lo, hi - lo), np.float32)
            total = int((n > 1).sum())
            for k in range(0, total, COLUMNS):  # bounds the matrix, however many shingles are shared
                now = (column >= k) & (column < k + COLUMNS)
                m = np.zeros((hi - lo, min(COLUMNS, total - k)), np.float32)
                m[row[now], column[now] - k] = 1
                both += m @ m.T
            near = both >= s.similarity * (sizes[:, None] + sizes[None, :] - both) - 1e-4
            i, j = common.cell_edges(near, side[lo:hi])
            a_out += node[lo:hi][i].tolist()
            b_out += node[lo:hi][j].tolist()
        return np.array(a_out, np.int64), np.array(b_out, np.int64)

    return run


def line_texts(docs: DataFrame, wanted: DataFrame, bits: int) -> DataFrame:
    """(node, line) for the nodes in ``wanted``.

    A bitmap of fixed size (one bit for each remainder of a node) is broadcast to leave out most
    other lines before they are shuffled; the join then leaves out the rest.
    """
    sent = docs.sparkSession.sparkContext.broadcast(common.bitmap(wanted, "node", bits))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in common.slices(common.texts_of(b.column(0)), SLICE_CHARS):
                lines = list(distinct_lines(part))
                nodes = nodes_of(lines)
                hit = np.flatnonzero(common.marked(sent.value, nodes, bits))
                if len(hit):
                    yield pa.record_batch({"node": pa.array(nodes[hit]), "line": pa.array([lines[k] for k in hit.tolist()])})

    found = common.mapped(docs.select("text"), run, "node long, line string")
    return found.join(wanted, "node", "left_semi").groupBy("node").agg(F.min("line").alias("line"))


def similar_lines(docs: DataFrame, sigs: DataFrame, s: Settings = Settings()) -> DataFrame:
    """(node, root) for every line (by its hash) that has a similar, different line."""
    own, stats = buckets(sigs, s)
    wanted = materialize(own.select("node").distinct(), "wanted")
    texts = materialize(line_texts(docs, wanted, common.bits_for(wanted.count())), "texts")
    edges = common.link_buckets(own, stats, s.block, linker(s), lambda cells: cells.join(texts, "node"))
    roots = materialize(common.components(edges), "roots")
    discard(own, stats, texts, wanted)
    return roots


def key_columns(docs: DataFrame) -> tuple[Column, Column]:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("_doc"), F.xxhash64("text").alias("_text")


def keepers(sigs: DataFrame, roots: DataFrame) -> DataFrame:
    """(_doc, _text, kept): numbers of the lines that stay, blank ones not among them."""
    first = sigs.groupBy("node").agg(F.min("at").alias("at")).join(roots, "node", "left").select("root", "at")
    first = materialize(first, "first")
    best = first.where("root is not null").groupBy("root").agg(F.min("at").alias("at")).select("at")
    alone = first.where("root is null").select("at")
    return alone.unionByName(best).select("at.*").groupBy("_doc", "_text").agg(F.collect_list("no").alias("kept"))


def dedup_lines(docs: DataFrame, s: Settings = Settings()) -> DataFrame:
    """docs with their columns, each line in ``text`` kept once over all documents.

    Lines are cut at line feeds and compared without white space at their ends; blank lines stay.
    Lines of Jaccard similarity ``s.similarity`` or more (character shingles) are linked, and one
    line of each component stays, that of the smallest doc_id (null first), then text hash, then
    line number. Rows repeated with one doc_id and text are one document and give the same result.
    Null text stays null, a document may end up with no lines and then has an empty text; n_chars,
    where there is such a column, follows the text.
    """
    names = docs.columns
    plain = docs.select(*key_columns(docs), "text")
    sigs = materialize(signature_table(plain, s), "signatures")
    kept = keepers(sigs, similar_lines(plain, sigs, s))
    # The caller's columns travel inside a struct, where no name can clash with those used here.
    carried = F.struct(F.lit(True).alias("_"), *[F.col(f"`{c}`") for c in names if c != "text"])
    keyed = docs.select(carried.alias("carried"), F.split("text", "\n").alias("lines"), *key_columns(docs)).join(kept.hint("shuffle_hash"), ["_doc", "_text"], "left")
    blank = F.filter(F.transform("lines", lambda x, k: F.when(F.ltrim(x, F.lit(BLANK)) == "", k)), lambda k: k.isNotNull())
    order = F.sort_array(F.concat(F.coalesce("kept", F.array().cast("array<int>")), blank))
    text = F.array_join(F.transform(order, lambda k: F.get("lines", k)), "\n")
    out = {c: F.col("carried")[c] for c in names if c != "text"} | {"text": F.col("text")}
    if "n_chars" in names:
        out["n_chars"] = F.length("text").cast(docs.schema["n_chars"].dataType)
    return keyed.select("carried", text.alias("text")).select(*[out[c].alias(c) for c in names])


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text after deduplication, and the number of lines before and after."""
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = dedup_lines(docs.withColumn("n_lines", F.size(F.split("text", "\n"))))
    return out.select("doc_id", "text", "n_lines", F.when(F.col("text") == "", 0).otherwise(F.size(F.split("text", "\n"))).alias("n_kept"))
