"""SimHash near-duplicates found by deletion variants of segments.

A 64-bit fingerprint is cut into fewer segments than the radius would ask for if segments had to
be equal: with k differing bits and more than k / 2 segments, one segment differs in at most one
bit. Every segment value is indexed once for each of its bits with that bit taken out, so equality of
such a variant stands for "at most one bit apart here"; pairs that meet are verified on all bits.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common, lines, wordsets
from deltamat.llm.wordsets import SPACE
from deltamat.sources.scratch import discard, materialize

SEED = 42
CHUNK = 1 << 16


def fingerprint(text: str | None, words: int = 4) -> int:
    """The 64-bit fingerprint of a whole text, as an unsigned number.

    A-Z are lower-cased, words are runs without ASCII white space, shingles are joined by single
    spaces and count as often as they occur. A bit is set if it is set in over half the hashes.
    A text of fewer words is one shingle; null or no words: zero.
    """
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass").lower(), np.uint8)
    blank = SPACE[raw]
    before = np.r_[True, blank[:-1]] if len(raw) else blank
    starts = np.flatnonzero(~blank & before)
    if not len(starts):
        return 0
    last = len(raw) - 1 - int(np.argmin(blank[::-1]))
    keep = (~blank | ~before)[: last + 1]
    at = np.cumsum(keep) - 1
    norm = np.where(blank, np.uint8(0x20), raw)[: last + 1][keep].tobytes()
    starts = at[starts]
    ends = np.r_[starts[1:] - 1, len(norm)]
    n = max(1, len(starts) - words + 1)
    starts, ends = starts[:n], ends[-n:]
    counts, digest = np.zeros(64, np.int64), xxhash.xxh64_intdigest
    for k in range(0, n, CHUNK):
        h = [digest(norm[a:b], SEED) for a, b in zip(starts[k : k + CHUNK].tolist(), ends[k : k + CHUNK].tolist(), strict=True)]
        bits = np.unpackbits(np.array(h, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(0, dtype=np.int32)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, text_hash): the fingerprint as a signed long, for every row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t.as_py()) for t in b.column(1)], np.uint64)
            yield pa.record_batch({"doc_id": b.column(0), "fp": pa.array(fp.view(np.int64)), "text_hash": b.column(2)})

    plain = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text").alias("text_hash"))
    return common.mapped(plain, run, "doc_id long, fp long, text_hash long")


def segments(radius: int) -> list[tuple[int, int]]:
    """(first bit, last bit + 1) of each segment: more than radius / 2 of them."""
    n = radius // 2 + 1
    edges = [64 * k // n for k in range(n + 1)]
    return list(zip(edges, edges[1:], strict=False))


def signed(bits: int) -> int:
    return bits - (1 << 64) if bits >> 63 else bits


def cut(fps: DataFrame, radius: int) -> DataFrame:
    """(s, u, node): each fingerprint's segments, by number and by value (in place)."""
    parts = [F.struct(F.lit(k).alias("s"), F.col("node").bitwiseAND(F.lit(signed((1 << hi) - (1 << lo)))).alias("u")) for k, (lo, hi) in enumerate(segments(radius))]
    return fps.select(F.explode(F.array(*parts)).alias("p"), "node").select("p.s", "p.u", "node")


def variants(groups: DataFrame, radius: int) -> DataFrame:
    """(s, bit, rest, n, least): every segment value with one of its bits taken out, for each bit.

    Two values share a variant if and only if they are equal but for that bit, so a variant has at
    most two values: ``rest`` itself and rest with the bit.
    """
    out = None
    for k, (lo, hi) in enumerate(segments(radius)):
        own = [F.struct(F.lit(bit).alias("bit"), F.col("u").bitwiseAND(F.lit(~signed(1 << bit))).alias("rest")) for bit in range(lo, hi)]
        part = groups.where(F.col("s") == k).select("s", F.explode(F.array(*own)).alias("v"), "n", "least").select("s", "v.bit", "v.rest", "n", "least")
        out = part if out is None else out.unionByName(part)
    return out


def links(fps: DataFrame, radius: int, block: int) -> DataFrame:
    """Edges (a, b) that connect the distinct fingerprints ``node`` within the radius.

    Fingerprints with one segment value are a group. The one-wildcard variants of the values tell
    which groups are one bit apart; of two such groups the smaller visits the larger, so a fingerprint
    stands in its own groups and in a few others, however many variants a large group shares. Lone
    fingerprints that meet, which chance makes, are verified by their exclusive or while counted.
    """
    h = F.xxhash64("node")
    parts = cut(fps, radius)
    sums = F.count("*").alias("n"), F.min("node").alias("least"), F.bit_xor("node").alias("xor"), F.bit_xor(h).alias("x"), F.sum(F.shiftrightunsigned(h, 34)).alias("y")
    groups = materialize(parts.groupBy("s", "u").agg(*sums), "groups")
    met = variants(groups, radius).groupBy("s", "bit", "rest").agg(F.count("*").alias("c"), F.max("n").alias("n"), F.min("least").alias("least"), F.bit_xor("least").alias("xor")).where("c = 2")
    met = materialize(met.where((F.col("n") > 1) | (F.bit_count("xor") <= radius)), "met")
    lone = met.where("n = 1").select(F.col("least").alias("a"), F.col("least").bitwiseXOR(F.col("xor")).alias("b"))

    one_bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("bit"))
    ends = met.where("n > 1").select("s", F.col("rest").alias("u"), F.col("rest").bitwiseOR(one_bit).alias("v"))
    of = lambda name: groups.select("s", F.col("u").alias(name), *[F.col(c).alias(f"{name}_{c}") for c in ("n", "x", "y")])
    both = ends.join(of("u"), ["s", "u"]).join(of("v"), ["s", "v"])
    up = F.struct("u_n", "u") < F.struct("v_n", "v")
    pick = lambda c, small: F.when(up if small else ~up, F.col(f"u{c}")).otherwise(F.col(f"v{c}"))
    visits = materialize(both.select("s", pick("", True).alias("u"), pick("", False).alias("to"), *[pick(f"_{c}", True).alias(f"v{c}") for c in ("n", "x", "y")]), "visits")
    came = visits.groupBy("s", F.col("to").alias("u")).agg(F.sum("vn").alias("vn"), F.bit_xor("vx").alias("vx"), F.sum("vy").alias("vy"))
    zero = F.lit(0).cast("long")
    total = groups.where("n > 1").join(came, ["s", "u"], "left").select("s", "u", (F.col("n") + F.coalesce("vn", zero)).alias("n"), "least", "xor", F.col("x").bitwiseXOR(F.coalesce("vx", zero)).alias("x"), (F.col("y") + F.coalesce("vy", zero)).alias("y"))
    two = total.where((F.col("n") == 2) & (F.bit_count("xor") <= radius)).select(F.col("least").alias("a"), F.col("least").bitwiseXOR(F.col("xor")).alias("b"))

    # Of buckets with the same fingerprints one is compared.
    key = lambda u: F.xxhash64("s", u)
    stats = total.where("n > 2").select(key("u").alias("key"), "n", "least", "x", "y").groupBy("n", "x", "y").agg(F.min("key").alias("key"), F.min("least").alias("least"))
    stats = materialize(stats.select("key", "n", "least"), "stats")
    routes = groups.where("n > 1").select("s", "u", key("u").alias("key")).unionByName(visits.select("s", "u", key("to").alias("key"))).join(stats.select("key"), "key", "left_semi")
    own = materialize(parts.join(routes.hint("merge"), ["s", "u"]).select("key", "node"), "own")
    edges = common.link_buckets(own, stats, block, linker(radius))
    discard(own, stats)
    return lone.unionByName(two).unionByName(edges)


def linker(radius: int) -> common.Linker:
    def run(t: pa.Table, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        node = fp = t.column("node").to_numpy()
        side = t.column("side").to_numpy()
        ends = np.r_[starts[1:], len(node)]
        near = lambda x, y: np.bitwise_count((x ^ y).view(np.uint64)) <= radius
        two = starts[ends - starts == 2]
        two = two[near(fp[two], fp[two + 1])]
        a, b = [node[two]], [node[two + 1]]
        for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
            if e - s > 2:
                f = fp[s:e]
                i, j = common.cell_edges(near(f[:, None], f[None, :]), side[s:e])
                a.append(node[s:e][i])
                b.append(node[s:e][j])
        return np.concatenate(a), np.concatenate(b)

    return run


def alike(docs: DataFrame, fp: DataFrame, s: lines.Settings) -> DataFrame:
    """Edges (a, b) between the fingerprints of texts whose word shingles are alike enough."""
    of = fp.select("text_hash", "fp").distinct()
    ends = [of.select(F.col("text_hash").alias(x), F.col("fp").alias(f"{x}_fp")) for x in "ab"]
    found = wordsets.links(docs, s).join(ends[0], "a").join(ends[1], "b")
    return found.where("a_fp <> b_fp").select(F.col("a_fp").alias("a"), F.col("b_fp").alias("b"))


def classes(docs: DataFrame, radius: int, block: int, words: lines.Settings | None) -> tuple[DataFrame, DataFrame]:
    """The written fingerprints() of docs, and (fp, root) for each fingerprint that is linked to another."""
    fp = materialize(fingerprints(docs), "fingerprints")
    spread = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    index = fp.select(F.col("fp").alias("node")).distinct().repartition(spread, F.xxhash64("node"))
    edges = links(index, radius, block)
    if words:
        edges = edges.unionByName(alike(docs, fp, words))
    return fp, materialize(common.components(edges).select(F.col("node").alias("fp"), "root"), "roots")


def near_duplicates(docs: DataFrame, radius: int = 4, block: int = 512, words: lines.Settings | None = None) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of docs.

    Fingerprints link at ``radius`` or fewer differing bits and, where ``words`` is given, also where
    two of their texts have that Jaccard similarity of word shingles; component_id is the smallest
    doc_id reachable. Equal fingerprints are one node, so copies never meet each other as pairs. Repeated
    rows give repeated results; rows without doc_id get their fingerprint and the component's id,
    which is null if no row of the component has a doc_id. Other columns are not looked at; an
    empty table gives an empty result.
    """
    fp, roots = classes(docs, radius, block, words)
    nodes = fp.groupBy("fp").agg(F.min("doc_id").alias("least"))
    # Only linked fingerprints have a component to look up; its smallest id is written, so that the
    # join by root is one that a giant component does not hold up.
    linked = materialize(nodes.join(roots, "fp").select("fp", "least", "root"), "linked")
    named = materialize(linked.groupBy("root").agg(F.min("least").alias("component_id")), "named")
    ids = linked.join(named.hint("merge"), "root").select("fp", F.lit(True).alias("linked"), "component_id")
    single = nodes.join(ids, "fp", "left").select("fp", F.when(F.col("linked"), F.col("component_id")).otherwise(F.col("least")).alias("component_id"))
    single = materialize(single, "single")  # the last join is then one whose hot fingerprints are split
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint")
    return fp.join(single.hint("merge"), "fp").select("doc_id", hexed, "component_id")


def drop_near_duplicates(docs: DataFrame, radius: int = 4, words: lines.Settings | None = None) -> DataFrame:
    """docs with one row of each component: that of the smallest doc_id.

    Rows of one doc_id and different texts are told apart: of equal ids the smaller fingerprint and
    then the smaller text hash stays. Rows without doc_id come after all others, so one stays where
    its whole component has no id. Of rows repeated with one doc_id and text any one stays.
    """
    fp, roots = classes(docs, radius, 512, words)
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "fp", "text_hash")
    best = fp.groupBy("fp").agg(F.min(place).alias("at")).join(roots, "fp", "left")
    best = best.groupBy(F.coalesce("root", "fp").alias("root")).agg(F.min("at").alias("at"))
    kept = best.select(F.coalesce("at.doc_id", F.lit(-(1 << 63))).alias("_doc"), F.col("at.none").alias("_none"), F.coalesce("at.text_hash", F.lit(0).cast("long")).alias("_text"))
    # The caller's columns travel inside a struct, where no name can clash with those used here.
    doc = F.col("doc_id").cast("long")
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.coalesce(doc, F.lit(-(1 << 63))).alias("_doc"), doc.isNull().alias("_none"), F.xxhash64("text").alias("_text"))
    once = keyed.join(kept, ["_doc", "_none", "_text"], "left_semi").dropDuplicates(["_doc", "_none", "_text"])
    return once.select("row.*")


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(common.table(spark, sf_dir, "documents"))
