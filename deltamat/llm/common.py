"""What several operators share: reading, Arrow helpers, linking inside buckets, components.

Links between near copies are found bucket by bucket. A bucket's members are compared where they
meet, but only a spanning forest of the links found there leaves the task, so a group of n copies
costs n - 1 rows and not n * n. Buckets over ``block`` members are cut, see link_buckets().
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.sources.scratch import discard, materialize
from deltamat.sources.shipping import ship

Linker = Callable[[pa.Table, np.ndarray], tuple[np.ndarray, np.ndarray]]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of a batch that goes to a Python worker; a single longer row is a batch of its own.
BATCH_BYTES = 8 << 20


def mapped(df: DataFrame, run: Callable, schema) -> DataFrame:
    """mapInArrow() in batches bounded by bytes as well, so that many long texts never travel at once."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    return df.mapInArrow(run, schema)


def mix(node: Column) -> Column:
    """A bijection of 64-bit numbers (xor-shifts) that breaks the order of ids."""
    for n, right in ((13, False), (7, True), (17, False)):
        node = node.bitwiseXOR(F.shiftrightunsigned(node, n) if right else F.shiftleft(node, n))
    return node


def components(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(node, root) for every node of the edges (a, b); root is its component's smallest node.

    Each round points every node at its smallest neighbour (in a mixed order, so that chains are
    short), follows pointers twice and contracts the graph to the nodes pointed at. Self-loops and
    repeated edges do no harm, rows with a null end are left out. Rounds are cut by written tables.
    """
    spark = edges.sparkSession
    first = edges.where("a is not null and b is not null and a <> b").select(F.col("a").cast("long"), F.col("b").cast("long"))
    first = materialize(first.distinct(), "edges")
    e = first.select(mix(F.col("a")).alias("a"), mix(F.col("b")).alias("b"))
    nodes = first.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    labels = materialize(nodes.select("node", mix(F.col("node")).alias("at")), "labels")
    old: list[DataFrame] = []
    for _ in range(max_rounds):
        both = e.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("x")).select("x.*")
        near = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("n"), F.least("a", "m").alias("p"))
        near = materialize(near, "near")
        if near.isEmpty():
            discard(near)
            break
        up = near.select(F.col("n").alias("p"), F.col("p").alias("q"))
        far = materialize(near.join(up, "p").select("n", F.col("q").alias("p")), "far")
        go = lambda name: far.select(F.col("n").alias(name), F.col("p").alias(f"{name}_to"))  # noqa: E731, B023
        moved = e.join(go("a"), "a").join(go("b"), "b").where("a_to <> b_to")
        fewer = materialize(moved.select(F.least("a_to", "b_to").alias("a"), F.greatest("a_to", "b_to").alias("b")).distinct(), "fewer")
        relabelled = materialize(labels.join(go("at"), "at", "left").select("node", F.coalesce("at_to", "at").alias("at")), "labels")
        discard(near, far, labels, *old)
        old, e, labels = [fewer], fewer, relabelled
    else:
        raise RuntimeError("components did not settle")
    discard(first, *old)
    smallest = labels.groupBy("at").agg(F.min("node").alias("root"))
    return labels.join(smallest, "at").select("node", "root")


def forest(adjacent: np.ndarray) -> tuple[list[int], list[int]]:
    """Edges of a spanning forest of a small graph given as a boolean matrix."""
    n, a, b = len(adjacent), [], []
    open_ = np.ones(n, bool)
    for seed in range(n):
        if not open_[seed]:
            continue
        open_[seed] = False
        front = np.array([seed])
        while len(front) and open_.any():
            hit = adjacent[front][:, open_]
            new = np.flatnonzero(open_)[hit.any(0)]
            a += front[hit[:, hit.any(0)].argmax(0)].tolist()
            b += new.tolist()
            open_[new] = False
            front = new
    return a, b


def cell_edges(near: np.ndarray, side: np.ndarray) -> tuple[list[int], list[int]]:
    """Edges that connect a cell's rows: within one piece a spanning forest.

    Between two pieces only edges that join what each piece has linked by itself (in the cell of its
    own), so a large group costs an edge for each row and each pair of pieces.
    """
    if not side.any():
        return forest(near)
    inner = near & (side[:, None] == side[None, :])
    root = np.arange(len(near))
    for a, b in zip(*forest(inner), strict=True):  # parents come before children
        root[b] = root[a]
    first = np.flatnonzero(side == 0)
    second = np.flatnonzero(side == 1)
    i, j = np.nonzero(near[np.ix_(first, second)])
    i, j = first[i], second[j]
    _, one = np.unique(root[i] * len(near) + root[j], return_index=True)
    up = list(range(len(near)))

    def find(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    a_out, b_out = [], []
    for a, b in zip(i[one].tolist(), j[one].tolist(), strict=True):
        x, y = find(int(root[a])), find(int(root[b]))
        if x != y:
            up[x] = y
            a_out.append(a)
            b_out.append(b)
    return a_out, b_out


def bitmap(keys: DataFrame, column: str, bits: int) -> np.ndarray:
    """A bit for each remainder of the column's values modulo ``bits``, as bytes for marked()."""
    place = (F.pmod(F.col(column), F.lit(bits)) + 1).alias("p")  # Spark numbers bits from 1
    maps = keys.select(place).groupBy(F.bitmap_bucket_number("p").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("m")).collect()
    field = np.zeros((bits // 32768 + 1, 4096), np.uint8)
    for k, m in maps:
        field[k - 1] = np.frombuffer(m, np.uint8)
    return field.reshape(-1)


def marked(field: np.ndarray, values: np.ndarray, bits: int) -> np.ndarray:
    """Which values may be among those of the bitmap; those that are not may be left out."""
    p = values % bits
    return (field[p >> 3] >> (p & 7).astype(np.uint8) & 1).astype(bool)


def bits_for(n: int) -> int:
    """Bits of a bitmap for n keys, 16 for each, of 16 MB at most."""
    return 1 << min(27, max(20, (16 * n).bit_length()))


def bucket_stats(own: DataFrame) -> DataFrame:
    """(key, n, least, chars) of the buckets of two nodes or more in own(key, node, size).

    Of buckets that hold the same nodes only one is kept.
    """
    h = F.xxhash64("node")
    marks = F.bit_xor(h).alias("x"), F.sum(F.shiftrightunsigned(h, 34)).alias("s")
    stats = own.groupBy("key").agg(F.count("*").alias("n"), F.min("node").alias("least"), F.sum("size").alias("chars"), *marks).where("n > 1")
    return stats.groupBy("n", "x", "s").agg(*[F.min(c).alias(c) for c in ("key", "least", "chars")]).drop("x", "s")


#: Characters of the payloads that meet in one piece of a bucket.
PIECE_CHARS = 1 << 21


def link_buckets(own: DataFrame, stats: DataFrame, block: int, linker: Linker, dress: Callable[[DataFrame], DataFrame] = lambda cells: cells) -> DataFrame:
    """Edges (a, b) that connect what ``linker`` links in the buckets own(key, node); stats: (key, n, least[, chars]).

    ``own`` is read twice and best written. ``dress`` adds the linker's payload to the cells. A bucket of up to ``block`` nodes is one cell. A
    larger one is cut by hash, and each piece meets one node of the bucket as well, so that what is near
    that node becomes one component in one linear pass. Only buckets that are still several components
    go on: in them nodes outside the main component meet each other and the main component, piece by
    piece, and the main component's nodes are not compared again among themselves. All pairs are thus
    compared or known to be connected.
    """
    pieces = F.ceil(F.col("n") / block)
    if "chars" in stats.columns:
        pieces = F.greatest(pieces, F.ceil(F.col("chars") / PIECE_CHARS))
    sized = materialize(stats.select("key", "least", pieces.cast("int").alias("pieces")), "sizes")
    piece = lambda count: F.pmod(F.xxhash64("node"), count).cast("int")
    no_side = F.lit(0).alias("side")
    whole = own.join(sized.select("key", "pieces").hint("merge"), "key").select("key", piece(F.col("pieces")).alias("i"), "node")
    heads = sized.where("pieces > 1").select("key", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)).alias("i"), F.col("least").alias("node"))
    first = whole.unionByName(heads).select("key", "i", F.col("i").alias("j"), no_side, "node")
    edges = materialize(link(dress(first), linker), "links")
    large = sized.where("pieces > 1")
    if large.isEmpty():
        discard(sized)
        return edges
    roots = components(edges)
    open_ = own.join(large.select("key", "pieces"), "key").join(roots, "node", "left").select("key", "node", "pieces", F.coalesce("root", "node").alias("root"))
    open_ = materialize(open_, "open")
    per = open_.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.max_by("root", F.xxhash64("node")).alias("main")).where("lo <> hi").select("key", "main")
    told = open_.join(per, "key").withColumn("apart", F.col("root") != F.col("main"))
    share = told.groupBy("key").agg(F.count_if("apart").alias("n_apart"), F.count("*").alias("n"), F.max("pieces").alias("pieces"))
    cuts = lambda n: F.greatest(F.lit(1), F.ceil(F.col("pieces") * n / F.col("n"))).cast("int")
    share = share.select("key", cuts(F.col("n_apart")).alias("pa"), cuts(F.col("n") - F.col("n_apart")).alias("pm"))
    dealt = told.join(share, "key").withColumn("own", piece(F.when(F.col("apart"), F.col("pa")).otherwise(F.col("pm"))))
    cell = lambda i, j, side: F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"), side.cast("int").alias("side"))
    mine, others, mains = F.col("own"), F.sequence(F.lit(0), F.col("pa") - 1), F.sequence(F.lit(0), F.col("pm") - 1)
    among = F.transform(others, lambda o: cell(F.least(mine, o), F.greatest(mine, o), mine > o))
    across = F.transform(mains, lambda m: cell(mine, F.col("pa") + m, F.lit(0)))
    visited = F.transform(others, lambda o: cell(o, F.col("pa") + mine, F.lit(1)))
    cells = dealt.select("key", "node", F.explode(F.when(F.col("apart"), F.concat(among, across)).otherwise(visited)).alias("c"))
    more = materialize(link(dress(cells.select("key", "c.i", "c.j", "c.side", "node")), linker), "links")
    discard(sized, open_)
    return edges.unionByName(more)


def slices(texts: list[str], most: int) -> Iterator[list[str]]:
    """Runs of texts of about ``most`` characters in all; a longer text is a run of its own."""
    part, size = [], 0
    for t in texts:
        if part and size + len(t) > most:
            yield part
            part, size = [], 0
        part.append(t)
        size += len(t)
    if part:
        yield part


def link(cells: DataFrame, linker: Linker) -> DataFrame:
    """Edges (a, b) that ``linker`` finds within each cell (key, i, j) of rows (node, payload).

    The linker gets whole cells: a table sorted by cell and the starts of its cells. Rows stream
    through; only the last, unfinished cell of a batch is held over.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None

        def found(t: pa.Table) -> tuple[pa.RecordBatch, pa.Table]:
            k = np.stack([t.column(c).to_numpy() for c in ("key", "i", "j")])
            starts = np.flatnonzero(np.r_[True, (k[:, 1:] != k[:, :-1]).any(0)])
            return t, starts

        def out(t: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
            a, b = linker(t, starts)
            return pa.record_batch({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t, starts = found(pa.concat_tables([held, t]).combine_chunks() if held is not None else t)
            whole = starts[-1]
            if whole:
                yield out(t.slice(0, whole), starts[:-1])
            held = pa.concat_tables([t.slice(whole)])
        if held is not None:
            t, starts = found(held.combine_chunks())
            yield out(t, starts)

    dealt = cells.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "node")
    return mapped(dealt, run, "a long, b long")


def texts_of(column: pa.Array) -> list[str]:
    return ["" if x is None else x for x in column.to_pylist()]
