"""Approximate nearest neighbours in a hierarchical k-means tree.

The tree is fitted on a bounded sample and broadcast; every vector is indexed in its leaf. A query
walks the tree best bin first, through a priority queue of nodes by the distance of their centres,
and visits as many leaves as the calibration asks for: queries with exactly known neighbours tell
in which of their leaves these lie, and the visits are widened until the target recall is reached.
Equal vectors are one entry with its smallest ids, which are all that any answer can hold.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamat.llm import common
from deltamat.sources.scratch import materialize


@dataclass(frozen=True)
class Settings:
    """sample: vectors the tree is fitted on; probes: queries of the calibration; cell: entries of a task's block."""

    neighbours: int = 10
    branch: int = 8
    leaf: int = 48
    sample: int = 20_000
    probes: int = 200
    recall: float = 0.97
    rounds: int = 8
    cell: int = 20_000
    queries_cell: int = 4096
    seed: int = 5


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres * centres).sum(1)[None, :] - 2 * (x @ centres.T)).argmin(1)


def kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    centres = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        own = nearest(x, centres)
        sizes = np.bincount(own, minlength=k)
        sums = np.zeros_like(centres)
        np.add.at(sums, own, x)
        centres = np.where(sizes[:, None] > 0, sums / np.maximum(sizes, 1)[:, None], centres)
    return centres


class Tree:
    """children[n]: first child and number of children of node n (0: a leaf); leaf[n]: its number."""

    def __init__(self, x: np.ndarray, s: Settings):
        rng = np.random.default_rng(s.seed)
        self.centres = [x.mean(0) if len(x) else np.zeros(x.shape[1])]
        self.children: list[tuple[int, int]] = [(0, 0)]
        self.leaf: list[int] = [-1]
        open_ = [(0, x)]
        while open_:
            node, own = open_.pop()
            k = min(s.branch, -(-len(own) // s.leaf))
            if k > 1:
                centres = kmeans(own, k, s.rounds, rng)
                to = nearest(own, centres)
                if len(np.unique(to)) > 1:
                    self.children[node] = (len(self.centres), k)
                    for c in range(k):
                        open_.append((len(self.centres), own[to == c]))
                        self.centres.append(centres[c])
                        self.children.append((0, 0))
                        self.leaf.append(-1)
        self.centres = np.array(self.centres)
        leaves = [n for n, (_, k) in enumerate(self.children) if not k]
        for number, n in enumerate(leaves):
            self.leaf[n] = number
        self.leaves = len(leaves)

    def route(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row, by the nearest child at every level."""
        out = np.zeros(len(x), np.int32)
        open_ = [(0, np.arange(len(x)))]
        while open_:
            node, rows = open_.pop()
            first, k = self.children[node]
            if not k:
                out[rows] = self.leaf[node]
            elif len(rows):
                to = nearest(x[rows], self.centres[first : first + k])
                open_ += [(first + c, rows[to == c]) for c in range(k)]
        return out

    def best_bins(self, q: np.ndarray, visits: int, enough: int, sizes: np.ndarray) -> list[int]:
        """Leaves in the order visited: at least ``visits``, and more until they hold ``enough`` entries."""
        d = ((self.centres - q) ** 2).sum(1).tolist()
        heap, out, held = [(0.0, 0)], [], 0
        while heap and (len(out) < visits or held < enough):
            _, node = heapq.heappop(heap)
            first, k = self.children[node]
            for c in range(first, first + k):
                heapq.heappush(heap, (d[c], c))
            if not k:
                out.append(self.leaf[node])
                held += int(sizes[self.leaf[node]])
        return out


def matrix(column: pa.Array) -> np.ndarray:
    """Rows of an array<float> column of one length, in double precision."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def usable(vec: Column) -> Column:
    """Not null, no null or non-finite component, not all zero."""
    fine = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vec.isNotNull() & fine & F.exists(vec, lambda x: x != 0)


def closest(q: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows, squared distances) of the k nearest of x, nearest first, ties to the smaller id."""
    d = ((x - q) ** 2).sum(1)
    if len(d) > k:
        cut = np.partition(d, k - 1)[k - 1]
        keep = np.flatnonzero(d <= cut)
    else:
        keep = np.arange(len(d))
    order = keep[np.lexsort((ids[keep], d[keep]))][:k]
    return order, d[order]


def entries(vectors: DataFrame, s: Settings) -> DataFrame:
    """(vec, ids): each distinct vector with its smallest ids, neighbours + 1 of them."""
    by_vec = Window.partitionBy("vec").orderBy("vec_id")
    few = vectors.distinct().withColumn("k", F.row_number().over(by_vec)).where(F.col("k") <= s.neighbours + 1)
    return few.groupBy("vec").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))


def search(rows: DataFrame, queries: Column, s: Settings = Settings()) -> DataFrame:
    """(query_id, rank, vec_id, score): the nearest entries found for each row of vec_id and vec chosen by ``queries``.

    Score is the Euclidean distance in double precision, rank from 1, nearest first, ties to the
    smaller vec_id; a query's own id is never its answer. Vectors that are null, empty, zero or hold
    null or non-finite components, rows without vec_id, and vectors of another length than the most
    common one take no part. Of several vectors under one id the smallest (as an array) holds.
    """
    spark = rows.sparkSession
    own = rows.select(F.col("vec_id").cast("long"), F.col("vec").cast("array<double>").alias("vec")).where(usable(F.col("vec")) & F.col("vec_id").isNotNull())
    common_size = own.groupBy(F.size("vec").alias("n")).count().orderBy(F.desc("count"), "n").first()
    schema = "query_id long, rank int, vec_id long, score double"
    if common_size is None:
        return spark.createDataFrame([], schema)
    own = own.where(F.size("vec") == common_size["n"]).groupBy("vec_id").agg(F.min("vec").alias("vec"))
    own = materialize(own, "vectors")
    table = entries(own, s)
    table = materialize(table.select("vec", "ids", F.element_at("ids", 1).alias("entry")), "entries")
    by_hash = table.orderBy(F.xxhash64("entry"), "entry")
    tree = Tree(np.array([r[0] for r in by_hash.select("vec").limit(s.sample).collect()], np.float64), s)
    sent = spark.sparkContext.broadcast(tree)

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.record_batch([*b.columns, pa.array(sent.value.route(matrix(b.column(0))))], names=["vec", "ids", "entry", "leaf"])

    index = materialize(common.mapped(table, route, "vec array<double>, ids array<long>, entry long, leaf int"), "index")
    sizes = np.zeros(tree.leaves, np.int64)
    for leaf, n in index.groupBy("leaf").count().collect():
        sizes[leaf] = n
    visits = calibrate(index, tree, sizes, s)

    # Queries with one vector are one; a query asks for one entry more than it needs, to leave itself out.
    asked = own.where(queries).select(F.col("vec_id").alias("query_id"), "vec")
    distinct = asked.groupBy("vec").agg(F.min("query_id").alias("q"))
    want = s.neighbours + 1
    pieces, cuts = np.maximum(1, -(-sizes // s.cell)), spark.sparkContext.broadcast(sizes)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, leaves = [], []
            for k, q in enumerate(matrix(b.column(0))):
                for leaf in sent.value.best_bins(q, visits, want, cuts.value):
                    at.append(k)
                    leaves.append(leaf)
                if len(at) > 20_000:
                    yield pa.record_batch([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(leaves, pa.int32())], names=["vec", "q", "leaf"])
                    at, leaves = [], []
            if at:
                yield pa.record_batch([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(leaves, pa.int32())], names=["vec", "q", "leaf"])

    walked = materialize(common.mapped(distinct, walk, "vec array<double>, q long, leaf int"), "walked")
    visited = np.zeros(tree.leaves, np.int64)
    for leaf, n in walked.groupBy("leaf").count().collect():
        visited[leaf] = n
    of_leaf = lambda counts: F.element_at(F.array(*[F.lit(int(p)) for p in counts]), F.col("leaf") + 1)
    # Blocks of a leaf's entries and of the queries that visit it: neither side of a block grows with
    # the data, and a leaf is copied for its own visits only; one that none visits takes no part.
    count, parts = of_leaf(pieces), of_leaf(-(-visited // s.queries_cell))
    x_side = index.where(parts > 0).select("vec", "ids", "entry", F.lit(None).cast("long").alias("q"), "leaf", F.pmod(F.xxhash64("entry"), count).cast("int").alias("piece"), F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    q_side = walked.select("vec", F.lit(None).cast("array<long>").alias("ids"), F.lit(None).cast("long").alias("entry"), "q", "leaf", F.explode(F.sequence(F.lit(0), count - 1)).alias("piece"), F.pmod(F.xxhash64("q"), parts).cast("int").alias("part"))

    def block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, t in grouped(batches, ("leaf", "piece", "part")):
            q = t.column("q").to_numpy(zero_copy_only=False)
            is_q = ~np.isnan(q.astype(np.float64))
            if is_q.all() or not is_q.any():
                continue
            m = matrix(t.column("vec"))
            x, at = m[~is_q], np.flatnonzero(~is_q)
            entry = t.column("entry").to_numpy(zero_copy_only=False)[at].astype(np.int64)
            norms = (x * x).sum(1)
            out_q, out_at, out_d = [], [], []
            for k in np.flatnonzero(is_q).tolist():
                rough = norms - 2 * (x @ m[k])
                if len(rough) > 2 * want:
                    cut = np.partition(rough, want - 1)[want - 1]
                    near = np.flatnonzero(rough <= cut + 1e-6 * (abs(cut) + norms.max()))
                else:
                    near = np.arange(len(rough))
                rows_, d = closest(m[k], x[near], entry[near], want)
                out_q += [int(q[k])] * len(rows_)
                out_at += at[near[rows_]].tolist()
                out_d += d.tolist()
            yield pa.record_batch([pa.array(out_q, pa.int64()), t.column("ids").take(pa.array(out_at, pa.int64())), pa.array(out_d)], names=["q", "ids", "d"])

    both = q_side.unionByName(x_side).repartition("leaf", "piece", "part").sortWithinPartitions("leaf", "piece", "part")
    partial = common.mapped(both, block, "q long, ids array<long>, d double")
    near = partial.withColumn("k", F.row_number().over(Window.partitionBy("q").orderBy("d", F.element_at("ids", 1)))).where(F.col("k") <= want)
    listed = near.groupBy("q").agg(F.array_sort(F.collect_list(F.struct("d", "ids"))).alias("near"))
    pairs = F.flatten(F.transform("near", lambda e: F.transform(e["ids"], lambda i: F.struct(e["d"].alias("d"), i.alias("vec_id")))))
    answers = distinct.join(listed, "q").select("vec", F.slice(F.array_sort(pairs), 1, want).alias("pairs"))
    told = asked.join(answers, "vec").select("query_id", F.posexplode(F.slice(F.filter("pairs", lambda p: p["vec_id"] != F.col("query_id")), 1, s.neighbours)).alias("rank", "p"))
    return told.select("query_id", (F.col("rank") + 1).alias("rank"), F.col("p.vec_id").alias("vec_id"), F.sqrt("p.d").alias("score"))


def grouped(batches: Iterator[pa.RecordBatch], names: tuple[str, ...]) -> Iterator[tuple[tuple, pa.RecordBatch]]:
    """Whole groups of rows sorted by the named columns."""
    held: list[pa.RecordBatch] = []
    key = None
    for b in batches:
        if not b.num_rows:
            continue
        k = np.stack([b.column(b.schema.get_field_index(n)).to_numpy() for n in names])
        cuts = [0, *(np.flatnonzero((k[:, 1:] != k[:, :-1]).any(0)) + 1).tolist(), b.num_rows]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            own = tuple(k[:, lo].tolist())
            if own != key:
                if held:
                    yield key, pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held, key = [], own
            held.append(b.slice(lo, hi - lo))
    if held:
        yield key, pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def calibrate(index: DataFrame, tree: Tree, sizes: np.ndarray, s: Settings) -> int:
    """The fewest leaves to visit for the target recall, from probes compared with every entry."""
    probes = [(r["entry"], r["vec"]) for r in index.orderBy(F.xxhash64(F.lit(1), "entry"), "entry").limit(s.probes).select("entry", "vec").collect()]
    sent = index.sparkSession.sparkContext.broadcast((np.array([e for e, _ in probes]), np.array([v for _, v in probes], np.float64)))
    k = s.neighbours

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = sent.value
        for b in batches:
            if not b.num_rows:
                continue
            x, leaf = matrix(b.column(0)), b.column(2).to_numpy()
            entry = b.column(1).to_numpy()
            d = (x * x).sum(1)[None, :] - 2 * (q @ x.T)
            d[ids[:, None] == entry[None, :]] = np.inf
            near = np.argpartition(d, min(k, d.shape[1]) - 1, axis=1)[:, :k]
            probe = np.repeat(np.arange(len(q)), near.shape[1])
            dist = np.take_along_axis(d, near, 1).reshape(-1) + np.repeat((q * q).sum(1), near.shape[1])
            fine = np.isfinite(dist)
            yield pa.record_batch({"probe": pa.array(probe[fine]), "d": pa.array(dist[fine]), "leaf": pa.array(leaf[near.reshape(-1)][fine])})

    found = common.mapped(index.select("vec", "entry", "leaf"), run, "probe long, d double, leaf int")
    best = found.withColumn("k", F.row_number().over(Window.partitionBy("probe").orderBy("d"))).where(F.col("k") <= k).groupBy("probe", "leaf").count().collect()
    order = [tree.best_bins(np.array(v, np.float64), tree.leaves, 0, sizes) for _, v in probes]
    hits, total = np.zeros(tree.leaves + 1), 0
    for probe, leaf, n in best:
        hits[order[probe].index(leaf)] += n
        total += n
    reached = np.cumsum(hits) / max(1, total)
    return int(np.searchsorted(reached, s.recall) + 1) if total else tree.leaves


def op1_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = common.table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("vec"))
    return search(rows, F.pmod("vec_id", F.lit(100)) == 0)
