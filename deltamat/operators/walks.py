"""Paths, reachability and powers on a graph that every task can hold.

Rows of such results depend on their own source and the graph only. Sources are dealt out in blocks
of neighbouring ids; a task keeps a block as a vertex × source table and lets the edges of every
vertex act on whole rows of it. For a bounded number of steps the table has only the vertices that
the block's sources come to, and blocks that come to many are halved. Graphs that are too large, or
whose values the table cannot carry exactly, are refused with None, and the caller goes on with
products of tables.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, LongType

from deltamat.operators.multiply import REACH_CELLS, fits
from deltamat.sources.shipping import ship

#: Bytes of one task's vertex × source table, and sources in a block at most and, if the table is to pay, at least.
TABLE_BYTES, BLOCK, LEAST = 64 << 20, 1024, 32
#: Sources dealt out together where the table is of the vertices they come to; entries of the table gathered at once.
TOGETHER, GATHERED = 256, 1 << 20


@dataclass(frozen=True)
class Graph:
    """Vertices by id, and each vertex's edges: heads of row k are at[k]:at[k + 1]."""

    ids: np.ndarray
    at: np.ndarray
    heads: np.ndarray
    values: np.ndarray

    def edges(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        cut = slice(self.at[k], self.at[k + 1])
        return self.heads[cut], self.values[cut]


def held(g: DataFrame, plus: np.ufunc, cells: int = REACH_CELLS, width: int = 24, least: int = LEAST) -> Graph | None:
    """The graph on the driver, or None where it has more than ``cells`` cells, nulls, other types or too many vertices.

    Too many: a table of ``least`` sources and all vertices, an entry of ``width`` bytes, has over TABLE_BYTES.
    """
    if not isinstance(g.schema["v"].dataType, LongType | BooleanType) or not fits(g, cells):
        return None
    g = g.select(*[F.col(c).cast("long").alias(c) for c in "ijv"])
    ends = g.agg(*[F.max(F.greatest(F.col(c), -1 - F.col(c))) for c in "ijv"]).first()  # a number and its complement
    t = g.select(*[F.col(c).cast("int").alias(c) if e is not None and e < 1 << 31 else F.col(c) for c, e in zip("ijv", ends, strict=True)]).toArrow()
    if any(c.null_count for c in t.columns):
        return None
    ids = np.union1d(*(pc.unique(t.column(c)).to_numpy() for c in "ij")).astype(np.int64)
    if len(ids) * width * least > TABLE_BYTES:
        return None
    key = np.searchsorted(ids, t.column("i").to_numpy())
    key *= len(ids)
    key += np.searchsorted(ids, t.column("j").to_numpy())
    v = t.column("v").to_numpy()
    del t  # the driver has little room
    order = np.argsort(key, kind="stable")
    key, v = key[order], v[order]
    del order
    first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.empty(0, np.int64)
    values = plus.reduceat(v.astype(np.int64), first) if len(first) < len(key) else v
    key = key[first]
    rows = key // max(len(ids), 1)
    return Graph(ids, np.searchsorted(rows, np.arange(len(ids) + 1)), (key % max(len(ids), 1)).astype(np.int32), values)


def run_blocks(sources: DataFrame, g, rows, schema: str, width: int, together: int = 1) -> DataFrame:
    """rows(g, ids of a block) gives arrays (place in the block, j, values...) for each block; v is true if None.

    together: sources of a block at least, however large a table of them and all vertices is.
    """
    spark = sources.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(g)
    block = int(min(BLOCK, max(together, TABLE_BYTES // (max(len(g.ids), 1) * width))))
    ids = sources.select(F.col("i").cast("long").alias("i")).distinct()
    n = ids.count()
    parts = max(1, -(-n // block))
    dealt = ids.repartitionByRange(parts, "i") if parts > 1 else ids.coalesce(1)
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = shared.value
        mine = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
        mine = np.sort(np.concatenate(mine)) if mine else np.empty(0, np.int64)
        for lo in range(0, len(mine), block):
            part = mine[lo : lo + block]
            for s, *columns in rows(graph, part):
                for at in range(0, len(s), 1 << 18):
                    cut = slice(at, at + (1 << 18))
                    out = [part[s[cut]], *[np.ones(len(s[cut]), bool) if c is None else c[cut] for c in columns]]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in out], names=names)

    return dealt.mapInArrow(run, schema)


def _start(g: Graph | Condensed, part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places in the block, vertices) of the sources that the graph has."""
    at = np.minimum(np.searchsorted(g.ids, part), max(len(g.ids) - 1, 0))
    known = np.flatnonzero(g.ids[at] == part) if len(g.ids) else np.empty(0, np.int64)
    return known, at[known] if len(g.ids) else known


@dataclass(frozen=True)
class Near:
    """The vertices that sources come to, and the edges between them by head.

    Edges into vertices[heads[n]] are at[n]:at[n + 1] of tails (places in vertices) and values.
    """

    vertices: np.ndarray
    heads: np.ndarray
    at: np.ndarray
    tails: np.ndarray
    values: np.ndarray


def _edges(g: Graph, vertices: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places in ``vertices``, edges) of all edges out of these."""
    n = g.at[vertices + 1] - g.at[vertices]
    return np.repeat(np.arange(len(vertices)), n), np.repeat(g.at[vertices] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))


def near(g: Graph, start: np.ndarray, hops: int, most: int) -> Near | None:
    """What ``hops`` steps from the starts can use, or None beyond ``most`` vertices."""
    depth = np.full(len(g.ids), -1, np.int32)
    depth[start] = 0
    front, found = np.flatnonzero(depth == 0), 0
    for h in range(1, hops + 2):
        found += len(front)
        if found > most:
            return None
        if h > hops or not len(front):
            break
        heads = g.heads[_edges(g, front)[1]]
        depth[heads[depth[heads] < 0]] = h
        front = np.flatnonzero(depth == h)
    vertices = np.flatnonzero(depth >= 0)
    place = np.cumsum(depth >= 0) - 1
    inner = np.flatnonzero((depth >= 0) & (depth < hops))
    tail, edge = _edges(g, inner)
    head = place[g.heads[edge]]
    order = np.argsort(head, kind="stable")
    head = head[order]
    first = np.flatnonzero(np.r_[True, head[1:] != head[:-1]]) if len(head) else np.empty(0, np.int64)
    return Near(vertices, head[first], np.append(first, len(head)), place[inner][tail[order]], g.values[edge[order]])


def by_reach(hops: int, width: int, rows_of):
    """rows() for run_blocks: rows_of(near, known, places) makes the rows of the known sources of a block.

    A block whose table of sources and vertices come to would have over TABLE_BYTES is halved.
    """

    def rows(g: Graph, part: np.ndarray):
        known, vertex = _start(g, part)
        of = near(g, vertex, hops, TABLE_BYTES // (width * len(part)) if len(part) > 1 else len(g.ids))
        if of is None:
            half = len(part) // 2
            for lo, piece in ((0, part[:half]), (half, part[half:])):
                for s, *columns in rows(g, piece):
                    yield s + lo, *columns
            return
        table = rows_of(of, known, np.searchsorted(of.vertices, vertex), len(part))
        for lo in range(0, len(of.vertices), 1024):
            cut = table[lo : lo + 1024]
            j, s = np.nonzero(cut)
            yield s, g.ids[of.vertices[lo + j]], cut[j, s].astype(np.int64)

    return rows


def path_rows(hops: int, kind: type = np.int64):
    """``far`` stands for no path; the costs of paths stay below a quarter of it."""
    far = kind(1 << (8 * np.dtype(kind).itemsize - 2))

    def table(of: Near, known: np.ndarray, places: np.ndarray, n: int) -> np.ndarray:
        best, weight = np.full((len(of.vertices), n), far), of.values.astype(kind)[:, None]
        best[places, known] = 0
        changed, step = np.zeros(len(of.vertices), bool), max(1, GATHERED // n)
        changed[places] = True
        for _ in range(hops):
            before = best.copy()
            acts = changed[of.tails]
            sums = np.r_[0, np.cumsum(acts)]
            tails, w, at = of.tails[acts], weight[acts], sums[of.at]
            for h, a, b in zip(of.heads.tolist(), at[:-1].tolist(), at[1:].tolist(), strict=True):
                for lo in range(a, b, step):
                    cut = slice(lo, min(lo + step, b))
                    np.minimum(best[h], (before[tails[cut]] + w[cut]).min(axis=0), out=best[h])
            changed = (best != before).any(axis=1)
            if not changed.any():
                break
        # Cells that are 0 are no rows, so costs, which may be 0, are given less far.
        return np.where(best < far // 2, best - far, kind(0))

    reached = by_reach(hops, 4 * np.dtype(kind).itemsize, table)

    def rows(g: Graph, part: np.ndarray):
        lost = np.setdiff1d(np.arange(len(part)), _start(g, part)[0])
        if len(lost):
            yield lost, part[lost], np.zeros(len(lost), np.int64)
        for s, j, v in reached(g, part):
            yield s, j, v + int(far)

    return rows


def paths(g: DataFrame, sources: DataFrame, hops: int, cells: int = REACH_CELLS) -> DataFrame | None:
    """(i, j, v): least costs over at most ``hops`` edges, the source itself at 0; None if refused.

    Costs are kept in the smallest type that holds them.
    """
    if not isinstance(g.schema["v"].dataType, LongType):
        return None
    graph = held(g, np.minimum, cells, least=1)
    if graph is None:
        return None
    most = int(np.abs(graph.values.astype(float)).max(initial=0)) * max(hops, 1)
    for kind in (np.int8, np.int16, np.int32, np.int64):
        if most < 1 << (8 * np.dtype(kind).itemsize - 4):
            return run_blocks(sources, graph, path_rows(hops, kind), "i long, j long, v long", 24, TOGETHER)
    return None


@dataclass(frozen=True)
class Condensed:
    """A graph by its strongly connected components, numbered so that edges go from larger to smaller numbers.

    of: each vertex's component; cyclic: components that reach themselves; those with an edge into
    component c are before[at[c]:at[c + 1]].
    """

    ids: np.ndarray
    of: np.ndarray
    cyclic: np.ndarray
    at: np.ndarray
    before: np.ndarray


def strong_components(at: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """Each vertex's strongly connected component (Tarjan's walk, without recursion); sinks have the smallest numbers."""
    n, h, cut = len(at) - 1, memoryview(heads), at.tolist()
    order, low, of, to = [0] * n, [0] * n, [-1] * n, cut[:-1]
    seen = found = 0
    open_: list[int] = []
    for root in range(n):
        if order[root]:
            continue
        path = [root]
        while path:
            v = path[-1]
            if not order[v]:
                seen += 1
                order[v] = low[v] = seen
                open_.append(v)
            k, end, least = to[v], cut[v + 1], low[v]
            while k < end:
                w = h[k]
                if not order[w]:
                    path.append(w)
                    break
                if of[w] < 0 and low[w] < least:
                    least = low[w]
                k += 1
            to[v], low[v] = k, least
            if k < end:
                continue  # the edge is looked at again when w is done
            path.pop()
            if least == order[v]:
                w = -1
                while w != v:
                    w = open_.pop()
                    of[w] = found
                found += 1
    return np.array(of, np.int64)


def condensed(g: Graph) -> Condensed:
    of = strong_components(g.at, g.heads)
    n = int(of.max()) + 1 if len(of) else 0
    tail, head = np.repeat(of, np.diff(g.at)), of[g.heads]
    cyclic = np.zeros(n, bool)
    cyclic[head[tail == head]] = True
    key = np.unique((head * n + tail)[tail != head])
    return Condensed(g.ids, of, cyclic, np.searchsorted(key, np.arange(n + 1) * n), (key % max(n, 1)).astype(np.int32))


def reach_rows(g: Condensed, part: np.ndarray):
    """Sources are bits; each component takes once what stands at, or has reached, those before it."""
    known, vertex = _start(g, part)
    words = -(-len(part) // 8)
    here, seen = np.zeros((len(g.cyclic), words), np.uint8), np.zeros((len(g.cyclic), words), np.uint8)
    start = g.of[vertex]
    np.bitwise_or.at(here, (start, known // 8), np.left_shift(1, known % 8).astype(np.uint8))
    at, cyclic = g.at.tolist(), g.cyclic.tolist()
    for c in range(int(start.max(initial=-1)), -1, -1):
        if at[c] < at[c + 1]:
            np.bitwise_or.reduce(here[g.before[at[c] : at[c + 1]]], axis=0, out=seen[c])
        here[c] |= seen[c]
        if cyclic[c]:
            seen[c] = here[c]
    for lo in range(0, len(g.ids), 1024):
        j, s = np.nonzero(np.unpackbits(seen[g.of[lo : lo + 1024]], axis=1, count=len(part), bitorder="little"))
        yield s, g.ids[lo + j], None


def reachable(g: DataFrame, cells: int = REACH_CELLS) -> DataFrame | None:
    """(i, j, true): j is reached from i over one edge or more; None if refused or if a cell stores false."""
    graph = held(g, np.minimum, cells, 1) if isinstance(g.schema["v"].dataType, BooleanType) else None
    if graph is None or len(graph.values) and not graph.values.min():
        return None
    return run_blocks(g.select("i"), condensed(graph), reach_rows, "i long, j long, v boolean", 1)


def power_rows(t: int, kind: type = np.int64):
    def table(of: Near, known: np.ndarray, places: np.ndarray, n: int) -> np.ndarray:
        now, weight, step = np.zeros((len(of.vertices), n), kind), of.values.astype(kind), max(1, GATHERED // n)
        now[places, known] = 1
        for _ in range(t):
            after = np.zeros_like(now)
            for h, a, b in zip(of.heads.tolist(), of.at[:-1].tolist(), of.at[1:].tolist(), strict=True):
                for lo in range(a, b, step):
                    cut = slice(lo, min(lo + step, b))
                    after[h] += weight[cut] @ now[of.tails[cut]]
            now = after
        return now

    return by_reach(t, 3 * np.dtype(kind).itemsize, table)


def positive_power(g: DataFrame, t: int, cells: int = REACH_CELLS) -> DataFrame | None:
    """Aᵗ for sums of products; None if refused, if a value is not above 0 or a sum could pass 64 bits."""
    if not isinstance(g.schema["v"].dataType, LongType):
        return None
    graph = held(g, np.add, cells, least=1)
    if graph is None or len(graph.values) and (int(graph.values.min()) <= 0 or not g.where("v <= 0").isEmpty()):
        return None
    sums = np.bincount(np.repeat(np.arange(len(graph.ids)), np.diff(graph.at)), graph.values.astype(float))
    most = int(sums.max(initial=0) * (1 + 1e-9)) + 1
    if most**t >= 1 << 63:
        return None
    kind = np.float32 if most**t < 1 << 24 else np.float64 if most**t < 1 << 53 else np.int64  # exact whole numbers
    return run_blocks(g.select("i"), graph, power_rows(t, kind), "i long, j long, v long", 24, TOGETHER)
