"""Applications of the products: paths, triangles, contraction, clustering, layers, co-occurrence."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from deltamat.functions.semiring import COUNT_PAIR, MIN_PLUS, PLUS_TIMES, Semiring
from deltamat.operators import walks
from deltamat.operators.blocks import block_product
from deltamat.operators.dense import dense_product
from deltamat.operators.dynamic_algebraic import delta_product, maintain
from deltamat.operators.matrix import apply, ewise_add, normalize, offdiag, prune_zeros, symmetrize, topk_per_row, transpose, triu
from deltamat.operators.multiply import BROADCAST_CELLS, REACH_CELLS, fits, sides, spgemm, spgemm_masked
from deltamat.operators.tiles import upper_products
from deltamat.sources.scratch import materialize


def shortest_paths(g: DataFrame, sources: DataFrame, hops: int, cells: int = REACH_CELLS) -> DataFrame:
    """(i, j, v): the least cost from each source i to j over at most ``hops`` edges; the source itself costs 0.

    A graph of at most ``cells`` cells goes to every task (walks.paths); a larger one is multiplied hop by hop.
    """
    if (out := walks.paths(g, sources, hops, cells)) is not None:
        return out
    start = sources.select(F.col("i"), F.col("i").alias("j"), F.lit(0).cast("long").alias("v")).distinct()
    best = frontier = materialize(start, "paths")
    for _ in range(hops):
        reached = spgemm(frontier, g, MIN_PLUS)
        old = best.select("i", "j", F.col("v").alias("old"))
        better = materialize(reached.join(old, ["i", "j"], "left").where("old is null or v < old").select("i", "j", "v"), "frontier")
        best = materialize(ewise_add(best, better, MIN_PLUS), "paths")
        frontier = better
    return best


def bfs(g: DataFrame, sources: DataFrame, max_level: int, cells: int = REACH_CELLS) -> DataFrame:
    """(i, j, v): the level at which j is first reached from source i."""
    unit = g.where("i <> j").select("i", "j", F.lit(1).cast("long").alias("v"))
    return shortest_paths(unit, sources, max_level, cells)


def triangles(g: DataFrame) -> DataFrame:
    """(triangles): of an undirected graph; edges point from the smaller id, and each triangle is closed once."""
    up = triu(symmetrize(g)).select("i", "j", F.lit(1).cast("long").alias("v"))
    up = materialize(up, "edges")
    closed = spgemm_masked(up, up, up, COUNT_PAIR)
    return closed.agg(F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("triangles"))


def _upward(g: DataFrame) -> DataFrame:
    """(i, j, v) with i < j, each undirected edge once."""
    return triu(symmetrize(g)).select("i", "j", F.lit(1).cast("long").alias("v"))


def triangles_after(count: DataFrame, g: DataFrame, new: DataFrame) -> DataFrame:
    """(triangles) once the edges ``new`` are there too; count: triangles() of g.

    A triangle that is not old has one, two or three new edges. With U old, N new and W both upward
    edges it is counted at the first of its edges that is new: N·W at W, U·N at W, U·U at N.
    """
    old = materialize(_upward(g), "old")
    fresh = materialize(_upward(new).join(old, ["i", "j"], "left_anti"), "fresh")
    both = old.unionByName(fresh)
    parts = [spgemm_masked(fresh, both, both, COUNT_PAIR), spgemm_masked(old, fresh, both, COUNT_PAIR), spgemm_masked(old, old, fresh, COUNT_PAIR)]
    more = parts[0].unionByName(parts[1]).unionByName(parts[2]).select(F.col("v").alias("triangles"))
    return count.select("triangles").unionByName(more).agg(F.sum("triangles").cast("long").alias("triangles"))


def contract(g: DataFrame, rows: DataFrame, cols: DataFrame | None = None, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Sᵀ·G·T: entities summed up to labels; rows and cols are entity × label, 1."""
    cols = rows if cols is None else cols
    return spgemm(spgemm(rows, g, s, (True, False)), cols, s)


def triple_product(r: DataFrame, a: DataFrame, p: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """R·A·P with weights, as multigrid coarsening asks for.

    Sums of products are taken as R·(A·P) by blocks of rows (blocks.block_product), so the large R·A is
    never made; values that it refuses are joined from the left.
    """
    if s is PLUS_TIMES and all(isinstance(m.schema["v"].dataType, LongType) for m in (r, a, p)) and (ap := exact_product(a, p)) is not None:
        left, right = sides(r, materialize(ap, "coarse"))
        zero = F.lit(0).cast("long")
        out = block_product(left.select(zero.alias("deal"), zero.alias("cut"), "i", "k", "av"), right.select(zero.alias("cut"), "k", "j", "bv"))
        if out is not None:
            return out.select("i", "j", "v")
    return spgemm(spgemm(r, a, s), p, s)


def exact_product(a: DataFrame, b: DataFrame) -> DataFrame | None:
    """A·B, or None where a value is null or a sum could pass 2**53."""
    total = lambda m: m.agg(F.sum(F.abs(F.col("v").cast("double"))), F.coalesce(F.bool_or(F.col("v").isNull()), F.lit(False))).first()
    (x, x_null), (y, y_null) = total(a), total(b)
    return None if x_null or y_null or (x or 0) * (y or 0) >= 2.0**52 else spgemm(a, b)


def cluster_step(g: DataFrame, inflation: int = 2, threshold: float = 1e-3) -> DataFrame:
    """One step of flow clustering: column shares, square, inflate, shares again, prune."""
    flow = normalize(g, "j")
    inflated = apply(spgemm(flow, flow), lambda v: F.pow(v, inflation))
    return normalize(inflated, "j").where(F.col("v") >= threshold)


def dnn_layer(x: DataFrame, w: DataFrame, bias: float | int | Column = 0) -> DataFrame:
    """max(0, X·W + b) at the product's cells; zeros are pruned."""
    bias = bias if isinstance(bias, Column) else F.lit(bias)
    return prune_zeros(apply(spgemm(x, w), lambda v: F.greatest(v + bias, F.lit(0))))


def cooccurrence(m: DataFrame, s: Semiring = COUNT_PAIR) -> DataFrame:
    """MᵀM without its diagonal."""
    return offdiag(spgemm(m, m, s, (True, False)))


def cooccurrence_after(c: DataFrame, m: DataFrame, new: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """MᵀM after new rows or cells are added to M: both operands of the product change."""
    mt, star_t = transpose(m), transpose(new)
    return maintain(c, delta_product(mt, star_t, m, new, s), s)


def top_partners(c: DataFrame, k: int) -> DataFrame:
    return topk_per_row(c, k)


def similarity(d: DataFrame, least: int = 1, tiled: bool = False) -> DataFrame:
    """(i, j, v): D·Dᵀ above the diagonal, pairs of at least ``least``; ``tiled``: by tiles where values allow (tiles.upper_products)."""
    if tiled and (out := upper_products(d, least)) is not None:
        return out
    return triu(spgemm(d, d, PLUS_TIMES, (False, True))).where(F.col("v") >= least)


def cosine(d: DataFrame, cells: int = BROADCAST_CELLS) -> DataFrame:
    """(i, j, v): cosines of rows, rounded to six places, above the diagonal.

    Up to ``cells`` cells, rows that share most of their columns are multiplied in full (dense_product);
    beyond, rows of which many share a column are multiplied by tiles (tiles.upper_products).
    """
    norm = d.groupBy("i").agg(F.sqrt(F.sum(F.col("v") * F.col("v")).cast("double")).alias("n"))
    dots = dense_product(d, d, (False, True), upper=True, cells=cells)
    if dots is None and nearly_full(d) and d.where("i is null or j is null or v is null or v <= 0").isEmpty():
        dots = upper_products(d, 1)  # of values above 0 every sum is 1 at least
    if dots is not None:  # made in Python, Spark takes them for small
        norm = F.broadcast(norm) if fits(norm) else norm.hint("merge")
    else:
        dots = triu(spgemm(d, d, PLUS_TIMES, (False, True)))
    left, right = norm.withColumnRenamed("n", "ni"), norm.select(F.col("i").alias("j"), F.col("n").alias("nj"))
    return dots.join(left, "i").join(right, "j").select("i", "j", F.round(F.col("v") / (F.col("ni") * F.col("nj")), 6).alias("v"))


def nearly_full(d: DataFrame) -> bool:
    """Whether D·Dᵀ has a term for each eight of its cells at least, so that tiles of it are worth their room."""
    terms = d.groupBy("j").agg(F.count("*").cast("double").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0]
    return terms is not None and terms * 8 >= float(d.select("i").distinct().count()) ** 2


def two_hop_by_window(events: DataFrame, width: str = "1 day") -> DataFrame:
    """(start, i, j, v): pairs of users joined by a property within each window of time.

    A window's product is made by blocks of its users, each of which holds the window's cells
    (blocks.block_product), so no pair is exchanged.
    """
    cells = events.select(F.window(F.col("ts").cast("timestamp"), width)["start"].alias("start"), F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("k")).where("i is not null and k is not null")
    counts = cells.where("start is not null").groupBy("start", "i", "k").agg(F.count("*").alias("n"))
    if isinstance(events.schema["user_id"].dataType, LongType):
        counts = materialize(counts, "counts")
        at = F.unix_micros("start").alias("cut")
        left = counts.select(F.lit(0).cast("long").alias("deal"), at, "i", "k", F.col("n").alias("av"))
        out = block_product(left, counts.select(at, "k", F.col("i").alias("j"), F.col("n").alias("bv")), ("cut", "i"), upper=True)
        if out is not None:
            return out.select(F.timestamp_micros("cut").alias("start"), "i", "j", "v")
    other = counts.select("start", F.col("i").alias("j"), "k", F.col("n").alias("m"))
    return counts.join(other, ["start", "k"]).where("i < j").groupBy("start", "i", "j").agg(F.sum(F.col("n") * F.col("m")).alias("v"))
