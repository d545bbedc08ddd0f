"""Static products of sparse matrices: one algebra, several physical strategies.

All take cells (i, j, v) and return cells; ``a`` is indexed (i, k), ``b`` (k, j). The join is on the
inner index, the aggregate over (i, j) combines partially before its exchange.
"""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.functions.semiring import OR_AND, PLUS_TIMES, Semiring
from deltamat.operators.layout import Grid
from deltamat.operators.matrix import ewise_add, identity, scale
from deltamat.sources.scratch import discard, materialize

#: Cells that one broadcast may hold: 24 bytes each and as much again for the hash relation.
BROADCAST_CELLS = 1_000_000
#: Edges of a graph that the driver reads and every task holds for walks from its rows.
REACH_CELLS = 8_000_000


def sides(a: DataFrame, b: DataFrame, trans: tuple[bool, bool] = (False, False)) -> tuple[DataFrame, DataFrame]:
    """(i, k, av) and (k, j, bv); transposition only changes which column is the key."""
    ai, ak = ("j", "i") if trans[0] else ("i", "j")
    bk, bj = ("j", "i") if trans[1] else ("i", "j")
    left = a.select(F.col(ai).alias("i"), F.col(ak).alias("k"), F.col("v").alias("av"))
    return left, b.select(F.col(bk).alias("k"), F.col(bj).alias("j"), F.col("v").alias("bv"))


def fits(df: DataFrame, cells: int = BROADCAST_CELLS) -> bool:
    """Whether the table has no more cells than may be broadcast; counting stops beyond."""
    return df.select(F.lit(1)).limit(cells + 1).count() <= cells


def folded(pairs: DataFrame, s: Semiring) -> DataFrame:
    return pairs.groupBy("i", "j").agg(s.plus_agg(s.times(F.col("av"), F.col("bv"))).alias("v"))


def spgemm(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, trans: tuple[bool, bool] = (False, False), strategy: str = "auto", cells: int = BROADCAST_CELLS) -> DataFrame:
    """The product; strategy: auto (Catalyst and AQE choose) or a join hint's name.

    A right operand of more than ``cells`` cells is never broadcast; a shuffled hash join takes its place.
    """
    left, right = sides(a, b, trans)
    if strategy == "broadcast" and not fits(right, cells):
        strategy = "shuffle_hash"
    if strategy != "auto":
        right = right.hint(strategy)
    return folded(left.join(right, "k"), s)


def spgemm_stationary(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, keep: str = "right", cells: int = BROADCAST_CELLS) -> DataFrame:
    """One operand stays where it is scanned, the other is broadcast if it is checked to be small.

    Beyond the bound the small side is shuffled to the large one (a shuffled hash join).
    """
    left, right = sides(a, b)
    small = left if keep == "right" else right
    hinted = F.broadcast(small) if fits(small, cells) else small.hint("shuffle_hash")
    left, right = (hinted, right) if keep == "right" else (left, hinted)
    return folded(left.join(right, "k"), s)


@contextmanager
def co_clustered(spark):
    """Within: tables dealt by a part of a join's keys need not be dealt anew."""
    name = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(name)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def spgemm_grid(a: DataFrame, b: DataFrame, g: Grid, gb: Grid, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Output-stationary: left blocks are copied along grid rows, right ones along grid columns.

    g lays out the left operand, gb the right one; a result block is made where both meet, and its
    aggregate needs no further exchange. Sums of products are made by blocks of rows within each grid
    block (blocks.block_product), so tasks are not tied to the number of grid blocks, and copies are
    made where blocks are dealt, after cells are counted, dealt by ranges and written; everything else
    is written once under the session setting that allows it.
    """
    from deltamat.operators.blocks import block_product

    spark = a.sparkSession
    q, qc = g.qr, gb.qc or gb.qr
    if s is PLUS_TIMES:
        left, right = sides(a, b)
        left = left.select(g.bi(F.col("i")).cast("long").alias("deal"), "i", "k", "av")
        right = right.select(gb.bj(F.col("j")).cast("long").alias("cut"), "k", "j", "bv")
        if (out := block_product(left, right, spread=q * qc, copies=qc)) is not None:
            return out
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    left = a.select("i", F.col("j").alias("k"), F.col("v").alias("av"), g.bi(F.col("i")).alias("bi"), F.explode(F.sequence(F.lit(0), F.lit(qc - 1))).alias("bj")).repartition(n, "bi", "bj")
    right = b.select(F.col("i").alias("k"), "j", F.col("v").alias("bv"), gb.bj(F.col("j")).alias("bj"), F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias("bi")).repartition(n, "bi", "bj")
    out = left.join(right, ["bi", "bj", "k"]).groupBy("bi", "bj", "i", "j").agg(s.plus_agg(s.times(F.col("av"), F.col("bv"))).alias("v"))
    with co_clustered(spark):
        return materialize(out.select("i", "j", "v"), "product")


def spgemm_rowpart(a: DataFrame, b: DataFrame, parts: int, s: Semiring = PLUS_TIMES) -> DataFrame:
    """One-dimensional: rows of the left operand are dealt, each part fetches the rows of b it names.

    Sums of products only, without masks, as the baseline it stands for. A part is worked off in blocks
    of rows that add up their own terms (blocks.block_product); values it refuses are joined.
    """
    from deltamat.operators.blocks import block_product

    if s is not PLUS_TIMES:
        raise ValueError("the row-partitioned baseline knows (+, ·) only")
    left, right = sides(a, b)
    zero = F.lit(0).cast("long").alias("cut")
    left = left.withColumn("part", F.coalesce(F.pmod("i", F.lit(parts)), F.lit(0)).cast("long"))
    out = block_product(left.select(F.col("part").alias("deal"), zero, "i", "k", "av"), right.select(zero, "k", "j", "bv"), spread=parts)
    if out is not None:
        return out.select("i", "j", "v")
    fetched = left.select("part", "k").distinct().join(right, "k")
    return folded(left.join(fetched, ["part", "k"]), s)


def spgemm_rowwise(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Row by row: cells of a row meet packed rows of b, and the hash aggregate is the accumulator."""
    packed = b.groupBy(F.col("i").alias("k")).agg(F.collect_list(F.struct("j", F.col("v").alias("bv"))).alias("row"))
    left = a.select("i", F.col("j").alias("k"), F.col("v").alias("av"))
    return folded(left.join(packed, "k").select("i", "av", F.inline("row")), s)


def spgemm_generic(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Both operands are dealt by the inner index on every call: no layout is used again."""
    left, right = sides(a, b)
    return folded(left.hint("shuffle_hash").join(right, "k"), s)


def spgemm_masked(a: DataFrame, b: DataFrame, mask: DataFrame, s: Semiring = PLUS_TIMES, complement: bool = False) -> DataFrame:
    """Only cells that the mask stores (or, complement, does not store).

    The mask is tested before anything is accumulated; a plain mask also narrows both operands.
    """
    left, right = sides(a, b)
    cells = mask.select("i", "j").distinct()
    if not complement:
        left = left.join(cells.select("i").distinct(), "i", "left_semi")
        right = right.join(cells.select("j").distinct(), "j", "left_semi")
    return folded(left.join(right, "k").join(cells, ["i", "j"], "left_anti" if complement else "left_semi"), s)


def gemm(alpha, a: DataFrame, b: DataFrame, beta, x: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """α A·B ⊕ β X."""
    return ewise_add(scale(spgemm(a, b, s), alpha, s), scale(x, beta, s), s)


def spgemm_salted(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, heavy: int = 1_000_000, pieces: int = 16) -> DataFrame:
    """Inner indices whose products number over ``heavy`` have their row of b cut into pieces.

    Heavy indices are few by construction (their flops sum up to all flops), which bounds the list.
    """
    left, right = sides(a, b)
    da, db = left.groupBy("k").agg(F.count("*").alias("da")), right.groupBy("k").agg(F.count("*").alias("db"))
    hubs = da.join(db, "k").where(F.col("da") * F.col("db") > heavy).select("k", F.lit(pieces).alias("cuts"))
    hub_left = left.join(hubs, "k", "left").select("i", "k", "av", F.explode(F.sequence(F.lit(0), F.coalesce("cuts", F.lit(1)) - 1)).alias("cut"))
    hub_right = right.join(hubs, "k", "left").select("k", "j", "bv", F.pmod(F.xxhash64("j"), F.coalesce("cuts", F.lit(1))).cast("int").alias("cut"))
    return folded(hub_left.join(hub_right, ["k", "cut"]), s)


def spgemm_layered(a: DataFrame, b: DataFrame, layers: int, s: Semiring = PLUS_TIMES) -> DataFrame:
    """The inner index is cut into layers whose partial results are combined last.

    A cell's partial results stand side by side in its row, so layers need no exchange of their own.
    Sums of products are made by blocks of rows with a sum for each layer (blocks.block_product), and
    their terms are not exchanged at all.
    """
    from deltamat.operators.blocks import block_product

    left, right = sides(a, b)
    if s is PLUS_TIMES:
        zero = F.lit(0).cast("long")
        out = block_product(left.select(zero.alias("deal"), zero.alias("cut"), "i", "k", "av"), right.select(zero.alias("cut"), "k", "j", "bv"), layers=layers)
        if out is not None:
            return out.select("i", "j", "v")
    layer = F.pmod("k", F.lit(layers)).cast("int")
    parts = left.withColumn("layer", layer).join(right.withColumn("layer", layer), ["layer", "k"])
    term = s.times(F.col("av"), F.col("bv"))
    partial = parts.groupBy("i", "j").agg(*[s.plus_agg(F.when(F.col("layer") == n, term)).alias(f"v{n}") for n in range(layers)])
    v = F.col("v0")
    for n in range(1, layers):
        more = F.col(f"v{n}")
        v = F.coalesce(s.plus(v, more), v, more)
    return partial.select("i", "j", v.alias("v"))


def power(a: DataFrame, t: int, s: Semiring = PLUS_TIMES, n: int | None = None, cells: int = REACH_CELLS) -> DataFrame:
    """Aᵗ; t = 0 needs the dimension n.

    Sums of products of at most ``cells`` cells are made row by row in one pass (walks.positive_power);
    otherwise each step is a product that is written, so lineage stays short.
    """
    from deltamat.operators import walks

    if t == 0:
        return identity(a.sparkSession, n, s.one)
    if s is PLUS_TIMES and t > 1 and (out := walks.positive_power(a, t, cells)) is not None:
        return out
    out = a.select("i", "j", "v")
    for _ in range(t - 1):
        out = materialize(spgemm(out, a, s), "power")
    return out


def closure(a: DataFrame, s: Semiring, max_rounds: int = 64, cells: int = REACH_CELLS) -> DataFrame:
    """A ⊕ A² ⊕ ... for an idempotent ⊕, by squaring until nothing changes.

    Reachability over at most ``cells`` edges is walked from every row instead (walks.reachable).
    """
    from deltamat.operators import walks

    if not s.idempotent:
        raise ValueError(f"{s.name} does not declare a ⊕ a = a")
    if s is OR_AND and (out := walks.reachable(a, cells)) is not None:
        return out
    out = materialize(a.select("i", "j", "v"), "closure")
    for _ in range(max_rounds):
        more = materialize(ewise_add(out, spgemm(out, out, s), s), "closure")
        changed = not more.exceptAll(out).isEmpty()
        discard(out)
        out = more
        if not changed:
            return out
    raise RuntimeError("the closure did not settle")


def flops(a: DataFrame, b: DataFrame) -> DataFrame:
    """Scalar products of the static product, from degrees alone."""
    da = a.groupBy(F.col("j").alias("k")).agg(F.count("*").alias("da"))
    db = b.groupBy(F.col("i").alias("k")).agg(F.count("*").alias("db"))
    return da.join(db, "k").agg(F.coalesce(F.sum(F.col("da") * F.col("db")), F.lit(0)).alias("flops"))


def estimate(a: DataFrame, b: DataFrame, n_rows: int, n_cols: int) -> tuple[int, int]:
    """(flops, an upper bound of the result's cells) before a product is run."""
    f = flops(a, b).first()[0]
    rows, cols = a.agg(F.approx_count_distinct("i")).first()[0], b.agg(F.approx_count_distinct("j")).first()[0]
    return f, min(f, int(1.1 * rows) * int(1.1 * cols), n_rows * n_cols)


