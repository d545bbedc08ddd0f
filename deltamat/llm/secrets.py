"""Secret scans with SQL functions only: named patterns, then entropy of sliding windows.

Base spans come from three fixed patterns. The entropy pass looks at runs of one character class,
slides a window over each run, updates the counts of its characters by the one that enters and the
one that leaves, and keeps the stretch whose windows reach the class's entropy. Entropies are
compared as whole numbers (millionths of a bit), so that engines agree on ties.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common

# The base patterns, in the order in which kinds at one start are listed.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
ASSIGN_LEAST = 6

# Fixed values of the entropy pass: class name, its characters, run pattern, window, least bits.
CLASSES = (
    ("entropy_hex", "0123456789abcdefABCDEF", r"[0-9a-fA-F]{24,}", 24, 3.0),
    ("entropy_base64", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-", r"[A-Za-z0-9+/_=-]{24,}", 24, 4.0),
)
#: Runs that look random and are not secrets: words, UUIDs, placeholders, runs of the alphabet.
ALLOW = (
    r"^[A-Z]?[a-z]+$|^[A-Z]+$|^[a-z]+([_-][a-z]+)+$"
    r"|^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$"
    r"|[Ee][Xx][Aa][Mm][Pp][Ll][Ee]|[Pp]laceholder|PLACEHOLDER|[Dd]ummy|DUMMY|[Xx]{8}"
    r"|0123456789|abcdefghij|ABCDEFGHIJ"
)
#: The one pattern of ALLOW that repeats a group, which the JVM's engine would walk by recursion.
SNAKE = r"^[a-z]+([_-][a-z]+)+$"
MICRO, BLOCK = 1_000_000, 512
#: Counts of a window, packed: bits of a count and counts in a number.
BITS, PACK = 6, 10


def weight(count: int) -> int:
    """count * log2(count) in millionths."""
    return round(count * math.log2(count) * MICRO) if count else 0


def limit(window: int, bits: float) -> int:
    """The largest sum of weights at which a window has ``bits`` of entropy a character."""
    return math.floor(window * (math.log2(window) - bits) * MICRO)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value computed once however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def running(items: Column, zero: Column, fold: Callable[[Column, Column], Column], merge: Callable[[Column, Column], Column], out: Callable[[Column, Column], Column], kind: str) -> Column:
    """out(what came before, item) for each item of an array, in time that grows with its length.

    fold takes up an item, merge joins two totals. Blocks are folded by themselves first, so that no
    array is appended to beyond a block's length; kind is the type of out.
    """
    last = lambda x: F.greatest(F.floor((F.size(x) - 1) / BLOCK), F.lit(0)).cast("int")
    none = F.array().cast(f"array<{kind}>")

    def walk(block: Column, start: Column) -> Column:
        step = lambda a, x: F.struct(fold(a["acc"], x).alias("acc"), F.array_append(a["out"], out(a["acc"], x)).alias("out"))
        return F.aggregate(block, F.struct(start.alias("acc"), none.alias("out")), step, lambda a: a["out"])

    def whole(blocks: Column) -> Column:
        totals = F.transform(blocks, lambda b: F.aggregate(b, zero, fold))
        empty = F.struct(zero.alias("acc"), F.array().cast("array<int>").alias("out"))
        before = F.aggregate(totals, empty, lambda a, t: F.struct(merge(a["acc"], t).alias("acc"), F.array_append(a["out"], a["acc"]).alias("out")), lambda a: a["out"])
        return F.flatten(F.zip_with(blocks, before, walk))

    cut = lambda x: F.transform(F.sequence(F.lit(0), last(x)), lambda k: F.slice(x, k * BLOCK + 1, F.lit(BLOCK)))
    return let(items, lambda x: let(cut(x), whole))


def located(text: Column, pattern: str) -> Column:
    """array<struct<text, start>> of the leftmost non-overlapping matches; starts are code points."""
    kind = "struct<text:string,start:int>"
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    pairs = let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda found: F.zip_with(found, F.slice(gaps, F.lit(1), F.size(found)), lambda m, g: F.struct(m.alias("text"), g.alias("gap"))))
    hits = running(
        pairs,
        F.lit(0),
        lambda at, p: at + p["gap"] + F.length(p["text"]),
        lambda a, b: a + b,
        lambda at, p: F.struct(p["text"].alias("text"), (at + p["gap"]).alias("start")),
        kind,
    )
    return F.when(text.rlike(pattern), hits).otherwise(F.array().cast(f"array<{kind}>")).cast(f"array<{kind}>")


def span(kind: str, rank: int, start: Column, end: Column) -> Column:
    return F.struct(start.cast("int").alias("start"), F.lit(rank).alias("rank"), end.cast("int").alias("end"), F.lit(kind).alias("kind"))


SPANS = "array<struct<start:int,rank:int,end:int,kind:string>>"


def base_spans(text: Column, kind: str, rank: int, pattern: str) -> Column:
    hits = located(text, pattern)
    if kind == "assign":
        hits = F.filter(hits, lambda h: F.length(F.regexp_extract(h["text"], ASSIGN, 2)) >= ASSIGN_LEAST)
    return F.transform(hits, lambda h: span(kind, rank, h["start"], h["start"] + F.length(h["text"]))).cast(SPANS)


def dense_stretch(run: Column, alphabet: str, window: int, bits: float) -> Column:
    """struct<first, last>: first start and last end of windows that reach the entropy; -1: none.

    The state holds a count for each character of the class, packed into a few numbers, and the
    window's sum of weights. One step takes in a character and lets go the one that stood ``window``
    places before; a window is judged when the next step, or the end, finds it complete.
    """
    if window >= 1 << BITS:
        raise ValueError(f"windows go up to {(1 << BITS) - 1} characters")
    gain = F.array(*[F.lit(weight(c + 1) - weight(c)) for c in range(window + 1)])
    most, none = limit(window, bits), F.lit(-1)
    shift = lambda c: F.pmod(c, F.lit(PACK)) * BITS
    count = lambda n, c: F.call_function("shiftrightunsigned", F.element_at(n, F.floor(c / PACK).cast("int") + 1), shift(c)).bitwiseAND(F.lit((1 << BITS) - 1)).cast("int")
    one = lambda c, k: F.when(F.floor(c / PACK) == k, F.call_function("shiftleft", F.lit(1).cast("long"), shift(c))).otherwise(F.lit(0).cast("long"))

    def step(a: Column, e: Column) -> Column:
        new, old = e["new"], e["old"]
        gone = F.when(old >= 0, F.element_at(gain, count(a["n"], old))).otherwise(F.lit(0))
        came = F.element_at(gain, count(a["n"], new) - F.when(old == new, 1).otherwise(0) + 1)
        hit = (a["i"] >= window) & (a["sum"] <= most)
        return F.struct(
            F.transform(a["n"], lambda x, k: x + one(new, k) - F.when(old >= 0, one(old, k)).otherwise(F.lit(0).cast("long"))).alias("n"),
            (a["sum"] - gone + came).alias("sum"),
            (a["i"] + 1).alias("i"),
            F.when(hit & (a["first"] < 0), a["i"] - window).otherwise(a["first"]).alias("first"),
            F.when(hit, a["i"]).otherwise(a["last"]).alias("last"),
        )

    def judged(a: Column) -> Column:
        hit = (a["i"] >= window) & (a["sum"] <= most)
        return F.struct(F.when(hit & (a["first"] < 0), a["i"] - window).otherwise(a["first"]).alias("first"), F.when(hit, a["i"]).otherwise(a["last"]).alias("last"))

    zero = F.struct(F.array_repeat(F.lit(0).cast("long"), -(-len(alphabet) // PACK)).alias("n"), F.lit(0).alias("sum"), F.lit(0).alias("i"), none.alias("first"), none.alias("last"))
    chars = F.transform(F.split(run, ""), lambda c: F.instr(F.lit(alphabet), c) - 1)
    pairs = let(chars, lambda x: F.zip_with(x, F.slice(F.concat(F.array_repeat(F.lit(-1), window), x), F.lit(1), F.size(x)), lambda new, old: F.struct(new.alias("new"), old.alias("old"))))
    return F.aggregate(pairs, zero, step, judged)


def allowed(run: Column) -> Column:
    """Whether a run is on the allow-list: ALLOW, with the pattern of joined words taken apart."""
    snake = run.rlike("^[a-z][a-z_-]*[a-z]$") & run.rlike("[_-]") & ~run.rlike("[_-][_-]")
    return snake | run.rlike(ALLOW.replace(f"|{SNAKE}", ""))


def entropy_spans(text: Column, rank: int, spec: tuple) -> Column:
    kind, alphabet, pattern, window, bits = spec
    runs = F.filter(located(text, pattern), lambda h: ~allowed(h["text"]))
    scored = F.transform(runs, lambda h: F.struct(h["start"].alias("at"), dense_stretch(h["text"], alphabet, window, bits).alias("d")))
    dense = F.filter(scored, lambda s: s["d"]["first"] >= 0)
    return F.transform(dense, lambda s: span(kind, rank, s["at"] + s["d"]["first"], s["at"] + s["d"]["last"])).cast(SPANS)


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(F.array_sort(spans), lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def scan(docs: DataFrame) -> DataFrame:
    """docs' doc_id with the secrets of every whole text.

    base and added are arrays of struct<start, rank, end, kind>; offsets are code points, ends
    exclusive. Base spans are leftmost and non-overlapping for each kind, and all stay; an entropy
    span is added unless a base span covers it or the run is on the allow-list. Null text counts as
    empty; repeated rows give repeated rows; columns besides doc_id and text are not looked at.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    named = [("assign", ASSIGN), ("access", ACCESS), ("hex", HEX)]
    base = docs.select("doc_id", text.alias("text")).select("doc_id", "text", *[base_spans(F.col("text"), k, n, p).alias(k) for n, (k, p) in enumerate(named)], *[entropy_spans(F.col("text"), n + 3, c).alias(c[0]) for n, c in enumerate(CLASSES)])
    both = base.select("doc_id", *[k for k, _ in named], F.concat(*[k for k, _ in named]).alias("base"), F.concat(*[c[0] for c in CLASSES]).alias("dense"))
    return both.select("doc_id", *[k for k, _ in named], "base", uncovered(F.col("base"), F.col("dense")).alias("added"))


def uncovered(base: Column, dense: Column) -> Column:
    """The dense spans that no base span covers: in order of start, no base span so far reaches their end."""
    kind = "struct<start:int,rank:int,end:int,kind:string>"
    is_base = lambda x: x["rank"] < 3
    told = running(
        F.array_sort(F.concat(base, dense)),
        F.lit(0),
        lambda far, x: F.greatest(far, F.when(is_base(x), x["end"]).otherwise(0)),
        lambda a, b: F.greatest(a, b),
        lambda far, x: F.when(~is_base(x) & (far < x["end"]), x).cast(kind),
        kind,
    )
    return F.when(F.size(dense) > 0, F.filter(told, lambda x: x.isNotNull())).otherwise(F.array()).cast(SPANS)


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(common.table(spark, sf_dir, "documents"))
    sizes = [F.size(k).cast("long").alias(f"n_{k}") for k in ("assign", "access", "hex")]
    return found.select("doc_id", *sizes, F.sha2(joined(F.col("base")), 256).alias("base_sha256"), joined(F.concat("base", "added")).alias("spans"))


def oracle() -> str:
    """DuckDB SQL for op9_secrets: windows are counted afresh, one by one."""
    assign = ASSIGN.replace("(?i)(password|passwd|secret|token|api_?key)", "([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])")
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    ctes, parts = [], []
    patterns = [("assign", assign), ("access", ACCESS), ("hex", HEX), *[(c[0], c[2]) for c in CLASSES]]
    for rank, (kind, p) in enumerate(patterns):
        ctes.append(f"m{rank} AS (SELECT rid, regexp_extract_all(t, {quote(p)}) AS ms, string_split_regex(t, {quote(p)}) AS gs FROM d WHERE regexp_matches(t, {quote(p)}))")
        ctes.append(f"h{rank} AS (SELECT rid, ms[k] AS s, list_sum(list_transform(gs[1:k], lambda x: length(x))) + coalesce(list_sum(list_transform(ms[1:k-1], lambda x: length(x))), 0) AS a FROM (SELECT *, unnest(range(1, len(ms) + 1)) AS k FROM m{rank}))")
        if rank < 3:
            keep = f"length(regexp_extract(s, {quote(assign)}, 2)) >= {ASSIGN_LEAST}" if rank == 0 else "true"
            parts.append(f"SELECT rid, {rank} AS rank, '{kind}' AS kind, a AS a, a + length(s) AS b FROM h{rank} WHERE {keep}")
        else:
            w, bits = CLASSES[rank - 3][3:]
            table = "[" + ", ".join(str(weight(c)) for c in range(w + 1)) + "]"
            score = f"list_sum(list_transform(list_distinct(string_split(substr(s, k, {w}), '')), lambda c: {table}[len(list_filter(string_split(substr(s, k, {w}), ''), lambda x: x = c)) + 1]))"
            ctes.append(f"w{rank} AS (SELECT rid, a, k FROM (SELECT *, unnest(range(1, length(s) - {w} + 2)) AS k FROM h{rank} WHERE NOT regexp_matches(s, {quote(ALLOW)})) WHERE {score} <= {limit(w, bits)})")
            parts.append(f"SELECT rid, {rank} AS rank, '{kind}' AS kind, a + min(k) - 1 AS a, a + max(k) - 1 + {w} AS b FROM w{rank} GROUP BY rid, a")
    return f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM documents),
{", ".join(ctes)},
spans AS ({" UNION ALL ".join(parts)}),
kept AS (SELECT * FROM spans s WHERE rank < 3 OR NOT EXISTS (SELECT 1 FROM spans b WHERE b.rid = s.rid AND b.rank < 3 AND b.a <= s.a AND b.b >= s.b)),
g AS (SELECT rid, count(*) FILTER (rank = 0) AS n0, count(*) FILTER (rank = 1) AS n1, count(*) FILTER (rank = 2) AS n2,
  string_agg(kind || ':' || a || ':' || b, ',' ORDER BY a, rank) FILTER (rank < 3) AS base,
  string_agg(kind || ':' || a || ':' || b, ',' ORDER BY a, rank) AS spans FROM kept GROUP BY rid)
SELECT d.doc_id, coalesce(n0, 0)::BIGINT AS n_assign, coalesce(n1, 0)::BIGINT AS n_access, coalesce(n2, 0)::BIGINT AS n_hex,
  sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN g ON d.rid = g.rid"""
