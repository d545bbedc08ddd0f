"""The ten operators against brute force, exact round trips and held-out labels, and their edge cases."""

import base64
import gzip
import hashlib
import math
import random
import re
import time
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from deltamat.llm import ann, chat, common, decontaminate, langid, lines, pieces, quality, registry, secrets, simhash, warc

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts, **extra):
    rows = [(k, t, "en", "s", None if t is None else len(t)) for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, a long text, repeated rows, clashing column names."""
    rows = [(0, None, None, None, None), (1, "", "en", "s", 0), (2, "word " * 20_000, "en", "s", 100_000), (2, "word " * 20_000, "en", "s", 100_000), (None, "no id here", None, "s", 10), (3, "a\n\na\n b \n", "en", "s", 8)]
    df = spark.createDataFrame(rows, DOCS)
    for name in ("node", "key", "line", "kept", "_x", "score"):
        df = df.withColumn(name, F.lit("clash"))
    return df


def words(rng, n):
    return " ".join("".join(rng.choice("bcdfglmnprst") + rng.choice("aeiou") for _ in range(rng.randint(1, 4))) for _ in range(n))


# ---- 1: nearest neighbours -------------------------------------------------------------------


def exact_neighbours(rows, k):
    ids, x = np.array([i for i, _ in rows]), np.array([v for _, v in rows], np.float64)
    out = {}
    for q in range(len(ids)):
        if ids[q] % 100 == 0:
            d = np.sqrt(((x - x[q]) ** 2).sum(1))
            out[ids[q]] = [(ids[n], d[n]) for n in np.lexsort((ids, d)) if ids[n] != ids[q]][:k]
    return out


def test_nearest_recall_ties_and_bad_vectors(spark):
    rng = np.random.default_rng(3)
    rows = [(k, rng.normal(size=8).astype(np.float32).tolist()) for k in range(1200)]
    rows[700:900] = [(k, rows[100][1]) for k in range(700, 900)]  # a large group of copies
    bad = [(2000, None), (2100, [0.0] * 8), (2200, [1.0, None] + [0.0] * 6), (2300, [float("nan")] + [1.0] * 7), (2400, [1.0, 2.0]), (None, [1.0] * 8)]
    df = spark.createDataFrame(rows + bad, "vec_id long, vec array<float>")
    got: dict = {}
    for r in ann.search(df, F.pmod("vec_id", F.lit(100)) == 0, ann.Settings(leaf=16, probes=50, cell=100)).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    want = exact_neighbours(rows, 10)
    assert set(got) == set(want) and all(len(x) == 10 for x in got.values())
    assert [i for i, _ in got[700]] == [100, *range(701, 710)]
    hits = sum(len({i for i, _ in got[q]} & {i for i, _ in want[q]}) for q in want)
    assert hits >= 0.9 * 10 * len(want)
    vec = dict(rows)
    for q, answers in got.items():
        for i, s in answers:
            assert math.isclose(s, float(np.sqrt(((np.array(vec[q], float) - np.array(vec[i], float)) ** 2).sum())), rel_tol=1e-12, abs_tol=1e-12)


def test_index_rows_are_copied_for_their_own_visits_only(spark, monkeypatch):
    """Blocks of queries and entries cover all visits; repeated ids and small blocks change no answer."""
    rng = np.random.default_rng(4)
    rows = [(k, rng.normal(size=6).astype(np.float32).tolist()) for k in range(900)]
    df = spark.createDataFrame(rows + rows[:50], "vec_id long, vec array<float>").withColumn("leaf", F.lit("clash"))
    ask = F.pmod("vec_id", F.lit(3)) == 0
    key = lambda out: sorted((r.query_id, r.rank, r.vec_id, r.score) for r in out.collect())
    s = ann.Settings(leaf=30, probes=50)
    assert key(ann.search(df, ask, ann.Settings(leaf=30, probes=50, cell=20, queries_cell=25))) == key(ann.search(df, ask, s))


def test_nearest_small_and_empty(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [3.0, 3.0])], "vec_id long, vec array<float>")
    assert [r.vec_id for r in ann.search(df, F.pmod("vec_id", F.lit(100)) == 0).orderBy("rank").collect()] == [1, 2]
    assert ann.search(df.limit(0), F.lit(True)).count() == 0


# ---- 2: languages ----------------------------------------------------------------------------


def phrases_by_search(text, sample):
    n = k = 0
    while k < len(text):
        m = 1
        while k + m < len(text) and text[k : k + m + 1] in sample:
            m += 1
        k, n = k + m, n + 1
    return n


def test_phrases_are_longest_matches():
    rng = random.Random(4)
    sample, text = "".join(rng.choice("abc") for _ in range(300)), "".join(rng.choice("abcd") for _ in range(200))
    p = langid.Parser((("x", sample),), langid.Settings(stretch=1000))
    assert p.phrases([p.codes(text)[0]])[0, 0] == phrases_by_search(text, sample)


def test_phrases_do_not_depend_on_stretches(monkeypatch):
    """Whole texts are parsed in one go, however they are cut, also where cuts never fall in step."""
    rng = random.Random(14)
    samples = tuple((c, "".join(rng.choice(c) for _ in range(300))) for c in ("abc", "bcd"))
    texts = ["".join(rng.choice("abcd") for _ in range(rng.randint(1, 500))) for _ in range(20)] + ["a" * 300, "abc" * 100]
    want = [[phrases_by_search(t, s) for _, s in samples] for t in texts]
    for stretch in (7, 64, 1000):
        p = langid.Parser(samples, langid.Settings(stretch=stretch))
        codes = [p.codes(t)[0] for t in texts]
        assert p.phrases(codes).tolist() == want
        with monkeypatch.context() as m:
            m.setattr(langid, "KEPT", 6 * stretch)  # groups of three stretches
            assert p.phrases(codes).tolist() == want


def test_languages_of_many_letters(spark):
    """Scripts of thousands of letters are told apart, and two languages of one script by what follows what."""
    rng = random.Random(15)

    def language(letters, seed):
        own = random.Random(seed)
        pool = ["".join(chr(own.choice(letters)) for _ in range(own.randint(1, 3))) for _ in range(400)]
        return lambda n: " ".join(pool[min(399, int(rng.expovariate(0.01)))] for _ in range(n))

    han, hangul, latin = range(0x4E00, 0x9000), range(0xAC00, 0xD000), range(0x61, 0x7B)
    speak = {"la": language(latin, 1), "ko": language(hangul, 2), "zh": language(han, 3), "ja": language(han, 4)}
    rows = [(k, text(300), lang, "s", None) for k, (lang, text) in enumerate(list(speak.items()) * 60)]
    docs = spark.createDataFrame(rows, DOCS)
    out = langid.identify(docs, langid.sample(docs, langid.Settings())).where("held_out").collect()
    lang = {r[0]: r[2] for r in rows}
    assert len(out) > 30 and sum(r.lang_pred == lang[r.doc_id] for r in out) >= 0.95 * len(out)


def test_languages_of_long_texts_only_are_learned(spark):
    rng = random.Random(16)
    rows = [(k, words(rng, 2000) if k % 2 else " ".join(chr(rng.randrange(0x3B1, 0x3C9)) * 2 for _ in range(40)), "xy"[k % 2], "s", None) for k in range(40)]
    docs = spark.createDataFrame(rows, DOCS)
    samples = langid.sample(docs, langid.Settings())
    assert [x for x, _ in samples] == ["x", "y"]
    assert all(r.lang_pred == "xy"[r.doc_id % 2] for r in langid.identify(docs, samples).collect())


def test_language_held_out_accuracy_and_edges(spark, sf, odd):
    docs = common.table(spark, sf, "documents")
    got = registry.QUERIES["op2_language_id"](spark, sf).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert len(got) > 20 and sum(r.lang == r.lang_pred for r in got) >= 0.93 * len(got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    out = langid.identify(odd, langid.sample(docs, langid.Settings())).collect()
    assert len(out) == 6 and {(r.lang_pred, r.score) for r in out if r.doc_id in (0, 1)} == {("und", 0.0)}
    assert all(0 <= r.score <= 1 for r in out)
    assert {r.lang_pred for r in langid.identify(odd, ()).collect()} == {"und"}
    assert langid.identify(docs.limit(0), langid.sample(docs.limit(0), langid.Settings())).count() == 0


# ---- 3: lines --------------------------------------------------------------------------------


def lines_by_force(rows, s=lines.Settings()):
    first = {}
    for doc, text in sorted(rows):
        for k, raw in enumerate(text.split("\n")):
            x = raw.strip(lines.BLANK)
            if x:
                first.setdefault(x, (doc, k))
    names = list(first)
    sets = [{y[k : k + s.shingle] for k in range(len(y) - s.shingle + 1)} for y in (x.ljust(s.shingle, "\0") for x in names)]
    up = list(range(len(names)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(names)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both >= s.similarity * (len(sets[a]) + len(sets[b]) - both):
                up[find(a)] = find(b)
    keep = {}
    for n, x in enumerate(names):
        keep[find(n)] = min(keep.get(find(n), (1 << 60, 0)), first[x])
    stay = set(keep.values())
    return {d: "\n".join(x for k, x in enumerate(t.split("\n")) if not x.strip(lines.BLANK) or (d, k) in stay) for d, t in rows}


def test_lines_against_brute_force(spark):
    rng = random.Random(9)
    base = [words(rng, rng.randint(3, 60)) for _ in range(30)]
    rows = []
    for d in range(60):
        own = []
        for x in rng.sample(base, 4):
            w = x.split(" ")
            if rng.random() < 0.5:
                w[rng.randrange(len(w))] = words(rng, 1)
            own.append(" ".join(w) + rng.choice(["", " ", "\t"]))
        own.insert(2, "")
        rows.append((d, "\n".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r.doc_id: r.text for r in lines.dedup_lines(df, lines.Settings(block=8)).collect()}
    assert got == lines_by_force(rows)


def test_line_edges(spark, odd):
    out = {(r.doc_id, r.text): r for r in lines.dedup_lines(odd).collect()}
    assert lines.dedup_lines(odd).columns == odd.columns
    assert out[0, None].n_chars is None and out[1, ""].n_chars == 0
    assert out[3, "a\n\n b \n"].n_chars == 7
    assert lines.dedup_lines(odd.limit(0)).count() == 0


def test_both_kinds_of_signature_meet():
    rng = random.Random(2)
    s = lines.Settings()
    for n in (20, 150, 170, 400):
        a = "".join(rng.choice("abcdefghij") for _ in range(n))
        b = a[: n // 2] + "X" + a[n // 2 + 1 :]
        keys = [set() for _ in "ab"]
        for kind, which, k in lines.signatures([a, b], s):
            for row, at in enumerate(which.tolist()):
                keys[at] |= {(kind, x) for x in k[row].tolist()}
        if n > 100:
            assert keys[0] & keys[1]


def test_repetitive_lines_of_unlike_lengths_meet(spark):
    """Sets decide, not lengths: equal sets from under 128 and from over 160 shingles with repeats."""
    phrase = "".join(chr(97 + k % 26) for k in range(11)) + ". "
    rows = [(0, "-" * 100), (1, "-" * 300), (2, phrase * 8), (3, phrase * 20), (4, "a " * 40), (5, "a " * 5000), (6, words(random.Random(1), 90))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in lines.dedup_lines(df).collect()}
    assert got == lines_by_force(rows)
    assert not any(got[k] for k in (1, 3, 5)) and all(got[k] for k in (0, 2, 4, 6))


def test_lines_at_the_threshold_meet():
    """Pairs of 0.80 Jaccard, long ones and short ones: all but 3 in 1,000 share a band."""
    s = lines.Settings()
    assert 1 - (1 - s.similarity**s.rows) ** s.bands >= 0.997
    rng = random.Random(11)
    for n in (84, 336):
        pairs = []
        for _ in range(3000):
            a = [chr(rng.randrange(0x4E00, 0x9FFF)) for _ in range(n + 6)]
            b, cut = list(a), n // 9  # n shingles, a ninth of them replaced: (8/9) / (10/9) = 0.8
            b[-cut:] = [chr(rng.randrange(0x3400, 0x4DBF)) for _ in range(cut)]
            pairs += ["".join(a), "".join(b)]
        keys = [set() for _ in pairs]
        for kind, which, k in lines.signatures(pairs, s):
            for row, at in enumerate(which.tolist()):
                keys[at] |= {(kind, x) for x in k[row].tolist()}
        missed = sum(not keys[k] & keys[k + 1] for k in range(0, len(pairs), 2))
        assert missed <= 15, (n, missed)  # 9 bands of 4 rows would miss 27 on average, 12 miss 5


# ---- 4: SimHash ------------------------------------------------------------------------------


def simhash_by_force(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    sh = [" ".join(w[k : k + 4]) for k in range(max(1, len(w) - 3))]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("text", [None, "", " \n ", "one", "Two words", "a b c d", " A\tb\x0bC  d e\xa0f g ÀB ", "x " * 500, "ß ÄÖ É"])
def test_fingerprint(text):
    assert simhash.fingerprint(text) == simhash_by_force(text)


def test_simhash_components(spark):
    rng = random.Random(6)
    base = [words(rng, 300) for _ in range(12)]
    texts = base + base[:4] + ["", None]
    for x in base[:6]:
        for _ in range(6):
            w = x.split(" ")
            w[rng.randrange(300)] = "changed"
            texts.append(" ".join(w))
    fps = [simhash_by_force(t) for t in texts]
    root = list(range(len(texts)))
    for _ in texts:
        for a in range(len(texts)):
            for b in range(len(texts)):
                if (fps[a] ^ fps[b]).bit_count() <= 4:
                    root[a] = root[b] = min(root[a], root[b])
    got = {r.doc_id: (int(r.fingerprint, 16), r.component_id) for r in simhash.near_duplicates(docs_of(spark, texts), block=3).collect()}
    assert got == {k: (fps[k], root[k]) for k in range(len(texts))}
    kept = {r.doc_id for r in simhash.drop_near_duplicates(docs_of(spark, texts)).collect()}
    assert kept == set(root)


def members_joined(spark, fps, monkeypatch):
    """Rows of the buckets' members, and the edges' components against brute force."""
    seen = []
    real = common.link_buckets

    def spy(own, *more, **named):
        seen.append(own.count())
        return real(own, *more, **named)

    monkeypatch.setattr(common, "link_buckets", spy)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(signed(x),) for x in fps], "node long")
    edges = simhash.links(df, 4, 64)
    roots = {r.node: r.root for r in common.components(edges).collect()}
    arr = np.array(sorted(fps), np.uint64)
    near = np.bitwise_count(arr[:, None] ^ arr[None, :]) <= 4
    label = np.arange(len(arr))
    for _ in range(len(arr)):
        new = np.where(near, label[None, :], len(arr)).min(1)
        if (new == label).all():
            break
        label = new
    groups: dict = {}
    for x, g in zip(arr.tolist(), label.tolist(), strict=True):
        groups.setdefault(g, set()).add(signed(x))
    got: dict = {}
    for x in map(signed, arr.tolist()):
        got.setdefault(roots.get(x, x), set()).add(x)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, groups.values()))
    return sum(seen)


@pytest.mark.parametrize("n", [200, 800])
def test_a_group_of_near_copies_stays_small_in_the_index(spark, monkeypatch, n):
    """Members of one group stand in under ten buckets each, and no link is lost, in large buckets either."""
    rng = random.Random(n)
    base = rng.getrandbits(64)
    fps = {base}
    while len(fps) < n:
        x = base
        for _ in range(rng.randint(1, 5)):
            x ^= 1 << rng.randrange(64)
        fps.add(x)
    assert members_joined(spark, fps, monkeypatch) < 10 * n


@pytest.mark.parametrize("page_keys", [5, 1 << 19])
def test_band_keys_of_several_nodes_are_found_in_pages(spark, page_keys):
    rng = random.Random(4)
    keys = [-(1 << 63), (1 << 63) - 1, -1, 0, *(rng.getrandbits(64) - (1 << 63) for _ in range(60))]
    rows = [(rng.choice([-7, 1, 2, 1 << 62, rng.getrandbits(40)]), rng.choice(keys), rng.choice(keys)) for _ in range(90)] + [(5, 77, 78)] * 9
    seen = {}
    for node, *own in rows:
        for k in own:
            seen.setdefault(k, set()).add(node)
    table = spark.createDataFrame(rows, "node long, b0 long, b1 long").repartition(5)
    out = lines.shared_keys(table, page_keys)
    assert sorted(r.key for r in out.collect()) == sorted(k for k, nodes in seen.items() if len(nodes) > 1)
    assert "HashAggregate" not in out._jdf.queryExecution().toString()
    assert lines.shared_keys(table.limit(0), page_keys).collect() == []


def test_small_cells_are_compared_pair_by_pair(monkeypatch):
    rng, s = random.Random(23), lines.Settings()
    monkeypatch.setattr(common, "cell_edges", None)  # matrices are for larger cells
    keys, texts = [], []
    for key in range(60):
        base = [rng.choice("abcdef ") for _ in range(rng.choice((1, 5, 8, 60, 300)))]
        for _ in range(rng.randint(1, lines.SMALL)):
            keys.append(key)
            texts.append("".join(rng.choice("xyz") if rng.random() < 0.01 else c for c in base))
    starts = np.flatnonzero(np.diff([-1, *keys]))
    t = pa.table({"key": keys, "node": range(len(keys)), "side": pa.array([0] * len(keys), pa.int32()), "line": texts})
    sets = [set(lines.shingle_hashes([x], s.shingle)[0].tolist()) for x in texts]
    near = [(a, b) for b in range(len(keys)) for a in range(b) if keys[a] == keys[b] and len(sets[a] & sets[b]) >= s.similarity * len(sets[a] | sets[b])]

    def roots(edges):
        root = list(range(len(keys)))
        for a, b in edges:
            root = [root[a] if r == root[b] else r for r in root]
        return [root.index(r) for r in root]

    got = list(zip(*(x.tolist() for x in lines.linker(s)(t, starts)), strict=True))
    assert set(got) <= set(near) and roots(got) == roots(near) and len(got) == len(keys) - len(set(roots(near)))
    assert len(near) > len(got) > 20


def test_band_keys_travel_as_one_value(spark):
    docs = spark.createDataFrame([(1, "one line\nanother, " + "longer " * 40), (2, "one line")], "doc_id long, text string")
    sigs = lines.signature_table(docs.select(*lines.key_columns(docs), "text"), lines.Settings())
    assert sigs.columns[-1] == "keys" and {len(r["keys"]) for r in sigs.collect()} == {96}
    keys = np.arange(-8, 28).reshape(3, 12)
    b = pa.record_batch([pa.array([1, 2, 3]), lines.packed(keys)], names=["node", "keys"])
    for cut in (b, b.slice(1), b.slice(1, 1), b.slice(3)):
        assert [x.tolist() for x in lines.unpacked(cut, 1)] == [x.tolist() for x in keys[[n - 1 for n in cut.column(0).to_pylist()]].T if len(cut)]


def test_shingles_are_rolled_in_runs(monkeypatch):
    texts = ["", "ab", "abcdefg", "é\U0001f600" * 9, "x" * 300, "the same line"] * 3
    want = [lines.shingle_hashes([t], 7)[0].tolist() for t in texts]
    monkeypatch.setattr(lines, "RUN", 5)
    h, counts = lines.shingle_hashes(texts, 7)
    assert h.tolist() == sum(want, []) and counts.tolist() == [len(w) for w in want]


def test_large_buckets_of_several_components_lose_no_link(spark, monkeypatch):
    rng = random.Random(17)
    low = rng.getrandbits(21)  # one segment for all, far apart elsewhere but for a few pairs and chains
    fps = set()
    while len(fps) < 260:
        x = rng.getrandbits(43) << 21 | low
        fps.add(x)
        for _ in range(rng.randint(0, 3)):
            x ^= 1 << rng.randrange(64)
            fps.add(x)
    members_joined(spark, fps, monkeypatch)


def test_one_row_of_each_component_stays(spark, odd):
    """Null and shared ids: rows far apart all stay, and each component keeps one row."""
    rng = random.Random(18)
    a, b, c, d, e = (words(rng, 200) for _ in range(5))
    rows = [(None, a), (None, b), (None, c), (1, d), (1, e), (1, e), (None, e), (2, a), (3, None), (None, ""), (4, d)]
    got = [(r.doc_id, r.text) for r in simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert sorted(got, key=str) == sorted([(2, a), (None, b), (None, c), (1, d), (1, e), (3, None)], key=str)
    assert len(simhash.drop_near_duplicates(odd).collect()) == 4


def test_simhash_edges(spark, odd):
    assert simhash.near_duplicates(odd).count() == 6
    assert simhash.near_duplicates(odd.limit(0)).count() == 0
    assert simhash.drop_near_duplicates(odd).columns == odd.columns


def test_near_dedup_stage_reaches_jaccard_of_five_words(spark, sf):
    """The pipeline's stage links what brute force finds at Jaccard 0.8, however far the fingerprints are."""
    import corpus_pipeline

    rng = random.Random(12)
    texts = [words(rng, n) for n in (40, 120, 300, 900, 2000) for _ in range(4)]
    for x in list(texts):
        for share in (0.01, 0.02, 0.03):
            w = x.split(" ")
            for _ in range(max(1, round(share * len(w)))):
                w[rng.randrange(len(w))] = words(rng, 1)
            texts.append(" ".join(w))
    texts += ["Three short WORDS", " three\tshort words", None, ""]
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))})
    fps = [simhash_by_force(t) for t in texts]
    root, far = list(range(len(texts))), 0
    for a in range(len(texts)):
        for b in range(a):
            alike = len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
            near = (fps[a] ^ fps[b]).bit_count() <= 4
            far += alike and not near
            if alike or near:
                root = [root[b] if x == root[a] else x for x in root]
    assert far >= 20
    first = {r: root.index(r) for r in root}
    kept = {r.doc_id for r in corpus_pipeline.near_dedup(spark, docs_of(spark, texts), sf).collect()}
    assert kept == set(first.values())


def test_components_of_paths_stars_and_negative_ids(spark):
    rng = random.Random(0)
    edges = [(k, k + 1) for k in range(-40, 40)] + [(100, 200 + k) for k in range(30)] + [(7, 7), (500, 501), (501, 500)]
    rng.shuffle(edges)
    got = {r.node: r.root for r in common.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: -40 for k in range(-40, 41)} | {100: 100} | {200 + k: 100 for k in range(30)} | {500: 500, 501: 500}
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_cell_edges_join_what_pieces_have():
    rng = np.random.default_rng(1)
    for _ in range(50):
        n = 12
        near = rng.random((n, n)) < 0.12
        near |= near.T | np.eye(n, dtype=bool)
        side = (np.arange(n) >= 6).astype(int)
        a, b = common.cell_edges(near, side)
        own = [common.forest(near & (side[:, None] == side[None, :]))]
        joined = np.eye(n, dtype=bool)
        for x, y in [*zip(*own[0], strict=True), *zip(a, b, strict=True)]:
            joined[x, y] = joined[y, x] = True
        reach = lambda m: np.linalg.matrix_power(m.astype(float), n) > 0
        assert (reach(joined) == reach(near)).all()


# ---- 5: SentencePiece ------------------------------------------------------------------------

SAMPLES = ["", " ", "  a  b", "a   b\n\n c", "<s> hi </s>", "▁x", "x▁ y", "é\U0001f600 日本 \x00\t", " " * 17 + "z", "▁ ▁", "a" * 500, "Tiouble ersh, ouwhre!"]


@pytest.fixture(scope="module")
def model():
    with open(pieces.MODEL, "rb") as f:
        return f.read()


def test_encoder_has_the_model_s_ids(model, sf, spark):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_proto=model)
    e = pieces.Encoder(model, 1)
    texts = SAMPLES + [r.text for r in common.table(spark, sf, "documents").select("text").limit(40).collect()]
    ids, same, whole = e.encode(texts)
    assert ids == sp.encode(texts) and all(same)
    assert e.fast.decode_batch(ids, skip_special_tokens=False) == sp.decode(ids)
    for t, i, w in zip(texts, ids, whole, strict=True):
        assert not w or sp.decode(i) == t
    assert [g.ids for g in e.fast.encode_batch(texts, add_special_tokens=False)] == ids


def varint(n):
    out = b""
    while n > 127:
        out += bytes([n & 127 | 128])
        n >>= 7
    return out + bytes([n])


def field(number, value):
    if isinstance(value, int):
        return varint(number << 3) + varint(value)
    return varint(number << 3 | 2) + varint(len(value)) + value


def test_unigram_model_with_byte_fallback(spark, sf, tmp_path):
    """A tiny hand-written unigram model: scores, squeezed blanks and byte pieces are rebuilt."""
    import struct

    import sentencepiece

    rows = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3), *((f"<0x{k:02X}>", 0.0, 6) for k in range(256))]
    rows += [(p, s, 1) for p, s in (("▁", -3.0), ("a", -4.0), ("b", -4.5), ("ab", -5.0), ("▁a", -4.2), ("▁ab", -6.0), ("ba", -5.5), ("aba", -8.0))]
    body = b"".join(field(1, field(1, p.encode()) + varint(2 << 3 | 5) + struct.pack("<f", s) + field(3, k)) for p, s, k in rows)
    body += field(2, field(3, 1) + field(4, len(rows)) + field(35, 1) + field(40, 0) + field(41, 1) + field(42, 2)) + field(3, field(1, b"identity") + field(3, 1) + field(4, 1))
    sp = sentencepiece.SentencePieceProcessor(model_proto=body)
    e = pieces.Encoder(body, 1)
    assert e.model.kind == pieces.UNIGRAM and not e.apart
    texts = ["ab ab", "  abba  baab ", "aé", "ababab", "b"]
    ids, same, _ = e.encode(texts)
    assert ids == sp.encode(texts) and all(same)
    path = tmp_path / "unigram.model"
    path.write_bytes(body)
    rows = pieces.encode(common.table(spark, sf, "documents").limit(60), str(path)).collect()
    text = {r.doc_id: r.text for r in common.table(spark, sf, "documents").collect()}
    assert all(r.parity and list(r.ids) == sp.encode(text[r.doc_id] or "") for r in rows) and sum(r.n_tokens for r in rows) > 1000


def test_ids_are_the_pipeline_s_and_a_difference_shows(model):
    """Where sentencepiece disagrees, ids stay the rebuilt pipeline's and parity is false."""
    e = pieces.Encoder(model, 1)
    real = e.reference

    class Other:
        def encode(self, texts, **more):
            return [[*x[:-1], 5] if "off" in t else x for x, t in zip(real.encode(texts, **more), texts, strict=True)]

    e.reference = Other()
    texts = ["all is well", "this is off"]
    ids, same, _ = e.encode(texts)
    assert ids == real.encode(texts) and same == [False, False] or same == [True, False]
    e.apart = False
    assert e.encode(texts)[:2] == (real.encode(texts), [True, False])


def test_encode_and_decode_tables(spark, odd):
    out = {r.doc_id: r for r in pieces.encode(odd).collect()}
    assert out[0].ids == [] and out[1].n_tokens == 0 and out[3].round_trip and out[2].n_tokens == len(out[2].ids)
    back = {r.doc_id: r.text for r in pieces.decode(pieces.encode(odd)).collect()}
    assert back[3] == "a\n\na\n b \n" and back[0] == ""
    assert pieces.encode(odd.limit(0)).count() == 0


# ---- 6: quality ------------------------------------------------------------------------------


def test_quality_held_out_and_edges(spark, sf, odd):
    docs, labels = common.table(spark, "/root/testdata/sf0.01", "documents"), common.table(spark, "/root/testdata/sf0.01", "labels")
    voter = quality.fit(docs, labels)
    got = quality.score(docs, voter).join(labels, "doc_id").where("held_out").collect()
    assert len(got) > 50 and sum(r.predicted == r.quality for r in got) >= 0.95 * len(got)
    assert all(r.predicted == int(r.score >= 0.7) and 0 <= r.score <= 1 for r in got)
    out = quality.score(odd, voter).collect()
    assert len(out) == 6 and len({r.score for r in out if r.doc_id in (0, 1)}) == 1
    assert quality.keep_good(odd, voter).columns == odd.columns
    nothing = quality.fit(docs, labels.limit(0))
    assert {r.score for r in quality.score(odd, nothing).collect()} == {0.5}


def test_votes_are_exact_cosines():
    texts = ["alpha beta", "beta gamma", "SHOUT!! LOUD!!", "alpha alpha gamma"]
    v = quality.Voter(quality.Settings(neighbours=2, dims=3), texts, [1, 1, 0, 1])
    x = v.space.place([*texts, "beta alpha"])
    cos = x[4] @ x[:4].T
    near = np.argsort(-cos)[:2]
    w = np.maximum(cos[near], 0).astype(float) ** 4
    assert math.isclose(v.scores(["beta alpha"])[0], float((w * np.array([1, 1, 0, 1])[near]).sum() / w.sum()), rel_tol=1e-6)


def test_ties_go_to_what_was_learned_first():
    v = quality.Voter(quality.Settings(neighbours=2, dims=2), ["alpha beta"] * 3 + ["SHOUT!!"], [1, 1, 0, 0])
    assert v.scores(["alpha beta"])[0] == 1.0
    one, many = v.scores(["alpha SHOUT"])[0], v.scores(["alpha SHOUT"] * 50)
    assert set(many.tolist()) == {one}


# ---- 7: decontamination ----------------------------------------------------------------------


def bm25_by_force(index, query):
    return [(k, s) for k in range(len(index.ids)) if (s := sum(dict(zip(*index.postings[t], strict=True)).get(k, 0.0) for t in query)) >= index.settings.threshold]


def test_wand_retrieves_all_above_the_threshold():
    rng = random.Random(8)
    vocabulary = [words(rng, 1) for _ in range(120)]
    items = [(k, " ".join(rng.choices(vocabulary, k=rng.randint(8, 30)))) for k in range(60)]
    for block, threshold in ((1, 0.3), (2, 0.5), (8, 0.25)):
        index = decontaminate.BlockMaxIndex(items, decontaminate.Settings(threshold=threshold, block=block))
        for _ in range(60):
            terms = sorted({index.vocab[w] for w in decontaminate.words(rng.choice(items)[1]) + rng.choices(vocabulary, k=20) if w in index.vocab and rng.random() < 0.8})
            want = bm25_by_force(index, terms)
            got = index.wand(terms)
            assert [k for k, _ in got] == [k for k, _ in want]
            assert not want or index.reaches(np.array(terms))


def test_planted_items_are_found_and_others_left(spark):
    rng = random.Random(5)
    items = [(k, words(rng, rng.randint(15, 55)).capitalize() + "? " + words(rng, 6)) for k in range(30)]
    texts, planted = [], {}
    for d in range(120):
        w = words(rng, 400).split(" ")
        if d % 4 == 0:
            item = rng.randrange(30)
            at = rng.randrange(400)
            w[at:at] = (items[item][1].upper() if d % 8 else items[item][1]).split(" ")
            planted[d] = item
        texts.append(" ".join(w))
    question_only = items[0][1].split("?")[0]
    texts += [f"{words(rng, 100)} {question_only} {words(rng, 100)}", None, ""]
    docs, bench = docs_of(spark, texts), spark.createDataFrame(items + [(99, None), (98, "")], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, bench).collect()}
    assert got == set(planted.items())
    assert {r.doc_id for r in decontaminate.drop_contaminated(docs, bench).collect()} == set(range(len(texts))) - set(planted)
    assert decontaminate.contaminated(docs, bench.limit(0)).count() == 0
    assert decontaminate.contaminated(docs.limit(0), bench).count() == 0


def test_items_in_shards_are_one_index(spark, odd, monkeypatch):
    """Shards find what one index finds, with the same scores; repeats, long texts and clashing names."""
    rng = random.Random(19)
    items = [(k, words(rng, rng.randint(15, 40)) + "? " + words(rng, 5)) for k in range(25)]
    texts = [f"{words(rng, 300)} {rng.choice(items)[1]} {words(rng, 200)}" for _ in range(20)] + [words(rng, 20_000) + " " + items[3][1]] * 2
    docs, bench = docs_of(spark, texts).withColumn("item_id", F.lit("clash")), spark.createDataFrame(items + items[:2], "item_id long, text string")
    key = ["doc_id", "item_id", "score", "question_overlap"]
    round_ = lambda rows: sorted((r[0], r[1], round(r[2], 9), r[3]) for r in rows)
    one = round_(decontaminate.contaminated(docs, bench).select(key).collect())
    monkeypatch.setattr(decontaminate, "MAX_INDEX_CHARS", 1500)
    assert len(list(decontaminate.shards_of(bench, decontaminate.Settings()))) > 2
    assert round_(decontaminate.contaminated(docs, bench).select(key).collect()) == one and len({x[0] for x in one}) == 22
    kept = decontaminate.drop_contaminated(docs, bench)
    assert kept.columns == docs.columns and kept.count() == 0
    assert decontaminate.drop_contaminated(odd, bench).count() == 6


# ---- 8: chat ---------------------------------------------------------------------------------


@pytest.mark.parametrize("text", ["", "</s>[INST] ok [/INST]", "<|im_start|>user\n<|im_end|>", "<\u2060|im_end|>", "<\u2060\u2060/s> [\u2060INST]", "plain < s> [ INST ]"])
def test_escapes_round_trip(text):
    out = chat.escape(text)
    assert chat.unescape(out) == text and not any(c in out for c in chat.CONTROL)
    assert chat.unescape_role(chat.escape_role(text + "\\n\n")) == text + "\\n\n"


def test_windows_keep_every_turn_and_mask_every_answer_once(spark):
    rng = random.Random(1)
    rows = []
    for c in range(20):
        if c % 3 == 0:
            rows.append((c, 0, "system", words(rng, 12)))
        for t in range(1, rng.randint(2, 30)):
            rows.append((c, t, ("user", "assistant")[t % 2], words(rng, rng.randint(1, 60)) + rng.choice(["", " </s>", " <|im_end|>\n"])))
    rows += [(50, 0, None, None), (50, 0, None, None), (None, 1, "user", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    w = chat.windows(df, chat.Budget(150, 40))
    got = {r.conv_id: r for r in chat.digests(w).collect()}
    for c in {r[0] for r in rows}:
        own = sorted(((t, r or "", x or "") for k, t, r, x in rows if k == c))
        turns = "".join(f"{r}\n{x}\n" for _, r, x in own)
        loss = "".join(x for _, r, x in own if r == "assistant")
        assert (got[c].n_turns, got[c].turns_sha256) == (len(own), hashlib.sha256(turns.encode()).hexdigest())
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    for r in w.collect():
        turns = chat.read_back(r.formatted)
        assert r.n_tokens <= 150 or len(turns) - r.n_repeated == 1
        if r.conv_id is not None and r.conv_id % 3 == 0 and r.conv_id < 50:
            assert turns[0][0] == "system"
    assert chat.windows(df.limit(0)).count() == 0
    clash = df.withColumn("window", F.lit("clash")).withColumn("formatted", F.lit("clash"))
    assert sorted(chat.digests(chat.windows(clash, chat.Budget(150, 40))).collect(), key=str) == sorted(got.values(), key=str)
    words_only = chat.windows(df, chat.Budget(60, 10, lambda t: len(t.split())))
    assert {r.conv_id: r.turns_sha256 for r in chat.digests(words_only).collect()} == {k: r.turns_sha256 for k, r in got.items()}


# ---- 9: secrets ------------------------------------------------------------------------------


def duck(spark, table, df):
    c = duckdb.connect()
    c.register(table, df.toPandas())
    return c


def test_secrets_against_sql_and_python(spark):
    rng = random.Random(3)
    key = lambda n, s="ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/": "".join(rng.choice(s) for _ in range(n))
    texts = [None, "", "Password: short", f"é\U0001f600 API_KEY = '{key(20)}' token=secret=abcdef", "secret: token =abcdefgh", f"AKIA{key(16, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789')} AKIAAKIA", key(40, "0123456789abcdef"), f"x {key(60)} y", f"{key(60)}EXAMPLE", "123e4567-e89b-12d3-a456-426614174000", "internationalisation" * 3, "ab" * 40, f"{key(30)}{'a' * 200}{key(30)}", f"tokens and {key(36, '0123456789abcdefABCDEF')}"]
    texts += [f"{words(rng, 50)} {key(rng.randint(20, 80))} {words(rng, 20)}" for _ in range(30)] + [" ".join(f"token={key(12)}" for _ in range(700))]
    df = docs_of(spark, texts)
    found = secrets.scan(df)
    out = {r.doc_id: r for r in found.select("doc_id", *[F.size(k).alias(f"n_{k}") for k in ("assign", "access", "hex")], secrets.joined(F.col("base")).alias("base"), secrets.joined(F.concat("base", "added")).alias("spans")).collect()}
    want = duck(spark, "documents", df).sql(secrets.oracle()).fetchall()
    for doc, n0, n1, n2, sha, spans in want:
        r = out[doc]
        assert (r.n_assign, r.n_access, r.n_hex, r.spans) == (n0, n1, n2, spans) and hashlib.sha256(r.base.encode()).hexdigest() == sha
    kinds = (("assign", re.compile(secrets.ASSIGN, re.ASCII)), ("access", re.compile("AKIA[A-Z0-9]+")), ("hex", re.compile("[0-9a-f]+")))
    for doc, text in enumerate(texts):
        spans = []
        for rank, (kind, p) in enumerate(kinds):
            for m in p.finditer(text or ""):
                if {"assign": rank == 0 and len(m[2]) >= 6, "access": len(m[0]) >= 20, "hex": len(m[0]) >= 24}[kind]:
                    spans.append((m.start(), rank, f"{kind}:{m.start()}:{m.end()}"))
        assert out[doc].base == ",".join(x[2] for x in sorted(spans))
    assert "entropy_base64" in out[7].spans and out[8].spans == "" == out[9].spans == out[10].spans and out[11].spans == "hex:0:80"
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_secret_scan_is_linear(spark):
    """A run of 10^5 characters, and 10^4 matches of each kind in one text."""
    rng = random.Random(20)
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
    run = "".join(rng.choice(letters) for _ in range(100_000))
    many = " ".join(f"token={''.join(rng.choice(letters) for _ in range(30))}" for _ in range(10_000))
    mixed = " ".join("".join(rng.choice(letters) for _ in range(30)) for _ in range(5_000))
    for text, most in ((run, 1), (many, 10_000), (mixed, 5_000), ("a_" * 50_000 + "b", 0), ("abcdef_" * 20_000, 0)):
        began = time.perf_counter()
        (r,) = secrets.scan(docs_of(spark, [text])).select(F.size("base").alias("b"), F.size("added").alias("a")).collect()
        assert time.perf_counter() - began < 30 and r.a + r.b <= most and (not most or r.a + r.b > 0.7 * most)


def test_secret_scan_edges(spark, odd):
    out = secrets.scan(odd.withColumn("base", F.lit("clash")).withColumn("assign", F.lit("clash")))
    assert out.count() == 6 and all(not r.base and not r.added for r in out.collect())
    assert secrets.scan(odd.limit(0)).count() == 0
    twice = docs_of(spark, ["secret=abcdef0123", "secret=abcdef0123"]).withColumn("doc_id", F.lit(7).cast("long"))
    assert [[(x.kind, x.start, x.end) for x in r.base] for r in secrets.scan(twice).collect()] == [[("assign", 0, 17)]] * 2
    half = docs_of(spark, ["id 1A2b3C4d5E6f7A8b9C0d1E2f30 end"])  # 26 digits in either case
    assert [x.kind for x in secrets.scan(half).collect()[0].added] == ["entropy_hex"]


# ---- 10: WARC --------------------------------------------------------------------------------


def test_archive_round_trip_and_oracle(spark):
    html = ["<p>é</p>", "", None, "<p>é</p>", "x" * 5000, "<p>é</p>\r\n\r\nWARC/1.1\r\n"]
    rows = [(k, f"http://a/{k}\nb" if k else None, h) for k, h in enumerate(html)] + [(4, "http://dup", "x" * 5000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("address", F.lit("clash"))
    archive = warc.write(pages)
    assert archive.payloads.count() == 4
    got = {(r.page_id, r.record_type, r.refers_to) for r in warc.index(archive).collect()}
    assert got == {(0, "revisit", 3), (1, "revisit", 2), (2, "response", None), (3, "response", None), (4, "response", None), (5, "response", None)}
    for r in warc.index(archive).collect():
        payload = (html[r.page_id] or "").encode()
        assert r.payload_digest == base64.b32encode(hashlib.sha1(payload).digest()).decode()
    for r in warc.records(archive).collect():
        ((fields, block),) = warc.parse(bytes(r.record))
        assert int(fields["Content-Length"]) == len(block) and block.startswith(b"HTTP/1.1 200 OK\r\n")
        if fields["WARC-Type"] == "response":
            assert block.partition(b"\r\n\r\n")[2] == (html[r.page_id] or "").encode()
    files = warc.warc_files(archive, 400)
    back = warc.read_warc(files).collect()
    assert len(back) == 7 and sum(r.record_type == "revisit" for r in back) == 2
    whole = b"".join(bytes(r.data) for r in files.collect())
    assert len(list(warc.parse(gzip.decompress(whole)))) == 7
    assert all(r.record_type == "response" for r in warc.index(warc.write(pages, min_bytes=10_000)).collect())
    assert warc.index(warc.write(pages.limit(0))).count() == 0


def test_records_are_rebuilt_and_damage_shows(spark):
    long = "x" * 3_000_000
    pages = spark.createDataFrame([(1, "u", long), (2, "u", long), (3, None, "y"), (None, "u", "y"), (3, None, "y")], "page_id long, url string, html string")
    archive = warc.write(pages)
    back = warc.rebuilt(archive).collect()
    html = {1: long, 2: long, 3: "y", None: "y"}
    assert len(back) == 5 and all(bytes(r.payload).decode() == html[r.page_id] for r in back)
    assert {(r.page_id, r.record_type, r.refers_to) for r in back} == {(1, "revisit", 2), (2, "response", None), (3, "response", None), (None, "revisit", 3)}
    bad = warc.Archive(archive.headers, archive.payloads.withColumn("payload", F.concat("payload", F.lit(b"!"))))
    with pytest.raises(Exception, match="does not fit its payload"):
        warc.rebuilt(bad).collect()
    short = warc.Archive(archive.headers.withColumn("header", F.regexp_replace(F.col("header").cast("string"), "(?s)(WARC/.*?Content-Length: )\\d+", "$117").cast("binary")), archive.payloads)
    with pytest.raises(Exception, match="does not fit its payload"):
        warc.rebuilt(short).collect()


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_oracles(spark, sf, name):
    c = duckdb.connect()
    for t in ("documents", "pages"):
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    got = registry.QUERIES[name](spark, sf)
    want = c.sql(registry.ORACLES[name])
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    key = lambda r: tuple((x is not None, x) for x in r)
    assert sorted(map(tuple, got.select(cols).collect()), key=key) == sorted(want.select(*cols).fetchall(), key=key)


# ---- the pipeline ----------------------------------------------------------------------------


def test_pipeline_against_brute_force(spark, sf):
    """Every stage on the whole table, each row decided by itself or by all pairs."""
    import corpus_pipeline
    import sentencepiece

    docs, labels, bench = (common.table(spark, sf, t) for t in ("documents", "labels", "benchmark"))
    voter = quality.fit(docs, labels)
    rows = {r.doc_id: r.text or "" for r in docs.collect()}
    left = {d: t for d, t in rows.items() if voter.scores([t])[0] >= 0.7}
    left = dict(lines_by_force(left.items()))
    ids = sorted(left)
    fps = np.array([simhash_by_force(left[d]) for d in ids], np.uint64)
    sets = []
    for d in ids:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), left[d]))
        sets.append({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))})
    root = list(range(len(ids)))
    for a in range(len(ids)):
        for b in range(a):
            if int(fps[a] ^ fps[b]).bit_count() <= 4 or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                root = [root[b] if x == root[a] else x for x in root]
    left = {ids[k]: left[ids[k]] for k in {root.index(r) for r in root}}
    plain = lambda t: " ".join(re.findall(r"\w+", t.lower()))
    items = [x for r in bench.collect() if (x := plain(r.text or ""))]
    held = {d for d, t in left.items() if any(f" {x} " in f" {plain(t)} " for x in items)}
    with open(pieces.MODEL, "rb") as f:
        sp = sentencepiece.SentencePieceProcessor(model_proto=f.read())
    got = {r.doc_id: list(r.ids) for r in corpus_pipeline.run(spark, sf).collect()}
    assert got.keys() <= left.keys() - held and len(left.keys() - held - got.keys()) <= len(held)  # others hold an item in part
    assert all(x == sp.encode(left[d]) for d, x in got.items()) and len(got) > 50


def test_pipeline_stages_on_odd_tables(spark, sf, odd):
    import corpus_pipeline

    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, odd, sf)
        assert out.columns == odd.columns, name
        assert out.count() <= 6 and stage(spark, odd.limit(0), sf).count() == 0, name
    last = corpus_pipeline.STAGES[-1][1]
    assert last(spark, odd, sf).count() == 6 and last(spark, odd.limit(0), sf).count() == 0


def test_pipeline_stages_keep_the_columns(spark, sf):
    import corpus_pipeline

    docs = common.table(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, sf)
        assert after.columns == docs.columns, name
        path = common.materialize(after, name)
        assert 0 < path.count() <= docs.count()
        docs = path
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert len(last) == docs.count() and all(r.parity for r in last)
    assert {r.doc_id for r in corpus_pipeline.run(spark, sf).collect()} == {r.doc_id for r in last}
