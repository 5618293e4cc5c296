"""Operators against brute-force versions on a fixture of awkward texts, and on the smallest tables."""

import hashlib
import itertools
import re
import zlib
from collections import Counter
from math import log10

import numpy as np
import pytest
import xxhash

from erfocus.llm import decontaminate, license_scan, line_dedup, lm_score, packing, quality, simhash, suffix_dedup, url_filter, warc

SPACE = re.compile(r"[\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
PASSAGE = " ".join(f"w{i * 7919 % 1000}x" for i in range(60))
LONG = " ".join(f"t{i * 104729 % 9973}" for i in range(30000))


def texts():
    base = " ".join(f"b{i * 31 % 89}" for i in range(120))
    return [
        (1, "One two three.\nOne two three.\n\nfour É ñ, five-six #$%"),
        (2, None),
        (3, ""),
        (4, " \t\n"),
        (5, base),
        (6, base),
        (7, base.replace("b7 ", "c7 ", 1)),
        (8, "lead in words here " + PASSAGE + " and then an end of its own"),
        (9, PASSAGE.upper() + " something else"),
        (10, LONG),
        (11, "a b"),
        (11, "a b"),
        (None, base),
        (12, "x" * 20000),
        (13, "line one is long enough to count\nmine alone 13"),
        (14, "Licensed under the Apache License, Version 2.0\nand more"),
        (15, "same same same same same same " * 12),
        (16, "\u00a0non breaking\u2003spaces\x1cseparator"),
        (17, "one <|endoftext|> two<|endoftext|>"),
    ]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["en", "fr", None][k % 3], f"s{k % 12}", k, "clash") for k, (i, t) in enumerate(texts())]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_words int, component_id string").repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("1 = 0")


@pytest.fixture(scope="module")
def sf(spark, small):
    return lambda name: spark.read.parquet(f"{small}/{name}.parquet")


def rows(df):
    return Counter(tuple(map(str, r)) for r in df.collect())


def words(text):
    return [w for w in SPACE.split((text or "")) if w]


def alnum(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOWER))


# 1: decontamination


def brute_hits(text, items, n=10):
    ws = alnum(text)
    hit, found = set(), set()
    for item, t in items:
        iw = alnum(t)
        k = min(n, len(iw))
        grams = {tuple(iw[i : i + k]) for i in range(len(iw) - k + 1)} if k else set()
        for i in range(len(ws) - k + 1) if k else ():
            if tuple(ws[i : i + k]) in grams:
                hit |= set(range(i, i + k))
                found.add(item)
    return len(ws), len(hit), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit)


ITEMS = [(1, "w791x w710x w629x"), (2, PASSAGE[:150]), (2, PASSAGE[:150]), (30, "five SIX"), (4, None), (5, ""), (6, "and then an end"), (7, "b5 " * 12)]


@pytest.mark.parametrize("block", [32 << 20, 100])
def test_decontamination_brute_force(spark, docs, block):
    bench = spark.createDataFrame([(i, t, "x") for i, t in ITEMS], "item_id long, text string, doc_id string")
    got = rows(decontaminate.digest(decontaminate.scan(docs, bench, max_block_bytes=block)))
    want = Counter(tuple(map(str, (i, *brute_hits(t, ITEMS)))) for i, t in texts())
    assert got == want


def test_decontamination_removes_documents_or_spans(spark, docs):
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    kept = decontaminate.decontaminate(docs, bench)
    clean = Counter(str(i) for i, t in texts() if not brute_hits(t, ITEMS)[1])
    assert Counter(str(r.doc_id) for r in kept.collect()) == clean and kept.columns == docs.columns
    cut = decontaminate.decontaminate(docs, bench, mode="span")
    assert cut.count() == len(texts())
    by = {r.doc_id: r.text for r in cut.collect()}
    assert by[8].startswith("lead in words here") and len(by[8]) < len(dict(texts())[8])


@pytest.mark.parametrize("block", [32 << 20, 80])
def test_spans_are_cut_alike_in_blocks(spark, block):
    ws = [f"w{i}" for i in range(40)]
    items = [(k, " ".join(ws[a:b])) for k, (a, b) in enumerate([(0, 12), (5, 16), (10, 20), (14, 25), (15, 30)])]
    bench = spark.createDataFrame(items, "no long, body string")
    df = spark.createDataFrame([(1, " ".join(ws), "k"), (2, None, "k"), (3, "", "k"), (1, "w1 w2", "k")], "doc_id long, text string, __key string")
    cut = decontaminate.decontaminate(df, bench, "span", item_col="no", item_text="body", max_block_bytes=block)
    assert cut.columns == df.columns and Counter(r.text for r in cut.collect()) == Counter([" " + " ".join(ws[30:]), None, "", "w1 w2"])


@pytest.mark.parametrize("kind", ["decimal(20,2)", "date", "tinyint", "string", "binary", "timestamp", "double"])
def test_ids_of_any_type(spark, kind):
    df = spark.createDataFrame([(k, PASSAGE + f" own {k}") for k in range(3)], "k long, text string")
    value = {"date": "date_add(date'2020-01-01', int(k))", "timestamp": "timestamp_seconds(k)", "binary": "encode(string(k), 'utf-8')"}.get(kind, f"cast(k as {kind})")
    df = df.selectExpr(f"{value} AS doc_id", "text")
    bench = df.selectExpr("doc_id AS item_id", "text")
    found = decontaminate.scan(df, bench).collect()
    assert all(sorted(map(str, r["items"])) == sorted(str(x.doc_id) for x in df.collect()) for r in found)
    assert suffix_dedup.repeated_spans(df).schema["doc_id"].dataType == df.schema["doc_id"].dataType and suffix_dedup.repeated_spans(df).count() == 3
    packed = packing.pack(df)
    assert packed.schema["doc_id"].dataType == df.schema["doc_id"].dataType and {str(r.doc_id) for r in packed.collect()} == {str(r.doc_id) for r in df.collect()}


# 2: SimHash


def brute_fp(text, width=3):
    ws = [w for w in SPACE.split((text or "").translate(LOWER)) if w]
    if not ws:
        return 0
    grams = [" ".join(ws[i : i + width]) for i in range(max(1, len(ws) - width + 1))]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(pairs, radius):
    fps = sorted({f for _, f in pairs})
    parent = {f: f for f in fps}

    def root(f):
        while parent[f] != f:
            f = parent[f]
        return f

    for a, b in itertools.combinations(fps, 2):
        if (a ^ b).bit_count() <= radius:
            parent[root(a)] = root(b)
    least = {}
    for i, f in pairs:
        if i is not None:
            least[root(f)] = min(i, least.get(root(f), i))
    return Counter((str(i), f"{f:016x}", str(least.get(root(f)))) for i, f in pairs)


def test_simhash_brute_force(docs, sf):
    small = [(r.doc_id, r.text) for r in sf("documents").collect()]
    for df, own in ((docs, texts()), (sf("documents"), small)):
        want = brute_components([(i, brute_fp(t)) for i, t in own], 2)
        assert rows(simhash.near_duplicates(df)) == want


def test_spark_hash_is_the_contract_hash(spark):
    assert spark.sql("select xxhash64('a b c')").first()[0] == int(np.uint64(xxhash.xxh64_intdigest("a b c", 42)).view(np.int64))


def sketch(f, bands=3):
    return int(np.uint64(f).view(np.int64)), f.to_bytes(8, "big"), f.bit_count(), simhash.band_keys(f, bands)


def test_tile_pairs_beyond_the_radius_are_skipped(spark):
    rng = np.random.default_rng(2)
    low = 0x155555
    fps = sorted({(int(sum(1 << int(b) for b in rng.choice(41, int(rng.integers(0, 42)), replace=False))) << 22 | low) for _ in range(400)})
    rows_ = spark.createDataFrame([(i, *sketch(f)) for i, f in enumerate(fps)], f"doc_id long, {simhash.SCHEMA}")
    dealt = rows_.selectExpr("node", "fp", "pop", "keys[0] AS key")
    placed = simhash._placed(dealt, 16, 2)
    tasks = {(r.p, r.q) for r in placed.select("p", "q").distinct().collect()}
    parts = 1 + max(q for _, q in tasks)
    assert parts > 20 and len(tasks) < 0.4 * parts * (parts + 1) / 2
    met = {}
    for r in placed.collect():
        met.setdefault((r.p, r.q), set()).add(r.node)
    near = [(a, b) for a, b in itertools.combinations(fps, 2) if (a ^ b).bit_count() <= 2]
    signed = lambda f: int(np.uint64(f).view(np.int64))
    assert near and all(any(signed(a) in m and signed(b) in m for m in met.values()) for a, b in near)


@pytest.mark.parametrize("tile", [8, 64, 4096])
def test_tiles_lose_no_link(spark, tile):
    rng = np.random.default_rng(1)
    seeds = rng.integers(0, 1 << 62, 40, dtype=np.uint64)
    fps = {0, *(int(s) for s in seeds)}
    for s in seeds[:12]:
        x = int(s)
        for _ in range(40):
            x ^= 1 << int(rng.integers(0, 62))
            fps.add(x)
    pairs = list(enumerate(sorted(fps)))
    sketches = spark.createDataFrame([(i, *sketch(f)) for i, f in pairs], f"doc_id long, {simhash.SCHEMA}")
    found = simhash.labelled(sketches, simhash.linked(sketches, 2, tile))
    got = Counter((str(r.doc_id), r.fp.hex(), str(r.component_id)) for r in found.collect())
    assert got == brute_components(pairs, 2)


def test_one_of_each_keeps_a_row_of_each_group(docs, spark):
    kept = simhash.one_of_each(docs)
    ids = Counter(r.doc_id for r in kept.collect())
    assert ids[5] == 1 and ids[6] == 0 and ids[7] == 0 and ids[11] == 1 and ids[None] == 1
    assert ids[2] == ids[3] == ids[4] == ids[8] == ids[10] == 1 and kept.columns == docs.columns


def test_one_of_each_finds_similar_texts(spark):
    rng = np.random.default_rng(7)
    rowsets, n = [], 0
    for g in range(60):
        ws = [f"v{g}_{int(x)}" for x in rng.integers(0, 5000, int(rng.integers(60, 400)))]
        rowsets.append((n, " ".join(ws)))
        other = list(ws)
        other[len(ws) // 2] = "changed"
        rowsets.append((n + 1, " ".join(other)))
        n += 2
    df = spark.createDataFrame(rowsets, "doc_id long, text string")
    left = {r.doc_id for r in simhash.one_of_each(df).collect()}
    assert left == set(range(0, n, 2))


def brute_left(own, width=5, least=0.8):
    sets = {i: {tuple(t.split()[k : k + width]) for k in range(len(t.split()) - width + 1)} for i, t in own}
    label = {i: i for i in sets}
    for a, b in itertools.combinations(sets, 2):
        if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]) and label[a] != label[b]:
            old, new = max(label[a], label[b]), min(label[a], label[b])
            label = {i: new if x == old else x for i, x in label.items()}
    return {i for i, x in label.items() if i == x}


def test_one_of_each_links_by_exact_similarity(spark):
    rng = np.random.default_rng(11)
    own = []
    for g in range(40):
        base = [f"u{g}_{i}" for i in range(200)]
        for _ in range(5):
            ws = list(base)
            for k in rng.choice(200, int(rng.integers(1, 7)), replace=False):
                ws[k] = f"x{len(own)}_{k}"
            own.append((len(own), " ".join(ws)))
    # Of the same multiset majority, but for the most part of other words.
    own += [(900 + k, "again " * 400 + " ".join(f"y{k}_{i}" for i in range(30))) for k in range(2)]
    df = spark.createDataFrame(own, "doc_id long, text string")
    left = {r.doc_id for r in simhash.one_of_each(df).collect()}
    want = brute_left(own)
    assert left == want and {900, 901} <= left and 40 < len(want) < 200


def test_recall_of_the_stage_at_the_threshold(spark):
    rng = np.random.default_rng(21)
    own, n = [], 0
    for g in range(150):
        base = [f"q{g}_{i}" for i in range(int(rng.integers(60, 500)))]
        m = len(base) - 4
        ws, k = list(base), 0
        while True:  # shingles changed until the similarity would fall under 0.8
            ws[int(rng.integers(0, len(ws)))] = f"z{g}_{k}"
            k += 1
            a, b = ({tuple(x[i : i + 5]) for i in range(m)} for x in (base, ws))
            if len(a & b) < 0.8 * len(a | b):
                break
            last = list(ws)
        own += [(n, " ".join(base)), (n + 1, " ".join(last))]
        n += 2
    left = {r.doc_id for r in simhash.one_of_each(spark.createDataFrame(own, "doc_id long, text string")).collect()}
    found = sum(k + 1 not in left for k in range(0, n, 2))
    assert found >= 0.98 * n / 2 and all(k in left for k in range(0, n, 2))


@pytest.mark.parametrize("tile", [2048, 3])
def test_verified_links_in_parts(spark, tile):
    base = [f"u{i}" for i in range(300)]
    own = [(k, " ".join([*base[: 10 * k], *(f"z{k}_{i}" for i in range(4)), *base[10 * k + 4 :]])) for k in range(12)] + [(20, " ".join(base[:200]))]
    df = spark.createDataFrame(own, "doc_id long, text string")
    sketches = simhash.minhash_sketches(df, width=5)
    links = simhash.verified(df, sketches, simhash.linked(sketches, 64), "doc_id", "text", 5, 64, 0.8, tile)
    found = simhash.labelled(sketches, links).where("doc_id = component_id").collect()
    assert {r.doc_id for r in found} == brute_left(own) == {0, 20}


# 3: line dedup


def test_line_dedup_removes_wide_lines(spark):
    wide = "this line is the footer of many sites"
    data = [(i, f"own text number {i} of this document goes on for a while\n{wide}\nshort", f"s{i % 15}") for i in range(30)]
    data += [(90, None, "s1"), (91, "", "s2"), (92, wide, None), (93, wide + "\n" + wide, "s3")]
    df = spark.createDataFrame(data, "doc_id long, text string, source string")
    got = {r.doc_id: r for r in line_dedup.line_report(df).collect()}
    assert all(got[i].cleaned_text == data[i][1].replace(wide + "\n", "") and got[i].n_removed == 1 for i in range(30))
    assert got[90].cleaned_text is None and got[90].n_lines == 0 and got[91].cleaned_text == "" and got[92].cleaned_text == wide and got[93].n_boilerplate == 2 and got[93].n_removed == 0
    out = line_dedup.without_boilerplate(df)
    assert out.columns == df.columns and out.count() == df.count()


def test_stages_keep_columns_of_any_name(spark, sf):
    names = "__id long, __key string, __keys string, n_lines int, n_boilerplate int, __strip int, __new int, __row int, __stratum string, __n_lines int, hit int"
    data = [(i, f"own {i}\nthis line is the footer of many sites\n" + " ".join(f"w{i}_{k}" for k in range(60)), f"s{i % 15}", "en", i, "a", "b", 1, 2, 3, 4, 5, "c", 6, 7) for i in range(30)]
    df = spark.createDataFrame(data, f"doc_id long, text string, source string, lang string, {names}")
    bench = sf("benchmark")
    for out in (line_dedup.without_boilerplate(df), quality.kept_documents(df, sf("labels")), simhash.one_of_each(df), decontaminate.decontaminate(df, bench), decontaminate.decontaminate(df, bench, "span", max_block_bytes=100)):
        assert out.columns == df.columns
        assert Counter(map(str, out.drop("text").collect())) == Counter(map(str, df.drop("text").collect()))


def test_without_boilerplate_takes_short_lines_and_any_share(spark):
    wide = "this line is the footer of many sites"
    data = [(i, f"own {i}\n{wide}\nmore\n\n{wide}", f"s{i % 15}") for i in range(30)]
    data += [(90, None, "s1"), (91, "", "s2"), (92, f"{wide}\n \nmore", "s3"), (93, "rare\n more ", "s4")]
    df = spark.createDataFrame(data, "doc_id long, text string, source string")
    got = {r.doc_id: r.text for r in line_dedup.without_boilerplate(df).collect()}
    assert all(got[i] == f"own {i}\n" for i in range(30))
    assert got[90] is None and got[91] == "" and got[92] == data[32][1] and got[93] == "rare"


def test_line_dedup_counts_exactly_near_the_threshold(spark):
    line = "exactly as many sites as it is given here"
    for n in (9, 10, 11):
        data = [(i, f"own text number {i} of this document goes on for a while\n{line}", f"s{i}") for i in range(n)]
        df = spark.createDataFrame(data, "doc_id long, text string, source string")
        assert {r.n_removed for r in line_dedup.line_report(df).collect()} == {int(n >= 10)}


@pytest.mark.parametrize("limit", [0, 1 << 30])
def test_line_dedup_joins_alike_beyond_the_broadcast(spark, sf, monkeypatch, limit):
    monkeypatch.setattr(line_dedup, "MAX_BROADCAST_BYTES", limit)
    wide = "this line is the footer of many sites"
    df = spark.createDataFrame([(i % 25, f"own {i}\n{wide}", f"s{i % 15}") for i in range(30)], "doc_id long, text string, source string")
    assert Counter(r.text for r in line_dedup.without_boilerplate(df).collect()) == Counter(f"own {i}" for i in range(30))


def test_line_dedup_is_one_plan_of_built_ins(docs):
    plan = line_dedup.line_report(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan


# 4: LM scoring


def brute_base(own):
    token = lambda t: [*(t or "").translate(LOWER).encode().split(), b"\0end"]
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 5 == 1
    c = Counter(w for i, t in own if not held(i) for w in token(t))
    n, v = sum(c.values()), len(c)
    out = []
    for i, t in own:
        ws = token(t)
        out.append((i, held(i), len(ws), sum(c[w] > 0 for w in ws), n, sum(log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws)))
    return out


@pytest.mark.parametrize("block", [256 << 20, 20_000])
def test_lm_base_brute_force(docs, sf, block):
    small = [(r.doc_id, r.text) for r in sf("documents").collect()]
    for df, own in ((docs, texts()), (sf("documents"), small)):
        model = lm_score.train(df.where(~lm_score.held_out("doc_id")))
        got = lm_score.score(df, model, block_bytes=block).collect()
        key = lambda r: (str(r[0]), r[2], round(r[5], 3))
        want = sorted(brute_base(own), key=key)
        have = sorted([tuple(r)[:6] for r in got], key=key)
        assert [w[:5] for w in want] == [h[:5] for h in have]
        assert np.allclose([w[5] for w in want], [h[5] for h in have])
        assert all(r.score < 0 for r in got)
        if df is not docs:
            out = [r for r in got if r.held_out]
            assert sum(r.score for r in out) > sum(r.base_score for r in out)


def brute_score(own, strength=lm_score.STRENGTH):
    """The model's log probability with bigram counts rounded down to their levels, without false positives."""
    token = lambda t: [*(t or "").translate(LOWER).encode().split(), b"\0end"]
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 5 == 1
    c, pairs = Counter(), Counter()
    for i, t in own:
        if not held(i):
            ws = token(t)
            c.update(ws)
            pairs.update(zip([b"\0end", *ws], ws, strict=False))
    n, v = sum(c.values()), len(c)
    share = lambda w: (c[w] + 0.5) / (n + 0.5 * (v + 1))
    low = lambda k: lm_score.LEAST[lm_score.level(np.array([k]))[0]] if k else 0.0
    p = lambda a, b: (low(pairs[a, b]) + strength * share(b)) / (c[a] + strength)
    sums = {a: sum(p(a, b) for b in c) + strength * 0.5 / (n + 0.5 * (v + 1)) / (c[a] + strength) for a in list(c)[:20]}
    return [sum(log10(p(a, b)) for a, b in zip([b"\0end", *token(t)], token(t), strict=False)) for _, t in own], sums


def test_lm_score_is_a_log_probability(spark, docs, sf):
    small = [(r.doc_id, r.text) for r in sf("documents").collect()]
    for df, own in ((docs, texts()), (sf("documents"), small)):
        for block in (256 << 20, 20_000):
            got = lm_score.score(df, lm_score.train(df.where(~lm_score.held_out("doc_id"))), block_bytes=block).collect()
            want, sums = brute_score(own)
            have = sorted(r.score for r in got)
            # A false positive can only raise a probability, and few are; after any word all words' add up to one at most.
            assert all(h <= 0 for h in have) and max(sums.values()) <= 1 + 1e-9
            gaps = np.array(have) - np.array(sorted(want))
            assert gaps.min() > -1e-6 and gaps.sum() < 0.03 * -sum(want)
    twice = spark.createDataFrame([(k, "a b") for k in range(1000)], "doc_id long, text string")
    assert all(r.score <= 0 for r in lm_score.score(twice, lm_score.train(twice)).collect())


def test_lm_levels_hold_counts():
    rng = np.random.default_rng(0)
    keys = np.unique(rng.integers(0, 1 << 63, 20000, dtype=np.uint64))
    counts = rng.geometric(0.3, len(keys)) * rng.choice([1, 40], len(keys))
    bits = lm_score.filter_bits(keys, counts)
    block = lm_score.Block(6, 0, np.zeros(64, dtype=np.int64), np.full(64, 8 * len(bits)), bits, np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64))
    found = block.counted(keys)
    assert (found >= lm_score.LEAST[lm_score.level(counts)]).all() and (lm_score.LEAST[lm_score.level(counts)] <= counts).all()
    assert (found == lm_score.LEAST[lm_score.level(counts)]).mean() > 0.95
    other = block.counted(np.setdiff1d(rng.integers(0, 1 << 63, 20000, dtype=np.uint64), keys))
    assert (other > 0).mean() < 0.05


# 5: URL filter


def split_url(url):
    _, found, rest = (url or "").partition("://")
    if not found:
        return "", ""
    host = re.match(r"[^/?#]*", rest)[0]
    return host.translate(LOWER), re.match(r"[^?#]*", rest[len(host) :])[0]


def brute_verdict(url, rules):
    host, path = split_url(url)
    fits = [r for r in rules if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    if not fits:
        return host, path, None, "allow"
    best = max(fits, key=lambda r: (len(r.text), len(r.host), r.action == "block"))
    return host, path, best.text, best.action


def test_url_rules_brute_force(spark):
    urls = [None, "", "no scheme", "http://NET", "http://net/", "http://x.NET/a?b#c", "https://example.net/en/q", "https://a.example.net/en", "http://b.example.com/de/x", "ftp://org/fr/", "http://xnet/", "http://a.org?fr/", "https://d.org/fr/a://b"]
    data = [(i, u, "n") for i, u in enumerate(urls * 2)] + [(None, "http://a.net/", "n")]
    df = spark.createDataFrame(data, "page_id long, url string, host string")
    got = rows(url_filter.judge(df))
    assert got == Counter(tuple(map(str, (i, *brute_verdict(u, url_filter.RULES)))) for i, u, _ in data)


@pytest.mark.parametrize("shard", [4 << 20, 100])
def test_cascade_is_exact_for_every_key(spark, shard):
    rng = np.random.default_rng(3)
    names = [f"h{i}.s{i % 40}.example" for i in range(3000)]
    rules = tuple(url_filter.Rule(str(rng.choice(["block", "allow"])), n, "/") for n in names[::7])
    rules += (url_filter.Rule("allow", "s3.example", "/p"), url_filter.Rule("block", "s3.example", "/p"), url_filter.Rule("block", "h7.s7.example", "/"))
    df = spark.createDataFrame([(i, f"http://{n}/p") for i, n in enumerate(names)], "page_id long, url string")
    table = url_filter.rule_table(df, rules)
    rows_ = url_filter.keyed(df, url_filter.shape(table), "page_id", "url")
    assert len(url_filter.build(rows_, table, 0, 1, 3000).levels) > 1
    want = Counter(tuple(map(str, (i, *brute_verdict(f"http://{n}/p", rules)))) for i, n in enumerate(names))
    assert rows(url_filter.judge(df, rules, shard_keys=shard)) == want == rows(url_filter.judge(df, table, shard_keys=shard))


def test_url_plan_splits_with_built_ins(sf):
    plan = url_filter.judge(sf("pages"))._jdf.queryExecution().toString()
    assert "MapInPandas" not in plan and "PythonUDF" not in plan and "Join" not in plan


# 6: packing


def test_packing_round_trip(docs, spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = Counter((i, tuple([*t.encode(x or "", add_special_tokens=False).ids, 1])) for i, x in texts())
    found = packing.pack(docs, with_ids=True).collect()
    sequences = {}
    for r in found:
        assert len(r.ids) == r.length and zlib.crc32(np.array(r.ids, dtype="<u4").tobytes()) == r.ids_crc32
        sequences.setdefault(r.sequence_id, []).append(r)
    for own in sequences.values():
        at = 0
        for r in sorted(own, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048 and at & (at - 1) == 0
    by = {}
    for r in found:
        by.setdefault((r.doc_id, r.doc_tokens), []).append(r)
    for (doc, n), pieces in by.items():
        copies = sum(v for (i, ids), v in want.items() if i == doc and len(ids) == n)
        assert sum(p.length for p in pieces) == n * copies
        if copies == 1:
            ids = [x for p in sorted(pieces, key=lambda p: p.start) for x in p.ids]
            assert (doc, tuple(ids)) in want


def test_encoder_gives_the_tokenizers_ids(sf):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    samples = [r.text for r in sf("documents").collect()] + [r.html for r in sf("pages").collect()] + ["<|endoftext|> a\r\n\t  b  ", "a  <|endoftext|><|endoftext|>\n\n x <|endoftext", "is <|endoftext|>", "  x'S 12345  \n\n", "日本語 текст 🙂🙂", "\u00a0\u2003a"]
    for x, ids in zip(samples, packing.encode(samples), strict=True):
        assert t.encode(x, add_special_tokens=False).ids == ids[:-1].tolist()


def test_hilbert_neighbours_touch():
    side = 8
    grid = np.array(list(itertools.product(range(side), repeat=3)))
    order = grid[np.argsort(packing.hilbert_key(grid, 3))]
    assert (np.abs(np.diff(order, axis=0)).sum(axis=1) == 1).all()


# 7: suffix arrays


def brute_spans(own, n=50):
    where = {}
    split = {k: (i, (t or "").translate(LOWER).encode().split()) for k, (i, t) in enumerate(own) if i is not None}
    for k, (i, ws) in split.items():
        for p in range(len(ws) - n + 1):
            where.setdefault(tuple(ws[p : p + n]), set()).add(i)
    out = set()
    for k, (i, ws) in split.items():
        last = None
        for p in range(len(ws) - n + 1):
            if len(where[tuple(ws[p : p + n])]) > 1:
                if last and p <= last[1]:
                    last[1] = p + n
                else:
                    if last:
                        out.add((i, *last))
                    last = [p, p + n]
        if last:
            out.add((i, *last))
    return out


@pytest.mark.parametrize(("live", "group"), [(8 << 20, 2048), (3, 2048), (8 << 20, 1), (3, 3)])
def test_repeated_spans_brute_force(docs, sf, live, group):
    small = [(r.doc_id, r.text) for r in sf("documents").collect()]
    for df, own in ((docs, texts()), (sf("documents"), small)):
        got = {(r.doc_id, r.start_word, r.end_word) for r in suffix_dedup.repeated_spans(df, max_live=live, group=group).collect()}
        assert got == brute_spans(own) and got


@pytest.mark.parametrize("parts", [1, 5])
def test_hot_windows_are_settled_in_and_between_tasks(spark, parts, monkeypatch):
    rng = np.random.default_rng(6)
    core = [f"c{i}" for i in range(120)]
    own = [(k, " ".join([*core[: 60 + k % 3], *(f"e{k}_{i}" for i in range(5)), *core[60 + k % 3 :]])) for k in range(40)] + [(k % 7 + 50, " ".join(core)) for k in range(14)]
    own += [(90, " ".join(core[:49])), (91, " ".join([*core[:50]] * 2)), (91, " ".join(core[20:75]))]
    rng.shuffle(own)
    df = spark.createDataFrame([(int(i), t) for i, t in own], "doc_id long, text string").repartition(parts)
    got = {(r.doc_id, r.start_word, r.end_word) for r in suffix_dedup.repeated_spans(df, group=1).collect()}
    assert got == {(r.doc_id, r.start_word, r.end_word) for r in suffix_dedup.repeated_spans(df).collect()}
    one = [(int(i), t) for i, t in own if [x for x, _ in own].count(i) == 1]
    some = df.where(df.doc_id.isin([i for i, _ in one]))
    assert {(r.doc_id, r.start_word, r.end_word) for r in suffix_dedup.repeated_spans(some, group=1).collect()} == brute_spans(one)


def test_matches_extend_both_ways_in_neighbours(spark):
    rng = np.random.default_rng(5)
    core = [f"c{i}" for i in range(70)]
    own = []
    for k in range(60):
        a, b = sorted(rng.integers(0, 71, 2).tolist())
        own.append((k, " ".join([*(f"l{k}_{i}" for i in range(30)), *core[a:b], *(f"r{k}_{i}" for i in range(30))])))
    df = spark.createDataFrame(own, "doc_id long, text string")
    got = {(r.doc_id, r.start_word, r.end_word) for r in suffix_dedup.repeated_spans(df).collect()}
    assert got == brute_spans(own) and len(got) > 5


def test_suffixes_are_sorted_and_neighbours_compared():
    gram = np.array([1, 1, 1, 2], dtype=np.uint64)
    side = np.array([[5, 6, 7], [5, 6, 9], [4, 6, 7], [5, 6, 7]], dtype=np.uint64)
    order, shared = suffix_dedup.neighbours(gram, side, np.array([3, 3, 3, 3]))
    assert order.tolist() == [2, 0, 1, 3] and shared.tolist() == [-1, 0, 2, -1]


def test_words_of_equal_hashes_are_compared(monkeypatch):
    from erfocus.llm import textarrays as ta

    data = np.frombuffer(b"one two one six", dtype=np.uint8)
    w = ta.words(data, np.array([0, len(data)]), ta.NOT_SPACE)
    monkeypatch.setattr(ta, "word_hashes", lambda w: np.full(len(w.start), 7, dtype=ta.U))
    assert ta.distinct_hashes(w).tolist() == [1, 2, 1, 3]


# 8: licences


def test_license_scan(docs):
    got = {r.doc_id: r for r in license_scan.scan(docs).collect()}
    assert got[14].license == "Apache-2.0" and got[14].n_licensed == 1 and got[14].dice == 1.0
    assert got[1].license is None and got[2].n_licensed == 0 and got[3].n_licensed == 0


def brute_license(text, threshold=0.8):
    pieces = [p for p in re.split(r"\n", re.sub(r"([.;:!?])[\x20\x09-\x0D]+", r"\1\n", text or "")) if re.search("[0-9A-Za-z]", p)]
    best = {}
    for i in range(len(pieces)):
        for j in range(i + 1, len(pieces) + 1):
            words_ = re.findall("[0-9a-z]+", "\n".join(pieces[i:j]).translate(LOWER))
            grams = {f"{a} {b}" for a, b in itertools.pairwise(words_)}
            for k, (name, t) in enumerate(license_scan.TEMPLATES.items()):
                own = set(license_scan.bigrams_of(t))
                dice = 2 * len(grams & own) / (len(grams) + len(own))
                if dice >= threshold and len(words_) - 1 <= 2 * license_scan._bounds(len(own), threshold)[1]:
                    best[name] = max(best.get(name, (0, 0)), (dice, -k))
    if not best:
        return 0, None, None
    name = max(best, key=lambda n: best[n])
    return len(best), name, round(best[name][0], 6)


def test_license_runs_brute_force(spark):
    own = " ".join(f"word{i}" for i in range(40))
    texts_ = license_scan.TEMPLATES
    wrap = lambda t, n: "\n".join(" * " + " ".join(t.split()[i : i + n]) for i in range(0, len(t.split()), n))
    data = [own, None, "", f"{own}. {texts_['MIT']} {own}.", f"{own}\n{wrap(texts_['Apache-2.0-notice'], 9)}\n{own}", wrap(texts_["MIT-text"], 13), "MIT License\n\nCopyright (c) 2020 Someone\n\n" + texts_["MIT-text"]]
    data += [f"{own}\n{texts_['GPL-3.0-notice']}\nsee there", texts_["BSD-3-Clause-text"], texts_["MIT-first"].replace("deal", "trade"), "released under the mit license " * 2, texts_["CC-BY-NC-4.0"]]
    df = spark.createDataFrame(list(enumerate(data)), "doc_id long, text string")
    got = {r.doc_id: (r.n_licensed, r.license, r.dice) for r in license_scan.scan(df).collect()}
    assert got == {i: brute_license(t) for i, t in enumerate(data)}
    assert [got[i][1] for i in (0, 3, 4, 5, 6, 7, 8, 9, 11)] == [None, "MIT", "Apache-2.0-notice", "MIT-text", "MIT-text", "GPL-3.0-notice", "BSD-3-Clause-text", "MIT-first", "CC-BY-NC-4.0"]
    ties = license_scan.scan(df, templates={"a": "one two three", "b": "one two three"})
    assert ties.where("license IS NOT NULL").count() == 0
    both = license_scan.scan(spark.createDataFrame([(1, "One two three.")], "doc_id long, text string"), templates={"a": "one two three", "b": "one two three"}).first()
    assert (both.n_licensed, both.license, both.dice) == (2, "a", 1.0)


def test_license_bounds_lose_nothing():
    for n in range(1, 80):
        low, high = license_scan._bounds(n, 0.8)
        for b in range(1, 200):
            if 2 * min(b, n) / (b + n) >= 0.8:
                assert low <= b <= high


def test_license_plan_is_built_in(sf):
    plan = license_scan.scan(sf("documents"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Exchange" not in plan


# 9: WARC


def test_warc_round_trip(spark):
    big, other = "é" * 700, "x" * 999
    data = [(1, "http://a/\r\nb", big, 5), (2, None, big, 5), (3, "u", other, 5), (4, "u", other, 5), (5, "u", None, 5), (6, "u", "", 5), (None, "u", big, 5), (2, "v", big, 5)]
    df = spark.createDataFrame(data, "page_id long, url string, html string, payload_bytes int")
    got = rows(warc.round_trip(df))
    want = Counter()
    for i, _, h, _ in data:
        payload = (h or "").encode()
        revisit = h == big and i != 2
        want[tuple(map(str, (i, len(payload), hashlib.sha1(payload).hexdigest(), "revisit" if revisit else "response", 2 if revisit else None)))] += 1
    assert got == want


def test_warc_keeps_ids_of_any_text(spark):
    data = [("a\r\nb", "u", "x"), ("", "u", "y"), (None, "u", "z"), ("a:<b>%3A é", "u", "x"), ("a\r\nb", "u", "other"), ("z", "u", "p" * 1000), ("a\r\nb", "u", "p" * 1000)]
    df = spark.createDataFrame(data, "page_id string, url string, html string")
    got = warc.round_trip(df).collect()
    assert Counter(r.page_id for r in got) == Counter(i for i, _, _ in data)
    assert [(r.page_id, r.refers_to) for r in got if r.record_type == "revisit"] == [("a\r\nb", "z")]
    listed = warc.write(df, warc.shared_path(spark, "ids"))
    ids = [r.headers["WARC-Record-ID"] for p in listed.collect() for r in warc.records(iter([open(p.path.removeprefix("file:"), "rb").read()]))]
    assert len(set(ids)) == len(data)


def test_warc_reader_finds_damage():
    whole = warc.member(1, "u", b"payload") + warc.member(2, "u", b"more")
    assert [warc.page_of(r.headers["WARC-Record-ID"]) for r in warc.records(iter([whole[:50], whole[50:]]))] == ["1", "2"]
    for bad in (whole[:-3], zlib.compress(b"no header", wbits=31)):
        with pytest.raises(warc.DamagedRecord):
            list(warc.records(iter([bad])))
    head = b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 4\r\nWARC-Block-Digest: sha1:" + b"A" * 32 + b"\r\n\r\nabcd\r\n\r\n"
    with pytest.raises(warc.DamagedRecord):
        list(warc.records(iter([zlib.compress(head, wbits=31)])))


def test_warc_archives_rotate(spark, tmp_path):
    df = spark.createDataFrame([(i, "u", f"page {i}") for i in range(40)], "page_id long, url string, html string").coalesce(1)
    listed = warc.write(df, str(tmp_path / "w"), file_bytes=2000)
    assert listed.count() > 1 and warc.read(listed, with_payload=True).count() == 40
    assert not [p for p in (tmp_path / "w").iterdir() if not p.name.endswith(".warc.gz")]


# 10: quality rules


def brute_measures(text):
    ws = words(text)
    grams = [tuple(ws[i : i + 3]) for i in range(len(ws) - 2)]
    often = Counter(grams)
    covered = {i + k for i, g in enumerate(grams) if often[g] > 1 for k in range(3)}
    lines = [x for x in (text or "").split("\n") if words(x)]
    return len(ws), sum(map(len, ws)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_brute_force(docs, sf):
    small = [(r.doc_id, r.text) for r in sf("documents").collect()]
    for df, own in ((docs, texts()), (sf("documents"), small)):
        got = rows(quality.judge(df, sf("labels")).select("doc_id", *quality.MEASURES, "base_failed"))
        want = Counter()
        for i, t in own:
            m = brute_measures(t)
            want[tuple(map(str, (i, *m, m[0] < 50 or 100 * m[4] > 50 * m[0])))] += 1
        assert got == want


def test_quality_rejects_no_more_good_texts_than_stated(sf):
    kept = quality.judge(sf("documents"), sf("labels")).join(sf("labels"), "doc_id").where("quality = 1 AND NOT base_failed")
    n, gone = kept.count(), kept.where("NOT kept").count()
    assert gone <= 0.01 * n
    assert quality.kept_documents(sf("documents"), sf("labels")).columns == sf("documents").columns


def test_binomial_tail():
    from math import comb

    for n, p in ((10, 0.1), (200, 0.01)):
        for k in range(0, 5):
            assert abs(quality.tail(k, n, p) - sum(comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))) < 1e-9


def test_quality_method_rejects_labelled_bad_texts(spark):
    own = " ".join(f"word{i}" for i in range(60))
    data = [(i, f"{own} mine{i}", ["en", "de", "fr", "es"][i % 4]) for i in range(4 * 440)]
    data += [(10_000 + i, f"{own} {'#$%& ' * 30}", "en") for i in range(20)]
    docs = spark.createDataFrame(data, "doc_id long, text string, lang string")
    labels = docs.selectExpr("doc_id", "int(doc_id < 10000) AS quality")
    got = quality.judge(docs, labels).where("NOT kept").collect()
    assert {r.doc_id for r in got} == set(range(10_000, 10_020)) and not any(r.base_failed for r in got)


def test_quality_steps_are_of_bad_texts_and_counts_are_joint():
    rules = {"a": (1.0, 2.0), "b": (1.0, 2.0)}
    bad = {(2, 3): 5, (3, 1): 2, (3, 3): 1}
    assert quality.steps(bad, rules) == [("b", 2.0), ("a", 1.0)]
    assert quality.rejected(bad, {"a": 2, "b": 1}) == 7 and quality.rejected(bad, {"a": 0, "b": 0}) == 0


def test_cutoffs_hold_their_bound():
    counts = {("en", "symbol_share", c): (k, 5000) for c, k in ((0.4, 0), (0.2, 1), (0.1, 300), (0.05, 0), (0.02, 0))}
    chosen = quality.choose(counts, ["en"], rules={"symbol_share": quality.RULES["symbol_share"]})
    assert chosen == {("en", "symbol_share"): 0.2}
    assert quality.choose({}, ["en"]) == {}


# all


def test_empty_tables(spark, empty, sf):
    bench = sf("benchmark").where("1 = 0")
    labels = sf("labels").where("1 = 0")
    pages = sf("pages").where("1 = 0")
    model = lm_score.train(empty)
    for out in (
        decontaminate.digest(decontaminate.scan(empty, bench)),
        decontaminate.decontaminate(empty, bench),
        simhash.near_duplicates(empty),
        simhash.one_of_each(empty),
        line_dedup.line_report(empty),
        line_dedup.without_boilerplate(empty),
        lm_score.score(empty, model),
        url_filter.judge(pages),
        packing.pack(empty),
        suffix_dedup.repeated_spans(empty),
        license_scan.scan(empty),
        warc.round_trip(pages),
        quality.judge(empty, labels),
        quality.kept_documents(empty, labels),
    ):
        assert out.count() == 0


def test_no_model_and_no_items(spark, docs, sf):
    assert decontaminate.digest(decontaminate.scan(docs, sf("benchmark").where("1 = 0"))).where("contaminated").count() == 0
    assert lm_score.score(docs, lm_score.train(docs.where("1 = 0"))).where("n_known = 0 AND train_tokens = 0").count() == len(texts())
    assert url_filter.judge(sf("pages"), ()).where("verdict = 'allow' AND rule IS NULL").count() == sf("pages").count()


def brute_pipeline(own, items):
    """Stage by stage: {doc_id: text} kept, from (doc_id, text, source); without cutoffs, as a small table has none."""
    own = [(i, t, s) for i, t, s in own if (m := brute_measures(t))[0] >= 50 and 100 * m[4] <= 50 * m[0]]
    yield {i: t for i, t, _ in own}
    sites = {}
    for _, t, s in own:
        for x in t.split("\n"):
            if words(x):
                sites.setdefault(x.strip(" "), set()).add(s)
    hit = lambda x: len(sites.get(x.strip(" "), ())) >= 10
    cut = lambda t: "\n".join(x for x in t.split("\n") if not hit(x)) if any(words(x) and not hit(x) for x in t.split("\n")) else t
    texts_ = {i: cut(t) for i, t, _ in own}
    yield texts_
    sets = {i: {tuple(ws[k : k + 5]) for k in range(max(1, len(ws) - 4))} if (ws := words((t or "").translate(LOWER))) else set() for i, t in texts_.items()}
    label = {i: i for i in sets}
    for a, b in itertools.combinations([i for i in sets if sets[i]], 2):
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) and label[a] != label[b]:
            old, new = max(label[a], label[b]), min(label[a], label[b])
            label = {i: new if x == old else x for i, x in label.items()}
    texts_ = {i: t for i, t in texts_.items() if label[i] == i}
    yield texts_
    yield {i: t for i, t in texts_.items() if not brute_hits(t, items)[1]}


def test_pipeline_brute_force(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    own = [(r.doc_id, r.text, r.source) for r in docs.collect()]
    for (name, stage), want in zip(corpus_pipeline.STAGES[:-1], brute_pipeline(own, items), strict=True):
        docs = stage(spark, docs, small)
        assert {r.doc_id: r.text for r in docs.collect()} == want, name
    pieces = corpus_pipeline.run(spark, small).collect()
    assert {r.doc_id for r in pieces} == set(want) and 0 < len(want) < len(own)
    by = {}
    for r in pieces:
        by.setdefault(r.doc_id, []).append((r.start, r.length, r.doc_tokens))
    encoded = dict(zip(want, packing.encode(list(want.values())), strict=True))
    for i, parts in by.items():
        at = 0
        for start, length, total in sorted(parts):
            assert start == at and total == len(encoded[i])
            at += length
        assert at == len(encoded[i])


def test_pipeline(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, small)
        assert after.columns == docs.columns
        assert after.join(docs, "doc_id", "left_anti").count() == 0, name
        docs = after
    kept = {r.doc_id for r in docs.collect()}
    pieces = corpus_pipeline.run(spark, small).collect()
    assert {r.doc_id for r in pieces} == kept and 0 < len(kept) < before.count()
