"""The ten operators against brute force, on a small table and on odd inputs."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

WS = r"[^\x20\x09-\x0D]+"
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LONG = "lorem ipsum dolor " * 4000 + "tail 4111 1111 1111 1111 end"
ODD = [
    (1, "the quick brown fox jumps over the lazy dog near the river bank today"),
    (2, "the quick brown fox jumps over the lazy dog near the river bank today"),
    (2, "the quick brown fox jumps over the lazy dog near the river bank today"),
    (3, None),
    (4, ""),
    (5, " \n\t \r\n"),
    (6, "one"),
    (None, "no id at all but some words here"),
    (7, LONG),
    (8, "mail a@b.co, 10.0.0.1 and +1 (555) 555-0100\nAll rights reserved.\ntoken = \"9f86d081884c7d659a2feaa0c55ad015a3bf4f1b\""),
    (9, "é😀 ünïcode wörds 中文 " * 5),
]


def lower(t):
    return re.sub("[A-Z]", lambda m: m.group().lower(), t or "")


@pytest.fixture(scope="module")
def docs(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.fixture(scope="module")
def odd(spark):
    """Odd rows with columns whose names clash with outputs."""
    rows = [(i, t, "en", "x", 0, "clash", 1.0, "old") for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_words int, fingerprint string, score double, candidates string")


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


# ---- 1 near duplicates


def brute_fingerprint(t):
    import xxhash

    w = re.findall(WS, lower(t))
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else ([" ".join(w)] if w else [])
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(prints):
    ids, fps = zip(*prints, strict=True)
    parent = list(range(len(ids)))

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                parent[find(i)] = find(j)
    least = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(least.get(find(i), d), d)
    return {d: least[find(i)] for i, d in enumerate(ids)}


def test_fingerprints_and_components(spark, sf, docs):
    from joindash.llm.simhash import op1_simhash_near_dedup

    got = op1_simhash_near_dedup(spark, sf).collect()
    want = {i: brute_fingerprint(t) for i, t in docs.items()}
    assert {r.doc_id: r.fingerprint for r in got} == {i: f"{v:016x}" for i, v in want.items()}
    assert {r.doc_id: r.component_id for r in got} == brute_components(list(want.items()))


@pytest.mark.parametrize("unit", [8, 8192])
def test_trie_join_finds_every_link(spark, unit):
    from joindash.llm.simhash import SimHashParams, components, fingerprint_links

    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 63, 60, dtype=np.int64)
    out = [int(b) for b in base]
    for b in base[:20]:  # dense neighbourhoods, so that nodes overflow
        for _ in range(12):
            out.append(int(b) ^ sum(1 << int(k) for k in rng.integers(0, 63, rng.integers(1, 5))))
    values = sorted(set(out))
    df = spark.createDataFrame([(v,) for v in values], "fp long")
    label = {r.node: r.root for r in components(fingerprint_links(df, SimHashParams(unit_rows=unit))).collect()}
    want = brute_components([(v, v) for v in values])
    groups = lambda m: {frozenset(k for k in values if m.get(k, k) == g) for g in {m.get(k, k) for k in values}}
    assert groups(label) == groups(want)


def test_routes_undo(spark):
    from joindash.llm.simhash import Routes, SimHashParams

    for n in (100, 10**6, 10**9, 10**12):
        r = Routes.plan(n, SimHashParams())
        v = np.array([0x0123456789ABCDEF, 2**64 - 1, 0, 1 << 63], np.uint64)
        df = spark.createDataFrame([(int(x.view(np.int64)),) for x in v], "fp long")
        for k in (0, len(r.orders) - 1):
            p = np.array([x[0] for x in df.select(r.column(F.col("fp"), k)).collect()], np.int64).view(np.uint64)
            assert (r.undo(np.full(len(v), k), p) == v).all()


def test_the_walk_prunes_and_compares_only_single_values():
    from joindash.llm.simhash import trie_links

    rng = np.random.default_rng(5)
    values = np.unique(rng.integers(0, 1 << 63, 2000, dtype=np.int64).astype(np.uint64))
    near = values[:300] ^ np.uint64(1 << 40) ^ np.uint64(3)
    values = np.unique(np.concatenate([values, near]))
    at, root, seen = trie_links(values, np.array([0]), np.array([len(values)]), 3)
    assert {frozenset((int(values[i]), int(values[j]))) for i, j in zip(at, root, strict=True)} == {frozenset((int(a), int(a ^ np.uint64((1 << 40) + 3)))) for a in near}
    assert 0 < seen["single"] < len(values) ** 2 / 10 and seen["pruned"] > 0 and seen["visited"] >= seen["pruned"] + seen["single"]


def test_one_per_group_with_repeated_ids(spark):
    from joindash.llm.simhash import one_per_group

    a, b = "one text about nothing at all", "an entirely different sentence stands here"
    kept = lambda rows: sorted((r.doc_id, r.text) for r in one_per_group(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert kept([(5, a), (5, b)]) == sorted([(5, a), (5, b)])
    assert kept([(5, a), (5, b), (3, b)]) == [(3, b), (5, a)]
    assert kept([(5, a), (5, a), (5, a.upper())]) in ([(5, a)], [(5, a.upper())])


def test_one_per_group_keeps_one_row(odd):
    from joindash.llm.simhash import one_per_group

    kept = one_per_group(odd)
    ids = [r.doc_id for r in kept.collect()]
    assert ids.count(1) == 1 and 2 not in ids and ids.count(3) == 1 and 4 not in ids and 5 not in ids and ids.count(None) == 1
    assert kept.columns == odd.columns


# ---- 2 decontamination


def brute_hits(text, items, window=10):
    w, wins = WORD.findall(lower(text)), defaultdict(set)
    for i, t in items:
        x = WORD.findall(lower(t))
        for k in range(max(1, len(x) - window + 1) if x else 0):
            wins[tuple(x[k : k + window])].add(str(i))
    hit, found = np.zeros(len(w), bool), set()
    for n in {len(k) for k in wins}:
        for k in range(len(w) - n + 1):
            got = wins.get(tuple(w[k : k + n]))
            if got:
                hit[k : k + n] = True
                found |= got
    return len(w), int(hit.sum()), sorted(found)


def test_decontamination(spark, sf, docs):
    from joindash.llm.decontaminate import op2_benchmark_decontamination

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    for r in op2_benchmark_decontamination(spark, sf).collect():
        n, h, found = brute_hits(docs[r.doc_id], items)
        assert (r.n_words, r.n_hit, r.n_items, r.contaminated) == (n, h, len(found), h > 0)
        assert r.items_sha256 == hashlib.sha256(",".join(found).encode()).hexdigest()


@pytest.mark.parametrize("block", [1 << 20, 20])
def test_decontamination_odd_items(spark, odd, block):
    from joindash.llm.decontaminate import DecontamParams, find_contamination, remove_spans

    items = [(1, "lazy dog"), (2, "Fox jumps over"), (3, None), (4, "!!"), (5, "dolor lorem"), (6, "quick brown fox jumps over the lazy dog near the river"), (7, "中文 é"), (6, "lazy dog")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    found = find_contamination(odd, bench, p=DecontamParams(block_bytes=block, shard_words=3000))
    for r in remove_spans(found).collect():
        n, h, names = brute_hits(r.text, items)
        assert (r.n_words, sum(s.end - s.start for s in r.hit_spans), sorted(r.hit_items)) == (n, h, names)
        if h:
            assert len(WORD.findall(r.clean_text)) <= n - h + 1
        else:
            assert r.clean_text == r.text


def test_fm_index_counts_and_places():
    from joindash.llm.decontaminate import FMIndex

    rng = np.random.default_rng(0)
    for n, top in ((50, 2), (400, 3), (300, 40)):
        text = rng.integers(0, top + 1, n)
        text[-1] = 0
        index = FMIndex(text, 4)
        for size in (1, 2, 3, 5):
            pats = rng.integers(1, top + 1, (30, size))
            low, high = index.search(pats)
            for p, a, b in zip(pats, low, high, strict=True):
                want = [i for i in range(n - size + 1) if (text[i : i + size] == p).all()]
                assert sorted(index.locate(np.arange(a, b)).tolist()) == want


# ---- 3 licences


def test_licences(spark, sf, docs):
    from joindash.llm.licenses import TEMPLATES, op3_license_scan, template_words

    def brute(t):
        w, out = template_words(t or ""), []
        for name, text in sorted(TEMPLATES.items()):
            x = template_words(text)
            k, reach = min(5, len(x)), 1 << (len(x) - 1).bit_length()
            want = {" ".join(x[i : i + k]) for i in range(len(x) - k + 1)}
            sh = [" ".join(w[i : i + k]) for i in range(max(0, len(w) - k + 1))]
            if any(len(want & set(sh[a : a + 2 * reach - k + 1])) >= 0.8 * len(want) for a in range(0, len(sh), reach)):
                out.append(name)
        return ",".join(out)

    assert {r.doc_id: r.licenses for r in op3_license_scan(spark, sf).collect()} == {i: brute(t) for i, t in docs.items()}


def test_altered_notice_is_found(spark):
    from joindash.llm.licenses import TEMPLATES, scan_licenses

    words = TEMPLATES["mit-grant"].split()
    words[1] = "was"
    text = "before " * 300 + " ".join(words) + " after" * 300
    got = scan_licenses(spark.createDataFrame([(1, text), (1, text)], "doc_id long, text string")).collect()
    assert [[s.name for s in r.licenses] for r in got] == [["mit-grant"]] * 2


def test_short_templates_in_long_texts_are_found(spark):
    """A five-word line has one shingle against the twelve of its window; each line here lies in one window only."""
    from joindash.llm.licenses import LicenseParams, bands_needed, scan_licenses

    p = LicenseParams()
    assert (1 - 1 / 12) ** bands_needed(12, [1], p) <= p.miss and (1 - 4 / 29) ** bands_needed(28, [5], p) <= p.miss
    words = lambda i, k: " ".join(f"w{i}x{j}" for j in range(k))
    rows = [(i, f"{words(i, 40)} Released under the MIT License. {words(i + 10000, 40)}") for i in range(600)]
    got = scan_licenses(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert [r.doc_id for r in got if [x.name for x in r.licenses] != ["mit-line"]] == []


# ---- 4 sharding


def test_shards(spark, sf, docs):
    from joindash.llm.sharding import ShardParams, assign_shards, op4_hilbert_sharding, shard_boxes

    got = op4_hilbert_sharding(spark, sf).collect()
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r.slot)
        data = docs[r.doc_id].encode()
        assert (r["size"], r.text_crc32, r.law, r.grown_shard) == (len(data) + 16, zlib.crc32(data), "rows", None)
    assert sorted(by) == list(range(40)) and all(sorted(v) == list(range(len(v))) for v in by.values())
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    even = assign_shards(spark.read.parquet(f"{sf}/documents.parquet"), ["lang", "source"], p=ShardParams(shards=4, law="bytes"))
    boxes = {r.shard: r for r in shard_boxes(even, ["lang"]).collect()}
    total, most = sum(b.n_bytes for b in boxes.values()), max(len(t.encode()) for t in docs.values()) + 16
    assert all(abs(b.n_bytes - total / 4) <= most for b in boxes.values())


def test_equal_texts_stand_together(spark):
    from joindash.llm.sharding import assign_shards

    rng = np.random.default_rng(2)
    rows = [(i, f"text {i % 40}" if i % 4 else None, str(rng.choice(["de", "en", "fr"])), f"https://host/{rng.integers(9)}") for i in range(400)]
    df = spark.createDataFrame([*rows, (400, "", "en", None)], "doc_id long, text string, lang string, source string").repartition(6)
    got = sorted(assign_shards(df, ["lang", "source"]).collect(), key=lambda r: (r.shard, r.slot))
    runs = [r.text_crc32 for i, r in enumerate(got) if not i or got[i - 1].text_crc32 != r.text_crc32]
    assert len(got) == 401 and len(runs) == len(set(runs)) == 31


def test_string_cells_follow_whole_strings(spark):
    from joindash.llm.sharding import assign_shards, shard_boxes, string_cuts

    rng = np.random.default_rng(2)
    values = [f"https://www.example.org/{k:03d}" for k in range(100)]
    rows = [(i, f"t{i}", values[rng.integers(100)]) for i in range(2000)] + [(2000, "n", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(6)
    cuts = string_cuts(df, "source", 4)
    shares = np.diff([0, *[sum(v <= c for _, _, v in rows[:-1]) for c in cuts], 2000])
    assert len(cuts) == 3 and cuts == sorted(cuts) and (abs(shares - 500) < 40).all()
    assert string_cuts(df.limit(0), "source", 4) == [] and string_cuts(df.withColumn("source", F.lit("one")), "source", 4) in ([], ["one"])
    boxes = shard_boxes(assign_shards(df, ["source"]), ["source"]).collect()
    narrow = [b for b in boxes if b.min_source is not None and int(b.max_source[-3:]) - int(b.min_source[-3:]) < 50]
    assert len(narrow) > 30  # a filter on the source skips most shards


def test_hilbert_curve_steps_to_neighbours():
    import itertools

    from joindash.llm.sharding import hilbert_index

    for dims, bits in ((2, 4), (3, 3), (4, 2)):
        points = np.array(list(itertools.product(range(1 << bits), repeat=dims)))
        place = hilbert_index(points, bits)
        assert sorted(place) == list(range(len(points)))
        assert (np.abs(np.diff(points[np.argsort(place)], axis=0)).sum(1) == 1).all()


# ---- 5 quality classifier


def test_classifier_on_held_out_documents(spark):
    from joindash.llm.quality_classifier import op5_quality_classifier

    sf = "/root/testdata/sf0.01"
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    got = op5_quality_classifier(spark, sf).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == int(r.score >= 0.3) and 0 <= r.score <= 1 for r in got)
    held = [(labels[r.doc_id], r.predicted) for r in got if r.held_out and r.doc_id in labels]
    assert len(held) > 40 and np.mean([a == b for a, b in held]) >= 0.93


def test_scores_against_a_plain_version(spark, sf, docs):
    """Features word by word, then the network's formula, for every whole text of the table."""
    import math

    import zstandard

    from joindash.llm.quality_classifier import fit_quality, op5_quality_classifier

    frame = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    net, _ = fit_quality(frame, spark.read.parquet(f"{sf}/labels.parquet"))
    squeeze = zstandard.ZstdCompressor(level=3).compress

    def plain(t):
        data = (t or "").encode()
        words = [w.encode() for w in re.findall(WS, t or "")]
        if not words:
            return [0.0] * 22
        n, size, length = len(words), len(data), [len(w) for w in words]
        mean = sum(length) / n
        of = lambda chars: sum(b in chars for b in data)
        upper, lower_, symbols = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz", b"#*$%&|<>"
        letters, counts = of(upper + lower_), Counter(words)
        lines = (t or "").split("\n")
        full = [x for x in lines if re.search(WS, x)]
        windows, inside = Counter(tuple(words[k : k + 5]) for k in range(n - 4)), set()
        for k in range(n - 4):
            if windows[tuple(words[k : k + 5])] > 1:
                inside |= set(range(k, k + 5))
        return [
            math.log1p(n), mean, math.sqrt(sum((x - mean) ** 2 for x in length) / n), math.log1p(max(length)), of(upper) / letters if letters else 0.0, letters / size,
            of(b"0123456789") / size, of(symbols) / size, of(b"!") / size, of(b".,;:?") / size, max(counts.values()) / n, len(counts) / n,
            sum(words[k] == words[k + 1] for k in range(n - 1)) / n, sum(any(b in symbols for b in w) for w in words) / n,
            sum(w.isupper() and len(w) > 1 for w in words) / n, sum(not w.strip(b"|#*$%&<>!.,-") for w in words) / n, sum(x <= 3 for x in length) / n,
            (len(full) - len(set(full))) / len(lines), math.log1p(size / len(lines)), len(inside) / n, min(20.0, size / len(squeeze(data))), sum(b >= 128 for b in data) / size,
        ]

    for r in op5_quality_classifier(spark, sf).collect():
        z = np.clip((np.array(plain(docs[r.doc_id])) - net.mean) / net.scale, -8, 8)
        logit = sum(math.tanh(sum(z[i] * net.w1[i][j] for i in range(len(z))) + net.b1[j]) * net.w2[j] for j in range(len(net.b1))) + net.b2
        assert abs(r.score - 1 / (1 + math.exp(-max(-30, min(30, logit))))) < 1e-9
        assert r.predicted == int(r.score >= 0.3)


def test_held_out_without_an_id(spark, odd):
    from joindash.llm.quality_classifier import held_out

    assert {r.h for r in odd.filter("doc_id is null").select(held_out("doc_id").alias("h")).collect()} == {False}


def test_prior_estimate_and_risk():
    from joindash.llm.quality_classifier import PuParams, estimate_prior, learn

    rng = np.random.default_rng(2)
    pos, neg = rng.normal(1.5, 1, (2400, 5)), rng.normal(-1.5, 1, (400, 5))
    p = PuParams()
    assert abs(estimate_prior(pos[:800], np.vstack([pos[800:], neg]), p) - 0.8) < 0.15  # the least ratio leans low on small samples
    net, _ = learn(pos[:800], np.vstack([pos[800:], neg]), p)
    assert (net.scores(pos) >= 0.5).mean() > 0.9 and (net.scores(neg) < 0.5).mean() > 0.8


# ---- 6 quality rules


def test_quality_counts(spark, sf, docs, odd):
    from joindash.llm.quality_rules import op6_quality_rules, quality_rules

    def brute(t):
        t = t or ""
        w = re.findall(WS, t)
        c, m = Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4)), np.zeros(len(w), bool)
        for k in range(len(w) - 4):
            if c[tuple(w[k : k + 5])] > 1:
                m[k : k + 5] = True
        seen, dup = set(), 0
        for line in t.split("\n"):
            if re.search(WS, line):
                dup += line in seen
                seen.add(line)
        return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, int(m.sum())

    pairs = [(r, docs[r.doc_id]) for r in op6_quality_rules(spark, sf).collect()] + [(r, r.text) for r in quality_rules(odd).collect()]
    for r, t in pairs:
        n = brute(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == n
        assert r.base_failed == (n[0] < 10 or 100 * n[4] > 20 * n[0]) and not (r.kept and r.base_failed)


def test_ratios_and_verdicts_against_a_plain_version(spark, sf, docs):
    import math

    import zstandard

    from joindash.llm.quality_rules import CompressionBands, op6_quality_rules

    bands = CompressionBands()
    squeezed = lambda b: len(zstandard.ZstdCompressor(level=bands.level).compress(b))

    def within(data):
        lo, hi = next((lo, hi) for most, lo, hi in bands.limits if len(data) <= most)
        return lo <= len(data) / squeezed(data) <= hi

    def chunk_is_odd(c):
        if len(c) < bands.chunk_bytes:
            return not within(c)
        ratio, share = len(c) / squeezed(c), [c.count(b) / len(c) for b in set(c)]
        bits = -sum(x * math.log2(x) for x in share)
        return not bands.chunk_low <= ratio <= bands.chunk_high or ratio < bands.chunk_gain * (8 / bits if bits else math.inf)

    for r in op6_quality_rules(spark, sf).collect():
        data = docs[r.doc_id].encode()
        chunks = [data[i : i + bands.chunk_bytes] for i in range(0, len(data), bands.chunk_bytes)] if len(data) >= bands.chunk_bytes else []
        odd_bytes = sum(len(c) for c in chunks if chunk_is_odd(c))
        assert r.ratio == pytest.approx(len(data) / squeezed(data)) and r.odd_chunks == pytest.approx(odd_bytes / len(data))
        assert r.kept == (not r.base_failed and within(data) and odd_bytes <= bands.chunk_share * len(data))


def test_compression_bands_reject_noise_and_repetition(spark):
    import base64
    import random

    from joindash.llm.quality_rules import quality_rules

    r = random.Random(1)
    noise = " ".join(base64.b85encode(r.randbytes(9)).decode() for _ in range(400))
    words = ["".join(r.choices("etaoinshrdlu", k=r.randint(2, 9))) for _ in range(300)]
    prose = " ".join(r.choices(words, k=900))
    near = "\n".join(f"row {i} of the same sentence again and again and again" for i in range(400))
    got = {x.doc_id: x.kept for x in quality_rules(spark.createDataFrame([(1, noise), (2, prose), (3, near)], "doc_id long, text string")).collect()}
    assert got == {1: False, 2: True, 3: False}


def test_compression_bands_reject_encoded_texts_and_parts(spark):
    import base64
    import random

    from joindash.llm.quality_rules import quality_rules

    r = random.Random(2)
    words = ["".join(r.choices("etaoinshrdlu", k=r.randint(2, 9))) for _ in range(300)]
    prose = lambda n: " ".join(r.choices(words, k=n))[:n]
    lines = lambda s, w: "\n".join(s[i : i + w] for i in range(0, len(s), w))
    b64 = lambda n, w=40: lines(base64.b64encode(r.randbytes(n)).decode(), w)[:n]
    hexes = lambda n: lines(r.randbytes(n).hex(), 64)[:n]
    bad = [b64(400, 20), b64(600), b64(2000), b64(4000), b64(9000), hexes(5000), hexes(12000), r.randbytes(3000).hex(" ")]
    bad += [prose(6000) + "\n" + b64(6000), prose(4096) + b64(3000), prose(15000) + b64(5000), prose(12000) + hexes(4500)]
    good = [prose(n) for n in (300, 700, 1500, 3000, 4097, 5000, 8000, 12000, 16400, 40000)]
    rows = [(i, t) for i, t in enumerate([*bad, *good])]
    got = {x.doc_id: x for x in quality_rules(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert not any(x.base_failed for x in got.values())
    assert [i for i, x in got.items() if x.kept != (i >= len(bad))] == []


# ---- 7 packing


def test_packing_round_trip(spark, sf, docs):
    from tokenizers import Tokenizer

    from joindash.llm.packing import PackParams, default_tokenizer, op7_best_fit_packing, pack, sequences, token_pieces

    rows = op7_best_fit_packing(spark, sf).collect()
    tok, by, seqs = Tokenizer.from_file(default_tokenizer()), defaultdict(list), defaultdict(list)
    for r in rows:
        by[r.doc_id].append(r)
        seqs[r.sequence_id].append(r)
    for i, t in docs.items():
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        for k, r in enumerate(sorted(by[i], key=lambda r: r.piece)):
            own = ids[4096 * k : 4096 * k + 4096]
            assert (r.piece, r.start, r.length, r.ids_crc32) == (k, 4096 * k, len(own), zlib.crc32(own.tobytes()))
    for s in seqs.values():
        at = 0
        for r in sorted(s, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 4096
    assert len(seqs) == -(-sum(r.length for r in rows) // 4096)
    some = spark.createDataFrame([(1, "hello world"), (2, None), (2, "x " * 60)], "doc_id long, text string")
    p = PackParams(default_tokenizer(), 32)
    whole = sequences(pack(token_pieces(some, p, keep_ids=True), 32)).collect()
    assert sum(len(r.ids) for r in whole) == 4 * sum(r.n_tokens for r in whole) and all(r.n_tokens <= 32 for r in whole)


HARD_TEXT = "İ . , ALİ AİLESİ a Z ß é e\u0301 \u0301 \u0307 \u0338 \u030c J K 's ' ’ 'll 'd <|endoftext|> <|ENDOFTEXT|> <| |> | # $ % & * ! ? : ; 1 9 ½ 中 文 \u037e ﬁ Å A\u030a ς Σ \ufeff </w> words Over".split(" ")
HARD_SPACE = [" ", "\t", "\n", "\x0b", "\x0c", "\r", "\u0085", "\u2003", "\u3000", "\u200b", "\x1c", "\x00"]


def test_ids_equal_the_library():
    import pyarrow as pa
    from tokenizers import Tokenizer

    from joindash.llm.packing import PackParams, TextCoder, default_tokenizer

    rng = np.random.default_rng(4)
    parts = np.array([*HARD_TEXT, *HARD_SPACE], object)
    texts = ["", None, "don't stop's 'll <|endoftext|>, x<|EndOfText|> 123,456.", "A" * 300 + ". " + "Ab," * 50, "é. \u0301. x\u0301,", "İ. ALİ, AİLESİ."]
    texts += ["".join(rng.choice(parts, n)) for n in rng.integers(0, 14, 20_000)]
    tok = Tokenizer.from_file(default_tokenizer())
    want = [np.array(tok.encode(t or "", add_special_tokens=False).ids, "<u4").tobytes() for t in texts]
    coder = TextCoder(PackParams(default_tokenizer()))
    assert coder.by_word and coder.texts(pa.array(texts)) == want
    assert coder.texts(pa.array(texts).slice(3)) == want[3:]  # from memory now, and from within a column
    small = TextCoder(PackParams(default_tokenizer(), memory=5))
    assert [x for i in range(0, 300, 50) for x in small.texts(pa.array(texts[i : i + 50]))] == want[:300]


def test_other_vocabulary_files_take_whole_texts():
    import public_tokenizers
    import pyarrow as pa
    from tokenizers import Tokenizer

    from joindash.llm.packing import PackParams, TextCoder

    path, texts = public_tokenizers.path("byte_bpe_50k.json"), ["Two  words.", None, " İ. x"]
    coder, tok = TextCoder(PackParams(path)), Tokenizer.from_file(path)
    assert not coder.by_word
    assert coder.texts(pa.array(texts)) == [np.array(tok.encode(t or "", add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def one_by_one(lengths, cap):
    """Sequences that best fit opens when it takes the pieces one by one, the longest first."""
    gaps: list[int] = []
    for size in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= size]
        if fit:
            gaps.remove(min(fit))
        gaps.append((min(fit) if fit else cap) - size)
    return len(gaps)


def packed(spark, lengths, cap, one_task=0):
    from joindash.llm.packing import pack

    df = spark.createDataFrame([(i, int(x)) for i, x in enumerate(lengths)], "doc_id long, length long").repartition(5)
    rows = pack(df, cap, one_task=one_task).collect()
    assert sorted((r.doc_id, r.length) for r in rows) == list(enumerate(lengths))
    seqs = defaultdict(list)
    for r in rows:
        seqs[r.sequence_id].append((r.offset, r.length))
    for own in seqs.values():
        own.sort()
        assert [o for o, _ in own] == [0, *np.cumsum([n for _, n in own])[:-1].tolist()] and sum(n for _, n in own) <= cap
    return len(seqs)


@pytest.mark.parametrize("kind", ["even", "small", "large", "ties"])
def test_rounds_pack_as_well_as_one_by_one(spark, kind):
    rng, cap = np.random.default_rng(3), 100
    lengths = {
        "even": rng.integers(1, 101, 1500),
        "small": np.minimum(rng.geometric(0.2, 3000), 100),
        "large": rng.integers(45, 80, 800),
        "ties": np.repeat([51, 50, 26, 25, 24, 1], [10, 20, 300, 40, 50, 90]),
    }[kind].tolist()
    best = one_by_one(lengths, cap)
    assert -(-sum(lengths) // cap) <= packed(spark, lengths, cap, one_task=200) <= 1.01 * best + 1
    assert packed(spark, lengths, cap, one_task=10_000) <= best + 1
    assert packed(spark, lengths[:1], cap) == 1


def test_a_sweep_takes_the_successor():
    from joindash.llm.packing import GAP_BELOW, GAP_LEFT, PIECE_LEFT, PLACED, rank_plan, sweep

    rows = sweep([10, 9, 8, 6, 5, 4, 4, 3, 2], [1, 2, 70, 3, 71, 72, 73, 74, 75], [True, True, False, True, False, False, False, False, False], 10)
    placed = {r[2]: (r[4], r[5]) for r in rows if r[0] == PLACED}
    assert placed == {70: (2, 1), 71: (3, 4), 72: (1, 0), 73: (1, 4)} | {75: (1, 8)}
    assert [r[2] for r in rows if r[0] == PIECE_LEFT] == [74] and not [r for r in rows if r[0] == GAP_LEFT]
    assert sorted((r[3], r[4]) for r in rows if r[0] == GAP_BELOW) == [(1, 2), (1, 3)]
    # two gaps of 9 and more in the first partition, three of 5 and more in the second
    assert rank_plan([(0, 0, 0, 2, 9), (1, 1, 7, 3, 5), (2, 9, 4, 0, 0)]) == [(1, 0, 1, 0, 0, 1), (2, 0, 3, 1, 0, 1), (2, 3, 5, 0, 1, 2)]


# ---- 8 revisits


def test_revisits_against_sql(spark, sf, duck):
    from joindash.llm.revisits import ORACLE_SQL, op8_revisit_resolution
    from tests.conftest import rows_of

    got = op8_revisit_resolution(spark, sf).toPandas().astype(object)
    got["full_page_id"] = got["full_page_id"].map(lambda x: None if pd.isna(x) else int(x))
    want = duck.sql(ORACLE_SQL["op8_revisit_resolution"]).df().astype(object)
    want["full_page_id"] = want["full_page_id"].map(lambda x: None if pd.isna(x) else int(x))
    assert rows_of(got) == rows_of(want)


def test_revisit_rules(spark):
    from joindash.llm.revisits import resolve_revisits, with_payload

    rec = [
        (1, "http://WWW.a.org/x/", 10, "response", 200, {"ETag": '"1"', "Content-Type": "text/html", "Date": "old"}, "d1", "one"),
        (2, "https://a.org/x?utm_source=f", 20, "response", 200, {"ETag": '"2"'}, "d2", "two"),
        (3, "https://a.org/x#f", 15, "revisit", 304, {"etag": 'W/"1"', "date": "new", "content-type": "no"}, None, None),
        (4, "https://a.org/x", 25, "revisit", 304, {"etag": '"1"'}, None, None),
        (5, "https://a.org/x", 10, "revisit", 304, {}, None, None),
        (6, "https://a.org/x", 30, "revisit", 304, {}, None, None),
        (7, None, 30, "revisit", 304, None, None, None),
        (8, "https://a.org/x", 40, "response", 500, {}, "d3", "bad"),
        (9, "https://a.org/x", 50, "revisit", 304, {}, "d2", None),
        (9, "https://a.org/x", 50, "revisit", 304, {}, "d2", None),
    ]
    df = spark.createDataFrame(rec, "record_id long, url string, captured_at long, kind string, status int, headers map<string,string>, digest string, payload string").repartition(5)
    out = with_payload(resolve_revisits(df), df).collect()
    got = {r.record_id: (r.full_id, r.outcome, r.payload) for r in out}
    assert got == {3: (1, "resolved", "one"), 4: (2, "mismatch", None), 5: (None, "missing", None), 6: (2, "unverified", "two"), 7: (None, "missing", None), 9: (2, "resolved", "two")}
    assert len(out) == 7 and next(r for r in out if r.record_id == 3).resolved_headers == {"etag": 'W/"1"', "date": "new", "content-type": "text/html"}


# ---- 9 personal data

KINDS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_spans(t):
    def ok(kind, m):
        d = re.sub("[^0-9]", "", m)
        if kind == "ip":
            return all(int(x) <= 255 for x in m.split("."))
        if kind == "phone":
            return 10 <= len(d) <= 15
        if kind == "card":
            return 14 <= len(d) <= 19 and sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
        return True

    found = [(m.start(), n, m.end(), k) for n, (k, p) in enumerate(KINDS.items()) for m in re.finditer(p, t or "") if ok(k, m.group())]
    return ",".join(f"{k}:{a}:{e}" for a, _, e, k in sorted(found))


def test_personal_data(spark, sf, docs):
    from joindash.llm.pii import op9_contextual_pii

    for r in op9_contextual_pii(spark, sf).collect():
        want = brute_spans(docs[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(want.encode()).hexdigest() and set(want.split(",")) - {""} <= set(r.spans.split(","))


def test_personal_data_odd_texts(spark):
    from joindash.llm.pii import find_personal_data, mask_personal_data, spans_text

    texts = ["a@b.c_d@e.f", "a@b..c@d.e", "1.2.3.4.5.6.7.8", "12345678901234567890", "4111-1111-1111-1111x+12", "x" * 5000 + "@a.b", "1" * 20000, "00255.1.2.3 256.1.1.1", "a@b.c." + "f." * 4000, "é😀 a@b.co 😀 1.2.3.4", "", None, "%a@-.-", "1 " * 5000, "+1 (555) 555-0000 1 4111 1111 1111 1111"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    got = {r.id: r.s for r in find_personal_data(df).select("id", spans_text(F.col("base")).alias("s")).collect()}
    assert got == {i: brute_spans(t) for i, t in enumerate(texts)}
    masked = {r.doc_id: r.text for r in mask_personal_data(df).collect()}
    assert masked[9] == "é😀 [EMAIL] 😀 [IP]" and masked[11] is None and masked[10] == ""


def test_contexts_discover_unseen_identifiers(spark):
    from joindash.llm.pii import find_personal_data

    rows = [(i, f"words here please contact person{i}9999@mail.example.com now") for i in range(30)]
    rows += [(100, "x y please contact AB-7700000-Z soon"), (101, "please contact AB-7700000-Z"), (200, "the number AB-1234567-Z elsewhere")]
    got = find_personal_data(spark.createDataFrame(rows, "doc_id int, text string")).filter("size(added) > 0").collect()
    assert {r.id: [(s.start, s.end) for s in r.added] for r in got} == {100: [(19, 31)], 101: [(15, 27)]}


def _added(spark, texts):
    from joindash.llm.pii import find_personal_data

    rows = find_personal_data(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    return {texts[r.id][s.start : s.end] for r in rows for s in r.added}


def _letters(i):
    return "".join(chr(97 + i // 26**k % 26) for k in range(3))


def test_long_identifiers_and_far_contexts_count(spark):
    """Nothing is cut: identifiers of any length, labels of any length, words far away."""
    from joindash.llm.pii import find_personal_data

    label, gap = "passenger" * 12, " " * 150
    known = [f"the {label}:{gap}person{i}9999@mail.example.com was seen" for i in range(14)]
    unseen = ["the " + label + ":" + gap + "A" * 90 + f"{i}7731 was seen" for i in range(3)]
    rows = find_personal_data(spark.createDataFrame(list(enumerate(known + unseen)), "doc_id long, text string")).collect()
    got = {r.id: [(s.start, s.end) for s in r.added] for r in rows if r.added}
    at = len("the " + label + ":" + gap)
    assert got == {14 + i: [(at, at + 95)] for i in range(3)}


def test_base_spans_of_any_shape_seed_contexts(spark):
    """E-mails without digits and phones with spaces and brackets introduce unseen identifiers."""
    texts = [f"words {_letters(7 * i)} contact me {_letters(i)}@mail.example.com thanks a lot" for i in range(20)]
    texts += [f"text {_letters(7 * i)} call back +1 (0{i + 10}) 555-77{i + 10} until noon" for i in range(20)]
    texts += ["words zzz contact me handle-77x thanks anyway", "text yyy call back ext-4417 until later", "nothing around lot-55512 to see"]
    assert _added(spark, texts) == {"handle-77x", "ext-4417"}


def test_contexts_grow_from_accepted_identifiers(spark):
    """Many unknown instances do not refuse a pattern, and a label that holds discovered ones alone earns trust."""
    texts = [f"note {_letters(i)} reach at {_letters(i)}@mail.example.com" for i in range(20)]
    texts += [f"note {_letters(i)} reach at member-{i}x" for i in range(12)]
    texts += [f"SSN: member-{i}x {_letters(i)}" for i in range(12)] + ["SSN: other-99y qqq", "price other-98y qqq"]
    found = _added(spark, texts)
    assert found == {f"member-{i}x" for i in range(12)} | {"other-99y"}


# ---- 10 secrets


def test_secret_forest_on_unseen_findings(spark):
    from joindash.llm.secrets import features, fit, forest_score, labelled_findings

    forest = fit(labelled_findings(spark))
    score = forest_score(forest, features(*[F.col(c) for c in ("value", "before", "after", "path")]))
    test = labelled_findings(spark, 1000, 99).select(score.alias("s"), "label").collect()
    assert np.mean([(r.s >= 0.5) == bool(r.label) for r in test]) >= 0.97


def test_forest_scores_against_a_plain_version(spark, sf, docs):
    """Candidates, features and trees in plain Python, for every text of the table and for odd ones."""
    from joindash.llm import secrets as sec

    forest = sec.fit(sec.labelled_findings(spark))
    pairs, words = r"[bcdfghjklmnpqrstvwxz]{2}[bcdfghjkmpqtvwxz]|q[^u]|[jvwxz][bcdfgjkmpqvwxz]", "|".join(sorted(set(sec.DICTIONARY), key=lambda w: (-len(w), w)))

    def plain(v, before, after, path):
        n, low = len(v), v.lower()
        flag = lambda x: float(bool(x))
        shape = re.sub("[_+/=-]+", "_", re.sub("[A-Z]+", "A", re.sub("[a-z]+", "a", re.sub("[0-9]+", "0", v))))
        return {
            "length": min(n, 256), "digits": len(re.findall("[0-9]", v)) / n, "uppers": len(re.findall("[A-Z]", v)) / n, "symbols": len(re.findall("[_+/=-]", v)) / n,
            "variety": len(set(v)) / min(n, 64), "changes": len(shape) / n, "rare_pairs": len(re.findall(pairs, low)) / n, "words": 1 - len(re.sub(words, "", low)) / n,
            "vowels": len(re.findall("[aeiou]", low)) / n, "hexish": flag(re.fullmatch("[0-9a-f]+|[0-9A-F]+", v)), "assigned": flag(re.search("[=:]\\s*[\"']?$", before)),
            "quoted": flag(re.search("[\"']$", before) and re.match("[\"']", after)), "near_secret": flag(re.search(sec.SECRET_WORDS, before.lower())),
            "near_harmless": flag(re.search(sec.HARMLESS_WORDS, before.lower())), "doc_path": flag(re.search(sec.DOC_PATHS, path.lower())),
            "sentence": flag(re.search("[a-z]{2,}[,.;]? $", before) and not re.search("[=:] *$", before)),
        }

    def leaf(node, f):
        while isinstance(node, tuple):
            node = node[2] if f[sec.FEATURES[node[0]]] <= node[1] else node[3]
        return node

    rows = [(i, t, "src/a.py") for i, t in docs.items()] + [(-i - 1, t, None) for i, (_, t) in enumerate(ODD)]
    found = sec.scan_secrets(spark.createDataFrame(rows, "doc_id long, text string, source string"), forest).collect()
    assert len(found) == len(rows)
    for r in found:
        t, want, last = r.text or "", [], 0
        for m in re.finditer(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{16,}", t):
            f = plain(m.group(), t[last : m.start()][-40:], t[m.end() : m.end() + 2], r.source or "")
            want.append((m.start(), m.end(), m.group(), round(sum(leaf(x, f) for x in forest) / len(forest), 6)))
            last = m.end()
        assert [(c.start, c.end, c.value) for c in r.candidates] == [w[:3] for w in want]
        assert all(abs(c.score - w[3]) < 2e-6 and c.secret == (c.score >= 0.5) for c, w in zip(r.candidates, want, strict=True))


def test_secret_scan(spark, sf, docs):
    from joindash.llm.secrets import op10_secret_scan

    found = {r.doc_id for r in op10_secret_scan(spark, sf).collect() if r.n_secrets}
    assert found == {i for i, t in docs.items() if re.search(r'(?i)token = "[0-9a-f]{40}"', t)}


# ---- odd inputs and empty tables for all


def calls(spark, df):
    from joindash.llm import decontaminate, licenses, packing, pii, quality_classifier, quality_rules, secrets, sharding, simhash

    bench = spark.createDataFrame([(1, "the lazy dog near the river bank")], "item_id long, text string")
    labels = df.select("doc_id").withColumn("quality", F.lit(1))
    return {
        "simhash": lambda: simhash.near_duplicates(df),
        "decontaminate": lambda: decontaminate.find_contamination(df, bench),
        "no benchmark": lambda: decontaminate.find_contamination(df, bench.limit(0)),
        "licenses": lambda: licenses.scan_licenses(df),
        "no templates": lambda: licenses.scan_licenses(df, {}),
        "shards": lambda: sharding.assign_shards(df, ["lang", "source"]),
        "shards by bytes": lambda: sharding.assign_shards(df, ["lang"], p=sharding.ShardParams(law="bytes")),
        "classifier": lambda: quality_classifier.score_quality(df, quality_classifier.fit_quality(df, labels)),
        "rules": lambda: quality_rules.quality_rules(df),
        "pii": lambda: pii.find_personal_data(df),
        "mask": lambda: pii.mask_personal_data(df),
        "secrets": lambda: secrets.scan_secrets(df, [0.5]),
        "packing": lambda: packing.pack_documents(df),
    }


NAMES = ["simhash", "decontaminate", "no benchmark", "licenses", "no templates", "shards", "shards by bytes", "classifier", "rules", "pii", "mask", "secrets", "packing"]


@pytest.mark.parametrize("name", NAMES)
def test_odd_rows_all_come_back(spark, odd, name):
    rows = calls(spark, odd)[name]().collect()
    if name == "packing":
        assert len({(r.doc_id, r.piece) for r in rows}) <= len(rows) and sum(r.piece == 0 for r in rows) == len(ODD)
    else:
        assert len(rows) == len(ODD)


@pytest.mark.parametrize("name", NAMES)
def test_empty_tables(spark, empty, name):
    assert calls(spark, empty)[name]().collect() == []


def test_empty_revisits(spark, sf):
    from joindash.llm.revisits import page_records, resolve_revisits

    assert resolve_revisits(page_records(spark.read.parquet(f"{sf}/pages.parquet").limit(0))).collect() == []
