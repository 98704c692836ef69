"""Each stage of the pipeline on what the stage before has kept, against brute force."""

import re

import numpy as np
import pytest

from tests.llm.test_operators import WS, brute_hits, brute_spans, lower


def test_stages(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    bench = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    kept = {r.doc_id: r.text for r in docs.collect()}
    assert [n for n, _ in cp.STAGES] == ["quality_rules", "near_dedup", "decontamination", "personal_data", "packing"]
    for name, stage in cp.STAGES:
        out = stage(spark, docs, sf)
        if name == "packing":
            break
        assert out.columns == docs.columns
        rows = {r.doc_id: r for r in out.collect()}
        if name == "near_dedup":
            assert set(rows) == brute_similar_heads(kept)
        if name == "decontamination":
            assert set(rows) == {i for i, t in kept.items() if not brute_hits(t, bench)[1]}
        if name == "personal_data":
            assert set(rows) == set(kept)
            assert all(not brute_spans(r.text) and r.n_chars == len(r.text) for r in rows.values())
            assert all(rows[i].text == t for i, t in kept.items() if not brute_spans(t))
        kept = {i: r.text for i, r in rows.items()}
        docs = spark.createDataFrame([tuple(r) for r in rows.values()], out.schema)
    packed = out.collect()
    assert {r.doc_id for r in packed} == set(kept)


def brute_similar_heads(texts):
    """Least id of every component of the pairs with 5-word Jaccard similarity 0.8 or more."""
    sets = {i: shingles(t) for i, t in texts.items()}
    root = {i: i for i in texts}
    for i in sorted(sets):
        for j in sorted(sets):
            if j < i and root[i] != root[j]:
                a, b = sets[i], sets[j]
                if a == b or 9 * len(a & b) >= 4 * (len(a) + len(b)):
                    old, new = max(root[i], root[j]), min(root[i], root[j])
                    root = {k: new if r == old else r for k, r in root.items()}
    return set(root.values())


def shingles(t):
    w = re.findall(WS, lower(t))
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_near_duplicate_stage_against_brute_force(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = [r.doc_id for r in cp.drop_near_duplicates(spark, docs, sf).collect()]
    want = brute_similar_heads({r.doc_id: r.text for r in docs.collect()})
    assert len(got) == len(set(got)) and set(got) == want


def test_near_duplicate_stage_around_the_threshold(spark, sf):
    """Edited copies from similarity 0.6 to 1, chains, ids that repeat or lack, and blank texts."""
    import corpus_pipeline as cp

    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    texts = []
    for _ in range(40):
        base = [word() for _ in range(150)]
        texts.append(base)
        for edits in (1, 2, 3, 4, 6):
            copy = list(base)
            for at in rng.choice(150, edits, replace=False):
                copy[at] = word()
            texts.append(copy)
    kept = {i: " ".join(t) for i, t in enumerate(texts)}
    df = spark.createDataFrame(list(kept.items()), "doc_id long, text string")
    got = [r.doc_id for r in cp.drop_near_duplicates(spark, df, sf).collect()]
    assert len(got) == len(set(got)) and set(got) == brute_similar_heads(kept)
    rows = [(1, "one text about nothing"), (1, "another text entirely"), (None, "one text about nothing"), (None, "no id here"), (None, "No id  here"), (2, ""), (3, None)]
    got = cp.drop_near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string"), sf).collect()
    assert sorted((r.doc_id or 0, (r.text or "").lower().split()) for r in got) == [(0, ["no", "id", "here"]), (1, ["another", "text", "entirely"]), (1, ["one", "text", "about", "nothing"]), (2, [])]


CLASH = "doc_id long, text string, kept string, n_words int, hit_spans string, fingerprint string, n_chars long"
SAID = "every word of this sentence is here to give the text a body that the quality rules accept as prose"


@pytest.mark.parametrize("name", ["quality_rules", "near_dedup", "decontamination", "personal_data", "packing"])
def test_stages_on_odd_tables(spark, sf, name):
    """Nulls, empty and very long texts, repeated rows and ids, ties, clashing columns, empty tables."""
    import corpus_pipeline as cp

    rng = np.random.default_rng(6)
    vocabulary = ["".join(rng.choice(list("aeioubcdlmnrst"), rng.integers(2, 9))) for _ in range(700)]
    very_long = " ".join(rng.choice(vocabulary, 60_000))
    stage = dict(cp.STAGES)[name]
    texts = [SAID, SAID, None, "", " \n", "short", f"{SAID} write to a@b.co or 10.0.0.1", very_long, f"{SAID} again with other words at its end"]
    rows = [(i % 7 if i % 4 else None, t, "own", 5, "own", "own", -1) for i, t in enumerate([*texts, texts[-1]])]
    df = spark.createDataFrame(rows, CLASH).repartition(3)
    out = stage(spark, df, sf)
    got = out.collect()
    if name == "packing":
        assert sum(r.piece == 0 for r in got) == len(rows) and stage(spark, df.limit(0), sf).collect() == []
        return
    assert out.columns == df.columns and stage(spark, df.limit(0), sf).collect() == []
    assert all((r.kept, r.n_words, r.hit_spans, r.fingerprint) == ("own", 5, "own", "own") for r in got)
    if name == "quality_rules":
        assert sorted(r.text[:99] for r in got) == sorted(r[1][:99] for r in rows if len((r[1] or "").split()) > 5)
    elif name == "near_dedup":
        assert sorted(((r.text or "").strip()) for r in got) == sorted(brute_kept_texts([r[1] for r in rows]))
    elif name == "decontamination":
        assert len(got) == len(rows)
    else:
        assert sorted((r.text is None, r.n_chars or 0) for r in got) == sorted((r[1] is None, len((r[1] or "").replace("a@b.co", "[EMAIL]").replace("10.0.0.1", "[IP]"))) for r in rows)


def brute_kept_texts(texts):
    return {texts[i].strip() if texts[i] else "" for i in brute_similar_heads(dict(enumerate(texts)))}


def test_rare_shingles_make_no_pairs_of_unlike_copies(spark):
    """Copies of one text with edits of their own, just below the threshold, share all common shingles."""
    from joindash.llm.resemblance import ResemblanceParams, rare_pairs, shingle_sets

    rng = np.random.default_rng(9)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    base = [word() for _ in range(60)]
    texts = []
    for k in range(150):
        copy = list(base)
        for at in rng.choice(60, 3, replace=False):
            copy[at] = word()
        texts.append(" ".join(copy))
    near = [" ".join([*texts[k].split(), "one", "more"]) for k in range(10)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts + near)], "uid long, text string")
    p = ResemblanceParams()
    got = rare_pairs(shingle_sets(df, "text", p).selectExpr("uid", "uid as root", "digests"), p).collect()
    sets = [shingles(t) for t in texts + near]
    similar = {(i, j) for j in range(len(sets)) for i in range(j) if 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j]))}
    assert similar and similar <= {(r.src, r.dst) for r in got} and len(got) < 100


def test_copies_of_one_text_are_compared_with_few_others(spark, sf, monkeypatch):
    """A text and copies of it with a few edits each are linked by comparisons that grow with their rows, not their pairs."""
    import corpus_pipeline as cp
    from joindash.llm import resemblance

    rng = np.random.default_rng(10)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 7))
    base = [word() for _ in range(150)]
    texts = [" ".join(base)]
    for _ in range(240):
        copy = list(base)
        for at in rng.choice(150, rng.integers(1, 5), replace=False):
            copy[at] = word()
        texts.append(" ".join(copy))
    tested, verified = [], resemblance.verified
    monkeypatch.setattr(resemblance, "verified", lambda pairs, *a: tested.append(pairs.count()) or verified(pairs, *a))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [r.doc_id for r in cp.drop_near_duplicates(spark, df, sf).collect()]
    assert len(got) == len(set(got)) and set(got) == brute_similar_heads(dict(enumerate(texts)))
    assert sum(tested) < 6 * len(texts)


def test_run_and_guard(spark, sf):
    import corpus_pipeline as cp

    assert cp.run(spark, sf).count() > 0


def test_texts_cross_to_python_once(spark):
    """Both stages that keep texts beside Python's columns send them once, and take any place of a text."""
    from joindash.llm.common import slices
    from joindash.llm.decontaminate import DecontamParams, find_contamination
    from joindash.llm.quality_rules import quality_rules

    texts = [SAID, None, "", "é ü " * 300, f"{SAID} {SAID}", "x " * 5000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    inside = df.selectExpr("doc_id", "named_struct('text', text) AS s")
    bench = spark.createDataFrame([(1, "every word of this sentence"), (2, "x x")], "item_id long, text string")
    found = lambda d, **k: find_contamination(d, bench, p=DecontamParams(block_bytes=20), **k)
    for run in (quality_rules, found):
        assert "__jd_bytes" not in run(df)._jdf.queryExecution().toString()
        cols = [c for c in run(df).columns if c not in ("doc_id", "text")]
        one, two = (sorted(map(str, d.select("doc_id", *cols).collect())) for d in (run(df), run(inside, text="s.text")))
        assert one == two and [r.text for r in run(df).orderBy("doc_id").collect()] == texts
    batch = df.toArrow().combine_chunks().to_batches()[0]
    parts = list(slices(batch, 1, 500))
    assert [x for p in parts for x in p.column(1).to_pylist()] == texts and [p.num_rows for p in parts] == [3, 1, 1, 1]


def test_few_rows_need_no_python_workers(spark):
    from joindash.llm import packing
    from joindash.llm.common import BATCH_ROWS, local_rows

    schema, rows, before = "a int, b long, c long", [(1, 2, None), (1, 2, 3)], spark.conf.get(BATCH_ROWS)
    try:
        for most in ("10000", "1", "0", "-1"):
            spark.conf.set(BATCH_ROWS, most)
            made, none = local_rows(spark, rows, schema), local_rows(spark, [], schema)
            assert [tuple(r) for r in made.collect()] == rows and none.collect() == []
            for df in (made, none):
                assert df.schema.simpleString() == "struct<a:int,b:bigint,c:bigint>"
                assert "LocalTableScan" in df._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set(BATCH_ROWS, before)
    pieces = spark.range(300).selectExpr("id", "1 + id % 40 size")
    out = packing.best_fit_rounds(pieces, 64, one_task=50)
    assert out.count() == 300
    assert "ExistingRDD" not in out._jdf.queryExecution().executedPlan().toString()


def test_a_worker_drops_what_another_step_kept():
    import pyarrow as pa

    from joindash.llm import common, packing

    p = packing.PackParams(packing.default_tokenizer())
    seen = []

    def packs(batches):
        for b in batches:
            seen.append(packing.coder(p))
            yield b

    batch = pa.RecordBatch.from_arrays([pa.array([1])], names=["a"])
    packing_step = common.lean(packs, holds=True)
    assert len([*packing_step(iter([batch, batch]))]) == 2 and len([*packing_step(iter([batch]))]) == 1
    assert seen[0] is seen[1] is seen[2] and [*common._held] == [p]
    assert [*common.lean(lambda batches: batches)(iter([batch]))] == [batch] and not common._held
