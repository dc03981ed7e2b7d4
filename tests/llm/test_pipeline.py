"""The pipeline's stages, each against brute force on its own input (all documents of sf0.001)."""

import re

import pytest

DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    """Each stage's name, rows in and rows out."""
    import corpus_pipeline as p
    from egoweave.llm import common

    docs, out = spark.read.parquet(f"{DIR}/documents.parquet"), {}
    for name, stage in p.STAGES:
        after = common.saved(stage(spark, docs, DIR), name)
        if name != p.STAGES[-1][0]:
            assert after.columns == docs.columns
        out[name] = (docs.collect(), after.collect())
        docs = after
    return out


def split(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def test_stages_run_and_take_effect(spark, stages):
    import corpus_pipeline as p

    assert list(stages) == ["toxicity", "ngram_jaccard", "substring_dedup", "decontamination", "best_fit_packing"]
    rows = p.run(spark, DIR).collect()
    assert 0 < len({r.doc_id for r in rows}) < len(stages["toxicity"][0]) and all(r.length <= 1024 for r in rows)
    assert {(r.doc_id, r.piece) for r in rows} == {(r.doc_id, r.piece) for r in stages["best_fit_packing"][1]}


def test_jaccard_stage(stages):
    before, after = stages["ngram_jaccard"]
    sets = {}
    for r in before:
        w = split("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in r.text or ""))
        sets[r.doc_id] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    up = {i: i for i in sets}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                up[y] = x
    assert {r.doc_id for r in after} == {i for i in ids if root(i) == i}
    assert len(after) < len(before)


def test_substring_stage(stages):
    before, after = stages["substring_dedup"]
    first = {}
    for r in sorted(before, key=lambda r: r.doc_id):
        w = split(r.text)
        for i in range(len(w) - 49):
            first.setdefault(tuple(w[i : i + 50]), r.doc_id)
    got = {r.doc_id: r.text for r in after}
    assert len(got) == len(before)
    for r in before:
        w = split(r.text)
        gone = set()
        for i in range(len(w) - 49):
            if first[tuple(w[i : i + 50])] < r.doc_id:
                gone.update(range(i, i + 50))
        assert got[r.doc_id] == (" ".join(x for i, x in enumerate(w) if i not in gone) if gone else r.text)


def test_packing_stage_keeps_every_document(stages):
    before, after = stages["best_fit_packing"]
    assert {r.doc_id for r in before} == {r.doc_id for r in after}
    load = {}
    for r in after:
        load.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for places in load.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 1024


def test_toxicity_stage(spark, stages):
    """The rows that go are those whose score by the fitted weights, added up one by one, reaches the threshold."""
    import math

    import pyarrow as pa

    from egoweave.llm import textkit, toxicity

    before, after = stages["toxicity"]
    labels = spark.read.parquet(f"{DIR}/labels.parquet").selectExpr("doc_id", "toxic as label")
    place, weight, bias = toxicity.fit(spark.read.parquet(f"{DIR}/documents.parquet"), labels)
    weights = dict(zip(place.tolist(), weight.tolist(), strict=True))
    want = set()
    for r in before:
        data, off = textkit.column(pa.array([r.text], pa.string()))
        places, _ = toxicity.features(textkit.split(data, off, textkit.NOT_ALNUM, True))
        logit = sum(weights.get(x, 0.0) for x in places.tolist()) + bias
        assert abs(logit - math.log(toxicity.THRESHOLD / (1 - toxicity.THRESHOLD))) > 1e-9
        if 1 / (1 + math.exp(-logit)) < toxicity.THRESHOLD:
            want.add(r.doc_id)
    assert {r.doc_id for r in after} == want and 0 < len(want) < len(before)


def test_decontamination_stage(spark, stages):
    before, after = stages["decontamination"]
    lower = lambda t: split("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    items = [lower(r.text) for r in spark.read.parquet(f"{DIR}/benchmark.parquet").collect()]
    held = set()
    for r in before:
        w = lower(r.text)
        own = {n: {tuple(w[a : a + n]) for a in range(len(w) - n + 1)} for n in range(1, 6)}
        for x in filter(None, items):
            n = min(5, len(x))
            g = list(dict.fromkeys(tuple(x[a : a + n]) for a in range(len(x) - n + 1)))
            met = [y in own[n] for y in g]
            cut = -(-2 * len(g) // 3)
            if sum(met) >= 0.8 * len(g) - 1e-9 and all(not part or sum(part) >= 0.5 * len(part) - 1e-9 for part in (met[:cut], met[cut:])):
                held.add(r.doc_id)
    assert {r.doc_id for r in after} == {r.doc_id for r in before} - held and held


def test_stages_on_an_empty_table(spark):
    import corpus_pipeline as p

    empty = spark.read.parquet(f"{DIR}/documents.parquet").limit(0)
    for name, stage in p.STAGES:
        got = stage(spark, empty, DIR)
        assert got.count() == 0 and (name == p.STAGES[-1][0] or got.columns == empty.columns)
