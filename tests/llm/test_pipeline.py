"""The corpus pipeline beside a plain version of its rules, stage by stage."""

import pytest

import corpus_pipeline
from fewbit.llm import quality
from fewbit.llm._store import stored
from tests.llm.test_operators import BASE, base_spans, groups, removed, set_of


@pytest.fixture(scope="module")
def steps(spark, sf):
    docs, out = spark.read.parquet(f"{sf}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = stored(stage(spark, docs, sf))
        out.append((name, before, docs))
    return {name: (a, b) for name, a, b in out}


def texts(df):
    return {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}


def test_columns(steps):
    for name, (before, after) in steps.items():
        assert name == "packing" or before.columns == after.columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_quality_stage(spark, sf, steps):
    before, after = map(texts, steps["quality"])
    model = quality.fit_quality(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    ids = sorted(before)
    score = model.score([(before[i] or "").encode() for i in ids])
    sure = {i: s for i, s in zip(ids, score, strict=True) if abs(s - 0.7) > 1e-4}
    assert all((i in after) == (s >= 0.7) for i, s in sure.items()) and all(after[i] == before[i] for i in after)


def test_line_stage(steps):
    before, after = map(texts, steps["lines"])
    ids = sorted(before)
    want = dict(zip(ids, removed([before[i] for i in ids], 50), strict=True))
    assert after == {i: t for i, t in want.items() if t == before[i] or t.strip()}


def test_duplicate_stage(steps):
    before, after = map(texts, steps["near_duplicates"])
    ids = sorted(before)
    sets = [set_of(before[i], 5) for i in ids]
    want = groups(len(ids), lambda a, b: bool(sets[a]) and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]))
    assert after == {i: before[i] for a, i in enumerate(ids) if want[a] == a}


def test_personal_stage(steps):
    before, after = map(texts, steps["personal_data"])
    assert before.keys() == after.keys()
    assert all(not base_spans(t) for t in after.values())
    assert all((after[i] == before[i]) == (not any(k in after[i] for k in (f"[{x.upper()}]" for x in (*BASE, "iban", "social")))) for i in after)


def test_packing_stage(steps):
    before, after = steps["packing"]
    rows = after.collect()
    assert {r.doc_id for r in rows} == set(texts(before))
    ends = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == ends.get(r.sequence_id, 0)
        ends[r.sequence_id] = r.offset + r.length
    assert max(ends.values()) <= 4096
