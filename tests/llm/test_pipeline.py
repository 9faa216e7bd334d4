"""The pipeline's stages against plain versions of them."""

import hashlib
import sys

import corpus_pipeline
import numpy as np
import pytest
from pathtraces.llm import components, quality, simhash
from pathtraces.llm.common import spill

sys.path.insert(0, __file__.rpartition("/")[0])
from test_operators import ODD, SF, WORD, library, plain_fingerprint, plain_quality, plain_removals, union  # noqa: E402

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def steps(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("length(text) < 6000").unionByName(spark.createDataFrame([r for r in ODD if r[0] is not None and r[0] != 1004], DOCS))
    out = [docs.toPandas()]
    for name, stage in corpus_pipeline.STAGES:
        docs = spill(stage(spark, docs, SF), name)
        out.append(docs.toPandas())
    return out


def test_columns_stay(steps):
    assert all(list(s.columns) == ["doc_id", "text", "lang", "source", "n_chars"] for s in steps[:5])


def test_rules(steps):
    before, after = steps[0], steps[1]
    refs = {}
    for t, lang in zip(before.text, before.lang, strict=True):
        if lang is not None and not plain_quality(t)[5]:
            refs[lang] = refs.get(lang, 0) + np.concatenate(quality.histograms(t.encode()))
    judge = quality.Judge(refs)
    assert set(after.doc_id) == {d for d, t in zip(before.doc_id, before.text, strict=True) if judge((t or "").encode())[-1]}


def test_near(steps):
    before, after = steps[1], steps[2]
    marks = {d: plain_fingerprint(t) for d, t in zip(before.doc_id, before.text, strict=True)}
    keys = list(marks)
    groups = union([(a, b) for k, a in enumerate(keys) for b in keys[k + 1 :] if (marks[a] ^ marks[b]).bit_count() <= 3], keys)
    assert sorted(after.doc_id) == sorted(set(groups.values()))


def test_passages(steps):
    before, after = steps[2], steps[3]
    want = plain_removals(before)
    texts = dict(zip(before.doc_id, before.text, strict=True))
    left = dict(zip(after.doc_id, after.text, strict=True))
    assert set(left) == {d for d, (n, gone, _) in want.items() if gone < n or not n}
    for d, t in left.items():
        assert t == texts[d] if want[d][1] == 0 else hashlib.sha256(t.encode()).hexdigest() == want[d][2]


def test_mix(steps):
    before, after = steps[3], steps[4]
    count = lambda t: len(WORD.findall(t))
    size, taken = before.groupby("source").text.apply(lambda s: sum(map(count, s))), after.groupby("source").text.apply(lambda s: sum(map(count, s)))
    assert abs(taken.sum() - 1.5 * size.sum()) <= len(size)
    assert all(taken[s] <= 2 * size[s] for s in taken.index)
    full = dict(zip(before.doc_id, before.text, strict=True))
    for d, t in zip(after.doc_id, after.text, strict=True):
        assert t == full[d] or WORD.findall(full[d])[: count(t)] == WORD.findall(t)


def test_pack(steps):
    before, after = steps[4], steps[5]
    coder = library("byte_bpe_50k.json")
    assert after.length.sum() == sum(len(x) // 4 + 1 for x in coder(list(before.text)))
    assert after.groupby("sequence_id").length.sum().max() <= 2048
    assert after.sequence_id.nunique() <= -(-after.length.sum() // 2048) + 1


def test_run(spark):
    got = corpus_pipeline.run(spark, SF)
    assert got.count() > 100 and "sequence_id" in got.columns


def test_near_duplicates_plans_no_broadcast_of_exploded_rows(spark, monkeypatch):
    """Under Spark's own broadcast limit, which guesses from files."""
    plans = []

    def seen(df, name):
        plans.append((name, df._jdf.queryExecution().executedPlan().toString()))
        return spill(df, name)

    monkeypatch.setattr(simhash, "spill", seen)
    corpus_pipeline.near_duplicates(spark, spark.read.parquet(f"{SF}/documents.parquet"), SF)
    assert {"anchors", "gone"} <= {name for name, _ in plans} and not [name for name, plan in plans if "Broadcast" in plan]


def test_near_duplicates_gathers_no_repeated_ids(spark, monkeypatch):
    """Beyond the bound neither the ids that go nor those of several rows are sent to every task."""
    monkeypatch.setattr(components, "BROADCAST_IDS", 0)
    docs = spark.createDataFrame([(k % 20, f"a b c d {k % 20}", "en", "web", 9) for k in range(50)], DOCS)
    left = corpus_pipeline.near_duplicates(spark, docs, SF)
    assert sorted(r.doc_id for r in left.collect()) == list(range(20))
    assert "Broadcast" not in left._jdf.queryExecution().executedPlan().toString()
