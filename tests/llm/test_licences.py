"""The licence scan against its plain version."""

import pytest
from pathtraces.llm import licences

ODD = [(1, None), (2, ""), (3, "\n\n"), (4, "Released under the MIT License.\nnothing here\n\nLicensed under CC BY-NC 4.0."), (5, "word " * 30000 + "Licensed under the Apache License, Version 2.0."), (6, "mit MIT\nThe Apache helicopter was under repair."), (6, "All rights reserved."), (None, "Licensed under Foo terms."), (7, "MIT"), (8, "software")]
WRAPPED = [(20, "Permission is hereby granted, free of charge, to any person obtaining a\ncopy of this software and associated documentation files (the \"Software\"),\nto deal in the Software without restriction, including without limitation\nthe rights to use, copy, modify, merge, publish, distribute, sublicense,\nand/or sell copies of the Software."), (21, "A line of forty characters and some more of them, é\r\nReleased under the MIT License.\r\nshort\nLicensed under CC BY-NC 4.0."), (22, "You may redistribute it and/or modify it under the terms of the \r\n\r\nGNU GPL\n")]


@pytest.fixture(scope="module")
def docs(spark):
    texts = [(100 + k, t) for k, (_, t) in enumerate(licences.notices(licences.HELD_OUT_FRAMES + licences.FRAMES[:3], True))]
    return spark.createDataFrame(ODD + WRAPPED + texts, "doc_id long, text string").unionByName(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").selectExpr("100000 + doc_id as doc_id", "text"))


def test_scan_equals_plain(docs):
    m = licences.model()
    want = []
    for d, t in docs.collect():
        for k, line in enumerate(licences.paragraphs_of(t or "")):
            c, p, sure = m.classify(line)
            if c != licences.NONE:
                want.append((d, k, c, sure, pytest.approx(p)))
    got = [(r.doc_id, r.paragraph, r.licence, r.confirmed, r.score) for r in licences.licence_paragraphs(docs).collect()]
    order = lambda rows: sorted(rows, key=lambda r: (r[0] or -1, r[1], r[2]))
    assert order(got) == order(want) and len(got) > 300


def test_rows_stay(docs):
    got = {}
    for r in licences.licences(docs).collect():
        got.setdefault(r.doc_id, []).append(r)
    assert sum(map(len, got.values())) == docs.count()
    assert got[4][0].licences == "cc-by-nc,mit" and got[4][0].n_paragraphs == 2 and got[4][0].confirmed
    assert got[1][0].licences is None and got[2][0].n_paragraphs == 0 and not got[3][0].confirmed
    assert len(got[6]) == 2 and got[None][0].licences == "unknown"
    assert licences.licences(docs.limit(0)).count() == 0


def test_families_in_new_frames():
    m = licences.model()
    held = licences.notices(licences.HELD_OUT_FRAMES, False)
    assert sum(m.classify(t)[0] == c for c, t in held) >= 0.97 * len(held)


def test_families_of_new_names():
    """A model that has seen neither names nor frames: what it names is right, what it doesn't know is ``unknown``."""
    m = licences.LicenceModel(blind=True)
    got = [(c, m.classify(t)[0]) for c, t in licences.notices(licences.HELD_OUT_FRAMES, False, licences.HELD_OUT.__contains__)]
    named = [c == g for c, g in got if g in licences.FAMILIES]
    known = [c == g for c, g in got if c in licences.FAMILIES]
    assert all(named) and sum(known) >= 0.8 * len(known)
    assert all(g == licences.UNKNOWN for c, g in got if c == licences.UNKNOWN)


def test_wrapped_notices():
    m = licences.model()
    assert licences.paragraphs_of("a\nb\n\nc") == ["a", "b", "", "c"]
    whole = licences.paragraphs_of(WRAPPED[0][1])
    assert len(whole) == 1 and m.classify(whole[0])[::2] == ("mit", True)
    assert [m.classify(p)[0] for p in licences.paragraphs_of(WRAPPED[1][1])] == ["none", "mit", "none", "cc-by-nc"]


def test_lines_of_the_documents(spark):
    """The documents' notices are of four families, and one of none: all are found, nothing else is."""
    kinds = {"apache-2.0": "Apache License, Version 2.0", "mit": "MIT License", "gpl": "GNU General Public License", "cc-by-nc": "CC BY-NC 4.0", "unknown": "All rights reserved."}
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    want = {r.doc_id: ",".join(sorted(k for k, name in kinds.items() if name in (r.text or ""))) or None for r in docs.collect()}
    assert {r.doc_id: r.licences for r in licences.licences(docs).collect()} == want


def test_clashing_columns_and_repeats(spark):
    names = ["id", "row", "paragraph", "gram", "w", "hits", "licence", "score", "__id"]
    rows = [(1, "Released under the MIT License."), (1, "Released under the MIT License."), (2, None)]
    docs = spark.createDataFrame([(*r, *(["MIT"] * len(names))) for r in rows], "doc_id long, text string, " + ", ".join(f"`{n}` string" for n in names))
    assert sorted((r.doc_id, r.n_paragraphs, r.licences) for r in licences.licences(docs).collect() if r.licences) == [(1, 2, "mit")] * 2
    assert licences.licence_paragraphs(docs).count() == 2


def test_no_python_in_the_plan(docs):
    plan = licences.licences(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan
