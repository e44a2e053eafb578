"""The corpus pipeline, stage by stage against plain versions."""

import re

import pytest

import corpus_pipeline as p
from slicelink.llm import pii, quality

from .test_operators import WORD, check_packing, plain_base, plain_counts, plain_similar, prose

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def stages(spark, sf, tmp_path_factory):
    """Each stage's input and output."""
    top, docs, out = tmp_path_factory.mktemp("pipeline"), spark.read.parquet(f"{sf}/documents.parquet"), []
    for name, stage in p.STAGES:
        path = str(top / name)
        stage(spark, docs, sf).write.parquet(path)
        got = spark.read.parquet(path)
        out.append((name, docs, got))
        docs = got
    return out


def test_names_and_columns(stages):
    assert [n for n, *_ in stages] == ["quality", "near_duplicates", "repeated_passages", "personal_data", "packing"]
    assert all(got.columns == p.COLUMNS for _, _, got in stages[:-1])


def test_quality_stage(stages):
    _, docs, got = stages[0]
    left = {r.doc_id for r in got.collect()}
    for r in docs.collect():
        n, _, _, _, repeated = plain_counts(r.text)
        if n < 20 or 100 * repeated > 30 * n:
            assert r.doc_id not in left
    assert left == {r.doc_id for r in quality.judge(docs).where("kept").collect()}


def test_near_duplicate_stage(stages):
    _, docs, got = stages[1]
    classes = plain_similar({r.doc_id: r.text for r in docs.collect()})
    assert {r.doc_id for r in got.collect()} == {d for d, (c, _) in classes.items() if d == c}


def test_passage_stage_leaves_one_of_each(stages):
    _, docs, got = stages[2]
    before, after = {r.doc_id: r for r in docs.collect()}, {r.doc_id: r for r in got.collect()}
    held: dict = {}
    for d, r in sorted(after.items()):
        w = re.findall(WORD, r.text)
        assert r.n_chars == len(r.text)
        for i in range(len(w) - 59):
            assert held.setdefault(tuple(w[i : i + 60]), d) == d
        assert set(w) <= set(re.findall(WORD, before[d].text)) or len(w) < len(re.findall(WORD, before[d].text))


def test_personal_data_stage(stages):
    _, docs, got = stages[3]
    after = {r.doc_id: r.text for r in got.collect()}
    for r in docs.collect():
        if not plain_base(r.text):
            assert "@" in r.text or after[r.doc_id].count("[EMAIL]") == 0
        assert not pii.base_spans(after[r.doc_id])


def test_packing_stage(stages):
    _, docs, got = stages[4]
    assert check_packing(got.collect(), {r.doc_id: r.text for r in docs.collect()}) > 0.95


def test_odd_rows_pass_all_stages(spark, sf, tmp_path):
    long = prose(200, 3)
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, long, "en", "s", 1), (3, long, "en", "s", 1), (4, prose(100, 4) + " é mail a.b@c.example.com", None, None, None), (None, prose(120, 5), "en", "s", 2), (6, "x" * 30_000, "en", "s", 3)]
    for data, n in ((rows, "a"), ([], "b")):
        docs = spark.createDataFrame(data, DOCS).withColumn("t", __import__("pyspark").sql.functions.lit(1))
        for name, stage in p.STAGES:
            path = str(tmp_path / n / name)
            stage(spark, docs, sf).write.parquet(path)
            docs = spark.read.parquet(path)
        assert (docs.count() > 0) == bool(data)


def test_rows_that_share_an_id_are_judged_one_by_one(spark, sf, tmp_path):
    good, other, junk = prose(300, 21, None), prose(300, 22, None), "again and again the very same words come along " * 12
    near = good.replace(good.split()[5], "changed", 1)
    rows = [(1, good), (1, good), (1, junk), (2, near), (None, near + " end"), (None, other), (None, other), (4, prose(300, 23, None)), (4, prose(300, 24, None))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], DOCS)
    kept = lambda d: sorted(((r.doc_id, r.text) for r in d.collect()), key=repr)
    one = p.quality(spark, docs, sf)
    assert kept(one) == sorted([r for r in rows if r[1] != junk], key=repr)
    one.write.parquet(str(tmp_path / "q"))
    two = p.near_duplicates(spark, spark.read.parquet(str(tmp_path / "q")), sf)
    assert kept(two) == sorted([(1, good), (None, other), rows[7], rows[8]], key=repr)


def test_spans_are_cut_from_the_text_that_holds_them(spark, sf):
    a, b, shared = prose(90, 31, None), prose(90, 32, None), prose(80, 33, None)
    rows = [(1, f"{a} {shared}"), (2, f"{b} {shared}"), (2, prose(60, 34, None)), (None, f"{shared} {b}")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], DOCS)
    got = sorted(((r.doc_id, " ".join(r.text.split())) for r in p.repeated_passages(spark, docs, sf).collect()), key=repr)
    assert (1, rows[0][1]) in got and (2, b) in got and (2, rows[2][1]) in got and (None, rows[3][1]) in got and len(got) == 4
