"""A set's dense group is looked up once, however many buckets hold the set."""

import re

from pyspark.sql import functions as F

from slicelink.llm import jaccard


def test_one_row_a_set_meets_its_group(spark):
    near = [(100 * k + v, v) for k in range(30) for v in range(20)]  # 30 buckets hold the same twenty sets
    member = spark.createDataFrame([*near, (7, 50), (8, 50)], "c long, v long")
    groups = spark.createDataFrame([(v, 0) for v in range(20)], "v long, c long")
    of = jaccard.owners(member, groups)
    got = {r.v: (r.us, r.d) for r in of.collect()}
    assert got == {v: ([100 * k + v for k in range(30)], 0) for v in range(20)} | {50: ([7, 8], None)}
    assert of.count() == member.select("v").distinct().count()


def test_no_outer_join_makes_a_row_a_membership(spark, monkeypatch):
    texts = [(i, " ".join(f"w{j}" if j != i else f"x{i}" for j in range(150))) for i in range(60)]
    first = jaccard.written(jaccard.sketches(spark.createDataFrame(texts, "doc_id long, text string")), "sketches").selectExpr("u AS v", "sig")
    vs, dense = jaccard.buckets(first, 3, 3)
    plans = []
    keep = jaccard.written
    monkeypatch.setattr(jaccard, "written", lambda df, name: plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or keep(df, name))
    assert jaccard.units(first, vs, dense, 3).agg(F.count("*")).first()[0] > 0
    outer = [p for p in plans if "Join LeftOuter, (v#" in p]
    assert outer and all(re.search(r"Join LeftOuter, \(v#\d+L = v#\d+L\).*\n[ :+-]*(Project.*\n[ :+-]*)?(Filter.*\n[ :+-]*)?Aggregate \[v#", p) for p in outer if "explode(us" in p)
    assert any("explode(us" in p for p in outer)
