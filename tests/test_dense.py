"""Nearest vectors against their SQL where a score ends on the last digit's half."""

import duckdb

from slicelink.plans import queries


def test_scores_round_as_in_sql(spark):
    sf = "/root/testdata/sf0.1"  # vectors 1950 and 1176: 0.38835
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{sf}/embeddings.parquet'")
    got = queries.dense_link_topk(spark, sf).select("query_id", "vec_id", "score", "rank").collect()
    assert sorted(map(tuple, got)) == sorted(duck.execute(queries.DENSE_SQL).fetchall())


def test_every_block_meets_every_other(spark):
    from slicelink.plans import linkers

    v = spark.range(60).selectExpr("id AS vec_id", "array(1.0D, 0.0D) AS embedding")
    got = linkers.DenseLinker(3, 7).nearest(v.where("vec_id = 0"), v).orderBy("rank").collect()
    assert [r.vec_id for r in got] == [1, 2, 3]
