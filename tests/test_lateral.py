"""The best rows a key, where orders come from many tasks."""

import duckdb
from pyspark.sql import functions as F

from slicelink.operators import relational


def test_best_orders_of_each_customer(spark, sf, tmp_path):
    for name in ("customer", "orders"):
        rows = spark.read.parquet(f"{sf}/{name}.parquet")
        spark.range(40).crossJoin(rows).drop("id").repartition(12).write.parquet(str(tmp_path / f"{name}.parquet"))
    duck = duckdb.connect()
    for name in ("customer", "orders"):
        duck.execute(f"CREATE VIEW {name} AS SELECT * FROM '{tmp_path}/{name}.parquet/*.parquet'")
    out = relational.join_lateral_top(spark, str(tmp_path))
    want = duck.execute(f"SELECT c_custkey, o_orderkey, count(*) FROM ({relational.S['op_join_lateral_top']}) GROUP BY ALL").fetchall()
    assert sorted(map(tuple, out.groupBy("c_custkey", "o_orderkey").agg(F.count("*")).collect())) == sorted(want)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "windowspecdefinition(o_custkey" in plan and all("DESC NULLS LAST" in x for x in plan.splitlines() if "windowspecdefinition" in x)
