"""The catalog of the given tables reads their rows."""

from slicelink.plans import catalog as C


def test_nullable_is_what_the_rows_hold(spark, sf, tmp_path):
    for name in C.TABLES:
        rows = spark.read.parquet(f"{sf}/{name}.parquet").limit(5)
        if name == "orders":
            rows = rows.selectExpr("o_orderkey", "o_custkey", "nullif(o_orderstatus, o_orderstatus) AS o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
        if name == "labels":
            rows = rows.where("false")
        rows.write.parquet(str(tmp_path / f"{name}.parquet"))
    base = C.base(spark, str(tmp_path)).collect()
    assert {(r.table_name, c["name"]) for r in base for c in r["columns"] if c["nullable"]} == {("orders", "o_orderstatus")}
    whole = C.describe(spark, C.footers(spark, str(tmp_path))).collect()
    assert [(r.table_name, r.text, r.n_tokens) for r in base] == [(r.table_name, r.text, r.n_tokens) for r in whole]


def test_budgets_are_of_given_texts(spark, sf):
    from slicelink.plans import queries, slicing
    from slicelink.plans.experiments import memory

    m, rows = memory(1), queries.budget_caps(spark, sf)
    assert rows.inputFiles() and queries.budget_gate(spark, sf).inputFiles()
    assert all(r.cap == slicing.Budget.from_memory(r.budget_mb, 2, m, 100).cap for r in rows.collect())


def test_levels_are_of_what_the_events_ask(spark, sf):
    from slicelink.plans import queries

    rows = queries.difficulty_levels(spark, sf)
    assert any("events.parquet" in x for x in rows.inputFiles())
    assert sorted(r.qid for r in rows.collect()) == sorted(r.event_id for r in spark.read.parquet(f"{sf}/events.parquet").select("event_id").collect())
    assert {r.level for r in rows.select("level").distinct().collect()} > {"easy"}
