"""Training examples: full schema, names only, slices with and without history, SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import templates, tokens


def _schema_text(catalog: DataFrame, text: str = "text") -> DataFrame:
    """db_id, schema: all descriptions of a database in canonical order; one row a database."""
    return catalog.groupBy("db_id").agg(F.array_sort(F.collect_list(F.struct("table_name", F.col(text).alias("d")))).alias("x")).select("db_id", F.array_join("x.d", "; ").alias("schema"))


def _finish(df: DataFrame, variant: str, kind: str, user: Column, assistant: Column, count: str = "word") -> DataFrame:
    out = df.select("qid", "slice_id", F.lit(variant).alias("variant"), F.lit(templates.SYSTEM[kind]).alias("system"), user.alias("user"), assistant.alias("assistant"), "history", "weight")
    whole = tokens.count("system", count) + tokens.count("user", count)
    return out.withColumn("label_tokens", tokens.count("assistant", count)).withColumn("n_tokens", whole + F.col("label_tokens"))


def _none() -> Column:
    return F.array().cast("array<string>")


def _whole(qa: DataFrame, catalog: DataFrame) -> DataFrame:
    """Questions with the whole schema: the texts are one row a database, joined by key (Spark broadcasts them if small)."""
    return qa.join(_schema_text(catalog), "db_id").withColumn("slice_id", F.lit(0)).withColumn("history", F.lit(None).cast("array<string>")).withColumn("weight", F.lit(1.0))


def full_schema(qa: DataFrame, catalog: DataFrame) -> DataFrame:
    """(question, all descriptions) -> gold tables."""
    return _finish(_whole(qa, catalog), "full_schema", "link", templates.user("link", schema=F.col("schema"), question=F.col("question")), templates.answer(F.col("gold_tables")))


def names_only(qa: DataFrame, catalog: DataFrame) -> DataFrame:
    """(question, all table names) -> gold tables."""
    df = _whole(qa, catalog.withColumn("text", F.col("table_name")))
    return _finish(df, "names_only", "link", templates.user("link", schema=F.col("schema"), question=F.col("question")), templates.answer(F.col("gold_tables")))


def sql_direct(qa: DataFrame, catalog: DataFrame) -> DataFrame:
    """(question, all descriptions) -> gold SQL."""
    return _finish(_whole(qa, catalog), "sql_direct", "sql", templates.user("sql", schema=F.col("schema"), question=F.col("question")), F.col("gold_sql"))


def steps(qa: DataFrame, slices: DataFrame) -> DataFrame:
    """qid, db_id, question, and an array of (slice_id, target, history) in slice order; no text, no shuffle of questions.

    target: gold tables of the slice; history: gold tables of all slices before.
    """
    lists = slices.groupBy("db_id").agg(F.array_sort(F.collect_list(F.struct("slice_id", "tables"))).alias("ws"))
    hit = F.transform("ws", lambda w: F.struct(w["slice_id"].alias("slice_id"), F.array_intersect(w["tables"], F.col("gold_tables")).alias("target")))
    df = qa.join(lists, "db_id").withColumn("hits", hit)
    with_history = F.transform("hits", lambda h, i: F.struct(h["slice_id"].alias("slice_id"), h["target"].alias("target"), F.flatten(F.slice(F.col("hits"), F.lit(1), i)["target"]).alias("history")))
    return df.select("qid", "db_id", "question", "gold_tables", with_history.alias("steps"))


def sliced(qa: DataFrame, slices: DataFrame, catalog: DataFrame, history: str = "gold", balance: str = "double_positive", emission: str = "per_slice", neg_rate: int = 2) -> DataFrame:
    """One example per question and slice: (question, slice, history) -> gold tables in the slice, or none.

    history: none or gold (the gold tables of earlier slices). balance: double_positive emits each positive again
    without history; weight gives it weight 2 instead; neg_sample keeps one in neg_rate of the negatives; none.
    emission per_table: one example per slice and gold table (a slice with one of two gold tables gives a none example
    for the other as well).
    """
    rows = steps(qa, slices).select("qid", "db_id", "question", "gold_tables", F.inline("steps"))
    if emission == "per_table":
        rows = rows.withColumn("own", F.explode("gold_tables"))
        rows = rows.withColumn("target", F.when(F.array_contains("target", F.col("own")), F.array("own")).otherwise(_none())).drop("own")
    rows = rows.withColumn("weight", F.lit(1.0))
    positive = F.size("target") > 0
    if history == "none":
        rows = rows.withColumn("history", _none())
    if balance == "double_positive":
        copies = F.when(positive, F.array(F.col("history"), _none())).otherwise(F.array(F.col("history")))
        rows = rows.select(*[c for c in rows.columns if c != "history"], F.posexplode(copies).alias("copy", "history"))
    elif balance == "weight":
        rows = rows.withColumn("weight", F.when(positive, 2.0).otherwise(1.0))
    elif balance == "neg_sample":
        rows = rows.where(positive | ((F.col("qid") * 31 + F.col("slice_id")) % neg_rate == 0))
    text = slice_texts(slices, catalog)
    rows = rows.join(text, ["db_id", "slice_id"])  # texts enter last, so only ids are in flight before
    user = templates.user("slice", schema=F.col("slice_text"), history=templates.answer(F.col("history")), question=F.col("question"))
    return _finish(rows, f"sliced_{history}", "slice", user, templates.answer(F.col("target")))


def slice_texts(slices: DataFrame, catalog: DataFrame) -> DataFrame:
    """db_id, slice_id, slice_text."""
    placed = slices.select("db_id", "slice_id", F.posexplode("tables").alias("k", "table_name")).join(catalog.select("db_id", "table_name", "text"), ["db_id", "table_name"])
    return placed.groupBy("db_id", "slice_id").agg(F.array_sort(F.collect_list(F.struct("k", "text"))).alias("x")).select("db_id", "slice_id", F.array_join("x.text", "; ").alias("slice_text"))


def sql_pipeline(qa: DataFrame, pred: DataFrame, catalog: DataFrame, union: str = "both") -> DataFrame:
    """(question, predicted and gold tables' descriptions) -> gold SQL; union gold or pred: only those."""
    df = qa.join(pred.select("qid", "pred_tables"), "qid", "left").withColumn("pred_tables", F.coalesce("pred_tables", _none()))
    used = {"both": F.array_union("pred_tables", "gold_tables"), "gold": F.col("gold_tables"), "pred": F.col("pred_tables")}[union]
    texts = df.select("qid", "db_id", F.explode(used).alias("table_name")).join(catalog.select("db_id", "table_name", "text"), ["db_id", "table_name"])
    schema = texts.groupBy("qid").agg(F.array_join(F.array_sort(F.collect_list("text")), "; ").alias("schema"))
    df = df.join(schema, "qid", "left").withColumn("slice_id", F.lit(0)).withColumn("history", F.lit(None).cast("array<string>")).withColumn("weight", F.lit(1.0))
    return _finish(df, f"sql_{union}", "sql", templates.user("sql", schema=F.col("schema"), question=F.col("question")), F.col("gold_sql"))
