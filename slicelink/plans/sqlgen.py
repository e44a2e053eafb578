"""SQL generators: nearest-question skeletons, damaged gold, and a fixed count."""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ready
from .linkers import word_list

SQLPRED = "qid long, sql string, status string"


class SkeletonGenerator:
    """Reuses the SQL of the training question with the largest common weight of words, its tables replaced by those
    given that share their base table (scope linked: only the tables of the prediction; all: any of the catalog)."""

    def __init__(self, scope: str = "linked"):
        self.scope = scope

    def fit(self, train: DataFrame, catalog: DataFrame) -> SkeletonGenerator:
        self.train, self.catalog = train, catalog
        return self

    def generate(self, questions: DataFrame, pred: DataFrame) -> DataFrame:
        """SQLPRED. Words that table names consist of don't count, so that a skeleton is found by the question's form."""
        names = self.catalog.select(F.explode(word_list(F.regexp_replace("table_name", "_", " "))).alias("word")).distinct()
        form = lambda df, key: df.select(F.col("qid").alias(key), F.explode(F.array_distinct(F.regexp_extract_all(F.lower("question"), F.lit("[a-z]+"), 0))).alias("word")).join(names, "word", "left_anti")
        t, q = form(self.train, "tid"), form(questions, "qid")
        total = self.train.agg(F.count("*").alias("n"))
        weight = t.groupBy("word").agg(F.count("*").alias("df")).crossJoin(total).select("word", F.log(1 + F.col("n") / F.col("df")).alias("w"))  # total is one row
        size = t.join(weight, "word").groupBy("tid").agg(F.sum("w").alias("tw"))
        # training questions with the same words and as many tables are one skeleton
        shape = t.groupBy("tid").agg(F.array_join(F.array_sort(F.collect_set("word")), " ").alias("shape")).join(self.train.select(F.col("qid").alias("tid"), F.size("gold_tables").alias("k")), "tid")
        first = shape.groupBy("shape", "k").agg(F.min("tid").alias("tid")).select("tid", "k")
        common = q.join(t.join(first, "tid").select("tid", "word"), "word").join(weight, "word").groupBy("qid", "tid").agg(F.sum("w").alias("cw")).join(size, "tid").join(first, "tid")
        wanted = common.join(pred.select("qid", F.size("pred_tables").alias("m")), "qid")
        fit = F.col("cw") / F.col("tw") + 0.3 * F.col("cw") + F.when(F.col("m") == F.col("k"), 1.0).otherwise(0.0)
        best = wanted.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy(F.round(fit, 9).desc(), "tid"))).where("r = 1")
        rows = best.join(self.train.select(F.col("qid").alias("tid"), "gold_sql", F.col("gold_tables").alias("old")), "tid")
        base = {r.table_name: r.base_table for r in self.catalog.select("table_name", "base_table").collect()}  # one database's tables
        linked = self.scope == "linked"
        rows = questions.select("qid", word_list("question").alias("words")).join(pred.select("qid", "pred_tables"), "qid").join(rows.select("qid", "gold_sql", "old"), "qid", "left")
        cols = ["qid", "words", "pred_tables", "gold_sql", "old"]

        def run(batches):
            for batch in batches:
                ids, out = batch.column(0).to_pylist(), []
                for words, given, sql, old in zip(*(batch.column(i).to_pylist() for i in range(1, 5)), strict=True):
                    out.append(fill(sql, old, given if linked else sorted(base), set(words), base) if sql else None)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(out, pa.string()), pa.array(["OK" if x else "EMPTY" for x in out])], names=["qid", "sql", "status"])

        ready(questions.sparkSession)
        return rows.select(*cols).mapInArrow(run, SQLPRED)


def fill(sql: str, old: list[str], given: list[str], words: set[str], base: dict[str, str]) -> str | None:
    """The skeleton with each old table replaced by the given one of the same base table that the question names best."""
    score = lambda t: sum((w[:-1] if len(w) > 3 and w.endswith("s") else w) in words for w in t.split("_")) / len(t.split("_"))
    swap = {}
    for t in old:
        fits = [g for g in given if base.get(g) == base.get(t) and g not in swap.values()]
        if not fits:
            return None
        swap[t] = min(fits, key=lambda g: (-score(g), g))
    return re.sub(r"\b(" + "|".join(map(re.escape, sorted(swap, key=len, reverse=True))) + r")\b", lambda m: swap[m[1]], sql)


class NoisyGenerator:
    """Gold SQL, a share of it damaged by seed (another constant in front of the result)."""

    def __init__(self, rate: int = 10, seed: int = 1):
        self.rate, self.seed = rate, seed

    def generate(self, qa: DataFrame) -> DataFrame:
        bad = (F.col("qid") * 7919 + self.seed) % 100 < self.rate
        return qa.select("qid", F.when(bad, F.concat(F.lit("SELECT -1 AS x FROM ("), "gold_sql", F.lit(") t"))).otherwise(F.col("gold_sql")).alias("sql"), F.lit("OK").alias("status"))


class ZeroShotGenerator:
    """A count of the first table linked."""

    def generate(self, pred: DataFrame) -> DataFrame:
        first = F.try_element_at("pred_tables", F.lit(1))
        return pred.select("qid", F.when(first.isNotNull(), F.concat(F.lit("SELECT count(*) AS n FROM "), first)).alias("sql"), F.when(first.isNotNull(), "OK").otherwise("EMPTY").alias("status"))
