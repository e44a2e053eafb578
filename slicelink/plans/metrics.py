"""Measures of table prediction and of SQL."""

from __future__ import annotations

import re
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def scored(pred: DataFrame, gold: DataFrame, extra: list[str] | None = None) -> DataFrame:
    """qid, total, filtered, precision, recall of each question; no prediction is an empty one."""
    g, p = F.col("gold_tables"), F.coalesce("pred_tables", F.array().cast("array<string>"))
    hit, empty = F.size(F.array_intersect(p, g)), F.size(p) == 0
    df = gold.join(pred.select("qid", "pred_tables"), "qid", "left")
    return df.select(
        "qid", *(extra or []),
        ((F.size(F.array_except(p, g)) == 0) & (F.size(F.array_except(g, p)) == 0)).cast("int").alias("total"),
        (F.size(F.array_except(g, p)) == 0).cast("int").alias("filtered"),
        F.when(empty, (F.size(g) == 0).cast("double")).otherwise(hit / F.size(p)).alias("precision"),
        F.when(F.size(g) == 0, F.lit(1.0)).otherwise(hit / F.size(g)).alias("recall"),
    )


def averages() -> list:
    return [F.count("*").alias("n"), *(F.round(100 * F.avg(c), 4).alias(a) for c, a in (("total", "tot_acc"), ("filtered", "filt_acc"), ("precision", "avg_prec"), ("recall", "avg_rec")))]


def link_scores(pred: DataFrame, gold: DataFrame, by: list[str] | None = None) -> DataFrame:
    """n and the four measures in percent, of all questions or by columns of gold."""
    return scored(pred, gold, by).groupBy(*(by or [])).agg(*averages())


def wilson(scores: DataFrame, hits: str, n: str = "n", z: float = 1.96) -> DataFrame:
    """lo and hi of a share of n given in percent: a 95 % interval."""
    p, m = F.col(hits) / 100, F.col(n)
    mid, half = p + z * z / (2 * m), z * F.sqrt(p * (1 - p) / m + z * z / (4 * m * m))
    return scores.withColumn("lo", F.round(100 * (mid - half) / (1 + z * z / m), 4)).withColumn("hi", F.round(100 * (mid + half) / (1 + z * z / m), 4))


def paired_test(a: DataFrame, b: DataFrame, gold: DataFrame, measure: str = "total") -> DataFrame:
    """n, only_a, only_b, chi2: on how many questions only one of two predictions is right (McNemar, corrected)."""
    x = scored(a, gold).select("qid", F.col(measure).alias("x"))
    y = scored(b, gold).select("qid", F.col(measure).alias("y"))
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    out = x.join(y, "qid").agg(F.count("*").alias("n"), n(F.expr("x > y")).alias("only_a"), n(F.expr("x < y")).alias("only_b"))
    d = F.greatest(F.abs(F.col("only_a") - F.col("only_b")) - 1, F.lit(0))
    return out.withColumn("chi2", F.when(F.col("only_a") + F.col("only_b") > 0, F.round(d * d / (F.col("only_a") + F.col("only_b")), 4)).otherwise(F.lit(0.0)))


def bootstrap(pred: DataFrame, gold: DataFrame, rounds: int = 200, seed: int = 1) -> DataFrame:
    """lo, hi of total accuracy in percent: the 2.5th and 97.5th of a hundred parts of resampled means. A question's
    weight in a round is drawn from the Poisson distribution by arithmetic on its number, so that SQL can follow it."""
    draw = (F.col("qid") * 7919 + F.col("round") * 104729 + seed * 31) % 1009 / 1009
    weight = sum((draw > x).cast("int") for x in (0.3679, 0.7358, 0.9197, 0.981, 0.9963))
    rows = scored(pred, gold).select("qid", "total", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    means = rows.groupBy("round").agg((100 * F.sum(F.col("total") * weight) / F.sum(weight)).alias("m"))
    at = F.row_number().over(Window.orderBy("m", "round"))  # as many rows as rounds
    low, high = max(1, round(rounds * 0.025)), round(rounds * 0.975)
    pick = lambda k: F.round(F.max(F.when(F.col("at") == k, F.col("m"))), 4)
    return means.withColumn("at", at).agg(pick(low).alias("lo"), pick(high).alias("hi"))


# --- SQL

_COMMAND = re.compile(r"^\s*(with|select)\b", re.I)


def guarded(spark: SparkSession, sql: str) -> DataFrame | None:
    """The query as a DataFrame; None unless it is one SELECT that can be analysed (generated SQL is not trusted)."""
    if not sql or not _COMMAND.match(sql) or ";" in sql.strip().rstrip(";"):
        return None
    try:
        return spark.sql(sql)
    except Exception:  # parse and analysis errors alike: an invalid prediction
        return None


def digest(df: DataFrame, ordered: bool = False, digits: int = 6) -> tuple:
    """(columns, rows, sum and xor of row hashes[, hash of the order]) of a result, one small row to the driver; doubles rounded, names and timestamps' kinds ignored."""
    cols = [F.col(f"c{i}") for i in range(len(df.columns))]
    df = df.toDF(*(f"c{i}" for i in range(len(df.columns))))
    kinds = {f.name: f.dataType for f in df.schema}
    plain = [F.round(c.cast("double"), digits) if isinstance(kinds[f"c{i}"], (T.NumericType,)) else c.cast("string") for i, c in enumerate(cols)]
    h = F.xxhash64(*plain)
    if ordered:  # a row's number in the result takes part in its hash: partitions are in order, and so are ids in them
        numbered = df.select(h.alias("h"), F.monotonically_increasing_id().alias("at")).select(F.xxhash64("h", F.row_number().over(Window.orderBy("at"))).alias("h"))
        r = numbered.agg(F.count("*").alias("n"), F.sum(F.col("h").cast("decimal(38,0)")).alias("s"), F.bit_xor("h").alias("x")).first()
        return (len(cols), r.n, r.s, r.x, "ordered")
    r = df.select(h.alias("h")).agg(F.count("*").alias("n"), F.sum(F.col("h").cast("decimal(38,0)")).alias("s"), F.bit_xor("h").alias("x")).first()
    return (len(cols), r.n, r.s, r.x)


def _ordered(sql: str) -> bool:
    depth, flat = 0, []
    for c in sql:
        depth += (c == "(") - (c == ")")
        flat.append(c if depth == 0 else " ")
    return re.search(r"\border\s+by\b", "".join(flat), re.I) is not None


def execution_matches(spark: SparkSession, pairs: list[tuple[int, str, str]], threads: int = 8, cache: dict | None = None) -> list[tuple[int, int, str]]:
    """(qid, 1 or 0, status) of (qid, predicted, gold): equal results; each distinct text runs once, also over several calls with one cache."""
    cache = {} if cache is None else cache

    def run(sql, ordered):
        df = guarded(spark, sql)
        if df is None:
            return None
        try:
            return digest(df, ordered)
        except Exception:
            return None

    todo = sorted({(s or "", _ordered(g)) for _, p, g in pairs for s in (p, g)} - set(cache))
    with ThreadPoolExecutor(threads) as pool:
        for key, value in zip(todo, pool.map(lambda k: run(*k), todo), strict=True):
            cache[key] = value
    out = []
    for qid, p, g in pairs:
        o = _ordered(g)
        a, b = cache[p or "", o], cache[g or "", o]
        out.append((qid, int(a is not None and a == b), "OK" if a is not None else "INVALID"))
    return out


def execution_accuracy(spark: SparkSession, sqlpred: DataFrame, qa: DataFrame, cache: dict | None = None) -> DataFrame:
    """qid, ex, status. The questions of an evaluation are collected; their results are not."""
    pairs = [(r.qid, r.sql, r.gold_sql) for r in qa.select("qid", "gold_sql").join(sqlpred.select("qid", "sql"), "qid", "left").collect()]
    return spark.createDataFrame(execution_matches(spark, pairs, cache=cache), "qid long, ex int, status string")


def normal_text(sql) -> F.Column:
    """A SQL text in lower case, spaces and end mark evened out."""
    s = F.col(sql) if isinstance(sql, str) else sql
    s = F.regexp_replace(F.lower(s), r"\s+", " ")
    s = F.regexp_replace(s, r"\s*([(),=<>+*/-])\s*", "$1")
    return F.trim(F.regexp_replace(s, r"\s*;\s*$", ""))


def clause_set(sql) -> F.Column:
    """The sorted set of a SQL text's clauses, conditions split at AND."""
    s = F.regexp_replace(normal_text(sql), r"\b(select|from|where|group by|having|order by|limit|union|except|intersect)\b", "\u0001$1")
    parts = F.split(F.regexp_replace(s, r" and ", "\u0001and "), "\u0001")
    return F.array_sort(F.array_distinct(F.filter(F.transform(parts, lambda p: F.trim(F.regexp_replace(F.regexp_replace(p, "^where ", "and "), "^and ", "? "))), lambda p: p != "")))


def logical_match(df: DataFrame, how: str = "text", pred: str = "sql", gold: str = "gold_sql") -> DataFrame:
    """df with em: equal normal texts, or equal clause sets."""
    same = normal_text(pred) == normal_text(gold) if how == "text" else clause_set(pred) == clause_set(gold)
    return df.withColumn("em", F.coalesce(same, F.lit(False)).cast("int"))


def plan_match(spark: SparkSession, a: str, b: str) -> bool:
    """Whether two texts have the same canonical plan, as written or after optimization."""
    x, y = guarded(spark, a), guarded(spark, b)
    if x is None or y is None:
        return False
    best = lambda df: df._jdf.queryExecution().optimizedPlan()
    return x.sameSemantics(y) or best(x).sameResult(best(y))
