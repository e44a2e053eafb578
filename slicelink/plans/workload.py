"""Questions with gold tables and gold SQL over a catalog, from families of templates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalog import DECLARED

QA = "qid bigint, db_id string, question string, gold_tables array<string>, gold_sql string, difficulty string, template string, split string"
# words by which questions name columns and tables
GLOSS = {
    "c_acctbal": "account balance", "s_acctbal": "account balance", "o_totalprice": "total price", "l_quantity": "quantity", "l_extendedprice": "extended price", "l_discount": "discount", "p_retailprice": "retail price", "p_size": "size",
    "value": "value", "n_chars": "length in characters", "quality": "quality", "toxic": "toxicity", "turn": "turn", "label": "label", "c_mktsegment": "market segment", "o_orderstatus": "order status", "o_orderpriority": "order priority",
    "l_returnflag": "return flag", "l_linestatus": "line status", "p_brand": "brand", "p_type": "type", "event_type": "event type", "lang": "language", "source": "source", "role": "role", "n_name": "nation name", "r_name": "region name", "c_name": "customer name", "s_name": "supplier name", "p_name": "part name",
}
NUMBERS = {"customer": "c_acctbal", "supplier": "s_acctbal", "orders": "o_totalprice", "lineitem": "l_quantity", "part": "p_retailprice", "events": "value", "documents": "n_chars", "labels": "quality", "conversations": "turn", "embeddings": "label"}
GROUPINGS = {"customer": "c_mktsegment", "orders": "o_orderstatus", "lineitem": "l_returnflag", "part": "p_brand", "events": "event_type", "documents": "lang", "conversations": "role", "nation": "n_name", "region": "r_name", "labels": "toxic", "supplier": "s_nationkey", "embeddings": "label"}
KEYS = {"customer": "c_custkey", "supplier": "s_suppkey", "orders": "o_orderkey", "part": "p_partkey", "events": "event_id", "documents": "doc_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id", "embeddings": "vec_id", "nation": "n_nationkey", "region": "r_regionkey", "lineitem": "l_orderkey"}
PATHS = [("customer", "nation", "region"), ("supplier", "nation", "region"), ("orders", "customer", "nation"), ("lineitem", "orders", "customer"), ("lineitem", "supplier", "nation")]
ASK = ["show", "give", "find", "report", "what is", "compute"]


def words(name: str) -> str:
    return GLOSS.get(name, name.replace("_", " "))


def _spoken(table: str, k: int) -> str:
    """How a question names a table: its words, in one of a few fashions."""
    w = table.replace("_", " ")
    return [w, f"the {w} table", w, f"{w} records"][k % 4]


def make_qa(tables: list[tuple[str, str]], n: int, db_id: str = "fleet", seed: int = 0) -> list[tuple]:
    """n questions over (table_name, base_table) pairs, the same for the same arguments; split is set by split()."""
    by_base: dict[str, list[str]] = {}
    for t, b in tables:
        by_base.setdefault(b, []).append(t)
    joins = [(c, cc[0], p, pc[0]) for c, cc, p, pc in DECLARED if c in by_base and p in by_base]
    paths = [p for p in PATHS if all(t in by_base for t in p)]
    fk = {(c, p): (cc[0], pc[0]) for c, cc, p, pc in DECLARED}
    out = []
    for i in range(n):
        x = (i * 7919 + seed * 104729 + 13) % 1_000_003
        pick = lambda xs, k, x=x: xs[(x // (k + 1) + 31 * k) % len(xs)]
        kind = i % 10
        t, b = pick(tables, 1)
        ask, say = pick(ASK, 2), _spoken(t, x // 7)
        num, grp, key = NUMBERS.get(b), GROUPINGS.get(b), KEYS[b]
        gold, level = [t], "easy"
        if kind in (0, 1) or kind in (2, 3, 4) and not (num and grp):
            q, sql = f"{ask} the number of {say}", f"SELECT count(*) AS n FROM {t}"
        elif kind == 2:
            level, q, sql = "medium", f"{ask} the average {words(num)} by {words(grp)} of {say}", f"SELECT {grp}, round(avg({num}), 4) AS m FROM {t} GROUP BY {grp}"
        elif kind == 3:
            q, sql = f"{ask} the largest {words(num)} of {say}", f"SELECT max({num}) AS m FROM {t}"
        elif kind == 4:
            level, q, sql = "medium", f"{ask} the {words(grp)} with more than {x % 50} {say}", f"SELECT {grp}, count(*) AS n FROM {t} GROUP BY {grp} HAVING count(*) > {x % 50}"
        elif kind in (5, 6, 7) and joins:
            c, ck, p, pk = pick(joins, 3)
            a, z = pick(by_base[c], 4), pick(by_base[p], 5)
            g = GROUPINGS.get(p) or KEYS[p]
            gold, level = [a, z], "medium"
            q = f"{ask} the number of {_spoken(a, x)} by {words(g)} of {_spoken(z, x // 3)}"
            sql = f"SELECT {z}.{g}, count(*) AS n FROM {a} JOIN {z} ON {a}.{ck} = {z}.{pk} GROUP BY {z}.{g}"
        elif kind == 8 and paths:
            c, m, p = pick(paths, 6)
            a, y, z = pick(by_base[c], 7), pick(by_base[m], 8), pick(by_base[p], 9)
            (k1, k2), (k3, k4) = fk[c, m], fk[m, p]
            g = GROUPINGS.get(p) or KEYS[p]
            gold, level = [a, y, z], "hard"
            q = f"for each {words(g)} of {_spoken(z, x)} {ask} the number of {_spoken(a, x // 3)} through {_spoken(y, x // 5)}"
            sql = f"SELECT {z}.{g}, count(*) AS n FROM {a} JOIN {y} ON {a}.{k1} = {y}.{k2} JOIN {z} ON {y}.{k3} = {z}.{k4} GROUP BY {z}.{g}"
        elif joins:
            c, ck, p, pk = pick(joins, 3)
            a, z = pick(by_base[c], 4), pick(by_base[p], 5)
            gold, level = [a, z], "extra"
            q = f"{ask} how many {_spoken(z, x)} have no {_spoken(a, x // 3)}"
            sql = f"SELECT count(*) AS n FROM {z} WHERE NOT EXISTS (SELECT 1 FROM {a} WHERE {a}.{ck} = {z}.{pk})"
        else:
            q, sql = f"{ask} the number of {say}", f"SELECT count(*) AS n FROM {t}"
        out.append((i, db_id, q, sorted(set(gold)), sql, level, f"t{kind}", None))
    return out


def qa_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, QA)


def split(qa: DataFrame, train: int, valid: int, seed: int = 17) -> DataFrame:
    """Exactly `train` and `valid` questions, chosen by an order that has nothing to do with their content; others go."""
    at = F.row_number().over(Window.partitionBy("db_id").orderBy((F.col("qid") * 7919 + seed) % 10007, "qid"))
    return qa.withColumn("at", at).where(F.col("at") <= train + valid).withColumn("split", F.when(F.col("at") <= train, "train").otherwise("valid")).drop("at")


#: (tables, training questions, validation questions) of the two databases.
DATASETS = {1: (254, 3647, 383), 2: (172, 1736, 178)}


def dataset(spark: SparkSession, sf_dir: str, which: int, scale: float = 1.0, detail: str = "types") -> tuple[DataFrame, DataFrame]:
    """(catalog, qa with splits) of one of the two databases; scale < 1 takes that share of the questions."""
    from . import catalog as C

    n, train, valid = DATASETS[which]
    cat = C.fleet(spark, sf_dir, n, f"dataset{which}", detail)
    train, valid = max(1, round(train * scale)), max(1, round(valid * scale))
    rows = make_qa([(t, b) for t, b, _ in C.fleet_names(n)], train + valid, f"dataset{which}", which)
    return cat, split(qa_frame(spark, rows), train, valid)


def difficulty(sql) -> F.Column:
    """easy, medium, hard or extra by the parts of a SQL text: joins, nesting, grouping, set operations."""
    s = F.upper(sql if not isinstance(sql, str) else F.col(sql))
    n = lambda p: F.regexp_count(s, F.lit(p))
    parts = n("JOIN ") + n("GROUP BY") + n("HAVING") + n("ORDER BY") + n("LIMIT ")
    nested = n(r"\(SELECT") + n("UNION") + n("EXCEPT") + n("INTERSECT")
    return F.when(nested > 0, "extra").when(parts >= 3, "hard").when(parts >= 1, "medium").otherwise("easy")
