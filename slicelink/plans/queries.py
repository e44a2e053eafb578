"""Driver queries of the linking engine, each with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import tokens
from ..session import table
from . import catalog as C
from . import cost, examples, experiments, groups, linkers, linking, metrics, slicing, workload

CAP = 100


def joined(c):
    return F.array_join(F.array_sort(c), ",")


# --- shared SQL: the catalog of the fourteen tables from DuckDB's own metadata

_TYPES = "CASE data_type WHEN 'BIGINT' THEN 'bigint' WHEN 'INTEGER' THEN 'int' WHEN 'DOUBLE' THEN 'double' WHEN 'VARCHAR' THEN 'string' WHEN 'FLOAT[]' THEN 'array<float>' ELSE 'timestamp' END"
_NAMES = ", ".join(f"'{t}'" for t in C.TABLES)
_FKS = ", ".join(f"('{t}', '{'+'.join(a)}', '{r}', '{'+'.join(b)}')" for t, a, r, b in C.DECLARED)
COLS = f"cols AS (SELECT table_name, column_name, ordinal_position AS pos, {_TYPES} AS type FROM information_schema.columns WHERE table_name IN ({_NAMES}))"
CAT = f"""{COLS}, cat AS (SELECT table_name, table_name || '(' || string_agg(column_name || ' ' || type, ', ' ORDER BY pos) || ')' AS text FROM cols GROUP BY table_name),
tok AS (SELECT table_name, text, len(regexp_extract_all(text, '[A-Za-z]+|[0-9]+|[^\\sA-Za-z0-9]'))::INT AS n_tokens FROM cat),
fk(table_name, col, ref_table, ref_col) AS (VALUES {_FKS})"""
GRP = """tied AS (SELECT table_name FROM fk UNION SELECT ref_table FROM fk),
edge AS (SELECT table_name AS a, ref_table AS b FROM fk UNION SELECT ref_table, table_name FROM fk),
reach AS (SELECT a AS v, a AS c FROM edge UNION SELECT e.b, r.c FROM reach r JOIN edge e ON e.a = r.v),
grp AS (SELECT v AS table_name, min(c) AS group_key FROM reach GROUP BY v),
ord AS (SELECT t.table_name, t.n_tokens, g.group_key IS NOT NULL AS has_reference, dense_rank() OVER (ORDER BY (g.group_key IS NULL)::INT, coalesce(g.group_key, '')) AS group_id,
  row_number() OVER (ORDER BY (g.group_key IS NULL)::INT, coalesce(g.group_key, ''), t.table_name) AS pos FROM tok t LEFT JOIN grp g USING (table_name))"""


def packed(cap: int, name: str = "pk", source: str = "ord", by_group: bool = False) -> str:
    """A recursive CTE that packs `source` (pos, table_name, n_tokens, group_id)."""
    opens = f"p.total + o.n_tokens >= {cap}" + (" OR o.group_id <> p.g" if by_group else "")
    return f"""{name} AS (SELECT pos, table_name, n_tokens, n_tokens AS total, 1 AS slice_id, group_id AS g FROM {source} WHERE pos = 1
UNION ALL SELECT o.pos, o.table_name, o.n_tokens, CASE WHEN {opens} THEN o.n_tokens ELSE p.total + o.n_tokens END, p.slice_id + CASE WHEN {opens} THEN 1 ELSE 0 END, o.group_id
FROM {name} p JOIN {source} o ON o.pos = p.pos + 1)"""


def sql(body: str, *ctes: str) -> str:
    return f"WITH RECURSIVE {', '.join(ctes)} {body}"


def _base(spark, sf):
    table(spark, sf, "region")
    return C.base(spark, sf)


def _slices(spark, sf, cap=CAP, **kw):
    return slicing.pack(groups.order(_base(spark, sf)), cap, **kw)


# --- questions over the fourteen tables, as VALUES for SQL

SMALL_QA = workload.make_qa([(t, t) for t in C.TABLES], 60, "main", 5)


def _qa(spark):
    return workload.qa_frame(spark, SMALL_QA)


def _lit(x) -> str:
    return "NULL" if x is None else "[" + ", ".join(f"'{v}'" for v in x) + "]" if isinstance(x, list) else str(x) if isinstance(x, (int, float)) else "'" + x.replace("'", "''") + "'"


QA_SQL = "qa(qid, question, gold, gold_sql, difficulty) AS (VALUES " + ", ".join(f"({q[0]}::BIGINT, {_lit(q[2])}, {_lit(q[3])}, {_lit(q[4])}, {_lit(q[5])})" for q in SMALL_QA) + ")"
SL = f"{packed(CAP)}, sl AS (SELECT slice_id, list(table_name ORDER BY pos) AS tables, sum(n_tokens) AS slice_tokens FROM pk GROUP BY slice_id)"
STEPS = f"{SL}, st AS (SELECT qid, question, gold, slice_id, list_sort(list_filter(tables, lambda t: list_contains(gold, t))) AS target FROM qa, sl), hist AS (SELECT *, (SELECT list_sort(flatten(list(b.target))) FROM st b WHERE b.qid = a.qid AND b.slice_id < a.slice_id) AS history FROM st a)"


def _show(e):
    return e.select("qid", "slice_id", "assistant", F.coalesce(joined(F.coalesce("history", F.array().cast("array<string>"))), F.lit("")).alias("history"), "weight", F.length("user").alias("user_chars"))


def catalog_columns(spark, sf):
    return _base(spark, sf).select("table_name", F.posexplode("columns").alias("pos", "c")).select("table_name", (F.col("pos") + 1).alias("pos"), F.col("c.name").alias("column_name"), F.col("c.type").alias("type"))


def render_schema(spark, sf):
    b = _base(spark, sf)
    return b.select("table_name", C.rendered("names").alias("names"), C.rendered("columns").alias("columns"), C.rendered("types").alias("types"), C.rendered("keys").alias("keys"))


#: The given tables' columns of simple types, by which the SQL below is made.
SIMPLE = {
    "region": {"r_regionkey": "int", "r_name": "string"}, "nation": {"n_nationkey": "int", "n_name": "string", "n_regionkey": "int"},
    "customer": {"c_custkey": "bigint", "c_name": "string", "c_nationkey": "int", "c_acctbal": "double", "c_mktsegment": "string"},
    "supplier": {"s_suppkey": "bigint", "s_name": "string", "s_nationkey": "int", "s_acctbal": "double"},
    "part": {"p_partkey": "bigint", "p_name": "string", "p_brand": "string", "p_type": "string", "p_size": "int", "p_retailprice": "double"},
    "orders": {"o_orderkey": "bigint", "o_custkey": "bigint", "o_orderstatus": "string", "o_totalprice": "double", "o_orderdate": "timestamp", "o_orderpriority": "string"},
    "lineitem": {"l_orderkey": "bigint", "l_partkey": "bigint", "l_suppkey": "bigint", "l_linenumber": "int", "l_quantity": "double", "l_extendedprice": "double", "l_discount": "double", "l_tax": "double", "l_returnflag": "string", "l_linestatus": "string", "l_shipdate": "timestamp"},
    "events": {"event_id": "bigint", "ts": "timestamp", "user_id": "bigint", "event_type": "string", "value": "double", "props": "string"},
    "documents": {"doc_id": "bigint", "text": "string", "lang": "string", "source": "string", "n_chars": "bigint"}, "embeddings": {"vec_id": "bigint", "label": "int"},
    "pages": {"page_id": "bigint", "url": "string", "html": "string"}, "benchmark": {"item_id": "bigint", "text": "string"},
    "labels": {"doc_id": "bigint", "quality": "int", "toxic": "int"}, "conversations": {"conv_id": "bigint", "turn": "bigint", "role": "string", "text": "string"},
}


def _unique(spark, sf):
    """The columns that hold no value twice, of all tables: what discovery takes for possible keys."""
    found = C.unique_columns({t: table(spark, sf, t) for t in C.TABLES})
    return {(r.table_name, r.column_name) for r in found.where("is_unique").collect()}  # columns of one database


def render_samples(spark, sf):
    return C.sampled(_base(spark, sf), {t: table(spark, sf, t) for t in C.TABLES}).select("table_name", "text")


_SHOWN = " UNION ALL ".join(f"SELECT '{t}' AS table_name, '{c}' AS column_name, concat_ws('..', substr(min({c})::VARCHAR, 1, 20), substr(max({c})::VARCHAR, 1, 20)) AS ends FROM {t}" for t, cs in SIMPLE.items() for c, k in cs.items() if k in ("int", "bigint", "string"))
SAMPLES_SQL = f"WITH {COLS}, e AS ({_SHOWN}) SELECT table_name, table_name || '(' || string_agg(column_name || ' ' || type || coalesce(' ' || ends, ''), ', ' ORDER BY pos) || ')' AS text FROM cols LEFT JOIN e USING (table_name, column_name) GROUP BY table_name"


def fk_inclusion_exact(spark, sf):
    return C.discover_fks({t: table(spark, sf, t) for t in C.TABLES}, _unique(spark, sf)).select("child", "child_column", "parent", "parent_column", "n_child", "n_missing")


_PAIRS = [(t, c, u, p) for t, cs in SIMPLE.items() for c, k in cs.items() for u, ps in SIMPLE.items() for p, j in ps.items() if t != u and k == j and C.same_suffix(c, p)]
FK_SQL = " UNION ALL ".join(f"SELECT * FROM (SELECT '{t}' AS child, '{c}' AS child_column, '{u}' AS parent, '{p}' AS parent_column, count(DISTINCT {c}) AS n_child, count(DISTINCT {c}) FILTER (WHERE {c} NOT IN (SELECT {p} FROM {u} WHERE {p} IS NOT NULL)) AS n_missing FROM {t}) WHERE n_missing = 0 AND (SELECT count(*) > 0 AND count(*) = count(DISTINCT {p}) FROM {u})" for t, c, u, p in _PAIRS)


def fk_inclusion_sketch(spark, sf):
    return C.discover_fks({t: table(spark, sf, t) for t in C.TABLES}, _unique(spark, sf), min_containment=0.95, mode="sketch").select("child", "child_column", "parent", "parent_column", F.round("containment", 2).alias("containment"))


def unique_columns(spark, sf):
    return C.unique_columns({t: table(spark, sf, t) for t in C.TABLES})


UNIQUE_SQL = " UNION ALL ".join(f"SELECT '{t}' AS table_name, '{c}' AS column_name, count(*) AS n_rows, count(DISTINCT {c}) AS n_distinct, count(*) > 0 AND count(*) = count(DISTINCT {c}) AS is_unique FROM {t}" for t, cs in SIMPLE.items() for c in cs)


def token_count_word(spark, sf):
    return _base(spark, sf).select("table_name", tokens.count("text").alias("n_tokens"))


def token_count_char4(spark, sf):
    return _base(spark, sf).select("table_name", tokens.count("text", "char4").alias("n_tokens"))


def token_count_bpe(spark, sf):
    b = _base(spark, sf)
    return b.select("table_name", tokens.bpe_counter(tokens.train_bpe(b, "text", 120))("text").alias("n_tokens"))


def reference_split(spark, sf):
    return groups.partition(_base(spark, sf)).drop("db_id")


def correlation_groups(spark, sf):
    return groups.correlate(_base(spark, sf)).drop("db_id")


def correlation_groups_by_joins(spark, sf):
    return groups.correlate(_base(spark, sf), driver_tables=0).drop("db_id")


def correlation_groups_per_fk(spark, sf):
    return groups.correlate(_base(spark, sf), "per_fk").drop("db_id")


def slice_order(spark, sf):
    return groups.order(_base(spark, sf)).select("table_name", "has_reference", "group_id", "pos")


def _pk(df):
    return df.select("slice_id", F.array_join("tables", ",").alias("tables"), F.col("slice_tokens").cast("long").alias("slice_tokens"), "oversize")


def _pk_sql(cap, **kw):
    return sql(f"SELECT slice_id, string_agg(table_name, ',' ORDER BY pos) AS tables, sum(n_tokens)::BIGINT AS slice_tokens, sum(n_tokens) >= {cap} AS oversize FROM pk GROUP BY slice_id", CAT, GRP, packed(cap, **kw))


def pack_slices(spark, sf):
    return _pk(_slices(spark, sf))


def pack_slices_small(spark, sf):
    return _pk(_slices(spark, sf, 50))


def pack_slices_group_boundary(spark, sf):
    return _pk(_slices(spark, sf, boundary="group"))


def pack_first_fit(spark, sf):
    return _pk(_slices(spark, sf, method="ffd"))


def pack_split_columns(spark, sf):
    return slicing.split_columns(_base(spark, sf).where("n_tokens >= 40"), 40).select("table_name", "part", F.array_join("columns.name", ",").alias("columns"))


def slice_coverage(spark, sf):
    b = _base(spark, sf)
    return slicing.check(slicing.pack(groups.order(b), CAP), b).drop("db_id")


SWEEP = [50, 84, 85, 100, 120, 200, 315]


def slice_cap_sweep(spark, sf):
    return slicing.cap_sweep(groups.order(_base(spark, sf)), SWEEP).select("cap", "n_slices", F.col("max_tokens").cast("long").alias("max_tokens"), "n_oversize")


SWEEP_SQL = sql(
    " UNION ALL ".join(f"SELECT {c} AS cap, count(*) AS n_slices, max(t)::BIGINT AS max_tokens, sum((t >= {c})::INT)::BIGINT AS n_oversize FROM (SELECT slice_id, sum(n_tokens) AS t FROM pk{c} GROUP BY slice_id)" for c in SWEEP),
    CAT, GRP, *(packed(c, f"pk{c}") for c in SWEEP),
)


def cap_search(spark, sf):
    sizes = [r.n_tokens for r in groups.order(_base(spark, sf)).orderBy("pos").collect()]
    return spark.createDataFrame([(m, *slicing.cap_for(sizes, m)) for m in range(1, 8)], "wanted int, cap int, slices int")


def qa_split(spark, sf):
    return workload.split(_qa(spark), 50, 10).groupBy("split").agg(F.count("*").alias("n"), F.sum("qid").alias("qids"))


QA_SPLIT_SQL = f"WITH {QA_SQL}, o AS (SELECT qid, row_number() OVER (ORDER BY (qid * 7919 + 17) % 10007, qid) AS k FROM qa) SELECT CASE WHEN k <= 50 THEN 'train' ELSE 'valid' END AS split, count(*) AS n, sum(qid)::BIGINT AS qids FROM o GROUP BY 1"


def workload_sizes(spark, sf):
    out = None
    for which in (1, 2):
        cat, qa = workload.dataset(spark, sf, which)
        one = qa.groupBy("db_id", "split").agg(F.count("*").alias("n")).join(cat.groupBy("db_id").agg(F.count("*").alias("n_tables")), "db_id")
        out = one if out is None else out.unionByName(one)
    return out


WORKLOAD_SQL = " UNION ALL ".join(f"SELECT 'dataset{w}' AS db_id, CASE WHEN pos <= {a} THEN 'train' ELSE 'valid' END AS split, count(*) AS n, (SELECT count(DISTINCT t) FROM (SELECT unnest([{', '.join(repr(x) for x, _, _ in C.fleet_names(n))}]) AS t)) AS n_tables FROM (SELECT row_number() OVER (ORDER BY (i * 7919 + 17) % 10007, i) AS pos FROM range({a + b}) r(i)) GROUP BY 2" for w, (n, a, b) in workload.DATASETS.items())


def difficulty_levels(spark, sf):
    """The level of what each event asks; as in the streams, an event asks question event_id % 60."""
    levels = _qa(spark).select(F.col("qid").alias("k"), workload.difficulty("gold_sql").alias("level"))
    asked = table(spark, sf, "events").select(F.col("event_id").alias("qid"), (F.col("event_id") % 60).alias("k"))
    return asked.join(F.broadcast(levels), "k").select("qid", "level")  # sixty questions


_N = lambda p: f"len(regexp_extract_all(s, '{p}'))"
DIFFICULTY_SQL = f"WITH {QA_SQL}, u AS (SELECT qid, upper(gold_sql) AS s FROM qa), k AS (SELECT qid, {' + '.join(_N(p) for p in ('JOIN ', 'GROUP BY', 'HAVING', 'ORDER BY', 'LIMIT '))} AS parts, {' + '.join(_N(p) for p in ('[(]SELECT', 'UNION', 'EXCEPT', 'INTERSECT'))} AS nested FROM u), l AS (SELECT qid, CASE WHEN nested > 0 THEN 'extra' WHEN parts >= 3 THEN 'hard' WHEN parts >= 1 THEN 'medium' ELSE 'easy' END AS level FROM k), a AS (SELECT event_id AS qid, event_id % 60 AS k FROM events) SELECT a.qid, level FROM a JOIN l ON l.qid = a.k"


def examples_full(spark, sf):
    return _show(examples.full_schema(_qa(spark), _base(spark, sf)))


_WHOLE = "(SELECT length('Tables: ' || string_agg({}, '; ') || chr(10) || 'Question: ') FROM tok)"
_ANSWER = "CASE WHEN len(gold) = 0 THEN '#None#' ELSE array_to_string(gold, ', ') END"


def _whole_sql(text, answer=_ANSWER):
    return sql(f"SELECT qid, 0 AS slice_id, {answer} AS assistant, '' AS history, 1.0::DOUBLE AS weight, ({_WHOLE.format(text)} + length(question))::INT AS user_chars FROM qa", CAT, QA_SQL)


def examples_names_only(spark, sf):
    return _show(examples.names_only(_qa(spark), _base(spark, sf)))


def examples_sql_direct(spark, sf):
    return _show(examples.sql_direct(_qa(spark), _base(spark, sf)))


def _ex(spark, sf, **kw):
    b = _base(spark, sf)
    return _show(examples.sliced(_qa(spark), slicing.pack(groups.order(b), CAP), b, **kw)).drop("user_chars")


def examples_sliced_nohist(spark, sf):
    return _ex(spark, sf, history="none", balance="none").withColumn("assistant", _sorted_names("assistant"))


def _sorted_names(c):
    return F.array_join(F.array_sort(F.split(c, ", ")), ", ")


def examples_sliced_hist(spark, sf):
    return _ex(spark, sf, balance="none").withColumn("assistant", _sorted_names("assistant"))


def examples_balanced(spark, sf):
    return _ex(spark, sf).withColumn("assistant", _sorted_names("assistant"))


def examples_weighted(spark, sf):
    return _ex(spark, sf, balance="weight").withColumn("assistant", _sorted_names("assistant"))


def examples_per_table(spark, sf):
    return _ex(spark, sf, emission="per_table")


_T = "CASE WHEN len(target) = 0 THEN '#None#' ELSE array_to_string(target, ', ') END"
_H = "coalesce(array_to_string(history, ','), '')"
_EX = lambda body: sql(body, CAT, GRP, QA_SQL, STEPS)
NOHIST_SQL = _EX(f"SELECT qid, slice_id, {_T} AS assistant, '' AS history, 1.0::DOUBLE AS weight FROM hist")
HIST_SQL = _EX(f"SELECT qid, slice_id, {_T} AS assistant, {_H} AS history, 1.0::DOUBLE AS weight FROM hist")
BALANCED_SQL = _EX(f"SELECT qid, slice_id, {_T} AS assistant, {_H} AS history, 1.0::DOUBLE AS weight FROM hist UNION ALL SELECT qid, slice_id, {_T}, '', 1.0 FROM hist WHERE len(target) > 0")
WEIGHTED_SQL = _EX(f"SELECT qid, slice_id, {_T} AS assistant, {_H} AS history, CASE WHEN len(target) > 0 THEN 2.0 ELSE 1.0 END::DOUBLE AS weight FROM hist")
PER_TABLE_SQL = _EX(f"""SELECT qid, slice_id, assistant, history, 1.0::DOUBLE AS weight FROM (SELECT qid, slice_id, history AS h, target, unnest(gold) AS own, {_H} AS hs FROM hist) x,
LATERAL (SELECT CASE WHEN list_contains(target, own) THEN own ELSE '#None#' END AS assistant, hs AS history UNION ALL SELECT own, '' WHERE list_contains(target, own)) y""")


def examples_sql_union(spark, sf):
    b, qa = _base(spark, sf), _qa(spark)
    pred = linkers.NoisyOracle(3, 20, 20).predict(qa, b)
    return _show(examples.sql_pipeline(qa, pred, b))


NOISY = """names AS (SELECT list_sort(list(table_name)) AS names FROM tok),
pred AS (SELECT qid, question, gold, gold_sql, difficulty, list_sort(list_distinct(list_concat(list_filter(gold, lambda t, i: (qid * 7919 + (i - 1) * 104729 + {seed}) % 100 >= {miss}),
  CASE WHEN (qid * 6007 + {seed}) % 100 < {spurious} THEN [names[(qid % len(names) + 1)::INT]] ELSE [] END))) AS pred FROM qa, names)"""


def _noisy(seed, miss, spurious):
    return NOISY.format(seed=seed, miss=miss, spurious=spurious)


SQL_UNION_SQL = sql("SELECT qid, 0 AS slice_id, gold_sql AS assistant, '' AS history, 1.0::DOUBLE AS weight, (length('Tables: ') + length((SELECT string_agg(text, '; ') FROM tok WHERE list_contains(list_concat(pred, gold), table_name))) + length(chr(10) || 'Question: ') + length(question))::INT AS user_chars FROM pred", CAT, QA_SQL, _noisy(3, 20, 20))


def token_report(spark, sf):
    b, qa = _base(spark, sf), _qa(spark)
    sl = slicing.pack(groups.order(b), CAP)
    parts = examples.full_schema(qa, b).unionByName(examples.names_only(qa, b)).unionByName(examples.sliced(qa, sl, b, "none", "none")).unionByName(examples.sliced(qa, sl, b))
    return cost.token_report(parts)


def rendered_examples(spark, sf):
    """The whole training texts of the full-schema examples, role marks and all."""
    from ..functions import templates

    e = examples.full_schema(_qa(spark), _base(spark, sf))
    return e.select("qid", templates.render("link", F.col("user"), F.col("assistant")).alias("text"))


def examples_neg_sample(spark, sf):
    return _ex(spark, sf, balance="neg_sample").withColumn("assistant", _sorted_names("assistant"))


def examples_sql_gold(spark, sf):
    """The ablation that trains the generator on gold tables alone."""
    b, qa = _base(spark, sf), _qa(spark)
    return _show(examples.sql_pipeline(qa, linkers.NoisyOracle(3, 20, 20).predict(qa, b), b, "gold"))


def _points(spark, points):
    return spark.createDataFrame([(d, float(x), float(y)) for d, ps in points.items() for x, y in ps], "dataset int, x double, y double")


def _fit_sql(points):
    rows = ", ".join(f"({d}, {x}::DOUBLE, {y}::DOUBLE)" for d, ps in points.items() for x, y in ps)
    return f"SELECT dataset, round(regr_slope(y, x), 4) AS slope, round(regr_intercept(y, x), 2) AS intercept, round(regr_r2(y, x), 4) AS r2 FROM (VALUES {rows}) p(dataset, x, y) GROUP BY dataset"


def memory_fit(spark, sf):
    return cost.fit_frame(_points(spark, cost.MEMORY_POINTS))


def time_fit(spark, sf):
    return cost.fit_frame(_points(spark, cost.TIME_POINTS))


#: Ways to give a model a whole text: (name, batch, context window).
_GATES = [("whole", 1, 100_000), ("pair", 2, 100_000), ("whole_4k", 1, 4096)]


def _longest(spark, sf):
    """source, max_tokens: the longest text of each source of the documents."""
    n = tokens.count(F.coalesce("text", F.lit("")))
    return table(spark, sf, "documents").groupBy("source").agg(F.max(n).alias("max_tokens"))


def budget_gate(spark, sf):
    """Whether the longest text of a source fits the memory and the context window."""
    m, report = experiments.memory(1), _longest(spark, sf)
    out = None
    for name, batch, context in _GATES:
        one = cost.gate(report.select(F.concat_ws("/", "source", F.lit(name)).alias("variant"), "max_tokens"), m, batch, experiments.BUDGET_MB, context)
        out = one if out is None else out.unionByName(one)
    return out


def budget_caps(spark, sf):
    """The cap of slices in pairs within the memory that the longest text of a source takes alone."""
    m = experiments.memory(1)
    rows = _longest(spark, sf).select("source", F.ceil(F.lit(m.mb(0, 1)) + F.lit(m.per_token) * F.col("max_tokens")).cast("int").alias("budget_mb"))
    return rows.select("source", "budget_mb", slicing.Budget.caps(F.col("budget_mb"), 2, m, 100).alias("cap"))


LEX = linkers.LexicalLinker(0.3, 0.8)
_WORDS = lambda c: f"list_distinct(list_filter(list_transform(regexp_extract_all(lower({c}), '[a-z]+|[0-9]+'), lambda w: CASE WHEN length(w) > 3 THEN regexp_replace(w, 's$', '') ELSE w END), lambda w: w NOT IN ({', '.join(repr(x) for x in linkers.STOP)})))"
LEX_SQL = f"""tw AS (SELECT table_name, {_WORDS("replace(table_name || ' ' || string_agg(column_name, ' ' ORDER BY pos), '_', ' ')")} AS words FROM cols GROUP BY table_name),
w1 AS (SELECT table_name, unnest(words) AS word FROM tw), iw AS (SELECT word, ln(1 + 14.0::DOUBLE / count(*)) AS idf FROM w1 GROUP BY word),
qw AS (SELECT qid, unnest({_WORDS("question")}) AS word FROM qa), qi AS (SELECT qid, word, idf FROM qw JOIN iw USING (word)), qn AS (SELECT qid, sum(idf) AS norm FROM qi GROUP BY qid),
sc AS (SELECT qid, table_name, round(sum(idf) / any_value(norm), 6) AS score FROM qi JOIN w1 USING (word) JOIN qn USING (qid) GROUP BY qid, table_name)"""


def _preds(df):
    return df.select("qid", joined("pred_tables").alias("pred"), "n_calls")


def infer_lexical_once(spark, sf):
    return _preds(linking.infer_once(LEX, _qa(spark), _base(spark, sf)))


_PICK = "ch AS (SELECT {keys}, table_name FROM {src} s JOIN (SELECT {keys}, max(score) AS best FROM {src} GROUP BY {keys}) b USING ({keys}) WHERE score >= 0.3 AND score >= 0.8 * best - 1e-9)"
_FINAL = "SELECT q.qid, coalesce(string_agg(DISTINCT table_name, ',' ORDER BY table_name), '') AS pred, {calls}::INT AS n_calls FROM qa q LEFT JOIN ch USING (qid) GROUP BY q.qid"
ONCE_SQL = sql(_FINAL.format(calls=1), CAT, QA_SQL, LEX_SQL, _PICK.format(keys="qid", src="sc"))


def infer_lexical_sliced(spark, sf):
    b = _base(spark, sf)
    return _preds(linking.infer_sliced(LEX, _qa(spark), slicing.pack(groups.order(b), CAP), b))


SLICED_SQL = sql(_FINAL.format(calls="(SELECT count(*) FROM sl)"), CAT, GRP, QA_SQL, LEX_SQL, SL, "ss AS (SELECT sc.*, slice_id FROM sc JOIN pk USING (table_name))", _PICK.format(keys="qid, slice_id", src="ss"))


def infer_lexical_fold(spark, sf):
    b = _base(spark, sf)
    return _preds(linking.fold_lexical(LEX, _qa(spark), slicing.pack(groups.order(b), CAP), b))


def infer_cap_sweep(spark, sf):
    b, qa = _base(spark, sf), _qa(spark)
    o, out = groups.order(b), None
    for cap in (60, 100, 200, 315):
        one = metrics.link_scores(linking.infer_sliced(LEX, qa, slicing.pack(o, cap), b), qa).withColumn("cap", F.lit(cap))
        out = one if out is None else out.unionByName(one)
    return out


def noisy_oracle_predictions(spark, sf):
    return linkers.NoisyOracle(1, 10, 5).predict(_qa(spark), _base(spark, sf)).select("qid", joined("pred_tables").alias("pred"))


NOISY_SQL = sql("SELECT qid, array_to_string(pred, ',') AS pred FROM pred", CAT, QA_SQL, _noisy(1, 10, 5))
SCORES = """sc AS (SELECT qid, difficulty, (len(list_filter(pred, lambda t: NOT list_contains(gold, t))) = 0 AND len(list_filter(gold, lambda t: NOT list_contains(pred, t))) = 0)::INT AS total,
  (len(list_filter(gold, lambda t: NOT list_contains(pred, t))) = 0)::INT AS filtered, len(list_intersect(pred, gold)) AS hit, len(pred) AS np, len(gold) AS ng FROM pred)"""
AVG = "count(*) AS n, round(100 * avg(total), 4) AS tot_acc, round(100 * avg(filtered), 4) AS filt_acc, round(100 * avg(CASE WHEN np = 0 THEN (ng = 0)::INT ELSE hit::DOUBLE / np END), 4) AS avg_prec, round(100 * avg(CASE WHEN ng = 0 THEN 1 ELSE hit::DOUBLE / ng END), 4) AS avg_rec"


def _scored(spark, sf, seed=1, miss=15, spurious=15):
    qa = _qa(spark)
    return qa, linkers.NoisyOracle(seed, miss, spurious).predict(qa, _base(spark, sf))


def link_scores(spark, sf):
    qa, p = _scored(spark, sf)
    return metrics.link_scores(p, qa)


def link_scores_by_difficulty_cube(spark, sf):
    qa, p = _scored(spark, sf)
    return metrics.scored(p, qa, ["difficulty"]).cube("difficulty").agg(*metrics.averages(), F.grouping_id().cast("long").alias("level"))


def link_intervals(spark, sf):
    qa, p = _scored(spark, sf)
    return metrics.wilson(metrics.link_scores(p, qa).select("n", "tot_acc"), "tot_acc")


WILSON_SQL = sql(f"SELECT n, tot_acc, round(100 * (mid - half) / (1 + 3.8416 / n), 4) AS lo, round(100 * (mid + half) / (1 + 3.8416 / n), 4) AS hi FROM (SELECT n, tot_acc, tot_acc / 100 + 3.8416 / (2 * n) AS mid, 1.96 * sqrt(tot_acc / 100 * (1 - tot_acc / 100) / n + 3.8416 / (4.0 * n * n)) AS half FROM (SELECT {AVG} FROM sc))", CAT, QA_SQL, _noisy(1, 15, 15), SCORES)


def paired_mcnemar(spark, sf):
    qa, p = _scored(spark, sf)
    return metrics.paired_test(p, linkers.NoisyOracle(2, 30, 5).predict(qa, _base(spark, sf)), qa)


def link_bootstrap(spark, sf):
    qa, p = _scored(spark, sf)
    return metrics.bootstrap(p, qa)


BOOTSTRAP_SQL = sql("""SELECT round(max(m) FILTER (WHERE pos = 5), 4) AS lo, round(max(m) FILTER (WHERE pos = 195), 4) AS hi FROM (SELECT m, row_number() OVER (ORDER BY m, r) AS pos FROM (
  SELECT r, 100 * sum(total * w)::DOUBLE / sum(w) AS m FROM (SELECT r, total, (u > 0.3679)::INT + (u > 0.7358)::INT + (u > 0.9197)::INT + (u > 0.981)::INT + (u > 0.9963)::INT AS w FROM (SELECT r, total, ((qid * 7919 + r * 104729 + 31) % 1009) / 1009.0::DOUBLE AS u FROM sc, range(1, 201) x(r))) GROUP BY r))""", CAT, QA_SQL, _noisy(1, 15, 15), SCORES)


def vote_of_three(spark, sf):
    qa, b = _qa(spark), _base(spark, sf)
    return linkers.vote([linkers.NoisyOracle(s, 20, 20).predict(qa, b) for s in (1, 2, 3)], 2).select("qid", joined("pred_tables").alias("pred"))


VOTE_SQL = sql("SELECT q.qid, coalesce(string_agg(t, ',' ORDER BY t), '') AS pred FROM qa q LEFT JOIN (SELECT qid, t FROM (SELECT qid, unnest(pred) AS t FROM p1 UNION ALL SELECT qid, unnest(pred) FROM p2 UNION ALL SELECT qid, unnest(pred) FROM p3) GROUP BY qid, t HAVING count(*) >= 2) USING (qid) GROUP BY q.qid", CAT, QA_SQL, *(_noisy(s, 20, 20).replace("names AS", f"names{s} AS").replace("FROM qa, names)", f"FROM qa, names{s})").replace("pred AS (SELECT qid, question", f"p{s} AS (SELECT qid, question") for s in (1, 2, 3)))


def prune_columns(spark, sf):
    qa = _qa(spark).select("qid", "db_id", "question", F.explode("gold_tables").alias("table_name"))
    return C.prune_columns(qa, _base(spark, sf), linkers.word_list).select("qid", "table_name", F.array_join("columns", ",").alias("columns"))


def execution_accuracy(spark, sf):
    from .sqlgen import NoisyGenerator

    C.register_fleet(spark, sf, [(t, t, "true") for t in C.TABLES])
    qa = _qa(spark)
    return metrics.execution_accuracy(spark, NoisyGenerator(30).generate(qa), qa)


def _damaged(q) -> str:
    return f"SELECT -1 AS x FROM ({q[4]}) t" if (q[0] * 7919 + 1) % 100 < 30 else q[4]


_ROWS = "(SELECT list_sort(list(r::VARCHAR)) FROM ({}) r)"
EXECUTION_SQL = " UNION ALL ".join(f"SELECT {q[0]}::BIGINT AS qid, ({_ROWS.format(_damaged(q))} IS NOT DISTINCT FROM {_ROWS.format(q[4])})::INT AS ex, 'OK' AS status" for q in SMALL_QA)


def _rewritten(spark):
    """Three predictions for each question: the gold text in other spelling, with its conditions turned round or a limit more, and another query."""
    gold = F.col("gold_sql")
    forms = F.array(F.concat(F.lit("  "), F.lower(F.regexp_replace(gold, " ", "  ")), F.lit(" ;")), F.concat(gold, F.lit(" LIMIT 7")), F.regexp_replace(gold, "WHERE (.*)$", "WHERE $1 AND 1 = 1"), F.regexp_replace(gold, "count", "max"))
    return _qa(spark).select("qid", "gold_sql", F.posexplode(forms).alias("form", "sql"))


def logical_match(spark, sf):
    df = _rewritten(spark)
    both = metrics.logical_match(metrics.logical_match(df, "text").withColumnRenamed("em", "em_text"), "clause_set")
    return both.select("qid", "form", "em_text", F.col("em").alias("em_clauses"))


def _sql_normal(c):
    return f"trim(regexp_replace(regexp_replace(regexp_replace(lower({c}), '\\s+', ' ', 'g'), '\\s*([(),=<>+*/-])\\s*', '\\1', 'g'), '\\s*;\\s*$', '', 'g'))"


def _sql_clauses(c):
    marked = f"regexp_replace(regexp_replace({_sql_normal(c)}, '\\b(select|from|where|group by|having|order by|limit|union|except|intersect)\\b', chr(1) || '\\1', 'g'), ' and ', chr(1) || 'and ', 'g')"
    part = "trim(regexp_replace(regexp_replace(p, '^where ', 'and '), '^and ', '? '))"
    return f"list_sort(list_distinct(list_filter(list_transform(string_split({marked}, chr(1)), lambda p: {part}), lambda p: p <> '')))"


LOGICAL_SQL = f"""WITH {QA_SQL}, f AS (SELECT qid, gold_sql, unnest([0, 1, 2, 3]) AS form, unnest(['  ' || lower(replace(gold_sql, ' ', '  ')) || ' ;', gold_sql || ' LIMIT 7', regexp_replace(gold_sql, 'WHERE (.*)$', 'WHERE \\1 AND 1 = 1'), replace(gold_sql, 'count', 'max')]) AS sql FROM qa)
SELECT qid, form::INT AS form, ({_sql_normal('sql')} = {_sql_normal('gold_sql')})::INT AS em_text, ({_sql_clauses('sql')} = {_sql_clauses('gold_sql')})::INT AS em_clauses FROM f"""


def plan_matches(spark, sf):
    """Logical match by canonical plans: conditions turned round and other names match, another constant does not."""
    C.register_fleet(spark, sf, [(t, t, "true") for t in C.TABLES])
    rows = [(q[0], f"SELECT * FROM ({q[4]}) t WHERE 1 = 1", q[4]) for q in SMALL_QA] + [(100 + q[0], f"SELECT * FROM ({q[4]}) t WHERE 1 = 0", q[4]) for q in SMALL_QA]
    return spark.createDataFrame([(i, int(metrics.plan_match(spark, a, b))) for i, a, b in rows], "qid long, em_plan int")


PLAN_SQL = f"WITH {QA_SQL} SELECT qid, 1 AS em_plan FROM qa UNION ALL SELECT qid + 100, 0 FROM qa"


# --- carriers: the methods on the given rows


def docs_pack(spark, sf):
    d = table(spark, sf, "documents").select(F.col("doc_id").alias("pos"), F.ceil(F.length(F.coalesce("text", F.lit(""))) / 4).alias("n_tokens"))
    return slicing.pack_distributed(d, 4096, 20_000).groupBy("slice_id").agg(F.count("*").alias("n"), F.sum("n_tokens").alias("tokens"), F.min("pos").alias("first"))


DOCS_PACK_SQL = f"""WITH RECURSIVE d AS (SELECT row_number() OVER (ORDER BY doc_id) AS pos, doc_id AS table_name, ceil(length(coalesce(text, '')) / 4.0)::BIGINT AS n_tokens, 1 AS group_id FROM documents), {packed(4096, source="d")}
SELECT slice_id::BIGINT AS slice_id, count(*) AS n, sum(n_tokens)::BIGINT AS tokens, min(table_name) AS first FROM pk GROUP BY slice_id"""


#: A passage is looked for by up to so many whole words inside it; sets up to MOST_ANCHORS passages are broadcast.
ANCHOR, MOST_ANCHORS = 4, 1_000_000


def _anchors(passages, id_col: str = "item_id"):
    """id, passage, k, anchor: a hash of the first k words that stand whole in any text with the passage (its second and so on)."""
    w = F.split("passage", "[ \\t\\n]+")
    k = F.least(F.greatest(F.size("w") - 2, F.lit(0)), F.lit(ANCHOR))
    return passages.withColumn("w", w).withColumn("k", k).select(id_col, "passage", "k", F.xxhash64("k", F.array_join(F.slice("w", F.lit(2), F.col("k")), " ")).alias("anchor"))


def _gram(k: int):
    return lambda i: F.xxhash64(F.lit(k), F.concat_ws(" ", *(F.col("w")[i + j - 1] for j in range(k))))


def _anchored(spark, sf):
    """(item_id, doc_id) of the passages whose anchor a document holds, the passages, and the documents."""
    b = _anchors(table(spark, sf, "benchmark").where(F.length("text") > 0).select("item_id", F.col("text").alias("passage")))
    sizes = {r.k: r.n for r in b.groupBy("k").agg(F.count("*").alias("n")).collect()}  # five sizes at most
    d = table(spark, sf, "documents")
    split = d.where("text IS NOT NULL").select("doc_id", F.split("text", "[ \\t\\n]+").alias("w"))  # once a text, not inside the lambda
    pairs = None
    for k in sorted(x for x in sizes if x):
        gram = F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), _gram(k))
        grams = split.where(F.size("w") >= k).select("doc_id", F.explode(gram).alias("anchor"))
        own = b.where(F.col("k") == k).select("item_id", "anchor")
        hit = grams.join(F.broadcast(own) if sizes[k] <= MOST_ANCHORS else own.hint("merge"), "anchor").select("item_id", "doc_id")
        pairs = hit if pairs is None else pairs.union(hit)
    if pairs is None:
        pairs = spark.createDataFrame([], "item_id long, doc_id long")
    return pairs.distinct(), b, d.select("doc_id", "text"), sizes


def passage_link(spark, sf):
    """Which documents hold which benchmark passage: by anchors of whole words, then checked; passages of two words and less, which may stand inside words, are looked for in every text."""
    pairs, b, d, sizes = _anchored(spark, sf)
    found = pairs.join(d, "doc_id").join(b.select("item_id", "passage"), "item_id").where(F.contains("text", F.col("passage"))).select("item_id", "doc_id")
    if sizes.get(0):  # a query set against all rows
        few = b.where("k = 0").select("item_id", "passage")
        found = found.union(d.join(F.broadcast(few) if sizes[0] <= MOST_ANCHORS else few, F.contains("text", F.col("passage"))).select("item_id", "doc_id"))
    return found


PASSAGE_SQL = "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text) WHERE length(b.text) > 0"


def passage_scores(spark, sf):
    """Documents as tables, passages as questions: the anchors' answer against the documents that hold the passage."""
    sets = lambda df, name: df.groupBy(F.col("item_id").alias("qid")).agg(F.array_sort(F.collect_set(F.col("doc_id").cast("string"))).alias(name))
    pairs, b, _, _ = _anchored(spark, sf)
    gold = b.select(F.col("item_id").alias("qid")).join(sets(passage_link(spark, sf), "gold_tables"), "qid", "left").withColumn("gold_tables", F.coalesce("gold_tables", F.array().cast("array<string>")))
    return metrics.link_scores(sets(pairs, "pred_tables"), gold)


def dense_link_topk(spark, sf):
    v = table(spark, sf, "embeddings")
    near = linkers.DenseLinker(3).nearest(v.where("vec_id % 50 = 0"), v)
    return near.select("query_id", "vec_id", (F.round(F.col("score") * 1e4) / 1e4).alias("score"), "rank")  # as SQL rounds: the product, not the decimal digits


DENSE_SQL = """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), s AS (SELECT a.vec_id AS query_id, b.vec_id, round(list_cosine_similarity(a.e, b.e), 6) AS s FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id)
SELECT query_id, vec_id, round(s, 4) AS score, rank FROM (SELECT *, (row_number() OVER (PARTITION BY query_id ORDER BY s DESC, vec_id))::INT AS rank FROM s) WHERE rank <= 3"""


def host_groups(spark, sf):
    p = table(spark, sf, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host"))
    return p.groupBy("host").agg(F.min("page_id").alias("group_key"), F.count("*").alias("n"))


HOST_SQL = "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, min(page_id) AS group_key, count(*) AS n FROM pages GROUP BY 1"


def label_balance(spark, sf):
    x = table(spark, sf, "labels").select("doc_id", F.when(F.col("quality") == 1, "good").otherwise("#None#").alias("target"))
    copies = F.when(F.col("target") == "good", F.array(F.lit(1), F.lit(0))).otherwise(F.array(F.lit(1)))
    return x.select("doc_id", "target", F.explode(copies).alias("with_history")).groupBy("target", "with_history").agg(F.count("*").alias("n"))


LABEL_SQL = "WITH x AS (SELECT CASE WHEN quality = 1 THEN 'good' ELSE '#None#' END AS target FROM labels) SELECT target, with_history, count(*) AS n FROM (SELECT target, 1 AS with_history FROM x UNION ALL SELECT target, 0 FROM x WHERE target = 'good') GROUP BY ALL"


def conversation_history(spark, sf):
    w = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf, "conversations").select("conv_id", "turn", "role", F.array_join(F.collect_list("role").over(w), ",").alias("before"), F.coalesce(F.sum(F.length("text")).over(w), F.lit(0)).alias("chars_before"))


CONVERSATION_SQL = "SELECT conv_id, turn, role, coalesce(string_agg(role, ',') OVER w, '') AS before, coalesce(sum(length(text)) OVER w, 0)::BIGINT AS chars_before FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"


def cost_tradeoff(spark, sf):
    return experiments.tradeoff(spark, groups.order(_base(spark, sf)), 1, [50, 100, 200, 315])


# fixed values: published rows (dataset, model, method, total accuracy, MB)
PUBLISHED = [(2, "A", "slice_wise", 94.38, 45506.0), (2, "A", "full_schema", 96.63, 78772.0), (2, "B", "slice_wise", 89.89, 38374.0), (2, "B", "full_schema", 92.70, 67342.0)]


def published_saving(spark, sf):
    """Memory saved and accuracy lost against the full-schema linker, from the published rows."""
    return cost.compare(spark.createDataFrame(PUBLISHED, "dataset int, model string, method string, tot_acc double, mem_mb double"))


SAVING_SQL = f"""WITH r(dataset, model, method, acc, mb) AS (VALUES {', '.join(f"({d}, '{m}', '{x}', {a}::DOUBLE, {b}::DOUBLE)" for d, m, x, a, b in PUBLISHED)})
SELECT s.dataset, s.model, s.method, round(100 * (1 - s.mb / f.mb), 2) AS saving_pct, round(f.acc - s.acc, 2) AS loss_points FROM r s JOIN r f ON s.model = f.model AND s.dataset = f.dataset AND f.method = 'full_schema' WHERE s.method <> 'full_schema'"""


def exp_methods(spark, sf):
    return experiments.methods(spark, sf)


def exp_train_granularity(spark, sf):
    return experiments.train_granularity(spark, sf)


def exp_history(spark, sf):
    return experiments.history(spark, sf)


def exp_infer_granularity(spark, sf):
    return experiments.infer_granularity(spark, sf)


def exp_end_to_end(spark, sf):
    return experiments.end_to_end(spark, sf)


def nation_groups(spark, sf):
    c, n = table(spark, sf, "customer"), table(spark, sf, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.min("c_custkey").alias("group_key"), F.count("*").alias("n"))  # twenty-five rows


NATION_SQL = "SELECT n_name, min(c_custkey) AS group_key, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"


def queries() -> dict:
    names = [
        catalog_columns, render_schema, fk_inclusion_exact, fk_inclusion_sketch, unique_columns, token_count_word, token_count_char4, token_count_bpe, reference_split, correlation_groups, correlation_groups_by_joins, correlation_groups_per_fk,
        slice_order, pack_slices, pack_slices_small, pack_slices_group_boundary, pack_first_fit, pack_split_columns, slice_coverage, slice_cap_sweep, cap_search, qa_split, workload_sizes, difficulty_levels, examples_full, examples_names_only,
        examples_sql_direct, examples_sliced_nohist, examples_sliced_hist, examples_balanced, examples_weighted, examples_per_table, examples_sql_union, token_report, rendered_examples, examples_neg_sample, examples_sql_gold, memory_fit, time_fit, budget_gate, budget_caps, infer_lexical_once,
        infer_lexical_sliced, infer_lexical_fold, infer_cap_sweep, noisy_oracle_predictions, link_scores, link_scores_by_difficulty_cube, link_intervals, link_bootstrap, render_samples, paired_mcnemar, vote_of_three, prune_columns, execution_accuracy, logical_match, plan_matches, docs_pack, passage_link, passage_scores, nation_groups,
        dense_link_topk, host_groups, label_balance, conversation_history, cost_tradeoff, published_saving, exp_methods, exp_train_granularity, exp_history, exp_infer_granularity, exp_end_to_end,
    ]
    return {f.__name__: f for f in names}


RENDER_SQL = sql("""SELECT c.table_name, c.table_name AS names, c.table_name || '(' || string_agg(column_name, ', ' ORDER BY pos) || ')' AS columns, any_value(t.text) AS types,
  any_value(substr(t.text, 1, length(t.text) - 1) || coalesce((SELECT ', ' || string_agg('fk(' || col || '->' || ref_table || '.' || ref_col || ')', ', ' ORDER BY col) FROM fk WHERE fk.table_name = c.table_name), '') || ')') AS keys
FROM cols c JOIN tok t USING (table_name) GROUP BY c.table_name""", CAT)
_TOTAL = "(len(list_filter(pred, lambda t: NOT list_contains(gold, t))) = 0 AND len(list_filter(gold, lambda t: NOT list_contains(pred, t))) = 0)::INT"
_SECOND = _noisy(2, 30, 5).replace("names AS", "names2 AS").replace("FROM qa, names)", "FROM qa, names2)").replace("pred AS (SELECT qid, question", "pred2 AS (SELECT qid, question")
PAIRED_SQL = sql(f"""SELECT n, only_a, only_b, CASE WHEN only_a + only_b > 0 THEN round(greatest(abs(only_a - only_b) - 1, 0)::DOUBLE * greatest(abs(only_a - only_b) - 1, 0) / (only_a + only_b), 4) ELSE 0.0 END AS chi2
FROM (SELECT count(*) AS n, count(*) FILTER (WHERE x > y) AS only_a, count(*) FILTER (WHERE x < y) AS only_b FROM (SELECT qid, {_TOTAL} AS x FROM pred) a JOIN (SELECT qid, {_TOTAL} AS y FROM pred2) b USING (qid))""", CAT, QA_SQL, _noisy(1, 15, 15), _SECOND)


def _tradeoff_sql(caps):
    m, t = experiments.memory(1), cost.TimeModel.fit(cost.TIME_POINTS[1])
    one = " UNION ALL ".join(f"SELECT {c} AS cap, max(slice_id)::BIGINT AS n_slices FROM pk{c}" for c in caps)
    return sql(f"SELECT cap, n_slices, round({m.base!r}::DOUBLE + {2 * m.per_token!r}::DOUBLE * cap, 1) AS est_mb, round({t.fixed!r}::DOUBLE + {t.per_call!r}::DOUBLE * n_slices, 3) AS est_s FROM ({one})", CAT, GRP, *(packed(c, f"pk{c}") for c in caps))


_M = "(SELECT regr_intercept(y, x) FROM p) AS base, (SELECT regr_slope(y, x) FROM p) / 2 AS per_token"
_P1 = "p(x, y) AS (VALUES " + ", ".join(f"({x}::DOUBLE, {y}::DOUBLE)" for x, y in cost.MEMORY_POINTS[1]) + f"), m AS (SELECT {_M})"
_LONGEST = r"l AS (SELECT source, max(len(regexp_extract_all(coalesce(text, ''), '[A-Za-z]+|[0-9]+|[^\sA-Za-z0-9]')))::INT AS max_tokens FROM documents GROUP BY source)"
GATE_SQL = f"""WITH {_P1}, {_LONGEST}, g(name, batch, context) AS (VALUES {", ".join(f"('{a}', {b}, {c})" for a, b, c in _GATES)}), e AS (SELECT *, base + per_token * batch * max_tokens AS mb FROM l, g, m)
SELECT concat_ws('/', source, name) AS variant, max_tokens, round(mb, 1) AS est_mb, CASE WHEN max_tokens > context THEN 'CONTEXT_EXCEEDED' WHEN mb > {experiments.BUDGET_MB} THEN 'OOM' ELSE 'OK' END AS status FROM e"""
CAPS_SQL = f"WITH {_P1}, {_LONGEST}, b AS (SELECT source, ceil(base + per_token * max_tokens)::INT AS b FROM l, m) SELECT source, b AS budget_mb, (trunc((b - base) / (per_token * 2)) - 100)::INT AS cap FROM b, m"
CAP_SEARCH_SQL = sql("""SELECT wanted::INT AS wanted, min(cap)::INT AS cap, arg_min(n, cap)::INT AS slices FROM range(1, 8) w(wanted) JOIN (SELECT cap, max(k) AS n FROM every GROUP BY cap) c ON n <= wanted GROUP BY wanted""", CAT, GRP,
    "caps AS (SELECT i AS cap FROM range((SELECT max(n_tokens) + 1 FROM tok), (SELECT sum(n_tokens)::BIGINT + 2 FROM tok)) r(i))",
    "every AS (SELECT cap, o.pos, o.n_tokens AS total, 1 AS k FROM caps, ord o WHERE o.pos = 1 UNION ALL SELECT e.cap, o.pos, CASE WHEN e.total + o.n_tokens >= e.cap THEN o.n_tokens ELSE e.total + o.n_tokens END, e.k + (e.total + o.n_tokens >= e.cap)::INT FROM every e JOIN ord o ON o.pos = e.pos + 1)")
_TOKENS = lambda c: f"len(regexp_extract_all({c}, '[A-Za-z]+|[0-9]+|[^\\sA-Za-z0-9]'))"
SPLIT_SQL = sql(f"SELECT table_name, part::INT AS part, string_agg(column_name, ',' ORDER BY pos) AS columns FROM parts GROUP BY ALL", CAT,
    f"sized AS (SELECT c.table_name, c.column_name, c.pos, {_TOKENS("column_name || ' ' || type || ','")} AS w, 2 + {_TOKENS('c.table_name')} AS f FROM cols c JOIN tok t USING (table_name) WHERE n_tokens >= 40)",
    "parts AS (SELECT table_name, column_name, pos, f, f + w AS total, 1 AS part FROM sized WHERE pos = 1 UNION ALL SELECT s.table_name, s.column_name, s.pos, s.f, CASE WHEN p.total + s.w >= 40 THEN s.f + s.w ELSE p.total + s.w END, p.part + (p.total + s.w >= 40)::INT FROM parts p JOIN sized s ON s.table_name = p.table_name AND s.pos = p.pos + 1)")
PRUNE_SQL = sql(f"""SELECT qid, table_name, coalesce(string_agg(column_name, ',' ORDER BY pos) FILTER (WHERE ends_with(column_name, 'key') OR ends_with(column_name, '_id') OR (table_name, column_name) IN (SELECT table_name, col FROM fk)
  OR len(list_intersect({_WORDS("replace(column_name, '_', ' ')")}, q)) > 0), '') AS columns FROM (SELECT qid, unnest(gold) AS table_name, {_WORDS("question")} AS q FROM qa) JOIN cols USING (table_name) GROUP BY qid, table_name""", CAT, QA_SQL)
FOLD = f"""known AS (SELECT list_distinct(flatten(list(words))) AS words FROM tw),
qq AS (SELECT qid, list_intersect({_WORDS("question")}, (SELECT words FROM known)) AS q FROM qa),
sw AS (SELECT slice_id, list({{'t': table_name, 'w': words}} ORDER BY pos) AS ts FROM pk JOIN tw USING (table_name) GROUP BY slice_id),
fold AS (SELECT qid, q, 0 AS slice_id, []::VARCHAR[] AS chosen, []::VARCHAR[] AS seen FROM qq
UNION ALL SELECT qid, q, slice_id, list_concat(chosen, list_transform(kept, lambda x: x.t)), list_concat(seen, flatten(list_transform(kept, lambda x: x.w))) FROM (
  SELECT *, list_filter(scored, lambda x: x.s >= 0.3 AND x.s >= 0.8 * best - 1e-9) AS kept FROM (
    SELECT *, list_max(list_transform(scored, lambda x: x.s)) AS best FROM (
      SELECT f.qid, f.q, w.slice_id, f.chosen, f.seen, list_transform(w.ts, lambda t: {{'s': (len(list_intersect(f.q, t.w)) - 0.5::DOUBLE * len(list_intersect(list_intersect(f.q, t.w), f.seen))) / greatest(len(f.q), 1), 't': t.t, 'w': t.w}}) AS scored FROM fold f JOIN sw w ON w.slice_id = f.slice_id + 1))))"""
FOLD_SQL = sql("SELECT qid, array_to_string(list_sort(list_distinct(chosen)), ',') AS pred, slice_id::INT AS n_calls FROM fold WHERE slice_id = (SELECT max(slice_id) FROM sw)", CAT, GRP, QA_SQL, LEX_SQL.split(",\nw1 AS")[0], packed(CAP), FOLD)
STREAM_LINK_SQL = sql("SELECT e.event_id AS qid, array_to_string(list_sort(list_distinct(chosen)), ',') AS pred, slice_id::INT AS n_calls FROM events e JOIN fold f ON f.qid = e.event_id % 60 WHERE slice_id = (SELECT max(slice_id) FROM sw)", CAT, GRP, QA_SQL, LEX_SQL.split(",\nw1 AS")[0], packed(CAP), FOLD)
_SYS = {k: v.replace("'", "''") for k, v in __import__("slicelink.functions.templates", fromlist=["SYSTEM"]).SYSTEM.items()}
REPORT_SQL = sql(f"""SELECT variant, count(*) AS n_examples, max({_TOKENS('sys')} + {_TOKENS('usr')} + {_TOKENS('ans')})::INT AS max_tokens, sum({_TOKENS('sys')} + {_TOKENS('usr')} + {_TOKENS('ans')})::BIGINT AS sum_tokens, sum({_TOKENS('ans')})::BIGINT AS label_tokens, sum(h)::BIGINT AS history_names FROM (
  SELECT 'full_schema' AS variant, '{_SYS['link']}' AS sys, 'Tables: ' || (SELECT string_agg(text, '; ') FROM tok) || chr(10) || 'Question: ' || question AS usr, {_ANSWER} AS ans, 0 AS h FROM qa
  UNION ALL SELECT 'names_only', '{_SYS['link']}', 'Tables: ' || (SELECT string_agg(table_name, '; ') FROM tok) || chr(10) || 'Question: ' || question, {_ANSWER}, 0 FROM qa
  UNION ALL SELECT 'sliced_none', '{_SYS['slice']}', 'Tables: ' || stext || chr(10) || 'Already chosen: #None#' || chr(10) || 'Question: ' || question, {_T}, 0 FROM hist JOIN stext USING (slice_id)
  UNION ALL SELECT 'sliced_gold', '{_SYS['slice']}', 'Tables: ' || stext || chr(10) || 'Already chosen: ' || CASE WHEN len(hh) = 0 THEN '#None#' ELSE array_to_string(hh, ', ') END || chr(10) || 'Question: ' || question, {_T}, len(hh) FROM (SELECT *, coalesce(history, []) AS hh FROM hist UNION ALL SELECT *, [] FROM hist WHERE len(target) > 0) x JOIN stext USING (slice_id)
) GROUP BY variant""", CAT, GRP, QA_SQL, STEPS, "stext AS (SELECT slice_id, string_agg(text, '; ' ORDER BY pos) AS stext FROM pk JOIN tok USING (table_name) GROUP BY slice_id)")
RENDERED_SQL = sql(f"SELECT qid, '<system>{_SYS['link']}<user>Tables: ' || (SELECT string_agg(text, '; ' ORDER BY table_name) FROM tok) || chr(10) || 'Question: ' || question || '<assistant>' || {_ANSWER} || '<end>' AS text FROM qa", CAT, QA_SQL)
NEG_SQL = _EX(f"SELECT qid, slice_id, {_T} AS assistant, {_H} AS history, 1.0::DOUBLE AS weight FROM hist WHERE len(target) > 0 OR (qid * 31 + slice_id) % 2 = 0")
SQL_GOLD_SQL = SQL_UNION_SQL.replace("list_contains(list_concat(pred, gold), table_name)", "list_contains(gold, table_name)")
CAP_SWEEP_SCORES = " UNION ALL ".join(f"SELECT {c} AS cap, * FROM (SELECT {AVG} FROM (SELECT qid, (pred = gold)::INT AS total, (len(list_intersect(pred, gold)) = len(gold))::INT AS filtered, len(list_intersect(pred, gold)) AS hit, len(pred) AS np, len(gold) AS ng FROM (SELECT q.qid, list_sort(any_value(q.gold)) AS gold, coalesce(list(DISTINCT table_name ORDER BY table_name) FILTER (WHERE table_name IS NOT NULL), []) AS pred FROM qa q LEFT JOIN ch{c} USING (qid) GROUP BY q.qid)))" for c in (60, 100, 200, 315))
INFER_SWEEP_SQL = sql(CAP_SWEEP_SCORES, CAT, GRP, QA_SQL, LEX_SQL, *(x for c in (60, 100, 200, 315) for x in (packed(c, f"pk{c}"), f"ss{c} AS (SELECT sc.*, slice_id FROM sc JOIN pk{c} USING (table_name))", _PICK.format(keys="qid, slice_id", src=f"ss{c}").replace("ch AS", f"ch{c} AS", 1))))
_GRAMS = "list_distinct([array_to_string(w[i:i + 3], ' ') FOR i IN range(1, len(w) - 2)])"
PASSAGE_SCORES_SQL = f"""WITH b AS (SELECT item_id, text, array_to_string(string_split_regex(text, '[ \\t\\n]+')[2:5], ' ') AS anchor FROM benchmark WHERE length(text) > 0), d AS (SELECT doc_id, text, string_split_regex(text, '[ \\t\\n]+') AS w FROM documents),
hit AS (SELECT DISTINCT item_id, doc_id FROM (SELECT doc_id, unnest({_GRAMS}) AS anchor FROM d) JOIN b USING (anchor)), own AS (SELECT item_id, doc_id FROM b JOIN d ON contains(d.text, b.text)),
s AS (SELECT item_id, (SELECT count(*) FROM hit h WHERE h.item_id = b.item_id) AS np, (SELECT count(*) FROM own o WHERE o.item_id = b.item_id) AS ng, (SELECT count(*) FROM hit h JOIN own o USING (item_id, doc_id) WHERE h.item_id = b.item_id) AS hit FROM b),
sc AS (SELECT *, (hit = np AND hit = ng)::INT AS total, (hit = ng)::INT AS filtered FROM s) SELECT {AVG} FROM sc"""


def oracle_sql() -> dict[str, str]:
    return {
        "link_bootstrap": BOOTSTRAP_SQL, "render_samples": SAMPLES_SQL, "budget_gate": GATE_SQL, "budget_caps": CAPS_SQL, "cap_search": CAP_SEARCH_SQL, "pack_split_columns": SPLIT_SQL, "prune_columns": PRUNE_SQL, "infer_lexical_fold": FOLD_SQL, "token_report": REPORT_SQL, "rendered_examples": RENDERED_SQL,
        "examples_neg_sample": NEG_SQL, "examples_sql_gold": SQL_GOLD_SQL, "infer_cap_sweep": INFER_SWEEP_SQL, "execution_accuracy": EXECUTION_SQL, "plan_matches": PLAN_SQL, "nation_groups": NATION_SQL, "passage_scores": PASSAGE_SCORES_SQL,
        "catalog_columns": f"WITH {COLS} SELECT table_name, pos, column_name, type FROM cols",
        "render_schema": RENDER_SQL, "paired_mcnemar": PAIRED_SQL, "cost_tradeoff": _tradeoff_sql([50, 100, 200, 315]), "fk_inclusion_exact": FK_SQL, "unique_columns": UNIQUE_SQL,
        "token_count_word": sql("SELECT table_name, n_tokens FROM tok", CAT), "token_count_char4": sql("SELECT table_name, ceil(length(text) / 4.0)::INT AS n_tokens FROM tok", CAT),
        "reference_split": sql("SELECT t.table_name, tied.table_name IS NOT NULL AS has_reference FROM tok t LEFT JOIN tied USING (table_name)", CAT, GRP),
        "correlation_groups": sql("SELECT * FROM grp", CAT, GRP), "correlation_groups_by_joins": sql("SELECT * FROM grp", CAT, GRP),
        "correlation_groups_per_fk": sql("SELECT table_name, min(group_key) AS group_key FROM (SELECT ref_table AS group_key, table_name FROM fk UNION ALL SELECT ref_table, ref_table FROM fk) GROUP BY table_name", CAT),
        "slice_order": sql("SELECT table_name, has_reference, group_id::INT AS group_id, pos::INT AS pos FROM ord", CAT, GRP),
        "pack_slices": _pk_sql(CAP), "pack_slices_small": _pk_sql(50), "pack_slices_group_boundary": _pk_sql(CAP, by_group=True),
        "slice_coverage": sql("SELECT (SELECT count(*) FROM tok) AS n_tables, count(DISTINCT table_name) AS n_placed, (SELECT count(*) FROM tok) - count(DISTINCT table_name) AS n_missing, (SELECT count(DISTINCT table_name) FROM pk WHERE table_name NOT IN (SELECT table_name FROM tok)) AS n_extra, count(*) - count(DISTINCT table_name) AS n_twice FROM pk", CAT, GRP, packed(CAP)),
        "slice_cap_sweep": SWEEP_SQL, "qa_split": QA_SPLIT_SQL, "workload_sizes": WORKLOAD_SQL, "difficulty_levels": DIFFICULTY_SQL,
        "examples_full": _whole_sql("text"), "examples_names_only": _whole_sql("table_name"), "examples_sql_direct": _whole_sql("text", "gold_sql"),
        "examples_sliced_nohist": NOHIST_SQL, "examples_sliced_hist": HIST_SQL, "examples_balanced": BALANCED_SQL, "examples_weighted": WEIGHTED_SQL, "examples_per_table": PER_TABLE_SQL, "examples_sql_union": SQL_UNION_SQL,
        "memory_fit": _fit_sql(cost.MEMORY_POINTS), "time_fit": _fit_sql(cost.TIME_POINTS),
        "infer_lexical_once": ONCE_SQL, "infer_lexical_sliced": SLICED_SQL, "noisy_oracle_predictions": NOISY_SQL,
        "link_scores": sql(f"SELECT {AVG} FROM sc", CAT, QA_SQL, _noisy(1, 15, 15), SCORES),
        "link_scores_by_difficulty_cube": sql(f"SELECT difficulty, {AVG}, grouping_id(difficulty) AS level FROM sc GROUP BY CUBE (difficulty)", CAT, QA_SQL, _noisy(1, 15, 15), SCORES),
        "link_intervals": WILSON_SQL, "vote_of_three": VOTE_SQL, "logical_match": LOGICAL_SQL, "docs_pack": DOCS_PACK_SQL, "passage_link": PASSAGE_SQL, "dense_link_topk": DENSE_SQL,
        "host_groups": HOST_SQL, "label_balance": LABEL_SQL, "conversation_history": CONVERSATION_SQL, "published_saving": SAVING_SQL,
    }
