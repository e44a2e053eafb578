"""Catalogs of tables: description from footers, rendering, foreign keys declared or discovered, shards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import tokens

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
DECLARED = [
    ("orders", ["o_custkey"], "customer", ["c_custkey"]), ("lineitem", ["l_orderkey"], "orders", ["o_orderkey"]),
    ("lineitem", ["l_partkey"], "part", ["p_partkey"]), ("lineitem", ["l_suppkey"], "supplier", ["s_suppkey"]),
    ("customer", ["c_nationkey"], "nation", ["n_nationkey"]), ("supplier", ["s_nationkey"], "nation", ["n_nationkey"]),
    ("nation", ["n_regionkey"], "region", ["r_regionkey"]), ("labels", ["doc_id"], "documents", ["doc_id"]),
]
COLUMN = "struct<name:string,type:string,nullable:boolean,comment:string>"
FK = "struct<cols:array<string>,ref_table:string,ref_cols:array<string>,origin:string>"
CATALOG = f"db_id string, table_name string, base_table string, predicate string, columns array<{COLUMN}>, fks array<{FK}>, text string, n_tokens int"
DETAILS = ("names", "columns", "types", "keys")


def type_name(t: T.DataType) -> str:
    """The one printing of a type used in schema texts."""
    if isinstance(t, (T.TimestampType, T.TimestampNTZType)):
        return "timestamp"
    if isinstance(t, T.ArrayType):
        return f"array<{type_name(t.elementType)}>"
    if isinstance(t, T.MapType):
        return f"map<{type_name(t.keyType)},{type_name(t.valueType)}>"
    if isinstance(t, T.StructType):
        return f"struct<{','.join(f'{f.name}:{type_name(f.dataType)}' for f in t)}>"
    return t.simpleString()


def columns_of(schema: T.StructType) -> list[tuple]:
    return [(f.name, type_name(f.dataType), f.nullable, f.metadata.get("comment")) for f in schema]


def rendered(detail: str = "types", columns: str = "columns", name: str = "table_name", fks: str = "fks"):
    """The description text of a table as a Column: its name; its columns; their types; its foreign keys."""
    if detail == "names":
        return F.col(name)
    part = (lambda c: c["name"]) if detail == "columns" else lambda c: F.concat(c["name"], F.lit(" "), c["type"])
    cols = F.transform(F.col(columns), part)
    if detail == "keys":
        keys = F.transform(F.col(fks), lambda k: F.concat(F.lit("fk("), F.array_join(k["cols"], "+"), F.lit("->"), k["ref_table"], F.lit("."), F.array_join(k["ref_cols"], "+"), F.lit(")")))
        cols = F.concat(cols, keys)
    return F.concat(F.col(name), F.lit("("), F.array_join(cols, ", "), F.lit(")"))


def render(catalog: DataFrame, detail: str = "types", kind: str = "word") -> DataFrame:
    """The catalog with text and n_tokens at that detail."""
    return catalog.withColumn("text", rendered(detail)).withColumn("n_tokens", tokens.count("text", kind))


def sampled(catalog: DataFrame, tables: dict[str, DataFrame], width: int = 20) -> DataFrame:
    """The catalog with text that shows each whole-number and string column's least and largest value, cut to `width`; a scan each table."""
    shown = None
    for name, df in tables.items():
        cols = [f.name for f in df.schema if isinstance(f.dataType, (T.IntegralType, T.StringType))]
        ends = df.agg(*(F.concat_ws("..", *(F.substring(g(c).cast("string"), 1, width) for g in (F.min, F.max))).alias(c) for c in cols))
        one = ends.select(F.lit(name).alias("base_table"), F.map_from_arrays(F.array(*map(F.lit, cols)), F.array(*cols)).alias("ends"))
        shown = one if shown is None else shown.unionByName(one)
    part = lambda c: F.concat(c["name"], F.lit(" "), c["type"], F.coalesce(F.concat(F.lit(" "), F.col("ends")[c["name"]]), F.lit("")))
    text = F.concat("table_name", F.lit("("), F.array_join(F.transform("columns", part), ", "), F.lit(")"))
    return catalog.join(shown, "base_table", "left").withColumn("text", text).drop("ends")


def declare_fks(keys=None) -> dict[str, list[tuple]]:
    """Table -> its foreign keys, from (table, columns, referenced table, referenced columns)."""
    out: dict[str, list[tuple]] = {}
    for t, cols, ref, ref_cols in DECLARED if keys is None else keys:
        out.setdefault(t, []).append((list(cols), ref, list(ref_cols), "declared"))
    return out


def describe(spark: SparkSession, sources: dict[str, T.StructType], fks=None, db_id: str = "main", detail: str = "types", kind: str = "word") -> DataFrame:
    """CATALOG of tables given by their schemas; one row a table."""
    own = declare_fks(fks)
    rows = [(db_id, n, n, None, columns_of(s), own.get(n, []), None, None) for n, s in sources.items()]
    return render(spark.createDataFrame(rows, CATALOG), detail, kind)


def footers(spark: SparkSession, sf_dir: str, names=TABLES) -> dict[str, T.StructType]:
    """Schemas of Parquet tables: footers only, no rows are read."""
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet").schema for n in names}


def registered(spark: SparkSession, names: list[str]) -> dict[str, T.StructType]:
    """Schemas of tables and views of the session's catalog."""
    return {n: spark.table(n).schema for n in names if spark.catalog.tableExists(n)}


def with_nulls(tables: dict[str, DataFrame]) -> dict[str, set[str]]:
    """The columns of each table that hold a null: a scan each table, run by the tasks; one row each comes back."""
    out = None
    for name, df in tables.items():
        held = F.filter(F.array(*(F.when(F.count_if(F.col(f"`{c}`").isNull()) > 0, c) for c in df.columns)), lambda x: x.isNotNull())
        one = df.agg(held.alias("held")).select(F.lit(name).alias("name"), "held")
        out = one if out is None else out.unionByName(one)
    return {r["name"]: set(r.held) for r in out.collect()}  # a row a table


def base(spark: SparkSession, sf_dir: str, detail: str = "types") -> DataFrame:
    """CATALOG of the given tables: names and types from the footers, nullable where the rows hold a null."""
    held = with_nulls({n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in TABLES})
    shape = {n: T.StructType([T.StructField(f.name, f.dataType, f.name in held[n], f.metadata) for f in s]) for n, s in footers(spark, sf_dir).items()}
    return describe(spark, shape, detail=detail)


def fk_edges(catalog: DataFrame) -> DataFrame:
    """db_id, table_name, cols, ref_table, ref_cols."""
    return catalog.select("db_id", "table_name", F.explode("fks").alias("k")).select("db_id", "table_name", F.array_join("k.cols", "+").alias("cols"), F.col("k.ref_table").alias("ref_table"), F.array_join("k.ref_cols", "+").alias("ref_cols"))


def prune_columns(chosen: DataFrame, catalog: DataFrame, words_of) -> DataFrame:
    """qid, table_name, columns kept of chosen tables (qid, db_id, question, table_name): keys, and those that share a word with the question.

    words_of: text column -> array of its words.
    """
    keys = F.flatten(F.transform(F.coalesce("fks", F.array().cast(f"array<{FK}>")), lambda k: k["cols"]))
    rows = chosen.join(catalog.select("db_id", "table_name", "columns", keys.alias("keys")), ["db_id", "table_name"]).withColumn("q", words_of(F.col("question")))
    named = lambda c: F.arrays_overlap(words_of(F.regexp_replace(c["name"], "_", " ")), F.col("q"))
    kept = F.filter("columns", lambda c: F.array_contains("keys", c["name"]) | c["name"].endswith("key") | c["name"].endswith("_id") | named(c))
    return rows.select("qid", "table_name", F.transform(kept, lambda c: c["name"]).alias("columns"))


# --- keys found in data


def unique_columns(tables: dict[str, DataFrame]) -> DataFrame:
    """table_name, column_name, n_rows, n_distinct, is_unique of every column of a simple type; a scan each table."""
    out = None
    for name, df in tables.items():
        cols = [f.name for f in df.schema if not isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType))]
        counts = df.agg(F.count("*").alias("n_rows"), *(F.count_distinct(F.col(c)).alias(c) for c in cols))
        long = counts.unpivot("n_rows", cols, "column_name", "n_distinct").select(F.lit(name).alias("table_name"), "column_name", "n_rows", "n_distinct")
        out = long if out is None else out.unionByName(long)
    return out.withColumn("is_unique", (F.col("n_rows") > 0) & (F.col("n_rows") == F.col("n_distinct")))


def same_suffix(child: str, parent: str) -> bool:
    """custkey of o_custkey and c_custkey; doc_id of both."""
    cut = lambda c: c.split("_", 1)[1] if "_" in c and len(c.split("_", 1)[0]) == 1 else c
    return cut(child) == cut(parent) and cut(parent) not in ("name", "text")


def candidates(tables: dict[str, DataFrame], unique: set[tuple[str, str]], name_rule=same_suffix) -> list[tuple[str, str, str, str]]:
    """Column pairs (child, parent) left after pruning by type, uniqueness of the parent and names."""
    kinds = {(t, f.name): f.dataType.simpleString() for t, df in tables.items() for f in df.schema}
    return [(t, c, u, p) for (t, c), k in kinds.items() for (u, p) in sorted(unique) if t != u and kinds[u, p] == k and name_rule(c, p)]


def discover_fks(tables: dict[str, DataFrame], unique: set[tuple[str, str]], name_rule=same_suffix, min_containment: float = 1.0, mode: str = "exact") -> DataFrame:
    """child, child_column, parent, parent_column, n_child (distinct values), n_missing, containment.

    mode sketch: containment is estimated from theta-sketch intersections, one partial aggregate a column; exact: by
    anti joins of distinct values.
    """
    out = None
    spark = next(iter(tables.values())).sparkSession
    for t, c, u, p in candidates(tables, unique, name_rule):
        child = tables[t].select(F.col(c).alias("v")).where("v IS NOT NULL")
        parent = tables[u].select(F.col(p).alias("v")).where("v IS NOT NULL")
        if mode == "sketch":
            a, b = child.agg(F.expr("theta_sketch_agg(v)").alias("a")), parent.agg(F.expr("theta_sketch_agg(v)").alias("b"))
            row = a.crossJoin(b).select(F.expr("theta_sketch_estimate(a)").alias("n_child"), F.expr("theta_sketch_estimate(theta_difference(a, b))").alias("n_missing"))  # one row each
        else:
            child = child.distinct()
            n, miss = child.agg(F.count("*").alias("n_child")), child.join(parent, "v", "left_anti").agg(F.count("*").alias("n_missing"))
            row = n.crossJoin(miss)  # one row each
        row = row.select(F.lit(t).alias("child"), F.lit(c).alias("child_column"), F.lit(u).alias("parent"), F.lit(p).alias("parent_column"), "n_child", "n_missing")
        out = row if out is None else out.unionByName(row)
    if out is None:
        out = spark.createDataFrame([], "child string, child_column string, parent string, parent_column string, n_child long, n_missing long")
    return out.withColumn("containment", 1 - F.col("n_missing") / F.greatest(F.col("n_child"), F.lit(1))).where(F.col("containment") >= min_containment)


# --- shards: one wide fleet of executable tables out of fourteen

SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
EVENTS = ["click", "error", "login", "purchase", "view"]


def shard_list() -> list[tuple[str, str, str]]:
    """(table_name, base_table, predicate) of horizontal shards from fixed value lists, in a fixed order."""
    out = [(t, t, "true") for t in TABLES]
    for f in "ANR":
        for s in "FO":
            out += [(f"lineitem_{f.lower()}{s.lower()}_{y}", "lineitem", f"l_returnflag = '{f}' AND l_linestatus = '{s}' AND year(l_shipdate) = {y}") for y in range(1995, 2002)]
    out += [(f"orders_{s.lower()}_p{p}", "orders", f"o_orderstatus = '{s}' AND substr(o_orderpriority, 1, 1) = '{p}'") for s in "FOP" for p in range(1, 6)]
    out += [(f"customer_{g.lower()}_r{r}", "customer", f"c_mktsegment = '{g}' AND c_nationkey % 5 = {r}") for g in SEGMENTS for r in range(5)]
    out += [(f"supplier_r{r}", "supplier", f"s_nationkey % 5 = {r}") for r in range(5)]
    out += [(f"part_brand{a}{b}", "part", f"p_brand = 'Brand#{a}{b}'") for a in range(1, 6) for b in range(1, 6)]
    out += [(f"part_size{k}", "part", f"p_size BETWEEN {10 * k + 1} AND {10 * k + 10}") for k in range(5)]
    out += [(f"events_{e}_w{w}", "events", f"event_type = '{e}' AND weekofyear(ts) = {w}") for e in EVENTS for w in range(1, 6)]
    out += [(f"documents_{g}_src{k}", "documents", f"lang = '{g}' AND source = 'src{k}'") for g in ("de", "en", "es", "fr") for k in range(20)]
    out += [(f"labels_q{q}_t{t}", "labels", f"quality = {q} AND toxic = {t}") for q in (0, 1) for t in (0, 1)]
    out += [(f"conversations_{r}", "conversations", f"role = '{r}'") for r in ("assistant", "system", "user")]
    out += [(f"embeddings_l{k}", "embeddings", f"label = {k}") for k in range(10)]
    out += [(f"pages_{g}", "pages", f"url LIKE '%/{g}/%'") for g in ("de", "en", "es", "fr")]
    return out


def fleet_names(n: int) -> list[tuple[str, str, str]]:
    """n of the shards; the base tables stay, the others are chosen in the order of a multiplicative hash."""
    every = shard_list()
    rest = sorted(range(len(TABLES), len(every)), key=lambda i: ((i * 7919) % 10007, i))
    keep = set(range(len(TABLES))) | set(rest[: n - len(TABLES)])
    return [x for i, x in enumerate(every) if i in keep]


def fleet(spark: SparkSession, sf_dir: str, n: int = 254, db_id: str = "fleet", detail: str = "types") -> DataFrame:
    """CATALOG of n tables: the base tables and shards of them, which inherit columns and foreign keys."""
    shape = describe(spark, footers(spark, sf_dir), db_id=db_id).select("base_table", "columns", "fks")
    names = spark.createDataFrame([(db_id, *x) for x in fleet_names(n)], "db_id string, table_name string, base_table string, predicate string")
    rows = names.join(F.broadcast(shape), "base_table")  # fourteen rows
    rows = rows.select("db_id", "table_name", "base_table", "predicate", "columns", "fks", F.lit(None).cast("string").alias("text"), F.lit(None).cast("int").alias("n_tokens"))
    return render(rows, detail)


def register_fleet(spark: SparkSession, sf_dir: str, names: list[tuple[str, str, str]], prefix: str = "") -> None:
    """Lazy views of shards over Parquet, so that questions' SQL can run; the predicate reaches the scan."""
    for name, base_table, predicate in names:
        df = spark.read.parquet(f"{sf_dir}/{base_table}.parquet")
        (df if predicate == "true" else df.where(predicate)).createOrReplaceTempView(prefix + name)
