"""Tables with and without foreign keys, their correlation groups, and the order in which slices are filled."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import settled
from .catalog import fk_edges

#: Databases with up to so many tables are grouped on the driver; larger ones by joins.
DRIVER_TABLES = 100_000


def partition(catalog: DataFrame) -> DataFrame:
    """db_id, table_name, has_reference: whether a foreign key leaves or enters the table."""
    e = fk_edges(catalog)
    tied = e.select("db_id", "table_name").union(e.select("db_id", F.col("ref_table"))).distinct().withColumn("tied", F.lit(True))
    return catalog.select("db_id", "table_name").join(tied, ["db_id", "table_name"], "left").select("db_id", "table_name", F.coalesce("tied", F.lit(False)).alias("has_reference"))


def correlate(catalog: DataFrame, mode: str = "component", driver_tables: int = DRIVER_TABLES) -> DataFrame:
    """db_id, table_name, group_key of the tables with references.

    component: connected components of the key graph, named by their smallest table. per_fk: one group for each
    referenced table with all that refer to it; a table in several is kept in the first by name.
    """
    e = fk_edges(catalog).select("db_id", "table_name", "ref_table")
    if mode == "per_fk":
        member = e.select("db_id", F.col("ref_table").alias("group_key"), "table_name").union(e.select("db_id", "ref_table", F.col("ref_table")))
        return member.groupBy("db_id", "table_name").agg(F.min("group_key").alias("group_key"))
    if mode != "component":
        raise ValueError(f"unknown mode: {mode}")
    if catalog.count() <= driver_tables:
        above: dict = {}

        def top(x):
            while above.setdefault(x, x) != x:
                above[x] = above[above[x]]
                x = above[x]
            return x

        for r in e.collect():
            a, b = sorted((top((r.db_id, r.table_name)), top((r.db_id, r.ref_table))))
            above[b] = a
        rows = [(x[0], x[1], top(x)[1]) for x in sorted(above)]
        return catalog.sparkSession.createDataFrame(rows, "db_id string, table_name string, group_key string")
    return components(e.select("db_id", F.col("table_name").alias("a"), F.col("ref_table").alias("b"))).select("db_id", F.col("v").alias("table_name"), F.col("c").alias("group_key"))


def components(edges: DataFrame) -> DataFrame:
    """(db_id, v, c): c is the smallest name of v's component, by joins: least neighbour, then the label of the label, until nothing changes."""
    both = settled(edges.select("db_id", "a", "b").union(edges.select("db_id", F.col("b"), F.col("a"))).distinct(), "edges")
    label = settled(both.groupBy("db_id", F.col("a").alias("v")).agg(F.min("b").alias("m")).select("db_id", "v", F.least("v", "m").alias("c")), "labels")
    while True:
        near = both.join(label.select("db_id", F.col("v").alias("b"), F.col("c").alias("n")), ["db_id", "b"]).groupBy("db_id", F.col("a").alias("v")).agg(F.min("n").alias("n"))
        step = label.join(near, ["db_id", "v"]).select("db_id", "v", "c", F.least("c", "n").alias("n"))
        jump = step.select("db_id", F.col("v").alias("n"), F.col("n").alias("j"))
        step = settled(step.join(jump, ["db_id", "n"], "left").select("db_id", "v", F.coalesce("j", "n").alias("c"), (F.coalesce("j", "n") != F.col("c")).alias("moved")), "labels")
        label = step.select("db_id", "v", "c")
        if step.where("moved").isEmpty():
            return label


def order(catalog: DataFrame, how: str = "canonical", mode: str = "component", seed: int = 1) -> DataFrame:
    """db_id, table_name, has_reference, group_id, pos (from 1): a fixed order of the tables.

    canonical: groups by their first table's name, tables by name, then the others by name. fk_bfs: in each group the
    most referenced tables first. size_desc: larger descriptions first. seeded_shuffle: by a hash of seed and name.
    """
    g = partition(catalog).join(correlate(catalog, mode), ["db_id", "table_name"], "left")
    g = g.join(catalog.select("db_id", "table_name", "n_tokens"), ["db_id", "table_name"])
    first = g.groupBy("db_id", "group_key").agg(F.min("table_name").alias("first_name"))
    g = g.join(first, (g.db_id == first.db_id) & g.group_key.eqNullSafe(first.group_key), "left").drop(first.db_id).drop(first.group_key)
    loose = (~F.col("has_reference")).cast("int")
    lead = F.when(F.col("has_reference"), F.col("first_name")).otherwise(F.lit(""))
    degree = fk_edges(catalog).groupBy("db_id", F.col("ref_table").alias("table_name")).agg(F.count("*").alias("refs"))
    g = g.join(degree, ["db_id", "table_name"], "left")
    by = {
        "canonical": [loose, lead, F.col("table_name")],
        "fk_bfs": [loose, lead, F.coalesce("refs", F.lit(0)).desc(), F.col("table_name")],
        "size_desc": [F.col("n_tokens").desc(), F.col("table_name")],
        "seeded_shuffle": [F.xxhash64(F.lit(seed), F.col("table_name")), F.col("table_name")],
    }[how]
    w = Window.partitionBy("db_id")
    return g.select("db_id", "table_name", "has_reference", "n_tokens", F.dense_rank().over(w.orderBy(loose, lead)).alias("group_id"), F.row_number().over(w.orderBy(*by)).alias("pos"))
