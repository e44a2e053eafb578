"""Connected components by contraction; every round is joins and partial aggregates on tables of the shared folder."""

from __future__ import annotations

from pyspark.sql import functions as F

from .common import written


def components(edges):
    """(v, c) for every vertex of edges (a, b: long): c is the smallest vertex of its component.

    Each round maps a vertex to the smallest of itself and its neighbours (in even rounds by a hash, so that long
    chains shrink as well) and contracts the edges; the maps are then composed.
    """
    both = edges.where("a <> b").select("a", "b").distinct()
    both = written(both.union(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    maps = []
    while True:
        if len(maps) % 2:
            best = F.min(F.struct(F.xxhash64("b").alias("p"), F.col("b").alias("b")))
            near = both.groupBy(F.col("a").alias("v")).agg(best.alias("m"))
            near = near.select("v", F.when(F.xxhash64("v") < F.col("m.p"), F.col("v")).otherwise(F.col("m.b")).alias("c"))
        else:
            near = both.groupBy(F.col("a").alias("v")).agg(F.min("b").alias("m")).select("v", F.least("v", "m").alias("c"))
        near = written(near, "near")
        maps.append(near)
        ends = both.join(near.select(F.col("v").alias("a"), F.col("c").alias("x")), "a").join(near.select(F.col("v").alias("b"), F.col("c").alias("y")), "b")
        both = written(ends.where("x <> y").select(F.col("x").alias("a"), F.col("y").alias("b")).distinct(), "edges")
        if both.isEmpty():
            break
    out = maps[0]
    for near in maps[1:]:
        out = out.join(near.select(F.col("v").alias("c"), F.col("c").alias("d")), "c", "left").select("v", F.coalesce("d", "c").alias("c"))
    if len(maps) > 1:
        first = out.groupBy("c").agg(F.min("v").alias("m"))
        out = out.join(first, "c").select("v", F.col("m").alias("c"))
    return written(out, "components")
