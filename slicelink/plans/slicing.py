"""Packing of ordered table descriptions into slices that stay strictly below a token cap."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import settled

SLICES = "db_id string, cap int, slice_id int, tables array<string>, slice_tokens int, oversize boolean"


def pack(ordered: DataFrame, cap: int, boundary: str = "carry", oversize: str = "alone", method: str = "next_fit") -> DataFrame:
    """SLICES of ordered tables (db_id, table_name, n_tokens, pos, group_id).

    Tables join the open slice while it stays strictly below cap; the last one is always closed, none is empty, and a
    table of cap tokens or more is a flagged slice of its own (oversize alone), an error (error), or is cut by columns
    before (split_columns, see split_columns()). boundary group: a slice also ends with its group. method ffd: first
    fit, largest first, without regard to the order.
    """
    if oversize == "error" and not ordered.where(F.col("n_tokens") >= cap).isEmpty():
        raise ValueError(f"a table has {cap} tokens or more")
    if method == "ffd":
        return _first_fit(ordered, cap)
    per_group = F.col("group_id").cast("int") if boundary == "group" else F.lit(0)
    items = ordered.select("db_id", F.struct(F.col("pos").cast("int").alias("pos"), "table_name", F.col("n_tokens").cast("int").alias("n"), per_group.alias("g")).alias("x"))
    lists = items.groupBy("db_id").agg(F.array_sort(F.collect_list("x")).alias("xs"))  # bounded by one database's tables
    start = F.struct(F.lit(0).alias("sum"), F.lit(0).alias("slice"), F.lit(-1).alias("g"), F.array().cast("array<struct<pos:int,table_name:string,n:int,slice:int>>").alias("out"))

    def step(acc, x):
        opens = (acc["slice"] == 0) | (acc["sum"] + x["n"] >= cap) | (acc["g"] != x["g"])
        slice_id = acc["slice"] + opens.cast("int")
        row = F.struct(x["pos"].alias("pos"), x["table_name"].alias("table_name"), x["n"].alias("n"), slice_id.alias("slice"))
        return F.struct(F.when(opens, x["n"]).otherwise(acc["sum"] + x["n"]).alias("sum"), slice_id.alias("slice"), x["g"].alias("g"), F.concat(acc["out"], F.array(row)).alias("out"))

    rows = lists.select("db_id", F.inline(F.aggregate("xs", start, step, lambda acc: acc["out"])))
    return _sliced(rows, cap)


def _sliced(rows: DataFrame, cap: int) -> DataFrame:
    out = rows.groupBy("db_id", F.col("slice").alias("slice_id")).agg(F.array_sort(F.collect_list(F.struct("pos", "table_name"))).alias("t"), F.sum("n").cast("int").alias("slice_tokens"))
    return out.select("db_id", F.lit(cap).alias("cap"), "slice_id", F.col("t.table_name").alias("tables"), "slice_tokens", (F.col("slice_tokens") >= cap).alias("oversize"))


def _first_fit(ordered: DataFrame, cap: int) -> DataFrame:
    def fill(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table.column("n_tokens").to_pylist(), table.column("table_name").to_pylist(), table.column("pos").to_pylist(), strict=True), key=lambda r: (-r[0], r[2]))
        room: list[int] = []
        out = []
        for n, name, pos in rows:
            k = next((i for i, left in enumerate(room) if n < left), len(room))
            if k == len(room):
                room.append(cap)
            room[k] -= n
            out.append((pos, name, n, k + 1))
        db = table.column("db_id")[0].as_py()
        cols = list(zip(*out, strict=True))
        return pa.table({"db_id": [db] * len(out), "pos": pa.array(cols[0], pa.int32()), "table_name": cols[1], "n": pa.array(cols[2], pa.int32()), "slice": pa.array(cols[3], pa.int32())})

    rows = ordered.select("db_id", "table_name", F.col("n_tokens").cast("int").alias("n_tokens"), F.col("pos").cast("int").alias("pos"))
    return _sliced(rows.groupBy("db_id").applyInArrow(fill, "db_id string, pos int, table_name string, n int, slice int"), cap)


def split_columns(catalog: DataFrame, cap: int, kind: str = "word") -> DataFrame:
    """Tables of cap tokens or more in parts of consecutive columns, each with the table's name and below cap where one column allows it."""
    from ..functions import tokens

    cols = catalog.select("db_id", "table_name", "base_table", F.posexplode("columns").alias("i", "c"))
    size = cols.withColumn("w", tokens.count(F.concat(F.col("c.name"), F.lit(" "), F.col("c.type"), F.lit(",")), kind))
    fixed = 2 + tokens.count("table_name", kind)
    run = size.groupBy("db_id", "table_name", "base_table").agg(F.array_sort(F.collect_list(F.struct("i", "w", "c"))).alias("xs"), F.first(fixed).alias("f"))
    start = F.struct(F.lit(0).alias("sum"), F.lit(0).alias("part"), F.array().cast("array<struct<part:int,i:int>>").alias("out"))

    def step(acc, x):
        opens = (acc["part"] == 0) | (acc["sum"] + x["w"] >= cap)
        return F.struct(F.when(opens, F.col("f") + x["w"]).otherwise(acc["sum"] + x["w"]).alias("sum"), (acc["part"] + opens.cast("int")).alias("part"), F.concat(acc["out"], F.array(F.struct((acc["part"] + opens.cast("int")).alias("part"), x["i"].alias("i")))).alias("out"))

    parts = run.select("db_id", "table_name", "base_table", "xs", F.inline(F.aggregate("xs", start, step, lambda a: a["out"])))
    return parts.groupBy("db_id", "table_name", "base_table", "part").agg(F.array_sort(F.collect_list(F.struct("i", F.expr("xs[i].c").alias("c")))).alias("t")).select("db_id", "table_name", "base_table", "part", F.col("t.c").alias("columns"))


@dataclass(frozen=True)
class Budget:
    """Slice cap = a model's token limit less its template's tokens."""

    max_tokens: int
    template_tokens: int

    @property
    def cap(self) -> int:
        return self.max_tokens - self.template_tokens

    @classmethod
    def from_memory(cls, mb: float, batch: int, model, template_tokens: int) -> Budget:
        """The largest token limit whose estimated memory stays within mb."""
        return cls(int((mb - model.base) / (model.per_token * batch)), template_tokens)

    @staticmethod
    def caps(mb, batch: int, model, template_tokens: int):
        """The cap of from_memory for a column of megabytes."""
        return ((mb - F.lit(model.base)) / F.lit(model.per_token * batch)).cast("int") - template_tokens


def count_slices(sizes: list[int], cap: int) -> int:
    slices, total = 0, 0
    for n in sizes:
        if not slices or total + n >= cap:
            slices, total = slices + 1, n
        else:
            total += n
    return slices


def cap_for(sizes: list[int], wanted: int) -> tuple[int, int]:
    """(cap, slices): the smallest cap with at most that many slices and no table alone above it; slices may be fewer than wanted."""
    lo, hi = max(sizes) + 1, sum(sizes) + 1
    while lo < hi:
        mid = (lo + hi) // 2
        if count_slices(sizes, mid) <= wanted:
            hi = mid
        else:
            lo = mid + 1
    return lo, count_slices(sizes, lo)


def cap_sweep(ordered: DataFrame, caps: list[int]) -> DataFrame:
    """cap, n_slices, max_tokens, n_oversize."""
    out = None
    for cap in caps:
        one = pack(ordered, cap).groupBy("cap").agg(F.count("*").alias("n_slices"), F.max("slice_tokens").alias("max_tokens"), F.sum(F.col("oversize").cast("int")).alias("n_oversize"))
        out = one if out is None else out.unionByName(one)
    return out


def check(slices: DataFrame, catalog: DataFrame) -> DataFrame:
    """db_id, n_tables, n_placed, n_missing, n_extra, n_twice: slices are a partition of the catalog when the last three are 0."""
    placed = slices.select("db_id", F.explode("tables").alias("table_name")).groupBy("db_id", "table_name").agg(F.count("*").alias("times"))
    both = catalog.select("db_id", "table_name", F.lit(1).alias("own")).join(placed, ["db_id", "table_name"], "full")
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    return both.groupBy("db_id").agg(n(F.col("own").isNotNull()).alias("n_tables"), n(F.col("times").isNotNull()).alias("n_placed"), n(F.col("times").isNull()).alias("n_missing"), n(F.col("own").isNull()).alias("n_extra"), n(F.col("times") > 1).alias("n_twice"))


# --- orders of any length


def _carry(n: np.ndarray, cap: int, carry: int) -> tuple[np.ndarray, int, int]:
    """(slice number from 0 of each item, 0 being the slice carried in; slices opened; what the last one carries on).

    A carry is an open slice's tokens and one, so that 0 is none even where an open slice has no tokens.
    """
    total = np.concatenate([[0], np.cumsum(n, dtype=np.int64)])
    out = np.zeros(len(n), np.int64)
    at, opened, last = 0, 0, carry
    if len(n):
        # what still joins the slice carried in
        to = int(np.searchsorted(total, cap + 1 - carry, "left")) - 1 if carry else 0
        at = min(max(to, 0), len(n))
        last = carry + int(total[at])
    while at < len(n):
        opened += 1
        to = min(max(int(np.searchsorted(total, total[at] + cap, "left")) - 1, at + 1), len(n))
        out[at:to] = opened
        last = int(total[to] - total[at]) + 1
        at = to
    return out, opened, last


def _summary(n: np.ndarray, cap: int) -> list[tuple[int, int, int]]:
    """(least carry, slices opened, tokens in the last slice less a carry that is still open): how a block answers to any
    carry. Its answer changes only where one item fewer joins the carried slice, so entries are bounded by the items that fit in cap."""
    out = [(0, *_carry(n, cap, 0)[1:])]
    total = np.cumsum(n, dtype=np.int64)
    fits = int(np.searchsorted(total, cap, "left"))
    for k in range(min(fits, len(n)), -1, -1):
        least = 1 if k == len(n) or total[k] >= cap else int(cap + 1 - total[k])
        if k and cap - int(total[k - 1]) < least:
            continue
        _, opened, last = _carry(n, cap, least)
        out.append((least, opened, last - least if opened == 0 else last))
    return out


SUMMARY = "b long, least long, opened long, last long"
ENTRY = "b long, carry long, before long"


def _answer(told: list[tuple], carry: int) -> tuple[int, int]:
    """(slices opened, tokens carried out) of a summary for a carry."""
    _, opened, last = max(x for x in told if x[0] <= carry)
    return opened, last if opened or not carry else carry + last


def _then(f: list[tuple], g: list[tuple]) -> list[tuple]:
    """The summary of two blocks in a row; both in order of their least carries, 0 and 1 first."""
    out = []
    for i, (least, opened, last) in enumerate(f):
        if least == 0 or opened:  # what is carried out does not depend on the carry
            more, carried = _answer(g, last)
            out.append((least, opened + more, carried))
            continue
        end = f[i + 1][0] if i + 1 < len(f) else None
        for j, (from_, more, left) in enumerate(g):
            if from_ == 0:
                continue
            low, high = max(least, from_ - last), g[j + 1][0] - last if j + 1 < len(g) else None
            if (high is None or low < high) and (end is None or low < end):
                out.append((low, more, left if more else last + left))
    return [x for k, x in enumerate(out) if not k or x[1:] != out[k - 1][1:] or out[k - 1][0] == 0]


def _told(t: pa.Table) -> list[tuple[int, list[tuple]]]:
    """The summaries of a table of SUMMARY rows, in order of their blocks."""
    out: dict = {}
    for b, *x in zip(*(t.column(c).to_pylist() for c in ("b", "least", "opened", "last")), strict=True):
        out.setdefault(b, []).append(tuple(x))
    return [(b, sorted(out[b])) for b in sorted(out)]


def _entries(summaries: DataFrame, blocks: int, fan: int) -> DataFrame:
    """ENTRY of each block: what is carried into it and the slices before. Groups of `fan` blocks are summed up, level by level, until one task can pass them; then every group passes on to its own."""
    up = F.floor(F.col("b") / fan).cast("long")

    def passed(t: pa.Table) -> pa.Table:
        carry, before, out = (t.column("carry")[0].as_py(), t.column("before")[0].as_py(), []) if "carry" in t.column_names else (0, 0, [])
        for b, told in _told(t):
            out.append((b, carry, before))
            opened, carry = _answer(told, carry)
            before += opened
        return pa.table([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["b", "carry", "before"])

    if blocks <= fan:
        return summaries.withColumn("up", F.lit(0)).groupBy("up").applyInArrow(passed, ENTRY)

    def summed(t: pa.Table) -> pa.Table:
        told = _told(t)
        whole = told[0][1]
        for _, more in told[1:]:
            whole = _then(whole, more)
        return pa.table([pa.array(c, pa.int64()) for c in ([told[0][0] // fan] * len(whole), *zip(*whole, strict=True))], names=["b", "least", "opened", "last"])

    above = _entries(settled(summaries.withColumn("up", up).groupBy("up").applyInArrow(summed, SUMMARY), "summaries"), -(-blocks // fan), fan)
    own = summaries.withColumn("up", up).join(above.withColumnRenamed("b", "up"), "up")
    return own.groupBy("up").applyInArrow(passed, ENTRY)


def pack_distributed(items: DataFrame, cap: int, block: int = 100_000, fan: int = 256) -> DataFrame:
    """pos, n_tokens, slice_id (from 1) of an order given by dense positions `pos` (not null), of any length; the same slices as pack().

    Blocks of consecutive positions are packed apart: each first tells how it would answer to any carry, the answers
    are put together in a tree of groups of `fan`, and every block is packed once more with its true carry. Nothing
    but the number of blocks reaches the driver.
    """
    rows = items.select(F.col("pos").cast("long").alias("pos"), F.col("n_tokens").cast("long").alias("n_tokens"), F.floor(F.col("pos") / block).cast("long").alias("b"))

    def sized(t: pa.Table):
        t = t.sort_by("pos")
        return t, t.column("n_tokens").to_numpy()

    def tell(t: pa.Table) -> pa.Table:
        t, n = sized(t)
        cols = list(zip(*_summary(n, cap), strict=True))
        return pa.table([pa.array(c, pa.int64()) for c in ([t.column("b")[0].as_py()] * len(cols[0]), *cols)], names=["b", "least", "opened", "last"])

    told = settled(rows.groupBy("b").applyInArrow(tell, SUMMARY), "told")
    ends = told.agg(F.min("b").alias("lo"), F.max("b").alias("hi")).first()
    shift = ends.lo or 0
    handed = _entries(told.withColumn("b", F.col("b") - shift), (ends.hi or 0) - shift + 1, fan).withColumn("b", F.col("b") + shift)

    def fill(t: pa.Table) -> pa.Table:
        t, n = sized(t)
        number, _, _ = _carry(n, cap, t.column("carry")[0].as_py())
        return pa.table({"pos": t.column("pos"), "n_tokens": t.column("n_tokens"), "slice_id": pa.array(number + t.column("before")[0].as_py(), pa.int64())})

    return rows.join(handed, "b").groupBy("b").applyInArrow(fill, "pos long, n_tokens long, slice_id long")


def window_history(df: DataFrame, key: str = "qid", at: str = "slice_id", target: str = "target") -> DataFrame:
    """The tables found in earlier slices, by a window (the cross-check of the in-array form)."""
    w = Window.partitionBy(key).orderBy(at).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn("history", F.flatten(F.collect_list(target).over(w)))
