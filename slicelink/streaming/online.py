"""Question streams: linking as they arrive, slice answers with state, monitoring, late labels, re-slicing."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans import linking
from ..session import ready, shared_path


def read_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    """A file source; event times of the given tables have no zone, and watermarks need one, so they are cast by the caller."""
    return ready(spark).readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream with event time `at`."""
    path = f"{sf_dir}/events.parquet"
    kind = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    rows = ready(spark).readStream.schema(kind).option("pathGlobFilter", name).parquet(folder) if not _is_folder(spark, path) else read_stream(spark, path, kind)
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def drain(stream: DataFrame, mode: str = "append", name: str = "stream") -> DataFrame:
    """Run a stream over what is there to its end and return what it wrote, as Parquet: all rows for append and update, the last batch's table for complete."""
    spark = stream.sparkSession
    check, out = shared_path(spark, f"{name}-checkpoint"), shared_path(spark, name)
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    batches = []

    def batch(df, k):
        df.write.mode("overwrite").parquet(f"{out}/{k}")
        batches.append(f"{out}/{k}")

    with _state_on_disk(spark):
        q = stream.writeStream.foreachBatch(batch).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(batches[-1:] if mode == "complete" else dict.fromkeys(batches)))


@contextmanager
def _state_on_disk(spark: SparkSession) -> Iterator[None]:
    """Queries started inside keep their state in RocksDB: a complete table's state holds every group."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def link(questions: DataFrame, linker, slices: DataFrame, catalog: DataFrame) -> DataFrame:
    """Stateless: each question of the stream meets the static slices and folds over them in one expression."""
    return linking.fold_lexical(linker, questions, slices, catalog)


def link_stateful(answers: DataFrame, n_slices: int, ttl: str = "10 minutes") -> DataFrame:
    """(qid, slice_id, found array, at) rows in any order -> one (qid, tables, complete) when all slices have answered, or when ttl has passed."""

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        done, tables = state.get if state.exists else ([], [])
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"qid": [key[0]], "tables": [sorted(tables)], "complete": [False]})
            return
        last = 0
        for p in parts:
            for k, found, at in zip(p.slice_id, p.found, p["at"], strict=True):
                if k not in done:
                    done, tables = [*done, int(k)], sorted({*tables, *found})
                last = max(last, int(at.timestamp() * 1000))
        if len(done) >= n_slices:
            if state.exists:
                state.remove()
            yield pd.DataFrame({"qid": [key[0]], "tables": [tables], "complete": [True]})
        else:
            state.update((done, tables))
            limit = max(last, state.getCurrentWatermarkMs()) + int(pd.Timedelta(ttl).total_seconds() * 1000)
            state.setTimeoutTimestamp(limit)

    rows = answers.withWatermark("at", ttl)
    return rows.groupBy("qid").applyInPandasWithState(run, "qid long, tables array<string>, complete boolean", "done array<int>, tables array<string>", "append", GroupStateTimeout.EventTimeTimeout)


def converse(turns: DataFrame, ttl: str = "1 day") -> DataFrame:
    """(conv_id, turn, role, at) in any order -> each turn with the roles of the smaller turns seen until its batch.

    The state holds a conversation's turns, so one that comes late gets its own history and none of what followed; it
    goes when the watermark is ttl past its last turn.
    """

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        seen = dict(zip(*state.get, strict=True)) if state.exists else {}
        rows = pd.concat(list(parts)).sort_values("turn")
        for turn, role in zip(rows.turn, rows.role, strict=True):
            seen.setdefault(int(turn), role)
        order = sorted(seen)
        state.update((order, [seen[t] for t in order]))
        last = max(int(rows["at"].max().timestamp() * 1000), state.getCurrentWatermarkMs())
        state.setTimeoutTimestamp(last + int(pd.Timedelta(ttl).total_seconds() * 1000))
        out = [(key[0], turn, role, ",".join(seen[t] for t in order if t < turn)) for turn, role in zip(rows.turn, rows.role, strict=True)]
        yield pd.DataFrame(out, columns=["conv_id", "turn", "role", "before"])

    rows = turns.withWatermark("at", ttl)
    return rows.groupBy("conv_id").applyInPandasWithState(run, "conv_id long, turn long, role string, before string", "turns array<long>, roles array<string>", "append", GroupStateTimeout.EventTimeTimeout)


def monitor(stream: DataFrame, kind: str = "tumbling", width: str = "1 hour", slide: str = "15 minutes", gap: str = "30 minutes", delay: str = "1 day", keys=("event_type",)) -> DataFrame:
    """Counts and sums of `value` by windows of event time `at`; rows later than the delay are dropped (and counted by Spark's metrics)."""
    w = {"tumbling": lambda: F.window("at", width), "sliding": lambda: F.window("at", width, slide), "session": lambda: F.session_window("at", gap)}[kind]()
    out = stream.withWatermark("at", delay).groupBy(w.alias("w"), *keys).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "total")


def dedup(stream: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    """Each key once within the watermark."""
    return stream.withWatermark("at", delay).dropDuplicatesWithinWatermark(keys)


def join_labels(pred: DataFrame, gold: DataFrame, within: str = "1 hour", how: str = "inner") -> DataFrame:
    """Predictions (qid, at, ...) with labels (gid, gold_at, ...) that arrive at most `within` later."""
    p, g = pred.withWatermark("at", within), gold.withWatermark("gold_at", within)
    return p.join(g, F.expr(f"qid = gid AND gold_at >= at AND gold_at <= at + INTERVAL {within}"), how)


class Reslicer:
    """Keeps the slices of a changing catalog: a change repacks from the first table it touches, earlier slices stay.

    Tables are (name, tokens) or (name, tokens, lead): tables of one key group have the same lead, the group's first
    name; loose ones (lead None) come after all groups, as in groups.order().
    """

    def __init__(self, tables: list[tuple], cap: int, version: int = 0):
        self.cap, self.version = cap, version
        self.of = {x[0]: (x[1], x[2] if len(x) > 2 else None) for x in tables}
        self._sort()
        self.slices = self._pack(0, [])

    def _key(self, name: str, lead) -> tuple:
        return (lead is None, lead or "", name)

    def _sort(self):
        self.tables = sorted(((name, n) for name, (n, _) in self.of.items()), key=lambda x: self._key(x[0], self.of[x[0]][1]))

    def _pack(self, at: int, kept: list[list[str]]) -> list[list[str]]:
        out, total = kept, 0
        for name, n in self.tables[at:]:
            if not out or total == 0 or total + n >= self.cap:
                out, total = [*out, [name]], n
            else:
                out[-1].append(name)
                total += n
        return out

    def apply(self, changes: list[tuple]) -> int:
        """Set (name, tokens[, lead]) or remove (name, None) tables; returns how many slices were kept."""
        if not changes:
            return len(self.slices)
        touched, old = [], {t: self._key(t, lead) for t, (_, lead) in self.of.items()}
        for name, n, *lead in changes:
            if name in self.of:
                touched.append(old[name])
            if n is None:
                self.of.pop(name, None)
            else:
                self.of[name] = (n, lead[0] if lead else self.of.get(name, (0, None))[1])
                touched.append(self._key(name, self.of[name][1]))
        self._sort()
        self.version += 1
        if not touched:
            return len(self.slices)
        first, kept = min(touched), []
        for s in self.slices:
            if old[s[-1]] >= first:
                break
            kept.append(s)
        if kept:  # the slice before may now take more
            kept.pop()
        self.slices = self._pack(sum(map(len, kept)), [list(s) for s in kept])
        return len(kept)

    def rows(self) -> list[tuple]:
        """(version, slice_id, pos, table_name, n_tokens, lead) of the present slices."""
        return [(self.version, k, i, t, *self.of[t]) for k, s in enumerate(self.slices, 1) for i, t in enumerate(s)]

    VERSION = "version long, slice_id int, pos int, table_name string, n_tokens int, lead string"

    @classmethod
    def latest(cls, spark: SparkSession, path: str, cap: int) -> Reslicer:
        """The last version that was written below a path: a stream that starts anew goes on from it."""
        rows = spark.read.schema(cls.VERSION).parquet(path)
        last = rows.agg(F.max("version")).first()[0]
        return cls([(r.table_name, r.n_tokens, r.lead) for r in rows.where(F.col("version") == last).collect()], cap, last)  # one catalog's tables


def reslice(changes: DataFrame, state: Reslicer, path: str | None = None):
    """A foreachBatch query over (table_name, n_tokens or null[, lead]): catalog changes become new slice versions, each written below `path`."""
    spark = changes.sparkSession
    check, path = shared_path(spark, "reslice"), path or shared_path(spark, "slices")
    cols = [c for c in ("table_name", "n_tokens", "lead") if c in changes.columns]

    def batch(df, _):
        state.apply([tuple(r) for r in df.select(cols).collect()])  # a batch of catalog changes
        spark.createDataFrame(state.rows(), Reslicer.VERSION).coalesce(1).write.mode("append").parquet(path)

    return changes.writeStream.foreachBatch(batch).option("checkpointLocation", check).trigger(availableNow=True).start()


# --- driver queries

Q: dict = {}
S: dict[str, str] = {}


def q(sql: str | None = None):
    def keep(f):
        Q[f.__name__] = f
        if sql:
            S[f.__name__] = sql
        return f

    return keep


_NTZ = lambda df: df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end") if c in df.columns})


@q("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS \"end\", event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_events_tumbling(spark, sf):
    return _NTZ(drain(monitor(events(spark, sf), delay="60 days"), "complete", "tumbling"))


@q("SELECT s AS start, s + INTERVAL 1 HOUR AS \"end\", event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT *, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE FOR i IN [0, 1, 2, 3]]) AS s FROM events) GROUP BY ALL")
def stream_events_sliding(spark, sf):
    return _NTZ(drain(monitor(events(spark, sf), "sliding", delay="60 days"), "complete", "sliding"))


@q("""WITH g AS (SELECT *, coalesce((ts - lag(ts) OVER w >= INTERVAL 30 MINUTE)::INT, 1) AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY user_id, k""")
def stream_events_session(spark, sf):
    return _NTZ(drain(monitor(events(spark, sf), "session", delay="60 days", keys=("user_id",)), "complete", "session"))


@q("SELECT user_id, event_type, count(*) AS n FROM (SELECT DISTINCT user_id, event_type FROM events) GROUP BY ALL")
def stream_dedup(spark, sf):
    return drain(dedup(events(spark, sf).select("at", "user_id", "event_type"), ["user_id", "event_type"], "60 days"), "append", "dedup").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@q("SELECT c.event_id AS qid, p.event_id AS gid FROM events c JOIN events p ON c.event_type = 'click' AND p.event_type = 'purchase' AND c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def stream_join_labels(spark, sf):
    a = events(spark, sf).where("event_type = 'click'").select(F.col("user_id").alias("qid"), "at", F.col("event_id").alias("click"))
    b = events(spark, sf).where("event_type = 'purchase'").select(F.col("user_id").alias("gid"), F.col("at").alias("gold_at"), F.col("event_id").alias("purchase"))
    out = drain(join_labels(a, b), "append", "labels")
    return out.select(F.col("click").alias("qid"), F.col("purchase").alias("gid"))


@q("""WITH c AS (SELECT * FROM events WHERE event_type = 'click'), p AS (SELECT * FROM events WHERE event_type = 'purchase'), m AS (SELECT c.event_id AS qid, p.event_id AS gid FROM c JOIN p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR)
SELECT qid, gid FROM m UNION ALL SELECT event_id, NULL FROM c WHERE event_id NOT IN (SELECT qid FROM m) AND ts < (SELECT least((SELECT max(ts) FROM c), (SELECT max(ts) FROM p))) - INTERVAL 2 HOUR""")
def stream_join_labels_outer(spark, sf):
    """Clicks without a purchase in time as well, once the watermark says that none can come."""
    a = events(spark, sf).where("event_type = 'click'").select(F.col("user_id").alias("qid"), "at", F.col("event_id").alias("click"))
    b = events(spark, sf).where("event_type = 'purchase'").select(F.col("user_id").alias("gid"), F.col("at").alias("gold_at"), F.col("event_id").alias("purchase"))
    return drain(join_labels(a, b, how="leftOuter"), "append", "labels_outer").select(F.col("click").alias("qid"), F.col("purchase").alias("gid"))


@q("SELECT conv_id, turn, role, coalesce(string_agg(role, ',') OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), '') AS before FROM conversations")
def stream_converse(spark, sf):
    path = f"{sf}/conversations.parquet"
    kind = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    rows = read_stream(spark, path, kind) if _is_folder(spark, path) else ready(spark).readStream.schema(kind).option("pathGlobFilter", name).parquet(folder)
    at = F.timestamp_seconds(F.col("turn") + 1_000_000_000).alias("at")  # the table has no times: a turn a second, after the first watermark
    return drain(converse(rows.select("conv_id", "turn", "role", at)), "append", "converse")


@q("SELECT event_id // 4 AS qid, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS tables, true AS complete FROM events GROUP BY 1 HAVING count(DISTINCT event_id % 4) = 4")
def stream_link_stateful(spark, sf):
    """Four answers a question: here each event is the answer of one slice, and four events in a row are a question's."""
    e = events(spark, sf)
    rows = e.select(F.floor(F.col("event_id") / 4).alias("qid"), (F.col("event_id") % 4).cast("int").alias("slice_id"), F.array("event_type").alias("found"), "at")
    return drain(link_stateful(rows, 4, "60 days"), "append", "stateful").where("complete").select("qid", F.array_join(F.array_sort("tables"), ",").alias("tables"), "complete")


@q()
def stream_link(spark, sf):
    """Questions arrive as events: an event asks question event_id % 60."""
    from ..plans import catalog, groups, queries, slicing

    b = catalog.base(spark, sf)
    qa = queries._qa(spark).select(F.col("qid").alias("k"), "db_id", "question")
    arrivals = events(spark, sf).select(F.col("event_id").alias("qid"), (F.col("event_id") % 60).alias("k"))
    out = link(arrivals.join(qa, "k"), queries.LEX, slicing.pack(groups.order(b), queries.CAP), b)
    return drain(out, "append", "link").select("qid", F.array_join("pred_tables", ",").alias("pred"), "n_calls")


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    from ..plans import queries

    return S | {"stream_link": queries.STREAM_LINK_SQL}
