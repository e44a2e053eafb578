"""Inference over slices: a running set of tables, folded slice by slice."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ready
from .linkers import NUMERIC, LexicalLinker, LowRankConfig, hashed, sigmoid, table_words, word_list

PRED = "qid long, pred_tables array<string>, n_calls int"


@dataclass(frozen=True)
class Regime:
    """Whether history is given in training and in inference."""

    train: bool
    infer: bool


REGIMES = {"no_history": Regime(False, False), "history": Regime(True, True), "history_infer_only": Regime(False, True)}


def _sets(chosen: DataFrame, questions: DataFrame, calls) -> DataFrame:
    """PRED of chosen (qid, table_name) rows; questions without any get an empty set."""
    got = chosen.groupBy("qid").agg(F.array_sort(F.collect_set("table_name")).alias("pred_tables"))
    return questions.select("qid", "db_id").join(got, "qid", "left").select("qid", F.coalesce("pred_tables", F.array().cast("array<string>")).alias("pred_tables"), calls.alias("n_calls"))


def infer_once(linker: LexicalLinker, questions: DataFrame, catalog: DataFrame) -> DataFrame:
    """One prompt with the whole schema."""
    return _sets(linker.choose(linker.scores(questions, catalog), ["qid"]), questions, F.lit(1))


def infer_sliced(linker: LexicalLinker, questions: DataFrame, slices: DataFrame, catalog: DataFrame) -> DataFrame:
    """A prompt for each slice without history; the answers are united. Names that are not in the slice can't be chosen."""
    where = slices.select("db_id", "slice_id", F.explode("tables").alias("table_name"))
    scores = linker.scores(questions, catalog).join(questions.select("qid", "db_id"), "qid").join(where, ["db_id", "table_name"])
    n = slices.groupBy("db_id").agg(F.count("*").cast("int").alias("n"))
    out = _sets(linker.choose(scores, ["qid", "slice_id"]), questions, F.lit(0))
    return out.drop("n_calls").join(questions.select("qid", "db_id").join(n, "db_id").select("qid", F.col("n").alias("n_calls")), "qid")


def fold_lexical(linker: LexicalLinker, questions: DataFrame, slices: DataFrame, catalog: DataFrame, stop_early: bool = False) -> DataFrame:
    """Slices in order with history as one Column expression: words that chosen tables explain count half in later slices.

    stop_early: no further slice is asked once all known words of the question are explained. Words are not weighted
    here, so the expression needs nothing but the question and its database's slices, which are joined by key.
    """
    w = table_words(catalog, linker.fields)
    placed = slices.select("db_id", "slice_id", F.posexplode("tables").alias("k", "table_name")).join(w, ["db_id", "table_name"])
    per = placed.groupBy("db_id", "slice_id").agg(F.array_sort(F.collect_list(F.struct("k", "table_name", "words"))).alias("ts"))
    lists = per.groupBy("db_id").agg(F.array_sort(F.collect_list(F.struct("slice_id", "ts"))).alias("ws"), F.array_distinct(F.flatten(F.flatten(F.collect_list("ts.words")))).alias("known"))
    df = questions.join(lists, "db_id").withColumn("q", F.array_intersect(word_list("question"), "known"))
    start = F.struct(F.array().cast("array<string>").alias("chosen"), F.array().cast("array<string>").alias("seen"), F.lit(0).alias("calls"))

    def step(acc, s):
        mass = lambda ws: F.size(F.array_intersect("q", ws)) - 0.5 * F.size(F.array_intersect(F.array_intersect("q", ws), acc["seen"]))
        scored = F.transform(s["ts"], lambda t: F.struct((mass(t["words"]) / F.greatest(F.size("q"), F.lit(1))).alias("s"), t["table_name"].alias("t"), t["words"].alias("w")))
        best = F.array_max(F.transform(scored, lambda x: x["s"]))
        kept = F.filter(scored, lambda x: (x["s"] >= linker.threshold) & (x["s"] >= linker.near * best - 1e-9))
        asked = ~(F.lit(stop_early) & (F.size(F.array_except("q", acc["seen"])) == 0))
        kept = F.when(asked, kept).otherwise(F.slice(kept, F.lit(1), F.lit(0)))
        return F.struct(F.array_union(acc["chosen"], F.transform(kept, lambda x: x["t"])).alias("chosen"), F.array_union(acc["seen"], F.flatten(F.transform(kept, lambda x: x["w"]))).alias("seen"), (acc["calls"] + asked.cast("int")).alias("calls"))

    done = df.select("qid", F.aggregate("ws", start, step).alias("r"))
    return done.select("qid", F.array_sort("r.chosen").alias("pred_tables"), F.col("r.calls").alias("n_calls"))


# --- trained stand-ins


class Shelf:
    """What a trained linker must know of a database: its slices in order, words, word weights and key neighbours.

    It is bounded by one database's tables, so it is held once and sent with the code.
    """

    def __init__(self, slices: list[list[str]], short: dict, long: dict, weight: dict, keys: dict):
        self.slices, self.short, self.long, self.weight, self.keys = slices, short, long, weight, keys

    @classmethod
    def of(cls, catalog: DataFrame, slices: DataFrame | None = None) -> Shelf:
        from .catalog import fk_edges
        from .linkers import idf

        words = table_words(catalog)
        long = {r.table_name: set(r.words) for r in words.collect()}
        short = {r.table_name: set(r.words) for r in table_words(catalog, "names").collect()}
        weight = {r.word: r.idf for r in idf(words).collect()}
        base = {r.table_name: r.base_table for r in catalog.select("table_name", "base_table").collect()}
        pairs = {(base[r.table_name], r.ref_table) for r in fk_edges(catalog).select("table_name", "ref_table").collect()}
        keys = {t: {u for u in long if (base[t], base[u]) in pairs or (base[u], base[t]) in pairs} for t in long}
        order = [r.tables for r in slices.orderBy("slice_id").collect()] if slices is not None else [sorted(long)]
        return cls(order, short, long, weight, keys)

    def of_slices(self, slices: DataFrame) -> Shelf:
        """The same database in other slices."""
        return Shelf([r.tables for r in slices.orderBy("slice_id").collect()], self.short, self.long, self.weight, self.keys)

    def names_only(self) -> Shelf:
        return Shelf([sorted(self.short)], self.short, self.short, self.weight, {})

    def bench(self, words: list[list[str]], dim: int) -> Bench:
        return Bench(self, words, dim)

    def matrices(self, dim: int) -> dict:
        """What a Bench needs of the tables alone; made once in each process."""
        made = self.__dict__.setdefault("_made", {})
        if dim not in made:
            names = [t for s in self.slices for t in s]
            vocab = {w: i for i, w in enumerate(sorted(set().union(*self.long.values(), *self.short.values())))}
            bag = lambda sets: np.array([[float(w in s) for w in vocab] for s in sets]).reshape(len(sets), len(vocab))
            made[dim] = {
                "names": names, "at": {t: i for i, t in enumerate(names)}, "slice_of": np.repeat(np.arange(len(self.slices)), [len(s) for s in self.slices]), "vocab": vocab,
                "short": bag([self.short[t] for t in names]), "long": bag([self.long[t] for t in names]), "weight": np.array([self.weight.get(w, 1.0) for w in vocab]),
                "near": np.array([[float(u in self.keys.get(t, ())) for u in names] for t in names]).reshape(len(names), len(names)),
                "inside": np.array([[float(self.short[t] < self.short[u]) for u in names] for t in names]).reshape(len(names), len(names)),
                "table_at": [hashed(self.long[t], dim) for t in names], "name_at": np.array([hashed(["h:" + t], dim)[0] for t in names]),
            }
        return made[dim]

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_made"}


class Prompts:
    """One slice for many questions: features x (n, tables, NUMERIC), the questions `some` and tables `here` they are of, and the history `past` (n, all tables)."""

    def __init__(self, x, some, here, past):
        self.x, self.some, self.here, self.past = x, some, here, past


class Bench:
    """A batch of questions over a shelf as matrices."""

    def __init__(self, shelf: Shelf, words: list[list[str]], dim: int):
        self.shelf = shelf
        self.__dict__.update(shelf.matrices(dim))
        vocab = self.vocab
        self.q = np.zeros((len(words), len(vocab)))
        other = np.zeros(len(words))
        for i, ws in enumerate(words):
            known = [vocab[w] for w in set(ws) if w in vocab]
            self.q[i, known] = 1
            other[i] = len(set(ws)) - len(known)  # words that no table has weigh one
        self.wq = self.q * self.weight
        self.total = self.wq.sum(1) + other
        self.total[self.total == 0] = 1.0
        rows = [hashed(w, dim) for w in words]
        self.q_size = np.array([len(r) for r in rows])
        self.q_row, self.q_at = np.repeat(np.arange(len(rows)), self.q_size), np.concatenate([*rows, np.zeros(0, np.int64)]).astype(np.int64)

    def gold(self, tables: list[list[str]]) -> np.ndarray:
        out = np.zeros((len(tables), len(self.names)))
        for i, ts in enumerate(tables):
            out[i, [self.at[t] for t in ts if t in self.at]] = 1
        return out

    def prompts(self, k: int, past: np.ndarray, some: np.ndarray | None = None) -> Prompts:
        """Slice k for all questions, or for those of the indices `some`, with their history."""
        some = np.arange(len(self.q)) if some is None else some
        here = np.flatnonzero(self.slice_of == k)
        wq, total, q, past = self.wq[some], self.total[some, None], self.q[some], past[some]
        name = wq @ self.short[here].T / total
        x = np.zeros((len(some), len(here), len(NUMERIC)))
        x[:, :, 0] = name
        x[:, :, 1] = wq @ self.long[here].T / total
        x[:, :, 2] = q @ self.short[here].T / np.maximum(self.short[here].sum(1), 1)
        whole = x[:, :, 2] > 1 - 1e-9
        x[:, :, 3] = whole
        x[:, :, 4] = whole & (whole @ self.inside[np.ix_(here, here)].T > 0)  # another of the prompt has this name and more
        x[:, :, 5] = (past @ self.short > 0) @ self.short[here].T / np.maximum(self.short[here].sum(1), 1)
        x[:, :, 6] = past @ self.near[here].T > 0
        x[:, :, 7] = ((wq * (past @ self.long > 0)).sum(1) / total[:, 0])[:, None]
        x[:, :, 8] = (np.minimum(past.sum(1), 4) / 4)[:, None]
        x[:, :, 9] = k / max(1, len(self.shelf.slices))
        best = name.max(1, keepdims=True, initial=0.0)
        x[:, :, 10] = np.divide(name, best, out=np.zeros_like(name), where=best > 0)
        return Prompts(x, some, here, past)

    def lessons(self, gold: np.ndarray, history: bool, balance: str = "double_positive"):
        """(prompts, labels, weights) of every slice: with the gold tables of earlier slices as history, and positives
        again without (double_positive) or with double weight."""
        for k in range(len(self.shelf.slices)):
            here, past = self.slice_of == k, gold * (self.slice_of < k)
            y = gold[:, here]
            hit = y.any(1)
            weight = np.where(hit & (balance == "weight" or balance == "double_positive" and not history), 2.0, 1.0)
            yield self.prompts(k, past if history else np.zeros_like(past)), y, weight
            again = np.flatnonzero(hit)
            if history and balance == "double_positive" and len(again):
                yield self.prompts(k, np.zeros_like(past), again), y[again], np.ones(len(again))

    def fold(self, linker, history: bool) -> np.ndarray:
        """The chosen tables (n, all tables): slices in order, each with those chosen before."""
        chosen, at = np.zeros((len(self.q), len(self.names))), linker.start(self)
        for k in range(len(self.shelf.slices)):
            p = sigmoid(linker.logits(self.prompts(k, chosen if history else np.zeros_like(chosen)), at))
            chosen[:, self.slice_of == k] = p >= linker.threshold
        return chosen


def questions_of(questions: DataFrame) -> DataFrame:
    """qid, words, gold_tables: what training and inference read of a question."""
    return questions.select(F.col("qid").cast("long").alias("qid"), word_list("question").alias("words"), "gold_tables")


def infer(linker, questions: DataFrame, shelf: Shelf, history: bool = True) -> DataFrame:
    """PRED: per question the slices in order, each prompt with the tables chosen so far; parallel over questions."""
    dim = getattr(linker, "config", LowRankConfig()).dim

    def run(batches):
        for batch in (b.slice(i, 512) for b in batches for i in range(0, b.num_rows, 512)):
            bench = shelf.bench(batch.column(1).to_pylist(), dim)
            chosen = bench.fold(linker, history)
            preds = [sorted(bench.names[j] for j in np.flatnonzero(row)) for row in chosen]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(preds, pa.list_(pa.string())), pa.array([len(shelf.slices)] * len(preds), pa.int32())], names=["qid", "pred_tables", "n_calls"])

    ready(questions.sparkSession)
    return questions_of(questions).select("qid", "words").mapInArrow(run, PRED)


def infer_rounds(answer, questions: DataFrame, slices: DataFrame, catalog: DataFrame) -> DataFrame:
    """As infer(), one round a slice for a linker that takes prompt texts: answer(DataFrame qid, user) -> (qid, answer).

    Every round is one batched DataFrame; its state is written, so a lost executor costs one round at most.
    """
    from ..functions import templates
    from ..session import settled
    from .examples import slice_texts

    texts = slice_texts(slices, catalog)
    order = [r.slice_id for r in slices.select("slice_id").distinct().orderBy("slice_id").collect()]
    state = questions.select("qid", "db_id", "question", F.array().cast("array<string>").alias("pred_tables"))
    for k in order:
        own = slices.where(F.col("slice_id") == k).select("db_id", "tables").join(texts.where(F.col("slice_id") == k), "db_id")
        now = state.join(own, "db_id")
        prompts = now.select("qid", templates.user("slice", schema=F.col("slice_text"), history=templates.answer(F.col("pred_tables")), question=F.col("question")).alias("user"))
        said = answer(prompts).select("qid", F.split("answer", ",\\s*").alias("said"))
        step = now.select("qid", "tables").join(said, "qid").select("qid", F.array_intersect("said", "tables").alias("new"))
        state = settled(state.join(step, "qid", "left").select("qid", "db_id", "question", F.when(F.col("new").isNull(), F.col("pred_tables")).otherwise(F.array_union("pred_tables", "new")).alias("pred_tables")), "round")
    return state.select("qid", F.array_sort("pred_tables").alias("pred_tables"), F.lit(len(order)).alias("n_calls"))
