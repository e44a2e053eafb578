"""Stand-ins for tuned language models: they score (question, tables in a prompt, tables already chosen)."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ready

STOP = "the of by a an and in for with to what is show give find report compute how many number each through have no than more table records".split()


def word_list(text: str | Column) -> Column:
    """Distinct lower-case words of a text without stop words; a plural s is cut."""
    c = F.col(text) if isinstance(text, str) else text
    ws = F.transform(F.regexp_extract_all(F.lower(c), F.lit("[a-z]+|[0-9]+"), 0), lambda w: F.when(F.length(w) > 3, F.regexp_replace(w, "s$", "")).otherwise(w))
    return F.array_distinct(F.filter(ws, lambda w: ~w.isin(STOP)))


def table_words(catalog: DataFrame, fields: str = "columns") -> DataFrame:
    """db_id, table_name, words of the name, and of the columns too."""
    text = F.col("table_name") if fields == "names" else F.concat_ws(" ", "table_name", F.array_join("columns.name", " "))
    return catalog.select("db_id", "table_name", word_list(F.regexp_replace(text, "_", " ")).alias("words"))


def idf(tables: DataFrame) -> DataFrame:
    """db_id, word, idf = ln(1 + tables / tables with the word)."""
    total = tables.groupBy("db_id").agg(F.count("*").alias("total"))
    df = tables.select("db_id", F.explode("words").alias("word")).groupBy("db_id", "word").agg(F.count("*").alias("df"))
    return df.join(total, "db_id").select("db_id", "word", F.log(1 + F.col("total") / F.col("df")).alias("idf"))


class LexicalLinker:
    """Untrained: weight of the question's words that a table's name or columns hold, over the weight of all its known
    words; chosen from `threshold` on and within `near` of the best table of the same prompt."""

    context_window = 1_000_000

    def __init__(self, threshold: float = 0.3, near: float = 0.8, fields: str = "columns"):
        self.threshold, self.near, self.fields = threshold, near, fields

    def scores(self, questions: DataFrame, catalog: DataFrame) -> DataFrame:
        """qid, table_name, score (six places) of the pairs with a common word, by an inverted index on words."""
        tables = table_words(catalog, self.fields)
        weights = idf(tables)
        q = questions.select("qid", "db_id", F.explode(word_list("question")).alias("word")).join(weights, ["db_id", "word"])
        norm = q.groupBy("qid").agg(F.sum("idf").alias("norm"))
        hits = q.join(tables.select("db_id", "table_name", F.explode("words").alias("word")), ["db_id", "word"])
        return hits.groupBy("qid", "table_name").agg(F.sum("idf").alias("s")).join(norm, "qid").select("qid", "table_name", F.round(F.col("s") / F.col("norm"), 6).alias("score"))

    def choose(self, scores: DataFrame, prompt: list[str]) -> DataFrame:
        """The rows chosen of a prompt: columns `prompt` say which scores stand in the same one."""
        best = scores.groupBy(*prompt).agg(F.max("score").alias("best"))
        return scores.join(best, prompt).where((F.col("score") >= self.threshold) & (F.col("score") >= self.near * F.col("best") - 1e-9)).drop("best")


class NoisyOracle:
    """Gold tables with seeded misses and spurious picks: arithmetic on ids, so that SQL can follow it."""

    context_window = 1_000_000

    def __init__(self, seed: int = 1, miss: int = 10, spurious: int = 5):
        self.seed, self.miss, self.spurious = seed, miss, spurious

    def predict(self, qa: DataFrame, catalog: DataFrame) -> DataFrame:
        """qid, pred_tables: of every hundred gold tables about `miss` are dropped; a table more in about `spurious` of a hundred questions."""
        n = catalog.groupBy("db_id").agg(F.array_sort(F.collect_list("table_name")).alias("names"))
        df = qa.join(n, "db_id")
        kept = F.filter(F.transform("gold_tables", lambda t, i: F.struct(t.alias("t"), i.alias("i"))), lambda x: ((F.col("qid") * 7919 + x["i"] * 104729 + self.seed) % 100) >= self.miss)["t"]
        extra = F.when((F.col("qid") * 6007 + self.seed) % 100 < self.spurious, F.array(F.element_at("names", (F.col("qid") % F.size("names") + 1).cast("int")))).otherwise(F.array().cast("array<string>"))
        return df.select("qid", F.array_sort(F.array_union(kept, extra)).alias("pred_tables"))


# --- trained stand-ins: both see the features of (question, table, prompt), for many questions at once

NUMERIC = ("name_overlap", "column_overlap", "name_share", "whole_name", "covered", "told", "neighbour_chosen", "explained", "history_size", "slice_at", "rank_in_prompt")


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class PairLogit:
    """Logistic regression on the features of (question, table, history); trained by Newton's steps on sums of gradients
    and curvatures."""

    context_window = 100_000
    steps = 14

    def __init__(self, reg: float = 1e-6, threshold: float = 0.5, context_window: int = 100_000):
        self.reg, self.threshold, self.context_window, self.w = reg, threshold, context_window, np.zeros(len(NUMERIC) + 1)

    def start(self, bench) -> dict:
        """What the prompts of a batch share, and where their gradients are added up."""
        return {"g": 0.0, "h": 0.0}

    def logits(self, prompt, at: dict) -> np.ndarray:
        return prompt.x @ self.w[:-1] + self.w[-1]

    def learn(self, prompt, y: np.ndarray, weight: np.ndarray, at: dict) -> float:
        """The loss; gradients go to `at`."""
        p = sigmoid(self.logits(prompt, at))
        x = np.concatenate([prompt.x, np.ones((*prompt.x.shape[:2], 1))], 2).reshape(-1, len(self.w))
        e, curve = ((p - y) * weight[:, None]).ravel(), (p * (1 - p) * weight[:, None]).ravel()
        at["g"] = at["g"] + x.T @ e
        at["h"] = at["h"] + (x * curve[:, None]).T @ x
        return _loss(p, y, weight)

    def rows(self, bench, at: dict) -> dict:
        """By name and row the vectors that are added up over all batches."""
        return {("g", 0): at["g"]} | {("h", i): row for i, row in enumerate(at["h"])}

    def step(self, rows: dict, n: float, opt) -> None:
        k = len(self.w)
        hess = np.stack([rows["h", i] for i in range(k)]) / n + self.reg * np.eye(k)
        move = np.linalg.solve(hess, rows["g", 0] / n + self.reg * self.w)
        self.w = self.w - move * min(1.0, 3.0 / np.abs(move).max())  # a step is bounded, for labels that features part


def _loss(p, y, weight) -> float:
    return float(-(weight[:, None] * (y * np.log(p + 1e-9) + (1 - y) * np.log(1 - p + 1e-9))).sum())


class LowRankConfig:
    """Published settings of low-rank tuning (rank, alpha, lr); the small stand-in has their rank and alpha, and a rate of its own."""

    published = {"rank": 64, "alpha": 32, "lr": 1e-5}

    def __init__(self, rank: int = 64, alpha: float = 32.0, lr: float = 0.1, dim: int = 1 << 12):
        self.rank, self.alpha, self.lr, self.dim = rank, alpha, lr, dim


def hashed(words, dim: int) -> np.ndarray:
    """Indices of words; the same in every process."""
    import zlib

    return np.array(sorted({zlib.crc32(w.encode()) % dim for w in words}), np.int64)


class LowRankText:
    """score = base + alpha/rank * (A q) . (B p): hashed words of the question against those of table and history; the
    base weights over the overlap features stay frozen, their corrections, A and B are trained."""

    def __init__(self, config: LowRankConfig | None = None, seed: int = 3, context_window: int = 100_000, threshold: float = 0.5):
        self.config = config or LowRankConfig()
        r = np.random.default_rng(seed)
        c = self.config
        self.a, self.b = r.normal(0, 0.05, (c.dim, c.rank)), r.normal(0, 0.05, (2 * c.dim, c.rank))
        self.base = np.array([2.0, 1.0, 2.0, 3.0, -3.0, 0.0, 0.0, 0.0, 0.0, 0.0, 1.0, -6.0])
        self.tuned = np.zeros(len(self.base))
        self.context_window, self.threshold = context_window, threshold

    def start(self, bench) -> dict:
        """The vectors of the batch's questions, of tables and of names in the history, and where gradients are added up."""
        c = self.config
        u = np.zeros((len(bench.q), c.rank))
        np.add.at(u, bench.q_row, self.a[bench.q_at])
        u /= np.maximum(bench.q_size, 1)[:, None]
        t, h = np.stack([self.b[at].sum(0) for at in bench.table_at]), self.b[c.dim + bench.name_at]
        return {"u": u, "t": t, "h": h, "n": np.array([len(at) for at in bench.table_at]), "du": np.zeros_like(u), "dt": np.zeros_like(t), "dh": np.zeros_like(h), "tuned": np.zeros_like(self.tuned)}

    def _parts(self, prompt, at: dict):
        """Question, table and history vectors of a prompt, and how many words a table and the history have (n, s)."""
        return at["u"][prompt.some], at["t"][prompt.here], prompt.past @ at["h"], at["n"][prompt.here][None, :] + prompt.past.sum(1)[:, None]

    def logits(self, prompt, at: dict) -> np.ndarray:
        u, t, h, size = self._parts(prompt, at)
        w = self.base + self.tuned
        return prompt.x @ w[:-1] + w[-1] + self.config.alpha / self.config.rank * (u @ t.T + (u * h).sum(1)[:, None]) / size

    def learn(self, prompt, y: np.ndarray, weight: np.ndarray, at: dict) -> float:
        """The loss; gradients go to `at`."""
        u, t, h, size = self._parts(prompt, at)
        p = sigmoid(self.logits(prompt, at))
        e = (p - y) * weight[:, None]
        g = self.config.alpha / self.config.rank * e / size
        at["tuned"] += np.append(np.einsum("ns,nsk->k", e, prompt.x), e.sum())
        at["du"][prompt.some] += g @ t + g.sum(1)[:, None] * h
        at["dt"][prompt.here] += g.T @ u
        at["dh"] += prompt.past.T @ (g.sum(1)[:, None] * u)
        return _loss(p, y, weight)

    def rows(self, bench, at: dict) -> dict:
        """By name and row the vectors that are added up over all batches; only rows whose words occur."""
        c, out = self.config, {("t", 0): at["tuned"]}

        def add(name, row, v):
            out[name, row] = out[name, row] + v if (name, row) in out else v

        words, where = np.unique(bench.q_at, return_inverse=True)
        da = np.zeros((len(words), c.rank))
        np.add.at(da, where, (at["du"] / np.maximum(bench.q_size, 1)[:, None])[bench.q_row])
        for w, v in zip(words.tolist(), da, strict=True):
            add("a", w, v)
        for rows, v in zip(bench.table_at, at["dt"], strict=True):
            for w in rows.tolist():
                add("b", w, v)
        for w, v in zip(bench.name_at.tolist(), at["dh"], strict=True):
            if v.any():
                add("b", c.dim + w, v)
        return out

    def step(self, rows: dict, n: float, opt) -> None:
        whole = {"t": np.zeros_like(self.tuned), "a": np.zeros_like(self.a), "b": np.zeros_like(self.b)}
        for (name, at), v in rows.items():
            if name == "t":
                whole["t"] += v
            else:
                whole[name][at] += v
        opt.t += 1
        self.tuned = opt.step("t", self.tuned, whole["t"] / n)
        self.a, self.b = opt.step("a", self.a, whole["a"] / n), opt.step("b", self.b, whole["b"] / n)


class ExternalLinker:
    """Calls a user's function on batches of prompts: fn(list of prompt texts) -> list of answer texts."""

    def __init__(self, fn, batch: int = 32, context_window: int = 100_000):
        self.fn, self.batch, self.context_window = fn, batch, context_window

    def answer(self, prompts: DataFrame, id_col: str = "qid", text_col: str = "user") -> DataFrame:
        """qid, answer: in Arrow batches on the executors."""
        fn, size = self.fn, self.batch

        def run(batches):
            for batch in batches:
                ids, texts = batch.column(0), batch.column(1).to_pylist()
                out: list[str] = []
                for i in range(0, len(texts), size):
                    out += fn(texts[i : i + size])
                yield pa.RecordBatch.from_arrays([ids, pa.array(out, pa.string())], names=["qid", "answer"])

        ready(prompts.sparkSession)
        return prompts.select(F.col(id_col).cast("long").alias("qid"), text_col).mapInArrow(run, "qid long, answer string")


class DenseLinker:
    """Cosine of vectors: the k nearest candidates of every query vector, by products of blocks.

    The number of blocks follows from the counts, so that a block holds about `block` vectors at any size.
    """

    def __init__(self, k: int = 5, block: int = 4096):
        self.k, self.block = k, block

    def nearest(self, queries: DataFrame, vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
        """query_id, vec_id, score, rank: every block of queries meets every block of vectors, which keeps its k best; then they are merged."""
        from pyspark.sql import Window

        k, n = self.k, self.block
        parts = {name: max(1, -(-df.count() // n)) for name, df in (("qb", queries), ("vb", vectors))}
        cells = lambda df, own, other: df.select(F.col(id_col).cast("long").alias("i"), F.col(vec_col).cast("array<double>").alias("v"), F.pmod(F.xxhash64(id_col), F.lit(parts[own])).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.lit(parts[other] - 1))).alias(other))
        left, right = cells(queries, "qb", "vb"), cells(vectors, "vb", "qb")

        def top(a: pa.Table, b: pa.Table) -> pa.Table:
            ids, other = a.column("i").to_numpy(), b.column("i").to_numpy()
            found = [[], [], []]
            if len(ids) and len(other):
                x, y = (np.stack(t.column("v").to_numpy()) for t in (a, b))
                x, y = (m / np.linalg.norm(m, axis=1, keepdims=True) for m in (x, y))
                for at in range(0, len(ids), 256):
                    s = np.round(x[at : at + 256] @ y.T, 6)
                    s[ids[at : at + 256, None] == other[None, :]] = -2.0
                    # the k best and all that tie with the last of them, then the smallest ids
                    least = -np.partition(-s, min(k, s.shape[1]) - 1, 1)[:, min(k, s.shape[1]) - 1]
                    row, col = np.nonzero((s >= least[:, None]) & (s > -2.0))
                    order = np.lexsort((other[col], -s[row, col], row))
                    row, col = row[order], col[order]
                    first = np.searchsorted(row, row)
                    row, col = row[np.arange(len(row)) - first < k], col[np.arange(len(col)) - first < k]
                    for out, v in zip(found, (ids[at + row], other[col], s[row, col]), strict=True):
                        out.append(v)
            found = [np.concatenate(f) if f else np.zeros(0) for f in found]
            return pa.table({"query_id": pa.array(found[0], pa.int64()), "vec_id": pa.array(found[1], pa.int64()), "score": pa.array(found[2], pa.float64())})

        found = left.groupBy("qb", "vb").cogroup(right.groupBy("qb", "vb")).applyInArrow(top, "query_id long, vec_id long, score double")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        return found.withColumn("rank", rank).where(F.col("rank") <= k)


def vote(preds: list[DataFrame], k: int) -> DataFrame:
    """qid, pred_tables: tables that at least k of several predictions name."""
    out = None
    for p in preds:
        one = p.select("qid", F.explode(F.array_distinct("pred_tables")).alias("t"))
        out = one if out is None else out.unionByName(one)
    kept = out.groupBy("qid", "t").agg(F.count("*").alias("n")).where(F.col("n") >= k)
    ids = preds[0].select("qid")
    return ids.join(kept.groupBy("qid").agg(F.array_sort(F.collect_list("t")).alias("pred_tables")), "qid", "left").withColumn("pred_tables", F.coalesce("pred_tables", F.array().cast("array<string>")))


def log_odds(p: float) -> float:
    return math.log(p / (1 - p))
