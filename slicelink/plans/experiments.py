"""The experiments: methods, slice sizes in training and inference, history, and end-to-end SQL, as RESULT rows.

All run at the published sizes, 254 tables with 3,647 + 383 questions and 172 tables with 1,736 + 178, for three
stand-ins of base models, two with long contexts and one with 4,096 tokens. Trained models, catalogs and prompts are
shared by the experiments of a session.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import settled
from . import catalog as C
from . import cost, examples, linking, metrics, slicing, sqlgen, train, workload
from .groups import order
from .linkers import LexicalLinker, LowRankConfig, LowRankText, PairLogit

RESULT = "exp string, dataset int, method string, model string, config string, n long, tot_acc double, filt_acc double, avg_prec double, avg_rec double, tot_lo double, tot_hi double, mem_mb double, calls int, time_s double, status string"
BUDGET_MB = 80_000
#: Stand-ins for base models: learner and context window in tokens.
MODELS = {"lowrank": ("rank", 100_000), "logit": ("pair", 100_000), "lowrank_4k": ("rank", 4096)}
#: Slice counts in training and inference: of the first study by dataset, of the second by the number in training.
TRAIN_COUNTS = {1: (6, 8, 10, 12), 2: (6, 8, 12, 14)}
INFER_COUNTS = {8: (8, 5, 4), 11: (11, 8, 7)}
BATCH = {"full_schema": 1}


@dataclass
class Setting:
    """A database with questions, its order and what is derived from it."""

    which: int
    catalog: DataFrame
    qa: DataFrame
    ordered: DataFrame
    sizes: list[int]
    shelf: linking.Shelf
    made: dict = field(default_factory=dict)

    @property
    def train(self):
        return self.qa.where("split = 'train'")

    @property
    def valid(self):
        return self.qa.where("split = 'valid'")

    def slices(self, wanted: int) -> tuple[DataFrame, int, int]:
        cap, n = slicing.cap_for(self.sizes, wanted)
        return slicing.pack(self.ordered, cap), cap, n


_SETTINGS: dict = {}


def setting(spark: SparkSession, sf_dir: str, which: int, scale: float = 1.0) -> Setting:
    """One of the two databases; made once in a session."""
    key = (spark.sparkContext.applicationId, sf_dir, which, scale)
    if key not in _SETTINGS:
        cat, qa = workload.dataset(spark, sf_dir, which, scale)
        cat, qa = settled(cat, "catalog"), settled(qa, "qa")
        ordered = settled(order(cat), "ordered")
        _SETTINGS[key] = Setting(which, cat, qa, ordered, [r.n_tokens for r in ordered.orderBy("pos").collect()], linking.Shelf.of(cat))
    return _SETTINGS[key]


def learner(model: str, seed: int = 3):
    kind, context = MODELS[model]
    return PairLogit(context_window=context) if kind == "pair" else LowRankText(LowRankConfig(), seed, context)


class Lab:
    """Trains each (model, slices, history) once, and infers each of its settings once."""

    def __init__(self, s: Setting, epochs: int | None = None, steps: int = 10):
        self.s, self.epochs, self.steps, self.made = s, epochs or (2 if s.which == 1 else 3), steps, s.made

    def shelf(self, method: str, wanted: int):
        """(shelf, cap, slices)"""
        key = ("shelf", method, wanted if method == "slice_wise" else 1)
        if key not in self.made:
            if method == "slice_wise":
                sl, cap, n = self.s.slices(wanted)
                self.made[key] = (self.s.shelf.of_slices(sl), cap, n)
            else:
                self.made[key] = (self.s.shelf.names_only() if method == "names_only" else self.s.shelf, sum(self.s.sizes), 1)
        return self.made[key]

    def model(self, model: str, method: str, wanted: int, history: bool):
        kind = MODELS[model][0]  # a context window changes what may run, not what is learnt
        key = (kind, method, wanted if method == "slice_wise" else 1, history)
        if key not in self.made:
            shelf, _, _ = self.shelf(method, wanted)
            self.made[key] = train.fit(learner(model), self.s.train, shelf, history, self.epochs, self.steps)[0]
        return self.made[key]

    def predicted(self, model: str, method: str, trained: int, history: bool, wanted: int, past: bool) -> tuple[DataFrame, float]:
        """(PRED, seconds a question) of a model trained on `trained` slices that infers on `wanted`."""
        kind = MODELS[model][0]
        key = ("pred", kind, method, trained, history, wanted, past)
        if key not in self.made:
            one, shelf = self.model(model, method, trained, history), self.shelf(method, wanted)[0]
            t = time.time()
            pred = settled(linking.infer(one, self.s.valid, shelf, past), "pred")
            self.made[key] = (pred, (time.time() - t) / max(1, self.s.valid.count()))
        return self.made[key]

    def prompted(self) -> tuple[DataFrame, float]:
        """The untrained linker on the whole schema."""
        if "prompted" not in self.made:
            t = time.time()
            pred = settled(linking.infer_once(LexicalLinker(), self.s.valid, self.s.catalog), "pred")
            self.made["prompted"] = (pred, (time.time() - t) / max(1, self.s.valid.count()))
        return self.made["prompted"]


def row(exp: str, s: Setting, method: str, model: str, config: str, pred: tuple[DataFrame, float] | None, status: str, mem: float, calls: int) -> tuple:
    if pred is None:
        return (exp, s.which, method, model, config, 0, *[None] * 6, None, calls, None, status)
    r = metrics.wilson(metrics.link_scores(pred[0], s.valid), "tot_acc").first()
    return (exp, s.which, method, model, config, r.n, r.tot_acc, r.filt_acc, r.avg_prec, r.avg_rec, r.lo, r.hi, round(mem, 1), calls, round(pred[1], 5), status)


def memory(which: int) -> cost.MemoryModel:
    return cost.MemoryModel.fit(cost.MEMORY_POINTS[which], batch=2)


NAME_TOKENS = "[a-z]+|[0-9]+|_"


def gated(s: Setting, method: str, model: str, wanted: int, lab: Lab) -> tuple[str, float]:
    """(status, estimated MB) of a method before it runs: the largest prompt against context and, in training, memory."""
    tokens = lab.shelf("slice_wise", wanted)[1] if method == "slice_wise" else sum(s.sizes)
    if method == "names_only":
        tokens = s.catalog.agg(F.sum(F.size(F.regexp_extract_all("table_name", F.lit(NAME_TOKENS), 0)) + 1)).first()[0]
    mb = memory(s.which).base if method == "untrained" else memory(s.which).mb(tokens, BATCH.get(method, 2))
    if tokens > MODELS[model][1]:
        return "CONTEXT_EXCEEDED", mb
    return ("OOM" if mb > BUDGET_MB else "OK"), mb


def slice_counts(which: int, model: str) -> int:
    return 11 if model == "lowrank_4k" and which == 1 else 8


METHODS = ("untrained", "names_only", "slice_wise", "full_schema")


def methods(spark: SparkSession, sf_dir: str, datasets=(1, 2), models=tuple(MODELS), scale: float = 1.0) -> DataFrame:
    """Untrained prompt, names only, slice-wise and full schema."""
    out = []
    for which in datasets:
        s = setting(spark, sf_dir, which, scale)
        lab = Lab(s)
        for method in METHODS:
            for model in models:
                m = slice_counts(which, model)
                status, mb = gated(s, method, model, m, lab)
                past = method == "slice_wise"
                _, cap, n = lab.shelf(method, m)
                config = f"{n} slices, cap {cap}" if past else ""
                if status != "OK":
                    out.append(row("methods", s, method, model, config, None, status, mb, 0))
                else:
                    pred = lab.prompted() if method == "untrained" else lab.predicted(model, method, m, past, m, past)
                    out.append(row("methods", s, method, model, config, pred, status, mb, n))
    return spark.createDataFrame(out, RESULT)


def train_granularity(spark, sf_dir, datasets=(1, 2), model="lowrank", scale: float = 1.0, counts=None) -> DataFrame:
    """Slice counts in training and inference alike."""
    out = []
    for which in datasets:
        s = setting(spark, sf_dir, which, scale)
        lab = Lab(s)
        for m in counts or TRAIN_COUNTS[which]:
            _, cap, n = lab.shelf("slice_wise", m)
            out.append(row("train_granularity", s, "slice_wise", model, f"{n} slices, cap {cap}", lab.predicted(model, "slice_wise", m, True, m, True), "OK", memory(which).mb(cap, 2), n))
    return spark.createDataFrame(out, RESULT)


def history(spark, sf_dir, datasets=(1, 2), models=tuple(MODELS), scale: float = 1.0) -> DataFrame:
    """No history, history in training and inference, history in inference only.

    The logistic stand-in has no weight for history that it never saw in training, so its last row equals its first but
    for the part that the prompt's size plays; the low-rank one sees history as words of the prompt.
    """
    out = []
    for which in datasets:
        s = setting(spark, sf_dir, which, scale)
        lab = Lab(s)
        for model in models:
            m = slice_counts(which, model)
            _, cap, n = lab.shelf("slice_wise", m)
            for name, regime in linking.REGIMES.items():
                out.append(row("history", s, name, model, f"{n} slices, cap {cap}", lab.predicted(model, "slice_wise", m, regime.train, m, regime.infer), "OK", memory(which).mb(cap, 2), n))
    return spark.createDataFrame(out, RESULT)


def infer_granularity(spark, sf_dir, datasets=(1, 2), models=tuple(MODELS), scale: float = 1.0) -> DataFrame:
    """Trained on one slice count, larger slices at inference."""
    out = []
    for which in datasets:
        s = setting(spark, sf_dir, which, scale)
        lab = Lab(s)
        for model in models:
            m = slice_counts(which, model)
            mb = memory(which).mb(lab.shelf("slice_wise", m)[1], 2)
            for wanted in INFER_COUNTS[m]:
                _, cap, n = lab.shelf("slice_wise", wanted)
                out.append(row("infer_granularity", s, "slice_wise", model, f"{n} slices, cap {cap}", lab.predicted(model, "slice_wise", m, True, wanted, True), "OK", mb, n))
    return spark.createDataFrame(out, RESULT)


SQL_RESULT = "dataset int, method string, n long, ex double, em double, em_text double, ex_lo double, ex_hi double, peak_mb double, calls int, link_s double, sql_s double, status string"
MODES = ("slice_wise", "untrained", "full_schema", "direct")


def answer(s: Setting, lab: Lab, mode: str, model: str = "lowrank") -> tuple[DataFrame | None, str, list[tuple], int]:
    """(SQLPRED, status, stages (stage, MB, seconds a question), calls) of link-then-generate or direct generation on the validation questions."""
    m, n = slice_counts(s.which, model), max(1, s.valid.count())

    def timed(sqlpred):
        t = time.time()
        done = settled(sqlpred, "sqlpred")
        return done, (time.time() - t) / n

    base = memory(s.which).base
    if mode == "untrained":
        pred, link_s = lab.prompted()
        out, sql_s = timed(sqlgen.ZeroShotGenerator().generate(pred))
        return out, "OK", [("link", base, link_s), ("sql", base, sql_s)], 1
    method = {"slice_wise": "slice_wise", "full_schema": "full_schema", "direct": "full_schema"}[mode]
    status, mb = gated(s, method, model, m, lab)
    if status != "OK":
        return None, status, [("link", mb, None)], 0
    if mode == "direct":
        every = s.catalog.groupBy("db_id").agg(F.array_sort(F.collect_list("table_name")).alias("pred_tables"))  # one database's tables
        out, sql_s = timed(sqlgen.SkeletonGenerator("all").fit(s.train, s.catalog).generate(s.valid, s.valid.select("qid", "db_id").join(every, "db_id").select("qid", "pred_tables")))
        return out, status, [("sql", mb, sql_s)], 1
    past = mode == "slice_wise"
    pred, link_s = lab.predicted(model, method, m, past, m, past)
    out, sql_s = timed(sqlgen.SkeletonGenerator("linked").fit(s.train, s.catalog).generate(s.valid, pred))
    return out, status, [("link", mb, link_s), ("sql", base, sql_s)], lab.shelf(method, m)[2] + 1


def repair(spark: SparkSession, sqlpred: DataFrame, retry) -> DataFrame:
    """SQLPRED whose invalid texts are replaced by retry's (same columns)."""
    bad = [r.qid for r in sqlpred.collect() if metrics.guarded(spark, r.sql or "") is None]
    ids = spark.createDataFrame([(i,) for i in bad], "qid long")
    again = retry.join(ids, "qid", "left_semi").withColumn("status", F.lit("RETRIED"))
    return sqlpred.join(ids, "qid", "left_anti").unionByName(again)


def end_to_end(spark, sf_dir, datasets=(1, 2), scale: float = 1.0) -> DataFrame:
    """Question to SQL: execution accuracy, clause-set and text match, peak memory and seconds of both stages."""
    out, cache = [], {}
    C.register_fleet(spark, sf_dir, C.fleet_names(max(workload.DATASETS[w][0] for w in datasets)))
    for which in datasets:
        s = setting(spark, sf_dir, which, scale)
        lab = Lab(s)
        for mode in MODES:
            pred, status, stages, calls = answer(s, lab, mode)
            spent = spark.createDataFrame([(mode, *x) for x in stages], "run_id string, stage string, mb double, seconds double")
            peak = round(cost.peak_mb(spent).first().mem_mb, 1)
            if pred is None:
                out.append((which, mode, 0, *[None] * 5, peak, calls, None, None, status))
                continue
            seconds = {x[0]: round(x[2], 5) for x in stages}
            ex = metrics.execution_accuracy(spark, pred, s.valid, cache).agg(F.count("*").alias("n"), F.round(100 * F.avg("ex"), 4).alias("ex"))
            ex = metrics.wilson(ex, "ex").first()
            both = s.valid.join(pred.select("qid", "sql"), "qid", "left")
            em = [metrics.logical_match(both, how).agg(F.round(100 * F.avg("em"), 4)).first()[0] for how in ("clause_set", "text")]
            out.append((which, mode, ex.n, ex.ex, *em, ex.lo, ex.hi, peak, calls, seconds.get("link"), seconds.get("sql"), status))
    return spark.createDataFrame(out, SQL_RESULT)


def tradeoff(spark: SparkSession, ordered: DataFrame, which: int, caps: list[int]) -> DataFrame:
    """cap, slices, estimated MB and seconds over a sweep of caps."""
    mm, tm = memory(which), cost.TimeModel.fit(cost.TIME_POINTS[which])
    sweep = slicing.cap_sweep(ordered, caps)
    return sweep.select("cap", "n_slices", F.round(F.lit(mm.base) + F.lit(2 * mm.per_token) * F.col("cap"), 1).alias("est_mb"), F.round(F.lit(tm.fixed) + F.lit(tm.per_call) * F.col("n_slices"), 3).alias("est_s"))


def token_frames(s: Setting, wanted: int = 8) -> DataFrame:
    """Token accounting of every kind of training example."""
    sl, _, _ = s.slices(wanted)
    parts = [examples.full_schema(s.train, s.catalog), examples.names_only(s.train, s.catalog), examples.sliced(s.train, sl, s.catalog, "none", "none"), examples.sliced(s.train, sl, s.catalog), examples.sql_direct(s.train, s.catalog)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return cost.token_report(out)
