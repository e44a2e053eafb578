"""Distributed training of the stand-ins: sums of gradients on executors, one step of the parameters on the driver."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..session import ready, settled
from .linkers import LowRankConfig
from .linking import Shelf, questions_of


class AdamW:
    def __init__(self, lr: float, decay: float = 0.01, b1: float = 0.9, b2: float = 0.999):
        self.lr, self.decay, self.b1, self.b2, self.t, self.m, self.v = lr, decay, b1, b2, 0, {}, {}

    def step(self, name: str, x: np.ndarray, g: np.ndarray) -> np.ndarray:
        m = self.m[name] = self.b1 * self.m.get(name, 0) + (1 - self.b1) * g
        v = self.v[name] = self.b2 * self.v.get(name, 0) + (1 - self.b2) * g * g
        m, v = m / (1 - self.b1**self.t), v / (1 - self.b2**self.t)
        return x - self.lr * (m / (np.sqrt(v) + 1e-8) + self.decay * x)


#: Up to so many partitions send their sums to the driver; those of more are added up by Spark before.
DIRECT = 64


SUMS = "name string, at long, v binary"


def packed(rows: dict) -> pa.RecordBatch:
    """SUMS of vectors by name and row."""
    names, at = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(names), pa.array(at, pa.int64()), pa.array([np.asarray(v, float).tobytes() for v in rows.values()], pa.binary())], names=["name", "at", "v"])


def added(batches):
    """SUMS with one vector for each name and row of the partition."""
    out: dict = {}
    for batch in batches:
        for name, at, v in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            out[name, at] = out.get((name, at), 0) + np.frombuffer(v)
    if out:
        yield packed(out)


def fit(linker, questions: DataFrame, shelf: Shelf, history: bool, epochs: int = 2, steps: int = 12, balance: str = "double_positive"):
    """(linker, mean loss of each step). A step is a pass: every partition sums the gradients of its questions' prompts,
    the sums are added, and the driver moves the parameters once; an epoch has `steps` of them. What reaches the driver
    is one vector for each parameter row that has words."""
    spark = ready(questions.sparkSession)
    rows = settled(questions_of(questions).select("words", "gold_tables"), "questions")
    direct = rows.rdd.getNumPartitions() <= DIRECT
    opt, losses = AdamW(linker.config.lr if hasattr(linker, "config") else 0.0), []
    dim = getattr(linker, "config", LowRankConfig()).dim
    shared = spark.sparkContext.broadcast(shelf)
    for _ in range(getattr(linker, "steps", epochs * steps)):
        held = spark.sparkContext.broadcast(linker)

        def run(batches, held=held):
            model, total, n, own = held.value, 0.0, 0.0, {}
            for batch in (b.slice(i, 512) for b in batches for i in range(0, b.num_rows, 512)):
                bench = shared.value.bench(batch.column(0).to_pylist(), dim)
                at = model.start(bench)
                for prompt, y, weight in bench.lessons(bench.gold(batch.column(1).to_pylist()), history, balance):
                    total, n = total + model.learn(prompt, y, weight, at), n + float(weight.sum() * y.shape[1])
                for key, v in model.rows(bench, at).items():
                    own[key] = own[key] + v if key in own else v
            own["_", 0] = np.array([total, n])
            yield packed(own)

        parts = rows.mapInArrow(run, SUMS)
        if not direct:  # rows of one parameter meet in one task before they reach the driver
            parts = parts.repartition(DIRECT, "name", "at").mapInArrow(added, SUMS)
        sums: dict = {}
        got = parts.toArrow()
        for name, at, v in zip(got.column("name").to_pylist(), got.column("at").to_pylist(), got.column("v").to_pylist(), strict=True):
            sums[name, at] = sums.get((name, at), 0) + np.frombuffer(v)
        total, n = sums.pop(("_", 0))
        linker.step(sums, n or 1.0, opt)
        losses.append(total / (n or 1.0))
        held.unpersist()
    return linker, losses
