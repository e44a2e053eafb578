"""Memory, time and token accounting of methods."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class MemoryModel:
    """mb = base + per_token * batch * tokens, scaled by bits a weight where quantized."""

    base: float
    per_token: float
    quant_bits: int = 16

    @classmethod
    def fit(cls, points: list[tuple[float, float]], batch: int = 2) -> MemoryModel:
        slope, at = line(points)
        return cls(at, slope / batch)

    def mb(self, tokens: float, batch: int) -> float:
        return self.base * self.quant_bits / 16 + self.per_token * batch * tokens


@dataclass(frozen=True)
class TimeModel:
    """seconds = fixed + per_call * calls."""

    fixed: float
    per_call: float

    @classmethod
    def fit(cls, points: list[tuple[float, float]]) -> TimeModel:
        slope, at = line(points)
        return cls(at, slope)

    def seconds(self, calls: float) -> float:
        return self.fixed + self.per_call * calls


def line(points: list[tuple[float, float]]) -> tuple[float, float]:
    """(slope, intercept) of least squares."""
    n = len(points)
    mx, my = sum(x for x, _ in points) / n, sum(y for _, y in points) / n
    slope = sum((x - mx) * (y - my) for x, y in points) / sum((x - mx) ** 2 for x, _ in points)
    return slope, my - slope * mx


# fixed values: published (cap, MB) and (slices, seconds) points of two databases
MEMORY_POINTS = {1: [(2100, 69599), (1600, 57152), (1300, 50429), (1100, 45825)], 2: [(1600, 55059), (1100, 45506), (800, 39155), (700, 38263)]}
TIME_POINTS = {1: [(6, 5.40), (8, 6.49), (10, 7.89), (12, 9.56)], 2: [(6, 4.49), (8, 5.79), (12, 7.01), (14, 9.34)]}


def fit_frame(points: DataFrame) -> DataFrame:
    """dataset, slope, intercept, r2 of points (dataset, x, y): least squares as aggregates."""
    return points.groupBy("dataset").agg(F.round(F.regr_slope("y", "x"), 4).alias("slope"), F.round(F.regr_intercept("y", "x"), 2).alias("intercept"), F.round(F.regr_r2("y", "x"), 4).alias("r2"))


def token_report(examples: DataFrame) -> DataFrame:
    """variant, n_examples, max_tokens, sum_tokens, label_tokens, history_names."""
    return examples.groupBy("variant").agg(F.count("*").alias("n_examples"), F.max("n_tokens").alias("max_tokens"), F.sum("n_tokens").alias("sum_tokens"), F.sum("label_tokens").alias("label_tokens"), F.sum(F.coalesce(F.greatest(F.size("history"), F.lit(0)), F.lit(0))).alias("history_names"))


def gate(report: DataFrame, model: MemoryModel, batch: int, budget_mb: float, context: int) -> DataFrame:
    """report with est_mb and status: CONTEXT_EXCEEDED, OOM or OK."""
    mb = F.lit(model.base * model.quant_bits / 16) + F.lit(model.per_token * batch) * F.col("max_tokens")
    status = F.when(F.col("max_tokens") > context, "CONTEXT_EXCEEDED").when(mb > budget_mb, "OOM").otherwise("OK")
    return report.withColumn("est_mb", F.round(mb, 1)).withColumn("status", status)


def peak_mb(stages: DataFrame) -> DataFrame:
    """run_id, mem_mb: the largest of a pipeline's stages (run_id, stage, mb)."""
    return stages.groupBy("run_id").agg(F.max("mb").alias("mem_mb"))


def inference_s(stages: DataFrame) -> DataFrame:
    """run_id, time_s: linking and generating together (run_id, stage, seconds)."""
    return stages.groupBy("run_id").agg(F.sum("seconds").alias("time_s"))


def compare(results: DataFrame, to: str = "full_schema") -> DataFrame:
    """dataset, model, method, saving_pct of memory and loss_points of total accuracy against a method's rows."""
    base = results.where(F.col("method") == to).select("dataset", "model", F.col("mem_mb").alias("m0"), F.col("tot_acc").alias("a0"))
    out = results.where(F.col("method") != to).join(base, ["dataset", "model"])
    return out.select("dataset", "model", "method", F.round(100 * (1 - F.col("mem_mb") / F.col("m0")), 2).alias("saving_pct"), F.round(F.col("a0") - F.col("tot_acc"), 2).alias("loss_points"))
