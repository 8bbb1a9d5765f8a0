"""Accuracy measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .claims import CELL


def judged(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """(entity_id, attr, value, truth, right) for answered cells of known truth."""
    return answers.select(*CELL, "value").join(truth.select(*CELL, F.col("value").alias("truth")), list(CELL)).withColumn("right", F.coalesce((F.col("value") == F.col("truth")), F.lit(False)).cast("int"))


def precision(answers: DataFrame, truth: DataFrame, by: tuple[str, ...] = (), unit: str = "cell") -> DataFrame:
    """Right answers over answers, by cell or by whole record."""
    j = judged(answers, truth)
    if unit == "record":
        j = j.groupBy("entity_id").agg(F.min("right").alias("right"))
    elif unit != "cell":
        raise ValueError("unit must be 'cell' or 'record'")
    return j.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.avg("right").alias("precision"))


def run_statistics(runs: DataFrame, value: str = "precision", by: tuple[str, ...] = ()) -> DataFrame:
    """Median, mean, variance and standard error over repeated runs."""
    v = F.col(value)
    return runs.groupBy(*by).agg(F.count(v).alias("runs"), F.median(v).alias("median"), F.avg(v).alias("mean"), F.var_samp(v).alias("variance"), (F.stddev_samp(v) / F.sqrt(F.count(v))).alias("std_error"))


def log_loss(p_true: Column) -> Column:
    return -F.avg(F.log(F.greatest(p_true, F.lit(1e-12))))


def probability_measures(scored: DataFrame, truth: DataFrame) -> DataFrame:
    """(log_loss, brier) of candidate probabilities p over cells whose truth somebody claims."""
    t = truth.select(*CELL, F.col("value").alias("truth"))
    rows = scored.join(t, list(CELL)).withColumn("y", (F.col("value") == F.col("truth")).cast("double"))
    cell = rows.groupBy(*CELL).agg(F.sum("y").alias("y"), F.sum(F.col("y") * F.col("p")).alias("p"), F.sum(F.pow(F.col("p") - F.col("y"), F.lit(2.0))).alias("b"))
    return cell.where("y = 1").agg(F.count(F.lit(1)).alias("n"), log_loss(F.col("p")).alias("log_loss"), F.avg("b").alias("brier"))


def calibration(scored: DataFrame, truth: DataFrame, bins: int = 10) -> DataFrame:
    """(bin, n, confidence, accuracy) of candidate probabilities."""
    t = truth.select(*CELL, F.col("value").alias("truth"))
    rows = scored.join(t, list(CELL)).withColumn("y", (F.col("value") == F.col("truth")).cast("double"))
    return rows.groupBy(F.least(F.floor(F.col("p") * bins), F.lit(bins - 1)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.avg("p").alias("confidence"), F.avg("y").alias("accuracy"))


def calibration_error(bins: DataFrame) -> DataFrame:
    return bins.agg((F.sum(F.col("n") * F.abs(F.col("confidence") - F.col("accuracy"))) / F.sum("n")).alias("ece"))


def improvement(results: DataFrame, ours: str) -> DataFrame:
    """(workload, ours, best_rival, points) from (workload, method, precision)."""
    mine = results.where(F.col("method") == ours).select("workload", F.col("precision").alias("ours"))
    rival = results.where(F.col("method") != ours).groupBy("workload").agg(F.max("precision").alias("best_rival"))
    return mine.join(rival, "workload").withColumn("points", 100 * (F.col("ours") - F.col("best_rival")))


def trust_error(estimated: DataFrame, actual: DataFrame) -> DataFrame:
    """(source_id, error): estimated less true accuracy, absolute."""
    return estimated.select("source_id", F.col("accuracy").alias("e")).join(actual.select("source_id", F.col("accuracy").alias("a")), "source_id").select("source_id", F.abs(F.col("e") - F.col("a")).alias("error"))
