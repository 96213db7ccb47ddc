"""Accuracy, cost and privacy measures (Q1-Q17)."""

from __future__ import annotations

import contextlib
import io
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def confusion(df: DataFrame, label: str = "label", pred: str = "pred", by: tuple[str, ...] = ()) -> DataFrame:
    """(label, pred, n), for each setting in ``by``: one shuffle of at most classes squared rows per task."""
    return df.groupBy(*by, F.col(label).alias("label"), F.col(pred).alias("pred")).agg(F.count("*").alias("n"))


def class_report(df: DataFrame, label: str = "label", pred: str = "pred", by: tuple[str, ...] = ()) -> DataFrame:
    """Support, precision, recall and F1 of each class; a measure without cases is 0."""
    cells = confusion(df, label, pred, by)
    sides = cells.select(*by, F.col("label").alias("class"), F.col("n").alias("support"), F.lit(0).cast("long").alias("predicted"), F.when(F.col("label") == F.col("pred"), F.col("n")).otherwise(0).alias("hit")).union(
        cells.select(*by, F.col("pred").alias("class"), F.lit(0).cast("long"), F.col("n"), F.lit(0).cast("long"))
    )
    sums = sides.where("class IS NOT NULL").groupBy(*by, "class").agg(F.sum("support").alias("support"), F.sum("predicted").alias("predicted"), F.sum("hit").alias("hit"))
    precision = F.when(F.col("predicted") > 0, F.col("hit") / F.col("predicted")).otherwise(0.0)
    recall = F.when(F.col("support") > 0, F.col("hit") / F.col("support")).otherwise(0.0)
    rated = sums.withColumn("precision", precision).withColumn("recall", recall)
    both = F.col("precision") + F.col("recall")
    return rated.withColumn("f1", F.when(both > 0, 2 * F.col("precision") * F.col("recall") / both).otherwise(0.0)).drop("predicted", "hit")


def weighted_report(df: DataFrame, label: str = "label", pred: str = "pred", by: tuple[str, ...] = ()) -> DataFrame:
    """Q1: precision, recall and F1 weighted by support, and the number of rows, for each setting in ``by``."""
    return class_report(df, label, pred, by).groupBy(*by).agg(*[(F.sum(F.col("support") * F.col(m)) / F.sum("support")).alias(m) for m in ("precision", "recall", "f1")], F.sum("support").alias("n"))


def macro(df: DataFrame, label: str = "label", pred: str = "pred") -> DataFrame:
    return class_report(df, label, pred).where("support > 0").agg(*[F.avg(m).alias(m) for m in ("precision", "recall", "f1")])


def accuracy(df: DataFrame, label: str = "label", pred: str = "pred") -> DataFrame:
    return df.agg(F.avg(F.col(label).eqNullSafe(F.col(pred)).cast("int")).alias("accuracy"), F.count("*").alias("n"))


def drop(curve: DataFrame, measure: str = "f1") -> DataFrame:
    """Q2: points lost at each budget against the row without noise (eps null)."""
    clean = curve.where("eps IS NULL").agg(F.max(measure).alias("clean"))
    return curve.where("eps IS NOT NULL").crossJoin(F.broadcast(clean)).withColumn("points_lost", (F.col("clean") - F.col(measure)) * 100)


def epochs_to_converge(curve: DataFrame, tol: float = 1e-4, patience: int = 10) -> DataFrame:
    """Q3: the first epoch after which the loss gains less than ``tol`` for ``patience`` epochs, else the last."""
    w = Window.orderBy("epoch")
    best = F.min("loss").over(w.rowsBetween(Window.unboundedPreceding, -1))
    gained = curve.withColumn("gain", (F.coalesce(best, F.lit(float("inf"))) - F.col("loss")) > tol)
    run = F.sum(F.col("gain").cast("int")).over(w.rowsBetween(1, patience))
    full = F.count("*").over(w.rowsBetween(1, patience)) == patience
    marked = gained.withColumn("done", full & (run == 0))
    return marked.agg(F.coalesce(F.min(F.when(F.col("done"), F.col("epoch"))), F.max("epoch")).alias("epochs"))


def sample_sheet(df: DataFrame, n: int = 8, salt: str = "sheet") -> DataFrame:
    """Q4: n test rows by keyed hash with truth, prediction and whether they agree."""
    picked = df.orderBy(F.md5(F.concat_ws("|", F.lit(salt), F.col("id").cast("string"))), "id").limit(n)
    return picked.select("id", F.col("label").alias("truth"), "pred", (F.col("label") == F.col("pred")).alias("ok"))


def seconds(action: Callable[[], DataFrame], repeats: int = 2) -> float:
    """Best wall-clock seconds of writing a plan's rows nowhere."""
    best = float("inf")
    for _ in range(repeats):
        began = time.perf_counter()
        action().write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - began)
    return best


def per_image_time(n: int, randomise: Callable[[], DataFrame], recognise: Callable[[], DataFrame]) -> dict[str, float]:
    """Q5: seconds per image of either step and their sum."""
    a, b = seconds(randomise) / n, seconds(recognise) / n
    return {"t_rand": a, "t_rec": b, "total": a + b}


def fit_slope(curve: DataFrame, x: str, y: str) -> DataFrame:
    """Q6, Q7: least-squares slope, intercept and share explained."""
    return curve.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


# The published marks of five issue types for three approaches.
ISSUES = ["joined to other records", "scales on light resources", "one-way", "unlinkable between applications", "revocable"]
MARKS = {"H1": ["partial", "no", "no", "partial", "no"], "H2": ["partial", "no", "no", "partial", "no"], "private": ["yes", "yes", "yes", "yes", "partial"]}

# Published seconds per image at a gallery of 798 (ranges as low and high).
PUBLISHED_SECONDS = [("H1", 24.0, 43.0), ("H2", 10.0, 10.0), ("private", 0.006, 0.006), ("V1", 0.0072, 0.0072), ("V2", 0.011, 0.011)]


def issue_matrix(spark: SparkSession) -> DataFrame:
    """Q8: one row per approach and issue."""
    rows = [(a, k + 1, ISSUES[k], m) for a, marks in MARKS.items() for k, m in enumerate(marks)]
    return spark.createDataFrame(rows, "approach string, issue int, meaning string, mark string")


def baseline_times(spark: SparkSession) -> DataFrame:
    """Published timing rows."""
    return spark.createDataFrame(PUBLISHED_SECONDS, "approach string, low double, high double")


def reconstruction(df: DataFrame, truth: str = "px", guess: str = "guess") -> DataFrame:
    """Q9: per row the mean squared error, peak signal ratio and cosine of truth and guess."""
    d = F.size(truth)
    mse = F.aggregate(F.zip_with(truth, guess, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v) / d
    dot = F.aggregate(F.zip_with(truth, guess, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)
    norms = [F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, x: s + x * x)) for c in (truth, guess)]
    made = df.withColumn("mse", mse).withColumn("cosine", F.when((norms[0] > 0) & (norms[1] > 0), dot / (norms[0] * norms[1])).otherwise(0.0))
    peak = F.array_max(truth)
    return made.withColumn("psnr", F.when(F.col("mse") > 0, 10 * F.log10(peak * peak / F.col("mse"))))


def merge_error(merged: np.ndarray, pooled: np.ndarray) -> float:
    """Q15, some rows at a time."""
    return max(float(np.abs(merged[at : at + 256] - pooled[at : at + 256]).max()) for at in range(0, len(merged), 256))


def cost_counters(df: DataFrame) -> dict[str, int]:
    """Q17: scans, exchanges, broadcasts and Python stages of a plan."""
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        df.explain()
    plan = text.getvalue()
    return {"scans": plan.count("Scan parquet"), "exchanges": plan.count("Exchange hashpartitioning") + plan.count("Exchange rangepartitioning") + plan.count("Exchange SinglePartition"), "broadcasts": plan.count("BroadcastExchange"), "python": plan.count("MapInArrow") + plan.count("ArrowEvalPython") + plan.count("FlatMapGroups")}
