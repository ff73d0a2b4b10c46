"""Measures of accuracy and cost of estimates (run, bucket, f[, eps_hat]) against the truth (bucket, psi)."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import mean, stdev
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bucket_error(estimates: DataFrame, truth: DataFrame) -> DataFrame:
    """(run, bucket, err); a bucket that only one side has counts as 0 on the other."""
    runs = estimates.select("run").distinct()
    full = truth.select("bucket", "psi").crossJoin(F.broadcast(runs)).join(estimates.select("run", "bucket", "f"), ["run", "bucket"], "full")
    return full.select("run", "bucket", F.abs(F.coalesce("f", F.lit(0.0)) - F.coalesce("psi", F.lit(0.0))).alias("err"))


def max_error(errors: DataFrame) -> DataFrame:
    """(bucket, max_err) over runs."""
    return errors.groupBy("bucket").agg(F.max("err").alias("max_err"))


def sup_error(errors: DataFrame) -> DataFrame:
    """(sup_err) over buckets and runs."""
    return errors.agg(F.max("err").alias("sup_err"))


def mean_sup_error(errors: DataFrame) -> DataFrame:
    """(avg_sup_err): the bucket average of each run, then the largest over runs."""
    return errors.groupBy("run").agg(F.avg("err").alias("e")).agg(F.max("e").alias("avg_sup_err"))


def tightness(results: DataFrame, truth: DataFrame) -> DataFrame:
    """(run, bucket, eps_hat, err, ratio): how wide an interval is against the true error; no ratio for no error."""
    both = results.select("run", "bucket", "f", "eps_hat").join(truth.select("bucket", "psi"), "bucket").withColumn("err", F.abs(F.col("f") - F.col("psi")))
    return both.select("run", "bucket", "eps_hat", "err", F.when(F.col("err") > 1e-12, F.col("eps_hat") / F.col("err")).alias("ratio"))


def coverage(results: DataFrame, truth: DataFrame, slack: float = 1e-9) -> DataFrame:
    """(runs, covered): the share of runs whose intervals hold all truths at once."""
    both = results.join(truth.select("bucket", "psi"), "bucket")
    inside = F.abs(F.col("f") - F.col("psi")) <= F.col("eps_hat") + slack
    return both.groupBy("run").agg(F.bool_and(inside).alias("all_in")).agg(F.count("*").alias("runs"), F.avg(F.col("all_in").cast("int")).alias("covered"))


def step_shares(seconds: dict[str, float]) -> list[tuple[str, float, float]]:
    """(step, seconds, share of the total)."""
    total = sum(seconds.values()) or 1.0
    return [(step, s, s / total) for step, s in seconds.items()]


def timed(action: Callable[[], Any]) -> tuple[Any, float]:
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began


def tuning_report(tuned: list[float], grid_errors: dict[float, float]) -> dict[str, float]:
    """Mean and deviation of the tuned split weight, and the grid's best."""
    return {"q_mean": mean(tuned), "q_sd": stdev(tuned) if len(tuned) > 1 else 0.0, "best_grid_q": min(grid_errors, key=lambda q: (grid_errors[q], q))}


def gain(ours: DataFrame, other: DataFrame) -> DataFrame:
    """(error_ratio, draw_ratio) from one-row tables (err, draws)."""
    return ours.select(F.col("err").alias("e1"), F.col("draws").alias("d1")).crossJoin(other.select(F.col("err").alias("e2"), F.col("draws").alias("d2"))).select((F.col("e2") / F.col("e1")).alias("error_ratio"), (F.col("d2") / F.col("d1")).alias("draw_ratio"))
