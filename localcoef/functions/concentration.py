"""Sample sizes and confidence half-widths, as plain functions and as Columns."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BUDGETS = ("strict", "printed")


def check_unit(name: str, x: float) -> None:
    if not 0 < x < 1:
        raise ValueError(f"{name} lies strictly between 0 and 1")


def budget_of_round(i: int, eta: float, budget: str = "strict") -> float:
    """The share of the failure budget that round i may use; with ``strict`` all rounds and the cap add up to eta."""
    if budget not in BUDGETS:
        raise ValueError(f"unknown budget {budget!r}")
    return eta / (4 if budget == "strict" else 2) / 2**i


def sample_start(r: float, eps: float, k: int, eta0: float) -> int:
    """The least size at which the half-width of constant data can be small enough."""
    return int(math.ceil(3 * r * math.log(4 * k / eta0) / eps + 1))


def sample_cap(r: float, eps: float, zeta: int, eta: float, budget: str = "strict") -> float:
    """The size at which the plain mean is good enough whatever the data."""
    return (r / eps) ** 2 * (zeta + math.log((2 if budget == "strict" else 1) / eta))


def hoeffding_size(eps: float, k: int, eta: float) -> int:
    """Draws for a two-sided bound on values in [0, 1], for k buckets at once."""
    return int(math.ceil(math.log(2 * k / eta) / (2 * eps * eps)))


def relative_error_size(eps: float, psi: float) -> float:
    return 1 / (eps * psi) ** 2


def bernstein_halfwidth(v: float, r: float, s: int, k: int, eta: float) -> float:
    log = math.log(4 * k / eta)
    return math.sqrt(2 * max(v, 0.0) * log / s) + 7 * r * log / (3 * (s - 1))


def bernstein_column(v: Column, r: Column, s: Column, k: int, eta: float) -> Column:
    log = math.log(4 * k / eta)
    return F.sqrt(F.greatest(v, F.lit(0.0)) * (2 * log) / s) + r * (7 * log) / (3 * (s - 1))


def variance_of_sums(sx: float, sxx: float, s: int, ddof: int = 1, centered: bool = True) -> float:
    """The empirical variance from running sums; zeros are in s."""
    mean = sx / s
    return max(0.0, (sxx - s * mean * mean if centered else sxx) / (s - ddof))


def variance_ceiling(psi: float, m: int, s: int) -> float:
    """No bucket mean of s draws varies more, whatever the split: no value is above m * psi, and their mean is psi."""
    return (m - 1) / s * psi * psi


def regime(r: float, eps: float, k: int, eta: float, zeta: int, budget: str = "strict") -> tuple[float, str]:
    """The share of the cap that the first round takes, and whether sizes grow as 1 / eps or as 1 / eps^2 there.

    The first round grows with r / eps and the cap with its square, so a small range makes an early end likely.
    """
    share = sample_start(r, eps, k, budget_of_round(0, eta, budget)) / max(sample_cap(r, eps, zeta, eta, budget), 1.0)
    return share, "optimistic" if r <= 1 else "mixed" if share < 1 else "pessimistic"


def omega(x: np.ndarray, r: float) -> np.ndarray:
    return (-np.log1p(-r * x) - r * x) / 4


def plugin_loop(xs: list[float], r: float, eta: float) -> tuple[float, float]:
    """(centre, half-width) of the betting bound by a plain loop, for tests; eta is the whole budget of this bucket."""
    s, mean, spread, total = len(xs), 0.0, r * r / 4, 0.0
    log = math.log(2 / eta)
    bets = weighted = penalty = dev = 0.0
    for i, x in enumerate(xs):
        bet = min(math.sqrt(2 * log / (s * spread)), 1 / (2 * r))
        off = (x - mean) ** 2
        bets += bet
        weighted += bet * x
        penalty += (-math.log(1 - r * bet) - r * bet) / 4 * off
        dev += off
        total += x
        mean, spread = total / (i + 1), (r * r / 4 + dev) / (i + 1)
    return weighted / bets, (log + (2 / r) ** 2 * penalty) / bets


def plugin_windows(dense: DataFrame, r: float, s: int, eta: float) -> DataFrame:
    """(bucket, center, halfwidth) from dense rows (bucket, ix, x) with zeros, by two ordered windows."""
    log = math.log(2 / eta)
    before = Window.partitionBy("bucket").orderBy("ix").rowsBetween(Window.unboundedPreceding, -1)
    step = dense.withColumn("mean", F.coalesce(F.avg("x").over(before), F.lit(0.0))).withColumn("off", F.pow(F.col("x") - F.col("mean"), 2))
    n = F.count("*").over(before)
    spread = F.when(n == 0, F.lit(r * r / 4)).otherwise((F.lit(r * r / 4) + F.coalesce(F.sum("off").over(before), F.lit(0.0))) / n)
    step = step.withColumn("bet", F.least(F.sqrt(F.lit(2 * log) / (F.lit(float(s)) * spread)), F.lit(1 / (2 * r))))
    penalty = (-F.ln(1 - F.col("bet") * r) - F.col("bet") * r) / 4 * F.col("off")
    return step.groupBy("bucket").agg((F.sum(F.col("bet") * F.col("x")) / F.sum("bet")).alias("center"), ((F.lit(log) + F.sum(penalty) * (4 / (r * r))) / F.sum("bet")).alias("halfwidth"))


def plugin_chunks(values: DataFrame, buckets: DataFrame, ranges: DataFrame, s: int, eta: float, chunk: int = 1 << 16) -> DataFrame:
    """(bucket, center, halfwidth) from sparse values (ix, bucket, x), zeros implied; ``ranges`` has (bucket, r).

    The draws are cut into chunks; sums of a chunk, then its squared deviations, are passed on to the chunks after it,
    so no bucket's draws are held by one task. Buckets with range 0 have half-width 0.
    """
    spark = values.sparkSession
    log = math.log(2 / eta)
    cells = buckets.select("bucket").distinct().join(ranges, "bucket").crossJoin(F.broadcast(spark.range(-(-s // chunk)).select(F.col("id").cast("int").alias("c"))))
    lists = values.groupBy("bucket", F.floor(F.col("ix") / chunk).cast("int").alias("c")).agg(F.sort_array(F.collect_list(F.struct("ix", "x"))).alias("xs"))
    base = cells.join(lists, ["bucket", "c"], "left").withColumn("total", F.coalesce(F.aggregate("xs", F.lit(0.0), lambda a, y: a + y["x"]), F.lit(0.0)))
    ahead = Window.partitionBy("bucket").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)
    base = base.withColumn("sum_before", F.coalesce(F.sum("total").over(ahead), F.lit(0.0)))

    def dense(row):
        low = row.c * chunk
        x = np.zeros(min(chunk, s - low))
        if row.xs is not None and len(row.xs):
            x[[int(p["ix"]) - low for p in row.xs]] = [p["x"] for p in row.xs]
        n = low + np.arange(len(x))
        mean = np.divide(row.sum_before + np.concatenate([[0.0], np.cumsum(x)[:-1]]), n, out=np.zeros(len(x)), where=n > 0)
        return x, n, (x - mean) ** 2

    def deviations(frames):
        for frame in frames:
            frame["dev"] = [float(dense(row)[2].sum()) for row in frame.itertuples()]
            yield frame[["bucket", "c", "dev"]]

    dev = base.select("bucket", "c", "xs", "sum_before").mapInPandas(deviations, "bucket int, c int, dev double")
    dev = dev.withColumn("dev_before", F.coalesce(F.sum("dev").over(ahead), F.lit(0.0))).select("bucket", "c", "dev_before")

    def bets(frames):
        for frame in frames:
            rows = []
            for row in frame.itertuples():
                x, n, off = dense(row)
                if row.r <= 0:
                    rows.append((row.bucket, float(len(x)), 0.0, 0.0))
                    continue
                spread = np.full(len(x), row.r**2 / 4)
                passed = row.dev_before + np.concatenate([[0.0], np.cumsum(off)[:-1]])
                np.divide(row.r**2 / 4 + passed, n, out=spread, where=n > 0)
                bet = np.minimum(np.sqrt(2 * log / (s * spread)), 1 / (2 * row.r))
                rows.append((row.bucket, float(bet.sum()), float((bet * x).sum()), float((omega(bet, row.r) * off).sum())))
            yield pd.DataFrame(rows, columns=["bucket", "bets", "weighted", "penalty"])

    done = base.join(dev, ["bucket", "c"]).select("bucket", "c", "xs", "sum_before", "dev_before", "r").mapInPandas(bets, "bucket int, bets double, weighted double, penalty double")
    found = done.groupBy("bucket").agg(F.sum("bets").alias("bets"), F.sum("weighted").alias("weighted"), F.sum("penalty").alias("penalty")).join(ranges, "bucket")
    half = F.when(F.col("r") > 0, (F.lit(log) + F.col("penalty") * 4 / (F.col("r") * F.col("r"))) / F.col("bets")).otherwise(F.lit(0.0))
    return found.select("bucket", (F.col("weighted") / F.col("bets")).alias("center"), half.alias("halfwidth"))


def rademacher_halfwidth(values: np.ndarray, s: int, r: float, eta: float, trials: int = 64, seed: int = 0) -> float:
    """A data-dependent width for all buckets at once: Monte-Carlo sign averages of a (buckets, draws) matrix and its deviation terms."""
    signs = np.random.default_rng(seed).choice([-1.0, 1.0], (trials, s))
    average = float(np.abs(values @ signs.T / s).max(axis=0).mean())
    return 2 * average + 3 * r * math.sqrt(math.log(4 / eta) / (2 * s)) + 2 * r * math.sqrt(math.log(4 / eta) / (2 * s * trials))


def cost_model(n: int, m: int, k: int, dmax: int, draws: int, r: float, eps: float, eta: float, zeta: int) -> list[tuple[str, float]]:
    """Rows touched by each step, as a planner compares them."""
    return [
        ("filter", float(n)), ("ranges", float(k) * m), ("tuning", float(dmax)), ("loop", float(draws) * dmax), ("exact", float(m) ** 1.5),
        ("memory", float(m + draws * k + k * n)), ("start", float(sample_start(r, eps, k, budget_of_round(0, eta)))), ("cap", sample_cap(r, eps, zeta, eta)),
    ]
