"""Accuracy and cost measures."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def align(true: np.ndarray, approx: np.ndarray, how: str = "sign") -> np.ndarray:
    """``approx`` turned towards ``true``: a sign for each mode, or the best orthogonal map of the k-space."""
    if how == "sign":
        s = np.sign((true * approx).sum(0))
        return approx * np.where(s == 0, 1.0, s)
    if how == "procrustes":
        u, _, vt = np.linalg.svd(approx.T @ true)
        return approx @ (u @ vt)
    if how == "none":
        return approx
    raise ValueError(how)


def zeta_local(true: np.ndarray, approx: np.ndarray, ranges: np.ndarray | None = None) -> np.ndarray:
    """Percent deviation of each point: root of the sum over the modes, every mode scaled by its range in the true embedding."""
    span = np.ptp(true, axis=0) if ranges is None else ranges
    return 100.0 * np.sqrt((((approx - true) / span) ** 2).sum(1))


def z_local(zeta: np.ndarray) -> float:
    return float(np.sqrt((zeta**2).mean()))


def zeta(true: DataFrame, approx: DataFrame, k: int) -> DataFrame:
    """``id, zeta`` of two embeddings ``id, psi``: ranges by one aggregation (a row of 2k numbers, broadcast)."""
    spans = true.agg(*[(F.max(F.col("psi")[c]) - F.min(F.col("psi")[c])).alias(f"r{c}") for c in range(k)])
    both = true.select("id", F.col("psi").alias("t")).join(approx.select("id", F.col("psi").alias("a")), "id").crossJoin(F.broadcast(spans))
    terms = [((F.col("a")[c] - F.col("t")[c]) / F.col(f"r{c}")) * ((F.col("a")[c] - F.col("t")[c]) / F.col(f"r{c}")) for c in range(k)]
    return both.select("id", (F.lit(100.0) * F.sqrt(sum(terms[1:], terms[0]))).alias("zeta"))


def zeta_max(z: DataFrame) -> DataFrame:
    return z.agg(F.max("zeta").alias("zeta_max"))


def z_error(z: DataFrame) -> DataFrame:
    return z.agg(F.sqrt(F.avg(F.col("zeta") * F.col("zeta"))).alias("z"))


def observed_shift(a: DataFrame, b: DataFrame) -> DataFrame:
    """``id, sigma``: norm of the difference of two embeddings."""
    from ..functions.metrics import euclidean

    return a.select("id", F.col("psi").alias("p")).join(b.select("id", F.col("psi").alias("q")), "id").select("id", euclidean(F.col("p"), F.col("q")).alias("sigma"))


def fold_summary(errors: DataFrame, by: tuple[str, ...] = ("method", "split")) -> DataFrame:
    """Mean and sample deviation over folds of Z, of the landmark count and of its percentage of the ``n`` points fitted."""
    percent = 100.0 * F.col("m") / F.col("n")
    return errors.groupBy(*by).agg(
        F.count("*").alias("folds"),
        F.avg("z").alias("z_mean"),
        F.stddev_samp("z").alias("z_sd"),
        F.max("z_max").alias("z_max"),
        F.avg("m").alias("m_mean"),
        F.stddev_samp("m").alias("m_sd"),
        F.avg(percent).alias("percent_mean"),
        F.stddev_samp(percent).alias("percent_sd"),
    )


def ideal_speedup(n: int, m: int) -> float:
    return n / m


def counted(metric, counter):
    """The metric with a Spark accumulator that every distance it computes is added to (also those of tasks run again)."""
    from ..functions import metrics

    m = metrics.get(metric)

    def block(x, y):
        d = m.block(x, y)
        counter.add(int(d.size))
        return d

    return metrics.Metric(m.name, block, m.is_metric, m.column)


def timed(df: DataFrame, repeats: int = 3, warm_up: bool = True) -> float:
    """Median wall time of running ``df`` into a sink that keeps nothing, after a run that is not counted."""
    took = []
    if warm_up:
        df.write.format("noop").mode("overwrite").save()
    for _ in range(repeats):
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return float(np.median(took))


def speedup(new: DataFrame, full, reduced, k: int, repeats: int = 3) -> dict[str, float]:
    """Wall time of extending ``new`` by both models, distances included, and the ideal ratio."""
    from .maps import extend

    tf, tr = timed(extend(new, full, k), repeats), timed(extend(new, reduced, k), repeats)
    return {"t_full": tf, "t_landmark": tr, "speedup": tf / tr, "ideal": ideal_speedup(full.size, reduced.size)}


def eigenvalue_error(full_lam: np.ndarray, reduced_lam: np.ndarray, k: int) -> np.ndarray:
    return reduced_lam[1 : k + 1] - full_lam[1 : k + 1]
