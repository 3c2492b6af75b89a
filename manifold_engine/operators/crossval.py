"""Cross-validation of the reduced map against the full map, sweeps and tuning.

Each fold's maps are fitted on a sample of bounded size (the whole table while
it is no larger), folds being independent jobs; then one pass over all points
extends every one of them by all maps and adds up the errors, so Z covers the
table whatever its size.
"""

from __future__ import annotations

import hashlib
import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import metrics
from ..functions.linalg import SymmetricEdges, bottleneck_rows
from ..plans import planner
from ..sources.points import by_hash_order
from ..spool import spool
from . import landmarks as L
from . import maps as M
from . import measures as E
from .pairs import matrix

ERRORS = "fold int, method string, m long, n long, eps double, split string, points long, z double, z_max double"


def fold_of(ids: np.ndarray, k: int = 5, seed: int = 0) -> np.ndarray:
    """Fold of each id by its own hash alone: near-equal folds of a table of any size."""
    return np.array([int(hashlib.md5(f"{seed}:{i}".encode()).hexdigest()[:8], 16) % k + 1 for i in ids.tolist()], np.int64)


def split_folds(ids: np.ndarray, k: int = 5, seed: int = 0) -> np.ndarray:
    """Fold of each id, as ``ntile`` over md5 order."""
    order = sorted(range(len(ids)), key=lambda i: (hashlib.md5(f"{seed}:{ids[i]}".encode()).hexdigest(), ids[i]))
    fold = np.zeros(len(ids), np.int64)
    sizes = [len(ids) // k + (i < len(ids) % k) for i in range(k)]
    fold[order] = np.repeat(np.arange(1, k + 1), sizes)
    return fold


def local_graph(x: np.ndarray, r: float, metric: str) -> SymmetricEdges:
    block = metrics.get(metric).block
    i, j = [], []
    for s in range(0, len(x), 500):
        d = block(x[s : s + 500], x)
        a, b = np.nonzero(d <= r)
        a = a + s
        i.append(a[a < b])
        j.append(b[a < b])
    i, j = np.concatenate(i), np.concatenate(j)
    return SymmetricEdges(len(x), i, j, np.ones(len(i)), np.zeros(len(x)))


def choose(x: np.ndarray, method: str, r: float, metric: str, seed: int = 0) -> np.ndarray:
    """Landmark rows by a method's name: ``pst``, ``pst:<growth>``, ``medoids:<m>``, ``random:<m>``."""
    name, _, arg = method.partition(":")
    if name == "pst":
        return L.local_pst(np.arange(len(x)), local_graph(x, r, metric), arg or "star_random", seed)
    m = int(arg) if float(arg) >= 1 else max(2, round(float(arg) * len(x)))
    if name == "medoids":
        return L.local_medoids(x, m, metric, seed=seed)
    if name == "random":
        return np.sort(np.random.default_rng(seed).choice(len(x), min(m, len(x)), replace=False))
    raise ValueError(method)


def reduced_of(ids: np.ndarray, x: np.ndarray, at: np.ndarray, eps: float, modes: int, metric: str, weights: str = "cells") -> tuple[M.Model, np.ndarray]:
    """Reduced model over the rows ``at``, and each row's landmark."""
    block = metrics.get(metric).block
    cell = np.concatenate([block(x[s : s + 2000], x[at]).argmin(1) for s in range(0, len(x), 2000)])
    c = np.bincount(cell, minlength=len(at)).astype(float)
    keep = c > 0
    at, c = at[keep], c[keep]
    cell = (np.cumsum(keep) - 1)[cell]
    return M.fit_local(ids[at], x[at], eps, modes, metric, c if weights == "cells" else np.ones(len(at)), kind="reduced"), cell


def compare(ids: np.ndarray, x: np.ndarray, train: np.ndarray, methods: list[str], eps: float, k: int, metric: str = "euclidean", drop_below: float = 0.0, align: str = "sign", seed: int = 0, radius_factor: float = 1.0, full: M.Model | None = None) -> tuple[list[tuple], M.Model]:
    """Errors ``(method, m, split, z, z_max)`` on train and test rows."""
    tr, te = np.flatnonzero(train), np.flatnonzero(~train)
    full = full or M.fit_local(ids[tr], x[tr], eps, k + 2, metric, drop_below=drop_below)
    true_train = full.coordinates(k)
    true_test = M.nystrom(x[te], full, k)[0] if len(te) else np.zeros((0, k))
    spans = np.ptp(true_train, axis=0)
    out = []
    for method in methods:
        base, _, weights = method.partition("!")
        at = choose(x[tr], base, radius_factor * eps**0.5, metric, seed)
        red, _ = reduced_of(ids[tr], x[tr], at, eps, k + 2, metric, "none" if weights else "cells")
        if weights:  # counts of one: bring the norm to that of all points
            red.psi = red.psi / np.sqrt(len(tr) / red.size)
        got = M.nystrom(x[tr], red, k)[0]
        s = np.sign((got * true_train).sum(0)) if align == "sign" else None
        turned = got * s if s is not None else E.align(true_train, got, align)
        z = E.zeta_local(true_train, turned, spans)
        out.append((method, red.size, "train", E.z_local(z), float(z.max())))
        if len(te):
            gt = M.nystrom(x[te], red, k)[0]
            if s is None:
                u, _, vt = np.linalg.svd(got.T @ true_train)
                gt = gt @ (u @ vt)
            else:
                gt = gt * s
            z = E.zeta_local(true_test, gt, spans)
            out.append((method, red.size, "test", E.z_local(z), float(z.max())))
    return out, full


def turn_of(true: np.ndarray, approx: np.ndarray, how: str) -> np.ndarray:
    """The matrix that ``measures.align`` multiplies ``approx`` with."""
    if how == "procrustes":
        u, _, vt = np.linalg.svd(approx.T @ true)
        return u @ vt
    s = np.sign((true * approx).sum(0))
    return np.diag(np.where(s == 0, 1.0, s)) if how == "sign" else np.eye(true.shape[1])


def fit_fold(ids: np.ndarray, x: np.ndarray, methods: list[str], eps: float | None, k: int, metric: str, drop_below: float, align: str, seed: int) -> tuple:
    """``eps, full, spans, [(method, reduced, turn)]`` fitted on the given points."""
    e = eps or bottleneck_rows(x, metrics.get(metric).block) ** 2
    full = M.fit_local(ids, x, e, k + 2, metric, drop_below=drop_below)
    true = full.coordinates(k)
    out = []
    for method in methods:
        base, _, weights = method.partition("!")
        red, _ = reduced_of(ids, x, choose(x, base, e**0.5, metric, seed), e, k + 2, metric, "none" if weights else "cells")
        if weights:  # counts of one: bring the norm to that of all points
            red.psi = red.psi / np.sqrt(len(ids) / red.size)
        out.append((method, red, turn_of(true, M.nystrom(x, red, k)[0], align)))
    return e, full, np.ptp(true, axis=0), out


def cross_validate(points: DataFrame, methods: list[str], eps: float | None, k: int, metric: str = "euclidean", n_folds: int = 5, drop_below: float = 0.0, align: str = "sign", seed: int = 0, fit_points: int = planner.LOCAL_POINTS) -> DataFrame:
    """``fold, method, m, n, eps, split, points, z, z_max`` of every method over all points.

    ``n`` of the first ``fit_points`` points in md5 order are fitted in each
    fold; ``points`` are those whose error counts, of the whole table.
    ``eps=None`` takes each fold's smallest connecting bandwidth; with
    ``n_folds=0`` all sampled points are fitted at once and the split is ``all``.
    """
    spark = points.sparkSession
    points = spool(points.select("id", "vec"), "points")
    ids, x = M.collect_points(by_hash_order(points, fit_points, seed), fit_points)
    folds = list(range(1, n_folds + 1)) or [0]
    fold = fold_of(ids, n_folds, seed) if n_folds else np.ones(len(ids), np.int64)
    jobs = spark.createDataFrame([(f,) for f in folds], "fold int").repartition(len(folds))

    def fit(batches):
        for b in batches:
            for f in b.column("fold").to_pylist():
                own = fold != f
                data = pickle.dumps((f, int(own.sum()), *fit_fold(ids[own], x[own], methods, eps, k, metric, drop_below, align, seed)))
                yield pa.RecordBatch.from_arrays([pa.array([data], pa.binary())], names=["fit"])

    fits = [pickle.loads(r["fit"]) for r in jobs.mapInArrow(fit, "fit binary").collect()]  # as large as the samples, not the table
    names = ["fold", "method", "m", "n", "eps", "split", "points", "z2", "z_max"]

    def score(batches):
        for b in batches:
            step = max(1, 4_000_000 // max(fit_points, 1))
            for s in range(0, b.num_rows, max(step, 256)):
                part = b.slice(s, max(step, 256))
                y = matrix(part.column("vec"))
                h = fold_of(part.column("id").to_numpy(), n_folds, seed) if n_folds else np.ones(len(y), np.int64)
                rows = []
                for f, n, e, full, spans, reds in fits:
                    true = M.nystrom(y, full, k)[0]
                    for method, red, turn in reds:
                        z = E.zeta_local(true, M.nystrom(y, red, k)[0] @ turn, spans)
                        for split, use in (("all", h > 0),) if not n_folds else (("train", h != f), ("test", h == f)):
                            if use.any():
                                rows.append((f, method, red.size, n, e, split, int(use.sum()), float((z[use] ** 2).sum()), float(z[use].max())))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.string(), pa.int64(), pa.float64(), pa.float64()))], names=names)

    parts = points.mapInArrow(score, "fold int, method string, m long, n long, eps double, split string, points long, z2 double, z_max double")
    sums = parts.groupBy("fold", "method", "m", "n", "eps", "split").agg(F.sum("points").alias("points"), F.sum("z2").alias("z2"), F.max("z_max").alias("z_max"))
    return sums.select("fold", "method", "m", "n", "eps", "split", "points", F.sqrt(F.col("z2") / F.col("points")).alias("z"), "z_max")


def bandwidth_sweep(points: DataFrame, methods: list[str], eps_min: float, k: int, factors=(1, 2, 4, 8), **kw) -> DataFrame:
    """Cross-validated errors at multiples of the smallest bandwidth."""
    out = None
    for f in factors:
        part = cross_validate(points, methods, eps_min * f, k, **kw)
        out = part if out is None else out.union(part)
    return out


def tune_landmarks(points: DataFrame, eps: float, k: int, z_target: float | None = None, runtime_target: float | None = None, metric: str = "euclidean", start: int = 8, seed: int = 0, drop_below: float = 0.0) -> dict:
    """Fewest medoids whose test error meets ``z_target`` percent, or most that meet an extension time per point; doubling, then bisection on a validation fold."""
    ids, x = M.collect_points(points, planner.LOCAL_POINTS)
    train = split_folds(ids, 5, seed) != 1
    tried: dict[int, float] = {}
    n = int(train.sum())
    if runtime_target is not None:
        per = _seconds_per_landmark(x[~train], x[train], metric, k)
        return {"m": max(1, min(n, int(runtime_target / per))), "tried": {}}
    full = None

    def z(m: int) -> float:
        nonlocal full
        if m not in tried:
            rows, full = compare(ids, x, train, [f"medoids:{m}"], eps, k, metric, drop_below, "procrustes", seed, full=full)
            tried[m] = rows[-1][3]
        return tried[m]

    low, high = 0, start
    while high < n and z(high) > z_target:
        low, high = high, min(n, high * 2)
    while high - low > max(1, high // 16):
        mid = (low + high) // 2
        low, high = (low, mid) if z(mid) <= z_target else (mid, high)
    return {"m": high, "z": z(high), "tried": dict(sorted(tried.items()))}


def _seconds_per_landmark(new: np.ndarray, z: np.ndarray, metric: str, k: int) -> float:
    import time

    t = time.perf_counter()
    metrics.get(metric).block(new[:200], z)
    return (time.perf_counter() - t) / (min(200, len(new)) * len(z))
